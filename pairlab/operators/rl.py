"""Difficulty, filters, schedules, rewards and advantages."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlab.sources.tables import saved


def filter_extremes(rates: DataFrame, lo: int = 0, hi: int = 8, enabled: bool = True) -> DataFrame:
    """Pairs whose number of right slots (n_right) lies strictly between lo and hi."""
    return rates.filter((F.col("n_right") > lo) & (F.col("n_right") < hi)) if enabled else rates


def global_rank(df: DataFrame, *order: Column, name: str = "rank") -> DataFrame:
    """Dense 0-based places in a total order with one shuffle: range partitions, sorted where they lie and written with their places
    inside; their sizes are summed on the driver (one number each)."""
    parts = max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    ranged = df.repartitionByRange(parts, *order).sortWithinPartitions(*order)
    # the id holds the partition above 33 bits of the row's place in it; written, so that it stays what was counted
    ranged = saved(ranged.withColumn("__m", F.monotonically_increasing_id()), "ranged")
    part = F.shiftright("__m", 33).cast("int")
    sizes = {r["p"]: r["n"] for r in ranged.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect()}
    start, at = {}, 0
    for p in sorted(sizes):
        start[p], at = at, at + sizes[p]
    offset = df.sparkSession.createDataFrame([(p, v) for p, v in start.items()], "__p int, __o long")
    inside = F.col("__m").bitwiseAND(F.lit((1 << 33) - 1))
    return ranged.withColumn("__p", part).join(F.broadcast(offset), "__p").withColumn(name, inside + F.col("__o")).drop("__p", "__o", "__m")


def _hash(seed: int, key: str) -> Column:
    return F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(key)))


def schedule_random(samples: DataFrame, size: int = 32, seed: int = 42) -> DataFrame:
    return to_batches(global_rank(samples, _hash(seed, "sample_id"), F.col("sample_id")), size)


def schedule_curriculum(samples: DataFrame, size: int = 32, seed: int = 42) -> DataFrame:
    """Easy first; ties by a seeded hash of the sample, so the sides of a pair may part."""
    return to_batches(global_rank(samples, F.col("n_right").desc(), _hash(seed, "sample_id"), F.col("sample_id")), size)


def schedule_paired(pairs: DataFrame, size: int = 32, seed: int = 42) -> DataFrame:
    """Curriculum over pairs; both sides take neighbouring places of one batch."""
    if size % 2:
        raise ValueError("a batch of whole pairs has an even size")
    ranked = global_rank(pairs, F.col("n_right").desc(), _hash(seed, "pair_id"), F.col("pair_id"))
    both = ranked.withColumn("__s", F.explode(F.array(F.lit(0), F.lit(1)))).withColumn("sample_id", 2 * F.col("pair_id") + F.col("__s")).withColumn("rank", 2 * F.col("rank") + F.col("__s"))
    return to_batches(both, size)


def to_batches(ranked: DataFrame, size: int) -> DataFrame:
    return ranked.select(F.floor(F.col("rank") / size).alias("batch_id"), (F.col("rank") % size).alias("pos"), "sample_id", "pair_id", "n_right")


def diagnose(plan: DataFrame) -> DataFrame:
    """Per batch: rows, rows before the fix, mean and variance of the pass rate, pairs with one side only."""
    rate = F.col("n_right") / 8
    pair = plan.groupBy("batch_id", "pair_id").agg(F.count("*").alias("k"), F.count_if(F.col("sample_id") % 2 == 0).alias("pre"), F.sum(rate).alias("s"), F.sum(rate * rate).alias("q"))
    n = F.sum("k")
    return pair.groupBy("batch_id").agg(n.alias("n"), F.sum("pre").alias("n_pre"), F.round(F.sum("s") / n, 6).alias("mean_rate"), F.round(F.sum("q") / n - F.pow(F.sum("s") / n, 2) + 0.0, 5).alias("var_rate"), F.count_if(F.col("k") == 1).alias("n_split_pairs"))


def specification(r1: Column, r2: Column, r3: Column, weights=("0.4", "0.2", "0.4"), gate: str = "linear") -> Column:
    """Decimal rubric total; gate="hard" ignores r2 and r3 where r1 is -1."""
    w = [F.lit(x).cast("decimal(3,2)") for x in weights]
    part = [x.cast("decimal(2,1)") for x in (r1, r2, r3)]
    if gate == "hard":
        part[1:] = [F.when(part[0] > 0, x).otherwise(F.lit("0").cast("decimal(2,1)")) for x in part[1:]]
    return (part[0] * w[0] + part[1] * w[1] + part[2] * w[2]).cast("decimal(6,3)")


def group_normalize(df: DataFrame, group: list[str], reward: str = "reward", ddof: int = 0, eps: float = 0.0) -> DataFrame:
    """df with advantage and dead; a group whose rewards are all equal (or one) is dead and has advantage 0."""
    w = W.partitionBy(*group)
    dead = F.min(reward).over(w) == F.max(reward).over(w)
    std = (F.stddev_pop if ddof == 0 else F.stddev_samp)(reward).over(w)
    return df.withColumn("dead", dead).withColumn("advantage", F.when(F.col("dead"), 0.0).otherwise((F.col(reward) - F.avg(reward).over(w)) / (std + eps)))
