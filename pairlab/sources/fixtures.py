"""Bindings of the given tables to pairs, rollouts, verdicts and token log-probabilities (FIXTURES.md), and the same in SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlab.sources.tables import load

ORDER = ("l_shipdate", "l_orderkey", "l_linenumber", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")


def _slots(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    """lineitem's rows as rollouts: eight response pairs of a part are its first sixteen rows, the k of the binding (a part has about
    thirty rows; those beyond the sixteenth are no responses). One shuffle by part."""
    line = load(spark, sf_dir, "lineitem", "l_partkey", *dict.fromkeys((*ORDER, *columns)))
    rn = F.row_number().over(W.partitionBy("l_partkey").orderBy(*ORDER))
    line = line.withColumn("rn", rn).filter("rn <= 16")
    part = load(spark, sf_dir, "part", "p_partkey", "p_size", "p_brand")
    before = F.col("rn") % 2 == 1
    return line.join(part, F.col("l_partkey") == F.col("p_partkey")).withColumns({
        "pair_id": F.col("l_partkey"), "sample_id": 2 * F.col("l_partkey") + F.when(before, 0).otherwise(1), "side": F.when(before, "pre").otherwise("post"), "slot": ((F.col("rn") + 1) / 2).cast("int"),
    })


def _reported(margin) -> Column:
    right = F.col("l_quantity") <= F.col("p_size") + margin
    return F.when(F.col("side") == "pre", right).otherwise(~right)


def policies(spark: SparkSession, sf_dir: str, margins: dict[str, int]) -> DataFrame:
    """policy_id, pair_id, sample_id, side, slot, p_brand, n_tok, target_reported of several policies from one scan, without classes."""
    cells = F.array(*(F.struct(F.lit(k).alias("policy_id"), _reported(m).alias("target_reported")) for k, m in margins.items()))
    n_tok = (10 * F.col("l_quantity").cast("int") + F.col("l_linenumber")).alias("n_tok")
    return _slots(spark, sf_dir).select("pair_id", "sample_id", "side", "slot", "p_brand", n_tok, F.explode(cells).alias("x")).select("pair_id", "sample_id", "side", "slot", "p_brand", "n_tok", "x.*")


def rollouts(spark: SparkSession, sf_dir: str, margin: int = 0) -> DataFrame:
    """Eight response pairs of each part with predicted classes; margin shifts how much a policy gets right."""
    df = _slots(spark, sf_dir, "l_returnflag")
    reported = _reported(margin)
    nation = load(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey").join(F.broadcast(load(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")), F.col("s_nationkey") == F.col("n_nationkey"))
    df = df.join(nation, F.col("l_suppkey") == F.col("s_suppkey"))
    flawed = reported | (F.col("l_returnflag") == "R")
    code = F.when((F.col("l_orderkey") + F.col("l_linenumber")) % 3 == 0, F.concat(F.lit("R"), F.col("n_regionkey").cast("string"))).otherwise(F.concat(F.lit("N"), F.col("s_nationkey").cast("string")))
    return df.select(
        "pair_id", "sample_id", "side", "slot", "p_brand", flawed.alias("says_flawed"), reported.alias("target_reported"), F.when(flawed, code).alias("pred_code"), F.concat(F.lit("N"), (F.col("l_partkey") % 25).cast("string")).alias("truth_code"),
        (10 * F.col("l_quantity").cast("int") + F.col("l_linenumber")).alias("n_tok"), "l_orderkey", "l_linenumber", "l_suppkey", "l_quantity", "l_discount", "l_tax",
    )


def roll_sql(margin: int = 0) -> str:
    """The same as a list of common table expressions that ends in roll."""
    return f"""
l0 AS (SELECT *, row_number() OVER (PARTITION BY l_partkey ORDER BY {", ".join(ORDER)}) AS rn FROM lineitem),
l1 AS (SELECT l0.*, p_size, p_brand, n_regionkey, s_nationkey, CASE WHEN rn % 2 = 1 THEN l_quantity <= p_size + {margin} ELSE l_quantity > p_size + {margin} END AS tr
       FROM l0 JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey JOIN nation ON n_nationkey = s_nationkey WHERE rn <= 16),
roll AS (SELECT l_partkey AS pair_id, 2 * l_partkey + (rn + 1) % 2 AS sample_id, CASE WHEN rn % 2 = 1 THEN 'pre' ELSE 'post' END AS side, (rn + 1) // 2 AS slot, p_brand,
       tr OR l_returnflag = 'R' AS says_flawed, tr AS target_reported,
       CASE WHEN tr OR l_returnflag = 'R' THEN CASE WHEN (l_orderkey + l_linenumber) % 3 = 0 THEN 'R' || n_regionkey ELSE 'N' || s_nationkey END END AS pred_code,
       'N' || (l_partkey % 25) AS truth_code, 10 * CAST(l_quantity AS INT) + l_linenumber AS n_tok, l_orderkey, l_linenumber, l_suppkey, l_quantity, l_discount, l_tax FROM l1)"""


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """child, parent of the two-level taxonomy."""
    n = load(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")
    return n.select(F.concat(F.lit("N"), F.col("n_nationkey").cast("string")).alias("child"), F.concat(F.lit("R"), F.col("n_regionkey").cast("string")).alias("parent"))


EDGES = "edge AS (SELECT 'N' || n_nationkey AS child, 'R' || n_regionkey AS parent FROM nation)"


def token_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, label, and arrays theta, ref, old of equal length 1 + vec_id % 64."""
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    total = e.agg(F.count("*")).first()[0]
    lp = lambda c: F.transform(F.slice(F.col(c), 1, (1 + F.col("vec_id") % 64).cast("int")), lambda x: -(F.lit(0.05) + F.abs(x.cast("double"))))
    shifted = lambda k, name: e.select(((F.col("vec_id") - k + total) % total).alias("vec_id"), F.col("embedding").alias(name))
    rows = e.withColumnRenamed("embedding", "e0").join(shifted(1, "e1"), "vec_id").join(shifted(2, "e2"), "vec_id")
    return rows.select("vec_id", "label", lp("e0").alias("theta"), lp("e1").alias("ref"), lp("e2").alias("old"))


TOKENS = """
cnt AS (SELECT count(*) AS m FROM embeddings),
tok AS (SELECT a.vec_id, a.label, t AS pos, -(0.05 + abs(CAST(a.embedding[t] AS DOUBLE))) AS th, -(0.05 + abs(CAST(b.embedding[t] AS DOUBLE))) AS rf, -(0.05 + abs(CAST(c.embedding[t] AS DOUBLE))) AS ol
  FROM embeddings a, cnt, embeddings b, embeddings c, range(1, 65) r(t) WHERE b.vec_id = (a.vec_id + 1) % m AND c.vec_id = (a.vec_id + 2) % m AND t <= 1 + a.vec_id % 64),
seq AS (SELECT vec_id, any_value(label) AS label, avg(th) AS lt, avg(rf) AS lr, sum(th) AS st, sum(rf) AS sr FROM tok GROUP BY vec_id)"""
