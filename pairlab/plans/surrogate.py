"""A log-linear policy over finite candidate responses: probabilities and draws in DataFrame functions, its six measures.

It stands in for a language model so that objectives, data curation and rewards can run; its figures say
nothing about one.  Objectives and training are in pairlab.plans.training."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

FEATURES = ("f0", "f1", "f2", "f3", "f4", "f5")


def candidates(rolls: DataFrame) -> DataFrame:
    """query_id, slot, features, root_ok, label_ok, safe of every rollout, and class_hit and spec_reward where rolls have them;
    correctness is no feature."""
    safe = ~F.col("says_flawed")
    values = (F.lit(1.0), F.col("l_quantity") / 50, F.col("l_discount").cast("double"), F.col("l_tax").cast("double"), F.col("says_flawed").cast("double"), F.coalesce(F.col("pred_code").startswith("R"), F.lit(False)).cast("double"))
    before = F.col("side") == "pre"
    root = F.when(before, F.col("target_reported")).otherwise(~F.col("target_reported"))
    more = [c for c in ("class_hit", "spec_reward") if c in rolls.columns]
    return rolls.select(F.col("sample_id").alias("query_id"), "pair_id", "side", "slot", *(v.alias(n) for v, n in zip(values, FEATURES)), root.alias("root_ok"), (F.col("says_flawed") == before).alias("label_ok"), safe.alias("safe"), F.col("target_reported"), *more)


def _dot(w: list[float]) -> Column:
    out = F.lit(0.0)
    for x, f in zip(w, FEATURES):
        out = out + F.lit(float(x)) * F.col(f)
    return out


def probabilities(cands: DataFrame, w: list[float]) -> DataFrame:
    """cands with prob: softmax of w . f inside each query."""
    q = W.partitionBy("query_id")
    z = cands.withColumn("__z", _dot(w)).withColumn("__e", F.exp(F.col("__z") - F.max("__z").over(q)))
    return z.withColumn("prob", F.col("__e") / F.sum("__e").over(q)).drop("__z", "__e")


def evaluate(cands: DataFrame, w: list[float]) -> DataFrame:
    """Expected share of right answers, of right labels and of safe answers, over queries."""
    p = probabilities(cands, w)
    per = p.groupBy("query_id").agg(F.sum(F.col("prob") * F.col("root_ok").cast("int")).alias("root"), F.sum(F.col("prob") * F.col("label_ok").cast("int")).alias("label"), F.sum(F.col("prob") * F.col("safe").cast("int")).alias("safe"))
    return per.agg(F.round(F.avg("root"), 6).alias("root_rate"), F.round(F.avg("label"), 6).alias("label_rate"), F.round(F.avg("safe"), 6).alias("safe_rate"))


def sample(cands: DataFrame, w: list[float], k: int = 8, seed: int = 42) -> DataFrame:
    """k draws per query (draw, slot drawn) from the policy, by hashed uniforms; arrays of 8 candidates at most."""
    rows = probabilities(cands, w).groupBy("query_id").agg(F.array_sort(F.collect_list(F.struct("slot", "prob"))).alias("c"))
    u = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), "query_id", "draw")), 1, 12), 16, 10).cast("double") / float(16**12)
    drawn = rows.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(k)))).withColumn("u", u)
    walk = F.aggregate("c", F.struct(F.lit(0.0).alias("at"), F.lit(None).cast("int").alias("slot")), lambda a, x: F.struct((a["at"] + x["prob"]).alias("at"), F.coalesce(a["slot"], F.when(a["at"] + x["prob"] > F.col("u"), x["slot"])).alias("slot")), lambda a: F.coalesce(a["slot"], F.lit(8)))
    return drawn.select("query_id", "draw", walk.alias("slot"))
