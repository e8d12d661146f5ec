"""Connected components of a distributed edge table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlab.llm.scratch import materialize


def connected_components(edges: DataFrame, limit: int = 60) -> DataFrame:
    """node, component (the smallest node reachable) of each node of an edge; edges: a, b (bigint, any direction).

    Alternates large-star and small-star steps, which link each node's neighbours to the smallest of them,
    until the edges form stars.  Every step is an aggregation by node and a join back; no neighbour list is
    ever gathered.  Edges with a null end or equal ends link nothing."""
    flat = edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).filter("a <> b")
    flat = materialize(flat.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")

    def large(e: DataFrame) -> DataFrame:
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        return both.join(low, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()

    def small(e: DataFrame) -> DataFrame:
        low = e.groupBy("u").agg(F.min("v").alias("m"))
        linked = e.join(low, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        return linked.union(low.select("u", F.col("m").alias("v"))).distinct()

    mark = None
    for _ in range(limit):
        flat = materialize(small(large(flat)), "stars")
        now = flat.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).first()
        if now == mark:
            break
        mark = now
    else:
        raise RuntimeError("components have not settled")
    nodes = flat.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.union(flat.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
