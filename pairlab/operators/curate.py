"""Dataset construction: deduplication, stripping, context, splits, statistics."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def exact_dedup(df: DataFrame, key: str = "doc_id", text: str = "text", within: str | None = None) -> DataFrame:
    """key (the smallest of each text), n_copies; with within, only rows of one value are merged."""
    groups = [F.sha2(F.regexp_replace(F.trim(text), "\\s+", " "), 256).alias("h")] + ([within] if within else [])
    return df.groupBy(*groups).agg(F.min(key).alias(key), F.count("*").alias("n_copies")).drop("h")


def strip_html_comments(text: Column) -> Column:
    return F.regexp_replace(text, "(?s)<!--.*?(-->|$)", "")


def strip_c_comments(text: Column) -> Column:
    """Line and block comments go, literals stay; an open block runs to the end."""
    return F.regexp_replace(text, r"""(?s)("(?:[^"\\]|\\.)*"|'(?:[^'\\]|\\.)*')|//(?:[^\n\\]|\\.)*|/\*.*?(?:\*/|$)""", "$1")


def strip_lines(text: Column, pattern: str) -> Column:
    return F.array_join(F.filter(F.split(text, "\n"), lambda x: ~x.rlike(pattern)), "\n")


def pair_dedup(samples: DataFrame, pair: str = "pair_id", side: str = "side", text: str = "text") -> DataFrame:
    """pair_id (the smallest), n_copies of the pairs whose both sides are equal; a side that is missing equals a missing one only.

    The two sides of one pair never merge, and neither does a pair whose one side alone is known already."""
    norm = F.sha2(F.regexp_replace(F.trim(text), "\\s+", " "), 256)
    at = lambda s: F.max(F.when(F.col(side) == s, norm)).alias(f"h_{s}")
    whole = samples.groupBy(F.col(pair).alias("pair_id")).agg(at("pre"), at("post"))
    return whole.groupBy("h_pre", "h_post").agg(F.min("pair_id").alias("pair_id"), F.count("*").alias("n_copies")).select("pair_id", "n_copies")


def closure_of(nodes: DataFrame, edges: DataFrame, hops: int) -> DataFrame:
    """src, kind, dst, hop: what each distinct node reaches within so many edges (src_kind, src, kind, dst), at its least distance. Nodes are (kind, id)."""
    step = edges.select("src_kind", "src", "kind", "dst").distinct()
    out = reach = nodes.select("src_kind", "src").distinct().join(step, ["src_kind", "src"]).withColumn("hop", F.lit(1))
    for k in range(2, hops + 1):
        nxt = step.select(F.col("src_kind").alias("kind"), F.col("src").alias("dst"), F.col("kind").alias("to_kind"), F.col("dst").alias("to"))
        reach = reach.join(nxt, ["kind", "dst"]).select("src_kind", "src", F.col("to_kind").alias("kind"), F.col("to").alias("dst")).distinct().withColumn("hop", F.lit(k))
        out = out.union(reach)
    return out.groupBy("src_kind", "src", "kind", "dst").agg(F.min("hop").alias("hop"))


def expand(seeds: DataFrame, edges: DataFrame, hops: int, kinds: tuple = (), bodies: DataFrame | None = None, budget: int | None = None) -> DataFrame:
    """sample, kind, id, hop (and n_tok): the context of each sample.

    seeds: sample, kind, id.  edges: src_kind, src, kind, dst, where kind is the dependency's (callee, type, macro, global).  Nodes
    are numbers with a kind.  The first hop is taken per sample; behind it each distinct node is expanded once, and samples join
    last, so a hub that many samples share is walked once and not once a sample.  kinds keeps some dependencies.
    bodies: kind, id, n_tok of each node; with budget a sample takes nodes by hop, kind and id while their tokens fit."""
    first = seeds.select("sample", F.col("kind").alias("src_kind"), F.col("id").alias("src")).join(edges, ["src_kind", "src"]).select("sample", "kind", F.col("dst").alias("id")).distinct().withColumn("hop", F.lit(1))
    out = first
    if hops > 1:
        nodes = first.select(F.col("kind").alias("src_kind"), F.col("id").alias("src"))
        far = closure_of(nodes, edges, hops - 1)
        more = first.select("sample", F.col("kind").alias("src_kind"), F.col("id").alias("src")).join(far, ["src_kind", "src"]).select("sample", "kind", F.col("dst").alias("id"), (F.col("hop") + 1).alias("hop"))
        out = first.union(more).groupBy("sample", "kind", "id").agg(F.min("hop").alias("hop"))
    if kinds:
        out = out.filter(F.col("kind").isin(*kinds))
    if bodies is None:
        return out
    out = out.join(bodies, ["kind", "id"])
    if budget is None:
        return out
    from pyspark.sql import Window as W

    used = F.sum("n_tok").over(W.partitionBy("sample").orderBy("hop", "kind", "id").rowsBetween(W.unboundedPreceding, 0))
    return out.withColumn("used", used).filter(F.col("used") <= budget).drop("used")


def coalesce_sources(primary: DataFrame, fallback: DataFrame) -> DataFrame:
    """Edges (sample, ...) of the precise source, and of the other one for samples that the first does not cover; with source."""
    rest = fallback.join(primary.select("sample").distinct(), "sample", "left_anti")
    return primary.withColumn("source", F.lit("primary")).unionByName(rest.withColumn("source", F.lit("fallback")))


def leakage(df: DataFrame, split: str, *keys: str) -> DataFrame:
    """n_keys and n_leaking: distinct values of keys, and those that occur in two splits or more."""
    k = df.groupBy(*keys).agg((F.min(split) != F.max(split)).alias("leaks"))
    return k.agg(F.count("*").alias("n_keys"), F.count_if("leaks").alias("n_leaking"))


def describe(df: DataFrame, measures: tuple, by: tuple = ()) -> DataFrame:
    """measure, min_v, mean_v, max_v of each of measures (columns), in one pass, by group and with by also over all."""
    rows = df.select(*by, F.explode(F.array(*(F.struct(F.lit(m).alias("measure"), F.col(m).cast("double").alias("v")) for m in measures))).alias("x")).select(*by, "x.*")
    groups = rows.groupingSets([["measure"], ["measure", *by]], "measure", *by) if by else rows.groupBy("measure")
    return groups.agg(F.min("v").alias("min_v"), F.round(F.avg("v"), 4).alias("mean_v"), F.max("v").alias("max_v"))


def length_guard(df: DataFrame, words: str, most: int, mode: str = "truncate") -> DataFrame:
    """Rows of an array column of at most ``most`` entries: longer ones cut, or dropped."""
    if mode == "drop":
        return df.filter(F.size(words) <= most)
    if mode != "truncate":
        raise ValueError(f"no mode {mode}")
    return df.withColumn(words, F.slice(words, 1, most))


def temporal_split(df: DataFrame, day: str, ratios=(8, 1, 1)) -> DataFrame:
    """df with split by date: cuts lie between days, where the running share of rows passes the ratios. Days, not rows, are summed."""
    from pyspark.sql import Window as W

    days = df.groupBy(day).agg(F.count("*").alias("n"))
    total = sum(ratios)
    run = F.sum("n").over(W.orderBy(day))  # a row per day
    all_rows = F.sum("n").over(W.partitionBy(F.lit(1)))
    cut = days.withColumn("split", F.when(run * total <= ratios[0] * all_rows, "train").when(run * total <= (ratios[0] + ratios[1]) * all_rows, "val").otherwise("test"))
    return df.join(cut.select(day, "split"), day)  # Spark broadcasts the cuts where their size allows; day may be any column


def hashed_split(df: DataFrame, key: str, seed: int = 42) -> DataFrame:
    b = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), key)), 1, 6), 16, 10).cast("long") % 10
    return df.withColumn("split", F.when(b < 8, "train").when(b == 8, "val").otherwise("test"))
