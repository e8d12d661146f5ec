"""Queries: scans, joins, aggregations, windows, sorts, sets and functions that users of the methods need."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlab.operators.rl import global_rank
from pairlab.registry import query
from pairlab.sources import tables as T
from pairlab.sources.tables import load

query("scan_pruned", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_quantity > 45 AND l_returnflag = 'R'")(lambda s, d: load(s, d, "lineitem").filter("l_quantity > 45 AND l_returnflag = 'R'").select("l_orderkey", "l_quantity"))
query("filter_compound", "SELECT o_orderkey FROM orders WHERE o_totalprice BETWEEN 1000 AND 90000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') OR o_orderstatus = 'P'")(lambda s, d: load(s, d, "orders").filter("o_totalprice BETWEEN 1000 AND 90000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') OR o_orderstatus = 'P'").select("o_orderkey"))
query("null_safe_class", "SELECT count(*) FILTER (nullif(l_returnflag, 'N') IS NOT DISTINCT FROM nullif(l_linestatus, 'O')) AS n FROM lineitem")(lambda s, d: load(s, d, "lineitem", "l_returnflag", "l_linestatus").agg(F.count_if(F.nullif("l_returnflag", F.lit("N")).eqNullSafe(F.nullif("l_linestatus", F.lit("O")))).alias("n")))
query("join_taxonomy", "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey")(lambda s, d: load(s, d, "supplier").join(load(s, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(load(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("s_suppkey", "n_name", "r_name"))
query("join_rollout_verdict", "SELECT o_orderkey, count(*) AS n, round(sum(l_quantity), 2) AS q FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey")(lambda s, d: load(s, d, "orders", "o_orderkey").join(load(s, d, "lineitem", "l_orderkey", "l_quantity"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q")))
query("semi_retained", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")(lambda s, d: load(s, d, "customer", "c_custkey").join(load(s, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_semi"))
query("anti_uncovered", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderstatus = 'P')")(lambda s, d: load(s, d, "customer", "c_custkey").join(load(s, d, "orders").filter("o_orderstatus = 'P'"), F.col("c_custkey") == F.col("o_custkey"), "left_anti"))
query("outer_judges", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, d.doc_id IS NULL AS only_right, l.doc_id IS NULL AS only_left FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")(lambda s, d: load(s, d, "documents", "doc_id").withColumn("a", F.lit(1)).join(load(s, d, "labels", "doc_id").withColumn("b", F.lit(1)), "doc_id", "full_outer").select("doc_id", F.isnull("a").alias("only_right"), F.isnull("b").alias("only_left")))


@query("range_split_band", "SELECT b.band, count(*) AS n FROM part JOIN (VALUES ('small', 1, 15), ('mid', 16, 35), ('big', 36, 50)) b(band, lo, hi) ON p_size BETWEEN lo AND hi GROUP BY b.band")
def range_split_band(s, d):
    band = s.createDataFrame([("small", 1, 15), ("mid", 16, 35), ("big", 36, 50)], "band string, lo int, hi int")
    return load(s, d, "part", "p_size").join(F.broadcast(band), F.col("p_size").between(F.col("lo"), F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


@query("asof_checkpoint", "SELECT event_id, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS last_purchase FROM events")
def asof_checkpoint(s, d):
    return last_purchases(load(s, d, "events"))


def last_purchases(events):
    """event_id and last_purchase, the user's latest purchase up to and with the event, of every event."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return events.select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("last_purchase"))


@query("asof_order", "SELECT e.event_id, o.day AS last_order FROM (SELECT event_id, user_id, CAST(ts AS DATE) AS day FROM events) e ASOF LEFT JOIN (SELECT DISTINCT o_custkey, CAST(o_orderdate AS DATE) AS day FROM orders) o ON o.o_custkey = e.user_id AND e.day >= o.day")
def asof_order(s, d):
    """The customer's latest order day up to each event: two tables in one time line, no join."""
    o = load(s, d, "orders", "o_custkey", "o_orderdate").select(F.col("o_custkey").alias("user_id"), F.to_date("o_orderdate").alias("day"), F.lit(None).cast("long").alias("event_id")).distinct()
    e = load(s, d, "events", "user_id", "ts", "event_id").select("user_id", F.to_date("ts").alias("day"), "event_id")
    # orders of a day come before its events
    w = W.partitionBy("user_id").orderBy("day", F.col("event_id").isNotNull(), "event_id")
    both = o.unionByName(e).withColumn("last_order", F.last(F.when(F.col("event_id").isNull(), F.col("day")), ignorenulls=True).over(w))
    return both.filter("event_id is not null").select("event_id", "last_order")


@query("theta_similarity", "SELECT a.doc_id AS a, b.doc_id AS b FROM documents a JOIN documents b ON a.lang = b.lang AND a.source = b.source AND substr(a.text, 1, 20) = substr(b.text, 1, 20) AND a.doc_id < b.doc_id AND abs(a.n_chars - b.n_chars) * 10 <= greatest(a.n_chars, b.n_chars)")
def theta_similarity(s, d):
    """A non-equal condition behind a block of equal keys, so that no nested loop runs."""
    x = load(s, d, "documents", "doc_id", "lang", "source", "text", "n_chars").select("doc_id", "lang", "source", F.substring("text", 1, 20).alias("head"), "n_chars")
    a, b = x.alias("a"), x.alias("b")
    near = F.abs(F.col("a.n_chars") - F.col("b.n_chars")) * 10 <= F.greatest("a.n_chars", "b.n_chars")
    same = [F.col(f"a.{c}") == F.col(f"b.{c}") for c in ("lang", "source", "head")]
    return a.join(b, same[0] & same[1] & same[2] & (F.col("a.doc_id") < F.col("b.doc_id")) & near).select(F.col("a.doc_id").alias("a"), F.col("b.doc_id").alias("b"))


@query("project_verdicts", "SELECT l_partkey AS pair_id, l_quantity > 25 AS flagged, coalesce(nullif(l_returnflag, 'N'), 'none') AS code FROM lineitem")
def project_verdicts(s, d):
    side = F.when(F.col("l_returnflag").isin("A", "N", "R"), True).otherwise(F.raise_error(F.lit("unknown flag")).cast("boolean"))  # a check of the domain
    rows = load(s, d, "lineitem", "l_partkey", "l_quantity", "l_returnflag").filter(side)
    return rows.select(F.col("l_partkey").alias("pair_id"), (F.col("l_quantity") > 25).alias("flagged"), F.coalesce(F.nullif("l_returnflag", F.lit("N")), F.lit("none")).alias("code"))


query("agg_histogram", "SELECT p_brand, p_size // 10 AS bin, count(*) AS n FROM part GROUP BY ALL")(lambda s, d: load(s, d, "part", "p_brand", "p_size").groupBy("p_brand", F.floor(F.col("p_size") / 10).alias("bin")).agg(F.count("*").alias("n")))
query("agg_corr", "SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 6) AS r, round(stddev_pop(l_quantity), 6) AS sd, round(stddev_samp(l_quantity), 6) AS ss FROM lineitem GROUP BY 1")(lambda s, d: load(s, d, "lineitem", "l_returnflag", "l_quantity", "l_extendedprice").groupBy("l_returnflag").agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.stddev_pop("l_quantity"), 6).alias("sd"), F.round(F.stddev_samp("l_quantity"), 6).alias("ss")))
query("agg_listagg", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")(lambda s, d: load(s, d, "nation").groupBy("n_regionkey").agg(F.expr("listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name)").alias("names")))
query("agg_min_max_by", "SELECT p_brand, min_by(p_partkey, (p_size, p_partkey)) AS easiest, max_by(p_partkey, (p_size, p_partkey)) AS hardest FROM part GROUP BY 1")(lambda s, d: load(s, d, "part", "p_brand", "p_partkey", "p_size").groupBy("p_brand").agg(F.min_by("p_partkey", F.struct("p_size", "p_partkey")).alias("easiest"), F.max_by("p_partkey", F.struct("p_size", "p_partkey")).alias("hardest")))
query("agg_sketches")(lambda s, d: load(s, d, "lineitem", "l_returnflag", "l_partkey", "l_quantity").groupBy("l_returnflag").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("n_parts"), F.percentile_approx("l_quantity", 0.5).alias("median")))


query("agg_cube_class_side", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda s, d: load(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n")))
query("agg_rollup_project", "SELECT source, lang, count(*) AS n FROM documents GROUP BY ROLLUP (source, lang)")(lambda s, d: load(s, d, "documents").rollup("source", "lang").agg(F.count("*").alias("n")))
query("agg_grouping_sets", "SELECT source, lang, count(*) AS n FROM documents GROUP BY GROUPING SETS ((source), (lang), ())")(lambda s, d: load(s, d, "documents").groupingSets([["source"], ["lang"], []], "source", "lang").agg(F.count("*").alias("n")))
query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS n_parts FROM lineitem GROUP BY 1")(lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("n_parts")))
query("agg_approx_distinct")(lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("n_parts")))
query("agg_percentiles", "SELECT p_brand, quantile_cont(p_size, 0.5) AS median FROM part GROUP BY 1")(lambda s, d: load(s, d, "part").groupBy("p_brand").agg(F.percentile("p_size", 0.5).alias("median")))
query("agg_pivot_levels", "SELECT lang, count(*) FILTER (q = 0) AS q0, count(*) FILTER (q = 1) AS q1 FROM (SELECT lang, quality AS q FROM documents JOIN labels USING (doc_id)) GROUP BY lang")(lambda s, d: load(s, d, "documents", "doc_id", "lang").join(load(s, d, "labels"), "doc_id").groupBy("lang").pivot("quality", [0, 1]).agg(F.count(F.lit(1))).select("lang", F.coalesce(F.col("`0`"), F.lit(0)).alias("q0"), F.coalesce(F.col("`1`"), F.lit(0)).alias("q1")))

_K = "l_shipdate, l_orderkey, l_linenumber, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax"
_WIN = {
    "win_slots": ("row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id)", lambda w: F.row_number().over(w)),
    "win_rank": ("dense_rank() OVER (PARTITION BY user_id ORDER BY event_type)", lambda w: F.dense_rank().over(W.partitionBy("user_id").orderBy("event_type"))),
    "win_ntile": ("ntile(4) OVER (PARTITION BY user_id ORDER BY ts, event_id)", lambda w: F.ntile(4).over(w)),
    "win_lag": ("lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id)", lambda w: F.lag("event_id").over(w)),
    "win_running_budget": ("round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4)", lambda w: F.round(F.sum("value").over(w.rowsBetween(W.unboundedPreceding, 0)), 4)),
    "win_moving_reward": ("round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 4 PRECEDING), 4)", lambda w: F.round(F.avg("value").over(w.rowsBetween(-4, 0)), 4)),
    "win_range_time": ("count(*) OVER (PARTITION BY user_id ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE 3600 PRECEDING)", lambda w: F.count("*").over(W.partitionBy("user_id").orderBy(F.col("ts").cast("timestamp").cast("long")).rangeBetween(-3600, 0))),
    "win_cume_dist": ("round(cume_dist() OVER (PARTITION BY user_id ORDER BY ts, event_id), 6)", lambda w: F.round(F.cume_dist().over(w), 6)),
}
for _n, (_s, _f) in _WIN.items():
    query(_n, f"SELECT event_id, {_s} AS v FROM events")(lambda s, d, f=_f: load(s, d, "events").select("event_id", f(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("v")))

query("topk_per_query", "SELECT user_id, event_id FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS k FROM events) WHERE k <= 3")(lambda s, d: load(s, d, "events").withColumn("k", F.row_number().over(W.partitionBy("user_id").orderBy(F.desc("value"), "event_id"))).filter("k <= 3").select("user_id", "event_id"))
query("topk_hard_pairs", "SELECT p_partkey, p_size FROM part ORDER BY p_size, p_partkey LIMIT 25")(lambda s, d: load(s, d, "part", "p_partkey", "p_size").orderBy("p_size", "p_partkey").limit(25))
query("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 40")(lambda s, d: load(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(40).limit(20).select("o_orderkey"))
query("global_rank", "SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice, o_orderkey) - 1 AS place FROM orders")(lambda s, d: global_rank(load(s, d, "orders", "o_orderkey", "o_totalprice"), F.col("o_totalprice"), F.col("o_orderkey"), name="place").select("o_orderkey", "place"))
_A, _B = "SELECT l_partkey AS k FROM lineitem WHERE l_quantity < 5", "SELECT p_partkey AS k FROM part WHERE p_size < 20"
for _n, _o in (("set_union", "UNION"), ("set_intersect", "INTERSECT"), ("set_except", "EXCEPT"), ("set_except_all", "EXCEPT ALL")):

    def _set(s, d, n=_n):
        a, b = load(s, d, "lineitem").filter("l_quantity < 5").select(F.col("l_partkey").alias("k")), load(s, d, "part").filter("p_size < 20").select(F.col("p_partkey").alias("k"))
        return {"set_union": lambda: a.union(b).distinct(), "set_intersect": lambda: a.intersect(b), "set_except": lambda: a.subtract(b), "set_except_all": lambda: a.exceptAll(b)}[n]()

    query(_n, f"{_A} {_o} {_B}")(_set)

query("fn_string", "SELECT doc_id, upper(lang) AS u, length(text) AS n, substr(md5(text), 1, 8) AS h, levenshtein(lang, source) AS dist FROM documents")(lambda s, d: load(s, d, "documents").select("doc_id", F.upper("lang").alias("u"), F.length("text").cast("long").alias("n"), F.substring(F.md5("text"), 1, 8).alias("h"), F.levenshtein("lang", "source").cast("long").alias("dist")))
query("fn_date", "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)) AS n, year(o_orderdate) AS y FROM orders")(lambda s, d: load(s, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("date").alias("m"), F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01").cast("date")).cast("long").alias("n"), F.year("o_orderdate").cast("long").alias("y")))
query("fn_math", "SELECT p_partkey, round(ln(1 + p_size), 6) AS a, round(sqrt(p_retailprice), 6) AS b, greatest(p_size, 10) AS c, bit_count(p_size) AS e FROM part")(lambda s, d: load(s, d, "part").select("p_partkey", F.round(F.log1p("p_size"), 6).alias("a"), F.round(F.sqrt("p_retailprice"), 6).alias("b"), F.greatest("p_size", F.lit(10)).alias("c"), F.bit_count("p_size").cast("tinyint").alias("e")))
query("fn_array", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS n, round(CAST(list_max(embedding) AS DOUBLE), 5) AS m FROM embeddings")(lambda s, d: load(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("n"), F.round(F.array_max("embedding").cast("double"), 5).alias("m")))
query("fn_map", "SELECT doc_id, lang AS v FROM documents")(lambda s, d: load(s, d, "documents").select("doc_id", F.element_at(F.create_map(F.lit("a"), "lang", F.lit("b"), "source"), "a").alias("v")))
query("fn_json", "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events")(lambda s, d: load(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))


query("fn_variant", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")(lambda s, d: load(s, d, "events", "event_id", "props").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "long").alias("k")))


def register_table_functions(spark):
    """split_response(text): the parts of a response; patch_diff(before, after): the lines that only one of two texts has."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="part string, body string")
    class SplitResponse:
        def eval(self, text: str):
            if text is None:
                return
            head, opened, rest = text.partition("<think>")
            thought, closed, answer = rest.partition("</think>")
            if opened:
                yield "think", thought
            yield "answer", head + answer if opened else text

    @udtf(returnType="sign string, line string")
    class PatchDiff:
        def eval(self, before: str, after: str):
            a, b = (before or "").split("\n"), (after or "").split("\n")
            for x in dict.fromkeys(a):
                if x not in set(b):
                    yield "-", x
            for x in dict.fromkeys(b):
                if x not in set(a):
                    yield "+", x

    spark.udtf.register("split_response", SplitResponse)
    spark.udtf.register("patch_diff", PatchDiff)


@query("udtf_split_response", "SELECT conv_id, turn, 'think' AS part, md5('t' || turn) AS h FROM conversations UNION ALL SELECT conv_id, turn, 'answer', md5(text) FROM conversations")
def udtf_split_response(s, d):
    register_table_functions(s)
    load(s, d, "conversations").withColumn("whole", F.concat(F.lit("<think>t"), F.col("turn").cast("string"), F.lit("</think>"), "text")).createOrReplaceTempView("whole_responses")
    return s.sql("SELECT conv_id, turn, part, md5(body) AS h FROM whole_responses, LATERAL split_response(whole)")


_PATCH = "WITH x AS (SELECT doc_id // 2 AS pair_id, doc_id % 2 AS s, string_split(coalesce(text, ''), chr(10)) AS l FROM documents), p AS (SELECT a.pair_id, a.l AS a, b.l AS b FROM x a JOIN x b ON a.pair_id = b.pair_id AND a.s = 0 AND b.s = 1)"


@query("patch_diff_lines", f"{_PATCH} SELECT pair_id, '-' AS sign, unnest(list_distinct(list_filter(a, lambda v: NOT list_contains(b, v)))) AS line FROM p UNION ALL SELECT pair_id, '+', unnest(list_distinct(list_filter(b, lambda v: NOT list_contains(a, v)))) FROM p")
def patch_diff_lines(s, d):
    """Lines that only one side of a pair (neighbouring documents) has, by the table function."""
    register_table_functions(s)
    x = load(s, d, "documents", "doc_id", "text").select(F.floor(F.col("doc_id") / 2).alias("pair_id"), (F.col("doc_id") % 2).alias("s"), "text")
    side = lambda k, name: x.filter(F.col("s") == k).select("pair_id", F.col("text").alias(name))
    side(0, "before").join(side(1, "after"), "pair_id").createOrReplaceTempView("text_pairs")
    return s.sql("SELECT pair_id, sign, line FROM text_pairs, LATERAL patch_diff(before, after)")


@query("sink_roundtrip_parquet", "SELECT o_orderkey, o_orderstatus FROM orders")
def sink_roundtrip_parquet(s, d):
    path = T.shared_path(s, "parquet")
    T.write_by(load(s, d, "orders", "o_orderkey", "o_orderstatus"), path, "o_orderstatus")
    return s.read.schema("o_orderkey long, o_orderstatus string").parquet(path)


@query("sink_roundtrip_jsonl", "SELECT conv_id, count(*) AS n FROM conversations GROUP BY conv_id")
def sink_roundtrip_jsonl(s, d):
    path = T.shared_path(s, "jsonl")
    m = F.transform(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))), lambda x: F.struct(x["role"].alias("role"), x["text"].alias("content")))
    T.write_chats(load(s, d, "conversations").groupBy("conv_id").agg(m.alias("messages")), path)
    return T.read_chats(s, path).select("conv_id", F.size("messages").cast("long").alias("n"))
