"""Queries: dataset construction (deduplication, context, splits, statistics)."""

from __future__ import annotations

from pyspark.sql import functions as F

from pairlab.operators import curate as C
from pairlab.operators.workloads import ROLL
from pairlab.registry import query
from pairlab.sources.fixtures import rollouts
from pairlab.sources.tables import load, saved, shingles, words


@query("pairs_complete", f"WITH {ROLL} SELECT pair_id, count(*) AS n FROM roll GROUP BY pair_id HAVING bool_or(side = 'pre') AND bool_or(side = 'post')")
def pairs_complete(spark, d):
    p = rollouts(spark, d).groupBy("pair_id").agg(F.count("*").alias("n"), F.bool_or(F.col("side") == "pre").alias("a"), F.bool_or(F.col("side") == "post").alias("b"))
    return p.filter("a and b").select("pair_id", "n")


query("dedup_exact", "SELECT min(doc_id) AS doc_id, count(*) AS n_copies FROM documents GROUP BY regexp_replace(trim(text), '\\s+', ' ', 'g')")(lambda spark, d: C.exact_dedup(load(spark, d, "documents", "doc_id", "text")))


@query(
    "dedup_pair_safe",
    "WITH n AS (SELECT doc_id // 2 AS pair_id, doc_id % 2 AS s, regexp_replace(trim(text), '\\s+', ' ', 'g') AS t FROM documents), p AS (SELECT pair_id, max(t) FILTER (s = 0) AS a, max(t) FILTER (s = 1) AS b FROM n GROUP BY pair_id) SELECT min(pair_id) AS pair_id, count(*) AS n_copies FROM p GROUP BY a, b",
)
def dedup_pair_safe(spark, d):
    """Neighbouring documents stand for the two sides of a pair."""
    s = load(spark, d, "documents", "doc_id", "text").select(F.floor(F.col("doc_id") / 2).alias("pair_id"), F.when(F.col("doc_id") % 2 == 0, "pre").otherwise("post").alias("side"), "text")
    return C.pair_dedup(s)


query("strip_html_comments", "SELECT page_id, md5(regexp_replace(html, '(?s)<!--.*?(-->|$)', '', 'g')) AS h FROM pages")(lambda spark, d: load(spark, d, "pages", "page_id", "html").select("page_id", F.md5(C.strip_html_comments(F.col("html"))).alias("h")))
query("strip_license_lines", "SELECT doc_id, md5(array_to_string(list_filter(string_split(text, chr(10)), lambda x: NOT regexp_matches(x, '[Ll]icen|[Cc]opyright')), chr(10))) AS h FROM documents")(lambda spark, d: load(spark, d, "documents", "doc_id", "text").select("doc_id", F.md5(C.strip_lines(F.col("text"), "[Ll]icen|[Cc]opyright")).alias("h")))


ORDER, CALLEE, TYPE, MACRO, GLOBAL = "order", "callee", "type", "macro", "global"


def _edges(df, src_kind, src, kind, dst):
    return df.select(F.lit(src_kind).alias("src_kind"), F.col(src).cast("long").alias("src"), F.lit(kind).alias("kind"), F.col(dst).cast("long").alias("dst"))


def ctx(spark, d):
    """Seeds (orders) and dependency edges: order to part (callee) and supplier (type), supplier to nation (macro), nation to region (global)."""
    li = load(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_suppkey")
    e = _edges(li, ORDER, "l_orderkey", CALLEE, "l_partkey").union(_edges(li, ORDER, "l_orderkey", TYPE, "l_suppkey"))
    e = e.union(above(spark, d))
    seeds = load(spark, d, "orders", "o_orderkey").select(F.col("o_orderkey").alias("sample"), F.lit(ORDER).alias("kind"), F.col("o_orderkey").alias("id"))
    return seeds, e


def above(spark, d):
    """The edges behind the first hop."""
    return _edges(load(spark, d, "supplier"), TYPE, "s_suppkey", MACRO, "s_nationkey").union(_edges(load(spark, d, "nation"), MACRO, "n_nationkey", GLOBAL, "n_regionkey"))


def bodies(spark, d):
    """kind, id, n_tok: the length of a node's name stands for its tokens."""
    one = lambda t, k, i, n: load(spark, d, t).select(F.lit(k).alias("kind"), F.col(i).cast("long").alias("id"), F.length(n).alias("n_tok"))
    return one("part", CALLEE, "p_partkey", "p_name").union(one("supplier", TYPE, "s_suppkey", "s_name")).union(one("nation", MACRO, "n_nationkey", "n_name")).union(one("region", GLOBAL, "r_regionkey", "r_name"))


H1 = "h1 AS (SELECT DISTINCT l_orderkey AS sample, 1 AS hop, 'callee' AS kind, l_partkey AS id FROM lineitem UNION SELECT l_orderkey, 1, 'type', l_suppkey FROM lineitem)"
H3 = f"{H1}, h2 AS (SELECT DISTINCT sample, 2 AS hop, 'macro' AS kind, CAST(s_nationkey AS BIGINT) AS id FROM h1 JOIN supplier ON kind = 'type' AND s_suppkey = id), h3 AS (SELECT DISTINCT sample, 3 AS hop, 'global' AS kind, CAST(n_regionkey AS BIGINT) AS id FROM h2 JOIN nation ON n_nationkey = id), h AS (SELECT * FROM h1 UNION ALL SELECT * FROM h2 UNION ALL SELECT * FROM h3)"
BODY = "body AS (SELECT 'callee' AS kind, p_partkey AS id, length(p_name) AS n_tok FROM part UNION ALL SELECT 'type', s_suppkey, length(s_name) FROM supplier UNION ALL SELECT 'macro', n_nationkey, length(n_name) FROM nation UNION ALL SELECT 'global', r_regionkey, length(r_name) FROM region)"
_HASHED = "sample, count(*) AS n_context, md5(string_agg(kind || id, ',' ORDER BY kind || id)) AS context_hash"


def _context(spark, d, hops):
    seeds, e = ctx(spark, d)
    node = F.concat("kind", F.col("id").cast("string"))
    return C.expand(seeds, e, hops).groupBy("sample").agg(F.count("*").alias("n_context"), F.md5(F.array_join(F.array_sort(F.collect_list(node)), ",")).alias("context_hash"))


query("context_expand_1hop", f"WITH {H1} SELECT {_HASHED} FROM h1 GROUP BY sample")(lambda spark, d: _context(spark, d, 1))
query("context_expand_3hop", f"WITH {H3} SELECT {_HASHED} FROM h GROUP BY sample")(lambda spark, d: _context(spark, d, 3))


@query("context_budgeted", f"WITH {H3}, {BODY}, r AS (SELECT sample, sum(n_tok) OVER (PARTITION BY sample ORDER BY hop, kind, id) AS used FROM h JOIN body USING (kind, id)) SELECT sample, count(*) AS n_context, CAST(max(used) AS BIGINT) AS n_tok FROM r WHERE used <= 120 GROUP BY sample")
def context_budgeted(spark, d, budget: int = 120):
    seeds, e = ctx(spark, d)
    return C.expand(seeds, e, 3, bodies=bodies(spark, d), budget=budget).groupBy("sample").agg(F.count("*").alias("n_context"), F.sum("n_tok").alias("n_tok"))


@query("context_kinds", f"WITH {H3}, {BODY} SELECT sample, kind, count(*) AS n, CAST(sum(n_tok) AS BIGINT) AS n_tok FROM h JOIN body USING (kind, id) WHERE kind IN ('type', 'global') GROUP BY sample, kind")
def context_kinds(spark, d):
    """Two of the four dependencies only, with the tokens of their bodies."""
    seeds, e = ctx(spark, d)
    return C.expand(seeds, e, 3, kinds=(TYPE, GLOBAL), bodies=bodies(spark, d)).groupBy("sample", "kind").agg(F.count("*").alias("n"), F.sum("n_tok").alias("n_tok"))


@query("context_fallback", "WITH a AS (SELECT l_orderkey AS sample, count(DISTINCT l_partkey) AS n FROM lineitem WHERE l_linestatus = 'F' GROUP BY 1), b AS (SELECT l_orderkey AS sample, count(DISTINCT l_partkey) AS n FROM lineitem WHERE l_orderkey NOT IN (SELECT sample FROM a) GROUP BY 1) SELECT sample, n, 'primary' AS source FROM a UNION ALL SELECT sample, n, 'fallback' FROM b")
def context_fallback(spark, d):
    """Edges of the one line status stand for the precise extraction, all edges for the other."""
    li = load(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_linestatus").withColumnRenamed("l_orderkey", "sample")
    return C.coalesce_sources(li.filter("l_linestatus = 'F'"), li).groupBy("sample", "source").agg(F.count_distinct("l_partkey").alias("n"))


def side_context(spark, d, key: str):
    """Context over two hops of samples, or of pairs: an order line's supplier is a side's dependency, and what lies behind it."""
    r = rollouts(spark, d).select(F.col(key).alias("sample"), "l_suppkey")
    seeds = r.select("sample", F.lit("sample").alias("kind"), F.col("sample").alias("id")).distinct()
    return C.expand(seeds, _edges(r, "sample", "sample", TYPE, "l_suppkey").union(above(spark, d)), 3)


_SIDED = "r1 AS (SELECT DISTINCT {key} AS sample, 'type' AS kind, l_suppkey AS id FROM roll), r2 AS (SELECT DISTINCT sample, 'macro', s_nationkey FROM r1 JOIN supplier ON s_suppkey = id), r3 AS (SELECT DISTINCT sample, 'global', n_regionkey FROM r1 JOIN supplier ON s_suppkey = id JOIN nation ON n_nationkey = s_nationkey), u AS (SELECT * FROM r1 UNION ALL SELECT * FROM r2 UNION ALL SELECT * FROM r3)"
for _name, _key in (("context_per_side", "sample_id"), ("context_shared_baseline", "pair_id")):
    query(_name, f"WITH {ROLL}, {_SIDED.format(key=_key)} SELECT sample AS {_key}, count(*) AS n_context FROM u GROUP BY sample")(lambda spark, d, k=_key: side_context(spark, d, k).groupBy(F.col("sample").alias(k)).agg(F.count("*").alias("n_context")))


@query("context_new_on_fix", f"WITH {ROLL}, {_SIDED.format(key='sample_id')}, p AS (SELECT sample // 2 AS pair_id, sample % 2 AS s, kind, id FROM u) SELECT a.pair_id, count(*) AS n_new FROM p a WHERE s = 1 AND NOT EXISTS (SELECT 1 FROM p b WHERE b.pair_id = a.pair_id AND b.s = 0 AND b.kind = a.kind AND b.id = a.id) GROUP BY a.pair_id")
def context_new_on_fix(spark, d):
    """Dependencies that only the fixed side has, which a context shared by both sides would give away or miss."""
    c = side_context(spark, d, "sample_id").select(F.floor(F.col("sample") / 2).alias("pair_id"), (F.col("sample") % 2).alias("s"), "kind", "id")
    fixed, before = c.filter("s = 1"), c.filter("s = 0")
    return fixed.join(before, ["pair_id", "kind", "id"], "left_anti").groupBy("pair_id").agg(F.count("*").alias("n_new"))


_LINES = "SELECT doc_id // 2 AS pair_id, doc_id % 2 AS s, list_distinct(list_filter(string_split(coalesce(text, ''), '. '), lambda x: x <> '')) AS l FROM documents"
_TERMS = "len(list_distinct(flatten(list_transform({0}, lambda x: regexp_extract_all(x, '[A-Za-z]+')))))"


@query("context_seed_compare", f"WITH x AS ({_LINES}), p AS (SELECT a.pair_id, a.l AS l, list_filter(a.l, lambda x: NOT list_contains(b.l, x)) AS c FROM x a JOIN x b ON a.pair_id = b.pair_id AND a.s = 0 AND b.s = 1) SELECT pair_id, {_TERMS.format('l')} AS n_blind, {_TERMS.format('c')} AS n_guided FROM p")
def context_seed_compare(spark, d):
    """Seeds of the context by pair: the terms of the whole text before the fix (blind to the place), and of its changed sentences
    only (guided by the diff, which an unfixed flaw does not have)."""
    lines = F.array_distinct(F.filter(F.split(F.coalesce("text", F.lit("")), "\\. "), lambda x: x != ""))
    x = load(spark, d, "documents", "doc_id", "text").select(F.floor(F.col("doc_id") / 2).alias("pair_id"), (F.col("doc_id") % 2).alias("s"), lines.alias("l"))
    at = lambda k: F.first(F.when(F.col("s") == k, F.col("l")), ignorenulls=True)  # noqa: E731  one of each
    p = x.groupBy("pair_id").agg(at(0).alias("a"), at(1).alias("b")).filter("a is not null and b is not null")
    terms = lambda c: F.size(F.array_distinct(F.flatten(F.transform(c, lambda s: F.regexp_extract_all(s, F.lit("([A-Za-z]+)"), F.lit(1)))))).cast("long")
    return p.select("pair_id", terms(F.col("a")).alias("n_blind"), terms(F.array_except("a", "b")).alias("n_guided"))


@query("context_coverage", "SELECT count(*) AS n, count(*) FILTER (EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)) AS n_with FROM orders")
def context_coverage(spark, d):
    li = load(spark, d, "lineitem", "l_orderkey").distinct().withColumn("has", F.lit(True))
    return load(spark, d, "orders", "o_orderkey").join(li, F.col("o_orderkey") == F.col("l_orderkey"), "left").agg(F.count("*").alias("n"), F.count_if(F.col("has")).alias("n_with"))


@query("page_link_edges", "WITH l AS (SELECT DISTINCT page_id AS src, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS dst FROM pages) SELECT src, dst, dst IN (SELECT url FROM pages) AS known FROM l")
def page_link_edges(spark, d):
    """Lexical edges of pages, and whether they lead to a page of the table."""
    links = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))
    e = load(spark, d, "pages", "page_id", "html").select(F.col("page_id").alias("src"), F.explode(links).alias("dst")).distinct()
    urls = load(spark, d, "pages", "url").distinct().select(F.col("url").alias("dst"), F.lit(True).alias("known"))
    return e.join(urls, "dst", "left").select("src", "dst", F.coalesce("known", F.lit(False)).alias("known"))


SPLIT = "dy AS (SELECT CAST(o_orderdate AS DATE) AS day, count(*) AS n FROM orders GROUP BY 1), rn AS (SELECT day, sum(n) OVER (ORDER BY day) AS run, sum(n) OVER () AS total FROM dy), ct AS (SELECT day, CASE WHEN 10 * run <= 8 * total THEN 'train' WHEN 10 * run <= 9 * total THEN 'val' ELSE 'test' END AS split FROM rn), os AS (SELECT o.*, split FROM orders o JOIN ct ON ct.day = CAST(o.o_orderdate AS DATE))"


def split_orders(spark, d):
    return C.temporal_split(load(spark, d, "orders").withColumn("day", F.to_date("o_orderdate")), "day")


@query("split_temporal", f"WITH {SPLIT} SELECT split, count(*) AS n, min(CAST(o_orderdate AS DATE)) AS min_date, max(CAST(o_orderdate AS DATE)) AS max_date FROM os GROUP BY split")
def split_temporal(spark, d):
    return split_orders(spark, d).groupBy("split").agg(F.count("*").alias("n"), F.min("day").alias("min_date"), F.max("day").alias("max_date"))


@query("split_balance", f"WITH {SPLIT} SELECT split, o_orderstatus, count(*) AS n FROM os GROUP BY ALL")
def split_balance(spark, d):
    return split_orders(spark, d).groupBy("split", "o_orderstatus").agg(F.count("*").alias("n"))


@query("split_hashed", "SELECT CASE WHEN b < 8 THEN 'train' WHEN b = 8 THEN 'val' ELSE 'test' END AS split, count(*) AS n FROM (SELECT CAST('0x' || substr(md5('42:' || o_orderkey), 1, 6) AS BIGINT) % 10 AS b FROM orders) GROUP BY 1")
def split_hashed(spark, d):
    return C.hashed_split(load(spark, d, "orders", "o_orderkey"), "o_orderkey").groupBy("split").agg(F.count("*").alias("n"))


@query("split_leakage", f"WITH {SPLIT}, k AS (SELECT o_custkey, count(DISTINCT split) AS n FROM os GROUP BY 1) SELECT count(*) AS n_keys, count(*) FILTER (n > 1) AS n_leaking FROM k")
def split_leakage(spark, d):
    """Projects in two splits."""
    return C.leakage(split_orders(spark, d), "split", "o_custkey")


_HSPLIT = "CASE WHEN b < 8 THEN 'train' WHEN b = 8 THEN 'val' ELSE 'test' END"


@query("split_leakage_text", f"WITH s AS (SELECT md5(coalesce(text, '')) AS h, {_HSPLIT} AS split FROM (SELECT text, CAST('0x' || substr(md5('42:' || doc_id), 1, 6) AS BIGINT) % 10 AS b FROM documents)), k AS (SELECT h, count(DISTINCT split) AS n FROM s GROUP BY h) SELECT count(*) AS n_keys, count(*) FILTER (n > 1) AS n_leaking FROM k")
def split_leakage_text(spark, d):
    """Equal texts in two splits of a hashed split by document."""
    s = C.hashed_split(load(spark, d, "documents", "doc_id", "text"), "doc_id").select("split", F.md5(F.coalesce("text", F.lit(""))).alias("h"))
    return C.leakage(s, "split", "h")


@query("bench_contamination", "WITH g AS (SELECT DISTINCT array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT regexp_extract_all(text, '\\S+') AS w FROM benchmark) WHERE len(w) >= 8)), s AS (SELECT doc_id, array_to_string(w[i:i + 7], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM (SELECT doc_id, regexp_extract_all(text, '\\S+') AS w FROM documents) WHERE len(w) >= 8)) SELECT doc_id, count(DISTINCT g) AS n_hits FROM s JOIN g USING (g) GROUP BY doc_id")
def bench_contamination(spark, d, n: int = 8):
    def grams(df, *keys):
        return df.select(*keys, F.explode_outer(shingles(F.col("text"), n)).alias("g")).filter("g is not null")

    hits = grams(load(spark, d, "documents", "doc_id", "text"), "doc_id").join(grams(load(spark, d, "benchmark", "text")).distinct(), "g", "left_semi")
    return hits.distinct().groupBy("doc_id").agg(F.count("*").alias("n_hits"))


_MEASURES = "SELECT doc_id, d.lang, d.source, len(regexp_extract_all(coalesce(d.text, ''), '\\S+')) AS function_tokens, len(regexp_extract_all(b.text, '\\S+')) AS context_tokens FROM documents d JOIN (SELECT *, count(*) OVER () AS m FROM benchmark) b ON b.item_id = d.doc_id % m"
_LONG = "SELECT {by} 'function_tokens' AS measure, function_tokens AS v FROM m UNION ALL SELECT {by} 'context_tokens', context_tokens FROM m UNION ALL SELECT {by} 'total_tokens', function_tokens + context_tokens FROM m"
_SUMS = "CAST(min(v) AS DOUBLE) AS min_v, round(avg(v), 4) AS mean_v, CAST(max(v) AS DOUBLE) AS max_v"
MEASURES = ("function_tokens", "context_tokens", "total_tokens")


def measured(spark, d):
    """Documents as functions, the benchmark item that is their evidence as context, in words."""
    from pairlab.operators.workloads_policy import with_evidence

    n = lambda c: F.size(words(F.coalesce(F.col(c), F.lit("")))).cast("long")
    rows = with_evidence(spark, d).select("doc_id", n("text").alias("function_tokens"), n("evidence").alias("context_tokens"))
    return rows.withColumn("total_tokens", F.col("function_tokens") + F.col("context_tokens"))


@query("dataset_stats", f"WITH m AS ({_MEASURES}), l AS ({_LONG.format(by='')}) SELECT measure, {_SUMS} FROM l GROUP BY measure")
def dataset_stats(spark, d):
    return C.describe(measured(spark, d), MEASURES)


@query("dataset_counts", "SELECT count(*) AS n_samples, count(DISTINCT source) AS n_projects, count(DISTINCT lang) AS n_classes FROM documents")
def dataset_counts(spark, d):
    return load(spark, d, "documents", "source", "lang").agg(F.count("*").alias("n_samples"), F.count_distinct("source").alias("n_projects"), F.count_distinct("lang").alias("n_classes"))


@query("dataset_stats_by_split", f"WITH m AS (SELECT *, {_HSPLIT} AS split FROM (SELECT *, CAST('0x' || substr(md5('42:' || doc_id), 1, 6) AS BIGINT) % 10 AS b FROM ({_MEASURES}))), l AS ({_LONG.format(by='split,')}) SELECT measure, split, {_SUMS} FROM l GROUP BY GROUPING SETS ((measure), (measure, split))")
def dataset_stats_by_split(spark, d):
    return C.describe(C.hashed_split(measured(spark, d), "doc_id"), MEASURES, ("split",))


def grade(catalogue, scales: tuple = (200, 1000), shares: tuple = (0.5, 0.95)):
    """name, n, context and accuracy (shares), each with its grade: low, middle or high."""
    def of(c, steps):
        return F.when(F.col(c) >= steps[1], "high").when(F.col(c) >= steps[0], "middle").otherwise("low").alias(f"{c}_grade")

    return catalogue.select("name", "n", F.round("context", 6).alias("context"), F.round("accuracy", 6).alias("accuracy"), of("n", scales), of("context", shares), of("accuracy", shares))


_GRADE = "CASE WHEN {0} >= {2} THEN 'high' WHEN {0} >= {1} THEN 'middle' ELSE 'low' END AS {0}_grade"


@query(
    "dataset_grades",
    "WITH q AS (SELECT quality, lang, source, text FROM documents JOIN labels USING (doc_id)), c AS ("
    "SELECT 'documents' AS name, count(*) AS n, avg(CAST(length(coalesce(text, '')) > 0 AS INT)) AS context, avg(CAST(lang IS NOT NULL AND source IS NOT NULL AS INT)) AS accuracy FROM documents "
    "UNION ALL SELECT 'pages', count(*), avg(CAST(contains(html, 'href') AS INT)), avg(CAST(starts_with(url, 'http') AS INT)) FROM pages "
    "UNION ALL SELECT 'labelled', count(*), avg(CAST(length(coalesce(text, '')) > 0 AS INT)), avg(CAST(quality AS INT)) FROM q "
    "UNION ALL SELECT 'conversations', count(*), avg(CAST(turn > 0 AS INT)), avg(CAST(role IN ('user', 'assistant', 'system') AS INT)) FROM conversations) "
    f"SELECT name, n, round(context, 6) AS context, round(accuracy, 6) AS accuracy, {_GRADE.format('n', 200, 1000)}, {_GRADE.format('context', 0.5, 0.95)}, {_GRADE.format('accuracy', 0.5, 0.95)} FROM c",
)
def dataset_grades(spark, d):
    """Four catalogues by scale, by the share of rows with context, and by the share of rows with a right label (as far as the table tells)."""
    share = lambda c, name: F.avg(c.cast("int")).alias(name)
    filled = F.length(F.coalesce("text", F.lit(""))) > 0
    docs = load(spark, d, "documents")
    parts = {
        "documents": docs.agg(F.count("*").alias("n"), share(filled, "context"), share(F.col("lang").isNotNull() & F.col("source").isNotNull(), "accuracy")),
        "pages": load(spark, d, "pages").agg(F.count("*").alias("n"), share(F.contains(F.col("html"), F.lit("href")), "context"), share(F.startswith(F.col("url"), F.lit("http")), "accuracy")),
        "labelled": docs.join(load(spark, d, "labels"), "doc_id").agg(F.count("*").alias("n"), share(filled, "context"), share(F.col("quality"), "accuracy")),
        "conversations": load(spark, d, "conversations").agg(F.count("*").alias("n"), share(F.col("turn") > 0, "context"), share(F.col("role").isin("user", "assistant", "system"), "accuracy")),
    }
    out = None
    for name, one in parts.items():
        one = one.withColumn("name", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return grade(out)


@query("length_guard", "SELECT doc_id, least(len(regexp_extract_all(text, '\\S+')), 100) AS n_kept, len(regexp_extract_all(text, '\\S+')) > 100 AS cut FROM documents")
def length_guard(spark, d, most: int = 100):
    w = load(spark, d, "documents", "doc_id", "text").select("doc_id", words(F.col("text")).alias("w")).withColumn("n", F.size("w"))
    return C.length_guard(w, "w", most).select("doc_id", F.size("w").cast("long").alias("n_kept"), (F.col("n") > most).alias("cut"))


@query("length_guard_drop", "SELECT doc_id FROM documents WHERE len(regexp_extract_all(text, '\\S+')) <= 100")
def length_guard_drop(spark, d, most: int = 100):
    w = load(spark, d, "documents", "doc_id", "text").select("doc_id", words(F.col("text")).alias("w"))
    return C.length_guard(w, "w", most, "drop").select("doc_id")


@query("spec_terms", "WITH w AS (SELECT item_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS t FROM benchmark), tf AS (SELECT item_id, t, count(*) AS f FROM w GROUP BY ALL), df AS (SELECT t, count(*) AS df FROM tf GROUP BY t), r AS (SELECT item_id, t, row_number() OVER (PARTITION BY item_id ORDER BY f DESC, df, t) AS k FROM tf JOIN df USING (t)) SELECT item_id, string_agg(t, ' ' ORDER BY k) AS terms FROM r WHERE k <= 5 GROUP BY item_id")
def spec_terms(spark, d):
    from pyspark.sql import Window as W

    w = load(spark, d, "benchmark").select("item_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("([a-z]+)"), F.lit(1))).alias("t"))
    tf = w.groupBy("item_id", "t").agg(F.count("*").alias("f"))
    r = tf.join(tf.groupBy("t").agg(F.count("*").alias("df")), "t").withColumn("k", F.row_number().over(W.partitionBy("item_id").orderBy(F.desc("f"), "df", "t"))).filter("k <= 5")
    return r.groupBy("item_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("k", "t"))), lambda x: x["t"]), " ").alias("terms"))


@query("guard_repetition", "SELECT doc_id, len(x) - len(list_distinct(x)) AS n_repeated FROM (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda s: s <> '') AS x FROM documents)")
def guard_repetition(spark, d):
    x = F.filter(F.split("text", "\n"), lambda s: s != "")
    return load(spark, d, "documents", "doc_id", "text").select("doc_id", x.alias("x")).select("doc_id", (F.size("x") - F.size(F.array_distinct("x"))).cast("long").alias("n_repeated"))


_SETS = "s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 3, 1))) AS i FROM (SELECT doc_id, regexp_extract_all(text, '\\S+') AS w FROM documents))), k AS (SELECT doc_id, md5(string_agg(g, '|' ORDER BY g)) AS h, count(*) AS c FROM s GROUP BY doc_id), cl AS (SELECT min(doc_id) AS rep, h, any_value(c) AS c FROM k GROUP BY h)"


def shingle_classes(spark, d, shingle: int = 5):
    """rep (smallest document), s (sorted shingle hashes), n_docs of each distinct set, written once: copies meet here and in no join."""
    hashed = F.array_sort(F.array_distinct(F.transform(shingles(F.col("text"), shingle), lambda g: F.xxhash64(g))))
    sets = load(spark, d, "documents", "doc_id", "text").select("doc_id", hashed.alias("s")).filter("s is not null")
    return saved(sets.groupBy("s").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n_docs")), "sets")


def _jaccard(pairs, sets, least: float):
    """The pairs (a, b) of class representatives that reach a Jaccard similarity of least."""
    both = pairs.join(sets.select(F.col("rep").alias("a"), F.col("s").alias("x")), "a").join(sets.select(F.col("rep").alias("b"), F.col("s").alias("y")), "b")
    c = F.size(F.array_intersect("x", "y"))
    return both.filter(c >= least * (F.size("x") + F.size("y") - c)).select("a", "b")


@query("near_pairs_exact", f"WITH {_SETS}, sc AS (SELECT rep, g FROM s JOIN cl ON cl.rep = s.doc_id), p AS (SELECT x.rep AS a, y.rep AS b, count(*) AS c FROM sc x JOIN sc y ON x.g = y.g AND x.rep < y.rep GROUP BY 1, 2) SELECT p.a, p.b FROM p JOIN cl x ON x.rep = p.a JOIN cl y ON y.rep = p.b WHERE 2 * p.c >= x.c + y.c - p.c")
def near_pairs_exact(spark, d, shingle: int = 5):
    """Pairs of class representatives (equal sets are one class) with Jaccard of one half or more, by a prefix filter: a pair shares one of each set's rarest shingles."""
    from pyspark.sql import Window as W

    sets = shingle_classes(spark, d, shingle)
    flat = sets.select("rep", F.size("s").alias("n"), F.explode("s").alias("g"))
    df = flat.groupBy("g").agg(F.count("*").alias("df"))
    place = F.row_number().over(W.partitionBy("rep").orderBy("df", "g"))
    prefix = flat.join(df, "g").withColumn("k", place).filter("df > 1 and k <= n - ceil(n / 2) + 1").select("rep", "n", "g")
    a, b = prefix.alias("a"), prefix.alias("b")
    meet = a.join(b, (F.col("a.g") == F.col("b.g")) & (F.col("a.rep") < F.col("b.rep")) & (F.col("a.n") <= 2 * F.col("b.n")) & (F.col("b.n") <= 2 * F.col("a.n"))).select(F.col("a.rep").alias("a"), F.col("b.rep").alias("b")).distinct()
    return _jaccard(meet, sets, 0.5)


@query("near_classes", f"WITH {_SETS} SELECT k.doc_id, cl.rep, cl.c AS n_shingles FROM k JOIN cl USING (h)")
def near_classes(spark, d, shingle: int = 5):
    """The classes' members: doc_id, its representative and the size of the set."""
    hashed = F.array_sort(F.array_distinct(F.transform(shingles(F.col("text"), shingle), lambda g: F.xxhash64(g))))
    sets = load(spark, d, "documents", "doc_id", "text").select("doc_id", hashed.alias("s")).filter("s is not null").select("doc_id", F.md5(F.concat_ws("|", F.transform("s", lambda x: x.cast("string")))).alias("h"), F.size("s").cast("long").alias("n_shingles"))
    rep = sets.groupBy("h").agg(F.min("doc_id").alias("rep"))
    return sets.join(rep, "h").select("doc_id", "rep", "n_shingles")


@query("near_pairs_lsh")
def near_pairs_lsh(spark, d, shingle: int = 5, bands: int = 40, rows: int = 2, least: float = 0.5):
    """The same pairs by MinHash bands: classes that agree on a band are verified. A pair of similarity s is found with
    probability 1 - (1 - s^rows)^bands, 0.99999 at one half. A class that agrees with its band's smallest one and with others meets all."""
    sets = shingle_classes(spark, d, shingle)
    mins = F.transform(F.sequence(F.lit(1), F.lit(bands * rows)), lambda k: F.array_min(F.transform("s", lambda x: F.xxhash64(x, k))))
    keys = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.xxhash64(b, F.slice("m", b * rows + 1, rows)))
    banded = sets.withColumn("m", mins).select("rep", F.explode(keys).alias("band"))
    pairs = banded.alias("x").join(banded.alias("y"), (F.col("x.band") == F.col("y.band")) & (F.col("x.rep") < F.col("y.rep"))).select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b")).distinct()
    return _jaccard(pairs, sets, least)
