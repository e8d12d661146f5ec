"""Registered queries of the ten operators, and DuckDB SQL for those that it can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlab.llm import fertility, gam_quality, licenses, mixing, partenum, rlz_dedup, secrets, topk, toxicity, unigram
from pairlab.llm.scratch import documents


def _labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/labels.parquet")


def _predicted(scored: DataFrame, least: float) -> DataFrame:
    return scored.select("doc_id", toxicity.held_out().alias("held_out"), "score", (F.col("score") >= least).cast("int").alias("predicted"))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return _predicted(toxicity.score(docs, toxicity.train(docs, _labels(spark, sf_dir))), 0.5)


def op2_fertility(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fertility.fertility_rules(documents(spark, sf_dir))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rlz_dedup.dedup_substrings(documents(spark, sf_dir))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir), _labels(spark, sf_dir))[0]


def op5_quality_gam(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return _predicted(gam_quality.score(docs, gam_quality.train(docs, _labels(spark, sf_dir))), 0.3)


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.summary(documents(spark, sf_dir))


def op6_license_notices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op6_license_scan, and the notices shorter than a shingle, which its SQL cannot tell."""
    return licenses.summary(documents(spark, sf_dir), templates=licenses.TEMPLATES | licenses.NOTICES)


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return partenum.near_duplicates(documents(spark, sf_dir))


def op8_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def op9_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return unigram.encode_documents(documents(spark, sf_dir))


def op10_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digests(documents(spark, sf_dir))


def op10_secret_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op10_secrets that SQL can tell: those of the fixed patterns."""
    return secrets.digests(documents(spark, sf_dir)).select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256")


QUERIES = {f.__name__: f for f in (op1_toxicity, op2_fertility, op3_substring_dedup, op4_mixing, op5_quality_gam, op6_license_scan, op6_license_notices, op7_jaccard_join, op8_topk, op9_sentencepiece, op10_secrets, op10_secret_base)}

_WORDS = "regexp_extract_all({}, '[^\\x20\\x09-\\x0D]+')"

_LICENSE_TEMPLATES = " UNION ALL ".join(f"SELECT '{k}' AS template, '{v.replace(chr(39), chr(39) * 2)}' AS body" for k, v in licenses.TEMPLATES.items())


def _secret_kind(kind: str, place: int, pattern: str, keep: str) -> str:
    """Spans of one pattern: start from the lengths of the texts between matches and of the matches before."""
    group = 2 if place == 0 else 0
    pattern = pattern.replace("'", "''")
    return f"""SELECT k, '{kind}' AS kind, {place} AS place, stop - n AS start, stop FROM (
  SELECT k, length(m) AS n, g, sum(length(p) + length(m)) OVER (PARTITION BY k ORDER BY i) AS stop FROM (
    SELECT k, unnest(range(1, len(ms) + 1)) AS i, unnest(ms) AS m, unnest(gs) AS g, unnest(ps[1:len(ms)]) AS p FROM (
      SELECT k, regexp_extract_all(t, '{pattern}') AS ms, regexp_extract_all(t, '{pattern}', {group}) AS gs, regexp_split_to_array(t, '{pattern}') AS ps FROM d))) WHERE {keep}"""


_SECRET_WORDS = "(?:[pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])"

ORACLE_SQL = {
    "op10_secret_base": f"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, coalesce(text, '') AS t FROM documents),
s AS ({_secret_kind("assign", 0, "(" + _SECRET_WORDS + """)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", "length(g) >= 8")}
 UNION ALL {_secret_kind("access", 1, "AKIA[A-Z0-9]+", "n >= 16")} UNION ALL {_secret_kind("hex", 2, "[0-9a-f]+", "n >= 32")}),
j AS (SELECT k, count(*) FILTER (place = 0) AS a, count(*) FILTER (place = 1) AS c, count(*) FILTER (place = 2) AS h,
             string_agg(kind || ':' || CAST(start AS BIGINT) || ':' || CAST(stop AS BIGINT), ',' ORDER BY start, place) AS x FROM s GROUP BY k)
SELECT doc_id, coalesce(a, 0) AS n_assign, coalesce(c, 0) AS n_access, coalesce(h, 0) AS n_hex, sha256(coalesce(x, '')) AS base_sha256 FROM d LEFT JOIN j USING (k)""",
    "op3_substring_dedup": f"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, {_WORDS.format("coalesce(text, '')")} AS w FROM documents),
win AS (SELECT k, s, hash(array_to_string(w[s:s + 34], ' ')) AS a, md5(array_to_string(w[s:s + 34], ' ')) AS h
        FROM (SELECT k, w, unnest(range(1, len(w) - 33)) AS s FROM d WHERE len(w) >= 35)),
dup AS (SELECT k, s FROM win JOIN (SELECT h FROM win GROUP BY h HAVING count(*) > 1) USING (h)),
gone AS (SELECT DISTINCT k, s + i AS p FROM dup, range(0, 35) t(i)),
word AS (SELECT k, unnest(range(1, len(w) + 1)) AS p, unnest(w) AS x FROM d),
kept AS (SELECT k, string_agg(x, ' ' ORDER BY p) AS t FROM word ANTI JOIN gone USING (k, p) GROUP BY k),
n AS (SELECT k, count(*) AS c FROM gone GROUP BY k)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(n.c, 0) AS BIGINT) AS n_removed, sha256(coalesce(kept.t, '')) AS kept_sha256
FROM d LEFT JOIN n USING (k) LEFT JOIN kept USING (k)""",
    "op6_license_scan": f"""
WITH t0 AS ({_LICENSE_TEMPLATES}),
t1 AS (SELECT template, regexp_extract_all(lower(body), '[a-z0-9]+') AS w FROM t0),
ts AS (SELECT DISTINCT template, CAST(pow(2, ceil(log2(len(w)))) AS BIGINT) AS step, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT template, w, unnest(range(1, len(w) - 3)) AS i FROM t1)),
tn AS (SELECT template, count(*) AS size FROM ts GROUP BY template),
d AS (SELECT row_number() OVER () AS k, doc_id, regexp_extract_all(lower(coalesce(text, '')), '[a-z0-9]+') AS w FROM documents),
s AS (SELECT k, doc_id, i - 1 AS p, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT k, doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM d WHERE len(w) >= 5)),
hit AS (SELECT k, doc_id, template, step, p, g FROM s JOIN ts USING (g)),
win AS (SELECT k, doc_id, template, p // step - b AS place, g FROM hit, range(0, 2) r(b) WHERE p // step - b >= 0 AND p - (p // step - b) * step < 2 * step - 4),
share AS (SELECT doc_id, template, k, place, 100.0 * count(DISTINCT g) / any_value(size) AS pct FROM win JOIN tn USING (template) GROUP BY doc_id, template, k, place)
SELECT doc_id, template, CAST(count(*) AS BIGINT) AS n_windows, CAST(max(pct) AS DOUBLE) AS best FROM share WHERE pct >= 80 GROUP BY doc_id, template""",
    "op7_jaccard_join": f"""
WITH RECURSIVE d AS (SELECT doc_id, {_WORDS.format("translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')")} AS w FROM documents),
s AS (SELECT DISTINCT doc_id, md5(array_to_string(w[i:i + 4], ' ')) AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(2, len(w) - 3))) AS i FROM d WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS c FROM s GROUP BY doc_id),
pair AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY x, y),
link AS (SELECT x, y FROM pair JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * pair.c >= 80 * (a.c + b.c - pair.c)),
reach AS (SELECT x AS who, x AS seen FROM link UNION SELECT r.who, l.y FROM reach r JOIN link l ON l.x = r.seen),
low AS (SELECT who, min(seen) AS m FROM reach GROUP BY who)
SELECT d.doc_id, CAST(coalesce(n.c, 0) AS BIGINT) AS n_shingles, coalesce(low.m, d.doc_id) AS component_id
FROM d LEFT JOIN n USING (doc_id) LEFT JOIN low ON low.who = d.doc_id""",
    "op8_topk": """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(range(1, len(q.e) + 1), lambda i: q.e[i] * c.e[i])) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 100 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM s)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM r WHERE rank <= 10""",
}
