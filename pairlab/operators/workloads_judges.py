"""Queries: judges, guards, specifications from evidence, cost."""

from __future__ import annotations

from pyspark.sql import functions as F

from pairlab.operators import judges as J
from pairlab.operators import rl
from pairlab.operators.workloads_policy import GOOD, PAIRED, answered, graded, with_evidence
from pairlab.registry import query
from pairlab.sources.tables import load, saved, shared_path


@query("judge_external", f"WITH {PAIRED}, t AS (SELECT conv_id, turn, list_distinct(regexp_extract_all(text, '\\S+')) AS e, list_distinct(regexp_extract_all(answer, '\\S+')) AS r FROM qa) SELECT 'words' AS judge_id, count(*) AS n, count(*) FILTER (5 * len(list_intersect(e, r)) >= len(e)) AS n_correct FROM t")
def judge_external(spark, d):
    """All answers through the plug-in interface, in batches."""
    rows = answered(spark, d).select("conv_id", "turn", F.col("answer").alias("response"), F.col("text").alias("evidence"))
    return J.Judge("words", J.shares_words).evaluate(rows).groupBy("judge_id").agg(F.count("*").alias("n"), F.count_if("correct").alias("n_correct"))


_VERDICTS = "v AS (SELECT sample_id, slot, CASE WHEN l_orderkey % 17 = 0 THEN NULL ELSE ok <> (l_orderkey % 50 = 0) END AS correct, ok FROM ok)"
for _p, _missing in (("drop", "false"), ("incorrect", "false")):
    query(f"judge_protocol_{_p}", f"WITH {GOOD}, {_VERDICTS} SELECT sample_id, CAST(slot AS INTEGER) AS slot FROM v WHERE coalesce(correct, {_missing})")(lambda spark, d, p=_p: judged_rollouts(spark, d, p))


def judged_rollouts(spark, d, on_missing: str):
    """Rollouts that pass a judge who errs on some rows and gives no verdict on others."""
    g = graded(spark, d)
    said = F.when(F.col("l_orderkey") % 17 != 0, F.col("ok") != (F.col("l_orderkey") % 50 == 0))
    rows = saved(g.select("sample_id", "slot", said.alias("correct")), "verdicts")
    return J.protocol(g.select("sample_id", "slot"), rows, on_missing=on_missing)


@query("guard_contradiction", "SELECT count(*) AS n, count(*) FILTER (regexp_matches(lower(t), 'no (flaw|issue|problem|vulnerabilit)[a-z]* (was |were )?(found|detected|present)|none found|is (safe|not flawed)') AND p IS NOT NULL) AS n_contradicting FROM (SELECT CASE event_id % 4 WHEN 0 THEN 'No flaw was found in ' WHEN 1 THEN 'The code is safe: ' WHEN 2 THEN 'Out of bounds write in ' ELSE 'None found ' END || event_type AS t, CASE WHEN event_id % 3 = 0 THEN event_type END AS p FROM events)")
def guard_contradiction(spark, d):
    """Verdict texts built on events, with a predicted class on each third."""
    said = F.element_at(F.array(*map(F.lit, ("No flaw was found in ", "The code is safe: ", "Out of bounds write in ", "None found "))), (F.col("event_id") % 4 + 1).cast("int"))
    rows = load(spark, d, "events", "event_id", "event_type").select(F.concat(said, "event_type").alias("t"), F.when(F.col("event_id") % 3 == 0, F.col("event_type")).alias("p"))
    return rows.agg(F.count("*").alias("n"), F.count_if(J.contradicts(F.col("t"), F.col("p"))).alias("n_contradicting"))


@query("guard_ngrams", "WITH w AS (SELECT doc_id, regexp_extract_all(text, '\\S+') AS w FROM documents), r AS (SELECT doc_id, list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) AS r FROM w WHERE len(w) >= 3) SELECT doc_id, round(1 - len(list_distinct(r)) / len(r), 6) AS repeated FROM r")
def guard_ngrams(spark, d):
    return load(spark, d, "documents", "doc_id", "text").select("doc_id", F.round(J.repetition(F.col("text")), 6).alias("repeated")).filter("repeated is not null")


_TERMS = "w AS (SELECT item_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS t FROM benchmark), tf AS (SELECT item_id, t, count(*) AS f FROM w GROUP BY ALL), r AS (SELECT *, count(*) OVER (PARTITION BY t) AS df FROM tf)"
_SPEC = f"{_TERMS}, sp AS (SELECT item_id, 'prediction' AS dimension, CAST(item_id % 5 AS VARCHAR) AS criterion FROM benchmark UNION ALL SELECT item_id, 'localization', t FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY df, f DESC, t) AS k FROM r) WHERE k <= 5 UNION ALL SELECT item_id, 'reasoning', t FROM (SELECT *, row_number() OVER (PARTITION BY item_id ORDER BY f DESC, df, t) AS k FROM r) WHERE k <= 5)"


def item_specs(spark, d):
    return J.specifications(load(spark, d, "benchmark").withColumn("c", (F.col("item_id") % 5).cast("string")), "item_id", "c", "text")


query("spec_dimensions", f"WITH {_SPEC} SELECT * FROM sp")(lambda spark, d: item_specs(spark, d))


@query(
    "spec_rewards",
    f"""WITH {_SPEC}, a AS (SELECT doc_id, doc_id % m AS item_id, d.text, CAST(doc_id % 5 AS VARCHAR) AS p FROM documents d, (SELECT count(*) AS m FROM benchmark)),
s AS (SELECT doc_id, p, dimension, avg(CAST(contains(lower(text), criterion) AS INT)) AS share, bool_or(criterion = p) AS hit FROM a JOIN sp USING (item_id) GROUP BY ALL),
q AS (SELECT doc_id, max(CASE WHEN dimension = 'prediction' THEN CASE WHEN hit THEN 1.0 ELSE -1.0 END END) AS r1, max(CASE WHEN dimension = 'localization' THEN CASE WHEN share >= 1 THEN 1.0 WHEN share > 0 THEN 0.5 ELSE 0 END END) AS r2, max(CASE WHEN dimension = 'reasoning' THEN CASE WHEN share >= 1 THEN 1.0 WHEN share > 0 THEN 0.5 ELSE 0 END END) AS r3 FROM s GROUP BY doc_id)
SELECT doc_id, CAST(round(0.4 * r1 + 0.2 * r2 + 0.4 * r3, 6) AS DOUBLE) AS reward FROM q""",
)
def spec_rewards(spark, d):
    """Documents as analyses, scored by the specification made from their evidence."""
    a = with_evidence(spark, d).select("doc_id", "item_id", "text", (F.col("doc_id") % 5).cast("string").alias("p"))
    scored = J.rubric_scores(a, item_specs(spark, d), "item_id", "text", "p")
    return scored.select("doc_id", rl.specification(F.col("r1"), F.col("r2"), F.col("r3")).cast("double").alias("reward"))


@query("cost_report", f"WITH {PAIRED} SELECT 'judge' AS stage, count(*) AS n_rows, CAST(sum(length(answer)) AS BIGINT) AS n_chars FROM qa UNION ALL SELECT 'specification', count(*), CAST(sum(length(text)) AS BIGINT) FROM benchmark")
def cost_report(spark, d):
    """What the stages that ask a model ask of it, counted as the rows pass (one row a stage); wall time and shuffle bytes come from collect."""
    rows = answered(spark, d).select("conv_id", "turn", F.col("answer").alias("response"), F.col("text").alias("evidence"))
    judged, cost = collect(J.Judge("words", J.shares_words).evaluate(rows), "response")
    _, spec = collect(load(spark, d, "benchmark", "item_id", "text"), "text")
    return spark.createDataFrame([("judge", cost["n_rows"], cost["n_chars"]), ("specification", spec["n_rows"], spec["n_chars"])], "stage string, n_rows long, n_chars long")


def collect(df, text: str):
    """df written once, and its cost: rows and characters (observed on the way), seconds."""
    import time

    from pyspark.sql import Observation

    seen = Observation()
    began = time.time()
    path = shared_path(df.sparkSession, "costed")
    df.observe(seen, F.count("*").alias("n_rows"), F.coalesce(F.sum(F.length(text)), F.lit(0)).alias("n_chars")).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), {**seen.get, "seconds": time.time() - began}
