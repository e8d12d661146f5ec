"""Queries: supervised curation, preferences, objectives, surrogate policy and recipes (RQ1-RQ3, RQ5-RQ6)."""

from __future__ import annotations

from pyspark.sql import functions as F

from pairlab.functions.scores import ratio, register_all
from pairlab.operators import objectives as O
from pairlab.operators.workloads import CLS, ROLL, classed
from pairlab.operators.workloads_rl import PLANS, graded_rollouts, plan
from pairlab.plans import surrogate as S
from pairlab.plans import training as T
from pairlab.registry import query
from pairlab.sources.fixtures import TOKENS, roll_sql, rollouts, token_rows
from pairlab.sources.tables import load, saved, words

OK = "CASE WHEN side = 'pre' THEN target_reported ELSE NOT target_reported END"
GOOD = f"{ROLL}, ok AS (SELECT *, {OK} AS ok FROM roll)"


def graded(spark, d, margin: int = 0):
    return rollouts(spark, d, margin).withColumn("ok", F.when(F.col("side") == "pre", F.col("target_reported")).otherwise(~F.col("target_reported")))


@query("reject_keep_all", f"WITH {GOOD} SELECT sample_id, CAST(slot AS INTEGER) AS slot, n_tok FROM ok WHERE ok")
def reject_keep_all(spark, d):
    return graded(spark, d).filter("ok").select("sample_id", "slot", "n_tok")


def _keep(spark, d, *order):
    best = F.min(F.struct(*order, "slot", "n_tok")).alias("b")
    return graded(spark, d).filter("ok").groupBy("sample_id").agg(best).select("sample_id", "b.slot", "b.n_tok")


def _keep_sql(order: str) -> str:
    return f"WITH {GOOD}, r AS (SELECT *, row_number() OVER (PARTITION BY sample_id ORDER BY {order}) AS k FROM ok WHERE ok) SELECT sample_id, CAST(slot AS INTEGER) AS slot, n_tok FROM r WHERE k = 1"


query("reject_keep_first", _keep_sql("slot"))(lambda spark, d: _keep(spark, d, F.col("slot").alias("o")))
query("reject_keep_shortest", _keep_sql("n_tok, slot"))(lambda spark, d: _keep(spark, d, F.col("n_tok").alias("o")))
query("reject_keep_random", _keep_sql("md5('42:' || sample_id || ':' || slot), slot"))(lambda spark, d: _keep(spark, d, F.md5(F.concat_ws(":", F.lit("42"), "sample_id", "slot")).alias("o")))


@query("reject_retained", f"WITH {GOOD} SELECT sample_id, CAST(sum(CAST(ok AS INT)) AS BIGINT) AS n_right FROM ok GROUP BY sample_id HAVING bool_or(ok)")
def reject_retained(spark, d):
    return graded(spark, d).groupBy("sample_id").agg(F.count_if("ok").alias("n_right")).filter("n_right > 0")


@query("reject_report", f"WITH {GOOD}, s AS (SELECT sample_id, truth_code, side, bool_or(ok) AS kept FROM ok GROUP BY ALL) SELECT truth_code, side, count(*) AS n, count(*) FILTER (kept) AS n_kept FROM s GROUP BY CUBE (truth_code, side)")
def reject_report(spark, d):
    s = graded(spark, d).groupBy("sample_id", "truth_code", "side").agg(F.bool_or("ok").alias("kept"))
    return s.cube("truth_code", "side").agg(F.count("*").alias("n"), F.count_if("kept").alias("n_kept"))


@query("reject_by_class", f"WITH {CLS} SELECT sample_id, count(*) AS n FROM rc WHERE CASE WHEN side = 'pre' THEN says_flawed AND class_ok ELSE NOT (says_flawed AND class_ok) END GROUP BY sample_id")
def reject_by_class(spark, d):
    hit = F.col("says_flawed") & F.col("class_ok")
    return classed(spark, d).filter(F.when(F.col("side") == "pre", hit).otherwise(~hit)).groupBy("sample_id").agg(F.count("*").alias("n"))


@query("rationalize_prompts", "SELECT d.doc_id, md5('class: ' || d.lang || chr(10) || 'description: ' || b.text || chr(10) || 'code: ' || d.text) AS prompt_hash FROM documents d JOIN (SELECT *, count(*) OVER () AS m FROM benchmark) b ON b.item_id = d.doc_id % m")
def rationalize_prompts(spark, d):
    b = load(spark, d, "benchmark")
    m = b.count()
    docs = load(spark, d, "documents", "doc_id", "lang", "text").withColumn("item_id", F.col("doc_id") % m)
    prompt = F.concat_ws("\n", F.concat(F.lit("class: "), "lang"), F.concat(F.lit("description: "), F.col("b.text")), F.concat(F.lit("code: "), F.col("d.text")))
    return docs.alias("d").join(b.alias("b"), "item_id").select("doc_id", F.md5(prompt).alias("prompt_hash"))


PAIRED = "u AS (SELECT conv_id, turn, role, text, lead(text) OVER (PARTITION BY conv_id ORDER BY turn) AS answer, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS next_role FROM conversations), qa AS (SELECT conv_id, turn, text, answer FROM u WHERE role = 'user' AND next_role = 'assistant')"


def answered(spark, d):
    from pyspark.sql import Window as W

    w = W.partitionBy("conv_id").orderBy("turn")
    c = load(spark, d, "conversations")
    return c.withColumns({"answer": F.lead("text").over(w), "next_role": F.lead("role").over(w)}).filter("role = 'user' and next_role = 'assistant'")


@query("leak_terms", f"WITH {PAIRED} SELECT conv_id, turn, len(list_distinct(list_filter(regexp_extract_all(answer, '[a-z]+'), lambda x: NOT list_contains(regexp_extract_all(text, '[a-z]+'), x)))) AS n_new FROM qa")
def leak_terms(spark, d):
    terms = lambda c: F.regexp_extract_all(c, F.lit("([a-z]+)"), F.lit(1))
    return answered(spark, d).select("conv_id", "turn", F.size(F.array_except(terms("answer"), terms("text"))).cast("long").alias("n_new"))


@query("judge_overlap", f"WITH {PAIRED}, t AS (SELECT conv_id, turn, list_distinct(regexp_extract_all(text, '[a-z]+')) AS a, list_distinct(regexp_extract_all(answer, '[a-z]+')) AS b FROM qa) SELECT conv_id, turn, 100 * len(list_intersect(a, b)) >= 20 * len(a) AS correct FROM t")
def judge_overlap(spark, d):
    terms = lambda c: F.array_distinct(F.regexp_extract_all(c, F.lit("([a-z]+)"), F.lit(1)))
    return answered(spark, d).select("conv_id", "turn", (100 * F.size(F.array_intersect(terms("text"), terms("answer"))) >= 20 * F.size(terms("text"))).alias("correct"))


@query("strip_think", f"WITH {PAIRED} SELECT conv_id, turn, md5(answer) AS answer_hash FROM qa")
def strip_think(spark, d):
    whole = F.concat(F.lit("<think>"), "text", F.lit("</think>"), "answer")
    return answered(spark, d).select("conv_id", "turn", F.md5(without_thoughts(whole)).alias("answer_hash"))


def without_thoughts(text):
    """The answer part: spans between think tags go, an unclosed one to the end."""
    return F.regexp_replace(text, "(?s)<think>.*?(</think>|$)", "")


def scrub(text, terms):
    """text without the sentences that hold a term of an array column."""
    return F.array_join(F.filter(F.split(text, "\\. "), lambda s: ~F.exists(terms, lambda t: F.contains(s, t))), ". ")


@query("scrub_leaks", "SELECT doc_id, array_to_string(list_filter(string_split(d.text, '. '), lambda s: len(list_filter(regexp_extract_all(b.text, '[A-Za-z]{8,}'), lambda t: contains(s, t))) = 0), '. ') AS text FROM documents d JOIN (SELECT *, count(*) OVER () AS m FROM benchmark) b ON b.item_id = d.doc_id % m")
def scrub_leaks(spark, d):
    """Sentences that hold a long term of the document's evidence go."""
    terms = F.regexp_extract_all("evidence", F.lit("([A-Za-z]{8,})"), F.lit(1))
    return with_evidence(spark, d).select("doc_id", scrub(F.col("text"), terms).alias("text"))


def with_evidence(spark, d):
    """Documents with the text of the benchmark item that stands for their ground truth."""
    b = load(spark, d, "benchmark")
    docs = load(spark, d, "documents", "doc_id", "text").withColumn("item_id", F.col("doc_id") % b.count())
    return docs.join(b.select("item_id", F.col("text").alias("evidence")), "item_id")


def drop_leaky_answers(df, answer: str, evidence: str, least: int = 8):
    """Rows whose answer holds none of the evidence's words of least letters or more."""
    terms = F.regexp_extract_all(evidence, F.lit(f"([A-Za-z]{{{least},}})"), F.lit(1))
    return df.filter(~F.exists(terms, lambda t: F.contains(F.col(answer), t)))


@query("drop_leaky_answers", "SELECT doc_id FROM documents d JOIN (SELECT *, count(*) OVER () AS m FROM benchmark) b ON b.item_id = d.doc_id % m WHERE len(list_filter(regexp_extract_all(b.text, '[A-Za-z]{8,}'), lambda t: contains(d.text, t))) = 0")
def leakless_documents(spark, d):
    return drop_leaky_answers(with_evidence(spark, d), "text", "evidence").select("doc_id")


@query("chat_examples", "SELECT conv_id, count(*) AS n_turns, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")
def chat_examples(spark, d):
    m = F.array_sort(F.collect_list(F.struct("turn", "role")))
    return load(spark, d, "conversations", "conv_id", "turn", "role").groupBy("conv_id").agg(F.count("*").alias("n_turns"), F.array_join(F.transform(m, lambda x: x["role"]), ">").alias("roles"))


@query("sft_step_plan", "WITH r AS (SELECT e AS epoch, doc_id, e * (SELECT count(*) FROM documents) + row_number() OVER (PARTITION BY e ORDER BY md5('42:' || e || ':' || doc_id), doc_id) - 1 AS k FROM documents, range(0, 5) t(e)), s AS (SELECT epoch, doc_id, k // 256 AS step, (5 * (SELECT count(*) FROM documents) + 255) // 256 AS total FROM r) SELECT CAST(step AS BIGINT) AS step, count(*) AS n, round(1e-5 * CASE WHEN step + 1 <= ceil(0.1 * any_value(total)) THEN (step + 1) / ceil(0.1 * any_value(total)) ELSE (any_value(total) - step) / (any_value(total) - ceil(0.1 * any_value(total))) END, 12) AS lr FROM s GROUP BY step")
def sft_step_plan(spark, d):
    from pairlab.operators.rl import global_rank

    docs = load(spark, d, "documents", "doc_id")
    n = docs.count()
    rows = docs.withColumn("epoch", F.explode(F.sequence(F.lit(0), F.lit(4))))
    k = global_rank(rows, F.col("epoch"), F.md5(F.concat_ws(":", F.lit("42"), "epoch", "doc_id")), F.col("doc_id"))
    total = (5 * n + 255) // 256
    warm = F.ceil(F.lit(0.1 * total))
    step = F.floor(F.col("rank") / 256)
    lr = F.when(F.col("step") + 1 <= warm, (F.col("step") + 1) / warm).otherwise((total - F.col("step")) / (total - warm))
    return k.groupBy(step.alias("step")).agg(F.count("*").alias("n")).select("step", "n", F.round(1e-5 * lr, 12).alias("lr"))


def _sides(df):
    pick = lambda ok: F.array_sort(F.collect_list(F.when(F.col("ok") == ok, F.col("slot"))))  # noqa: E731  of eight slots
    return df.groupBy("sample_id").agg(pick(True).alias("good"), pick(False).alias("bad"))


def prefs(df, pairing: str):
    s = _sides(df)
    if pairing == "first":
        return s.filter((F.size("good") > 0) & (F.size("bad") > 0)).select("sample_id", F.col("good")[0].alias("chosen_slot"), F.col("bad")[0].alias("rejected_slot"))
    if pairing == "cross":
        return s.select("sample_id", F.explode("good").alias("chosen_slot"), "bad").select("sample_id", "chosen_slot", F.explode("bad").alias("rejected_slot"))
    n = F.least(F.size("good"), F.size("bad"))
    both = s.withColumn("n", n).filter("n > 0")
    return both.select("sample_id", F.inline(F.arrays_zip(F.expr("slice(good, 1, n)").alias("chosen_slot"), F.expr("slice(bad, 1, n)").alias("rejected_slot"))))


_RANK = "ra AS (SELECT *, row_number() OVER (PARTITION BY sample_id, ok ORDER BY slot) AS k FROM ok)"
_SIDES = f"{_RANK}, good AS (SELECT sample_id, slot, k FROM ra WHERE ok), bad AS (SELECT sample_id, slot, k FROM ra WHERE NOT ok)"
_SLOTS = "SELECT sample_id, CAST(good.slot AS INTEGER) AS chosen_slot, CAST(bad.slot AS INTEGER) AS rejected_slot FROM"
_MEET = {"first": "(SELECT * FROM good WHERE k = 1) good JOIN (SELECT * FROM bad WHERE k = 1) bad USING (sample_id)", "zip": "good JOIN bad USING (sample_id, k)", "cross": "good JOIN bad USING (sample_id)"}
for _p, _c in _MEET.items():
    query(f"prefs_{_p}", f"WITH {GOOD}, {_SIDES} {_SLOTS} {_c}")(lambda spark, d, p=_p: prefs(graded(spark, d), p))
query("prefs_teacher", f"WITH {roll_sql(10)}, ok AS (SELECT *, {OK} AS ok FROM roll), {_SIDES} {_SLOTS} {_MEET['zip']}")(lambda spark, d: prefs(graded(spark, d, 10), "zip"))


@query("prefs_coverage", f"WITH {GOOD}, s AS (SELECT sample_id, count(*) AS n, count(*) FILTER (ok) AS c FROM ok GROUP BY sample_id) SELECT count(*) AS n, count(*) FILTER (c = n) AS n_all_right, count(*) FILTER (c = 0) AS n_all_wrong FROM s")
def prefs_coverage(spark, d):
    s = graded(spark, d).groupBy("sample_id").agg(F.count("*").alias("n"), F.count_if("ok").alias("c"))
    return s.agg(F.count("*").alias("n"), F.count_if(F.col("c") == F.col("n")).alias("n_all_right"), F.count_if(F.col("c") == 0).alias("n_all_wrong"))


_HIST = "SELECT n_tok // 50 AS b, count(*) / sum(count(*)) OVER () AS {p} FROM (WITH {roll}, ok AS (SELECT *, {ok} AS ok FROM roll) SELECT * FROM ok WHERE ok) GROUP BY b"


def shift(a, b):
    """distance: total variation between the histograms (columns b, p) of two sources, of which each may lack a bin."""
    both = a.select("b", F.col("p").alias("p")).join(b.select("b", F.col("p").alias("q")), "b", "full_outer")
    return both.agg(F.round(F.sum(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0)))) / 2, 6).alias("distance"))


@query(
    "prefs_shift",
    f"WITH x AS ({_HIST.format(p='p', roll=roll_sql(), ok=OK)}), y AS ({_HIST.format(p='q', roll=roll_sql(10), ok=OK)}) SELECT round(sum(abs(coalesce(p, 0) - coalesce(q, 0))) / 2, 6) AS distance FROM x FULL JOIN y USING (b)",
)
def prefs_shift(spark, d):
    """How far the lengths of the policy's own chosen responses lie from the teacher's."""
    def lengths(margin: int):
        h = graded(spark, d, margin).filter("ok").groupBy(F.floor(F.col("n_tok") / 50).alias("b")).agg(F.count("*").alias("n"))  # some bins
        return h.join(F.broadcast(h.agg(F.sum("n").alias("all")))).select("b", (F.col("n") / F.col("all")).alias("p"))

    return shift(lengths(0), lengths(10))


# objectives

PREF = f"{TOKENS}, pf AS (SELECT a.vec_id // 2 AS row_id, a.lt AS ca, a.lr AS cr, b.lt AS ra, b.lr AS rr, a.st AS sca, a.sr AS scr, b.st AS sra, b.sr AS srr FROM seq a JOIN seq b ON a.vec_id % 2 = 0 AND b.vec_id = a.vec_id + 1)"
LS = "(CASE WHEN {0} >= 0 THEN -ln(1 + exp(-({0}))) ELSE ({0}) - ln(1 + exp({0})) END)"


def pref_rows(spark, d):
    t = token_rows(spark, d)
    pick = lambda k, a, b: t.filter(F.col("vec_id") % 2 == k).select(F.floor(F.col("vec_id") / 2).alias("row_id"), F.col("theta").alias(a), F.col("ref").alias(b))
    return pick(0, "c", "cr").join(pick(1, "r", "rr"), "row_id")


def _value(spark, d, value):
    return pref_rows(spark, d).select("row_id", F.round(value, 6).alias("value"))


query("obj_sft", f"WITH {TOKENS} SELECT vec_id AS row_id, round(lt, 6) AS value FROM seq")(lambda spark, d: token_rows(spark, d).select(F.col("vec_id").alias("row_id"), F.round(O.sft(F.col("theta")), 6).alias("value")))
query("obj_dpo", f"WITH {PREF} SELECT row_id, round({LS.format('0.1 * ((ca - cr) - (ra - rr))')}, 6) AS value FROM pf")(lambda spark, d: _value(spark, d, O.dpo(F.col("c"), F.col("cr"), F.col("r"), F.col("rr"))))
query("obj_dpo_sum", f"WITH {PREF} SELECT row_id, round({LS.format('0.1 * ((sca - scr) - (sra - srr))')}, 6) AS value FROM pf")(lambda spark, d: _value(spark, d, O.dpo(F.col("c"), F.col("cr"), F.col("r"), F.col("rr"), length_norm=False)))
query("obj_orpo", f"WITH {PREF} SELECT row_id, round(ca + 0.1 * {LS.format('((ca - ln(1 - exp(ca))) - (ra - ln(1 - exp(ra))))')}, 6) AS value FROM pf")(lambda spark, d: _value(spark, d, O.orpo(F.col("c"), F.col("r"))))


_ODDS = "((ca - ln(1 - exp(ca))) - (ra - ln(1 - exp(ra))))"


@query(
    "beta_sweep",
    f"WITH {PREF}, g AS (SELECT CAST(beta AS DOUBLE) AS beta FROM (VALUES (0.01), (0.1), (1.0)) v(beta)), x AS (SELECT beta, beta * ((ca - cr) - (ra - rr)) AS z, ca + beta * {LS.format(_ODDS)} AS o FROM pf, g) "
    f"SELECT beta, round(avg({LS.format('z')}), 6) AS dpo, round(avg(o), 6) AS orpo FROM x GROUP BY beta",
)
def beta_sweep(spark, d):
    c, cr, r, rr = (F.col(k) for k in ("c", "cr", "r", "rr"))
    cells = F.array(*(F.struct(F.lit(b).alias("beta"), O.dpo(c, cr, r, rr, b).alias("dpo"), O.orpo(c, r, b).alias("orpo")) for b in (0.01, 0.1, 1.0)))
    rows = pref_rows(spark, d).select(F.explode(cells).alias("x")).select("x.*")
    return rows.groupBy("beta").agg(F.round(F.avg("dpo"), 6).alias("dpo"), F.round(F.avg("orpo"), 6).alias("orpo"))


@query("pref_margins", f"WITH {PREF}, x AS (SELECT 0.1 * ((ca - cr) - (ra - rr)) AS m FROM pf) SELECT count(*) AS n, round(avg(m), 6) AS mean_margin, round(avg(CAST(m > 0 AS INT)), 6) AS accuracy FROM x")
def pref_margins(spark, d):
    m = pref_rows(spark, d).select((0.1 * ((O.mean_of(F.col("c")) - O.mean_of(F.col("cr"))) - (O.mean_of(F.col("r")) - O.mean_of(F.col("rr"))))).alias("m"))
    return m.agg(F.count("*").alias("n"), F.round(F.avg("m"), 6).alias("mean_margin"), F.round(F.avg((F.col("m") > 0).cast("int")), 6).alias("accuracy"))


def group_rows(spark, d):
    from pairlab.operators.rl import group_normalize

    t = token_rows(spark, d).withColumns({"group_id": F.floor(F.col("vec_id") / 8), "reward": F.when(F.col("label") % 2 == 0, 1.0).otherwise(-1.0)})
    return group_normalize(t, ["group_id"])


_ADV = f"{TOKENS}, a AS (SELECT vec_id, vec_id // 8 AS group_id, CASE WHEN label % 2 = 0 THEN 1.0 ELSE -1.0 END AS r FROM seq), g AS (SELECT group_id, avg(r) AS m, stddev_pop(r) AS s FROM a GROUP BY group_id), v AS (SELECT vec_id, group_id, CASE WHEN s = 0 THEN 0 ELSE (r - m) / s END AS adv FROM a JOIN g USING (group_id))"
_TERM = {"": "least(exp(th - ol) * adv, greatest(0.8, least(1.2, exp(th - ol))) * adv)", "_kl": "least(exp(th - ol) * adv, greatest(0.8, least(1.2, exp(th - ol))) * adv) - 0.1 * (exp(rf - th) - 1 + th - rf)", "_onpolicy": "adv"}
for _n, _t in _TERM.items():
    _opt = {"": {}, "_kl": {"beta": 0.1}, "_onpolicy": {"on_policy": True}}[_n]
    query(f"obj_group_relative{_n}", f"WITH {_ADV}, s AS (SELECT group_id, vec_id, avg({_t}) AS x FROM tok JOIN v USING (vec_id) GROUP BY ALL) SELECT group_id, count(*) AS n, round(avg(x), 5) AS value FROM s GROUP BY group_id")(
        lambda spark, d, o=_opt: O.group_relative(group_rows(spark, d), "group_id", **o).withColumn("value", F.round("value", 5) + F.lit(0.0))
    )


@query("udf_sql_log_sigmoid", f"WITH {PREF} SELECT row_id, round({LS.format('(ca - ra)')}, 6) AS value FROM pf")
def udf_sql_log_sigmoid(spark, d):
    register_all(spark)
    rows = pref_rows(spark, d).select("row_id", (O.mean_of(F.col("c")) - O.mean_of(F.col("r"))).alias("z"))
    return rows.select("row_id", F.round(F.expr("log_sigmoid(z)"), 6).alias("value"))


@query("judge_cosine", "SELECT a.vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 4) AS cosine, list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= 0.05 AS correct, a.label = b.label AS gold FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def judge_cosine(spark, d, tau: float = 0.05):
    """A judge that calls a response right if it lies near the evidence; with the true answer beside it."""
    e = load(spark, d, "embeddings")
    b = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("o"), F.col("label").alias("l"))
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)
    cosine = dot("embedding", "o") / F.sqrt(dot("embedding", "embedding") * dot("o", "o"))
    return e.join(b, "vec_id").select("vec_id", F.round(cosine, 4).alias("cosine"), (cosine >= tau).alias("correct"), (F.col("label") == F.col("l")).alias("gold"))


# surrogate policy

W0 = [0.1, -0.8, 0.5, -0.5, 0.3, -0.2]
_FEAT = f"{ROLL}, ft AS (SELECT sample_id AS query_id, slot, {OK} AS ok, 0.1 - 0.8 * l_quantity / 50 + 0.5 * l_discount - 0.5 * l_tax + 0.3 * CAST(says_flawed AS INT) - 0.2 * CAST(coalesce(pred_code LIKE 'R%', false) AS INT) AS z FROM roll), pb AS (SELECT *, exp(z) / sum(exp(z)) OVER (PARTITION BY query_id) AS prob FROM ft)"


@query("surrogate_probs", f"WITH {_FEAT} SELECT query_id, CAST(slot AS INTEGER) AS slot, round(prob, 6) AS prob FROM pb")
def surrogate_probs(spark, d):
    return S.probabilities(S.candidates(rollouts(spark, d)), W0).select("query_id", "slot", F.round("prob", 6).alias("prob"))


@query("surrogate_expected", f"WITH {_FEAT}, q AS (SELECT query_id, sum(CASE WHEN ok THEN prob ELSE 0 END) AS r FROM pb GROUP BY query_id) SELECT round(avg(r), 6) AS root_rate FROM q")
def surrogate_expected(spark, d):
    return S.evaluate(S.candidates(rollouts(spark, d)), W0).select("root_rate")


W1 = [0.0, -0.4, 0.2, -0.1, 0.1, 0.3]
#: Log-probabilities under W0 (l0), W1 (l1) and the uniform policy (lu), and the mean of the second feature (e1).
_LOGP = f"""{ROLL}, f0 AS (SELECT sample_id AS query_id, slot, {OK} AS ok, l_quantity / 50 AS f1,
  0.1 - 0.8 * l_quantity / 50 + 0.5 * l_discount - 0.5 * l_tax + 0.3 * CAST(says_flawed AS INT) - 0.2 * CAST(coalesce(pred_code LIKE 'R%', false) AS INT) AS z0,
  -0.4 * l_quantity / 50 + 0.2 * l_discount - 0.1 * l_tax + 0.1 * CAST(says_flawed AS INT) + 0.3 * CAST(coalesce(pred_code LIKE 'R%', false) AS INT) AS z1 FROM roll),
l AS (SELECT *, z0 - ln(sum(exp(z0)) OVER w) AS l0, z1 - ln(sum(exp(z1)) OVER w) AS l1, -ln(count(*) OVER w) AS lu, sum(exp(z0) * f1) OVER w / sum(exp(z0)) OVER w AS e1,
  row_number() OVER (PARTITION BY query_id, ok ORDER BY slot) AS k FROM f0 WINDOW w AS (PARTITION BY query_id)),
pr AS (SELECT c.l0 AS cl, r.l0 AS rl, c.l1 AS c1, r.l1 AS r1, c.f1 AS cf, r.f1 AS rf, c.e1 AS e1 FROM l c JOIN l r ON c.query_id = r.query_id AND c.ok AND NOT r.ok AND c.k = r.k)"""
_STEPS = {
    "sft": (f"q AS (SELECT avg(l0) AS v, avg(f1) - any_value(e1) AS g FROM l WHERE ok GROUP BY query_id)", "sft", {}),
    "dpo": (f"z AS (SELECT *, 0.1 * ((cl - c1) - (rl - r1)) AS z FROM pr), q AS (SELECT {LS.format('z')} AS v, 0.1 / (1 + exp(z)) * (cf - rf) AS g FROM z)", "dpo", {"pref_source": "teacher"}),
    "orpo": (f"z AS (SELECT *, (cl - ln(1 - exp(cl))) - (rl - ln(1 - exp(rl))) AS z FROM pr), q AS (SELECT cl + 0.1 * {LS.format('z')} AS v, cf - e1 + 0.1 / (1 + exp(z)) * ((cf - e1) / (1 - exp(cl)) - (rf - e1) / (1 - exp(rl))) AS g FROM z)", "orpo", {}),
    "group": (
        "a0 AS (SELECT *, CASE WHEN ok THEN 1.0 ELSE -1.0 END AS r FROM l), a1 AS (SELECT *, avg(r) OVER (PARTITION BY query_id) AS m, stddev_pop(r) OVER (PARTITION BY query_id) AS s FROM a0), "
        "a2 AS (SELECT *, CASE WHEN s < 1e-12 THEN 0 ELSE (r - m) / s END AS a, exp(l0 - l1) AS rho, l0 - lu AS d FROM a1), a3 AS (SELECT *, rho * a AS free, greatest(0.8, least(1.2, rho)) * a AS held FROM a2), "
        "q AS (SELECT avg(least(free, held) - 0.1 * (exp(-d) - 1 + d)) AS v, avg(((CASE WHEN free <= held THEN free ELSE 0 END) - 0.1 * (1 - exp(-d))) * (f1 - e1)) AS g FROM a3 GROUP BY query_id)",
        "rl", {"rl_reward": "reasoning", "rl_beta": 0.1},
    ),
}


def one_step(spark, d, kind: str, **options):
    """Objective and gradient (its second entry) of one objective at fixed weights, over the whole table."""
    import numpy as np

    ref = np.zeros(T.D) if kind == "rl" else np.array(W1)
    step = T.Step(kind, T.Recipe("r", **options), np.array(W0), ref, np.array(W1), all_once=True)
    return T.gradients(packed(spark, d), [step]).select("n", F.round("value", 6).alias("value"), F.round("g1", 6).alias("g1"))


def packed(spark, d):
    return saved(T.pack(S.candidates(graded_rollouts(spark, d))), "packed")


for _n, (_sql, _kind, _opt) in _STEPS.items():
    query(f"surrogate_step_{_n}", f"WITH {_LOGP}, {_sql} SELECT count(*) AS n, round(avg(v), 6) AS value, round(avg(g), 6) AS g1 FROM q")(lambda spark, d, k=_kind, o=_opt: one_step(spark, d, k, **o))


@query("surrogate_rollouts")
def surrogate_rollouts(spark, d):
    return S.sample(S.candidates(rollouts(spark, d)), W0)


def _results(table, recipes):
    """The six measures of each recipe's last weights."""
    return T.measure(table, {name: w[-1] for name, w in T.fit(table, tuple(recipes)).items()})


@query("rq1_metrics")
def rq1_metrics(spark, d):
    """Supervised data by rejection, by rationalisation, and rationalised without reasoning and leaked truth."""
    return _results(packed(spark, d), [T.zero_shot(1), *(T.Recipe(s, sft_source=s) for s in ("rejection", "rationalized", "answers"))])


@query("rq2_epochs")
def rq2_epochs(spark, d):
    return _results(packed(spark, d), [T.Recipe(f"{p}_{e}", sft_epochs=e, preference=p) for p in ("dpo", "orpo") for e in range(1, 6)])


@query("rq3_epochs")
def rq3_epochs(spark, d):
    return _results(packed(spark, d), [T.Recipe(f"rl_{e}", sft_source="rejection" if e else "none", sft_epochs=e, rl_reward="reasoning") for e in range(6)])


@query("rq4_metrics")
def rq4_metrics(spark, d):
    """On-policy training over each filter and schedule from one supervised start. Every batch comes once, in its plan's order;
    a step takes a run of neighbouring batches."""
    arms = [(f, k) for f in ("full", "difficulty") for k in PLANS]
    recipes = [T.Recipe(f"{f}_{k}", rl_reward="reasoning", rl_filter=f, rl_schedule=k) for f, k in arms]
    table = T.with_plans(packed(spark, d), {f"{f}_{k}": plan(spark, d, k, f == "difficulty") for f, k in arms}, recipes[0].rl_steps)
    return _results(table, recipes)


@query("rq5_curves")
def rq5_curves(spark, d):
    """Measures after each on-policy step under each of the four rewards; step 0 is the supervised start."""
    table = packed(spark, d)
    trained = T.fit(table, tuple(T.Recipe(level, rl_reward=level) for level in T.REWARDS))
    out = T.measure(table, {f"{level}:{k}": w for level, all in trained.items() for k, w in enumerate(all)})
    return out.withColumns({"reward": F.substring_index("recipe", ":", 1), "step": F.substring_index("recipe", ":", -1).cast("int")}).drop("recipe")


@query("rq6_compare")
def rq6_compare(spark, d):
    return _results(packed(spark, d), (*T.COMPARED, *T.FURTHER))


@query("rq1_datasets", f"WITH {GOOD} SELECT 'rejection' AS source, count(DISTINCT sample_id) AS n_samples, count(*) AS n_rows FROM ok WHERE ok UNION ALL SELECT 'rationalized', count(DISTINCT sample_id), count(DISTINCT sample_id) FROM ok")
def rq1_datasets(spark, d):
    g = graded(spark, d)
    a = g.filter("ok").agg(F.lit("rejection").alias("source"), F.count_distinct("sample_id").alias("n_samples"), F.count("*").alias("n_rows"))
    return a.union(g.agg(F.lit("rationalized"), F.count_distinct("sample_id"), F.count_distinct("sample_id")))
