"""Queries: matching, pairwise measures, agreement, flows (RQ6-RQ8)."""

from __future__ import annotations

import math

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlab.operators import pairwise as P
from pairlab.functions.scores import ratio
from pairlab.registry import query
from pairlab.sources.fixtures import EDGES, edges, policies, roll_sql, rollouts
from pairlab.sources.tables import load

ROLL = roll_sql()
#: slots seen on both sides, as a self join (the engine uses bit masks)
SLOT = f"""{ROLL},
sl AS (SELECT a.pair_id, a.slot, a.p_brand, a.target_reported AS x, b.target_reported AS y FROM roll a JOIN roll b ON a.pair_id = b.pair_id AND a.slot = b.slot AND a.side = 'pre' AND b.side = 'post')"""
CLS = f"""{ROLL}, {EDGES},
rc AS (SELECT roll.*, coalesce(pred_code = truth_code, false) OR EXISTS (SELECT 1 FROM edge WHERE (child = pred_code AND parent = truth_code) OR (child = truth_code AND parent = pred_code)) AS class_ok FROM roll),
lev AS (SELECT 'label' AS level, side, says_flawed AS hit FROM rc UNION ALL SELECT 'class', side, says_flawed AND class_ok FROM rc UNION ALL SELECT 'root', side, target_reported FROM rc),
conf AS (SELECT level, count(*) FILTER (side = 'pre' AND hit) AS tp, count(*) FILTER (side = 'post' AND hit) AS fp, count(*) FILTER (side = 'post' AND NOT hit) AS tn, count(*) FILTER (side = 'pre' AND NOT hit) AS fn FROM lev GROUP BY level)"""


def classed(spark, d, **options):
    return P.class_match(rollouts(spark, d), edges(spark, d), **options)


def _policies(spark, d):
    return policies(spark, d, {"sft": 0, "teacher": 10})


def plain(spark, d):
    """Verdicts of the one policy without classes, which no measure of pairs reads."""
    return policies(spark, d, {"sft": 0})


def _summary_sql(by: str, src: str) -> str:
    return f"""SELECT {by}, count(DISTINCT pair_id) AS n_pairs, count(*) AS n_response_pairs, round(avg(CAST(x AND NOT y AS INT)), 6) AS p_pass_1,
round(count(DISTINCT CASE WHEN x AND NOT y THEN pair_id END) / count(DISTINCT pair_id), 6) AS p_pass_8, round(avg(CAST(x AND y AS INT)), 6) AS p_v, round(avg(CAST(NOT x AND NOT y AS INT)), 6) AS p_b,
round(avg(CAST(NOT x AND y AS INT)), 6) AS p_r, round(2 * sum(CAST(x AS INT)) / (2 * sum(CAST(x AS INT)) + sum(CAST(y AS INT)) + sum(CAST(NOT x AS INT))), 6) AS f1 FROM {src} GROUP BY {by}"""


def _two(margin: int, name: str) -> str:
    return f"SELECT * FROM (WITH {roll_sql(margin)} SELECT '{name}' AS policy_id, a.pair_id, a.slot, a.target_reported AS x, b.target_reported AS y FROM roll a JOIN roll b ON a.pair_id = b.pair_id AND a.slot = b.slot AND a.side = 'pre' AND b.side = 'post')"


BOTH = f"pol AS ({_two(0, 'sft')} UNION ALL {_two(10, 'teacher')})"


@query("pairwise_summary", f"WITH {BOTH} {_summary_sql('policy_id', 'pol')}")
def pairwise_summary(spark, d):
    return P.summary(_policies(spark, d))


@query("pairwise_by_brand", f"WITH {SLOT} {_summary_sql('p_brand', 'sl')}")
def pairwise_by_brand(spark, d):
    return P.summary(plain(spark, d), ("p_brand",))


@query("ppass8_product", f"WITH {SLOT}, p AS (SELECT pair_id, 1 - product(1 - CAST(x AND NOT y AS INT)) AS v FROM sl GROUP BY pair_id) SELECT round(avg(v), 6) AS p_pass_8 FROM p")
def ppass8_product(spark, d):
    return P.counts(plain(spark, d)).filter("n > 0").agg(F.round(F.avg((F.col("c") > 0).cast("int")), 6).alias("p_pass_8"))


@query("pass_at_curve", f"WITH {SLOT}, p AS (SELECT pair_id, count(*) AS n, sum(CAST(x AND NOT y AS INT)) AS c FROM sl GROUP BY pair_id), q AS (SELECT m, n, c, list_product(list_transform(range(0, m), lambda i: CAST(greatest(n - c - i, 0) AS DOUBLE) / (n - i))) AS miss FROM p, range(1, 9) r(m) WHERE m <= n) SELECT CAST(m AS INTEGER) AS m, round(avg(1 - miss), 6) AS pass_at FROM q GROUP BY m")
def pass_at_curve(spark, d):
    return P.pass_at(plain(spark, d))


@query("pair_pass_rate", f"WITH {SLOT} SELECT pair_id, count(*) AS n_slots, CAST(sum(CAST(x AND NOT y AS INT)) AS BIGINT) AS n_right, round(avg(CAST(x AND NOT y AS INT)), 6) AS rate FROM sl GROUP BY pair_id")
def pair_pass_rate(spark, d):
    return P.counts(plain(spark, d)).filter("n > 0").select("pair_id", F.col("n").alias("n_slots"), F.col("c").alias("n_right"), F.round(F.col("c") / F.col("n"), 6).alias("rate"))


for _level in P.LEVELS:
    _name = {"label": "match_binary", "class": "match_class", "root": "match_root"}[_level]
    query(_name, f"WITH {CLS} SELECT * FROM conf WHERE level = '{_level}'")(lambda spark, d, level=_level: P.confusion(classed(spark, d), (level,)))


@query("match_root_strict", f"WITH {CLS} SELECT 'root' AS level, count(*) FILTER (side = 'pre' AND target_reported) AS tp, count(*) FILTER (side = 'post' AND says_flawed) AS fp, count(*) FILTER (side = 'post' AND NOT says_flawed) AS tn, count(*) FILTER (side = 'pre' AND NOT target_reported) AS fn FROM rc")
def match_root_strict(spark, d):
    return P.confusion(classed(spark, d), ("root",), "FP")


@query("confusion_levels", f"WITH {CLS} SELECT * FROM conf")
def confusion_levels(spark, d):
    return P.confusion(classed(spark, d))


@query("f1_levels", f"WITH {CLS} SELECT level, round(tp / (tp + fp), 6) AS precision, round(tp / (tp + fn), 6) AS recall, round(2 * tp / (2 * tp + fp + fn), 6) AS f1 FROM conf")
def f1_levels(spark, d):
    return P.f1(P.confusion(classed(spark, d)))


@query("level_inflation", f"WITH {CLS}, f AS (SELECT level, 2 * tp / (2 * tp + fp + fn) AS f1 FROM conf) SELECT round((SELECT f1 FROM f WHERE level = 'label') - (SELECT f1 FROM f WHERE level = 'root'), 6) AS label_over_root, round((SELECT f1 FROM f WHERE level = 'class') - (SELECT f1 FROM f WHERE level = 'root'), 6) AS class_over_root")
def level_inflation(spark, d):
    c = P.confusion(classed(spark, d)).withColumn("f1", ratio(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn")))
    at = {k: F.max(F.when(F.col("level") == k, F.col("f1"))) for k in P.LEVELS}
    return c.agg(F.round(at["label"] - at["root"], 6).alias("label_over_root"), F.round(at["class"] - at["root"], 6).alias("class_over_root"))


@query("granularity_flow", f"WITH {CLS} SELECT says_flawed AS label_ok, says_flawed AND class_ok AS class_ok, target_reported AS root_ok, count(*) AS n FROM rc WHERE side = 'pre' GROUP BY ALL")
def granularity_flow(spark, d):
    df = classed(spark, d).filter("side = 'pre'")
    return df.groupBy(F.col("says_flawed").alias("label_ok"), (F.col("says_flawed") & F.col("class_ok")).alias("class_ok"), F.col("target_reported").alias("root_ok")).agg(F.count("*").alias("n"))


@query("rq8_shares", f"WITH {CLS}, p AS (SELECT * FROM rc WHERE side = 'pre') SELECT count(*) AS n, count(*) FILTER (says_flawed) AS n_label, round(count(*) FILTER (says_flawed AND NOT class_ok) / count(*) FILTER (says_flawed), 6) AS share_class_wrong, count(*) FILTER (says_flawed AND class_ok) AS n_class, round(count(*) FILTER (says_flawed AND class_ok AND NOT target_reported) / count(*) FILTER (says_flawed AND class_ok), 6) AS share_root_wrong, round(count(*) FILTER (says_flawed AND NOT class_ok AND target_reported) / count(*) FILTER (says_flawed AND NOT class_ok), 6) AS share_root_right_class_wrong FROM p")
def rq8_shares(spark, d):
    lab, cls, root = F.col("says_flawed"), F.col("class_ok"), F.col("target_reported")
    n = F.count_if
    return classed(spark, d).filter("side = 'pre'").agg(
        F.count("*").alias("n"), n(lab).alias("n_label"), F.round(ratio(n(lab & ~cls), n(lab)), 6).alias("share_class_wrong"), n(lab & cls).alias("n_class"),
        F.round(ratio(n(lab & cls & ~root), n(lab & cls)), 6).alias("share_root_wrong"), F.round(ratio(n(lab & ~cls & root), n(lab & ~cls)), 6).alias("share_root_right_class_wrong"),
    )


JUDGED = f"{ROLL}, j AS (SELECT *, target_reported <> (l_orderkey % 50 = 0) AS a, target_reported <> (l_orderkey % 13 = 0) AS b, target_reported <> (l_orderkey % 400 = 0) AS c FROM roll)"


def judged(spark, d):
    df = rollouts(spark, d)
    flip = lambda k: F.col("target_reported") != (F.col("l_orderkey") % k == 0)
    return df.withColumns({"a": flip(50), "b": flip(13), "c": flip(400)})


@query("kappa_labels", "WITH c AS (SELECT count(*) AS n, sum(CAST(quality = toxic AS INT)) AS same, sum(quality) AS q, sum(toxic) AS t FROM labels), k AS (SELECT n, same / n AS po, (q * t + (n - q) * (n - t)) / (n * n) AS pe FROM c) SELECT n, round(po, 6) AS p_observed, round(pe, 6) AS p_chance, round((po - pe) / (1 - pe), 6) AS kappa FROM k")
def kappa_labels(spark, d):
    return P.kappa(load(spark, d, "labels"), "quality", "toxic")


@query("kappa_judges", f"WITH {JUDGED}, c AS (SELECT count(*) AS n, sum(CAST(a = b AS INT)) AS same, sum(CAST(a AS INT)) AS q, sum(CAST(b AS INT)) AS t FROM j), k AS (SELECT n, same / n AS po, (q * t + (n - q) * (n - t)) / (n * n) AS pe FROM c) SELECT n, round(po, 6) AS p_observed, round(pe, 6) AS p_chance, round((po - pe) / (1 - pe), 6) AS kappa FROM k")
def kappa_judges(spark, d):
    return P.kappa(judged(spark, d), "a", "b")


def draw(df, n: int = 400, seed: int = 42):
    """n rows by a hash of the sample and slot: the same on every run, one bounded heap a task."""
    return df.orderBy(F.md5(F.concat_ws(":", F.lit(str(seed)), "sample_id", "slot")), "sample_id", "slot").limit(n)


DRAW = "dr AS (SELECT * FROM j ORDER BY md5('42:' || sample_id || ':' || slot), sample_id, slot LIMIT 400)"


@query("audit_draw", f"WITH {JUDGED}, {DRAW} SELECT sample_id, slot FROM dr")
def audit_draw(spark, d):
    return draw(judged(spark, d)).select("sample_id", "slot")


@query("audit_accuracy", f"WITH {JUDGED}, {DRAW}, s AS (SELECT count(*) AS n, avg(CAST(a = target_reported AS INT)) AS p FROM dr) SELECT n, round(p, 6) AS accuracy, round((p + 1.96 * 1.96 / (2 * n) - 1.96 * sqrt(p * (1 - p) / n + 1.96 * 1.96 / (4 * n * n))) / (1 + 1.96 * 1.96 / n), 6) AS low, round((p + 1.96 * 1.96 / (2 * n) + 1.96 * sqrt(p * (1 - p) / n + 1.96 * 1.96 / (4 * n * n))) / (1 + 1.96 * 1.96 / n), 6) AS high FROM s")
def audit_accuracy(spark, d):
    s = draw(judged(spark, d)).agg(F.count("*").alias("n"), F.avg((F.col("a") == F.col("target_reported")).cast("int")).alias("p"))
    n, p, z = F.col("n"), F.col("p"), 1.96
    half = z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n))
    mid = p + z * z / (2 * n)
    return s.select("n", F.round(p, 6).alias("accuracy"), F.round((mid - half) / (1 + z * z / n), 6).alias("low"), F.round((mid + half) / (1 + z * z / n), 6).alias("high"))


@query("judge_error", f"WITH {JUDGED}, {DRAW}, u AS (SELECT 'a' AS judge, a AS v, target_reported AS g FROM dr UNION ALL SELECT 'b', b, target_reported FROM dr UNION ALL SELECT 'c', c, target_reported FROM dr) SELECT judge, count(*) AS n, count(*) FILTER (v = g) AS n_correct, count(*) FILTER (v <> g) AS n_incorrect, count(*) FILTER (v AND NOT g) AS n_lenient, round(count(*) FILTER (v <> g) / count(*), 6) AS error_rate FROM u GROUP BY judge")
def judge_error(spark, d):
    rows = draw(judged(spark, d)).select(F.col("target_reported").alias("g"), F.explode(F.array(*(F.struct(F.lit(k).alias("judge"), F.col(k).alias("v")) for k in "abc"))).alias("x")).select("g", "x.*")
    wrong = F.count_if(F.col("v") != F.col("g"))
    return rows.groupBy("judge").agg(F.count("*").alias("n"), F.count_if(F.col("v") == F.col("g")).alias("n_correct"), wrong.alias("n_incorrect"), F.count_if(F.col("v") & ~F.col("g")).alias("n_lenient"), F.round(ratio(wrong, F.count("*")), 6).alias("error_rate"))


@query("judge_lenient", f"WITH {CLS} SELECT side, count(*) AS n, count(*) FILTER (target_reported OR (side = 'pre' AND class_ok)) AS n_right, count(*) FILTER (side = 'pre' AND class_ok AND NOT target_reported) AS n_lenient FROM rc GROUP BY side")
def judge_lenient(spark, d):
    spared = (F.col("side") == "pre") & F.col("class_ok")
    return classed(spark, d).groupBy("side").agg(F.count("*").alias("n"), F.count_if(F.col("target_reported") | spared).alias("n_right"), F.count_if(spared & ~F.col("target_reported")).alias("n_lenient"))


@query("independent_judge", " UNION ALL ".join(f"SELECT * FROM (WITH {JUDGED}, sl AS (SELECT x.pair_id, x.slot, x.{c} AS x, y.{c} AS y, '{c}' AS judge FROM j x JOIN j y ON x.pair_id = y.pair_id AND x.slot = y.slot AND x.side = 'pre' AND y.side = 'post') {_summary_sql('judge', 'sl')})" for c in "ab"))
def independent_judge(spark, d):
    df = judged(spark, d)
    rows = df.select("pair_id", "side", "slot", F.explode(F.array(*(F.struct(F.lit(k).alias("judge"), F.col(k).alias("target_reported")) for k in "ab"))).alias("x")).select("pair_id", "side", "slot", "x.*")
    return P.summary(rows, ("judge",))


@query("side_bias", f"WITH {ROLL}, s AS (SELECT pair_id, side, sum(CAST(CASE WHEN side = 'pre' THEN target_reported ELSE NOT target_reported END AS INT)) AS c, count(*) AS n FROM roll GROUP BY pair_id, side) SELECT side, count(*) AS n, count(*) FILTER (c > 0 AND c < n) AS n_kept, round(avg(c / n), 6) AS mean_rate FROM s GROUP BY side")
def side_bias(spark, d):
    right = F.when(F.col("side") == "pre", F.col("target_reported")).otherwise(~F.col("target_reported"))
    s = rollouts(spark, d).groupBy("pair_id", "side").agg(F.count_if(right).alias("c"), F.count("*").alias("n"))
    return s.groupBy("side").agg(F.count("*").alias("n"), F.count_if((F.col("c") > 0) & (F.col("c") < F.col("n"))).alias("n_kept"), F.round(F.avg(F.col("c") / F.col("n")), 6).alias("mean_rate"))


@query(
    "exploration_gap",
    f"""WITH {BOTH}, s AS ({_summary_sql('policy_id', 'pol')}), v AS (SELECT 'sft' AS policy_id, sample_id, target_reported AS t, n_tok FROM (WITH {ROLL} SELECT * FROM roll) UNION ALL SELECT 'teacher', sample_id, target_reported, n_tok FROM (WITH {roll_sql(10)} SELECT * FROM roll)),
u AS (SELECT policy_id, sample_id, count(DISTINCT (t, n_tok // 100)) AS n FROM v GROUP BY ALL), w AS (SELECT policy_id, round(avg(n), 5) AS distinct_answers FROM u GROUP BY policy_id)
SELECT policy_id, round(p_pass_8 - p_pass_1, 5) AS gap, distinct_answers FROM s JOIN w USING (policy_id)""",
)
def exploration_gap(spark, d):
    """How far the best of eight lies above one, and distinct answers (verdict and length class) a query."""
    rows = _policies(spark, d)
    answers = rows.groupBy("policy_id", "sample_id").agg(F.count_distinct("target_reported", F.floor(F.col("n_tok") / 100)).alias("n")).groupBy("policy_id").agg(F.round(F.avg("n"), 5).alias("distinct_answers"))
    gap = P.summary(rows).select("policy_id", F.round(F.col("p_pass_8") - F.col("p_pass_1"), 5).alias("gap"))
    return gap.join(F.broadcast(answers), "policy_id")  # a row a policy


EPOCHS = f"pol AS ({' UNION ALL '.join(_two(3 * e - 9, str(e)) for e in range(6))})"


def epochs(spark, d):
    return P.summary(policies(spark, d, {str(e): 3 * e - 9 for e in range(6)}))


@query("relative_gain", f"WITH {EPOCHS}, s AS ({_summary_sql('policy_id', 'pol')}) SELECT policy_id, p_pass_1, round((p_pass_1 - lag(p_pass_1) OVER (ORDER BY policy_id)) / lag(p_pass_1) OVER (ORDER BY policy_id), 5) AS gain FROM s")
def relative_gain(spark, d):
    before = F.lag("p_pass_1").over(W.orderBy("policy_id"))  # six rows
    return epochs(spark, d).select("policy_id", "p_pass_1", F.round((F.col("p_pass_1") - before) / before, 5).alias("gain"))


@query("rank_marks", f"WITH {EPOCHS}, s AS ({_summary_sql('policy_id', 'pol')}), l AS (SELECT policy_id, 'p_pass_1' AS metric, p_pass_1 AS v, -p_pass_1 AS o FROM s UNION ALL SELECT policy_id, 'f1', f1, -f1 FROM s UNION ALL SELECT policy_id, 'p_v', p_v, p_v FROM s UNION ALL SELECT policy_id, 'p_r', p_r, p_r FROM s), r AS (SELECT *, dense_rank() OVER (PARTITION BY metric ORDER BY o) AS mark FROM l) SELECT metric, policy_id, v AS value, CAST(mark AS INTEGER) AS mark FROM r WHERE mark <= 3")
def rank_marks(spark, d):
    long = epochs(spark, d).select("policy_id", F.expr("stack(4, 'p_pass_1', p_pass_1, -p_pass_1, 'f1', f1, -f1, 'p_v', p_v, p_v, 'p_r', p_r, p_r) as (metric, value, o)"))
    mark = F.dense_rank().over(W.partitionBy("metric").orderBy("o"))
    return long.withColumn("mark", mark).filter("mark <= 3").select("metric", "policy_id", "value", "mark")


@query("case_slots", f"WITH {SLOT} SELECT pair_id, CAST(slot AS INTEGER) AS slot, x AS before_reported, y AS after_reported FROM sl WHERE pair_id = 7")
def case_slots(spark, d):
    df = rollouts(spark, d).filter("pair_id = 7")
    side = lambda s, name: df.filter(F.col("side") == s).select("pair_id", "slot", F.col("target_reported").alias(name))
    return side("pre", "before_reported").join(side("post", "after_reported"), ["pair_id", "slot"])


@query("self_pair_join", f"WITH {SLOT} {_summary_sql('p_brand', 'sl')}")
def self_pair_join(spark, d):
    """The pairwise measures by a self join of before and after, which the masks replace: rows meet by pair and slot."""
    rows = plain(spark, d)
    a = rows.filter("side = 'pre'").select("pair_id", "slot", "p_brand", F.col("target_reported").alias("x"))
    b = rows.filter("side = 'post'").select("pair_id", "slot", F.col("target_reported").alias("y"))
    one = lambda c: F.count_if(c).alias
    x, y = F.col("x"), F.col("y")
    per = a.join(b, ["pair_id", "slot"]).groupBy("p_brand", "pair_id").agg(F.count("*").alias("n"), one(x & ~y)("c"), one(x & y)("v"), one(~x & ~y)("b"), one(~x & y)("r"))
    return P.summary_of(per, ("p_brand",))


def bootstrap(df, reps: int = 200, seed: int = 42, by: tuple = ()):
    """rep, p_pass_1, p_pass_8 of resampled pairs: each pair counts as often as a Poisson draw by a hash of pair and repetition says,
    so one pass makes all repetitions, whatever the partitions."""
    per = P.counts(df, by).filter("n > 0").select(*by, "pair_id", "n", "c").withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))))
    u = F.pmod(F.xxhash64("pair_id", "rep", F.lit(seed)), F.lit(1_000_003)) / F.lit(1_000_003.0)
    below, weight = 0.0, F.lit(0)
    for k in range(8):  # P(more than 8) is 1e-6
        below += math.exp(-1) / math.factorial(k)
        weight = weight + (u >= below).cast("int")
    w = per.withColumn("w", weight)
    share = lambda a, b: F.round(ratio(F.sum(a), F.sum(b)), 6)
    return w.groupBy(*by, "rep").agg(share(F.col("w") * F.col("c"), F.col("w") * F.col("n")).alias("p_pass_1"), share(F.when(F.col("c") > 0, F.col("w")).otherwise(0), F.col("w")).alias("p_pass_8"))


@query("pair_bootstrap")
def pair_bootstrap(spark, d):
    """Intervals of P-Pass@1 and P-Pass@8 over 200 resamples of pairs."""
    q = lambda c, p, n: F.expr(f"percentile({c}, {p})").alias(n)
    return bootstrap(plain(spark, d)).agg(*(q(c, p, f"{c}_{n}") for c in ("p_pass_1", "p_pass_8") for p, n in ((0.025, "low"), (0.5, "mid"), (0.975, "high"))))
