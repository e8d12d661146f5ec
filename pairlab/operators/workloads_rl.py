"""Queries: difficulty, schedules, rewards, advantages (RQ4, RQ5)."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlab.functions.scores import ratio
from pairlab.operators import pairwise as P
from pairlab.operators import rl
from pairlab.operators.workloads import CLS, ROLL, SLOT, classed, plain
from pairlab.registry import query
from pairlab.sources.fixtures import edges, rollouts
from pairlab.sources.tables import load

RATE = f"{SLOT}, pr AS (SELECT pair_id, count(*) AS n, CAST(sum(CAST(x AND NOT y AS INT)) AS BIGINT) AS n_right FROM sl GROUP BY pair_id), pf AS (SELECT * FROM pr WHERE n = 8)"


def rates(spark, d):
    """Pairs with all eight slots."""
    return P.counts(plain(spark, d), complete="require").select("pair_id", F.col("c").alias("n_right"))


@query("difficulty_hist", f"WITH {RATE} SELECT CAST(k AS BIGINT) AS n_right, count(pf.pair_id) AS n_pairs FROM range(0, 9) r(k) LEFT JOIN pf ON pf.n_right = k GROUP BY k")
def difficulty_hist(spark, d):
    bins = rates(spark, d).groupBy("n_right").agg(F.count("*").alias("n"))
    return spark.range(9).withColumnRenamed("id", "n_right").join(F.broadcast(bins), "n_right", "left").select("n_right", F.coalesce("n", F.lit(0)).alias("n_pairs"))


query("diff_filtered", f"WITH {RATE} SELECT pair_id, n_right FROM pf WHERE n_right > 0 AND n_right < 8")(lambda spark, d: rl.filter_extremes(rates(spark, d)))
query("diff_full", f"WITH {RATE} SELECT pair_id, n_right FROM pf")(lambda spark, d: rl.filter_extremes(rates(spark, d), enabled=False))


@query("coverage_loss", f"WITH {RATE} SELECT count(*) AS n, count(*) FILTER (n_right IN (0, 8)) AS n_lost, round(count(*) FILTER (n_right IN (0, 8)) / count(*), 6) AS share FROM pf")
def coverage_loss(spark, d):
    lost = F.count_if(F.col("n_right").isin(0, 8))
    return rates(spark, d).agg(F.count("*").alias("n"), lost.alias("n_lost"), F.round(ratio(lost, F.count("*")), 6).alias("share"))


def samples(pairs):
    return pairs.withColumn("sample_id", F.explode(F.array(2 * F.col("pair_id"), 2 * F.col("pair_id") + 1)))


SAMP = "sa AS (SELECT 2 * pair_id + s AS sample_id, pair_id, n_right FROM {src}, range(0, 2) r(s))"
PLANS = {
    "random": "SELECT *, row_number() OVER (ORDER BY md5('42:' || sample_id), sample_id) - 1 AS k FROM sa",
    "curriculum": "SELECT *, row_number() OVER (ORDER BY n_right DESC, md5('42:' || sample_id), sample_id) - 1 AS k FROM sa",
    "paired": "SELECT sa.*, 2 * (dense_rank() OVER (ORDER BY n_right DESC, md5('42:' || pair_id), pair_id) - 1) + sample_id % 2 AS k FROM sa",
}


def plan(spark, d, kind: str, filtered: bool):
    pairs = rl.filter_extremes(rates(spark, d), enabled=filtered)
    if kind == "paired":
        return rl.schedule_paired(pairs)
    return (rl.schedule_random if kind == "random" else rl.schedule_curriculum)(samples(pairs))


def _plan_sql(kind: str, filtered: bool = False) -> str:
    src = "(SELECT * FROM pf WHERE n_right > 0 AND n_right < 8)" if filtered else "pf"
    return f"WITH {RATE}, {SAMP.format(src=src)}, ra AS ({PLANS[kind]}) SELECT CAST(k // 32 AS BIGINT) AS batch_id, CAST(k % 32 AS BIGINT) AS pos, sample_id, pair_id, n_right FROM ra"


for _kind in PLANS:
    query(f"sched_{_kind}", _plan_sql(_kind))(lambda spark, d, kind=_kind: plan(spark, d, kind, False))

_DIAG = "SELECT '{k}' AS plan, batch_id, count(*) AS n, count(*) FILTER (sample_id % 2 = 0) AS n_pre, round(avg(n_right / 8), 6) AS mean_rate, round(var_pop(n_right / 8), 5) AS var_rate, CAST(count(DISTINCT pair_id) * 2 - count(*) AS BIGINT) AS n_split_pairs FROM ({p}) GROUP BY batch_id"


@query("sched_diagnose", " UNION ALL ".join(_DIAG.format(k=k, p=_plan_sql(k)) for k in PLANS))
def sched_diagnose(spark, d):
    out = None
    for k in PLANS:
        one = rl.diagnose(plan(spark, d, k, False)).withColumn("plan", F.lit(k))
        out = one if out is None else out.unionByName(one)
    return out


@query("rq4_grid", " UNION ALL ".join(f"SELECT '{'difficulty' if f else 'full'}' AS filter, '{k}' AS schedule, count(*) AS n, count(DISTINCT batch_id) AS n_batches FROM ({_plan_sql(k, f)})" for f in (False, True) for k in PLANS))
def rq4_grid(spark, d):
    out = None
    for f in (False, True):
        for k in PLANS:
            one = plan(spark, d, k, f).agg(F.count("*").alias("n"), F.count_distinct("batch_id").alias("n_batches")).withColumns({"filter": F.lit("difficulty" if f else "full"), "schedule": F.lit(k)})
            out = one if out is None else out.unionByName(one)
    return out


LIVE = f"lv AS (SELECT sample_id, min(CAST(target_reported AS INT)) <> max(CAST(target_reported AS INT)) AS live FROM roll GROUP BY sample_id)"


@query("live_share_by_batch", f"SELECT batch_id, count(*) AS n, count(*) FILTER (live) AS n_live FROM ({_plan_sql('curriculum')}) JOIN (WITH {ROLL}, {LIVE} SELECT * FROM lv) USING (sample_id) GROUP BY batch_id")
def live_share_by_batch(spark, d):
    live = rollouts(spark, d).groupBy("sample_id").agg((F.min("target_reported") != F.max("target_reported")).alias("live"))
    return plan(spark, d, "curriculum", False).join(live, "sample_id").groupBy("batch_id").agg(F.count("*").alias("n"), F.count_if("live").alias("n_live"))


OKS = {
    "detection": ("says_flawed = (side = 'pre')", lambda: F.col("says_flawed") == (F.col("side") == "pre")),
    "prediction": ("CASE WHEN side = 'pre' THEN says_flawed AND class_ok ELSE NOT (says_flawed AND class_ok) END", lambda: F.when(F.col("side") == "pre", F.col("says_flawed") & F.col("class_ok")).otherwise(~(F.col("says_flawed") & F.col("class_ok")))),
    "reasoning": ("CASE WHEN side = 'pre' THEN target_reported ELSE NOT target_reported END", lambda: F.when(F.col("side") == "pre", F.col("target_reported")).otherwise(~F.col("target_reported"))),
}
for _k, (_s, _f) in OKS.items():
    query(f"reward_{_k}", f"WITH {CLS} SELECT sample_id, CAST(slot AS INTEGER) AS slot, CASE WHEN {_s} THEN 1 ELSE -1 END AS reward FROM rc")(lambda spark, d, f=_f: classed(spark, d).select("sample_id", "slot", F.when(f(), 1).otherwise(-1).alias("reward")))


@query("reward_exact_class", f"WITH {CLS} SELECT side, count(*) AS n, count(*) FILTER (pred_code = truth_code) AS n_exact, count(*) FILTER (class_ok) AS n_near FROM rc GROUP BY side")
def reward_exact_class(spark, d):
    exact = P.class_match(rollouts(spark, d), edges(spark, d), distance=0).withColumnRenamed("class_ok", "exact")
    return P.class_match(exact, edges(spark, d)).groupBy("side").agg(F.count("*").alias("n"), F.count_if("exact").alias("n_exact"), F.count_if("class_ok").alias("n_near"))


@query("taxonomy_closure", "SELECT DISTINCT 'N' || n_nationkey AS low, 'R' || n_regionkey AS high FROM nation")
def taxonomy_closure(spark, d):
    return P.closure(edges(spark, d), 3)


SPEC = f"{CLS}, sp AS (SELECT sample_id, slot, side, CASE WHEN side = 'pre' THEN CASE WHEN class_ok THEN 1 ELSE -1 END ELSE CASE WHEN target_reported THEN -1 ELSE 1 END END AS r1, l_linenumber, l_suppkey FROM rc), s3 AS (SELECT sample_id, slot, r1, CASE WHEN side = 'pre' THEN (l_linenumber % 3) / 2 ELSE CASE WHEN r1 = 1 THEN 1 ELSE 0 END END AS r2, CASE WHEN side = 'pre' THEN (l_suppkey % 3) / 2 ELSE CASE WHEN r1 = 1 THEN 1 ELSE 0 END END AS r3 FROM sp)"


def rubric(spark, d):
    df = classed(spark, d)
    before = F.col("side") == "pre"
    r1 = F.when(before, F.when(F.col("class_ok"), 1).otherwise(-1)).otherwise(F.when(F.col("target_reported"), -1).otherwise(1))
    rest = lambda c: F.when(before, (F.col(c) % 3) / 2).otherwise(F.when(F.col("r1") == 1, 1).otherwise(0))
    return df.withColumn("r1", r1).withColumns({"r2": rest("l_linenumber"), "r3": rest("l_suppkey")})


def graded_rollouts(spark, d):
    """Rollouts with what each of the four rewards needs: class_hit (right by class), spec_reward (the rubric's total)."""
    total = rl.specification(F.col("r1"), F.col("r2"), F.col("r3")).cast("double")
    return rubric(spark, d).withColumns({"class_hit": OKS["prediction"][1](), "spec_reward": total})


for _g in ("linear", "hard"):
    _e = "0.4 * r1 + 0.2 * r2 + 0.4 * r3" if _g == "linear" else "CASE WHEN r1 = 1 THEN 0.4 * r1 + 0.2 * r2 + 0.4 * r3 ELSE -0.4 END"
    query(f"reward_spec_{_g}", f"WITH {SPEC} SELECT sample_id, CAST(slot AS INTEGER) AS slot, CAST(r1 AS DOUBLE) AS r1, CAST(r2 AS DOUBLE) AS r2, CAST(r3 AS DOUBLE) AS r3, round({_e}, 6) AS reward FROM s3")(
        lambda spark, d, g=_g: rubric(spark, d).select("sample_id", "slot", F.col("r1").cast("double").alias("r1"), F.col("r2").cast("double").alias("r2"), F.col("r3").cast("double").alias("r3"), rl.specification(F.col("r1"), F.col("r2"), F.col("r3"), gate=g).cast("double").alias("reward"))
    )


def score(df, level: str, gate: str = "linear"):
    """df (with class_ok, and r1, r2, r3 for the specification) with reward at a level."""
    if level == "specification":
        return df.withColumn("reward", rl.specification(F.col("r1"), F.col("r2"), F.col("r3"), gate=gate).cast("double"))
    if level not in OKS:
        raise ValueError(f"no reward level {level}")
    return df.withColumn("reward", F.when(OKS[level][1](), 1.0).otherwise(-1.0))


@query(
    "reward_all_levels",
    f"WITH {SPEC} " + " UNION ALL ".join(f"SELECT sample_id, CAST(slot AS INTEGER) AS slot, '{k}' AS level, CAST(CASE WHEN {s} THEN 1 ELSE -1 END AS DOUBLE) AS reward FROM rc" for k, (s, _) in OKS.items())
    + " UNION ALL SELECT sample_id, CAST(slot AS INTEGER), 'specification', CAST(round(0.4 * r1 + 0.2 * r2 + 0.4 * r3, 6) AS DOUBLE) FROM s3",
)
def reward_all_levels(spark, d):
    df = rubric(spark, d)
    for k in (*OKS, "specification"):
        df = score(df, k).withColumnRenamed("reward", f"by_{k}")
    cells = F.array(*(F.struct(F.lit(k).alias("level"), F.col(f"by_{k}").alias("reward")) for k in (*OKS, "specification")))
    return df.select("sample_id", "slot", F.explode(cells).alias("x")).select("sample_id", "slot", "x.*")


GRID = ((0.4, 0.2, 0.4), (0.6, 0.2, 0.2), (0.2, 0.4, 0.4), (1.0, 0.0, 0.0))


@query("weight_sweep", f"WITH {SPEC}, g AS (SELECT * FROM (VALUES {', '.join(map(str, GRID))}) v(w1, w2, w3)) SELECT CAST(w1 AS DOUBLE) AS w1, CAST(w2 AS DOUBLE) AS w2, CAST(w3 AS DOUBLE) AS w3, round(avg(w1 * r1 + w2 * r2 + w3 * r3), 6) AS mean_reward FROM s3, g GROUP BY ALL")
def weight_sweep(spark, d):
    grid = spark.createDataFrame([tuple(map(float, g)) for g in GRID], "w1 double, w2 double, w3 double")  # some rows
    return rubric(spark, d).join(F.broadcast(grid)).groupBy("w1", "w2", "w3").agg(F.round(F.avg(F.col("w1") * F.col("r1") + F.col("w2") * F.col("r2") + F.col("w3") * F.col("r3")), 6).alias("mean_reward"))


@query("rq5_reward_table", f"WITH {CLS} " + " UNION ALL ".join(f"SELECT '{k}' AS level, count(*) AS n, count(*) FILTER ({s}) AS n_positive, count(*) FILTER (({s}) <> ({OKS['reasoning'][0]})) AS n_disagree FROM rc" for k, (s, _) in OKS.items()))
def rq5_reward_table(spark, d):
    cells = F.array(*(F.struct(F.lit(k).alias("level"), f().alias("ok"), OKS["reasoning"][1]().alias("root")) for k, (_, f) in OKS.items()))
    rows = classed(spark, d).select(F.explode(cells).alias("x")).select("x.*")
    return rows.groupBy("level").agg(F.count("*").alias("n"), F.count_if("ok").alias("n_positive"), F.count_if(F.col("ok") != F.col("root")).alias("n_disagree"))


EV = "e0 AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn FROM events), ev AS (SELECT user_id AS query_id, (rn - 1) // 8 AS iteration, event_id, ts, CASE WHEN event_type IN ('purchase', 'signup') THEN 1.0 ELSE -1.0 END AS reward FROM e0)"


def event_groups(spark, d):
    rn = F.row_number().over(W.partitionBy("user_id").orderBy("ts", "event_id"))
    e = load(spark, d, "events", "user_id", "event_id", "ts", "event_type").withColumn("rn", rn)
    return e.select(F.col("user_id").alias("query_id"), F.floor((F.col("rn") - 1) / 8).alias("iteration"), "event_id", "ts", F.when(F.col("event_type").isin("purchase", "signup"), 1.0).otherwise(-1.0).alias("reward"))


@query("group_advantage", f"WITH {EV}, g AS (SELECT query_id, iteration, avg(reward) AS m, stddev_pop(reward) AS s, min(reward) = max(reward) AS dead FROM ev GROUP BY ALL) SELECT query_id, CAST(iteration AS BIGINT) AS iteration, event_id, CAST(reward AS DOUBLE) AS reward, round(CASE WHEN dead THEN 0 ELSE (reward - m) / s END, 6) AS advantage, dead FROM ev JOIN g USING (query_id, iteration)")
def group_advantage(spark, d):
    a = rl.group_normalize(event_groups(spark, d), ["query_id", "iteration"])
    return a.select("query_id", "iteration", "event_id", "reward", F.round("advantage", 6).alias("advantage"), "dead")


@query("dead_groups", f"WITH {EV}, g AS (SELECT min(reward) = max(reward) AS dead FROM ev GROUP BY query_id, iteration HAVING count(*) = 8) SELECT count(*) AS n_groups, count(*) FILTER (dead) AS n_dead, round(count(*) FILTER (dead) / count(*), 6) AS share FROM g")
def dead_groups(spark, d):
    g = event_groups(spark, d).groupBy("query_id", "iteration").agg(F.count("*").alias("k"), (F.min("reward") == F.max("reward")).alias("dead")).filter("k = 8")
    return g.agg(F.count("*").alias("n_groups"), F.count_if("dead").alias("n_dead"), F.round(ratio(F.count_if("dead"), F.count("*")), 6).alias("share"))


@query(
    "hacking_monitor",
    """WITH e0 AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS rn FROM events),
e1 AS (SELECT (rn - 1) // 8 AS iteration, CASE WHEN event_type IN ('purchase', 'signup') THEN 1.0 ELSE -1.0 END AS reward, CAST(json_extract(props, '$.k') AS INTEGER) >= 50 AS root, event_type = 'view' AS safe FROM e0),
i AS (SELECT iteration, avg(reward) AS m, avg(CAST(root AS INT)) AS r, avg(CAST(safe AS INT)) AS s FROM e1 GROUP BY iteration),
w AS (SELECT iteration, s, avg(m) OVER v AS m, avg(r) OVER v AS r, lag(iteration) OVER (ORDER BY iteration) AS before FROM i WINDOW v AS (ORDER BY iteration ROWS 2 PRECEDING))
SELECT CAST(iteration AS BIGINT) AS iteration, round(m, 6) AS mean_reward, round(r, 6) AS root_rate, round(s, 6) AS safe_share,
  coalesce(round(m, 9) > round(lag(m) OVER (ORDER BY iteration), 9) AND round(r, 9) < round(lag(r) OVER (ORDER BY iteration), 9), false) AS alarm FROM w""",
)
def hacking_monitor(spark, d):
    """By iteration: reward and root-cause rate (graded reward of props not negative) in moving windows of three, share of safe answers;
    an alarm where the first rises while the second falls."""
    rn = F.row_number().over(W.partitionBy("user_id").orderBy("ts", "event_id"))
    e = load(spark, d, "events", "user_id", "event_id", "ts", "event_type", "props").withColumn("iteration", F.floor((rn - 1) / 8))
    reward = F.when(F.col("event_type").isin("purchase", "signup"), 1.0).otherwise(-1.0)
    share = lambda c: F.avg(c.cast("int"))
    i = e.groupBy("iteration").agg(F.avg(reward).alias("m"), share(F.from_json("props", "k int")["k"] >= 50).alias("r"), share(F.col("event_type") == "view").alias("s"))
    order = W.orderBy("iteration")  # a row per iteration
    moving = i.select("iteration", "s", F.avg("m").over(order.rowsBetween(-2, 0)).alias("m"), F.avg("r").over(order.rowsBetween(-2, 0)).alias("r"))
    rise = lambda c: F.round(c, 9) - F.round(F.lag(c).over(order), 9)
    return moving.select("iteration", F.round("m", 6).alias("mean_reward"), F.round("r", 6).alias("root_rate"), F.round("s", 6).alias("safe_share"), F.coalesce((rise("m") > 0) & (rise("r") < 0), F.lit(False)).alias("alarm"))
