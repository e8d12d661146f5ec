"""Properties, worked examples and oracle comparisons of the library."""

import glob
import math
import os

import duckdb
import pytest
from pyspark.sql import functions as F

from conftest import SF
from pairlab import catalogue as registry
from pairlab.functions.scores import log_odds, log_sigmoid
from pairlab.operators import curate, pairwise, rl
from pairlab.operators.workloads_policy import without_thoughts

ROWS = "pair_id long, side string, slot int, target_reported boolean"


def test_one_slot_of_each_kind(spark):
    rows = [(1, s, k, v) for k, (a, b) in enumerate([(True, False), (True, True), (False, False), (False, True)], 1) for s, v in (("pre", a), ("post", b))]
    r = pairwise.summary(spark.createDataFrame(rows, ROWS), ()).first()
    assert (r.p_pass_1, r.p_v, r.p_b, r.p_r, r.f1, r.p_pass_8) == (0.25, 0.25, 0.25, 0.25, 0.5, 1.0)


def test_slot_given_twice_fails(spark):
    rows = [(1, "pre", 1, True), (1, "pre", 1, True), (1, "post", 1, False)]
    with pytest.raises(Exception, match="twice"):
        pairwise.summary(spark.createDataFrame(rows, ROWS), ()).collect()


def test_kappa_by_hand(spark):
    cells = [(1, 1)] * 20 + [(1, 0)] * 5 + [(0, 1)] * 10 + [(0, 0)] * 15
    assert pairwise.kappa(spark.createDataFrame(cells, "a int, b int"), "a", "b").first().kappa == 0.4


def test_rubric(spark):
    rows = spark.createDataFrame([(1, 1.0, 1.0), (1, 0.5, 0.5), (1, 0.0, 0.0), (-1, 1.0, 1.0), (-1, 0.0, 0.0)], "a int, b double, c double")
    got = [(float(x), float(y)) for x, y in rows.select(*(rl.specification(F.col("a"), F.col("b"), F.col("c"), gate=g) for g in ("linear", "hard"))).collect()]
    assert got == [(1.0, 1.0), (0.7, 0.7), (0.4, 0.4), (0.2, -0.4), (-0.4, -0.4)]


def test_advantage(spark):
    rows = [("a", 1.0)] * 4 + [("b", 1.0), ("b", -1.0)] * 2 + [("c", 1.0)]
    got = rl.group_normalize(spark.createDataFrame(rows, "g string, reward double"), ["g"]).collect()
    assert all(r.advantage == (0 if r.g in "ac" else r.reward) and r.dead == (r.g in "ac") for r in got)


def test_stable_functions(spark):
    r = spark.range(1).select(log_sigmoid(F.lit(-800.0)).alias("a"), log_sigmoid(F.lit(0.0)).alias("b"), log_odds(F.lit(-1e-12)).alias("c"), log_odds(F.lit(0.0)).alias("d")).first()
    assert r.a == -800 and math.isclose(r.b, math.log(0.5)) and math.isclose(r.c, -math.log(1e-12), rel_tol=1e-6) and r.d is None


def test_comments_and_thoughts(spark):
    texts = ['"http://x" // y', "/* a */ b", "'\"' c", "d /* open", "<think>a</think>b", "<think>open"]
    got = [(r.c, r.t) for r in spark.createDataFrame([(t,) for t in texts], "s string").select(curate.strip_c_comments(F.col("s")).alias("c"), without_thoughts(F.col("s")).alias("t")).collect()]
    assert [c for c, _ in got[:4]] == ['"http://x" ', " b", "'\"' c", "d "] and [t for _, t in got[4:]] == ["b", ""]


def test_closure_ends_on_a_cycle(spark):
    got = {tuple(r) for r in pairwise.closure(spark.createDataFrame([("a", "b"), ("b", "a")], "child string, parent string"), 4).collect()}
    assert got == {("a", "b"), ("b", "a"), ("a", "a"), ("b", "b")}


def test_paired_schedule_keeps_pairs(spark):
    plan = rl.schedule_paired(spark.createDataFrame([(k, k % 9) for k in range(50)], "pair_id long, n_right long"), 8)
    rows = plan.collect()
    assert len({(r.batch_id, r.pos) for r in rows}) == 100 and len({(r.batch_id, r.pair_id) for r in rows}) == 50


ORACLE = ("pairwise_summary", "difficulty_hist", "sched_paired", "f1_levels", "group_advantage", "reject_keep_shortest", "prefs_zip", "obj_dpo", "obj_group_relative", "split_temporal", "context_expand_1hop", "surrogate_probs", "stream_tumbling", "stream_sliding", "stream_session", "stream_group_advantage")


@pytest.mark.parametrize("name", ORACLE)
def test_equals_sql(spark, name):
    con = duckdb.connect()
    for p in glob.glob(SF + "/*.parquet"):
        con.execute(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    want = con.sql(registry.ORACLE_SQL[name])
    df = registry.QUERIES[name](spark, SF)
    columns = sorted(df.columns)
    assert columns == sorted(want.columns)
    flat = lambda rows, names: sorted(str([round(float(r[names.index(c)]), 5) if isinstance(r[names.index(c)], float) else str(r[names.index(c)]) for c in columns]) for r in rows)
    assert flat([tuple(r) for r in df.collect()], df.columns) == flat(want.fetchall(), want.columns)


def test_one_shuffle_by_pair(spark):
    from pairlab.sources.fixtures import rollouts

    plan = pairwise.counts(rollouts(spark, SF))._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan


def test_as_of_rows_of_every_user(spark):
    sf = SF.replace("0.001", "0.01")
    events = sorted(spark.read.parquet(sf + "/events.parquet").collect(), key=lambda r: (r.ts, r.event_id))
    want, latest = set(), {}
    for r in events:
        if r.event_type == "purchase":
            latest[r.user_id] = r.event_id
        want.add((r.event_id, latest.get(r.user_id)))
    assert max(r.user_id for r in events) > 30
    got = registry.QUERIES["asof_checkpoint"](spark, sf).collect()
    assert len(got) == len(events) and {tuple(r) for r in got} == want
