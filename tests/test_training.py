"""Objectives of the surrogate policy against finite differences and their definitions, and its training."""

import math

import numpy as np
import pytest

from conftest import SF
from pairlab import catalogue as registry
from pairlab.plans import objectives_np as N
from pairlab.plans import training as T


@pytest.fixture(scope="module")
def batch():
    g = np.random.default_rng(3)
    live = np.arange(6)[None] < np.array([6, 5, 2, 6, 1, 4, 6])[:, None]
    x = np.where(live[:, :, None], g.normal(size=(7, 6, T.D)), 0.0)
    return x, live, g.random((7, 6)) < 0.5, g.normal(size=(3, T.D)) * 0.7, g.normal(size=(7, 6))


def objectives(x, live, ok, ref, old, reward):
    drawn = N.draw(N.log_probs(x, live, old), live, np.arange(7), 8, 5)
    pairs = N.zipped(ok, live)
    return {
        "sft": lambda w: N.sft(x, live, w, ok & live), "dpo": lambda w: N.dpo(x, live, w, ref, pairs, 0.3), "orpo": lambda w: N.orpo(x, live, w, pairs, 0.3),
        "group": lambda w: N.group_relative(x, live, w, old, ref, drawn, reward, 0.2, 0.0), "group with divergence": lambda w: N.group_relative(x, live, w, old, ref, drawn, np.sign(reward), 0.1, 0.2),
    }


@pytest.mark.parametrize("name", ["sft", "dpo", "orpo", "group", "group with divergence"])
def test_gradients_equal_finite_differences(batch, name):
    x, live, ok, (w, ref, old), reward = batch
    f = objectives(x, live, ok, ref, w + 0.05 * old, reward)[name]
    _, g, n = f(w)
    assert n > 0
    for k in range(T.D):
        e = np.eye(T.D)[k] * 1e-6
        assert abs((f(w + e)[0] - f(w - e)[0]) / 2e-6 - g[k]) < 1e-5


def test_identities(batch):
    x, live, ok, (w, ref, old), reward = batch
    pairs = N.zipped(ok, live)
    value, _, n = N.dpo(x, live, w, w, pairs, 0.5)
    assert math.isclose(value, n * math.log(0.5))  # at the reference
    q, c, _ = pairs
    assert math.isclose(N.orpo(x, live, w, pairs, 0.0)[0], N.log_probs(x, live, w)[q, c].sum())  # the supervised term alone
    drawn = N.draw(N.log_probs(x, live, w), live, np.arange(7), 8, 1)
    on_policy = N.group_relative(x, live, w, w, ref, drawn, reward)
    assert abs(on_policy[0]) < 1e-9  # advantages of a group sum to nothing
    assert np.allclose(on_policy[1], N.group_relative(x, live, w, w, ref, drawn, reward, clip=9.0)[1])  # the clip is inert at ratio 1
    assert np.allclose(N.group_relative(x, live, w, w, ref, drawn, 3 * reward + 5)[1], on_policy[1])  # neither shift nor scale matters
    assert not N.group_relative(x, live, w, old, ref, drawn, np.ones_like(reward))[1].any()  # dead groups
    assert N.group_relative(x, live, w, w, ref, drawn, np.ones_like(reward), beta=1.0)[0] <= 0  # the divergence is no less than zero


def test_draws_follow_the_policy():
    x = np.zeros((4000, 3, T.D))
    x[:, :, 0] = [0.0, math.log(2), math.log(5)]
    live = np.ones((4000, 3), bool)
    live[:, 2] = False
    lp = N.log_probs(x, live, np.eye(T.D)[0])
    drawn = N.draw(lp, live, np.arange(4000), 8, 3)
    assert drawn.max() == 1 and abs((drawn == 1).mean() - 2 / 3) < 0.01
    order = np.random.default_rng(0).permutation(4000)
    assert (N.draw(lp, live, np.arange(4000)[order], 8, 3) == drawn[order]).all()


def test_unknown_choices_fail():
    for bad in ({"rl_reward": "lenient"}, {"sft_source": "x"}, {"preference": "kto"}, {"rl_schedule": "sorted"}):
        with pytest.raises(ValueError, match="no such choice"):
            T.Recipe("r", **bad)


def test_rates():
    r = [T.rate_at(1.0, k, 20) for k in range(20)]
    assert r[:2] == [0.5, 1.0] and all(a > b > 0 for a, b in zip(r[2:], r[3:]))


@pytest.fixture(scope="module")
def table(spark):
    from pairlab.operators.workloads_policy import packed

    return packed(spark, SF).cache()


def test_lock_step_equals_one_by_one(spark, table):
    recipes = (T.Recipe("a", sft_epochs=2, preference="dpo"), T.Recipe("b", sft_epochs=1, rl_reward="specification", inner=2, rl_steps=2), T.Recipe("c", sft_source="class", sft_epochs=1, preference="orpo", rl_reward="detection", rl_steps=1))
    together = T.fit(table, recipes)
    for r in recipes:
        alone = T.fit(table, (r,))[r.name]
        assert len(alone) == len(together[r.name]) and all(np.allclose(x, y, atol=1e-7) for x, y in zip(alone, together[r.name]))


def test_steps_raise_their_objective(spark, table):
    for kind, r in (("sft", T.Recipe("r")), ("dpo", T.Recipe("r")), ("orpo", T.Recipe("r"))):
        w = np.zeros(T.D)
        values = []
        for _ in range(4):
            s = T.Step(kind, r, w, np.zeros(T.D), np.zeros(T.D))
            row = T.gradients(table, [s]).first()
            values.append(row.value)
            w = w + 0.2 * np.array([row[f"g{k}"] for k in range(T.D)])
        assert values == sorted(values) and values[0] < values[-1]


def test_every_reward_pulls_elsewhere(spark, table):
    rows = T.gradients(table, [T.Step("rl", T.Recipe("r", rl_reward=k), np.zeros(T.D), np.zeros(T.D), np.zeros(T.D)) for k in T.REWARDS]).collect()
    assert len({tuple(r[f"g{k}"] for k in range(T.D)) for r in rows}) == 4
    want = {(r.sample_id, r.slot): r.reward for r in registry.QUERIES["reward_spec_linear"](spark, SF).collect()}
    for r in table.limit(20).collect():
        assert [want[r.query_id, k + 1] for k in range(len(r.spec_reward))] == pytest.approx(r.spec_reward)


def test_findings_of_the_comparison(spark):
    got = {r.recipe: r for r in registry.QUERIES["rq6_compare"](spark, SF).collect()}
    assert len(got) == len(T.COMPARED) + len(T.FURTHER) and len(T.COMPARED) == 17
    for r in got.values():
        assert abs(r.p_pass_1 + r.p_v + r.p_b + r.p_r - 1) < 5e-6 and r.p_pass_1 <= r.p_pass_8 <= min(1, 8 * r.p_pass_1)
        assert abs(r.f1 - 2 * (r.p_pass_1 + r.p_v) / (2 * (r.p_pass_1 + r.p_v) + r.p_v + r.p_r + r.p_b + r.p_r)) < 1e-5
    p1 = lambda k: got[k].p_pass_1
    assert p1("dpo") > p1("sft") > p1("class_filtered") and p1("orpo") > p1("sft") > p1("zero_shot_1")
    assert p1("dpo") > p1("rationalized_dpo") and p1("rl_reasoning") > p1("rl_detection")


def test_findings_of_epochs_and_curation(spark):
    one = {r.recipe: r.p_pass_1 for r in registry.QUERIES["rq1_metrics"](spark, SF).collect()}
    assert one["rejection"] > one["answers"] and one["rejection"] > one["rationalized"] > one["zero_shot_1"]
    three = {r.recipe: r.p_pass_1 for r in registry.QUERIES["rq3_epochs"](spark, SF).collect()}
    assert len(three) == 6 and min(three, key=three.get) == "rl_0"
    five = registry.QUERIES["rq5_curves"](spark, SF).collect()
    assert {(r.reward, r.step) for r in five} == {(k, s) for k in T.REWARDS for s in range(7)}


def test_grid_is_whole_and_plans_cover_every_query(spark):
    rows = registry.QUERIES["rq4_metrics"](spark, SF).collect()
    assert {r.recipe for r in rows} == {f"{f}_{k}" for f in ("full", "difficulty") for k in ("random", "curriculum", "paired")}
