"""Training of the surrogate policy: supervised, preference and on-policy stages of any number of recipes in lock step.

A query's candidates are packed into one row once.  A step of all recipes is one scan of the packed table: each task works
out every recipe's gradient (pairlab.plans.objectives_np) and sends one row of sums per recipe; the driver holds a weight
vector for each.  So the number of jobs is the length of the longest recipe, whatever the number of recipes.

An on-policy step takes the next part of its plan (filter and schedule), draws a group of responses from the policy as it
is, looks up their verdicts, rewards them at the recipe's level, normalises in the group and moves the weights; with
inner > 1 it moves again on the same draws, where ratio and clip matter."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlab.operators.pairwise import summary_of
from pairlab.plans import objectives_np as N
from pairlab.plans.surrogate import FEATURES
from pairlab.sources.tables import saved

D = len(FEATURES)
ZERO = (0.0,) * D
#: Reward levels: of label, class and root cause (+1 or -1), and the rubric's total.
REWARDS = ("detection", "prediction", "reasoning", "specification")
#: What a supervised source keeps: right root causes; answers written towards a known label, as they are; these less the ones that
#: name the true class without the cause (no reasoning, no leaked truth); right classes.
SOURCES = ("rejection", "rationalized", "answers", "class")


@dataclass(frozen=True)
class Recipe:
    name: str
    start: tuple = ZERO  # weights of the untrained policy
    sft_source: str = "rejection"  # one of SOURCES, or none
    sft_epochs: int = 3
    preference: str = ""  # dpo or orpo
    pref_source: str = ""  # policy (own draws) or teacher (all candidates); empty: policy for dpo, teacher for orpo
    rl_reward: str = ""  # one of REWARDS
    rl_filter: str = "full"  # or difficulty
    rl_schedule: str = ""  # random, curriculum, paired; empty: the whole table each step
    rl_steps: int = 6
    inner: int = 1
    rate: float = 2.0
    beta: float = 0.1
    rl_beta: float = 0.0
    clip: float = 0.2
    seed: int = 42

    def __post_init__(self) -> None:
        for value, known in ((self.sft_source, (*SOURCES, "none")), (self.preference, ("", "dpo", "orpo")), (self.rl_reward, ("", *REWARDS)), (self.rl_filter, ("full", "difficulty")), (self.rl_schedule, ("", "random", "curriculum", "paired")), (self.pref_source, ("", "policy", "teacher"))):
            if value not in known:
                raise ValueError(f"{self.name}: no such choice: {value}")


def zero_shot(k: int) -> Recipe:
    """Untrained system k of ten: the further on, the more it reports and the more it prefers easy responses."""
    return Recipe(f"zero_shot_{k}", (0.0, -0.2 * k, 0.0, 0.0, -1.5 + 0.3 * k, 0.0), "none", 0)


#: The systems of the main comparison: ten untrained ones, the off-policy ones, the on-policy ones.
COMPARED = (
    *(zero_shot(k) for k in range(1, 11)),
    Recipe("sft"), Recipe("rationalized_orpo", sft_source="rationalized", preference="orpo"), Recipe("rationalized_dpo", sft_source="rationalized", preference="dpo"), Recipe("dpo", preference="dpo"), Recipe("orpo", preference="orpo"),
    Recipe("rl_detection", rl_reward="detection"), Recipe("rl_specification", rl_reward="specification"),
)
#: Further recipes of the text: by class-filtered data, the other rewards, and without a cold start.
FURTHER = (Recipe("class_filtered", sft_source="class"), Recipe("rl_prediction", rl_reward="prediction"), Recipe("rl_reasoning", rl_reward="reasoning"), Recipe("rl_no_cold_start", sft_source="none", sft_epochs=0, rl_reward="specification"))
SFT_STEPS, PREF_STEPS = 3, 6  # of an epoch; of the preference stage
FLAGS = ("root_ok", "label_ok", "class_hit", "target_reported", "safe")


def pack(cands: DataFrame) -> DataFrame:
    """One row a query: query_id, pair_id, before, and arrays over its candidates by slot (x has all features, one candidate after the other)."""
    c = F.array_sort(F.collect_list(F.struct("slot", *FEATURES, *FLAGS, "spec_reward")))  # eight a query
    rows = cands.groupBy("query_id").agg(F.first("pair_id").alias("pair_id"), F.first(F.col("side") == "pre").alias("before"), c.alias("c"))
    x = F.flatten(F.transform("c", lambda o: F.array(*(o[f] for f in FEATURES))))
    return rows.select("query_id", "pair_id", "before", x.alias("x"), *(F.col(f"c.{f}").alias(f) for f in FLAGS), F.col("c.spec_reward").alias("spec_reward"))


class Batch:
    """Arrays of a record batch of packed queries, padded to the most candidates in it."""

    def __init__(self, batch: pa.RecordBatch):
        self.query, self.pair = batch.column("query_id").to_numpy(), batch.column("pair_id").to_numpy()
        self.before = batch.column("before").to_numpy(zero_copy_only=False)
        n = pa.compute.list_value_length(batch.column("root_ok")).to_numpy()
        k = int(n.max())
        self.live = np.arange(k)[None] < n[:, None]
        self.x = np.zeros((len(n), k, D))
        self.x[self.live] = batch.column("x").flatten().to_numpy().reshape(-1, D)
        for f in (*FLAGS, "spec_reward"):
            v = batch.column(f).flatten().to_numpy(zero_copy_only=False)
            full = np.zeros((len(n), k), v.dtype)
            full[self.live] = v
            setattr(self, f, full)
        self.parts = {c: batch.column(c).to_numpy(zero_copy_only=False) for c in batch.schema.names if c.startswith("part_")}

    def chosen(self, source: str) -> np.ndarray:
        kept = {"rejection": self.root_ok, "rationalized": self.label_ok, "answers": self.label_ok & ~(self.class_hit & ~self.root_ok), "class": self.class_hit}[source]
        return kept & self.live

    def reward(self, level: str) -> np.ndarray:
        if level == "specification":
            return self.spec_reward
        return np.where({"detection": self.label_ok, "prediction": self.class_hit, "reasoning": self.root_ok}[level], 1.0, -1.0)

    def some(self, rows: np.ndarray) -> "Batch":
        out = object.__new__(Batch)
        out.__dict__ = {k: v[rows] if isinstance(v, np.ndarray) else v for k, v in self.__dict__.items()}
        return out


@dataclass
class Step:
    """What one recipe asks of one scan."""

    kind: str  # sft, dpo, orpo, rl
    recipe: Recipe
    w: np.ndarray
    ref: np.ndarray
    old: np.ndarray
    number: int = 0  # of the on-policy step; draws and the plan's part go by it
    all_once: bool = False  # the group is every candidate once, not draws

    def of(self, b: Batch) -> N.Result:
        r = self.recipe
        if self.kind == "rl" and r.rl_schedule:
            part = b.parts[f"part_{r.rl_filter}_{r.rl_schedule}"]
            b = b.some(np.flatnonzero(np.nan_to_num(part.astype(float), nan=-1) == self.number))
        elif self.kind == "rl" and r.rl_filter == "difficulty":
            b = b.some(np.flatnonzero(b.parts["part_difficulty"].astype(bool)))
        if not len(b.query):
            return 0.0, np.zeros(D), 0
        if self.kind == "sft":
            return N.sft(b.x, b.live, self.w, b.chosen(r.sft_source))
        if self.kind == "rl":
            places = np.where(b.live, np.arange(b.live.shape[1])[None], -1) if self.all_once else N.draw(N.log_probs(b.x, b.live, self.old), b.live, b.query, 8, r.seed + self.number)
            return N.group_relative(b.x, b.live, self.w, self.old, self.ref, places, b.reward(r.rl_reward), r.clip, r.rl_beta)
        if (r.pref_source or ("policy" if self.kind == "dpo" else "teacher")) == "policy":
            drawn = N.draw(N.log_probs(b.x, b.live, self.ref), b.live, b.query, 8, r.seed)
            q, c, j = N.zipped(np.take_along_axis(b.root_ok, drawn, 1), np.ones_like(drawn, bool))
            pairs = q, drawn[q, c], drawn[q, j]
        else:
            pairs = N.zipped(b.root_ok, b.live)
        return N.dpo(b.x, b.live, self.w, self.ref, pairs, r.beta) if self.kind == "dpo" else N.orpo(b.x, b.live, self.w, pairs, r.beta)


def gradients(packed: DataFrame, steps: list[Step]) -> DataFrame:
    """step (place in steps), n, value and g0, g1, ...: means over the rows of each step's objective."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((len(steps), D + 2))
        for batch in batches:
            if batch.num_rows:
                b = Batch(batch)
                for k, s in enumerate(steps):
                    value, g, n = s.of(b)
                    total[k] += [n, value, *g]
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(steps))), *(pa.array(total[:, k]) for k in range(D + 2))], names=["step", "n", "value", *(f"g{k}" for k in range(D))])

    rows = packed.mapInArrow(run, "step long, n double, value double, " + ", ".join(f"g{k} double" for k in range(D)))
    mean = lambda c: (F.sum(c) / F.when(F.sum("n") > 0, F.sum("n"))).alias(c)
    return rows.groupBy("step").agg(F.sum("n").cast("long").alias("n"), mean("value"), *(mean(f"g{k}") for k in range(D)))


def rate_at(rate: float, k: int, total: int, warm: float = 0.1) -> float:
    """Linear warm-up over a share of the steps, then linear decay."""
    up = max(1, round(warm * total))
    return rate * ((k + 1) / up if k < up else (total - k) / (total - up + 1))


def _move(packed: DataFrame, steps: list[Step], rates: list[float]) -> None:
    for row in gradients(packed, steps).collect():  # a row a recipe
        s = steps[row["step"]]
        if row["n"]:
            # rounded, so that the order of partial sums does not matter
            s.w = np.round(s.w + rates[row["step"]] * np.array([row[f"g{k}"] for k in range(D)]), 10)


def fit(packed: DataFrame, recipes: tuple[Recipe, ...]) -> dict[str, list[np.ndarray]]:
    """Weights of each recipe: those before its last stage's first step, and after each of its steps."""
    starts = {r.name: np.array(r.start) for r in recipes}
    # one supervised run for all recipes that share it; its checkpoints are kept by epoch
    runs = {}
    for r in recipes:
        if r.sft_source != "none" and r.sft_epochs:
            key = (r.start, r.sft_source, r.rate)
            runs[key] = max(runs.get(key, 0), r.sft_epochs)
    held = {k: [np.array(k[0])] for k in runs}
    steps = {k: Step("sft", Recipe("", sft_source=k[1]), np.array(k[0]), np.array(k[0]), np.array(k[0])) for k in runs}
    for e in range(max(runs.values(), default=0)):
        live = [k for k in runs if e < runs[k]]
        for i in range(SFT_STEPS):
            _move(packed, [steps[k] for k in live], [rate_at(k[2], e * SFT_STEPS + i, 5 * SFT_STEPS) for k in live])
        for k in live:
            held[k].append(steps[k].w)
    out = {}
    for r in recipes:
        done = held.get((r.start, r.sft_source, r.rate))
        out[r.name] = [starts[r.name]] if not done else done[: r.sft_epochs + 1]

    def stage(kind_of, total_of) -> None:
        live = [(r, Step(kind_of(r), r, out[r.name][-1], out[r.name][-1], out[r.name][-1])) for r in recipes if kind_of(r)]
        for r, s in live:
            out[r.name] = [s.w]
        for k in range(max((total_of(r) for r, _ in live), default=0)):
            now = [(r, s) for r, s in live if k < total_of(r)]
            for inner in range(max(r.inner if s.kind == "rl" else 1 for r, s in now)):
                mine = [(r, s) for r, s in now if inner < (r.inner if s.kind == "rl" else 1)]
                for _, s in mine:
                    s.number, s.old = k, s.w if inner == 0 else s.old
                _move(packed, [s for _, s in mine], [rate_at(r.rate / (r.beta if s.kind == "dpo" else 1), k, total_of(r)) for r, s in mine])
            for r, s in now:
                out[r.name].append(s.w)

    stage(lambda r: r.preference, lambda r: PREF_STEPS)
    stage(lambda r: "rl" if r.rl_reward else "", lambda r: r.rl_steps)
    return out


def measure(packed: DataFrame, weights: dict[str, np.ndarray], k: int = 8, seed: int = 7) -> DataFrame:
    """recipe and the six measures over k drawn responses a sample, for all policies in one scan."""
    names = list(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            b = Batch(batch)
            for name in names:
                drawn = N.draw(N.log_probs(b.x, b.live, weights[name]), b.live, b.query, k, seed)
                mask = (np.take_along_axis(b.target_reported, drawn, 1) * (1 << np.arange(k))).sum(1)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(mask)), pa.array(b.pair), pa.array(b.before), pa.array(mask.astype(np.int32))], names=["recipe", "pair_id", "before", "mask"])

    rows = packed.mapInArrow(run, "recipe string, pair_id long, before boolean, mask int")
    side = lambda s: F.bit_or(F.when(F.col("before") == s, F.col("mask")).otherwise(0))
    pairs = rows.groupBy("recipe", "pair_id").agg(side(True).alias("pre"), side(False).alias("post"), F.count_distinct("before").alias("sides")).filter("sides = 2")
    full = (1 << k) - 1
    term = lambda e: F.expr(f"bit_count(({e}) & {full})").cast("long")
    per = pairs.select("recipe", "pair_id", F.lit(k).cast("long").alias("n"), term("pre & ~post").alias("c"), term("pre & post").alias("v"), term("~pre & ~post").alias("b"), term("~pre & post").alias("r"))
    return summary_of(per, ("recipe",))


def with_plans(packed: DataFrame, plans: dict[str, DataFrame], steps: int) -> DataFrame:
    """packed with a column part_<name> for each plan (batch_id, sample_id): the step in which a query's batch comes."""
    for name, plan in plans.items():
        last = plan.agg((F.max("batch_id") + 1).alias("n")).first()["n"] or 1
        part = F.floor(F.col("batch_id") * steps / last).cast("int")
        packed = packed.join(plan.select(F.col("sample_id").alias("query_id"), part.alias(f"part_{name}")), "query_id", "left")
    return saved(packed, "planned")
