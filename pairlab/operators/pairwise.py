"""Matching rules, pairwise measures, difficulty, agreement and flows over verdict rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlab.functions.scores import ratio

LEVELS = ("label", "class", "root")


def class_match(df: DataFrame, edges: DataFrame, distance: int = 1, siblings: bool = False) -> DataFrame:
    """df with class_ok: the predicted code equals the true one or is within distance of it in the taxonomy.

    The taxonomy's pairs are broadcast; it holds some thousand codes at most (checked)."""
    near = closure(edges, distance)
    if siblings:
        near = near.union(edges.alias("a").join(edges.alias("b"), "parent").select(F.col("a.child").alias("low"), F.col("b.child").alias("high"))).distinct()
    size = near.limit(200_001).count()
    both = near.select(F.col("low").alias("pred_code"), F.col("high").alias("truth_code")).union(near.select(F.col("high").alias("pred_code"), F.col("low").alias("truth_code"))).distinct().withColumn("__near", F.lit(True))
    joined = df.join(F.broadcast(both) if size <= 200_000 else both, ["pred_code", "truth_code"], "left")
    ok = F.coalesce(F.col("pred_code") == F.col("truth_code"), F.lit(False)) | F.coalesce("__near", F.lit(False))
    return joined.withColumn("class_ok", ok).drop("__near").select(*df.columns, "class_ok")


def closure(edges: DataFrame, distance: int) -> DataFrame:
    """low, high: descendants and ancestors up to distance steps; a cycle ends at the bound."""
    step = edges.select(F.col("child").alias("low"), F.col("parent").alias("high"))
    out = reach = step.limit(0) if distance < 1 else step
    for _ in range(distance - 1):
        reach = reach.join(edges, F.col("high") == F.col("child")).select("low", F.col("parent").alias("high"))
        out = out.union(reach)
    return out.distinct()


def reported(df: DataFrame, level: str, unknown_on_fixed: str = "TN") -> Column:
    """Whether the response counts as reporting the flaw at a level; after the fix other flaws are no false alarm,
    except at the label level or with unknown_on_fixed="FP"."""
    if level == "label" or unknown_on_fixed == "FP" and level == "root":
        any_flaw = F.col("says_flawed")
        return any_flaw if level == "label" else F.when(F.col("side") == "pre", F.col("target_reported")).otherwise(any_flaw)
    return F.col("says_flawed") & F.col("class_ok") if level == "class" else F.col("target_reported")


def outcome(level: str, unknown_on_fixed: str = "TN") -> Column:
    hit = reported(None, level, unknown_on_fixed)
    return F.when(F.col("side") == "pre", F.when(hit, "tp").otherwise("fn")).otherwise(F.when(hit, "fp").otherwise("tn"))


def confusion(df: DataFrame, levels: tuple = LEVELS, unknown_on_fixed: str = "TN") -> DataFrame:
    """level, tp, fp, tn, fn in one pass."""
    named = F.array(*(F.struct(F.lit(k).alias("level"), outcome(k, unknown_on_fixed).alias("o")) for k in levels))
    rows = df.select(F.explode(named).alias("x"))
    return rows.groupBy(F.col("x.level").alias("level")).agg(*(F.count_if(F.col("x.o") == k).alias(k) for k in ("tp", "fp", "tn", "fn")))


def f1(counts: DataFrame) -> DataFrame:
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return counts.select("level", F.round(ratio(tp, tp + fp), 6).alias("precision"), F.round(ratio(tp, tp + fn), 6).alias("recall"), F.round(ratio(2 * tp, 2 * tp + fp + fn), 6).alias("f1"))


def masks(df: DataFrame, by: tuple = ()) -> DataFrame:
    """One row per pair: 8-bit masks of the slots that report the target and that were seen, by side. A slot given twice fails."""
    bit = F.expr("shiftleft(1, slot - 1)")
    pick = lambda side, cond: F.bit_or(F.when((F.col("side") == side) & cond, bit).otherwise(0))
    hit, all = F.col("target_reported"), F.lit(True)
    n = lambda side: F.count_if(F.col("side") == side)
    out = df.groupBy(*by, "pair_id").agg(pick("pre", hit).alias("pre"), pick("post", hit).alias("post"), pick("pre", all).alias("seen_pre"), pick("post", all).alias("seen_post"), n("pre").alias("n_pre"), n("post").alias("n_post"))
    once = (F.expr("bit_count(seen_pre)") == F.col("n_pre")) & (F.expr("bit_count(seen_post)") == F.col("n_post"))
    seen = F.when(once, F.expr("seen_pre & seen_post")).otherwise(F.raise_error(F.lit("a slot occurs twice")).cast("int"))
    return out.withColumn("seen", seen)


def counts(df: DataFrame, by: tuple = (), complete: str = "observed", k: int = 8) -> DataFrame:
    """Per pair: slots seen on both sides, right on both (c), reported on both (v), on neither (b), the wrong way round (r)."""
    m = masks(df, by)
    if complete == "require":
        m = m.filter(F.expr("bit_count(seen)") == k)
    term = lambda e: F.expr(f"bit_count({e})").cast("long")
    return m.select(*by, "pair_id", term("seen").alias("n"), term("pre & ~post & seen").alias("c"), term("pre & post & seen").alias("v"), term("~pre & ~post & seen").alias("b"), term("~pre & post & seen").alias("r"))


def summary(df: DataFrame, by: tuple = ("policy_id",), complete: str = "observed") -> DataFrame:
    """P-Pass@1, P-Pass@8, P-V, P-B, P-R and F1 by group: one shuffle by pair, one of a row per group and task."""
    return summary_of(counts(df, by, complete).filter("n > 0"), by)


def summary_of(per: DataFrame, by: tuple) -> DataFrame:
    """The same from counts by pair (n, c, v, b, r)."""
    s = {x: F.sum(x) for x in "ncvbr"}
    share = lambda x: F.round(ratio(s[x], s["n"]), 6)
    tp, fn, fp = s["c"] + s["v"], s["b"] + s["r"], s["v"] + s["r"]
    return per.groupBy(*by).agg(
        F.count("*").alias("n_pairs"), s["n"].alias("n_response_pairs"), share("c").alias("p_pass_1"), F.round(ratio(F.count_if(F.col("c") > 0), F.count("*")), 6).alias("p_pass_8"),
        share("v").alias("p_v"), share("b").alias("p_b"), share("r").alias("p_r"), F.round(ratio(2 * tp, 2 * tp + fp + fn), 6).alias("f1"),
    )


def pass_at(df: DataFrame, k: int = 8) -> DataFrame:
    """m, pass_at: the chance that m slots drawn from a pair's n hold a right one, over pairs."""
    per = counts(df).filter("n > 0").groupBy("n", "c").agg(F.count("*").alias("pairs"))  # at most 72 rows
    rows = per.withColumn("m", F.explode(F.sequence(F.lit(1), F.lit(k)))).filter("m <= n")
    miss = F.aggregate(F.sequence(F.lit(0), F.col("m") - 1), F.lit(1.0), lambda a, i: a * F.greatest(F.col("n") - F.col("c") - i, F.lit(0)) / (F.col("n") - i))
    return rows.groupBy("m").agg(F.round(F.sum((1 - miss) * F.col("pairs")) / F.sum("pairs"), 6).alias("pass_at"))


def kappa(df: DataFrame, a: str, b: str) -> DataFrame:
    """n, p_observed, p_chance, kappa from one contingency table; null where chance agreement is 1."""
    cells = df.groupBy(F.col(a).alias("x"), F.col(b).alias("y")).agg(F.count("*").alias("n"))
    row = cells.groupBy("x").agg(F.sum("n").alias("nx"))
    col = cells.groupBy(F.col("y").alias("x")).agg(F.sum("n").alias("ny"))
    chance = row.join(col, "x").agg(F.coalesce(F.sum(F.col("nx").cast("double") * F.col("ny")), F.lit(0.0)).alias("prod"))
    total = cells.agg(F.sum("n").alias("n"), F.coalesce(F.sum(F.when(F.col("x") == F.col("y"), F.col("n"))), F.lit(0)).alias("same"))
    both = total.join(F.broadcast(chance), F.lit(True))
    po, pe = F.col("same") / F.col("n"), F.col("prod") / (F.col("n").cast("double") * F.col("n"))
    return both.select("n", F.round(po, 6).alias("p_observed"), F.round(pe, 6).alias("p_chance"), F.round(F.when(pe < 1, (po - pe) / (1 - pe)), 6).alias("kappa"))
