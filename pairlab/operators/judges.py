"""Judges: an interface for external ones with batches and retries, guards for what they say, and the filter by a judge."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlab.sources.tables import shingles

#: What becomes of a row whose judge failed (verdict null).
POLICIES = ("fail", "incorrect", "drop")


@dataclass(frozen=True)
class Judge:
    """An external judge: ask gets lists of responses and of evidence, and returns a verdict (true, false or None) of each.

    It is asked in batches of ``batch`` rows; a batch that raises, or that answers with another number of verdicts, is asked again
    up to ``retries`` times, after ``wait`` seconds, twice as many and so on.  A batch that fails to the end has no verdicts (null),
    which is a third state and no "wrong"; n_asked says how often its batch was asked.  A verdict is asked for again if
    a task is lost, so ask must be safe to repeat; write verdicts before using them twice."""

    judge_id: str
    ask: Callable[[list, list], list]
    batch: int = 32
    retries: int = 2
    wait: float = 0.0

    def _answers(self, responses: list, evidence: list) -> tuple[list, int]:
        for k in range(self.retries + 1):
            try:
                out = list(self.ask(responses, evidence))
                if len(out) == len(responses):
                    return [None if v is None else bool(v) for v in out], k + 1
            except Exception:  # noqa: BLE001  whatever an external service raises
                pass
            if k < self.retries:
                time.sleep(self.wait * 2**k)
        return [None] * len(responses), self.retries + 1

    def evaluate(self, df: DataFrame, response: str = "response", evidence: str = "evidence") -> DataFrame:
        """df with judge_id, correct and n_asked."""
        judge = self
        names = [c for c in df.columns if c not in ("judge_id", "correct", "n_asked")]

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for frame in frames:
                for at in range(0, len(frame), judge.batch):
                    part = frame.iloc[at : at + judge.batch].copy()
                    verdicts, n = judge._answers(part[response].tolist(), part[evidence].tolist())
                    yield part.assign(judge_id=judge.judge_id, correct=pd.array(verdicts, "boolean"), n_asked=n)

        slim = df.select(*names)
        fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in slim.schema.fields)
        return slim.mapInPandas(run, f"{fields}, judge_id string, correct boolean, n_asked long")


def shares_words(responses: list, evidence: list) -> list:
    """A stand-in for an external judge: right if a fifth of the evidence's words stand in the response."""
    return [len(set(r.split()) & set(e.split())) * 5 >= len(set(e.split())) for r, e in zip(responses, evidence)]


def resolve(judged: DataFrame, on_missing: str = "drop") -> DataFrame:
    """judged without null verdicts: their rows go, count as wrong, or end the job."""
    if on_missing not in POLICIES:
        raise ValueError(f"no policy {on_missing}")
    if on_missing == "drop":
        return judged.filter(F.col("correct").isNotNull())
    other = F.lit(False) if on_missing == "incorrect" else F.raise_error(F.lit("a judge gave no verdict")).cast("boolean")
    return judged.withColumn("correct", F.coalesce("correct", other))


def protocol(rollouts: DataFrame, verdicts: DataFrame, keys: tuple = ("sample_id", "slot"), on_missing: str = "drop") -> DataFrame:
    """Rollouts that the judge calls right; verdicts are a table by the rollouts' keys, so a judge is asked once."""
    joined = rollouts.join(verdicts.select(*keys, "correct"), list(keys), "left")
    return resolve(joined, on_missing).filter("correct").drop("correct")


def contradicts(text: Column, predicted: Column) -> Column:
    """Whether a verdict says that nothing was found though a class is predicted."""
    return F.coalesce(F.lower(text).rlike("no (flaw|issue|problem|vulnerabilit)[a-z]* (was |were )?(found|detected|present)|none found|is (safe|not flawed)"), F.lit(False)) & predicted.isNotNull()


def repetition(text: Column, n: int = 3) -> Column:
    """Share of a text's n-word runs that repeat an earlier one; null for texts of fewer words."""
    share = lambda r: F.when(F.size(r) > 0, 1 - F.size(F.array_distinct(r)) / F.size(r))
    return F.element_at(F.transform(F.array(shingles(text, n)), share), 1)  # bound once, or the text would be split for every run


def specifications(evidence: DataFrame, key: str, class_col: str, text: str, most: int = 5) -> DataFrame:
    """key, dimension, criterion: one specification a sample, in the three dimensions of the rubric.

    Prediction holds the class; localization the sample's rarest terms, reasoning its most frequent ones (by document
    frequency over all samples), each as the criteria that an analysis must name. A language model's generator can take its place."""
    from pyspark.sql import Window as W

    terms = evidence.select(key, F.explode(F.regexp_extract_all(F.lower(text), F.lit("([a-z]+)"), F.lit(1))).alias("t"))
    tf = terms.groupBy(key, "t").agg(F.count("*").alias("f"))
    r = tf.join(tf.groupBy("t").agg(F.count("*").alias("df")), "t")
    pick = lambda dimension, *order: r.withColumn("k", F.row_number().over(W.partitionBy(key).orderBy(*order))).filter(F.col("k") <= most).select(key, F.lit(dimension).alias("dimension"), F.col("t").alias("criterion"))
    classes = evidence.select(key, F.lit("prediction").alias("dimension"), F.col(class_col).cast("string").alias("criterion"))
    return classes.unionByName(pick("localization", "df", F.desc("f"), "t")).unionByName(pick("reasoning", F.desc("f"), "df", "t"))


def rubric_scores(answers: DataFrame, specs: DataFrame, key: str, text: str, predicted: str) -> DataFrame:
    """answers with r1 (+1 if the predicted class is the specification's, else -1), and r2 and r3 (1, 0.5 or 0 as all, some or none of the
    dimension's criteria stand in the text)."""
    lists = specs.groupBy(key).pivot("dimension", ["prediction", "localization", "reasoning"]).agg(F.collect_set("criterion"))  # some terms a sample
    joined = answers.join(lists, key)
    share = lambda c: F.size(F.filter(c, lambda x: F.contains(F.lower(F.col(text)), x))) / F.size(c)
    step = lambda s: F.when(s >= 1, 1.0).when(s > 0, 0.5).otherwise(0.0)
    out = joined.withColumns({"r1": F.when(F.array_contains("prediction", F.col(predicted).cast("string")), 1.0).otherwise(-1.0), "r2": step(share("localization")), "r3": step(share("reasoning"))})
    return out.drop("prediction", "localization", "reasoning")
