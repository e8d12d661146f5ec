"""Objective values over token log-probability arrays; every row's work is local, only scalars are shuffled."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlab.functions.scores import log_odds, log_sigmoid, mean_of, sum_of


def sft(lp: Column) -> Column:
    return mean_of(lp)


def dpo(chosen: Column, chosen_ref: Column, rejected: Column, rejected_ref: Column, beta: float = 0.1, length_norm: bool = True) -> Column:
    s = mean_of if length_norm else sum_of
    return log_sigmoid(beta * ((s(chosen) - s(chosen_ref)) - (s(rejected) - s(rejected_ref))))


def orpo(chosen: Column, rejected: Column, beta: float = 0.1, seq_prob: str = "mean") -> Column:
    s = mean_of if seq_prob == "mean" else sum_of
    return mean_of(chosen) + beta * log_sigmoid(log_odds(s(chosen)) - log_odds(s(rejected)))


def token_term(theta: str, old: str, ref: str, advantage: str, clip: float = 0.2, beta: float = 0.0, kl: str = "k3", on_policy: bool = False) -> Column:
    """Mean over tokens of the clipped surrogate less beta times the divergence; unused arrays are not read."""
    a = F.col(advantage)

    def surrogate(lp: Column, before: Column) -> Column:
        r = F.exp(lp - before)
        return F.least(r * a, F.greatest(F.lit(1 - clip), F.least(F.lit(1 + clip), r)) * a)

    gain = a if on_policy else mean_of(F.zip_with(theta, old, surrogate))
    if not beta:
        return gain
    delta = F.zip_with(theta, ref, lambda x, y: x - y)
    return gain - beta * mean_of(F.transform(delta, (lambda d: F.exp(-d) - 1 + d) if kl == "k3" else (lambda d: d)))


def group_relative(rows: DataFrame, group: str, **options) -> DataFrame:
    """group, n, value: mean over the group's responses (columns theta, old, ref, advantage)."""
    return rows.withColumn("__v", token_term("theta", "old", "ref", "advantage", **options)).groupBy(group).agg(F.count("*").alias("n"), F.avg("__v").alias("value"))
