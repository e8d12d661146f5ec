"""Soft-membership mixing to target domain weights, in DataFrame functions.

Domains are the label combinations of a labelled table.  A naive Bayes classifier over hashed words, counted on
a bounded sample of labelled rows, gives every document a posterior over the domains; long texts speak
with the voice of ``voice`` words at most, so memberships stay soft.  Rates r (expected copies of a document,
0 or more) then solve a least-squares problem: the rates times the documents' tokens times their posteriors
should add up to the targets.  Projected gradient steps run from r = 1; a step needs only one aggregation to
a vector of as many sums as domains, and a document's rate is a function of its posterior and the steps so far, so no
iterate is stored.  Residuals are weighted by the inverse Gram matrix, which makes steps of length one fast, and
rates move in the metric of their tokens, so equal posteriors get equal rates.

Targets: ``weights`` of the domains over a budget, the least one at which no domain of ``whole`` shrinks.

Defined results: null or empty text has no tokens and the prior as its posterior, and counts nothing towards
the targets; labels of domains without a weight are ignored; without labels all documents form one domain at rate 1;
rows that repeat get equal rates; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import json
import math
import warnings
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlab.llm.scratch import materialize

MOST_DOMAINS = 16


@dataclass(frozen=True)
class Mixture:
    weights: dict = field(default_factory=lambda: {"q1t0": 0.85, "q0t0": 0.10, "q1t1": 0.04, "q0t1": 0.01})
    whole: tuple = ("q1t0",)  # domains that must not shrink; empty: all
    buckets: int = 4096
    sample: int = 2_000  # labelled documents of each domain
    voice: float = 60.0
    steps: int = 25
    tolerance: float = 1e-4


def domain_of(quality: str = "quality", toxic: str = "toxic") -> Column:
    return F.concat(F.lit("q"), F.col(quality).cast("string"), F.lit("t"), F.col(toxic).cast("string"))


def _words(text: Column) -> Column:
    return F.filter(F.split(text, "[\\x20\\x09-\\x0D]+"), lambda w: w != "")


def _bucket(word: Column, buckets: int) -> Column:
    return F.pmod(F.xxhash64(F.lower(word)), F.lit(buckets)).cast("int")


def _literal(values: list[float]) -> Column:
    return F.from_json(F.lit(json.dumps(values)), "array<double>")


def classifier(docs: DataFrame, labels: DataFrame, m: Mixture) -> tuple[list[str], list[float], list[list[float]]]:
    """Domains, log priors (of all labelled rows), log likelihoods by domain and bucket."""
    rows = labels.select("doc_id", domain_of().alias("domain")).filter(F.col("domain").isin([d for d, w in m.weights.items() if w > 0]))
    sizes = {r["domain"]: r["n"] for r in rows.groupBy("domain").agg(F.count("*").alias("n")).limit(MOST_DOMAINS + 1).collect()}
    if len(sizes) > MOST_DOMAINS:
        raise ValueError(f"more than {MOST_DOMAINS} domains")
    domains = sorted(sizes)
    if not domains:
        return ["all"], [0.0], [[0.0] * m.buckets]
    share = {d: int(1000003 * min(1.0, 1.2 * m.sample / n)) for d, n in sizes.items()}
    picked = rows.filter(" OR ".join(f"(domain = '{d}' AND pmod(xxhash64(doc_id, 5), 1000003) <= {v})" for d, v in share.items()))
    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    words = texts.join(F.broadcast(picked.limit(2 * m.sample * len(domains))), "doc_id").select("domain", F.explode(_words(F.col("text"))).alias("w"))
    counts = words.groupBy("domain", _bucket(F.col("w"), m.buckets).alias("b")).agg(F.count("*").alias("c")).collect()  # domains x buckets rows at most
    table = {d: [0] * m.buckets for d in domains}
    for r in counts:
        table[r["domain"]][r["b"]] = r["c"]
    everything = [sum(table[d][b] for d in domains) for b in range(m.buckets)]
    whole = sum(everything) or 1
    like = []
    for d in domains:
        n = sum(table[d])
        like.append([math.log((table[d][b] + 20 * (everything[b] + 0.5) / (whole + 0.5 * m.buckets)) / (n + 20)) for b in range(m.buckets)])
    total = sum(sizes.values())
    # only differences count; the first domain is the base
    return domains, [math.log(sizes[d] / total) for d in domains], [[x - y for x, y in zip(row, like[0])] for row in like]


def memberships(docs: DataFrame, model: tuple, m: Mixture) -> DataFrame:
    """All columns of docs, with __n (tokens) and __p (posterior over the model's domains)."""
    domains, prior, like = model
    words = docs.withColumn("__b", F.transform(_words(F.coalesce("text", F.lit(""))), lambda w: _bucket(w, m.buckets)))
    scaled = F.lit(m.voice) / F.greatest(F.size("__b").cast("double"), F.lit(m.voice))
    tables = [None, *(_literal([round(x, 5) for x in row]) for row in like[1:])]

    def logit(k: int) -> Column:
        if not k:
            return F.lit(prior[0])
        return prior[k] + scaled * F.aggregate("__b", F.lit(0.0), lambda acc, b: acc + F.element_at(tables[k], b + 1))

    scored = words.select(*docs.columns, F.size("__b").cast("long").alias("__n"), F.array(*(logit(k) for k in range(len(domains)))).alias("__z"))
    top = F.array_max("__z")
    e = F.transform("__z", lambda z: F.exp(z - top))
    scored = scored.withColumn("__e", e)
    return scored.withColumn("__p", F.transform("__e", lambda x: x / F.aggregate("__e", F.lit(0.0), lambda acc, y: acc + y))).drop("__z", "__e")


def rate_of(history: list[list[float]], domains: int) -> Column:
    """A document's rate after the steps: r <- max(0, r - p . step), from 1."""
    out = F.lit(1.0)
    if not history:
        return out
    steps = F.from_json(F.lit(json.dumps(history)), "array<array<double>>")

    def moved(r: Column, step: Column) -> Column:
        dot = F.lit(0.0)
        for k in range(domains):
            dot = dot + F.element_at("__p", k + 1) * F.element_at(step, k + 1)
        return F.greatest(F.lit(0.0), r - dot)

    return F.aggregate(steps, out, moved)


def _solve(a: list[list[float]], b: list[float]) -> list[float]:
    """x of a x = b for a small positive matrix."""
    n = len(b)
    rows = [[*r, v] for r, v in zip(a, b)]
    for k in range(n):
        pivot = max(range(k, n), key=lambda i: abs(rows[i][k]))
        rows[k], rows[pivot] = rows[pivot], rows[k]
        for i in range(n):
            if i != k and rows[k][k]:
                f = rows[i][k] / rows[k][k]
                rows[i] = [x - f * y for x, y in zip(rows[i], rows[k])]
    return [rows[k][n] / rows[k][k] if rows[k][k] else 0.0 for k in range(n)]


def fit(member: DataFrame, domains: list[str], m: Mixture) -> tuple[list[list[float]], list[float], list[float]]:
    """Steps of the projected gradient, targets and the token totals that they reach; member has __n and __p."""
    k = len(domains)
    p = [F.element_at("__p", i + 1) for i in range(k)]
    first = member.agg(*(F.sum(F.col("__n") * x).alias(f"s{i}") for i, x in enumerate(p)), *(F.sum(F.col("__n") * p[i] * p[j]).alias(f"g{i}_{j}") for i in range(k) for j in range(i + 1))).first()
    have = [first[f"s{i}"] or 0.0 for i in range(k)]
    if not sum(have) or domains == ["all"]:
        return [], have, have
    gram = [[first[f"g{max(i, j)}_{min(i, j)}"] or 0.0 for j in range(k)] for i in range(k)]
    for i in range(k):
        gram[i][i] += 1e-9 * sum(gram[j][j] for j in range(k)) + 1e-12
    weight = [float(m.weights.get(d, 0.0)) for d in domains]
    weight = [w / (sum(weight) or 1.0) for w in weight]
    budget = max([h / w for d, h, w in zip(domains, have, weight) if w and (d in m.whole or not m.whole)], default=sum(have))
    target = [budget * w for w in weight]
    history: list[list[float]] = []
    reached = have
    for _ in range(m.steps):
        gap = [a - b for a, b in zip(reached, target)]
        if max(abs(g) for g in gap) <= m.tolerance * budget:
            break
        history.append(_solve(gram, gap))
        r = rate_of(history, k)
        row = member.agg(*(F.sum(F.col("__n") * x * r).alias(f"s{i}") for i, x in enumerate(p))).first()
        reached = [row[f"s{i}"] or 0.0 for i in range(k)]
    if max(abs(a - b) for a, b in zip(reached, target)) > m.tolerance * budget:
        warnings.warn(f"rates reach {reached} of the targets {target} in {m.steps} steps", stacklevel=2)
    return history, target, reached


def mix(docs: DataFrame, labels: DataFrame, m: Mixture = Mixture()) -> tuple[DataFrame, dict]:
    """doc_id, n_tokens, one posterior per domain (p_<domain>), rate, copies; and the fit's figures.

    copies rounds the rate down, or up with the chance of its fraction, by a hash of the row."""
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    model = classifier(slim, labels, m)
    member = memberships(slim, model, m)
    member = materialize(member.select("doc_id", F.xxhash64("doc_id", "text").alias("__h"), "__n", "__p"), "members")
    history, target, reached = fit(member, model[0], m)
    rated = member.withColumn("rate", rate_of(history, len(model[0])))
    out = rated.select("doc_id", F.col("__n").alias("n_tokens"), *(F.element_at("__p", i + 1).alias(f"p_{d}") for i, d in enumerate(model[0])), "rate", copies("rate", "__h").alias("copies"))
    return out, {"domains": model[0], "target": target, "reached": reached, "steps": len(history)}


def copies(rate: Column | str, row_hash: str) -> Column:
    rate = F.col(rate) if isinstance(rate, str) else rate
    part = F.pmod(F.xxhash64(F.col(row_hash), F.lit(17)), F.lit(1_000_003)) / F.lit(1_000_003.0)
    return (F.floor(rate) + (part < rate - F.floor(rate)).cast("long")).cast("long")


def resample(docs: DataFrame, labels: DataFrame, m: Mixture = Mixture()) -> DataFrame:
    """docs with each row as often as its copies say; all columns stay."""
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    model = classifier(slim, labels, m)
    row = F.struct(*(F.col(f"`{c}`") for c in docs.columns))
    member = memberships(docs.select(row.alias("row"), "text", F.xxhash64(F.col("doc_id").cast("long"), "text").alias("h")), model, m).drop("text")
    # written once: the fit reads two narrow columns, and no step of the rate scores a text again
    member = materialize(member, "members", codec="zstd")
    history, _, _ = fit(member.select("__n", "__p"), model[0], m)
    rated = member.withColumn("copies", copies(rate_of(history, len(model[0])), "h")).filter("copies > 0")
    return rated.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))).select(*(F.col(f"row.`{c}`") for c in docs.columns))
