"""Quality scores: a generalised additive model with pairwise interactions.

Each text gives ``FEATURES``, figures of its bytes, words and lines.  Features are binned at quantiles of the
training sample.  Boosting goes round the features: each step fits a shallow tree (``leaves`` leaves over one
feature's bins, at the best cuts for the Newton gain) to the current residuals, and adds it, shrunk, to that
feature's lookup table.  Then the pairs of features with the largest residual gain get tables over pairs of
bins, filled by the same cyclic boosting with trees of one cut in each direction.  A score is the logistic of
the intercept and one table entry per feature and pair, added for all rows at once.

Defined results: null or empty text has all features 0 and is scored by the tables like any other; rows that
repeat get equal scores; extra columns are ignored; an empty table gives an empty result.  Without labels of
both classes every score is the share of label 1 (0 without labels).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from pairlab.llm import textbatch as tb
from pyspark.sql import functions as F

_U = np.uint64
FEATURES = (
    "log_chars", "log_words", "word_length", "upper_share", "digit_share", "symbol_share", "shout_share", "stop_share", "bar_share",
    "not_ascii_share", "line_length", "repeat_word_share", "repeat_line_share", "distinct_share", "same_next_share", "longest_word",
)


def _class(text: bytes) -> np.ndarray:
    t = np.zeros(256, np.int64)
    t[list(text)] = 1
    return t


_CLASSES = {
    "upper": _class(bytes(range(65, 91))), "digit": _class(b"0123456789"), "symbol": _class(b"#*$%&<>@^~_={}[]\\/"), "shout": _class(b"!?"), "stop": _class(b".,;:"),
    "bar": _class(b"|"), "high": _class(bytes(range(128, 256))), "tail": _class(bytes(range(128, 192))), "line": _class(b"\n"),
}


def _again(key: np.ndarray, row: np.ndarray) -> np.ndarray:
    """Whether the row holds the key more than once."""
    mixed = tb.mix(key ^ tb.mix(row.astype(_U)))
    order = np.argsort(mixed, kind="stable")
    s = mixed[order]
    same = np.zeros(len(s) + 1, bool)
    same[1:-1] = s[1:] == s[:-1]
    out = np.zeros(len(s), bool)
    out[order] = same[1:] | same[:-1]
    return out


def features(buf: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Rows x FEATURES."""
    n = len(off) - 1
    total = lambda x: np.diff(np.concatenate([[0], np.cumsum(x)])[off])
    count = {k: total(t[buf]) for k, t in _CLASSES.items()}
    chars = np.diff(off) - count["tail"]
    per_char = np.maximum(chars, 1)
    starts, ends, first = tb.words(buf, off)
    words = np.diff(first)
    per_word = np.maximum(words, 1)
    row = np.repeat(np.arange(n), words)
    h = tb.hash_spans(buf, starts, ends)
    by_row = lambda x: np.diff(np.concatenate([[0], np.cumsum(x)])[first])
    at, window_row = tb.window_starts(first, 3)
    again = _again(tb.ngrams(h, 3)[at], window_row) if len(at) else np.zeros(0, bool)
    cover = np.zeros(len(h) + 1, np.int64)
    for k in range(3):
        np.add.at(cover, at[again] + k, 1)
    same = np.zeros(len(h), bool)
    same[1:] = (h[1:] == h[:-1]) & (row[1:] == row[:-1])
    alone = ~_again(h, row) if len(h) else np.zeros(0, bool)
    line = np.ones(256, bool)
    line[:] = False
    line[10] = True
    ls, le, lf = tb.words(buf, off, line)
    lines = np.diff(lf)
    twice = _again(tb.hash_spans(buf, ls, le), np.repeat(np.arange(n), lines)) if len(ls) else np.zeros(0, bool)
    line_bytes = np.diff(np.concatenate([[0], np.cumsum((le - ls) * twice)])[lf])
    longest = np.zeros(n)
    if len(h):
        has = np.flatnonzero(words)
        longest[has] = np.maximum.reduceat(ends - starts, first[has])
    inside = total(~tb.SPACE[buf]) - by_row(np.diff(np.concatenate([[0], np.cumsum(_CLASSES["tail"][buf])])[np.stack([starts, ends], 1).ravel()])[::2] if len(starts) else np.zeros(0))
    return np.stack([
        np.log1p(chars), np.log1p(words), inside / per_word, count["upper"] / per_char, count["digit"] / per_char, count["symbol"] / per_char, count["shout"] / per_char, count["stop"] / per_char, count["bar"] / per_char,
        count["high"] / np.maximum(np.diff(off), 1), np.log1p(chars / np.maximum(lines, 1)), by_row(cover[:-1] > 0) / per_word, line_bytes / np.maximum(np.diff(off), 1), by_row(alone) / per_word, by_row(same) / per_word, np.log1p(longest),
    ], 1).astype(np.float64)


@dataclass(frozen=True)
class Settings:
    bins: int = 48
    pair_bins: int = 12
    leaves: int = 4
    rounds: int = 60
    pairs: int = 6
    pair_rounds: int = 25
    shrink: float = 0.15
    ridge: float = 2.0  # added to each leaf's second derivative
    sample: int = 4_000  # labelled documents of each class


@dataclass
class Model:
    """Lookup tables: a feature's bin by its cuts; single[f][bin]; double[(f, g)][bin of f, bin of g]."""

    base: float
    cuts: list
    single: list
    pair_cuts: list
    double: dict

    def scores(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.base)
        for f, table in enumerate(self.single):
            z += table[np.searchsorted(self.cuts[f], x[:, f])]
        for (f, g), table in self.double.items():
            z += table[np.searchsorted(self.pair_cuts[f], x[:, f]), np.searchsorted(self.pair_cuts[g], x[:, g])]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _tree(g: np.ndarray, h: np.ndarray, leaves: int, ridge: float) -> np.ndarray:
    """Values by bin of the tree with so many leaves, grown by best gain; g, h: sums of derivatives by bin."""
    edges, gs, hs = [0, len(g)], np.concatenate([[0], np.cumsum(g)]), np.concatenate([[0], np.cumsum(h)])
    gain = lambda a, b: (gs[b] - gs[a]) ** 2 / (hs[b] - hs[a] + ridge)
    while len(edges) <= leaves:
        best = (1e-9, None)
        for a, b in zip(edges, edges[1:]):
            c = np.arange(a + 1, b)
            if len(c) and (won := gain(a, c) + gain(c, b) - gain(a, b)).max() > best[0]:
                best = (won.max(), int(c[won.argmax()]))
        if best[1] is None:
            break
        edges = sorted([*edges, best[1]])
    out = np.zeros(len(g))
    for a, b in zip(edges, edges[1:]):
        out[a:b] = -(gs[b] - gs[a]) / (hs[b] - hs[a] + ridge)
    return out


def _cross(g: np.ndarray, h: np.ndarray, ridge: float) -> tuple[float, np.ndarray]:
    """Gain and values of the best tree with one cut in each direction over a table of derivative sums."""
    cum = lambda x: np.pad(x.cumsum(0).cumsum(1), ((1, 0), (1, 0)))
    G, H = cum(g), cum(h)
    i, j = np.arange(1, g.shape[0])[:, None], np.arange(1, g.shape[1])[None]
    parts = []
    for C in (G, H):
        a = C[i, j]
        b, c = C[i, -1] - a, C[-1, j] - a
        parts.append((a, b, c, C[-1, -1] - a - b - c))
    won = sum(x * x / (y + ridge) for x, y in zip(*parts))
    k = np.unravel_index(won.argmax(), won.shape)
    values = [-x[k] / (y[k] + ridge) for x, y in zip(*parts)]
    out = np.empty(g.shape)
    r, s = k[0] + 1, k[1] + 1
    out[:r, :s], out[:r, s:], out[r:, :s], out[r:, s:] = values
    return float(won[k] - G[-1, -1] ** 2 / (H[-1, -1] + ridge)), out


def fit(x: np.ndarray, y: np.ndarray, s: Settings = Settings(), prior: float | None = None) -> Model | float:
    y = np.asarray(y, float)
    if len(set(y.tolist())) < 2:
        return float(prior if prior is not None else (y.mean() if len(y) else 0.0))
    cut = lambda k: [np.unique(np.quantile(x[:, f], np.linspace(0, 1, k + 1)[1:-1])) for f in range(x.shape[1])]
    cuts, pair_cuts = cut(s.bins), cut(s.pair_bins)
    bins = [np.searchsorted(c, x[:, f]) for f, c in enumerate(cuts)]
    base = float(np.log(y.mean() / (1 - y.mean())))
    z = np.full(len(y), base)
    single = [np.zeros(len(c) + 1) for c in cuts]

    def slopes():
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        return p - y, p * (1 - p)

    for _ in range(s.rounds):
        for f, b in enumerate(bins):
            g, h = slopes()
            n = len(single[f])
            step = s.shrink * _tree(np.bincount(b, g, n), np.bincount(b, h, n), s.leaves, s.ridge)
            single[f] += step
            z += step[b]
    wide = [np.searchsorted(c, x[:, f]) for f, c in enumerate(pair_cuts)]
    shape = [len(c) + 1 for c in pair_cuts]

    def table(f: int, k: int):
        g, h = slopes()
        at, size = wide[f] * shape[k] + wide[k], shape[f] * shape[k]
        return (np.bincount(at, v, size).reshape(shape[f], shape[k]) for v in (g, h))

    able = [(f, k) for f in range(len(cuts)) for k in range(f) if shape[f] > 1 and shape[k] > 1]
    ranked = sorted(able, key=lambda fk: (-_cross(*table(*fk), s.ridge)[0], fk))[: s.pairs]
    double = {fk: np.zeros((shape[fk[0]], shape[fk[1]])) for fk in ranked}
    for _ in range(s.pair_rounds):
        for f, k in ranked:
            step = s.shrink * _cross(*table(f, k), s.ridge)[1]
            double[f, k] += step
            z += step[wide[f], wide[k]]
    if prior is not None and 0 < prior < 1:
        base += float(np.log(prior / (1 - prior)) - np.log(y.mean() / (1 - y.mean())))
    return Model(base, cuts, single, pair_cuts, double)


def _columns(texts: list[str]) -> np.ndarray:
    buf, off = tb.utf8(pa.array(texts, pa.string()))
    parts = [features(buf[off[a] : off[b]], off[a : b + 1] - off[a]) for a, b in tb.chunks(off)]
    return np.concatenate(parts) if parts else np.zeros((0, len(FEATURES)))


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", settings: Settings = Settings()) -> Model | float:
    """Model of the labelled rows outside the held-out fifth: at most settings.sample of each class, chosen by
    a hash; their features, not their texts, come to the driver."""
    from pairlab.llm.toxicity import held_out

    rows = labels.select(F.col("doc_id"), F.col(label).cast("int").alias("label")).filter(F.col("label").isin(0, 1) & ~held_out())
    counts = {r["label"]: r["n"] for r in rows.groupBy("label").agg(F.count("*").alias("n")).collect()}
    share = {k: int(1000003 * min(1.0, 1.3 * settings.sample / max(1, n))) for k, n in counts.items()}
    picked = rows.filter(" OR ".join(f"(label = {k} AND pmod(xxhash64(doc_id, 11), 1000003) <= {v})" for k, v in share.items()) or "false")
    picked = picked.orderBy(F.xxhash64("doc_id", F.lit(11))).limit(int(2.6 * settings.sample) + 50)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            for a, b in tb.chunks(off):
                x = features(buf[off[a] : off[b]], off[a : b + 1] - off[a])
                yield pa.RecordBatch.from_arrays([batch.column("doc_id")[a:b], batch.column("label")[a:b], pa.array(list(x), pa.list_(pa.float64()))], names=["doc_id", "label", "x"])

    texts = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    got = texts.join(F.broadcast(picked), "doc_id").select("doc_id", "label", "text").mapInArrow(run, "doc_id long, label int, x array<double>").toPandas()
    got = got.sort_values(["doc_id", "label"]).groupby("label").head(settings.sample)
    total = sum(counts.values())
    x = np.stack(got["x"].tolist()) if len(got) else np.zeros((0, len(FEATURES)))
    return fit(x, got["label"].to_numpy(), settings, counts.get(1, 0) / total if total else 0.0)


def score(docs: DataFrame, model: Model | float) -> DataFrame:
    """doc_id, score of every document."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)  # tables of Settings' size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shipped.value
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            for a, b in tb.chunks(off):
                value = np.full(b - a, m) if isinstance(m, float) else m.scores(features(buf[off[a] : off[b]], off[a : b + 1] - off[a]))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id")[a:b], pa.array(value, pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")
