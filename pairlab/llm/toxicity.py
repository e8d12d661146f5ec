"""Toxicity scores: a bidirectional gated recurrent network with attention pooling, trained in numpy.

Input of each step is a word as a whole (an embedding of the words known from training, one more for all
others) and as characters in their order (embeddings of its byte trigrams, with marks at both ends, averaged, and of its
first four and six bytes).  A text is scored in windows of ``size`` words, each starting ``size / 2`` words after the
last; all windows of all texts are scored, and the document gets the highest score.

Training sees a bounded sample (``Settings.sample`` documents a class, by a hash of the id) of labelled rows with their whole texts, which
stay in a shared table: in each epoch executors pick from a toxic document the window that the current model finds
most toxic (the label says only that one exists), from others a random one and the worst one, and only these windows
go to the driver.  Before there is a model, summed log odds of the known words stand for it.

Defined results: null or empty text, or one without any word, scores the share of label 1; rows that
repeat get equal scores; extra columns are ignored; an empty table gives an empty result; a null id is in no
labelled row, and its held_out is null.  Without labels of both classes every score is the share of label 1 (0 without labels).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlab.llm import textbatch as tb
from pairlab.llm.scratch import materialize

_U = np.uint64
SEPARATOR = np.ones(256, dtype=bool)
SEPARATOR[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False


@dataclass(frozen=True)
class Settings:
    size: int = 32  # words in a window
    hidden: int = 8  # units of each direction
    words: int = 8  # width of a word's embedding
    chars: int = 6  # width of a character group's embedding
    groups: int = 8192  # hashed trigrams, and as many hashed beginnings
    vocabulary: int = 20_000
    least: int = 5  # documents of the sample that a known word occurs in
    sample: int = 1_500  # documents of each class
    epochs: int = 8
    steps: int = 400  # at least; a small sample's windows are read several times an epoch
    rate: float = 0.01
    seed: int = 7


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def tokens(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, ...]:
    low = tb.lower_ascii(buf)
    starts, ends, first = tb.words(low, off, SEPARATOR)
    return low, starts, ends, first, tb.hash_spans(low, starts, ends)


def windows(first: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, length and row of all windows; a row without words has none."""
    n, step = np.diff(first), size // 2
    per = np.where(n == 0, 0, 1 + np.maximum(0, -(-(n - size) // step)))
    row = np.repeat(np.arange(len(n)), per)
    at = tb.spread(per) * step
    return first[:-1][row] + at, np.minimum(size, n[row] - at), row


class Network:
    """Weights p: W (words x 8), C (2 groups x 6), X (14 x 6H), b (6H), U (2, H, 3H), A (2H x 2H), v (2H), o (2H), k (1)."""

    def __init__(self, s: Settings, known: np.ndarray):
        self.s, self.known, self.blank = s, known, 0.0  # sorted hashes, word 0 is any other; logit of a text without words
        g, h = np.random.default_rng(s.seed), s.hidden
        scaled = lambda *shape, by=None: (g.normal(size=shape) / np.sqrt(by or shape[-2])).astype(np.float32)
        self.p = {
            "W": 0.3 * scaled(len(known) + 1, s.words, by=1), "C": 0.3 * scaled(2 * s.groups, s.chars, by=1), "X": scaled(s.words + s.chars, 6 * h), "b": np.zeros(6 * h, np.float32),
            "U": scaled(2, h, 3 * h), "A": scaled(2 * h, 2 * h), "v": scaled(2 * h, by=2 * h), "o": scaled(2 * h, by=2 * h), "k": np.zeros(1, np.float32),
        }

    def ids(self, hashes: np.ndarray) -> np.ndarray:
        if not len(self.known):
            return np.zeros(len(hashes), np.int64)
        at = np.minimum(np.searchsorted(self.known, hashes), len(self.known) - 1)
        return np.where(self.known[at] == hashes, at + 1, 0)

    def characters(self, buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Character input of each word."""
        if not len(starts):
            return np.zeros((0, self.s.chars), np.float32)
        ids, weight, begin = grams(buf, starts, ends, self.s.groups)
        return np.add.reduceat(self.p["C"][ids] * weight[:, None], begin, axis=0)

    def forward(self, x: np.ndarray, length: np.ndarray, keep: bool = False):
        """x: steps x windows x 6H, the inputs' part of the gates. Logits; with keep also what backward needs."""
        steps, n, h = x.shape[0], x.shape[1], self.s.hidden
        live = (np.arange(steps)[:, None] < length[None]).astype(np.float32)[:, :, None]
        out, trace = np.zeros((steps, n, 2 * h), np.float32), ([], [])
        for d in (0, 1):
            u, state = self.p["U"][d], np.zeros((n, h), np.float32)
            for t in range(steps) if d == 0 else range(steps - 1, -1, -1):
                xt = x[t, :, 3 * h * d : 3 * h * (d + 1)]
                m = live[t]
                gates = _sigmoid(xt[:, : 2 * h] + state @ u[:, : 2 * h])
                z, r = gates[:, :h], gates[:, h:]
                inner = state @ u[:, 2 * h :]
                c = np.tanh(xt[:, 2 * h :] + r * inner)
                new = state + m * (1 - z) * (c - state)
                if keep:
                    trace[d].append((t, state, z, r, c, inner))
                state = new
                out[t, :, h * d : h * (d + 1)] = state
        q = np.tanh(out @ self.p["A"])
        e = q @ self.p["v"] + np.where(live[:, :, 0] > 0, 0, -1e9).astype(np.float32)
        a = np.exp(e - e.max(0))
        a /= a.sum(0)
        pooled = (a[:, :, None] * out).sum(0)
        logit = pooled @ self.p["o"] + self.p["k"][0]
        return (logit, (live, out, trace, q, a, pooled)) if keep else logit

    def backward(self, x: np.ndarray, kept, err: np.ndarray) -> tuple[dict, np.ndarray]:
        """err: gradient of the loss by logit. Gradients of p's recurrent part, and by x."""
        live, out, trace, q, a, pooled = kept
        h, p = self.s.hidden, self.p
        grad = {k: np.zeros_like(p[k]) for k in ("U", "A", "v", "o", "k")}
        grad["o"], grad["k"] = pooled.T @ err, np.array([err.sum()], np.float32)
        by_pooled = err[:, None] * p["o"][None]
        by_a = (out * by_pooled[None]).sum(2)
        by_e = a * (by_a - (a * by_a).sum(0))
        grad["v"] = np.einsum("tnk,tn->k", q, by_e)
        by_q = by_e[:, :, None] * p["v"] * (1 - q * q)
        grad["A"] = np.einsum("tni,tnj->ij", out, by_q)
        by_out = a[:, :, None] * by_pooled[None] + by_q @ p["A"].T
        by_x = np.zeros_like(x)
        for d in (0, 1):
            u, carry = p["U"][d], np.zeros((x.shape[1], h), np.float32)
            for t, state, z, r, c, inner in reversed(trace[d]):
                carry = carry + by_out[t, :, h * d : h * (d + 1)]
                m = live[t]
                by_c = carry * m * (1 - z) * (1 - c * c)
                by_z = carry * m * (state - c) * z * (1 - z)
                by_r = by_c * inner * r * (1 - r)
                by_inner = by_c * r
                g = np.concatenate([by_z, by_r], 1)
                grad["U"][d][:, : 2 * h] += state.T @ g
                grad["U"][d][:, 2 * h :] += state.T @ by_inner
                by_x[t, :, 3 * h * d : 3 * h * (d + 1)] = np.concatenate([g, by_c], 1)
                carry = carry * (1 - m * (1 - z)) + g @ u[:, : 2 * h].T + by_inner @ u[:, 2 * h :].T
        return grad, by_x

    def rows(self, buf: np.ndarray, off: np.ndarray, part: int = 2048) -> tuple[np.ndarray, tuple]:
        """Logits of all windows of all rows, and the windows."""
        low, starts, ends, first, hashes = tokens(buf, off)
        at, length, row = windows(first, self.s.size)
        logit = np.zeros(len(at), np.float32)
        word = self.ids(hashes)
        _, some, of = np.unique(hashes, return_index=True, return_inverse=True)
        chars = self.characters(low, starts[some], ends[some])
        w, s = self.s.words, self.s.size
        by_word = self.p["W"] @ self.p["X"][:w] + self.p["b"]
        by_chars = chars @ self.p["X"][w:]
        step = np.arange(s)[:, None]
        for a in range(0, len(at), part):
            i = np.minimum(at[None, a : a + part] + step, len(word) - 1)
            logit[a : a + part] = self.forward(by_word[word[i]] + by_chars[of[i]], length[a : a + part])
        return logit, (at, length, row)

    def scores(self, buf: np.ndarray, off: np.ndarray) -> np.ndarray:
        logit, (_, _, row) = self.rows(buf, off)
        best = np.full(len(off) - 1, self.blank, np.float32)
        if len(row):
            new = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]]))
            best[row[new]] = np.maximum.reduceat(logit, new)
        return _sigmoid(best.astype(np.float64))


def grams(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray, groups: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Character groups of words: their rows in C, weights, and where each word's begin. A word has its trigrams in equal parts,
    and its first four and six bytes with weight one."""
    n = ends - starts
    size = n + 2  # n trigrams of the word between two marks, two beginnings
    begin = np.cumsum(size) - size
    inner = tb.spread(n)
    at = np.repeat(starts, n) + inner
    left = np.where(inner == 0, 2, buf[np.maximum(at - 1, 0)])
    right = np.where(inner == np.repeat(n, n) - 1, 3, buf[np.minimum(at + 1, len(buf) - 1)])
    code = (left.astype(_U) << _U(16)) | (buf[at].astype(_U) << _U(8)) | right.astype(_U)
    ids = np.zeros(int(size.sum()), np.int64)
    weight = np.ones(len(ids), np.float32)
    place = np.repeat(begin, n) + inner
    ids[place] = (tb.mix(code + _U(1)) % _U(groups)).astype(np.int64)
    weight[place] = np.repeat(1 / n, n)
    for k, first in ((0, 4), (1, 6)):
        ids[begin + n + k] = groups + (tb.hash_spans(buf, starts, np.minimum(ends, starts + first)) % _U(groups)).astype(np.int64)
    return ids, weight, begin


def fit(pick, known: np.ndarray, s: Settings = Settings(), prior: float | None = None) -> Network:
    """Network trained on windows; pick(epoch, network) gives texts of windows and their labels, known is sorted word hashes.
    prior: the share of label 1 in all rows, if the windows have another."""
    net = Network(s, known)
    g = np.random.default_rng(s.seed)
    moment = {k: [np.zeros_like(v), np.zeros_like(v)] for k, v in net.p.items()}
    count, seen = 0, 0.5
    for epoch in range(s.epochs):
        texts, label = pick(epoch, net)
        label = np.asarray(label, np.float32)
        buf, off = tb.utf8(pa.array(texts, pa.string()))
        low, starts, ends, first, hashes = tokens(buf, off)
        word, at, length = net.ids(hashes), first[:-1], np.minimum(np.diff(first), s.size)
        use = np.flatnonzero(length > 0)
        if not len(use):
            return net
        seen = float(label[use].mean())
        times = max(1, -(-s.steps // (s.epochs * -(-len(use) // 64))))
        use = np.concatenate([g.permutation(use) for _ in range(times)])
        rate = s.rate * (1 - epoch / s.epochs) + 1e-4
        for a in range(0, len(use), 64):
            w = use[a : a + 64]
            i = np.minimum(at[w][None] + np.arange(s.size)[:, None], len(word) - 1)
            ids = word[i]
            ids = np.where(g.random(ids.shape) < 0.05, 0, ids)  # so that the word for all others is trained, too
            flat = i.ravel()
            group, weight, begin = grams(low, starts[flat], ends[flat], s.groups)
            chars = np.add.reduceat(net.p["C"][group] * weight[:, None], begin, axis=0)
            inputs = np.concatenate([net.p["W"][ids.ravel()], chars], 1)
            x = (inputs @ net.p["X"] + net.p["b"]).reshape(s.size, len(w), -1)
            logit, kept = net.forward(x, length[w], keep=True)
            err = ((_sigmoid(logit) - label[w]) / len(w)).astype(np.float32)
            grad, by_x = net.backward(x, kept, err)
            by_x = by_x.reshape(len(flat), -1)
            grad["X"], grad["b"] = inputs.T @ by_x, by_x.sum(0)
            by_in = by_x @ net.p["X"].T
            grad["W"] = np.zeros_like(net.p["W"])
            np.add.at(grad["W"], ids.ravel(), by_in[:, : s.words])
            grad["C"] = np.zeros_like(net.p["C"])
            np.add.at(grad["C"], group, np.repeat(by_in[:, s.words :], np.diff(np.append(begin, len(group))), axis=0) * weight[:, None])
            count += 1
            for k, v in net.p.items():
                m = moment[k]
                m[0] = 0.9 * m[0] + 0.1 * grad[k]
                m[1] = 0.999 * m[1] + 0.001 * grad[k] ** 2
                v -= (rate * (m[0] / (1 - 0.9**count) / (np.sqrt(m[1] / (1 - 0.999**count)) + 1e-8) + 1e-3 * v)).astype(np.float32)
    if prior is not None and 0 < prior < 1 and 0 < seen < 1:
        net.blank = float(np.log(prior / (1 - prior)))
        net.p["k"] = net.p["k"] + np.float32(np.log(prior / (1 - prior)) - np.log(seen / (1 - seen)))
    return net


def held_out(doc_id: str = "doc_id"):
    return F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(5)) == 0


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, per_class: int) -> tuple[DataFrame, dict[int, int]]:
    """doc_id, label and whole text of at most per_class labelled rows of each class outside the held-out fifth, the first by a
    hash of the id, as a written table; and the number of all such rows of each class. Of an id's rows one counts."""
    rows = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("label")).filter(F.col("label").isin(0, 1) & ~held_out())
    counts = {r["label"]: r["n"] for r in rows.groupBy("label").agg(F.count("*").alias("n")).collect()}
    picked = [rows.filter(F.col("label") == k).orderBy(F.xxhash64("doc_id", F.lit(11)), "doc_id").limit(per_class) for k in (0, 1)]
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    got = texts.join(F.broadcast(picked[0].union(picked[1])), "doc_id").groupBy("doc_id", "label").agg(F.min("text").alias("text"))
    return materialize(got, "labelled"), counts


def _distinct_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """label and hash of each word of a text, once."""
    for batch in batches:
        buf, off = tb.utf8(batch.column("text"))
        label = batch.column("label").to_numpy()
        for a, b in tb.chunks(off):
            _, _, _, first, hashes = tokens(buf[off[a] : off[b]], off[a : b + 1] - off[a])
            row = np.repeat(np.arange(b - a), np.diff(first))
            order = np.lexsort((hashes, row))
            hashes, row = hashes[order], row[order]
            new = np.ones(len(row), bool)
            new[1:] = (hashes[1:] != hashes[:-1]) | (row[1:] != row[:-1])
            yield pa.RecordBatch.from_arrays([pa.array(label[a:b][row[new]]), pa.array(hashes[new].view(np.int64))], names=["label", "word"])


def _window_picker(model, size: int, epoch: int):
    """Of each text the window that model(buf, off) scores highest, and, if its label is 0, one drawn at random."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            label, doc = batch.column("label").to_numpy(), batch.column("doc_id").to_numpy()
            for a, b in tb.chunks(off, 1_500_000):
                part, cut = buf[off[a] : off[b]], off[a : b + 1] - off[a]
                logit, at, length, row = model(part, cut)
                low, starts, ends, _, _ = tokens(part, cut)
                new = np.flatnonzero(np.concatenate([[True], row[1:] != row[:-1]])) if len(row) else np.zeros(0, np.int64)
                n = np.diff(np.append(new, len(row)))
                texts, labels = [], []
                for k, c in zip(new, n):
                    i = row[k]
                    chosen = [k + int(np.argmax(logit[k : k + c]))]
                    if label[a + i] == 0:
                        chosen.append(k + int(tb.mix(np.array([doc[a + i] * 64 + epoch], np.int64).view(_U))[0] % _U(c)))
                    for w in chosen:
                        texts.append(low[starts[at[w]] : ends[at[w] + length[w] - 1]].tobytes().decode(errors="replace"))
                        labels.append(int(label[a + i]))
                yield pa.RecordBatch.from_arrays([pa.array(texts, pa.string()), pa.array(labels, pa.int32())], names=["text", "label"])

    return run


def _by_odds(known: np.ndarray, odds: np.ndarray, size: int):
    """Scores of windows by the highest log odds of a known word in them."""

    def run(buf: np.ndarray, off: np.ndarray):
        _, _, _, first, hashes = tokens(buf, off)
        at, length, row = windows(first, size)
        if not len(at):
            return np.zeros(0), at, length, row
        place = np.minimum(np.searchsorted(known, hashes), max(0, len(known) - 1))
        value = np.append(np.where(known[place] == hashes, odds[place], -9.0) if len(known) else np.full(len(hashes), -9.0), -9.0)
        return np.maximum.reduceat(value, np.stack([at, at + length], 1).ravel())[::2], at, length, row

    return run


def _by_network(net: Network):
    def run(buf: np.ndarray, off: np.ndarray):
        logit, (at, length, row) = net.rows(buf, off)
        return logit, at, length, row

    return run


def score(docs: DataFrame, model: Network | float) -> DataFrame:
    """doc_id, score of every document."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)  # a few MB at most: Settings bounds it

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = shipped.value
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            for a, b in tb.chunks(off, 1_500_000):
                value = np.full(b - a, net) if isinstance(net, float) else net.scores(buf[off[a] : off[b]], off[a : b + 1] - off[a])
                yield pa.RecordBatch.from_arrays([batch.column("doc_id")[a:b], pa.array(value, pa.float64())], names=["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")


def train(docs: DataFrame, labels: DataFrame, label: str = "toxic", settings: Settings = Settings()) -> Network | float:
    sample, counts = labelled_sample(docs, labels, label, settings.sample)
    total = sum(counts.values())
    sizes = {r["label"]: r["n"] for r in sample.groupBy("label").agg(F.count("*").alias("n")).collect()}
    if len(sizes) < 2:
        return counts.get(1, 0) / total if total else 0.0
    words = sample.select("label", "text").mapInArrow(_distinct_words, "label int, word long").groupBy("word").agg(F.count("*").alias("n"), F.sum("label").alias("n1"))
    top = words.filter(F.col("n") >= settings.least).orderBy(F.desc("n"), "word").limit(settings.vocabulary).collect()
    known = np.array([r["word"] for r in top], np.int64).view(_U)
    n1, n = np.array([r["n1"] for r in top], float), np.array([r["n"] for r in top], float)
    odds = np.log((n1 + 0.5) / (sizes[1] + 1)) - np.log((n - n1 + 0.5) / (sizes[0] + 1))
    order = np.argsort(known)
    known, odds = known[order], odds[order]

    def pick(epoch: int, net: Network) -> tuple[list[str], list[int]]:
        model = _by_odds(known, odds, settings.size) if epoch < 2 else _by_network(net)
        got = sample.mapInArrow(_window_picker(model, settings.size, epoch), "text string, label int").toPandas()  # three windows a sampled pair of documents at most
        got = got.sort_values(["text", "label"])  # the same order on every run
        return got["text"].tolist(), got["label"].tolist()

    return fit(pick, known, settings, counts.get(1, 0) / total)


def keep(docs: DataFrame, model: Network | float, below: float = 0.5) -> DataFrame:
    """The rows of docs, all columns as they are, whose text scores under ``below``."""
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = shipped.value
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            for a, b in tb.chunks(off, 1_500_000):
                value = np.full(b - a, net) if isinstance(net, float) else net.scores(buf[off[a] : off[b]], off[a : b + 1] - off[a])
                yield batch.slice(a, b - a).filter(pa.array(value < below))

    return docs.mapInArrow(run, docs.schema)
