"""The network against a scalar form, its windows, its inputs' order, whole training texts, and the pipeline's filter."""

import math

import numpy as np
import pyarrow as pa

from pairlab.llm import textbatch as tb
from pairlab.llm import toxicity


def small(**k):
    s = toxicity.Settings(size=6, hidden=3, words=2, chars=2, groups=64, **k)
    return toxicity.Network(s, np.zeros(0, np.uint64))


def score_of(net, text):
    buf, off = tb.utf8(pa.array([text], pa.string()))
    return float(net.scores(buf, off)[0])


def plain_score(net, words):
    """Score of a text of words, window by window and unit by unit."""
    p, h, s = net.p, net.s.hidden, net.s
    if not words:
        return 0.5
    best = None
    starts = [0] + ([k for k in range(s.size // 2, len(words), s.size // 2) if k < len(words) and k - s.size // 2 + s.size < len(words)] if len(words) > s.size else [])
    sig = lambda x: 1 / (1 + math.exp(-x))
    for at in starts:
        rows = []
        for w in words[at : at + s.size]:
            raw = w.encode()
            buf = np.frombuffer(raw, np.uint8)
            ids, weight, _ = toxicity.grams(buf, np.array([0]), np.array([len(raw)]), s.groups)
            char = sum(p["C"][i] * c for i, c in zip(ids, weight))
            rows.append(np.concatenate([p["W"][0], char]) @ p["X"] + p["b"])
        states = []
        for d in (0, 1):
            order = range(len(rows)) if d == 0 else range(len(rows) - 1, -1, -1)
            state, out = [0.0] * h, {}
            u = p["U"][d]
            for t in order:
                x = rows[t][3 * h * d : 3 * h * (d + 1)]
                dot = lambda col: sum(state[k] * u[k, col] for k in range(h))  # noqa: B023, E731
                z = [sig(x[j] + dot(j)) for j in range(h)]
                r = [sig(x[h + j] + dot(h + j)) for j in range(h)]
                c = [math.tanh(x[2 * h + j] + r[j] * dot(2 * h + j)) for j in range(h)]
                state = [z[j] * state[j] + (1 - z[j]) * c[j] for j in range(h)]
                out[t] = state
            states.append(out)
        both = [np.array(states[0][t] + states[1][t]) for t in range(len(rows))]
        e = [float(np.tanh(v @ p["A"]) @ p["v"]) for v in both]
        a = np.exp(np.array(e) - max(e))
        logit = float((a / a.sum()) @ np.stack(both) @ p["o"]) + float(p["k"][0])
        best = logit if best is None else max(best, logit)
    return sig(best)


def test_scores_equal_a_scalar_network():
    net = small()
    for n in (0, 1, 5, 6, 7, 9, 10, 14, 23):
        words = [f"w{k}x" * (1 + k % 3) for k in range(n)]
        assert abs(score_of(net, " ".join(words)) - plain_score(net, words)) < 1e-5, n


def test_windows_cover_every_word():
    for n in range(0, 70):
        at, length, row = toxicity.windows(np.array([0, n]), 8)
        seen = {k for a, c in zip(at, length) for k in range(a, a + c)}
        assert seen == set(range(n)) and all(b - a == 4 for a, b in zip(at, at[1:])) and len(at) == len(row)


def test_characters_keep_their_order():
    net = small()
    assert abs(score_of(net, "listen") - score_of(net, "silent")) > 1e-6


def test_passage_at_the_end_of_a_long_text_trains(spark):
    clean, bad = "alpha beta gamma delta " * 900, "vile nasty awful crude " * 3
    rows = [(k, clean + (bad if k % 2 else "mild gentle kind soft " * 3) + clean[:400]) for k in range(80)] + [(901, None), (902, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(k, k % 2) for k in range(80)], "doc_id long, toxic int")
    model = toxicity.train(docs, labels, settings=toxicity.Settings(sample=50, epochs=4, steps=150, least=2))
    got = {r.doc_id: r.score for r in toxicity.score(docs, model).collect()}
    assert all((got[k] >= 0.5) == (k % 2 == 1) for k in range(80)) and got[901] == got[902]
    wide = docs.selectExpr("*", "1 as score", "2 as label", "3 as n")
    kept = toxicity.keep(wide, model)
    assert kept.columns == wide.columns and sorted(r.doc_id for r in kept.collect() if r.doc_id < 900) == [*range(0, 80, 2)]
    assert toxicity.keep(wide.limit(0), model).count() == 0


def test_held_out_accuracy(spark):
    from pairlab.llm import queries

    sf = "/root/testdata/sf0.1"
    lab = spark.read.parquet(sf + "/labels.parquet")
    rows = queries.op1_toxicity(spark, sf).filter("held_out").join(lab, "doc_id").groupBy("toxic", "predicted").count().collect()
    n = {(r.toxic, r.predicted): r["count"] for r in rows}
    assert n[1, 1] >= 0.88 * (n[1, 1] + n.get((1, 0), 0)) and n[1, 1] >= 0.85 * (n[1, 1] + n.get((0, 1), 0)), n
