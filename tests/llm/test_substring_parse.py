"""The relative Lempel-Ziv parse: factors are true copies, hot rows take no square time."""

import random
import time

import numpy as np
from pyspark.sql import functions as F

from pairlab.llm import rlz_dedup


def test_greedy_takes_the_farthest_factor():
    of = lambda *m: rlz_dedup.parse(*(np.array(x, np.int64) for x in zip(*m)), 5)
    # two neighbours of one shift are one factor; another reference at the same start reaches less far
    assert of((0, 3, 100), (3, 4, 100), (0, 2, 900)) == [(0, 11, 100, False)]
    # the second match holds no window that starts behind the first factor: only the boundary check gives its end
    assert of((0, 3, 100), (3, 4, 200)) == [(0, 7, 100, False), (7, 4, 200, True)]
    # a literal gap, then a factor
    assert of((0, 1, 7), (20, 1, 7)) == [(0, 5, 7, False), (20, 5, 7, False)]


def test_factors_are_copies_of_their_references(spark):
    g = random.Random(2)
    pool = [[str(g.randrange(50)) for _ in range(g.randint(30, 90))] for _ in range(6)]
    texts = [" ".join(sum((g.choice(pool)[g.randrange(10) :] if g.random() < 0.6 else [f"u{g.random()}"] * 1 for _ in range(8)), [])) for _ in range(40)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    at = {r.h: r.doc_id for r in docs.withColumns({"k1": F.col("doc_id"), "k2": F.xxhash64("text"), "lo": F.lit(0)}).select("doc_id", rlz_dedup.place().alias("h")).collect()}
    starts = sorted(at)
    some = 0
    for r in rlz_dedup.dedup_substrings(docs, window=12, gram=4, spans=True).collect():
        words, gone = texts[r.doc_id].split(), set()
        for f in r.spans:
            h = starts[int(np.searchsorted(starts, f.reference, side="right")) - 1]
            there, lo = texts[at[h]].split(), f.reference - h
            assert words[f.start : f.start + f.length] == there[lo : lo + f.length] and (at[h], lo) != (r.doc_id, f.start)
            assert f.boundary or f.length >= 12
            gone |= set(range(f.start, f.start + f.length))
            some += 1
        assert r.n_removed == len(gone) and r.kept_text == " ".join(w for k, w in enumerate(words) if k not in gone)
    assert some > 50


def test_repeated_rows_take_linear_time(spark):
    text = " ".join(f"w{k % 350}" for k in range(400))
    took = []
    for n in (400, 3200):
        for i in (None, 7):
            rows = spark.createDataFrame([(i, text)] * n, "doc_id long, text string")
            began = time.time()
            assert [tuple(r) for r in rlz_dedup.dedup_substrings(rows).groupBy("n_words", "n_removed").count().collect()] == [(400, 400, n)]
            took.append(time.time() - began)
    assert max(took[2:]) < 4 * max(took[:2]) + 5


def test_hot_keys_meet_by_broadcast(spark):
    rows = spark.range(30_000).select(F.when(F.col("id") < 25_000, 1).otherwise(F.col("id")).alias("k"), "id")
    known = rows.groupBy("k").agg(F.count("*").alias("c"))
    assert rlz_dedup._met(rows, known, "k").groupBy("k", "c").count().filter("c <> count").isEmpty()
    assert rlz_dedup._met(rows, known, "k").count() == 30_000
