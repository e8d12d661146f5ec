"""Substring deduplication by a relative Lempel-Ziv parse of every document against indexed reference blocks.

The references are the corpus itself, cut into blocks; the index is distributed and holds no text:

* Each window of ``window`` words picks the smallest hash of its ``gram``-word grams as its anchor.  Equal
  windows pick the same anchor, and successive windows that share an anchor form one reference block.
* The index knows every block under its anchor and the hash of its words, with two of its places (the first and
  last by a hash order).  A document's block that stands in the index elsewhere is matched as a whole.
* A block whose anchor recurs in different surroundings may hold the end of a duplicate.  There single windows are
  looked up, over one block of each kind, so a hot passage costs one row per block and never a pair.

A match says that words of the document equal those of a reference at one shift.  Matches of the same reference and
shift that follow each other are one.  The parse then walks a document from its first word: at each position it
takes the factor that reaches farthest among the matches there, and goes on behind it.  A factor of ``window`` words or
more is a duplicate span.  At its end the boundary is checked: if a window that straddles it matches, the words behind
it up to the window's end are a span, too (``boundary``), though what is left of that match is shorter than a window.
Thus the spans cover exactly the words of windows that occur twice or more.

Lookups are by 128 bits of hash (anchor and block, or two window hashes).  Keys that hold more than
1 / (2 * partitions) of the rows, of which there are 2 * partitions at most, are looked up by broadcast, so that no task
gets all rows of a hot one.

Defined results: null or empty text has no words and loses none; texts under ``window`` words lose none;
rows that repeat (same id or not) are occurrences of their own, so both lose their windows; extra columns
are ignored; an empty table gives an empty result; very long texts are processed in one piece each.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlab.llm import textbatch as tb
from pairlab.llm.scratch import materialize

_U = np.uint64


def _hashed(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, ...]:
    starts, ends, first = tb.words(buf, off)
    return starts, ends, first, tb.hash_spans(buf, starts, ends)


def block_table(h: np.ndarray, first: np.ndarray, window: int, gram: int) -> tuple[np.ndarray, ...]:
    """Per block: row, first window start in the row, number of windows, anchor hash, hash of all its words."""
    at, row = tb.window_starts(first, window)
    if not len(at):
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, _U),) * 2
    up, down = tb.powers(len(h) + 1)
    grams = tb.rolling(h, gram, up, down)
    width = window - gram + 1
    view = np.lib.stride_tricks.sliding_window_view(grams, width)
    anchor = view[at].argmin(axis=1) + at if len(at) * 2 < len(view) else view.argmin(axis=1)[at] + at
    new = np.ones(len(at), bool)
    new[1:] = (anchor[1:] != anchor[:-1]) | (row[1:] != row[:-1])
    k = np.flatnonzero(new)
    lo, n = at[k], np.diff(np.append(k, len(at)))
    total = np.concatenate([np.zeros(1, _U), np.cumsum(tb.mix(h) * up[: len(h)], dtype=_U)])
    body = tb.mix((total[lo + n + window - 1] - total[lo]) * down[lo])
    sig = tb.mix(body ^ tb.mix((n * 64 + anchor[k] - lo).astype(_U)))
    return row[k], lo - first[row[k]], n, grams[anchor[k]], sig


def _blocks(window: int, gram: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            k1, k2 = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("k1", "k2"))
            for a, b in tb.chunks(off):
                _, _, first, h = _hashed(buf[off[a] : off[b]], off[a : b + 1] - off[a])
                row, lo, n, anchor, sig = block_table(h, first, window, gram)
                yield pa.RecordBatch.from_arrays([pa.array(k1[a:b][row]), pa.array(k2[a:b][row]), pa.array(lo.astype(np.int32)), pa.array(n.astype(np.int32)), pa.array(anchor.view(np.int64)), pa.array(sig.view(np.int64))], names=["k1", "k2", "lo", "n", "anchor", "sig"])

    return run


def _ranges(column: pa.Array) -> tuple[np.ndarray, ...]:
    """Of a column of arrays of structs: entries per row, and all values of each field; a null array is empty."""
    lists = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    sizes = np.nan_to_num(pa.compute.list_value_length(lists).to_numpy(zero_copy_only=False).astype(float)).astype(np.int64)
    flat = lists.flatten()
    return sizes, *(flat.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in range(flat.type.num_fields))


def parse(lo: np.ndarray, n: np.ndarray, shift: np.ndarray, window: int) -> list[tuple[int, int, int, bool]]:
    """Greedy factors of one document: start, length, shift of the reference, and whether only a boundary check gives it.

    A match (lo, n, shift) says that the n windows from lo on stand in a reference too, shift places further."""
    order = np.lexsort((lo, shift))
    lo, n, shift = lo[order], n[order], shift[order]
    new = np.ones(len(lo), bool)
    new[1:] = (shift[1:] != shift[:-1]) | (lo[1:] != lo[:-1] + n[:-1])
    k = np.flatnonzero(new)
    begin, last, by = lo[k], (lo + n - 1)[np.append(k[1:], len(lo)) - 1], shift[k]
    order = np.argsort(begin, kind="stable")
    begin, last, by = begin[order].tolist(), last[order].tolist(), by[order].tolist()
    out, at, i = [], 0, 0
    while i < len(begin):
        at = max(at, begin[i])
        best = i
        while i < len(begin) and begin[i] <= at:
            best = i if last[i] > last[best] else best
            i += 1
        end = last[best] + window
        if end > at:
            out.append((at, end - at, by[best], last[best] < at))
            at = end
    return out


def _windows(window: int):
    """Hashes of the windows in the ranges of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            k1, k2 = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("k1", "k2"))
            sizes, lo, n = _ranges(batch.column("ranges"))
            upto = np.concatenate([[0], np.cumsum(sizes)])
            for a, b in tb.chunks(off):
                _, _, first, h = _hashed(buf[off[a] : off[b]], off[a : b + 1] - off[a])
                up, down = tb.powers(len(h) + 1)
                mine = slice(upto[a], upto[b])
                rows = np.repeat(np.repeat(np.arange(b - a), sizes[a:b]), n[mine])
                start = np.repeat(lo[mine], n[mine]) + tb.spread(n[mine])
                at = first[:-1][rows] + start
                w1, w2 = (tb.rolling(x, window, up, down)[at] if len(at) else np.zeros(0, _U) for x in (h, tb.mix(h + _U(1))))
                yield pa.RecordBatch.from_arrays([pa.array(k1[a:b][rows]), pa.array(k2[a:b][rows]), pa.array(start.astype(np.int32)), pa.array(w1.view(np.int64)), pa.array(w2.view(np.int64))], names=["k1", "k2", "lo", "w1", "w2"])

    return run


def _parsed(window: int, spans: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            sizes, lo, n, shift = _ranges(batch.column("ranges"))
            upto = np.concatenate([[0], np.cumsum(sizes)])
            for a, b in tb.chunks(off):
                part = buf[off[a] : off[b]]
                starts, ends, first = tb.words(part, off[a : b + 1] - off[a])
                gone, factors = np.zeros(len(starts), bool), []
                for i in range(a, b):
                    mine = slice(upto[i], upto[i + 1])
                    factors.append(parse(lo[mine], n[mine], shift[mine], window) if sizes[i] else [])
                    for start, length, _, _ in factors[-1]:
                        gone[first[i - a] + start : first[i - a] + start + length] = True
                removed = np.diff(np.concatenate([[0], np.cumsum(gone)])[first])
                digest, found = [], []
                # a space after every kept word, in one piece; each row's slice loses the last one
                width = np.where(gone, 0, ends - starts + 1)
                put = np.concatenate([[0], np.cumsum(width)])
                keep = np.flatnonzero(~gone)
                out = np.full(int(put[-1]), 32, np.uint8)
                length = ends[keep] - starts[keep]
                inner = tb.spread(length)
                out[np.repeat(put[keep], length) + inner] = part[np.repeat(starts[keep], length) + inner]
                text = memoryview(out.tobytes())
                for i in range(b - a):
                    s, e = put[first[i]], put[first[i + 1]]
                    digest.append(hashlib.sha256(text[s : max(s, e - 1)]).hexdigest())
                    if spans:
                        found.append([{"start": x, "length": y, "reference": x + s, "boundary": c} for x, y, s, c in factors[i]])
                columns = [batch.column("doc_id")[a:b], pa.array(np.diff(first)), pa.array(removed), pa.array(digest, pa.string())]
                names = ["doc_id", "n_words", "n_removed", "kept_sha256"]
                if spans:
                    columns += [pa.array(found, pa.list_(pa.struct([("start", pa.int64()), ("length", pa.int64()), ("reference", pa.int64()), ("boundary", pa.bool_())]))), pa.array([bytes(text[put[first[i]] : max(put[first[i]], put[first[i + 1]] - 1)]).decode() for i in range(b - a)], pa.string())]
                    names += ["spans", "kept_text"]
                yield pa.RecordBatch.from_arrays(columns, names=names)

    return run


def place(lo: str = "lo") -> Column:
    """Number of a word's place: successive words of a row have successive numbers, other rows' begin elsewhere in 62 bits."""
    return F.shiftrightunsigned(F.xxhash64("k1", "k2"), 2) + F.col(lo)


def _met(rows: DataFrame, known: DataFrame, *keys: str) -> DataFrame:
    """rows joined with known, which has c, the number of rows of each key. Hot keys meet by broadcast: their counts sum up to
    the rows' number, so at most 2 * partitions of them exceed the limit."""
    spark = rows.sparkSession
    total = known.agg(F.sum("c")).first()[0] or 0
    limit = max(10_000, total // (2 * int(spark.conf.get("spark.sql.shuffle.partitions"))))
    hot = F.broadcast(known.filter(F.col("c") > limit))
    if hot.isEmpty():
        return rows.join(known, [*keys])
    return rows.join(hot, [*keys]).unionByName(rows.join(hot, [*keys], "left_anti").join(known.filter(F.col("c") <= limit), [*keys]))


def dedup_substrings(docs: DataFrame, window: int = 35, gram: int = 8, spans: bool = False) -> DataFrame:
    """One row per document: doc_id, n_words, n_removed, kept_sha256; with spans also its factors (start and length in
    words, place of the reference as of ``place``, boundary) and the kept text.  See the module's docstring for the
    method and for special inputs."""
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    keyed = keyed.withColumns({"k1": F.coalesce("doc_id", F.lit(-1)), "k2": F.xxhash64("text")})
    blocks = materialize(keyed.select("k1", "k2", "text").mapInArrow(_blocks(window, gram), "k1 long, k2 long, lo int, n int, anchor long, sig long"), "blocks")
    known = blocks.groupBy("anchor").agg(F.count("*").alias("c"), F.min("sig").alias("sig_min"), F.max("sig").alias("sig_max")).filter("c > 1")
    known = materialize(known.select("anchor", "c", (F.col("sig_min") != F.col("sig_max")).alias("mixed")), "known")
    met = materialize(_met(blocks, known, "anchor").select("k1", "k2", "lo", "n", "anchor", "sig", "mixed"), "met")
    ends = F.min(place()).alias("first"), F.max(place()).alias("last")
    kinds = materialize(met.groupBy("anchor", "sig").agg(F.count("*").alias("c"), *ends), "kinds")
    # the reference is the first place of a kind, or the last one for the first itself
    here = F.col("first") == place()
    shift = F.when(here, F.col("last")).otherwise(F.col("first")) - F.col("lo")
    matched = _met(met, kinds, "anchor", "sig").select("k1", "k2", "lo", "n", (F.col("c") > 1).alias("whole"), (F.col("mixed") & here).alias("chosen"), shift.alias("shift"))
    matched = materialize(matched, "matched")
    ranges = lambda df, *columns: df.groupBy("k1", "k2").agg(F.collect_set(F.struct(*columns)).alias("ranges"))  # noqa: E731  as many entries as the document has words at most
    asked = ranges(matched.filter("chosen"), "lo", "n")
    windows = keyed.join(asked.hint("shuffle_hash"), ["k1", "k2"]).select("k1", "k2", "text", "ranges")
    windows = materialize(windows.mapInArrow(_windows(window), "k1 long, k2 long, lo int, w1 long, w2 long"), "windows")
    twice = materialize(windows.groupBy("w1", "w2").agg(F.count("*").alias("c"), *ends).filter("c > 1"), "twice")
    single = _met(windows, twice, "w1", "w2").select("k1", "k2", "lo", F.lit(1).alias("n"), shift.alias("shift"))
    found = ranges(matched.filter("whole").select("k1", "k2", "lo", "n", "shift").union(single), "lo", "n", "shift")
    columns = "doc_id long, n_words long, n_removed long, kept_sha256 string"
    if spans:
        columns += ", spans array<struct<start:long,length:long,reference:long,boundary:boolean>>, kept_text string"
    return keyed.join(found.hint("shuffle_hash"), ["k1", "k2"], "left").select("doc_id", "text", "ranges").mapInArrow(_parsed(window, spans), columns)
