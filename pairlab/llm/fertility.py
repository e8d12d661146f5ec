"""Tokeniser fertility as a quality rule.

Public vocabularies cut every word of a text (words stand alone, led by one space); three measures per
vocabulary describe the cut: code points per token, share of tokens that stand for single bytes of a
character the vocabulary lacks (byte fallback), and entropy of the text's tokens over the logarithm of their number.
Bands per language (the ``lang`` column where it names one of ``LANGUAGES``, else the script of most letters)
are fitted over all documents: the quartiles widened by ``spread`` times their distance.  A document is
rejected if it lies outside a band of its group, or fails the base rule.  Texts of under ``least`` tokens give
no reliable measures; only the base rule judges them.

Defined results: null or empty text has no words, all counts 0, fails the base rule; a null lang counts as
none of LANGUAGES; rows that repeat get equal results; extra columns are ignored; an empty table gives an
empty result.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlab.llm import textbatch as tb
from pairlab.llm.scratch import materialize

_U = np.uint64
LANGUAGES = ("en", "de", "fr", "es", "it", "pt", "nl", "pl", "ru", "uk", "ar", "fa", "he", "hi", "zh", "ja", "ko", "tr", "vi", "id")
#: First bytes of UTF-8 sequences, by rough script.
SCRIPTS = {"latin": (0xC3, 0xC6), "greek": (0xCD, 0xD0), "cyrillic": (0xD0, 0xD4), "semitic": (0xD6, 0xDC), "indic": (0xE0, 0xE2), "cjk": (0xE3, 0xEE)}
MEASURES = ("chars_per_token", "fallback_share", "entropy")
BASE = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, script string"


class Vocabulary:
    """Cuts distinct words; kind "piece" (a SentencePiece model) or "ranks" (a tiktoken rank file)."""

    def __init__(self, name: str, path: str):
        self.name, self.size = name, 0
        if path.endswith(".model"):
            import sentencepiece

            self.sp = sentencepiece.SentencePieceProcessor(model_file=path)
            self.size = self.sp.get_piece_size()
            self.fallback = np.array([self.sp.is_byte(k) or self.sp.is_unknown(k) for k in range(self.size)])
            self.cut = lambda words: self.sp.encode(words, num_threads=1)
        else:
            import public_tokenizers
            import tiktoken

            with open(path, "rb") as f:
                ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
            code = tiktoken.Encoding(name, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
            self.size = max(ranks.values()) + 1
            self.fallback = np.zeros(self.size, bool)
            for token, k in ranks.items():
                self.fallback[k] = len(token) == 1 and token[0] >= 128
            self.cut = lambda words: [code.encode_ordinary(" " + w) for w in words]


def paths(folder: str | None = None) -> dict[str, str]:
    """Files of the vocabularies used by default; folder: where they lie, else where public_tokenizers has them."""
    names = {"piece": "piece_bpe_32k.model", "ranks": "byte_bpe_multi_50k.tiktoken"}
    if folder:
        return {k: f"{folder}/{v}" for k, v in names.items()}
    import public_tokenizers

    return {k: str(public_tokenizers.path(v)) for k, v in names.items()}


def base_counts(buf: np.ndarray, off: np.ndarray) -> tuple[dict[str, np.ndarray], tuple]:
    """The base rule's counts by row, and starts, ends, hashes and rows' first words."""
    n = len(off) - 1
    starts, ends, first = tb.words(buf, off)
    h = tb.hash_spans(buf, starts, ends)
    tail = np.concatenate([[0], np.cumsum((buf & 0xC0) == 0x80)])
    chars = ends - starts - (tail[ends] - tail[starts])
    by = lambda x, at: np.diff(np.concatenate([[0], np.cumsum(x)])[at])
    symbol = np.zeros(256, bool)
    symbol[list(b"#*$%&|<>")] = True
    symbols = np.diff(np.searchsorted(np.flatnonzero(symbol[buf]), off))
    row = np.repeat(np.arange(n), np.diff(first))
    # lines with a word, equal to an earlier one of the text
    newline = np.zeros(256, bool)
    newline[10] = True
    ls, le, lf = tb.words(buf, off, newline)
    inside = np.concatenate([[0], np.cumsum(~tb.SPACE[buf])])
    full = inside[le] > inside[ls]
    lrow = np.repeat(np.arange(n), np.diff(lf))[full]
    _, kind = np.unique(tb.mix(tb.hash_spans(buf, ls[full], le[full]) ^ tb.mix(lrow.astype(_U))), return_index=True)
    lines, kinds = np.bincount(lrow, minlength=n), np.bincount(lrow[kind], minlength=n)
    # words of 3-word windows that the text holds twice or more
    at, wrow = tb.window_starts(first, 3)
    cover = np.zeros(len(h) + 3, bool)
    if len(at):
        mixed = tb.mix(tb.ngrams(h, 3)[at] ^ tb.mix(wrow.astype(_U)))
        order = np.argsort(mixed)
        same = mixed[order][1:] == mixed[order][:-1]
        again = np.zeros(len(at), bool)
        again[order[1:][same]] = again[order[:-1][same]] = True
        for k in range(3):
            cover[at[again] + k] = True
    lead = np.zeros(256, np.uint8)
    for k, (a, b) in enumerate(SCRIPTS.values(), 1):
        lead[a:b] = k
    lead[[*range(65, 91), *range(97, 123)]] = 1
    kind = lead[buf]
    count = np.stack([np.bincount(kind[off[i] : off[i + 1]], minlength=len(SCRIPTS) + 1)[1:] for i in range(n)]) if n else np.zeros((0, len(SCRIPTS)), np.int64)
    script = np.where(count.max(1, initial=0) > 0, np.array(list(SCRIPTS))[count.argmax(1)], "none")
    out = {"n_words": np.diff(first), "word_chars": by(chars, first), "n_symbols": symbols, "n_dup_lines": lines - kinds, "n_repeat_words": by(cover[: len(h)], first), "script": script}
    return out, (starts, ends, first, h, chars, row)


def _measures(vocabulary: Vocabulary, raw: bytes, starts, ends, first, which: np.ndarray, pick: np.ndarray, chars) -> np.ndarray:
    """Rows x (tokens, code points per token, fallback share, entropy). pick: a place of each distinct word; which: each word's number among them."""
    n = len(first) - 1
    cut = vocabulary.cut([raw[starts[k] : ends[k]].decode("utf-8", "replace") for k in pick])
    size = np.fromiter(map(len, cut), np.int64, len(cut))
    flat = np.fromiter(chain.from_iterable(cut), np.int32, int(size.sum()))
    begin = np.cumsum(size) - size
    per = size[which]
    bounds = np.concatenate([[0], np.cumsum(per)])
    total = np.diff(bounds[first])
    token = flat[np.repeat(begin[which], per) + tb.spread(per)]
    row = np.repeat(np.arange(n, dtype=np.int32 if n * vocabulary.size < 2**31 else np.int64), total)
    fallback = np.bincount(row[vocabulary.fallback[token]], minlength=n)
    key = np.sort(row * vocabulary.size + token)
    new = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
    count = np.diff(np.append(new, len(key)))
    of = key[new] // vocabulary.size
    safe = np.maximum(total, 1)
    # entropy of the counts, log2 n - sum(c log2 c) / n
    spread = np.log2(safe) - np.bincount(of, count * np.log2(np.maximum(count, 1)), n) / safe
    points = np.diff(np.concatenate([[0], np.cumsum(chars)])[first])
    return np.stack([total, points / safe, fallback / safe, spread / np.log2(np.maximum(safe, 2))], 1)


_loaded: dict[tuple, list[Vocabulary]] = {}


def measure(docs: DataFrame, vocabularies: dict[str, str]) -> DataFrame:
    """doc_id, lang, the base counts, script, and for each vocabulary <name>_tokens and <name>_<measure>."""
    named = tuple(vocabularies.items())
    columns = [f"{name}_{m}" for name, _ in named for m in ("tokens", *MEASURES)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if named not in _loaded:  # once a worker
            _loaded[named] = [Vocabulary(*x) for x in named]
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            for a, b in tb.chunks(off, 10_000_000):  # large, so that many words are known already
                part = buf[off[a] : off[b]]
                base, (starts, ends, first, h, chars, _) = base_counts(part, off[a : b + 1] - off[a])
                _, pick, which = np.unique(h, return_index=True, return_inverse=True)
                raw = part.tobytes()
                got = [_measures(v, raw, starts, ends, first, which, pick, chars) for v in _loaded[named]]
                arrays = [batch.column("doc_id")[a:b], batch.column("lang")[a:b], *(pa.array(base[k]) for k in list(base)[:-1]), pa.array(base["script"].tolist(), pa.string())]
                arrays += [pa.array(x[:, k], pa.float64()) for x in got for k in range(4)]
                yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "lang", *base, *columns])

    schema = f"doc_id long, lang string, {BASE}, " + ", ".join(f"{c} double" for c in columns)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), "text").mapInArrow(run, schema)


def fertility_rules(docs: DataFrame, vocabularies: dict[str, str] | None = None, spread: float = 6.0, least: int = 50) -> DataFrame:
    """doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, the group and all measures.

    Bands come from all documents that they judge: those of a group that hold ``least`` tokens or more and pass the
    base rule.  A group without such a document has no band, and none of its documents needs one."""
    vocabularies = vocabularies or paths()
    groups = [*LANGUAGES, *SCRIPTS, "none"]
    group = F.when(F.col("lang").isin(*LANGUAGES), F.col("lang")).otherwise(F.col("script"))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    measured = materialize(measure(docs, vocabularies).withColumns({"group": group, "base_failed": failed}), "fertility")
    names = [f"{v}_{m}" for v in vocabularies for m in MEASURES]
    first = next(iter(vocabularies))
    quartiles = measured.filter(f"not base_failed and {first}_tokens >= {least}").groupBy("group").agg(*(F.percentile_approx(c, [0.25, 0.75], 1000).alias(c) for c in names))
    bands = {r["group"]: r for r in quartiles.collect()}  # at most len(groups) rows
    assert len(bands) <= len(groups)
    #: The least width of a band on each side of the quartiles, so that a uniform corpus rejects nothing.
    floor = {"chars_per_token": 0.4, "fallback_share": 0.05, "entropy": 0.08}
    outside = F.lit(False)
    for key, r in bands.items():
        bad = F.lit(False)
        for c in names:
            q1, q3 = r[c]
            room = max(spread * (q3 - q1), floor[c.split("_", 1)[1]])
            bad = bad | ~F.col(c).between(q1 - room, q3 + room)
        outside = outside | ((F.col("group") == key) & bad)
    long_enough = F.col(f"{first}_tokens") >= least
    kept = ~F.col("base_failed") & ~(long_enough & outside)
    base = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"]
    return measured.select(*base, kept.alias("kept"), "group", *(c for c in measured.columns if c.split("_", 1)[0] in vocabularies))
