"""SentencePiece-style encoding: Unigram Viterbi over a double-array trie, with byte fallback.

The pieces come from a public SentencePiece model.  Its merge model has ranks for scores, so the log score of
the piece at rank r is taken from Zipf's law, -log(r + 1) - log H(n); a model of unigram type keeps its own scores
(``Pieces.load``).  A text's spaces become the marker U+2581, one marker is set in front, and the text is
cut after each run of markers and word, which no piece crosses; each distinct part is cut once per block of
texts by the Viterbi recursion, run for all parts of one length at a time in numpy.  A character that
no piece covers costs ``unknown`` and becomes one token per UTF-8 byte.  The marker itself, where a text
holds it, is encoded by its bytes, so that decoding gives back every text.

Ties in score go to the longer last piece, then nothing is left to choose.

Defined results: null or empty text has no tokens and decodes to the empty text; rows that repeat get equal
results; extra columns are ignored; an empty table gives an empty result; very long texts and very long words
need memory in proportion to their length.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlab.llm import textbatch as tb

MARK = "▁".encode()


class DoubleArray:
    """Trie over byte strings: the child of state s by byte c is base[s] + c if check[there] is s."""

    def __init__(self, keys: dict[bytes, int]):
        tree: list[dict[int, int]] = [{}]
        value = [-1]
        for key, v in keys.items():
            at = 0
            for c in key:
                if c not in tree[at]:
                    tree[at][c] = len(tree)
                    tree.append({})
                    value.append(-1)
                at = tree[at][c]
            value[at] = v
        size = 32 * len(tree) + 8192
        base, check, out = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
        place, used, cursor = {0: 0}, np.zeros(size, bool), [1] * 16
        used[0] = True
        todo, k = [0], 0
        while k < len(todo):
            node = todo[k]
            k += 1
            s = place[node]
            out[s] = value[node]
            if not tree[node]:
                base[s] = -1
                continue
            codes = np.fromiter(tree[node], np.int64)
            c0, kind = int(codes.min()), min(len(codes), 15)
            at, b = max(cursor[kind], c0 + 1), 0
            while not b:  # the first place that suits all children, from where nodes of as many children lie
                free = at + np.flatnonzero(~used[at : at + 512])
                fits = free[~used[free[:, None] - c0 + codes].any(1)]
                b = int(fits[0]) - c0 if len(fits) else 0
                at += 512
            cursor[kind] = b + c0
            base[s] = b
            used[b + codes] = True
            check[b + codes] = s
            for c, child in tree[node].items():
                place[child] = b + c
                todo.append(child)
        end = int(np.flatnonzero(used)[-1]) + 257
        self.base, self.check, self.out = base[:end], check[:end], out[:end]

    def step(self, state: np.ndarray, byte: np.ndarray) -> np.ndarray:
        """Next states; -1 where there is none."""
        to = np.maximum(self.base[state], 0) + byte
        return np.where((self.check[to] == state) & (self.base[state] > 0), to, -1)


@dataclass
class Pieces:
    text: list[bytes]  # by id; what the piece stands for, with markers; bytes of byte pieces
    score: np.ndarray
    byte: np.ndarray  # ids of the 256 byte pieces
    trie: DoubleArray
    longest: int
    unknown: float

    @classmethod
    def build(cls, text: list[bytes], score: np.ndarray, byte: np.ndarray, usable: np.ndarray) -> Pieces:
        keys = {text[k]: int(k) for k in np.flatnonzero(usable) if text[k]}
        # no piece may hold a marker after another character: parts end there
        keys = {t: k for t, k in keys.items() if MARK not in t.lstrip(MARK) or not t.lstrip(MARK)}
        lowest = min((score[k] for k in keys.values()), default=0.0)
        return cls(text, score, byte, DoubleArray(keys), max(map(len, keys), default=1), float(lowest - 10.0))

    @classmethod
    def load(cls, path: str) -> Pieces:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        byte, text, usable = np.full(256, -1), [], np.zeros(n, bool)
        for k in range(n):
            piece = sp.id_to_piece(k)
            if sp.is_byte(k):
                byte[int(piece[3:5], 16)] = k
                text.append(bytes([int(piece[3:5], 16)]))
            elif sp.is_control(k) or sp.is_unknown(k) or sp.is_unused(k):
                text.append(b"")
            else:
                text.append(piece.encode())
                usable[k] = True
        score = np.array([sp.get_score(k) for k in range(n)], float)
        ranks = np.sort(-score[usable])
        if len(ranks) > 1 and np.array_equal(ranks, np.round(ranks)):  # a merge model
            order = np.argsort(-score[usable], kind="stable")
            zipf = np.empty(len(order))
            zipf[order] = -np.log(np.arange(len(order)) + 1.0) - np.log((1 / (np.arange(len(order)) + 1.0)).sum())
            score[usable] = zipf
        return cls.build(text, score, byte, usable)


def marked(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Texts with markers for spaces and one in front (empty texts stay empty): bytes, offsets, and which
    bytes are of markers set here."""
    space = buf == 32
    some = np.diff(off) > 0
    width = np.where(space, 3, 1)
    lead = np.zeros(len(buf) + 1, np.int64)
    np.add.at(lead, off[:-1][some], 3)
    end = np.cumsum(width + lead[:-1]) if len(buf) else np.zeros(0, np.int64)
    total = int(end[-1]) if len(buf) else 0
    out = np.zeros(total, np.uint8)
    ours = np.zeros(total, bool)
    put = end - width
    out[put[~space]] = buf[~space]
    for at in (put[space], put[off[:-1][some]] - 3):
        for k in range(3):
            out[at + k] = MARK[k]
            ours[at + k] = True
    return out, np.concatenate([[0], end])[off], ours


def parts_of(buf: np.ndarray, off: np.ndarray, ours: np.ndarray) -> np.ndarray:
    """Starts of the parts: at each text's start, and at a marker that follows no marker."""
    first = ours & (buf == MARK[0])
    after = np.zeros(len(buf), bool)
    after[1:] = ours[:-1]
    begin = first & ~after
    begin[off[:-1][np.diff(off) > 0]] = True
    return np.flatnonzero(begin)


def viterbi(p: Pieces, parts: np.ndarray, ours: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of each row of parts (rows x length bytes; ours: which bytes are markers of ours): all ids, and ids per row.

    Where a text's own marker occurs, no piece may be used over it."""
    n, length = parts.shape
    lead = (parts & 0xC0) != 0x80
    width = np.select([parts < 0x80, parts < 0xE0, parts < 0xF0], [1, 2, 3], 4)
    foreign = (parts == MARK[0]) & ~ours
    if length >= 3:
        foreign[:, :-2] &= (parts[:, 1:-1] == MARK[1]) & (parts[:, 2:] == MARK[2])
        foreign[:, -2:] = False
    else:
        foreign[:] = False
    best = np.full((n, length + 1), -np.inf)
    best[:, 0] = 0
    back = np.zeros((n, length + 1), np.int32)
    token = np.full((n, length + 1), -1, np.int32)
    rows = np.arange(n)
    for i in range(length):
        live = rows[lead[:, i]]
        if not len(live):
            continue
        state, at = np.zeros(len(live), np.int32), live
        from_score = best[:, i]
        for j in range(i, min(length, i + p.longest)):
            go = ~foreign[at, j]
            at, state = at[go], state[go]
            state = p.trie.step(state, parts[at, j])
            ok = state >= 0
            at, state = at[ok], state[ok]
            if not len(at):
                break
            piece = p.trie.out[state]
            has = piece >= 0
            r, v = at[has], piece[has]
            s = from_score[r] + p.score[v]
            up = s > best[r, j + 1]
            r, v = r[up], v[up]
            best[r, j + 1], back[r, j + 1], token[r, j + 1] = s[up], i, v
        end = np.minimum(i + width[live, i], length)
        s = best[live, i] + p.unknown
        up = s > best[live, end]
        r, e = live[up], end[up]
        best[r, e], back[r, e], token[r, e] = s[up], i, -1
    # from the end: a token per piece, one per byte of an uncovered character
    mark = np.full((n, length), -1, np.int32)  # id at the piece's first byte
    at = np.full(n, length)
    live = rows[at > 0]
    while len(live):
        e = at[live]
        s, v = back[live, e], token[live, e]
        whole = v >= 0
        mark[live[whole], s[whole]] = v[whole]
        for k in range(4):
            some = ~whole & (s + k < e)
            mark[live[some], s[some] + k] = p.byte[parts[live[some], s[some] + k]]
        at[live] = s
        live = live[s > 0]
    chosen = mark >= 0
    return mark[chosen], chosen.sum(1)


def encode(p: Pieces, buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts, and where each text's begin (one more entry than texts)."""
    text, at, ours = marked(buf, off)
    begin = parts_of(text, at, ours)
    if not len(begin):
        return np.zeros(0, np.int32), np.zeros(len(off), np.int64)
    end = np.append(begin[1:], len(text))
    h = tb.hash_spans(text, begin, end) + tb.mix(np.logical_and.reduceat(ours | (text != MARK[0]), begin).astype(np.uint64))
    _, pick, which = np.unique(h, return_index=True, return_inverse=True)
    size = (end - begin)[pick]
    order = np.argsort(size, kind="stable")
    count = np.zeros(len(pick), np.int64)
    ids: list[np.ndarray] = []
    edges = np.flatnonzero(np.concatenate([[True], np.diff(size[order]) > 0, [True]]))
    for a, b in zip(edges, edges[1:]):
        length = int(size[order[a]])
        step = max(1, 4_000_000 // (length + 1))
        for c in range(a, b, step):
            which_parts = order[c : min(b, c + step)]
            grid = begin[pick[which_parts]][:, None] + np.arange(length)
            got, per = viterbi(p, text[grid], ours[grid])
            ids.append(got)
            count[which_parts] = per
    flat = np.concatenate(ids)
    start = np.empty(len(pick), np.int64)
    start[order] = np.cumsum(count[order]) - count[order]
    per = count[which]
    out = flat[np.repeat(start[which], per) + tb.spread(per)]
    total = np.concatenate([[0], np.cumsum(per)])
    return out.astype(np.int32), total[np.searchsorted(begin, at)]


def decode(p: Pieces, ids: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets of the texts: pieces with markers as spaces, bytes as such, less the space in front."""
    whole = set(p.byte.tolist())
    table = [t if k in whole else t.replace(MARK, b" ") for k, t in enumerate(p.text)]
    size = np.array([len(t) for t in table])
    start = np.cumsum(size) - size
    raw = np.frombuffer(b"".join(table), np.uint8)
    per = size[ids]
    out = raw[np.repeat(start[ids], per) + tb.spread(per)]
    off = np.concatenate([[0], np.cumsum(per)])[first]
    keep = np.ones(len(out), bool)
    keep[off[:-1][np.diff(off) > 0]] = False
    return out[keep], np.concatenate([[0], np.cumsum(keep)])[off]


_loaded: dict[str, Pieces] = {}


def pieces(path: str) -> Pieces:
    if path not in _loaded:
        _loaded[path] = Pieces.load(path)
    return _loaded[path]


def default_path() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("piece_bpe_32k.model"))


def encode_documents(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, n_byte_tokens, round_trip (whether decoding gives the text back), ids."""
    path = path or default_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = pieces(path)
        fallback = np.zeros(len(p.text), bool)
        fallback[p.byte[p.byte >= 0]] = True
        for batch in batches:
            buf, off = tb.utf8(batch.column("text"))
            for a, b in tb.chunks(off, 6_000_000):
                part, at = buf[off[a] : off[b]], off[a : b + 1] - off[a]
                ids, first = encode(p, part, at)
                back, back_at = decode(p, ids, first)
                same = np.diff(back_at) == np.diff(at)
                if not (len(back) == len(part) and same.all() and np.array_equal(back, part)):
                    same = np.array([back[back_at[k] : back_at[k + 1]].tobytes() == part[at[k] : at[k + 1]].tobytes() for k in range(b - a)], bool)
                bytes_used = np.diff(np.concatenate([[0], np.cumsum(fallback[ids])])[first])
                lists = pa.ListArray.from_arrays(pa.array(first.astype(np.int32)), pa.array(ids))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id")[a:b], pa.array(np.diff(first)), pa.array(bytes_used), pa.array(same), lists], names=["doc_id", "n_tokens", "n_byte_tokens", "round_trip", "ids"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_tokens long, n_byte_tokens long, round_trip boolean, ids array<int>")


def decode_documents(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, text of rows with doc_id, ids; null ids decode to the empty text."""
    path = path or default_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = pieces(path)
        for batch in batches:
            lists = batch.column("ids")
            per = np.nan_to_num(pa.compute.list_value_length(lists).to_numpy(zero_copy_only=False).astype(float)).astype(np.int64)
            back, at = decode(p, lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.concatenate([[0], np.cumsum(per)]))
            raw = back.tobytes()
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([raw[at[k] : at[k + 1]].decode("utf-8", "replace") for k in range(len(per))], pa.string())], names=["doc_id", "text"])

    return encoded.select(F.col("doc_id").cast("long").alias("doc_id"), "ids").mapInArrow(run, "doc_id long, text string")
