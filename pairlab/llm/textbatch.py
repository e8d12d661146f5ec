"""Whole columns of text as byte arrays: words, hashes and n-grams without a Python object per word."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_U = np.uint64
_MASKS = np.array([(1 << (8 * k)) - 1 for k in range(9)], dtype=_U)
_ODD = (_U(0x9E3779B97F4A7C15), _U(0xC2B2AE3D27D4EB4F), _U(0x165667B19E3779F9), _U(0xD6E8FEB86659FD93), _U(0xA0761D6478BD642F))

#: 0x20 and 0x09-0x0D separate words.
SPACE = np.zeros(256, dtype=bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of all texts and the rows' offsets in them; null reads as an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = pc.fill_null(column.cast(pa.large_string()), "")
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]], off - off[0]


def chunks(off: np.ndarray, limit: int = 3_000_000) -> Iterator[tuple[int, int]]:
    """Row ranges of about limit bytes at most; a longer text is a range of its own."""
    n, a = len(off) - 1, 0
    while a < n:
        b = int(np.searchsorted(off, off[a] + limit, side="right")) - 1
        b = min(n, max(b, a + 1))
        yield a, b
        a = b


def lower_ascii(buf: np.ndarray) -> np.ndarray:
    return np.where((buf >= 65) & (buf <= 90), buf + np.uint8(32), buf)


def words(buf: np.ndarray, off: np.ndarray, separator: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words in buf, and the first word of each row (one more entry than rows)."""
    inside = ~separator[buf]
    n = len(buf)
    first = np.zeros(n + 1, dtype=bool)
    first[off] = True
    before = np.zeros(n, dtype=bool)
    before[1:] = inside[:-1]
    starts = np.flatnonzero(inside & (~before | first[:n]))
    after = np.zeros(n, dtype=bool)
    after[:-1] = inside[1:]
    ends = np.flatnonzero(inside & (~after | first[1:])) + 1
    return starts, ends, np.searchsorted(starts, off)


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> _U(32))) * _U(0xD6E8FEB86659FD93)
    h = (h ^ (h >> _U(29))) * _U(0x9E3779B97F4A7C15)
    return h ^ (h >> _U(32))


def hash_spans(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans, eight bytes a step."""
    size = ends - starts
    h = mix(size.astype(_U) + _ODD[0])
    padded = np.concatenate([buf, np.zeros(8, np.uint8)])
    eight = np.ndarray(shape=(len(buf) + 1,), dtype="<u8", buffer=padded, strides=(1,))
    live, at = np.arange(len(starts)), 0
    live = live[size > 0]
    while len(live):
        s = starts[live] + at
        h[live] = mix(h[live] * _ODD[1] + (eight[s] & _MASKS[np.minimum(size[live] - at, 8)]))
        at += 8
        live = live[size[live] > at]
    return h


def ngrams(h: np.ndarray, n: int) -> np.ndarray:
    """Hash of h[i], ..., h[i+n-1] for each i (rows not regarded); n at most 5."""
    if len(h) < n:
        return np.zeros(0, _U)
    out = np.zeros(len(h) - n + 1, _U)
    for k in range(n):
        out += mix(h[k : len(h) - n + 1 + k] + _ODD[k]) * _ODD[(k + 2) % 5]
    return mix(out)


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """P^i and P^-i modulo 2^64 for i < n."""
    p = 0x9E3779B97F4A7C15
    out = []
    for x in (p, pow(p, -1, 2**64)):
        a = np.full(max(n, 1), x, _U)
        a[0] = 1
        out.append(np.multiply.accumulate(a))
    return out[0], out[1]


def rolling(h: np.ndarray, n: int, up: np.ndarray, down: np.ndarray) -> np.ndarray:
    """Hash of each n consecutive entries, for long n; up, down = powers(len(h) + 1 or more)."""
    if len(h) < n:
        return np.zeros(0, _U)
    total = np.concatenate([np.zeros(1, _U), np.cumsum(mix(h) * up[: len(h)], dtype=_U)])
    return mix((total[n:] - total[:-n]) * down[: len(h) - n + 1])


def spread(counts: np.ndarray) -> np.ndarray:
    """0, 1, ..., c-1 for each c of counts, one after the other."""
    counts = np.asarray(counts, dtype=np.int64)
    ends = np.cumsum(counts)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - counts, counts)


def window_starts(first: np.ndarray, size: int, min_one: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """Starts of all windows of size words inside one row each, and their rows."""
    n = np.diff(first)
    per = np.maximum(n - size + 1, np.minimum(n, 1) if min_one else 0)
    return np.repeat(first[:-1], per) + spread(per), np.repeat(np.arange(len(n)), per)
