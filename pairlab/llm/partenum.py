"""Exact Jaccard self-join of word-shingle sets through PartEnum signatures.

A document's set holds the hashes of its distinct ``shingle``-word runs.  Two sets with Jaccard similarity of
at least ``percent`` / 100 differ in few elements, and by how many at most follows from their sizes.  Sizes are
cut into bands; a set takes part in its own band and, if a partner may lie there, in the next.  In a band the domain is cut
into n1 partitions (of sets of up to 100 elements each into 3 smaller ones, of which all subsets of 2 are
enumerated), so many that two similar sets agree on one of them.  The hash of a set's elements
there is a signature.  Signatures of no element are only used where a set has so few others that the count demands it,
so the join stays exact.

1. Every text: size and hash of its set.  Equal sets are one class from here on.
2. Signatures of all classes travel in packed blocks (texts of candidates, later, in compressed ones); classes that share one are candidates.  Within a block
   of texts a signature is sent once, so a hot one costs a row a block.
3. Of the candidates, those go on that share so many shingles with other candidates that a link is possible.
4. The sets that share a signature are a group; groups with the same smallest set become one where that takes no more comparisons.  Bit parities of two sets bound their difference from below; a pair
   that passes is counted exactly, and only then are elements sent.  A group's sets meet one of them, its hub; then the
   nearest of those that no link has joined; then all that are still apart, in blocks.  Pairs joined already are never compared.

Sets are told apart by 64-bit hashes, of which one pair in 10^18 collides at 10^9 sets' scale or so.

Defined results: a null or empty text, or one without words, has no shingles and is linked with nothing; a
text with fewer words than ``shingle`` has its whole sequence as the one element; rows that repeat are linked
(equal sets); a null id is never the smallest id of a component unless all are null; extra columns are
ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlab.llm import textbatch as tb
from pairlab.llm.components import connected_components
from pairlab.llm.scratch import discard, materialize

_U = np.uint64


def shingle_sets(buf: np.ndarray, off: np.ndarray, shingle: int = 5, most: int = 400_000) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all texts (A-Z lower-cased), and where each text's begin; worked out for about most bytes
    at a time, as a byte takes some 13 on the way."""
    got = [_shingle_sets(buf[off[a] : off[b]], off[a : b + 1] - off[a], shingle) for a, b in tb.chunks(off, most)]
    if not got:
        return np.zeros(0, _U), np.zeros(1, np.int64)
    sizes = np.concatenate([np.diff(first) for _, first in got])
    return np.concatenate([grams for grams, _ in got]), np.concatenate([[0], np.cumsum(sizes)])


def _shingle_sets(buf: np.ndarray, off: np.ndarray, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    low = tb.lower_ascii(buf)
    starts, ends, first = tb.words(low, off)
    h = tb.hash_spans(low, starts, ends)
    n = np.diff(first)
    at, row = tb.window_starts(first, shingle)
    grams = tb.ngrams(h, shingle)[at] if len(at) else np.zeros(0, _U)
    short = np.flatnonzero((n > 0) & (n < shingle))
    if len(short):  # the whole sequence, told apart from runs by its length
        whole = np.zeros(len(short), _U)
        for k in range(shingle - 1):
            some = n[short] > k
            whole[some] = tb.mix(whole[some] * _U(31) + h[first[:-1][short[some]] + k] + _U(k + 1))
        grams, row = np.concatenate([grams, tb.mix(whole ^ n[short].astype(_U))]), np.concatenate([row, short])
    order = np.lexsort((grams, row))
    grams, row = grams[order], row[order]
    new = np.ones(len(grams), bool)
    new[1:] = (grams[1:] != grams[:-1]) | (row[1:] != row[:-1])
    grams, row = grams[new], row[new]
    return grams, np.searchsorted(row, np.arange(len(off)))


def set_keys(grams: np.ndarray, first: np.ndarray) -> np.ndarray:
    total = np.concatenate([np.zeros(1, _U), np.cumsum(tb.mix(grams), dtype=_U)])
    n = np.diff(first).astype(_U)
    return tb.mix((total[first[1:]] - total[first[:-1]]) ^ tb.mix(n))


def band_ends(largest: int, percent: int, ratio: float = 1.6) -> np.ndarray:
    """Last size of each band; a set's partners lie in its own band or the next."""
    ends = [4]
    while ends[-1] < largest * 100 // percent + 1:
        ends.append(max(int(ends[-1] * ratio), ends[-1] * 100 // percent + 1))
    return np.array(ends)


def signatures(grams: np.ndarray, first: np.ndarray, percent: int = 80, most: int = 50_000) -> tuple[np.ndarray, np.ndarray]:
    """Signatures of all sets (sorted hashes, as of shingle_sets), and the set of each; worked out for about most elements at a time."""
    if not len(grams):
        return np.zeros(0, _U), np.zeros(0, np.int64)
    got = [(sig, of + a) for a, b in tb.chunks(first, most) for sig, of in [_signatures(grams[first[a] : first[b]], first[a : b + 1] - first[a], percent)]]
    return np.concatenate([s for s, _ in got]), np.concatenate([o for _, o in got])


def _signatures(grams: np.ndarray, first: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray]:
    n = np.diff(first)
    if not len(grams):
        return np.zeros(0, _U), np.zeros(0, np.int64)
    ends = band_ends(int(n.max()), percent)
    own = np.searchsorted(ends, n)
    out, owner = [], []
    for next_band in (0, 1):
        some = np.flatnonzero((n > 0) & ((100 * n >= percent * (ends[own] + 1)) if next_band else (n > 0)))
        if not len(some):
            continue
        band = own[some] + next_band
        last, size = ends[band], n[some]
        # most elements in which a partner of at most `last` elements may differ
        partner = np.minimum(last, size * 100 // percent)
        differ = (size + partner) * (100 - percent) // (100 + percent)
        most = 2 * last * (100 - percent) // (100 + percent)
        second = (last <= 100) & (most > 0)
        spared = np.where(second, 1, 0)
        need = most // (spared + 1) + 1
        full = np.where(second, 0.0, 1.0)
        load = last / np.maximum(need, 1)
        slack = np.where(most == 0, 0, np.ceil(need * np.exp(-load) + 3 * np.sqrt(need * np.exp(-load)) + 0 * full)).astype(np.int64)
        n1 = need + slack
        cells = np.where(second, 3 * n1, n1)
        start = np.cumsum(cells) - cells
        length = n[some]
        which = np.repeat(np.arange(len(some)), length)
        e = grams[np.repeat(first[:-1][some], length) + tb.spread(length)]
        cell = start[which] + (((e >> _U(32)) * cells[which].astype(_U)) >> _U(32)).astype(np.int64)
        total = np.concatenate([np.zeros(1, _U), np.cumsum(tb.mix(e + tb._ODD[1]), dtype=_U)])
        edge = np.searchsorted(cell, np.arange(int(cells.sum()) + 1))
        value, count = total[edge[1:]] - total[edge[:-1]], np.diff(edge)
        for two in (False, True):
            sets = np.flatnonzero(second == two)
            if not len(sets):
                continue
            at = np.repeat(start[sets], cells[sets]) + tb.spread(cells[sets])
            v, c, s = value[at], count[at], np.repeat(sets, cells[sets])
            part = tb.spread(cells[sets])
            if two:
                v3, c3, s, part = v.reshape(-1, 3), c.reshape(-1, 3), s[::3], part[::3] // 3
                good = (c3 > 0).sum(1) >= 2
                v = np.stack([v3[:, 1] + v3[:, 2], v3[:, 0] + v3[:, 2], v3[:, 0] + v3[:, 1]], 1).ravel()
                c = np.stack([c3[:, 1] + c3[:, 2], c3[:, 0] + c3[:, 2], c3[:, 0] + c3[:, 1]], 1).ravel()
                enough = np.bincount(s, good, len(some)) > differ // 2
                s, part = np.repeat(s, 3), 3 * np.repeat(part, 3) + np.tile(np.arange(3), len(s))
            else:
                enough = np.bincount(s, c > 0, len(some)) > differ
            keep = (c > 0) | ~enough[s]
            v, c, s, part = v[keep], c[keep], s[keep], part[keep]
            place = tb.mix((band[s].astype(_U) << _U(40)) + part.astype(_U))
            out.append(tb.mix(v * tb._ODD[2] + place))
            owner.append(some[s])
    return np.concatenate(out), np.concatenate(owner)


def _batches(batch: pa.RecordBatch, limit: int = 5_000_000) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    buf, off = tb.utf8(batch.column("text"))
    for a, b in tb.chunks(off, limit):
        yield a, b, buf[off[a] : off[b]], off[a : b + 1] - off[a]


def _classes(grams: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Keys, elements and starts of the distinct non-empty sets."""
    keys = set_keys(grams, first)
    some = np.flatnonzero(np.diff(first))
    _, at = np.unique(keys[some], return_index=True)
    some = some[at]
    size = np.diff(first)[some]
    return keys[some], grams[np.repeat(first[:-1][some], size) + tb.spread(size)], np.concatenate([[0], np.cumsum(size)])


def _dealt(bucket: np.ndarray, n: int, *columns: np.ndarray) -> Iterator[tuple]:
    """The rows of columns by bucket, as bytes."""
    order = np.argsort(bucket, kind="stable")
    edge = np.searchsorted(bucket[order], np.arange(n + 1))
    columns = tuple(np.ascontiguousarray(c[order]) for c in columns)
    for k in np.flatnonzero(np.diff(edge)):
        yield (int(k), *(c[edge[k] : edge[k + 1]].tobytes() for c in columns))


def _bucket(x: np.ndarray, buckets: int) -> np.ndarray:
    """By the upper 24 bits."""
    return ((x >> _U(40)) * _U(buckets) >> _U(24)).astype(np.int64)


def _packed(value: np.ndarray, key: np.ndarray, buckets: int) -> Iterator[tuple]:
    """By bucket of the values: bucket, their lower 40 bits (four bytes and one), the distinct keys, and each value's place in these
    (two bytes, or four beyond 65,536 keys)."""
    bucket = _bucket(value, buckets)
    order = np.argsort(bucket, kind="stable")
    edge = np.searchsorted(bucket[order], np.arange(buckets + 1))
    value, key = value[order], key[order]
    for k in np.flatnonzero(np.diff(edge)):
        v = value[edge[k] : edge[k + 1]]
        keys, place = np.unique(key[edge[k] : edge[k + 1]], return_inverse=True)
        yield int(k), v.astype(np.uint32).tobytes(), (v >> _U(32)).astype(np.uint8).tobytes(), keys.tobytes(), place.astype(np.uint16 if len(keys) <= 65_536 else np.uint32).tobytes()


_PACKED = ("bucket", "low", "high", "keys", "place")


def _unpacked(table: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    """Values and keys of the packed rows of one bucket."""
    values, keys = [np.zeros(0, _U)], [np.zeros(0, _U)]
    for low, high, k, place in zip(*(table.column(c).to_pylist() for c in _PACKED[1:])):
        if low:
            value = np.frombuffer(low, np.uint32).astype(_U) | (np.frombuffer(high, np.uint8).astype(_U) << _U(32))
            values.append(value)
            keys.append(np.frombuffer(k, _U)[np.frombuffer(place, np.uint16 if len(place) == 2 * len(value) else np.uint32)])
    return np.concatenate(values), np.concatenate(keys)


def _record(rows: list[tuple], names: tuple) -> pa.RecordBatch:
    cols = list(zip(*rows))
    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], names=list(names))


def _sizes(shingle: int):
    def run(batches):
        for batch in batches:
            for a, b, buf, off in _batches(batch):
                grams, first = shingle_sets(buf, off, shingle)
                yield pa.RecordBatch.from_arrays([batch.column("rid")[a:b], batch.column("doc_id")[a:b], pa.array(np.diff(first)), pa.array(set_keys(grams, first).view(np.int64))], names=["rid", "doc_id", "n", "key"])

    return run


def _once(value: np.ndarray, key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct values, the key of one occurrence, and whether there are more than one."""
    order = np.argsort(value, kind="stable")
    v = value[order]
    new = np.flatnonzero(np.concatenate([[True], v[1:] != v[:-1]])) if len(v) else np.zeros(0, np.int64)
    return v[new], key[order[new]], np.diff(np.append(new, len(v))) > 1


def _sent_signatures(shingle: int, percent: int, buckets: int):
    """bucket, and signatures with one class each; classes that meet another one here are candidates at once."""

    def run(batches):
        for batch in batches:
            for _, _, buf, off in _batches(batch):
                keys, grams, first = _classes(*shingle_sets(buf, off, shingle))
                sig, of = signatures(grams, first, percent)
                one, key, more = _once(sig, keys[of])
                met = np.unique(keys[of][more[np.searchsorted(one, sig)]]) if len(sig) else np.zeros(0, _U)
                rows = [(*row, b"") for row in _packed(one, key, buckets)]
                rows += [(k, b"", b"", b"", b"", m) for k, m in _dealt(_bucket(met, buckets), buckets, met)]
                if rows:
                    yield _record(rows, (*_PACKED, "met"))

    return run


def _joined(table: pa.Table, column: str, kind) -> np.ndarray:
    return np.frombuffer(b"".join(table.column(column).to_pylist()), kind)


def _shared(key, table):
    """Candidates of one bucket. The 40 bits and the bucket may take two signatures for one, which only adds candidates."""
    sig, keys = _unpacked(table)
    order = np.argsort(sig, kind="stable")
    sig, keys = sig[order], keys[order]
    edge = sig[1:] == sig[:-1]
    differ = np.zeros(len(sig), bool)
    if len(sig):
        run = np.concatenate([[0], np.cumsum(~edge)])
        begin = np.flatnonzero(np.concatenate([[True], ~edge]))
        odd = keys != keys[begin][run]  # equal sets of other blocks are no partners
        mixed = np.logical_or.reduceat(odd, begin)
        differ = mixed[run]
    found = np.unique(np.concatenate([keys[differ], _joined(table, "met", _U)]))
    return pa.table({"key": found.view(np.int64)})


def _sent_elements(shingle: int, buckets: int):
    """bucket, and two fifths of the elements with the class of one occurrence (0: it has several here)."""

    def run(batches):
        for batch in batches:
            for _, _, buf, off in _batches(batch):
                keys, grams, first = _classes(*shingle_sets(buf, off, shingle))
                of = np.repeat(keys, np.diff(first))
                part = (tb.mix(grams) % _U(5)) < _U(2)
                one, key, more = _once(grams[part], of[part])
                key = np.where(more, _U(0), key)
                rows = list(_packed(one, key, buckets))
                if rows:
                    yield _record(rows, _PACKED)

    return run


def _alone(key, table):
    """Of one bucket: classes and how many elements only they have; two elements taken for one only keep a candidate more."""
    one, of, more = _once(*_unpacked(table))
    owner, n = np.unique(of[~more & (of != 0)], return_counts=True)
    return pa.table({"key": owner.view(np.int64), "u": n})


def _packed_texts(buckets: int):
    """bucket, and the rows of a block of texts that belong there: their rids, sizes and compressed bytes."""

    def run(batches):
        codec = pa.Codec("zstd", compression_level=3)
        for batch in batches:
            for a, b, _, _ in _batches(batch, 10_000_000):
                rid = batch.column("rid")[a:b].to_numpy()
                bucket = ((rid.view(_U) >> _U(40)) * _U(buckets) >> _U(24)).astype(np.int64)
                order = np.argsort(bucket, kind="stable")
                buf, off = tb.utf8(batch.column("text")[a:b].take(pa.array(order)))
                rid, bucket = rid[order], bucket[order]
                edge = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1], [True]]))
                rows = [(int(bucket[x]), rid[x:y].tobytes(), np.diff(off[x : y + 1]).tobytes(), codec.compress(buf[off[x] : off[y]].tobytes(), asbytes=True)) for x, y in zip(edge, edge[1:])]
                cols = list(zip(*rows))
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], names=["bucket", "rids", "sizes", "texts"])

    return run


def _picked(batches):
    """rid and text of the wanted rows. Rows come by bucket, in each the wanted rids (in wanted) before the packed texts."""
    codec = pa.Codec("zstd")
    here, want = None, np.zeros(0, np.int64)
    for batch in batches:
        bucket, wanted = batch.column("bucket").to_numpy(), batch.column("wanted")
        ids = np.flatnonzero(wanted.is_valid().to_numpy(zero_copy_only=False))
        known, of = wanted.take(pa.array(ids)).to_numpy(), bucket[ids]
        packed = np.setdiff1d(np.arange(len(bucket)), ids, assume_unique=True)
        rids, texts, held = [], [], 0
        for at in np.unique(bucket).tolist():
            more = known[of == at]
            want = np.concatenate([want, more]) if at == here else more
            here = at
            for k in packed[bucket[packed] == at].tolist():
                rid = np.frombuffer(batch.column("rids")[k].as_py(), np.int64)
                hit = np.flatnonzero(np.isin(rid, want))
                if len(hit):
                    end = np.cumsum(np.frombuffer(batch.column("sizes")[k].as_py(), np.int64))
                    raw = codec.decompress(batch.column("texts")[k].as_py(), int(end[-1]), asbytes=True)
                    rids.append(rid[hit])
                    texts += [raw[end[h - 1] if h else 0 : end[h]] for h in hit.tolist()]
                    held += len(raw)
                if held > 16_000_000:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(rids)), pa.array(texts, pa.binary()).cast(pa.string())], names=["rid", "text"])
                    rids, texts, held = [], [], 0
        if texts:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(rids)), pa.array(texts, pa.binary()).cast(pa.string())], names=["rid", "text"])


def _pick(texts: DataFrame, wanted: DataFrame, buckets: int) -> DataFrame:
    """The rows (rid, text) of texts whose rid is in wanted. Texts travel in compressed blocks, one a bucket and block
    of texts; a task holds the wanted rids of one bucket and one packed block."""
    place = F.shiftrightunsigned(F.shiftrightunsigned("rid", 40) * buckets, 24).cast("int")
    sent = texts.select("rid", "text").mapInArrow(_packed_texts(buckets), "bucket int, rids binary, sizes binary, texts binary").withColumn("wanted", F.lit(None).cast("long"))
    both = sent.unionByName(wanted.select(place.alias("bucket"), F.col("rid").alias("wanted")), allowMissingColumns=True)
    ordered = both.repartition(buckets, "bucket").sortWithinPartitions("bucket", F.col("wanted").isNull())
    return ordered.mapInArrow(_picked, "rid long, text string")


def _class_rows(shingle: int):
    def run(batches):
        for batch in batches:
            for _, _, buf, off in _batches(batch, 3_000_000):
                keys, grams, first = _classes(*shingle_sets(buf, off, shingle))
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array([grams[a:b].tobytes() for a, b in zip(first, first[1:])], pa.binary())], names=["key", "elements"])

    return run


def _class_signatures(percent: int):
    def run(batches):
        for batch in batches:
            sets = [np.frombuffer(x, _U) for x in batch.column("elements").to_pylist()]
            if sets:
                sig, of = signatures(np.concatenate(sets), np.concatenate([[0], np.cumsum([len(x) for x in sets])]), percent)
                yield pa.RecordBatch.from_arrays([pa.array(sig.view(np.int64)), pa.array(batch.column("key").to_numpy()[of])], names=["sig", "key"])

    return run


def _sketched(batches):
    """key, size and sketch of each set: bit parities of its elements, two to four bits an element, 512 at least. Halves of a sketch
    fold by xor to one of half the length."""
    for batch in batches:
        sizes, sketches = [], []
        for x in batch.column("elements").to_pylist():
            s = np.frombuffer(x, _U)
            bits = max(512, 1 << (2 * len(s) - 1).bit_length())
            sizes.append(len(s))
            sketches.append(np.packbits((np.bincount((tb.mix(s) % _U(bits)).astype(np.int64), minlength=bits) & 1).astype(np.uint8)).tobytes())
        yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(sizes, pa.int64()), pa.array(sketches, pa.binary())], names=["key", "n", "sketch"])


def _stacked(sketches: list[bytes], length: int) -> np.ndarray:
    """Sketches of length bytes, or of twice as many and folded, as rows."""
    rows = np.frombuffer(b"".join(sketches), _U).reshape(len(sketches), -1, length // 8)
    return np.bitwise_xor.reduce(rows, axis=1)


def _near(percent: int):
    """Of pairs with sizes and sketches those that may link."""

    def run(batches):
        for batch in batches:
            na, nb = batch.column("na").to_numpy(), batch.column("nb").to_numpy()
            sa, sb = batch.column("sa").to_pylist(), batch.column("sb").to_pylist()
            la, lb = np.array([len(x) for x in sa], np.int64), np.array([len(x) for x in sb], np.int64)
            fine = np.zeros(len(na), bool)
            for x, y in {*zip(la.tolist(), lb.tolist())}:
                at = np.flatnonzero((la == x) & (lb == y))
                one, two = (_stacked([s[k] for k in at.tolist()], min(x, y)) for s in (sa, sb))
                fine[at] = np.bitwise_count(one ^ two).sum(1, dtype=np.int64) * (100 + percent) <= (na[at] + nb[at]) * (100 - percent)
            keep = pa.array(fine)
            yield pa.RecordBatch.from_arrays([batch.column(c).filter(keep) for c in ("a", "b", "na", "nb")], names=["a", "b", "na", "nb"])

    return run


def close_pairs(size: np.ndarray, sketch: list[bytes], part: np.ndarray, side: np.ndarray, percent: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places and distances of the pairs of two parts that may link. Where side holds two values, only pairs between both count."""
    length = np.array([len(x) for x in sketch], np.int64)
    both = len(np.unique(side)) > 1
    out = [(np.zeros(0, np.int64),) * 3]
    for at in np.unique(length).tolist():
        own = np.flatnonzero(length == at)
        ids = np.concatenate([own, np.flatnonzero(length == 2 * at)])  # sets of more than twice the size never link
        rows = np.concatenate([_stacked([sketch[k] for k in x.tolist()], at) for x in (own, ids[len(own) :]) if len(x)])
        for k, i in enumerate(own.tolist()):
            j = np.arange(k + 1, len(ids))
            to = ids[j]
            fine = (part[to] != part[i]) & (100 * np.minimum(size[to], size[i]) >= percent * np.maximum(size[to], size[i]))
            j = j[fine & (side[to] != side[i])] if both else j[fine]
            differ = np.bitwise_count(rows[j] ^ rows[k]).sum(1, dtype=np.int64)
            fine = differ * (100 + percent) <= (size[ids[j]] + size[i]) * (100 - percent)
            out.append((np.full(int(fine.sum()), i), ids[j[fine]], differ[fine]))
    return tuple(np.concatenate(x) for x in zip(*out))


def _forest(a: np.ndarray, b: np.ndarray, differ: np.ndarray, part: np.ndarray) -> np.ndarray:
    """The nearest pairs that would join all parts that any of the pairs joins."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while (up := parent.get(x, x)) != x:
            parent[x] = parent.get(up, up)
            x = up
        return x

    out, left = [], len(np.unique(part)) - 1
    for k in np.argsort(differ, kind="stable").tolist():
        x, y = root(int(part[a[k]])), root(int(part[b[k]]))
        if x != y:
            parent[x] = y
            out.append(k)
            if len(out) == left:
                break
    return np.array(out, np.int64)


def _met(percent: int, forest: bool):
    """Of the groups of one task: pairs of two parts that may link, or a spanning forest of these."""

    def run(key, table):
        table = table.sort_by([("sig", "ascending"), ("key", "ascending")])
        sig, keys, size, part, side = (table.column(c).to_numpy() for c in ("sig", "key", "n", "part", "side"))
        sketch = table.column("sketch").to_pylist()
        edges = np.flatnonzero(np.concatenate([[True], sig[1:] != sig[:-1], [True]])) if len(sig) else []
        found = [np.zeros((4, 0), np.int64)]
        for x, y in zip(edges, edges[1:]):
            i, j, differ = close_pairs(size[x:y], sketch[x:y], part[x:y], side[x:y], percent)
            if forest:
                some = _forest(i, j, differ, part[x:y])
                i, j = i[some], j[some]
            low, high = np.where(keys[x + i] < keys[x + j], x + i, x + j), np.where(keys[x + i] < keys[x + j], x + j, x + i)
            found.append(np.stack([keys[low], keys[high], size[low], size[high]]))
        return pa.table(dict(zip(("a", "b", "na", "nb"), np.unique(np.concatenate(found, axis=1), axis=1))))

    return run


def _verified(percent: int):
    """Of the pairs of one task (key, other) those that link; the elements of all their sets are here (key, elements)."""

    def run(key, table):
        keys, other, elements = table.column("key").to_numpy(), table.column("other"), table.column("elements")
        pair = other.is_valid().to_numpy()
        sets = {int(keys[k]): np.frombuffer(elements[k].as_buffer(), _U) for k in np.flatnonzero(~pair).tolist()}  # no copies
        a, b = [], []
        for x, y in zip(keys[pair].tolist(), other.drop_null().to_pylist()):
            one, two = sets[x], sets[y]
            c = int((one[np.minimum(np.searchsorted(one, two), len(one) - 1)] == two).sum())
            if 100 * c >= percent * (len(one) + len(two) - c):
                a.append(x)
                b.append(y)
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return run


def _exact(pairs: DataFrame, sets: DataFrame, percent: int, heavy: int) -> DataFrame:
    """The pairs (a, b, sizes na and nb) that link. A set is sent once to each task that has a pair of it; a task takes pairs of about
    heavy elements."""
    spark = pairs.sparkSession
    load = pairs.groupBy("a").agg((F.sum("nb") + F.max("na")).alias("w"))
    total = load.agg(F.sum("w")).first()[0] or 0
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), total // heavy + 1)
    parts = load.select("a", F.ceil(F.col("w") / heavy).alias("g"))
    place = F.when(F.col("g") == 1, -F.pmod(F.xxhash64("a"), F.lit(tasks)) - 1).otherwise(F.abs(F.xxhash64("a", F.pmod(F.xxhash64("b"), F.col("g")))))
    dealt = materialize(pairs.join(parts, "a").select("a", "b", place.alias("task")), "dealt")
    ends = dealt.select("task", F.col("a").alias("key")).union(dealt.select("task", F.col("b").alias("key"))).distinct()
    rows = ends.join(sets, "key").select("task", "key", "elements", F.lit(None).cast("long").alias("other"))
    rows = rows.union(dealt.select("task", F.col("a").alias("key"), F.lit(None).cast("binary").alias("elements"), F.col("b").alias("other")))
    out = materialize(rows.groupBy("task").applyInArrow(_verified(percent), "a long, b long"), "verified")
    discard(dealt)
    return out


def _meeting(members: DataFrame, sketches: DataFrame, percent: int, block: int, forest: bool) -> DataFrame:
    """Pairs (a < b, sizes na and nb) of two parts that share a group and may link; blocks of a large group meet in tasks of their own."""
    sizes = members.groupBy("sig").agg(F.count("*").alias("m"), F.min("part").alias("low"), F.max("part").alias("high")).filter("low < high").select("sig", F.ceil(F.col("m") / block).cast("int").alias("g"))
    opened = materialize(members.select("sig", "key", "part").join(sizes, "sig"), "open")
    tasks = max(int(opened.sparkSession.conf.get("spark.sql.shuffle.partitions")), opened.count() // 20_000 + 1)
    rows = opened.withColumn("i", F.pmod(F.xxhash64("key"), F.col("g")).cast("int")).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("g") - 1)))
    task = F.when(F.col("g") == 1, -F.pmod(F.xxhash64("sig"), F.lit(tasks)) - 1).otherwise(F.abs(F.xxhash64("sig", F.least("i", "j"), F.greatest("i", "j"))))
    rows = rows.select("sig", "key", "part", F.col("i").alias("side"), task.alias("task")).join(sketches, "key")
    return rows.groupBy("task").applyInArrow(_met(percent, forest), "a long, b long, na long, nb long").distinct()


def _links(sets: DataFrame, members: DataFrame, percent: int, block: int, heavy: int = 4_000_000, every: bool = False) -> DataFrame:
    """Links (a, b) between sets that connect all that link, or all links. Members (sig, hub, key) are the groups of sets.

    A group's sets meet its hub first, then the nearest of those that no link has joined yet, and last whatever
    is not joined; pairs that were refused once are not sent again."""
    sketches = materialize(sets.mapInArrow(_sketched, "key long, n long, sketch binary"), "sketches")
    if every:
        pairs = _meeting(members.withColumn("part", F.col("key")), sketches, percent, block, False)
        return _exact(materialize(pairs, "pairs_all"), sets, percent, heavy)
    named = lambda x: sketches.select(F.col("key").alias(x), F.col("n").alias(f"n{x}"), F.col("sketch").alias(f"s{x}"))
    star = members.filter("key <> hub").select(F.col("hub").alias("a"), F.col("key").alias("b")).distinct()
    star = star.join(named("b"), "b").join(named("a"), "a").filter(100 * F.least("na", "nb") >= percent * F.greatest("na", "nb"))
    tried = materialize(star.mapInArrow(_near(percent), "a long, b long, na long, nb long"), "pairs_hub")
    found = _exact(tried, sets, percent, heavy)
    rest = members.filter("key <> hub").select("sig", "key")
    for forest in (True, False):
        joined = connected_components(found).select(F.col("node").alias("key"), F.col("component").alias("part"))
        parts = rest.join(joined, "key", "left").withColumn("part", F.coalesce("part", "key"))
        pairs = _meeting(parts, sketches, percent, block, forest).join(tried.select("a", "b"), ["a", "b"], "left_anti")
        pairs = materialize(pairs, "pairs_near" if forest else "pairs_left")
        if not pairs.isEmpty():
            found = found.union(_exact(pairs, sets, percent, heavy))
            tried = tried.union(pairs)
    return found


def _by_hub(members: DataFrame) -> DataFrame:
    """Members (sig, hub, key) with the groups of one hub as one group, named after the hub, where all its pairs are no more than those
    of the groups together. Near copies of one text share hundreds of signatures and would meet under each."""
    squares = members.groupBy("sig", "hub").agg(F.count("*").alias("m")).groupBy("hub").agg(F.sum(F.col("m") * F.col("m")).alias("squares"))
    once = materialize(members.select("hub", "key").distinct(), "by_hub")
    whole = once.groupBy("hub").agg(F.count("*").alias("u")).join(squares, "hub").filter(F.col("u") * F.col("u") <= F.col("squares")).select("hub")
    whole = materialize(whole, "whole_hubs")
    merged = once.join(whole, "hub", "left_semi").select(F.col("hub").alias("sig"), "hub", "key")
    out = materialize(merged.union(members.join(whole, "hub", "left_anti").select("sig", "hub", "key")), "groups")
    discard(members, once, whole)
    return out


def _possible(docs: DataFrame, percent: int, shingle: int) -> tuple[DataFrame, ...]:
    """Every row (rid, doc_id, n, key); classes of equal sets (key, rid, n, least id); elements of the sets that may link; and
    their groups (sig, hub, key): the sets that share a signature, or one of the signatures with one hub, and the one with the smallest key, the hub."""
    spark = docs.sparkSession
    partitions = int(spark.conf.get("spark.sql.shuffle.partitions"))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).withColumn("rid", F.xxhash64("doc_id", "text"))
    narrow = materialize(docs.mapInArrow(_sizes(shingle), "rid long, doc_id long, n long, key long"), "sizes")
    total = narrow.agg(F.sum("n")).first()[0] or 0
    buckets = max(64, total // 2_500_000 + 1)
    classes = materialize(narrow.filter("n > 0").groupBy("key").agg(F.min("rid").alias("rid"), F.max("n").alias("n"), F.min("doc_id").alias("least")), "classes")

    sent = docs.select("text").mapInArrow(_sent_signatures(shingle, percent, buckets), "bucket int, low binary, high binary, keys binary, place binary, met binary")
    candidates = materialize(sent.groupBy("bucket").applyInArrow(_shared, "key long").distinct(), "candidates")
    chosen = classes.join(candidates, "key", "left_semi")
    blocks = max(partitions, total // 16_000_000 + 1)
    texts = materialize(_pick(docs, chosen.select("rid"), blocks), "texts", codec="zstd")

    alone = texts.select("text").mapInArrow(_sent_elements(shingle, buckets), "bucket int, low binary, high binary, keys binary, place binary").groupBy("bucket").applyInArrow(_alone, "key long, u long")
    alone = alone.groupBy("key").agg(F.sum("u").alias("u"))
    left = chosen.join(alone, "key", "left").filter(100 * F.coalesce("u", F.lit(0)) <= (100 - percent) * F.col("n"))
    left = materialize(left.select("rid", "key"), "possible")
    sets = _pick(texts, left.select("rid"), blocks).select("text").mapInArrow(_class_rows(shingle), "key long, elements binary")
    sets = materialize(sets, "sets")
    discard(texts, candidates, left)

    signs = materialize(sets.mapInArrow(_class_signatures(percent), "sig long, key long"), "signs")
    groups = signs.groupBy("sig").agg(F.count("*").alias("m"), F.min("key").alias("hub"), F.bit_xor(F.xxhash64("key")).alias("same")).filter("m > 1")
    groups = groups.groupBy("m", "hub", "same").agg(F.min("sig").alias("sig")).select("sig", "hub")  # signatures of the same sets are one group
    members = materialize(signs.join(groups, "sig").select("sig", "hub", "key"), "members")
    discard(signs)
    return narrow, classes, sets, _by_hub(members)


def _grouped(docs: DataFrame, percent: int, shingle: int, block: int) -> DataFrame:
    """rid (hash of id and text), doc_id, n, group (of linked sets), c (its smallest id) of every row."""
    narrow, classes, sets, members = _possible(docs, percent, shingle)
    linked = connected_components(_links(sets, members, percent, block)).withColumnRenamed("node", "key")
    linked = materialize(linked.join(classes.select("key", "least"), "key"), "linked")
    discard(sets, members)
    least = linked.groupBy("component").agg(F.min("least").alias("c"))
    final = materialize(linked.join(least, "component").select("key", "component", "c"), "labels")
    named = classes.join(final, "key", "left").select("key", F.coalesce("component", "key").alias("group"), F.coalesce("c", "least").alias("c"))
    return narrow.join(materialize(named, "named"), "key", "left").select("rid", "doc_id", "n", "group", "c")


def near_duplicates(docs: DataFrame, percent: int = 80, shingle: int = 5, block: int = 1024) -> DataFrame:
    """doc_id, n_shingles, component_id of every document; see the module's docstring."""
    out = _grouped(docs, percent, shingle, block)
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("c")).otherwise(F.col("doc_id")).alias("component_id"))


def linked_classes(docs: DataFrame, percent: int = 80, shingle: int = 5, block: int = 1024) -> tuple[DataFrame, DataFrame]:
    """The whole join: pairs of classes of equal sets that link (a < b), none left out; and doc_id, key (class, null without
    words) and n_links of every row, the number of other rows that it links with, those of its own class included.

    Unlike near_duplicates it compares every pair of a group, so its cost grows with the square of a group's classes,
    spread over tasks of block x block."""
    narrow, classes, sets, members = _possible(docs, percent, shingle)
    pairs = _links(sets, members, percent, block, every=True)
    pairs = materialize(pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "pairs")
    sizes = materialize(narrow.filter("n > 0").groupBy("key").agg(F.count("*").alias("m")), "class_sizes")
    both = pairs.select(F.col("a").alias("key"), F.col("b").alias("other")).union(pairs.select(F.col("b"), F.col("a")))
    more = both.join(sizes.select(F.col("key").alias("other"), "m"), "other").groupBy("key").agg(F.sum("m").alias("more"))
    per = sizes.join(more, "key", "left").select("key", (F.col("m") - 1 + F.coalesce("more", F.lit(0))).alias("n_links"))
    rows = narrow.select("doc_id", F.when(F.col("n") > 0, F.col("key")).alias("key")).join(per, "key", "left").select("doc_id", "key", F.coalesce("n_links", F.lit(0)).alias("n_links"))
    return pairs, rows


def _without(rows: DataFrame, goes: DataFrame, words: int = 1 << 17) -> DataFrame:
    """The rows whose rid is not in goes. Only rows whose bit is set among those of goes (words x 64 bits, broadcast) are shuffled."""
    word, bit = F.pmod(F.shiftrightunsigned("rid", 6), F.lit(words)).alias("word"), F.col("rid").bitwiseAND(F.lit(63)).cast("int")
    bits = materialize(goes.select(word, F.call_function("shiftleft", F.lit(1).cast("long"), bit).alias("b")).groupBy("word").agg(F.bit_or("b").alias("bits")), "bits")
    marked = rows.withColumn("word", word).join(F.broadcast(bits), "word", "left")
    marked = marked.withColumn("hit", F.call_function("shiftrightunsigned", F.coalesce("bits", F.lit(0).cast("long")), bit).bitwiseAND(F.lit(1).cast("long")) == 1)
    return marked.filter(~F.col("hit")).select(*rows.columns).union(marked.filter("hit").select(*rows.columns).join(goes, "rid", "left_anti").select(*rows.columns))


def keep_one(docs: DataFrame, percent: int = 80, shingle: int = 5, block: int = 1024) -> DataFrame:
    """The rows of docs, all columns as they are, less those linked with a kept one: of each group one row with
    its smallest id stays, and so do all rows without words."""
    grouped = materialize(_grouped(docs, percent, shingle, block), "grouped")
    first = materialize(grouped.filter(F.col("n") > 0).filter(F.col("doc_id").eqNullSafe(F.col("c"))).groupBy("group").agg(F.min("rid").alias("rid")).select("rid"), "first")
    goes = materialize(grouped.filter("n > 0").select("rid").distinct().join(first, "rid", "left_anti"), "goes")
    keyed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.xxhash64(F.col("doc_id").cast("long"), F.coalesce("text", F.lit(""))).alias("rid"))
    kept = _without(keyed, goes)
    again = grouped.filter("n > 0").groupBy("rid").agg(F.count("*").alias("m")).filter("m > 1").select("rid")
    again = materialize(again.join(first, "rid", "left_semi"), "again")  # rows that repeat as a whole
    if not again.isEmpty():
        kept = kept.join(again, "rid", "left_anti").union(kept.join(again, "rid", "left_semi").dropDuplicates(["rid"]))
    return kept.select(*(F.col(f"row.`{c}`") for c in docs.columns))
