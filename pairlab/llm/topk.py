"""Exact top-k search by inner product of integer vectors.

The queries are packed into blocks and sent to every task, as many at a time as ``held`` bytes hold (their size is
counted first); beyond that they go in several passes over the candidates, each with its own share of the queries by a hash.
The candidates stay where they lie.  A task cuts its rows into shards; a tile is one matrix product of a query block and a
shard, and each query keeps its best k of a tile by partial selection.  Lists of one task are merged in place; those of
tasks meet in a tree: first by group of tasks, then all groups.  Only lists are shuffled.

Defined results: vectors that are null or hold null or non-finite components take no part, as queries or
candidates, and neither do rows without an id; only vectors of equal length are compared; empty vectors score
0; ids that repeat are candidates of their own; a query that repeats with the same vector is searched once, with another vector it
has a list of its own under the same query_id (its own id is never its candidate); extra columns are ignored; an empty
table gives an empty result.  Products are exact below 2^53 in floating point, beyond in 64-bit integers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pairlab.llm.scratch import materialize


def usable(vectors: DataFrame, scale: int) -> DataFrame:
    """vec_id, v (integers), dim of the rows that take part."""
    x = F.transform("embedding", lambda e: e.cast("double"))
    fine = F.col("embedding").isNotNull() & F.col("vec_id").isNotNull() & F.forall("x", lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < F.lit(float("inf"))))
    v = F.transform("x", lambda e: F.floor(e * F.lit(float(scale))))
    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), x.alias("x"), "embedding").filter(fine).select("vec_id", v.alias("v"), F.size("x").alias("dim"))


def product(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """a @ b.T, exactly."""
    if a.size == 0 or b.size == 0:
        return np.zeros((len(a), len(b)), np.int64)
    bound = float(np.abs(a).max()) * float(np.abs(b).max()) * a.shape[1]
    if bound < 2**53:
        return (a.astype(np.float64) @ b.T.astype(np.float64)).astype(np.int64)
    return a @ b.T


def best(score: np.ndarray, ids: np.ndarray, own: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of each row's k highest scores, ties to smaller ids; a row's own id is no candidate."""
    low = np.iinfo(np.int64).min + 1  # can be negated
    score = np.where(ids[None] == own[:, None], low, score)
    n = score.shape[1]
    if n > k:
        least = -np.partition(-score, k - 1, axis=1)[:, k - 1]
        r, c = np.nonzero(score >= least[:, None])  # with all ties of the last
    else:
        r, c = np.nonzero(np.ones_like(score, bool))
    fine = ids[c] != own[r]
    r, c = r[fine], c[fine]
    order = np.lexsort((ids[c], -score[r, c], r))
    r, c = r[order], c[order]
    place = np.arange(len(r)) - np.searchsorted(r, r)
    return r[place < k], c[place < k]


def _rows(column: pa.Array, dim: int, some: np.ndarray) -> np.ndarray:
    """The vectors at some of a column of arrays, all of dim components."""
    flat = column.take(pa.array(some)).flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    return flat.reshape(len(some), dim)


def _least(q: np.ndarray, ids: np.ndarray, score: np.ndarray, k: int) -> tuple[np.ndarray, ...]:
    """The k best entries of each query."""
    order = np.lexsort((ids, -score, q))
    q, ids, score = q[order], ids[order], score[order]
    keep = np.arange(len(q)) - np.searchsorted(q, q) < k
    return q[keep], ids[keep], score[keep]


def _tiles(shipped, k: int, groups: int, query_block: int, shard: int):
    """Best candidates of all rows of a task for all queries of a pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_dim = shipped.value
        every = sum(len(own) for own, _, _ in by_dim.values())
        held = tuple(np.zeros(0, np.int64) for _ in range(3))
        fresh, n = [], 0
        for batch in batches:
            ids, vectors = batch.column("vec_id").to_numpy(), batch.column("v")
            size = pa.compute.list_value_length(vectors).to_numpy()
            for dim in np.unique(size).tolist():
                if dim not in by_dim:
                    continue
                own, number, a = by_dim[dim]
                some = np.flatnonzero(size == dim)
                step = max(1, min(shard, 32_000_000 // (8 * max(dim, 1))))
                for x in range(0, len(some), step):
                    mine = some[x : x + step]
                    b = _rows(vectors, dim, mine)
                    for at in range(0, len(own), query_block):
                        r, c = best(score := product(a[at : at + query_block], b), ids[mine], own[at : at + query_block], k)
                        fresh.append((number[at : at + query_block][r], ids[mine][c], score[r, c]))
                        n += len(r)
                    if n > max(100_000, 3 * every * k):
                        held, fresh, n = _least(*(np.concatenate([h, *f]) for h, f in zip(held, zip(*fresh))), k), [], 0
        if fresh:
            held = _least(*(np.concatenate([h, *f]) for h, f in zip(held, zip(*fresh))), k)
        if len(held[0]):
            part = np.full(len(held[0]), TaskContext.get().partitionId() % groups)
            yield pa.RecordBatch.from_arrays([*map(pa.array, (held[0], part, held[1], held[2]))], names=["query", "part", "vec_id", "score"])

    return run


def _merged(lists: DataFrame, k: int, *keys: str) -> DataFrame:
    """The k best of each key; per key come k rows from each list that meets here."""
    entry = F.struct((-F.col("score")).alias("down"), F.col("vec_id"))
    top = F.slice(F.array_sort(F.collect_list(entry)), 1, k)
    return lists.groupBy(*keys).agg(top.alias("top")).select(*keys, F.posexplode("top")).select(*keys, (F.col("pos") + 1).alias("rank"), F.col("col.vec_id").alias("vec_id"), (-F.col("col.down")).alias("score"))


def _pass(rows: DataFrame, asked: DataFrame, k: int, query_block: int, shard: int) -> DataFrame:
    """query_id, rank, vec_id, score of the queries asked, which the caller has bounded."""
    table = asked.toArrow()
    ids, vectors = table.column("vec_id").to_numpy().astype(np.int64), table.column("v").combine_chunks()
    size = table.column("dim").to_numpy()
    by_dim = {int(d): (ids[s := np.flatnonzero(size == d)], s.astype(np.int64), _rows(vectors, int(d), s)) for d in np.unique(size)}
    spark = rows.sparkSession
    groups = max(1, round(int(spark.conf.get("spark.sql.shuffle.partitions")) ** 0.5))
    lists = rows.select("vec_id", "v").mapInArrow(_tiles(spark.sparkContext.broadcast(by_dim), k, groups, query_block, shard), "query long, part long, vec_id long, score long")
    top = _merged(_merged(lists, k, "query", "part"), k, "query")
    names = spark.createDataFrame(pa.table({"query": np.arange(len(ids)), "query_id": ids}))  # a number and id for each query of the pass
    return top.join(F.broadcast(names), "query").select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def top_k(vectors: DataFrame, every: int = 100, k: int = 10, scale: int = 1024, query_block: int = 256, shard: int = 8192, held: int = 64_000_000) -> DataFrame:
    """query_id, rank, vec_id, score for the rows whose vec_id is divisible by ``every``."""
    rows = usable(vectors, scale)
    asked = rows.filter(F.pmod("vec_id", F.lit(every)) == 0).dropDuplicates(["vec_id", "v"])
    size = asked.agg(F.coalesce(F.sum(F.col("dim") + 2), F.lit(0)).alias("n")).first()["n"] * 8
    passes = max(1, -(-size // held))
    if passes == 1:
        return _pass(rows, asked, k, query_block, shard)
    asked = materialize(asked.withColumn("pass", F.pmod(F.xxhash64("vec_id", "v"), F.lit(passes))), "queries")
    done = None
    for number in range(passes):
        one = materialize(_pass(rows, asked.filter(F.col("pass") == number), k, query_block, shard), "lists")
        done = one if done is None else done.union(one)
    return done
