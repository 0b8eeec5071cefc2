"""Exact top-k by inner product: the threshold algorithm on sorted lists.

Vectors are held in blocks, a batch each; a block has, for every dimension, its
rows sorted by that component.  Queries walk all lists from both ends.  At depth
r every unseen row scores at most the sum, over the dimensions, of the query's
component times the component at depth r of the end that it favours.  A query
stops where that bound is below the kth score it has found, or where no row is
unseen.  Depths double; rows are scored once, when first seen.  The kth score of
earlier blocks carries over to the next ones of the same task.

Queries are gathered in blocks of at most ``query_block`` rows, which are
broadcast (a bound that is kept by counting them); every block is a scan of the
vectors in place.  Nothing but the best k of each query and vector block is
shuffled, and the ranking is limited before its shuffle.  Arithmetic is exact:
scores that could leave 2**53 are summed as 64-bit integers and their bounds get
a margin; where 64 bits may not do, the search fails rather than be wrong.

How far the walk saves work depends on the data: with many dimensions of equal
spread (unit vectors without structure) the bound falls slowly and most rows are
seen before it stops (``walk`` measures both).

Defined cases: vectors that are null or hold a null or a non-finite component
take no part, nor do rows whose id is null; shorter vectors count as padded
with zeros; rows that share a query's id are its own and are no candidates;
repeated rows are candidates each, repeated query rows are one query, and
different vectors under one query id are queries of their own, with five rows
each; a query without candidates has no rows; an empty table gives none.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

LOW = -(1 << 62)


def _matrix(column: pa.Array, scale: float) -> tuple[np.ndarray, np.ndarray]:
    """(row numbers that take part, their integer components)."""
    column = column.cast(pa.large_list(pa.float64()))
    size = pc.list_value_length(column).fill_null(0).to_numpy(zero_copy_only=False)
    flat = column.flatten()
    row = np.repeat(np.arange(len(column)), size)
    values = flat.fill_null(np.nan).to_numpy(zero_copy_only=False) if len(flat) else np.zeros(0)
    bad = np.zeros(len(column), bool)
    bad[row[~np.isfinite(values)]] = True
    ok = np.flatnonzero(column.is_valid().to_numpy(zero_copy_only=False) & ~bad)
    out = np.zeros((len(column), int(size.max(initial=0))))
    out[row, np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)] = np.floor(np.where(np.isfinite(values), values, 0) * scale)
    return ok, out[ok]


def _pack(scale: float):
    def run(batches):
        for batch in batches:
            ids = np.asarray(batch.column(0))
            ok, m = _matrix(batch.column(1), scale)
            if len(ok):
                yield pa.RecordBatch.from_arrays([pa.array([m.shape[1]], pa.int32()), pa.array([ids[ok].astype("<i8").tobytes()], pa.binary()), pa.array([m.astype("<f8").tobytes()], pa.binary())], ["dims", "ids", "cells"])

    return run


def _query_blocks(packed: DataFrame, most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Queries in runs of at most ``most``, one batch at a time at the driver."""
    ids, rows, n = [], [], 0

    def close():
        width = max(r.shape[1] for r in rows)
        return np.concatenate(ids), np.concatenate([np.pad(r, ((0, 0), (0, width - r.shape[1]))) for r in rows])

    for dims, i, cells in packed.toLocalIterator():
        i = np.frombuffer(i, "<i8")
        m = np.frombuffer(cells, "<f8").reshape(len(i), dims)
        for at in range(0, len(i), most):
            part = slice(at, at + most)
            if n and n + len(i[part]) > most:
                yield close()
                ids, rows, n = [], [], 0
            ids.append(i[part])
            rows.append(m[part])
            n += len(i[part])
    if n:
        yield close()


class Lists:
    """The sorted lists of one block of vectors."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray):
        self.ids, self.rows = ids, rows
        self.order = np.argsort(rows, axis=0, kind="stable")
        self.sorted = np.take_along_axis(rows, self.order, 0)

    def top(self, query_ids: np.ndarray, queries: np.ndarray, k: int, floor: np.ndarray, walk: list | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(query number, vector id, score) of the best k of each query that
        may rank (score at least ``floor``), and the new floors.  ``walk`` gets
        (depth, rows scored, queries that stopped by their bound) a step."""
        n = len(self.rows)
        d = min(self.rows.shape[1], queries.shape[1])
        q, rows, lists = queries[:, :d], self.rows[:, :d], self.sorted[:, :d]
        most = float(np.abs(q).max(initial=0)) * float(np.abs(rows).max(initial=0)) * max(d, 1)
        if most >= 2**62:
            raise OverflowError("scores beyond 64-bit integers")
        kind = np.float64 if most < 2**53 else np.int64
        margin = 0.0 if most < 2**53 else most * 1e-12
        exact, cells = q.astype(kind), rows.astype(kind)
        up, down = np.maximum(q, 0), np.minimum(q, 0)
        seen = np.zeros(n, bool)
        kth = floor.copy()
        kept = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        waiting, depth = np.arange(len(q)), min(n, max(2 * k, 8))
        while len(waiting) and not seen.all():
            fresh = np.zeros(n, bool)
            fresh[self.order[:depth, :d].ravel()] = True
            fresh[self.order[n - depth :, :d].ravel()] = True
            if not d:
                fresh[:] = True
            new = np.flatnonzero(fresh & ~seen)
            seen |= fresh
            score = (exact[waiting] @ cells[new].T).astype(np.int64)
            score[query_ids[waiting][:, None] == self.ids[new][None, :]] = LOW
            least = kth[waiting]
            if len(new) > k:
                least = np.maximum(least, np.partition(score, len(new) - k, axis=1)[:, len(new) - k])
            a, b = np.nonzero((score >= least[:, None]) & (score > LOW))
            one = np.concatenate([kept[0], waiting[a]]), np.concatenate([kept[1], self.ids[new[b]]]), np.concatenate([kept[2], score[a, b]])
            order = np.lexsort((one[1], -one[2], one[0]))
            of = one[0][order]
            rank = np.arange(len(of)) - np.searchsorted(of, of)
            order = order[rank < k]
            kept = tuple(c[order] for c in one)
            last = rank[rank < k] == k - 1
            kth[kept[0][last]] = np.maximum(kth[kept[0][last]], kept[2][last])
            bound = up[waiting] @ lists[n - depth] + down[waiting] @ lists[depth - 1] + margin
            stop = bound < kth[waiting]
            if walk is not None:
                walk.append((depth, len(new), int(stop.sum())))
            waiting = waiting[~stop]
            depth = min(n, depth * 2)
        return *kept, kth


def _search(k: int, scale: float, block_b):
    def run(batches):
        ids, queries, floor = *block_b.value, None
        for batch in batches:
            ok, m = _matrix(batch.column(1), scale)
            if not len(ok):
                continue
            floor = np.full(len(ids), LOW + 1) if floor is None else floor
            a, b, s, floor = Lists(np.asarray(batch.column(0))[ok], m).top(ids, queries, k, floor)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(ids[a]), pa.array(a), pa.array(b), pa.array(s)], ["query_id", "number", "vec_id", "score"])

    return run


def exact_top_k(vectors: DataFrame, is_query: str, k: int = 5, scale: float = 256.0, query_block: int = 32_768, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score) for the rows that fulfil ``is_query``
    (SQL over the column ``id``), against all rows."""
    src = vectors.select(F.col(id_col).cast("bigint").alias("id"), F.col(vector_col).alias("v")).where("id is not null")
    packed = src.where(is_query).dropDuplicates(["id", "v"]).mapInArrow(_pack(scale), "dims int, ids binary, cells binary")
    sc, best = vectors.sparkSession.sparkContext, None
    for n, block in enumerate(_query_blocks(packed, query_block)):
        one = src.mapInArrow(_search(k, scale, sc.broadcast(block)), "query_id bigint, number bigint, vec_id bigint, score bigint").withColumn("block", F.lit(n))
        best = one if best is None else best.unionByName(one)
    if best is None:
        return vectors.sparkSession.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score bigint")
    order = Window.partitionBy("query_id", "block", "number").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
