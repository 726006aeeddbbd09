"""What the two vector searches share: valid rows, blocks of queries, local and final lists.

A search holds a stated query set against all rows in blocks: a block of about
``BLOCK_QUERIES`` queries (fewer of wide vectors, within ``BLOCK_BYTES``) is broadcast, every partition keeps its best ``k`` per query while it streams its rows, and one
small sort per query merges the partitions' lists.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

BLOCK_QUERIES = 4096
#: Rows that a partition holds against a block at once.
CHUNK = 2048
#: Bytes of a block of queries, at most; wide vectors make smaller blocks.
BLOCK_BYTES = 128 << 20


def finite(v: str) -> Column:
    """Not null and without null, NaN or infinite components."""
    odd = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
    return F.col(v).isNotNull() & ~F.exists(v, lambda x: F.coalesce(odd(x), F.lit(True)))


def width_of(rows: DataFrame, v: str) -> int:
    return rows.agg(F.max(F.size(v))).first()[0] or 0


def matrix(lists: pa.Array, width: int, dtype=np.float64) -> np.ndarray:
    """A list column as a matrix; shorter vectors end in zeros."""
    flat = lists.flatten().to_numpy(zero_copy_only=False).astype(dtype)
    if len(flat) == len(lists) * width:
        return flat.reshape(-1, width)
    size = np.diff(lists.offsets.to_numpy())
    out = np.zeros((len(lists), width), dtype)
    out[np.repeat(np.arange(len(lists)), size), np.arange(len(flat)) - np.repeat(np.cumsum(size) - size, size)] = flat
    return out


def query_blocks(queries: DataFrame, width: int, block: int = BLOCK_QUERIES) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(ids, matrix) of blocks of queries (columns id, v), one at a time. An id that repeats is one query, with its least vector."""
    queries = queries.groupBy("id").agg(F.min("v").alias("v"))
    block = max(1, min(block, BLOCK_BYTES // (8 * max(width, 1))))
    n = math.ceil(queries.count() / block)
    for i in range(n):
        own = queries.where(F.pmod(F.xxhash64("id"), F.lit(n)) == i).toArrow().combine_chunks()
        if own.num_rows:
            lists = own.column("v").chunk(0)
            order = np.argsort(own.column("id").to_numpy())
            yield own.column("id").to_numpy()[order].astype(np.int64), matrix(lists, width)[order]


def chunks(batches: Iterator[pa.RecordBatch], size: int = CHUNK) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for i in range(0, b.num_rows, size):
            yield b.slice(i, size)


def own_cells(query_ids: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Cells (query, row) where a row has the query's own id; query_ids ascend."""
    at = np.searchsorted(query_ids, ids)
    at[at == len(query_ids)] = 0
    col = np.nonzero(query_ids[at] == ids)[0] if len(query_ids) else np.zeros(0, np.int64)
    return at[col], col


class BestLists:
    """The best k rows per query so far: larger scores first, then smaller ids."""

    def __init__(self, n: int, k: int, dtype=np.float64):
        self.k, self.low = k, np.iinfo(dtype).min if np.issubdtype(dtype, np.integer) else -np.inf
        self.score, self.id = np.full((n, k), self.low, dtype), np.full((n, k), np.iinfo(np.int64).max)
        self.note = np.zeros((n, k))
        self.count = np.zeros(n, np.int64)

    @property
    def worst(self) -> np.ndarray:
        """Score of the k-th; the least value while there are fewer."""
        return self.score[:, -1]

    def add(self, q: np.ndarray, ids: np.ndarray, score: np.ndarray, note: np.ndarray | None = None) -> None:
        """Entries by query; a note, if any, stays with its entry."""
        some = score >= self.worst[q]
        note = np.zeros(len(q)) if note is None else note
        q, ids, score, note = q[some], ids[some], score[some], note[some]
        if not len(q):
            return
        rows = np.unique(q)
        held = np.arange(self.k)[None, :] < self.count[rows][:, None]
        q = np.concatenate([q, np.repeat(rows, self.k)[held.ravel()]])
        ids = np.concatenate([ids, self.id[rows].ravel()[held.ravel()]])
        score = np.concatenate([score, self.score[rows].ravel()[held.ravel()]])
        note = np.concatenate([note, self.note[rows].ravel()[held.ravel()]])
        order = np.lexsort((ids, -score, q))
        q, ids, score, note = q[order], ids[order], score[order], note[order]
        place = np.arange(len(q)) - np.searchsorted(q, q)
        top = place < self.k
        self.score[rows], self.id[rows] = self.low, np.iinfo(np.int64).max
        self.score[q[top], place[top]], self.id[q[top], place[top]], self.note[q[top], place[top]] = score[top], ids[top], note[top]
        self.count[rows] = np.bincount(q[top], minlength=len(self.count))[rows]

    def entries(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        q, j = np.nonzero(np.arange(self.k)[None, :] < self.count[:, None])
        return q, self.id[q, j], self.score[q, j]


def final_lists(found: DataFrame, k: int) -> DataFrame:
    """query_id, id, score -> query_id, rank, id, score: the best k of all partitions' lists."""
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "id", "score")
