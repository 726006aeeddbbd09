"""Exact top-k by inner product with a three-phase uniform threshold.

A vector's components are split into m groups; a group is a list of partial scores, and a
score is the sum of its m partial scores. A row that reaches a score tau has a partial score
of at least tau / m in some list, so entries below that uniform cutoff need not be seen.

1. Every partition makes its lists once. The exact scores of the rows that lead a list give
   a bound that rises as the partition streams; entries at or above the cutoff that follows
   from it are kept beside the row, and nothing is multiplied for them again. The k best of
   those scores leave the partition; the k-th best of all is tau, per query.
2. The cutoff tau / m is broadcast for the block of queries. It is at least every
   partition's own, so the kept entries that reach it are all that are needed.
3. A row with such an entry and an upper bound (the cutoff for each part that was not kept)
   of at least tau is resolved: only its missing parts are multiplied, and the k best of each
   partition are merged.

Of many rows with one vector only those that can be among k come into question (the k + 1
least ids); the others are folded before the lists are made, so a frequent vector is no hot
group and keeps no long list of ties. Scores are whole numbers and exact.

Defined cases: rows with a null id or with a vector that is null or holds null or
non-finite components take no part; shorter vectors end in zeros; a repeated row is a
candidate each time, save for its own id; equal scores go to the smaller id; with fewer
than k candidates all are returned; an empty table gives an empty result. Components so
large that a score could pass 63 bits are refused.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bundlemv.llm.vectors import BestLists, chunks, final_lists, finite, matrix, own_cells, query_blocks, width_of
from bundlemv.session import materialise

RESULT = "query_id long, rank int, id long, score long"


def whole_components(v: str, scale: int) -> Column:
    return F.transform(v, lambda x: F.floor(x.cast("double") * scale).cast("long"))


def fold_copies(rows: DataFrame, k: int) -> DataFrame:
    """Rows (id, v) without those that k others of the same vector come before, for every query."""
    ids = Window.partitionBy("v").orderBy("id")
    same = Window.partitionBy("v", "id").orderBy("id")
    near = rows.withColumn("__d", F.dense_rank().over(ids)).where(F.col("__d") <= k + 1)  # a query leaves out its own id
    return near.withColumn("__r", F.row_number().over(same)).where(F.col("__r") <= k).select("id", "v")


def exact_top_k(rows: DataFrame, queries: DataFrame, k: int, groups: int = 2) -> DataFrame:
    """rows, queries: id long, v array<long>, all valid. -> query_id, rank, id, score."""
    found = _found(rows, queries, k, groups)
    if not found:
        return rows.sparkSession.createDataFrame([], RESULT)
    return final_lists(reduce(DataFrame.unionAll, found).where("query_id is not null").select("query_id", "id", "score"), k)


def products(rows: DataFrame, queries: DataFrame, k: int, groups: int = 2) -> DataFrame:
    """One row (lists, resolved): how many partial scores phases 1 and 3 multiply."""
    found = _found(rows, queries, k, groups)
    if not found:
        return rows.sparkSession.createDataFrame([(0, 0)], "lists long, resolved long")
    return reduce(DataFrame.unionAll, found).where("query_id is null").agg(F.coalesce(F.sum("id"), F.lit(0)).alias("lists"), F.coalesce(F.sum("score"), F.lit(0)).alias("resolved"))


def _found(rows: DataFrame, queries: DataFrame, k: int, groups: int) -> list[DataFrame]:
    """Per block of queries: query_id, id, score of the partitions' best; rows without a query_id count products."""
    spark = rows.sparkSession
    width = width_of(rows.unionByName(queries), "v")
    size = rows.unionByName(queries).agg(F.max(F.array_max(F.transform("v", lambda x: F.abs(x))))).first()[0] or 0
    if width * size * size >= 2**62:
        raise ValueError("scores may pass 63 bits")
    # sums below 2**53 are exact in doubles, whose products are much faster
    number = np.float64 if width * size * size < 2**53 else np.int64
    parts = [slice(g * width // groups, (g + 1) * width // groups) for g in range(groups)]
    rows, found = fold_copies(rows, k), []
    for ids, q in query_blocks(queries, width):
        block = spark.sparkContext.broadcast((ids, q.astype(number)))
        lists = materialise(_gather(rows, block, k, width, parts, number), "topk-lists")
        tau = spark.sparkContext.broadcast(_thresholds(lists, k, len(ids)))
        found.append(_resolve(lists, block, tau, k, width, parts, number))
    return found


def _gather(rows: DataFrame, block, k: int, width: int, parts: list[slice], number) -> DataFrame:
    """Phase 1. With an id or v: a row and its kept entries (query, list, partial score). Without: the k best scores of a query."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        query_ids, q = block.value
        n, m, least = len(query_ids), len(parts), np.iinfo(np.int64).min
        best = BestLists(n, k, np.int64)  # named by places, as ids may repeat
        at_row = 0
        for b in chunks(batches):
            ids, x = b.column(0).to_numpy().astype(np.int64), matrix(b.column(1), width, number)
            lists = [(q[:, p] @ x[:, p].T).astype(np.int64) for p in parts]
            own = own_cells(query_ids, ids)
            few = min(k, len(ids))
            leads = []
            for s in lists:
                s[own] = least
                leads.append(np.argpartition(s, len(ids) - few, axis=1)[:, -few:])
            qi, col = np.divmod(np.unique((np.arange(n)[:, None] * len(ids) + np.concatenate(leads, axis=1)).ravel()), len(ids))
            open_ = lists[0][qi, col] > least
            qi, col = qi[open_], col[open_]
            best.add(qi, at_row + col, sum(s[qi, col] for s in lists))
            cut = uniform_cutoff(np.where(best.count == k, best.worst, least), m)[:, None]
            kept = [np.nonzero(((s >= cut) & (s > least)).T) for s in lists]  # by row
            row = np.concatenate([r for r, _ in kept])
            query = np.concatenate([c for _, c in kept]).astype(np.int32)
            group = np.repeat(np.arange(m, dtype=np.int8), [len(r) for r, _ in kept])
            part = np.concatenate([s[c, r] for s, (r, c) in zip(lists, kept)])
            order = np.lexsort((query, row))
            ends = pa.array(np.concatenate([[0], np.cumsum(np.bincount(row, minlength=len(ids)))]), pa.int32())
            cells = pa.array(np.full(len(ids), n * m), pa.int64())
            columns = [b.column(0), b.column(1), *(pa.ListArray.from_arrays(ends, pa.array(z[order])) for z in (query, group, part)), cells]
            yield pa.RecordBatch.from_arrays(columns, names=["id", "v", "q", "g", "s", "cells"])
            at_row += len(ids)
        qi, _, score = best.entries()
        ones = pa.array(np.arange(len(qi) + 1), pa.int32())
        none = pa.nulls(len(qi), pa.int64())
        columns = [none, pa.nulls(len(qi), pa.list_(pa.int64())), *(pa.ListArray.from_arrays(ones, pa.array(z)) for z in (qi.astype(np.int32), np.zeros(len(qi), np.int8), score)), none]
        yield pa.RecordBatch.from_arrays(columns, names=["id", "v", "q", "g", "s", "cells"])

    return rows.mapInArrow(work, "id long, v array<long>, q array<int>, g array<byte>, s array<long>, cells long")


def uniform_cutoff(tau: np.ndarray, m: int) -> np.ndarray:
    """Some part of a score of at least ``tau`` has at least so much; the least number where tau is not known."""
    return np.where(tau == np.iinfo(np.int64).min, tau, -(-tau // m))


def _thresholds(lists: DataFrame, k: int, n: int) -> np.ndarray:
    """tau by query; the least number where fewer than k rows are known. The driver gets a row per query of the block."""
    best = lists.where("id is null").select(F.col("q")[0].alias("q"), F.col("s")[0].alias("s"))
    order = Window.partitionBy("q").orderBy(F.desc("s"))
    out = np.full(n, np.iinfo(np.int64).min)
    for r in best.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).where(F.col("r") == k).collect():
        out[r.q] = r.s
    return out


def _resolve(lists: DataFrame, block, tau, k: int, width: int, parts: list[slice], number) -> DataFrame:
    """Phases 2 and 3: query_id, id, score of each partition's best."""
    m = len(parts)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        query_ids, q = block.value
        known, cut = tau.value, uniform_cutoff(tau.value, m)
        best, multiplied, cells = BestLists(len(query_ids), k, np.int64), 0, 0
        for b in chunks(batches):
            ids, x = b.column(0).to_numpy().astype(np.int64), matrix(b.column(1), width, number)
            cells += int(np.sum(b.column(5).to_numpy()))
            row = np.repeat(np.arange(len(ids)), np.diff(b.column(2).offsets.to_numpy()))
            query, group, part = (b.column(i).flatten().to_numpy() for i in (2, 3, 4))
            enough = part >= cut[query]
            row, query, group, part = row[enough], query[enough], group[enough], part[enough]
            pair, of = np.unique(row * len(query_ids) + query, return_inverse=True)
            row, query = np.divmod(pair, len(query_ids))
            seen, score = np.zeros((len(pair), m), bool), np.zeros(len(pair), np.int64)
            seen[of, group] = True
            np.add.at(score, of, part)
            # where fewer than k rows are known, every part was kept
            reach = (known[query] == np.iinfo(np.int64).min) | (score + (m - seen.sum(axis=1)) * cut[query] >= known[query])
            for g, p in enumerate(parts):
                lack = np.nonzero(reach & ~seen[:, g])[0]
                multiplied += len(lack)
                for i in range(0, len(lack), 1 << 16):
                    some = lack[i : i + (1 << 16)]
                    score[some] += np.einsum("ij,ij->i", q[query[some], p], x[row[some], p]).astype(np.int64)
            best.add(query[reach], ids[row[reach]], score[reach])
        qi, ids, score = best.entries()
        yield pa.RecordBatch.from_arrays([pa.array([*query_ids[qi].tolist(), None], pa.int64()), pa.array(np.append(ids, cells)), pa.array(np.append(score, multiplied))], names=["query_id", "id", "score"])

    return lists.where("id is not null").mapInArrow(work, "query_id long, id long, score long")


def op1(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    table = load_table(spark, sf_dir, "embeddings").where(F.col("vec_id").isNotNull() & finite("embedding"))
    rows = table.select(F.col("vec_id").cast("long").alias("id"), whole_components("embedding", 256).alias("v"))
    out = exact_top_k(rows, rows.where("id % 50 = 0"), k=5)
    return out.select("query_id", "rank", F.col("id").alias("vec_id"), "score")


OP1_SQL = """
with v as (
  select cast(vec_id as bigint) as id, list_transform(embedding, lambda x: floor(256 * cast(x as double))) as v from embeddings
  where vec_id is not null and embedding is not null
    and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0),
s as (
  select q.id as query_id, c.id as vec_id, cast(list_inner_product(q.v, c.v) as bigint) as score
  from v q join v c on q.id <> c.id where q.id % 50 = 0),
r as (select *, row_number() over (partition by query_id order by score desc, vec_id) as rank from s)
select query_id, cast(rank as integer) as rank, vec_id, score from r where rank <= 5
"""
