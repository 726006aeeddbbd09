"""Approximate nearest neighbours by additive quantisation.

A vector is coded as a sum of one word from each of ``books`` full-dimensional codebooks.

* Codebooks are fitted on a bounded sample (``SAMPLE`` vectors, the first by a hash of the
  id): k-means on the residuals of the books before, then rounds of beam coding and a least
  squares fit of all words at once.
* Every row is coded by beam search over the residuals and stored with its norms: that of
  its decoded vector (for distances) and that of what the code leaves out.
* A query scores rows through one table of word scores per book. First every partition
  gives the k best estimates per query with their exact scores; the k-th best of those is
  the query's bar. Then a row is reranked by its exact score if its estimate, plus a margin
  from the stored remainder's norm, reaches the bar, or if it is among the k best estimates of
  its partition. The margin follows the remainder (and covers copies of the query, for which the
  remainder is not in any direction), so tight clusters get long short lists and no row count
  is fixed; ``reranked`` counts them.

Defined cases: rows with a null id or a vector that is null, zero or holds null or
non-finite components take no part; shorter vectors end in zeros; a repeated row is a
candidate each time, save for its own id; equal scores go to the smaller id; with fewer
than k candidates all are returned; an empty table gives an empty result.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bundlemv.llm.vectors import BestLists, chunks, final_lists, finite, matrix, own_cells, query_blocks, width_of
from bundlemv.session import materialise

#: Vectors that codebooks are fitted on, at most, and their bytes.
SAMPLE, SAMPLE_BYTES = 8192, 64 << 20
BOOKS, WORDS, BEAM = 16, 128, 4
#: Margin in standard deviations of an estimate whose remainder points anywhere.
MARGIN = 3.0
#: Least cosine of a query with the decoded form of a row that may be its copy.
NEAR = 0.5
METRICS = ("inner_product", "euclidean")


def encode(x: np.ndarray, books: np.ndarray, beam: int = BEAM) -> np.ndarray:
    """n x books codes: each step keeps the ``beam`` partial sums that leave the least residual."""
    n, (m, words, d) = len(x), books.shape
    residual, codes = x[:, None, :], np.zeros((n, 1, 0), np.uint8)
    for book in books:
        width = residual.shape[1]
        cost = (residual**2).sum(2)[:, :, None] - 2 * residual.reshape(-1, d).dot(book.T).reshape(n, width, words) + (book**2).sum(1)
        cost = cost.reshape(n, -1)
        keep = min(beam, cost.shape[1])
        at = np.argpartition(cost, keep - 1, axis=1)[:, :keep]
        from_, word = at // words, at % words
        rows = np.arange(n)[:, None]
        residual = residual[rows, from_] - book[word]
        codes = np.concatenate([codes[rows, from_], word[:, :, None].astype(np.uint8)], axis=2)
    best = np.argmin((residual**2).sum(2), axis=1)
    return codes[np.arange(n), best]


def decode(codes: np.ndarray, books: np.ndarray) -> np.ndarray:
    return sum(book[codes[:, i]] for i, book in enumerate(books))


def _k_means(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 8) -> np.ndarray:
    centre = x[rng.choice(len(x), k, replace=len(x) < k)].copy()
    for _ in range(rounds):
        near = np.argmin((centre**2).sum(1) - 2 * x @ centre.T, axis=1)
        n = np.bincount(near, minlength=k)
        total = np.zeros_like(centre)
        np.add.at(total, near, x)
        centre = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], x[rng.choice(len(x), k)])
    return centre


def fit_books(x: np.ndarray, books: int = BOOKS, words: int = WORDS, rounds: int = 2, seed: int = 11) -> np.ndarray:
    rng, residual, out = np.random.default_rng(seed), x.copy(), []
    for _ in range(books):
        out.append(_k_means(residual, words, rng))
        residual -= out[-1][np.argmin((out[-1] ** 2).sum(1) - 2 * residual @ out[-1].T, axis=1)]
    out = np.array(out)
    for _ in range(rounds):
        codes = encode(x, out)
        flat = codes + np.arange(books) * words
        one = np.zeros((len(x), books * words))
        np.put_along_axis(one, flat.astype(np.int64), 1.0, axis=1)
        gram = one.T @ one + 0.1 * np.eye(books * words)
        out = np.linalg.solve(gram, one.T @ x + 0.1 * out.reshape(books * words, -1)).reshape(out.shape)
    return out


@dataclass
class AdditiveIndex:
    """rows: id, v, code (bytes), norm2 (of the decoded vector), rest (norm of what the code leaves out)."""

    rows: DataFrame
    books: np.ndarray

    @property
    def width(self) -> int:
        return self.books.shape[2]


def build_index(rows: DataFrame, books: int = BOOKS, words: int = WORDS, beam: int = BEAM, sample: int = SAMPLE) -> AdditiveIndex | None:
    """Index every row (id long, v array<double>); None if there is none."""
    width = width_of(rows, "v")
    some = rows.orderBy(F.xxhash64("id"), "id").limit(max(1, min(sample, SAMPLE_BYTES // (8 * max(width, 1))))).select("v").toArrow().combine_chunks()
    if not some.num_rows or not width:
        return None
    cb = fit_books(matrix(some.column("v").chunk(0), width), books, words)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in chunks(batches):
            x = matrix(b.column(1), width)
            codes = encode(x, cb, beam)
            near = decode(codes, cb)
            yield pa.RecordBatch.from_arrays([
                b.column(0), b.column(1), pa.array([c.tobytes() for c in codes], pa.binary()),
                pa.array((near**2).sum(1)), pa.array(np.sqrt(((x - near) ** 2).sum(1))),
            ], names=["id", "v", "code", "norm2", "rest"])

    coded = rows.mapInArrow(work, "id long, v array<double>, code binary, norm2 double, rest double")
    return AdditiveIndex(materialise(coded, "additive-index"), cb)


def search(index: AdditiveIndex | None, queries: DataFrame, k: int, metric: str = "inner_product", margin: float = MARGIN) -> DataFrame:
    """query_id, rank, id, score: inner product, or minus the squared distance; queries: id, v."""
    found = _found(index, queries, k, metric, margin)
    if not found:
        return queries.sparkSession.createDataFrame([], "query_id long, rank int, id long, score double")
    return final_lists(reduce(DataFrame.unionAll, found).where("query_id is not null"), k)


def reranked(index: AdditiveIndex, queries: DataFrame, k: int, metric: str = "inner_product", margin: float = MARGIN) -> float:
    """Share of all pairs of a query and a row whose exact score is taken in the search."""
    found = reduce(DataFrame.unionAll, _found(index, queries, k, metric, margin))
    taken = found.where("query_id is null").agg(F.sum("id")).first()[0] or 0
    return taken / max(1, index.rows.count() * queries.select("id").distinct().count())


def _found(index: AdditiveIndex | None, queries: DataFrame, k: int, metric: str, margin: float) -> list[DataFrame]:
    """Per block of queries: query_id, id, score of the partitions' best; rows without a query_id count exact scores."""
    if metric not in METRICS:
        raise ValueError(f"metric is one of {METRICS}")
    found = []
    for block in query_blocks(queries, index.width) if index is not None else ():
        held = queries.sparkSession.sparkContext.broadcast(block)
        bars = queries.sparkSession.sparkContext.broadcast(_bars(index, held, k, metric, len(block[0])))
        found.append(_search_block(index, held, bars, k, metric, margin))
    return found


class _Estimates:
    """What a block of queries needs to score coded rows."""

    def __init__(self, query_ids: np.ndarray, q: np.ndarray, books: np.ndarray, far: bool):
        self.query_ids, self.q, self.far = query_ids, q, far
        self.tables = [(q @ book.T).astype(np.float32) for book in books]
        self.norm2 = (q**2).sum(1)
        self.spread = np.sqrt(self.norm2 / books.shape[2]).astype(np.float32) * (2 if far else 1)

    def of(self, b: pa.RecordBatch, ids: np.ndarray) -> np.ndarray:
        """Queries x rows; minus infinity for a query's own id."""
        codes = np.frombuffer(b"".join(b.column(2).to_pylist()), np.uint8).reshape(len(ids), -1)
        guess = np.take(self.tables[0], codes[:, 0], axis=1)
        for i, t in enumerate(self.tables[1:], 1):
            guess += np.take(t, codes[:, i], axis=1)
        if self.far:  # the stored norms turn products into distances
            guess = 2 * guess - b.column(3).to_numpy().astype(np.float32)[None, :] - self.norm2.astype(np.float32)[:, None]
        guess[own_cells(self.query_ids, ids)] = -np.inf
        return guess

    def slack(self, b: pa.RecordBatch, margin: float, guess: np.ndarray) -> np.ndarray:
        """How far below its exact score an estimate may be, by query and row.

        The remainder stands in any direction to most queries, but along one that (nearly) is
        the row itself; such a query has at least NEAR as its cosine with the decoded row.
        """
        rest, norm = b.column(4).to_numpy(), np.sqrt(b.column(3).to_numpy())
        out = self.spread[:, None] * rest.astype(np.float32)[None, :]
        if self.far:
            out *= margin
        else:
            copy = guess >= (NEAR * np.sqrt(self.norm2)).astype(np.float32)[:, None] * norm.astype(np.float32)[None, :]
            out = np.where(copy, np.maximum(margin * out, out + (rest**2).astype(np.float32)[None, :]), margin * out)
        out += (np.sqrt(self.norm2)[:, None] * (4e-6 * (norm + rest))[None, :]).astype(np.float32)  # single precision
        if self.far:
            out += (rest**2 + 4e-6 * norm**2).astype(np.float32)[None, :] + (4e-6 * self.norm2).astype(np.float32)[:, None]
        return out

    def leading(self, guess: np.ndarray, best: BestLists) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, row, estimate) of a chunk's best estimates that may enter the lists."""
        few = min(best.k, guess.shape[1])
        col = np.argpartition(guess, guess.shape[1] - few, axis=1)[:, -few:]
        qi, col = np.repeat(np.arange(len(guess)), few), col.ravel()
        val = guess[qi, col].astype(np.float64)
        good = (val > -np.inf) & (val >= best.worst[qi])
        return qi[good], col[good], val[good]

    def exact(self, qi: np.ndarray, x: np.ndarray, col: np.ndarray) -> np.ndarray:
        out = np.empty(len(qi))
        for i in range(0, len(qi), 1 << 16):
            some = slice(i, i + (1 << 16))
            q, v = self.q[qi[some]], x[col[some]]
            out[some] = -((q - v) ** 2).sum(1) if self.far else np.einsum("ij,ij->i", q, v)
        return out


def _bars(index: AdditiveIndex, block, k: int, metric: str, n: int) -> np.ndarray:
    """A lower bound of each query's k-th best score, from the exact scores of the partitions' best estimates. The driver gets a row per query of the block."""
    books, width = index.books, index.width

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        est = _Estimates(*block.value, books, metric == "euclidean")
        best, at_row = BestLists(len(est.q), k), 0
        for b in chunks(batches):
            ids = b.column(0).to_numpy().astype(np.int64)
            qi, col, val = est.leading(est.of(b, ids), best)
            best.add(qi, at_row + col, val, est.exact(qi, matrix(b.column(1), width), col))
            at_row += len(ids)
        qi, j = np.nonzero(np.arange(k)[None, :] < best.count[:, None])
        yield pa.RecordBatch.from_arrays([pa.array(qi, pa.int32()), pa.array(best.note[qi, j])], names=["q", "score"])

    lists = index.rows.mapInArrow(work, "q int, score double")
    ranked = lists.withColumn("r", F.row_number().over(Window.partitionBy("q").orderBy(F.desc("score")))).where(F.col("r") <= k)
    out = np.full(n, -np.inf)
    for r in ranked.where(F.col("r") == k).collect():
        out[r.q] = r.score
    return out


def _search_block(index: AdditiveIndex, block, bars, k: int, metric: str, margin: float) -> DataFrame:
    books, width = index.books, index.width

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        est = _Estimates(*block.value, books, metric == "euclidean")
        best, lead, taken, at_row = BestLists(len(est.q), k), BestLists(len(est.q), k), 0, 0
        for b in chunks(batches):
            ids = b.column(0).to_numpy().astype(np.int64)
            guess = est.of(b, ids)
            li, lcol, val = est.leading(guess, lead)
            lead.add(li, at_row + lcol, val)
            at_row += len(ids)
            bar = np.maximum(bars.value, np.where(best.count == k, best.worst, -np.inf))
            guess += est.slack(b, margin, guess)
            keep = (guess >= bar[:, None]) & (guess > -np.inf)
            keep[li, lcol] = True
            qi, col = np.nonzero(keep)
            taken += len(qi)
            best.add(qi, ids[col], est.exact(qi, matrix(b.column(1), width), col))
        qi, ids, score = best.entries()
        yield pa.RecordBatch.from_arrays([pa.array([*est.query_ids[qi].tolist(), None], pa.int64()), pa.array(np.append(ids, taken)), pa.array(np.append(score, 0.0))], names=["query_id", "id", "score"])

    return index.rows.mapInArrow(work, "query_id long, id long, score double")


def op8(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    table = load_table(spark, sf_dir, "embeddings").where(F.col("vec_id").isNotNull() & finite("embedding") & F.exists("embedding", lambda x: x != 0))
    rows = table.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("v"))
    out = search(build_index(rows), rows.where("id % 20 = 0"), k=20)
    return out.select("query_id", "rank", F.col("id").alias("vec_id"), "score")
