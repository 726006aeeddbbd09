"""Quality by regularised quadratic discriminant over transformed document statistics.

Per document a vector of log and square-root transformed statistics of the whole text.
Each class has a mean and a covariance, shrunk towards the pooled covariance and then
towards its diagonal; the Cholesky factors are computed once and go with the scorer. The
score is the logistic of the difference of the two log densities plus the log prior odds.

Training uses all labelled rows: class sums and cross products are added up in partitions
and then by key, so the driver sees a table of fixed size.

Defined cases: null and empty texts have the statistics of the empty text and get a score;
repeated rows score alike; labels that are null are left out, ids with two labels count for
both; with fewer than two classes every score is the share of label 1 (0.5 without labels).
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bundlemv.llm.common import numpy_of
from bundlemv.session import materialise

NAMES = (
    "log_bytes", "log_words", "word_len", "upper", "digit", "punct", "symbol", "space", "newline", "high_byte",
    "distinct_words", "distinct_lines", "line_len", "end_marks", "word_len_spread", "top_word", "adjacent_repeat",
)


def _classes() -> np.ndarray:
    """256 x 9: upper, lower, digit, plain punctuation, other symbols, space, newline, high byte, sentence end."""
    m = np.zeros((256, 9))
    for b in range(256):
        c = chr(b)
        kind = (
            0 if "A" <= c <= "Z" else 1 if "a" <= c <= "z" else 2 if c.isdigit() and b < 128 else 6 if c == "\n" else 5 if b < 33
            else 7 if b >= 128 else 3 if c in ".,;:!?'\"()-" else 4
        )
        m[b, kind] = 1
        m[b, 8] = c in ".!?"
    return m


_CLASS = _classes()


def text_statistics(data: bytes | None) -> np.ndarray:
    data = data or b""
    n = len(data)
    up, low, dig, punct, sym, space, newline, high, ends = np.bincount(np.frombuffer(data, np.uint8), minlength=256) @ _CLASS
    words = data.split()
    nw = len(words)
    lens = np.fromiter(map(len, words), np.float64, nw) if nw else np.zeros(1)
    counts: dict[bytes, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    same = sum(map(bytes.__eq__, words, words[1:]))
    lines = [x for x in data.split(b"\n") if x.strip()]
    some = max(n, 1)
    return np.array([
        np.log1p(n), np.log1p(nw), np.log1p(lens.mean()), np.sqrt(up / max(up + low, 1)), np.sqrt(dig / some), np.sqrt(punct / some),
        np.sqrt(sym / some), np.sqrt(space / some), np.sqrt(newline / some), np.sqrt(high / some),
        np.sqrt(len(counts) / max(nw, 1)), len(set(lines)) / max(len(lines), 1), np.log1p(n / max(len(lines), 1)), np.sqrt(ends / max(nw, 1)),
        np.log1p(lens.std()), np.sqrt(max(counts.values(), default=0) / max(nw, 1)), np.sqrt(same / max(nw, 1)),
    ])


def document_statistics(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, stats array<double>."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.array([text_statistics(t.as_py()) for t in b.column(1)]).reshape(-1, len(NAMES))
            flat = pa.array(x.ravel())
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * len(NAMES), pa.int32()), flat)
            yield pa.RecordBatch.from_arrays([b.column(0), lists], names=[id_col, "stats"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(text_col).cast("binary").alias("__text")).mapInArrow(work, f"`{id_col}` {kind}, stats array<double>")


@dataclass(frozen=True)
class Discriminant:
    """prior: log odds of label 1; per class a mean, the inverse Cholesky factor of its covariance and half its log determinant."""

    prior: float
    means: tuple
    factors: tuple
    half_log_dets: tuple

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.prior)
        for sign, mean, inv, half in zip((-1, 1), self.means, self.factors, self.half_log_dets):
            y = (x - mean) @ inv.T
            z += sign * (-0.5 * np.einsum("ij,ij->i", y, y) - half)
        return 1 / (1 + np.exp(-np.clip(z, -60, 60)))


def fit_discriminant(moments: dict[int, np.ndarray], shrink: float, ridge: float) -> Discriminant:
    """moments: by class the sum of outer products of (1, x)."""
    d = len(NAMES)
    n = {c: moments[c][0, 0] if c in moments else 0.0 for c in (0, 1)}
    if min(n.values()) < 2:
        share = (n[1] + 0.5) / (n[0] + n[1] + 1) if n[0] + n[1] else 0.5
        return Discriminant(float(np.log(share / (1 - share))), (), (), ())
    means, covs = [], []
    for c in (0, 1):
        mean = moments[c][0, 1:] / n[c]
        means.append(mean)
        covs.append(moments[c][1:, 1:] / n[c] - np.outer(mean, mean))
    pooled = (n[0] * covs[0] + n[1] * covs[1]) / (n[0] + n[1])
    scale = np.maximum(np.diag(pooled), 1e-8)
    factors, halves = [], []
    for c in (0, 1):
        weight = min(1.0, shrink + d / (d + n[c]))  # few rows lean on the pooled covariance
        cov = (1 - weight) * covs[c] + weight * pooled
        cov = (1 - ridge) * cov + ridge * np.diag(scale) + 1e-9 * np.eye(d)
        low = np.linalg.cholesky(cov)
        factors.append(np.linalg.inv(low))
        halves.append(float(np.log(np.diag(low)).sum()))
    return Discriminant(float(np.log(n[1] / n[0])), tuple(means), tuple(factors), tuple(halves))


def class_moments(rows: DataFrame) -> dict[int, np.ndarray]:
    """rows: label int, stats. Sums of outer products by class; partitions send one row per class and entry."""
    d = len(NAMES) + 1

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = np.zeros((2, d, d))
        for b in batches:
            label, x = b.column(0).to_numpy(zero_copy_only=False), numpy_of(b.column(1), d - 1)
            x = np.hstack([np.ones((len(x), 1)), x])
            for c in (0, 1):
                own = x[label == c]
                sums[c] += own.T @ own
        flat = sums.reshape(2, -1)
        for c in (0, 1):
            if flat[c, 0]:
                yield pa.RecordBatch.from_arrays([pa.array(np.full(d * d, c), pa.int32()), pa.array(np.arange(d * d), pa.int32()), pa.array(flat[c])], names=["label", "k", "v"])

    added = rows.mapInArrow(work, "label int, k int, v double").groupBy("label", "k").agg(F.sum("v").alias("v"))
    out: dict[int, np.ndarray] = {}
    for r in added.collect():  # 2 x (statistics + 1)^2 rows
        out.setdefault(r.label, np.zeros(d * d))[r.k] = r.v
    return {c: v.reshape(d, d) for c, v in out.items()}


def learn(stats: DataFrame, labels: DataFrame, id_col: str = "doc_id", label_col: str = "quality", shrink: float = 0.1, ridge: float = 0.02, where: Column | None = None) -> Discriminant:
    """A discriminant from the labelled rows of ``stats`` (all of them that ``where`` admits)."""
    known = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull())
    if where is not None:
        known = known.where(where)
    rows = stats.join(known.select(id_col, F.col(label_col).cast("int").alias("label")), id_col)
    return fit_discriminant(class_moments(rows.select("label", "stats")), shrink, ridge)


def score(stats: DataFrame, model: Discriminant, id_col: str = "doc_id") -> DataFrame:
    """id_col, score."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.score(numpy_of(b.column(1), len(NAMES))))], names=[id_col, "score"])

    kind = stats.schema[id_col].dataType.simpleString()
    return stats.select(id_col, "stats").mapInArrow(work, f"`{id_col}` {kind}, score double")


def remainder_of(id_col: str, n: int) -> Column:
    """crc32 of the id as text, modulo n; null for a null id."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % n


def quality_scores(docs: DataFrame, labels: DataFrame, train_on: Column | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, score in 0 to 1, predicted int."""
    stats = materialise(document_statistics(docs, id_col, text_col), "quality-stats")
    scored = score(stats, learn(stats, labels, id_col, where=train_on), id_col)
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def filter_quality(docs: DataFrame, labels: DataFrame, train_on: Column | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose text is predicted to have label 1; columns unchanged.

    A text is read and measured once: the rows are written with their statistics.
    """

    @F.arrow_udf("array<double>")
    def measured(texts: pa.Array) -> pa.Array:
        x = np.array([text_statistics(t.as_py()) for t in texts]).reshape(-1, len(NAMES))
        return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * len(NAMES), pa.int32()), pa.array(x.ravel()))

    # one column holds the whole row, so that no name clashes
    rows = docs.select(F.struct(*docs.columns).alias("doc"), F.col(id_col).alias(f"{id_col}"), measured(F.col(text_col).cast("binary")).alias("stats"))
    rows = materialise(rows, "quality-rows")
    model = learn(rows.select(id_col, "stats"), labels, id_col, where=train_on)

    @F.arrow_udf("boolean")
    def good(stats: pa.Array) -> pa.Array:
        return pa.array(model.score(numpy_of(stats, len(NAMES))) >= 0.5)

    return rows.where(good("stats")).select("doc.*")


def op6(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    out = quality_scores(load_table(spark, sf_dir, "documents"), load_table(spark, sf_dir, "labels"), remainder_of("doc_id", 3) != 1)
    held = F.coalesce(remainder_of("doc_id", 3) == 1, F.lit(False))
    return out.select("doc_id", held.alias("held_out"), "score", "predicted")
