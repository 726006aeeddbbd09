"""Language identification as inference of a mixture of languages.

Training counts hashed byte n-grams per language and smooths them into log likelihoods. A
text is a bag of words; the likelihood of a word under a language is that of its n-grams.
Expectation-maximisation estimates the document's language proportions from the words.
The language set is chosen by penalised likelihood: languages join in the order of their
proportions, and a set of m languages pays ``penalty`` x (m - 1) x log(words + 1) / 2. Sets
of all sizes are in question, up to all languages; a text is done with when not even the
likelihood of the fit over all languages would pay for a larger set. The prediction is the
language of the largest proportion in the chosen set.

Training reads at most about ``PER_LANGUAGE`` documents of each language, drawn by a hash
of the id with a rate from the counts over all rows; the tables it makes have ``BUCKETS``
rows per language.

Defined cases: null texts and texts without a letter are ``und`` with score 0; rows with a
null language or id teach nothing; without any training row every text is ``und``; ties go
to the language that is first in order; long texts count whole; repeated rows come back
once each; an empty table gives an empty result.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BUCKETS = 1 << 16
ORDERS = (2, 3)
PER_LANGUAGE = 4000
UNKNOWN = "und"
LETTER = regex.compile(r"\p{L}")
#: Iterations of each fit.
ROUNDS = 12
#: Bytes of text whose words are fitted at once.
SLAB = 1 << 21

# Byte classes: ASCII letters fold to lower case and bytes beyond ASCII are letters; all else parts words.
_FOLD = np.array([b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256)], np.uint8)


def grams(data: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
    """Folded bytes -> (word number of each byte, -1 outside words; buckets of the n-grams that end at each byte, by order).

    An n-gram may begin in the blanks before its word; beyond those it holds no other word.
    """
    b = _FOLD[data]
    letter = b != 32
    start = letter & np.concatenate([[True], ~letter[:-1]])
    word = np.where(letter, np.cumsum(start) - 1, -1)
    wide, out = b.astype(np.uint32), []
    for n in ORDERS:
        h = np.full(len(b), n, np.uint32)
        for k in range(n - 1, -1, -1):
            past = np.concatenate([np.full(k, 32, np.uint32), wide])[: len(b)]
            h = (h * np.uint32(0x01000193)) ^ past
        h ^= h >> np.uint32(15)
        out.append((h * np.uint32(0x85EBCA6B)) >> np.uint32(16))
    return word, out


@dataclass(frozen=True)
class LanguageModel:
    languages: tuple[str, ...]
    table: np.ndarray  # BUCKETS x languages, log likelihoods

    def word_likelihoods(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(first byte of each word, words x languages log likelihoods)."""
        word, buckets = grams(data)
        starts = np.nonzero((word >= 0) & (np.concatenate([[-1], word[:-1]]) != word))[0]
        if not len(starts):
            return starts, np.zeros((0, len(self.languages)))
        inside = np.nonzero(word >= 0)[0]
        first = np.searchsorted(inside, starts)
        scores = self.table[buckets[0][inside]] + self.table[buckets[1][inside]]
        return starts, np.add.reduceat(scores, first, axis=0).astype(np.float64)


def _em(lik: np.ndarray, doc: np.ndarray, first: np.ndarray, share: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """Proportions and log likelihood per document; lik: words x languages, scaled per word; share: where to start."""
    n = np.diff(np.append(first, len(lik)))[:, None]
    for _ in range(rounds):
        here = share[doc]
        part = lik * (here / np.maximum(np.einsum("ij,ij->i", lik, here), 1e-300)[:, None])
        share = np.add.reduceat(part, first, axis=0) / n
    return share, _log_likelihood(lik, doc, first, share)


def _log_likelihood(lik: np.ndarray, doc: np.ndarray, first: np.ndarray, share: np.ndarray) -> np.ndarray:
    return np.add.reduceat(np.log(np.maximum(np.einsum("ij,ij->i", lik, share[doc]), 1e-300)), first)


def infer(model: LanguageModel, texts: list[bytes], penalty: float) -> np.ndarray:
    """texts x languages: proportions in the chosen set, 0 outside it; all 0 without a word."""
    size = len(model.languages)
    out = np.zeros((len(texts), size))
    if not size:
        return out
    joined = np.frombuffer(b" ".join(texts) + b" ", np.uint8)
    starts, ll = model.word_likelihoods(joined)
    ends = np.cumsum([len(t) + 1 for t in texts])
    of = np.searchsorted(ends, starts, side="right")
    if not len(of):
        return out
    here, first, doc = np.unique(of, return_index=True, return_inverse=True)
    top = ll.max(axis=1)
    lik = np.exp(ll - top[:, None])
    share, full = _em(lik, doc, first, np.full((len(here), size), 1 / size), ROUNDS)
    order = np.argsort(-share, axis=1, kind="stable")
    price = penalty * np.log(np.diff(np.append(first, len(of))) + 1.0) / 2
    fit = np.zeros((len(here), size))
    np.put_along_axis(fit, order[:, :1], 1.0, axis=1)
    value = _log_likelihood(lik, doc, first, fit)
    for m in range(2, size + 1):
        open_ = full - price * (m - 1) > value
        if not open_.any():
            break
        pick = open_[doc]
        some, some_first, some_doc = np.unique(doc[pick], return_index=True, return_inverse=True)
        allowed = np.zeros((len(some), size))
        np.put_along_axis(allowed, order[some, :m], 1.0 / m, axis=1)
        now, total = _em(lik[pick], some_doc, some_first, allowed, ROUNDS)
        total -= price[some] * (m - 1)
        better = total > value[some]
        value[some[better]], fit[some[better]] = total[better], now[better]
    out[here] = np.clip(fit, 0.0, 1.0)
    return out


def train(docs: DataFrame, where: Column | None = None, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = PER_LANGUAGE, smooth: float = 0.3) -> LanguageModel:
    """Counts of n-grams of a bounded share of the labelled rows."""
    known = docs.where(F.col(lang_col).isNotNull() & F.col(id_col).isNotNull() & F.col(text_col).isNotNull())
    if where is not None:
        known = known.where(where)
    total = {r[0]: r[1] for r in known.groupBy(lang_col).count().collect()}  # a row per language
    languages = tuple(sorted(total))
    number = {name: i for i, name in enumerate(languages)}
    if not languages:
        return LanguageModel((), np.zeros((BUCKETS, 0), np.float32))
    rate = F.element_at(F.create_map(*[F.lit(x) for name in languages for x in (name, min(1.0, per_language / total[name]))]), F.col(lang_col))
    drawn = known.where(F.pmod(F.xxhash64(F.col(id_col).cast("string"), F.lit("language")), F.lit(1_000_000)) < rate * 1_000_000)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((len(languages), BUCKETS), np.int64)
        for b in batches:
            for lang, text in zip(b.column(0), b.column(1)):
                word, buckets = grams(np.frombuffer(text.as_py(), np.uint8))
                for h in buckets:
                    counts[number[lang.as_py()]] += np.bincount(h[word >= 0], minlength=BUCKETS)
        lang, bucket = np.nonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(lang, pa.int32()), pa.array(bucket, pa.int32()), pa.array(counts[lang, bucket])], names=["l", "h", "n"])

    sums = drawn.select(lang_col, F.col(text_col).cast("binary").alias("__text")).mapInArrow(work, "l int, h int, n long").groupBy("l", "h").agg(F.sum("n").alias("n"))
    table = np.zeros((BUCKETS, len(languages)))
    got = sums.toArrow()  # at most BUCKETS rows per language
    table[got.column("h").to_numpy(), got.column("l").to_numpy()] = got.column("n").to_numpy()
    table = np.log((table + smooth) / (table.sum(axis=0) + smooth * BUCKETS))
    return LanguageModel(languages, table.astype(np.float32))


def identify(docs: DataFrame, model: LanguageModel, id_col: str = "doc_id", text_col: str = "text", penalty: float = 2.0) -> DataFrame:
    """id_col, lang_pred, score (its proportion), languages and proportions of the chosen set, the largest first."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [t or "" for t in b.column(1).to_pylist()]
            shares = np.zeros((len(texts), len(model.languages)))
            at = 0
            while at < len(texts):
                end, size = at, 0
                while end < len(texts) and (size < SLAB or end == at):
                    size += len(texts[end])
                    end += 1
                shares[at:end] = infer(held.value, [t.encode() for t in texts[at:end]], penalty)
                at = end
            lettered = np.array([LETTER.search(t) is not None for t in texts], bool)
            found = [[(names[j], s[j]) for j in np.argsort(-s, kind="stable") if s[j] > 0] if x else [] for s, x in zip(shares, lettered)]
            first = [x[0] if x else (UNKNOWN, 0.0) for x in found]
            yield pa.RecordBatch.from_arrays([
                b.column(0), pa.array([x[0] for x in first], pa.string()), pa.array([x[1] for x in first], pa.float64()),
                pa.array([[n for n, _ in x] for x in found], pa.list_(pa.string())), pa.array([[s for _, s in x] for x in found], pa.list_(pa.float64())),
            ], names=[id_col, "lang_pred", "score", "languages", "proportions"])

    names, kind = model.languages, docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(text_col).alias("__text")).mapInArrow(work, f"`{id_col}` {kind}, lang_pred string, score double, languages array<string>, proportions array<double>")


def op4(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    docs = load_table(spark, sf_dir, "documents")
    rest = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5
    out = identify(docs, train(docs, rest != 0))
    return out.select("doc_id", F.coalesce(rest == 0, F.lit(False)).alias("held_out"), "lang_pred", "score")
