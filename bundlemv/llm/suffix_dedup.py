"""Removal of long repeated passages with a logarithmic family of suffix arrays.

A byte goes if it lies in a string of ``length`` bytes that also starts elsewhere, in any
document. Texts are never compared pair by pair and no document's text waits for another's.

Sampling. In each window of ``length`` bytes the gram with the least hash is the anchor, so
equal windows have equal anchors at equal places. The windows of one anchor form a stretch;
texts hold about one anchor in 190 bytes. A window equals another only if one of five
fingerprints of theirs is equal: that of the whole stretch, or that of the part which all
windows share whose anchor stands in the same quarter. These are the suffixes that the
arrays hold, cut to the length that has to agree and ordered by fingerprint (for matches of
a set length, equality of prefixes is what counts, not their alphabetical order).

Family. A batch of documents becomes an array: per bucket, one sorted run of (key, value),
equal keys folded, where the value 0 marks a key that occurs for different contents. The
batch is merge-scanned against every level, which yields the keys that match; then it
merges with the full low levels, like a carry in binary counting, so level i holds 2**i
batches and each entry is rewritten about log(batches) times. Levels are written to the
shared folder and serve later batches.

Resolution. A match of 64 bits only proposes: what is removed agrees in two independent
fingerprints, 128 bits. Stretches that agree as a whole are removed at once. Where only a
part matches, the stretch's distinct contents are compared window by window, by the
fingerprints of all ``length`` bytes. Parts shared by very many contents go another way
that aggregates per window before it shuffles, so a frequent passage is no hot group.

Passages in words. ``length`` bytes may be more than a passage of 50 words has. The family
therefore holds suffixes that start at words as well, cut to 32 words: of each 19 neighbours
the one of least hash, so 50 words that stand in two rows share one. They remove nothing; they
count, per row, the strings that another row has too (``n_shared``).

Defined cases: null text is empty; texts shorter than ``length`` stay whole; repeated rows
are copies of each other; null and repeated ids are told apart by their texts; an empty
table gives an empty result.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache, reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bundlemv.llm.graphs import key_filter, may_hold
from bundlemv.session import materialise

LENGTH, GRAM = 400, 16
#: Documents are inserted in so many batches by the query.
BATCHES = 4
#: Bytes of text per bucket of the family's arrays.
BUCKET_BYTES = 32 << 20
#: Contents that share a part and are compared in one bucket; parts with more are aggregated by window.
HOT = 4096
#: Texts are fingerprinted in slabs of so many bytes, which overlap by a window.
SLAB = 1 << 20
#: Words of a passage and of the strings that are drawn from it (a power of two).
PASSAGE, STRING = 50, 32
#: Words are hashed in blocks of so many, which overlap by a passage.
BLOCK = 1 << 16

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15
_LETTERS = [np.random.default_rng(seed).integers(0, 2**63, 256, dtype=np.int64).astype(_U) * _U(2) + _U(1) for seed in (20, 21)]
_SOLID = np.array([b not in b" \t\n\v\f\r" for b in range(256)])
ARRAY = "bucket int, level int, keys binary, vals binary"


@lru_cache(1)
def _powers() -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2**64, for one slab."""
    out = []
    for base in (_BASE, pow(_BASE, -1, 1 << 64)):
        p, n = np.ones(1, _U), 1
        while n <= SLAB + LENGTH:
            p, n = np.concatenate([p, p * _U(pow(base, n, 1 << 64))]), 2 * n
        out.append(p)
    return out[0], out[1]


class Fingerprints:
    """Fingerprints of any substring of a slab, from one running sum; ``which`` names one of two independent kinds."""

    def __init__(self, data: np.ndarray, which: int = 0):
        up, self.down = _powers()
        self.sums = np.zeros(len(data) + 1, _U)
        np.cumsum(_LETTERS[which][data] * up[: len(data)], out=self.sums[1:])

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return _mixed((self.sums[end] - self.sums[start]) * self.down[start])


def _mixed(h: np.ndarray) -> np.ndarray:
    h ^= h >> _U(32)
    h *= _U(0xD6E8FEB86659FD93)
    return h ^ (h >> _U(29))


def _sliding_least(x: np.ndarray, w: int) -> np.ndarray:
    """Least value of each w neighbours: running minima inside blocks, from both sides."""
    n = len(x) - w + 1
    padded = np.full(-(-len(x) // w) * w, np.iinfo(_U).max, _U)
    padded[: len(x)] = x
    blocks = padded.reshape(-1, w)
    left = np.minimum.accumulate(blocks, axis=1).ravel()
    right = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(right[:n], left[w - 1 : w - 1 + n])


def anchors(data: np.ndarray, length: int) -> np.ndarray:
    """Place of each window's anchor: the leftmost gram of least hash."""
    x = data.astype(_U)
    for k in (1, 2, 4):
        x = x[:-k] | (x[k:] << _U(8 * k))  # 2, 4, then 8 bytes at each place
    h = (x[:-8] * _U(0xD6E8FEB86659FD93)) ^ (x[8:] * _U(0xA0761D6478BD642F))
    h ^= h >> _U(29)
    h *= _U(0xE7037ED1A0B428DB)
    keyed = (h >> _U(24) << _U(24)) | np.arange(len(h), dtype=_U)
    return (_sliding_least(keyed, length - GRAM + 1) & _U(0xFFFFFF)).astype(np.int64)


def quarters(length: int) -> list[tuple[int, int]]:
    """Ranges of the anchor's place within a window."""
    edges = [i * (length - GRAM + 1) // 4 for i in range(5)]
    return [(a, b - 1) for a, b in zip(edges, edges[1:])]


def whole_prints(data: bytes) -> Fingerprints | None:
    """Fingerprints of a text that is one slab."""
    return Fingerprints(np.frombuffer(data, np.uint8)) if len(data) <= SLAB else None


def word_strings(data: bytes, prints: Fingerprints | None = None) -> np.ndarray:
    """Distinct odd keys of the strings of STRING words that have the least hash among the strings of a passage."""
    raw = np.frombuffer(data, np.uint8)
    solid = np.concatenate([[False], _SOLID[raw], [False]])
    edge = np.flatnonzero(solid[1:] != solid[:-1])
    first, end = edge[::2], edge[1::2]
    found = [np.zeros(0, _U)]
    for a in range(0, len(first) - PASSAGE + 1, BLOCK):
        at, stop = first[a : a + BLOCK + PASSAGE - 1], end[a : a + BLOCK + PASSAGE - 1]
        if prints is not None:
            h = prints.of(at, stop)
        else:  # words of any length: their letters are placed one by one
            piece = raw[at[0] : stop[-1]]
            place = np.arange(len(piece)) - np.repeat(at - at[0], np.diff(np.append(at - at[0], len(piece))))
            h = _mixed(np.add.reduceat(_LETTERS[0][piece] * _powers()[0][place % SLAB] * _SOLID[piece], at - at[0]))
        w = 1
        while w < STRING:
            h, w = h[:-w] * _U(pow(_BASE, w, 1 << 64)) + h[w:], 2 * w
        h = _mixed(h)
        least = _sliding_least((h >> _U(24) << _U(24)) | np.arange(len(h), dtype=_U), PASSAGE - STRING + 1) & _U(0xFFFFFF)
        found.append(h[least[np.concatenate([[True], least[1:] != least[:-1]])].astype(np.int64)] | _U(1))
    return np.unique(np.concatenate(found))


def suffixes(data: bytes, length: int, checked: bool = False, prints: Fingerprints | None = None) -> Iterator[tuple[np.ndarray, ...]]:
    """Per slab and kind: (kind, keys, contents, first window, last window, check of the content); windows by place in the text.

    Kind 0 is the whole stretch (odd keys), kinds 1 to 4 are the quarters (even keys). Without
    ``checked`` the check, the content's other fingerprint, is 0. ``prints``: of the whole text, if it is one slab.
    """
    for at in range(0, max(1, len(data) - length + 1), SLAB):
        piece = np.frombuffer(data, np.uint8)[at : at + SLAB + length - 1]
        if len(piece) < length:
            return
        place = anchors(piece, length)
        cut = np.nonzero(np.diff(place))[0] + 1
        first, last = np.concatenate([[0], cut]), np.concatenate([cut - 1, [len(place) - 1]])
        mark, own = place[first], prints or Fingerprints(piece)
        content = own.of(first, last + length)
        check = Fingerprints(piece, 1).of(first, last + length) if checked else np.zeros_like(content)
        yield 0, content | _U(1), content, at + first, at + last, check
        for kind, (near, far) in enumerate(quarters(length), 1):
            lo, hi = np.maximum(first, mark - far), np.minimum(last, mark - near)
            some = lo <= hi
            key = own.of(mark[some] - near, mark[some] - far + length) * _U(2 * kind + 1)
            yield kind, key & ~_U(1), content[some], at + lo[some], at + hi[some], check[some]


# --- arrays -------------------------------------------------------------------


def fold(keys: np.ndarray, vals: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys; a key's value, or 0 for different values or for an odd key (a whole stretch, a string of words) that occurs again."""
    order = np.argsort(keys, kind="stable")
    keys, vals = keys[order], vals[order]
    first = np.nonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))[0] if len(keys) else np.zeros(0, np.int64)
    if not len(first):
        return keys, vals
    n = np.diff(np.append(first, len(keys)))
    least, most = np.minimum.reduceat(vals, first), np.maximum.reduceat(vals, first)
    keys = keys[first]
    return keys, np.where((least != most) | ((keys & _U(1) == 1) & (n > 1)), _U(0), least)


def batch_array(docs: DataFrame, buckets: int, length: int, text_col: str) -> DataFrame:
    """Runs of a batch as rows of ARRAY with level -1: several per bucket, folded where they were made."""

    def runs(keys: list, vals: list) -> pa.RecordBatch:
        k, v = fold(np.concatenate(keys), np.concatenate(vals))
        at = (k >> _U(33)) % _U(buckets)
        order = np.argsort(at, kind="stable")
        k, v, at = k[order], v[order], at[order]
        cuts = np.searchsorted(at, np.arange(buckets + 1, dtype=_U))
        some = [i for i in range(buckets) if cuts[i] < cuts[i + 1]]
        return pa.RecordBatch.from_arrays([
            pa.array(some, pa.int32()), pa.array([-1] * len(some), pa.int32()),
            pa.array([k[cuts[i] : cuts[i + 1]].tobytes() for i in some], pa.binary()), pa.array([v[cuts[i] : cuts[i + 1]].tobytes() for i in some], pa.binary()),
        ], names=["bucket", "level", "keys", "vals"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, vals, held = [], [], 0
        for b in batches:
            for t in b.column(0):
                data = t.as_py() or b""
                prints = whole_prints(data)
                for kind, key, content, *_ in suffixes(data, length, False, prints):
                    keys.append(key)
                    vals.append(np.ones(len(key), _U) if kind == 0 else content | _U(1))
                    held += len(key)
                keys.append(word_strings(data, prints))
                vals.append(np.ones(len(keys[-1]), _U))
                held += len(keys[-1])
                if held > 1 << 20:
                    yield runs(keys, vals)
                    keys, vals, held = [], [], 0
        if held:
            yield runs(keys, vals)

    return docs.select(F.col(text_col).cast("binary").alias("__text")).mapInArrow(work, ARRAY)


class SuffixFamily:
    """Levels of suffix arrays; level i holds 2**i batches or nothing. ``matches`` gathers matching keys."""

    FOUND = -2

    def __init__(self, spark: SparkSession, buckets: int, length: int = LENGTH):
        self.spark, self.buckets, self.length = spark, buckets, length
        self.levels: list[DataFrame | None] = []
        self.found: list[DataFrame] = []

    def insert(self, docs: DataFrame, text_col: str = "text", last: bool = False) -> None:
        """Merge-scan a batch against every level and let full low levels merge with it.

        After the ``last`` batch no level is written: the family ends.
        """
        to = next((i for i, x in enumerate(self.levels) if x is None), len(self.levels))
        found_mark = self.FOUND

        def step(table: pa.Table) -> pa.Table:
            runs: dict[int, tuple[list, list]] = {}
            for level, k, v in zip(*(table.column(c).to_pylist() for c in ("level", "keys", "vals"))):
                a, b = runs.setdefault(level, ([], []))
                a.append(np.frombuffer(k, _U))
                b.append(np.frombuffer(v, _U))
            keys, vals = fold(np.concatenate(runs[-1][0]), np.concatenate(runs[-1][1])) if -1 in runs else (np.zeros(0, _U), np.zeros(0, _U))
            hits, merged = [keys[vals == 0]], (keys, vals)
            for level in sorted(runs.keys() - {-1}):
                own = (np.concatenate(runs[level][0]), np.concatenate(runs[level][1]))
                k, v = fold(np.concatenate([keys, own[0]]), np.concatenate([vals, own[1]]))
                hits.append(np.intersect1d(k[v == 0], keys, assume_unique=True))
                if level < to:  # part of the carry
                    merged = fold(np.concatenate([merged[0], own[0]]), np.concatenate([merged[1], own[1]]))
            hit = np.unique(np.concatenate(hits))
            out = [(found_mark, hit.tobytes(), b"")] + ([] if last else [(to, merged[0].tobytes(), merged[1].tobytes())])
            level, k, v = zip(*out)
            bucket = table.column("bucket")[0].as_py()
            return pa.table({"bucket": pa.array([bucket] * len(out), pa.int32()), "level": pa.array(level, pa.int32()), "keys": pa.array(k, pa.binary()), "vals": pa.array(v, pa.binary())})

        rows = reduce(DataFrame.unionAll, [x for x in self.levels if x is not None], batch_array(docs, self.buckets, self.length, text_col))
        out = materialise(rows.groupBy("bucket").applyInArrow(step, ARRAY), "suffix-level")
        self.found.append(out.where(F.col("level") == self.FOUND))
        self.levels = [] if last else [None] * to + [out.where(F.col("level") == to)] + self.levels[to + 1 :]

    def matches(self) -> DataFrame:
        """key: distinct keys that occur with different contents, or as whole stretches more than once."""

        def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                for k in b.column(0):
                    yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(k.as_py(), np.int64))], names=["key"])

        return reduce(DataFrame.unionAll, self.found).select("keys").mapInArrow(unpack, "key long").distinct()


# --- resolution ---------------------------------------------------------------


def _places(docs: DataFrame, bits: np.ndarray, length: int) -> DataFrame:
    """Suffixes of ``docs`` (__id, __print, __text) whose key may match: where they stand. Kind 5: strings of words, without a place."""
    held = docs.sparkSession.sparkContext.broadcast(bits)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            parts, of = [], []
            for i, t in enumerate(b.column(2)):
                data = t.as_py()
                prints = whole_prints(data)
                words = word_strings(data, prints)
                none = np.zeros(len(words), np.int64)
                for kind, key, content, lo, hi, check in [*suffixes(data, length, True, prints), (5, words, none, none, none, none)]:
                    some = np.nonzero(may_hold(held.value, key))[0]
                    if len(some):
                        parts.append((np.full(len(some), kind), key[some].view(np.int64), content[some].view(np.int64), lo[some], hi[some], check[some].view(np.int64)))
                        of.append(np.full(len(some), i))
            if not parts:
                continue
            kind, key, content, lo, hi, check = (np.concatenate(x) for x in zip(*parts))
            at = pa.array(np.concatenate(of))
            yield pa.RecordBatch.from_arrays([
                b.column(0).take(at), b.column(1).take(at), pa.array(kind, pa.int32()), pa.array(key), pa.array(content), pa.array(check), pa.array(lo, pa.int32()), pa.array(hi, pa.int32()),
            ], names=["__id", "__print", "kind", "key", "content", "check", "lo", "hi"])

    kind = docs.schema["__id"].dataType.simpleString()
    return docs.mapInArrow(work, f"__id {kind}, __print long, kind int, key long, content long, check long, lo int, hi int")


def _window_prints(reps: DataFrame, docs: DataFrame, length: int) -> DataFrame:
    """key, kind, content, check, prints, checks (the two fingerprints of the windows lo to hi, packed)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for t, ranges in zip(b.column(0), b.column(1)):
                data = np.frombuffer(t.as_py(), np.uint8)
                for r in ranges.as_py():
                    piece = data[r["lo"] : r["hi"] + length]
                    i = np.arange(len(piece) - length + 1)
                    out.append((r["key"], r["kind"], r["content"], r["check"], *(Fingerprints(piece, w).of(i, i + length).tobytes() for w in (0, 1))))
            if out:
                kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=["key", "kind", "content", "check", "prints", "checks"])

    ranges = reps.groupBy("__id", "__print").agg(F.collect_list(F.struct("key", "kind", "content", "check", "lo", "hi")).alias("ranges"))  # within one text
    both = docs.join(ranges, docs["__print"].eqNullSafe(ranges["__print"]) & docs["__id"].eqNullSafe(ranges["__id"]))
    return both.select("__text", "ranges").mapInArrow(work, "key long, kind int, content long, check long, prints binary, checks binary")


def repeated_windows(reps: DataFrame, docs: DataFrame, buckets: int, length: int, hot: int = HOT) -> DataFrame:
    """kind, content, check, runs array<struct<i, j>>: windows, counted from the first, that another content has as well."""
    schema = "kind int, content long, check long, runs array<struct<i: int, j: int>>"
    runs_type = pa.list_(pa.struct([("i", pa.int32()), ("j", pa.int32())]))

    def runs_of(flags: np.ndarray) -> list[dict]:
        edge = np.diff(np.concatenate([[0], flags.astype(np.int8), [0]]))
        return [{"i": int(a), "j": int(b) - 1} for a, b in zip(np.nonzero(edge == 1)[0], np.nonzero(edge == -1)[0])]

    def solve(table: pa.Table) -> pa.Table:
        kind, content, check = (table.column(c).to_numpy() for c in ("kind", "content", "check"))
        packed = [[np.frombuffer(x, _U) for x in table.column(c).to_pylist()] for c in ("prints", "checks")]
        size = np.array([len(x) for x in packed[0]])
        _, name = np.unique(np.stack([content, check]), axis=1, return_inverse=True)
        differs = shared_by_others(np.concatenate(packed[0]), np.concatenate(packed[1]), np.repeat(name.ravel(), size))
        found = [(k, c, h, r) for k, c, h, f in zip(kind.tolist(), content.tolist(), check.tolist(), np.split(differs, np.cumsum(size)[:-1])) if (r := runs_of(f))]
        columns = zip(*found) if found else ((), (), (), ())
        return pa.table([pa.array(x, t) for x, t in zip(columns, (pa.int32(), pa.int64(), pa.int64(), runs_type))], names=["kind", "content", "check", "runs"])

    def explode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for kind, content, check, x, y in zip(*(b.column(i) for i in range(5))):
                w = np.frombuffer(x.as_py(), np.int64)
                same = lambda v, t: pa.array(np.full(len(w), v.as_py()), t)  # noqa: E731, B023
                yield pa.RecordBatch.from_arrays([
                    pa.array(w), pa.array(np.frombuffer(y.as_py(), np.int64)), same(kind, pa.int32()), same(content, pa.int64()), same(check, pa.int64()), pa.array(np.arange(len(w)), pa.int32()),
                ], names=["w", "w2", "kind", "content", "check", "i"])

    def join_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for x in b.column(3):
                i = np.array(x.as_py())
                flags = np.zeros(i.max() + 1, bool)
                flags[i] = True
                out.append(runs_of(flags))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(out, runs_type)], names=["kind", "content", "check", "runs"])

    reps = materialise(reps, "suffix-parts")
    many = reps.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > hot).select("key")
    many = materialise(many, "suffix-hot")
    some = many.count() > 0
    prints = _window_prints(reps.join(many, "key", "left_anti") if some else reps, docs, length)
    plain = prints.groupBy(F.pmod("key", F.lit(buckets)).alias("b")).applyInArrow(solve, schema)
    if not some:
        return plain
    prints = _window_prints(reps.join(many, "key", "left_semi"), docs, length)
    rows = prints.select("kind", "content", "check", "prints", "checks").mapInArrow(explode, "w long, w2 long, kind int, content long, check long, i int")
    spread = rows.groupBy("w", "w2").agg(F.min("content").alias("a"), F.max("content").alias("b"), F.min("check").alias("c"), F.max("check").alias("d"))
    twice = spread.where("a <> b or c <> d").select("w", "w2")
    marked = rows.join(twice, ["w", "w2"], "left_semi").groupBy("kind", "content", "check").agg(F.collect_set("i").alias("i"))  # at most a quarter's windows
    return plain.unionAll(marked.mapInArrow(join_runs, schema))


def shared_by_others(keys: np.ndarray, checks: np.ndarray, names: np.ndarray) -> np.ndarray:
    """Whether each entry's key and check occur with another name as well."""
    order = np.lexsort((checks, keys))
    k, h, v = keys[order], checks[order], names[order]
    first = np.nonzero(np.concatenate([[True], (k[1:] != k[:-1]) | (h[1:] != h[:-1])]))[0]
    differs = np.minimum.reduceat(v, first) != np.maximum.reduceat(v, first)
    out = np.zeros(len(keys), bool)
    out[order] = np.repeat(differs, np.diff(np.append(first, len(k))))
    return out


def repeated_spans(docs: DataFrame, batches: int = BATCHES, length: int = LENGTH, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> tuple[DataFrame, DataFrame]:
    """(docs as __id, __print, __text; spans as __id, __print, spans array<struct<lo, hi>>, n_shared), for texts that repeat something."""
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col).cast("binary"), F.lit(b""))
    named = docs.select(F.col(id_col).alias("__id"), F.xxhash64(text).alias("__print"), text.alias("__text"))
    size = named.agg(F.sum(F.length("__text"))).first()[0] or 0
    family = SuffixFamily(spark, max(16, -(-size // BUCKET_BYTES)), length)
    for i in range(batches):
        family.insert(named.where(F.pmod(F.xxhash64("__id"), F.lit(batches)) == i), "__text", last=i == batches - 1)
    keys = materialise(family.matches(), "suffix-keys")
    places = _places(named, key_filter(keys, "key", keys.count()), length).join(keys, "key", "left_semi")
    places = materialise(places, "suffix-places")
    # the count is grouped by one key more than the join's, so that the join deals both sides anew and can split a hot stretch
    whole = places.where("kind = 0")
    twice = whole.groupBy("key", "check", F.pmod(F.hash("key"), F.lit(2)).alias("half")).agg(F.count("*").alias("n")).where("n > 1").select("key", "check")
    whole = whole.join(twice, ["key", "check"], "left_semi").select("__id", "__print", "lo", "hi")
    parts = places.where("kind between 1 and 4")
    reps = parts.groupBy("key", "kind", "content", "check").agg(F.min(F.struct("__id", "__print", "lo", "hi")).alias("r")).select("key", "kind", "content", "check", "r.*")
    # not written out: the texts dealt for the windows here are dealt for the spans below as well, and Spark reuses them
    runs = repeated_windows(reps, named, family.buckets, length, hot)
    # repeated rows give repeated runs; grouped by one key more than the join's, as above
    runs = runs.groupBy("kind", "content", "check", F.size("runs").alias("n")).agg(F.first("runs").alias("runs"))
    partial = parts.join(runs, ["kind", "content", "check"]).select("__id", "__print", "lo", F.explode("runs").alias("r")).select("__id", "__print", (F.col("lo") + F.col("r.i")).alias("lo"), (F.col("lo") + F.col("r.j")).alias("hi"))
    spans = whole.unionAll(partial).select("*", F.lit(None).cast("long").alias("string"))
    strings = places.where("kind = 5").select("__id", "__print", F.lit(None).cast("int").alias("lo"), F.lit(None).cast("int").alias("hi"), F.col("key").alias("string"))
    both = spans.unionAll(strings).groupBy("__id", "__print")
    spans = both.agg(F.collect_list(F.when(F.col("lo").isNotNull(), F.struct("lo", "hi"))).alias("spans"), F.size(F.collect_set("string")).cast("long").alias("n_shared"))  # within one text
    return named, spans


def union_of(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs that the half-open spans cover; spans that touch are one run."""
    order = np.argsort(lo, kind="stable")
    lo, hi = lo[order], np.maximum.accumulate(hi[order])
    new = np.concatenate([[True], lo[1:] > hi[:-1]])
    return lo[new], hi[np.append(np.nonzero(new)[0][1:] - 1, len(hi) - 1)]


def deduplicated(docs: DataFrame, batches: int = BATCHES, length: int = LENGTH, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> DataFrame:
    """id_col, n_bytes, removed array<struct<start, end>> (byte places), kept binary, n_shared (strings of words that another row has)."""
    named, spans = repeated_spans(docs, batches, length, id_col, text_col, hot)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        for b in batches:
            size, removed, kept, shared = [], [], [], pc.fill_null(b.column(3), 0)
            for t, s in zip(b.column(1), b.column(2)):
                data, s = t.as_py(), s.as_py()
                size.append(len(data))
                if not s:
                    removed.append([])
                    kept.append(data)
                    continue
                lo, hi = union_of(np.array([x["lo"] for x in s]), np.array([x["hi"] for x in s]) + length)
                removed.append([{"start": int(x), "end": int(y)} for x, y in zip(lo, hi)])
                kept.append(b"".join([data[x:y] for x, y in zip([0, *hi.tolist()], [*lo.tolist(), len(data)])]))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(size, pa.int64()), pa.array(removed, kind), pa.array(kept, pa.binary()), shared], names=[id_col, "n_bytes", "removed", "kept", "n_shared"])

    both = named.join(spans.withColumnsRenamed({"__id": "__sid", "__print": "__sprint"}), F.col("__print").eqNullSafe(F.col("__sprint")) & F.col("__id").eqNullSafe(F.col("__sid")), "left")
    kind = docs.schema[id_col].dataType.simpleString()
    return both.select(F.col("__id").alias(id_col), "__text", "spans", "n_shared").mapInArrow(work, f"`{id_col}` {kind}, n_bytes long, removed array<struct<start: bigint, end: bigint>>, kept binary, n_shared long")


def op2(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    out = deduplicated(load_table(spark, sf_dir, "documents"))
    length = F.aggregate("removed", F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["start"])
    return out.select("doc_id", "n_bytes", length.alias("n_removed"), F.size("removed").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"), "n_shared")
