"""Best-two-fit packing of tokenised documents into sequences of bounded length.

1. Documents are tokenised whole (Arrow batches); only those longer than a sequence are
   cut. A piece leaves its worker as (id, piece, start, length, crc32), never as tokens.
2. Lengths are whole numbers up to the capacity, so the pieces of all documents sum up to
   one histogram of ``capacity`` entries. The plan is made on that histogram: a bin is
   filled greedily (the longest piece that fits, again and again), then its smallest piece
   is exchanged for the two unpacked pieces that fill the widened gap most. Equal bins
   are planned at once, as often as the counts allow.
3. Pieces of one length are interchangeable: the i-th of a length takes the i-th slot of
   that length. Ranks come from running sums over about sqrt(n) buckets per length, so no
   task holds all pieces of a length.

Defined cases: null text is empty and gives the end mark alone; repeated rows are packed
each; null ids stay null; an empty table gives no piece; long texts are tokenised whole.
Columns beside the named ones are not read, whatever they are called; functions that
return whole rows return them as they are.
"""

from __future__ import annotations

import re
import zlib
from bisect import bisect_right
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from bundlemv.session import materialise

CAPACITY = 2048
END = 0
#: Words kept per worker; the store starts anew when it is full.
CACHE_WORDS = 200_000
#: Texts of these characters only are normalised and split here; all others by the tokenizer itself.
PLAIN = re.compile(r"[\t\n\r\x20-\x7e¡-©«-±´¶-¸»¿-ÿ]*")
#: The vocabulary's own split pattern, for those characters: contractions, letters, single digits, other marks.
SPLIT = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zµß-öø-ÿ]+|[0-9]|[^\sa-z0-9µß-öø-ÿ]+")


def byte_letters() -> dict[int, str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    hidden = [b for b in range(256) if b not in shown]
    return {b: chr(b) for b in shown} | {b: chr(256 + i) for i, b in enumerate(hidden)}


class WordIds(dict):
    """Ids of a word as little-endian unsigned 32-bit numbers, merged on first use."""

    def __init__(self, model):
        super().__init__()
        self.model, self.letters = model, byte_letters()

    def __missing__(self, word: str) -> bytes:
        if len(self) >= CACHE_WORDS:
            self.clear()
        form = word if word.isascii() else "".join([self.letters[b] for b in word.encode()])
        self[word] = ids = np.array([t.id for t in self.model.tokenize(form)], dtype="<u4").tobytes()
        return ids


class WordTokenizer:
    """``encode`` of a tokenizer that lower-cases, splits into words and merges within words.

    A word's ids depend on the word alone, so frequent words are merged once and kept.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        self.special = [t.content for t in self.whole.get_added_tokens_decoder().values()]
        self.words = WordIds(self.whole.model)

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit numbers."""
        if not PLAIN.fullmatch(text) or "<|" in text and any(t in text for t in self.special):
            return np.array(self.whole.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()
        return b"".join(map(self.words.__getitem__, SPLIT.findall(text.lower())))


@lru_cache(2)
def word_tokenizer(path: str) -> WordTokenizer:
    return WordTokenizer(path)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def pieces_of(ids: bytes, capacity: int) -> list[tuple[int, int, int, int]]:
    """(piece, start, length, crc32) of one document's ids."""
    n = len(ids) // 4
    return [(i, s, min(capacity, n - s), zlib.crc32(ids[4 * s : 4 * (s + capacity)])) for i, s in enumerate(range(0, n, capacity))]


def tokenised_pieces(docs: DataFrame, vocabulary: str | None = None, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", encoder: Callable | None = None) -> DataFrame:
    """id_col, piece, start, length, ids_crc32. ``vocabulary`` is a path that every executor has."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder or word_tokenizer(vocabulary or default_vocabulary()).encode
        end = np.array([END], dtype="<u4").tobytes()
        for b in batches:
            rows = [(i, *p) for i, t in enumerate(b.column(1)) for p in pieces_of(encode(t.as_py() or "") + end, capacity)]
            of, *cols = zip(*rows) if rows else ((), (), (), (), ())
            kinds = (pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(of, pa.int64())), *[pa.array(c, k) for c, k in zip(cols, kinds)]], names=[id_col, "piece", "start", "length", "ids_crc32"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, F.col(text_col).alias("__text")).mapInArrow(work, f"`{id_col}` {kind}, piece int, start long, length long, ids_crc32 long")


def plan_bins(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, tuple[int, ...]]]:
    """{length: pieces} -> [(bins, lengths in a bin)] by best-two-fit.

    Every step uses up at least one length or half of what is left of one, so the plan has
    at most about 2 x capacity x log2(pieces) entries.
    """
    left = {k: n for k, n in counts.items() if n}
    order = sorted(left)  # lengths that are left, ascending
    plan = []

    def largest(most: int, used: dict[int, int]) -> int | None:
        i = bisect_right(order, most) - 1
        while i >= 0 and left[order[i]] - used.get(order[i], 0) <= 0:
            i -= 1
        return order[i] if i >= 0 else None

    while order:
        used: dict[int, int] = {}
        bin_, gap = [], capacity
        while gap and (x := largest(gap, used)) is not None:
            bin_.append(x)
            used[x] = used.get(x, 0) + 1
            gap -= x
        if gap and len(bin_) > 1:
            small = bin_[-1]
            widened = gap + small
            used[small] -= 1
            best = (small, None)  # total of what replaces it, the pair
            j = len(order) - 1
            for a in order:  # two pointers: a rises, its best partner falls
                if a > widened // 2:
                    break
                if left[a] - used.get(a, 0) <= 0:
                    continue
                while j >= 0 and order[j] > widened - a:
                    j -= 1
                i = j
                while i >= 0 and order[i] >= a and left[order[i]] - used.get(order[i], 0) < 1 + (order[i] == a):
                    i -= 1
                if i >= 0 and order[i] >= a and a + order[i] > best[0]:
                    best = (a + order[i], (order[i], a))
                    if best[0] == widened:
                        break
            pair = best[1] or (small,)
            bin_[-1:] = pair
            for x in pair:
                used[x] = used.get(x, 0) + 1
        times = min(left[x] // n for x, n in used.items() if n)
        plan.append((times, tuple(bin_)))
        for x, n in used.items():
            left[x] -= n * times
        order = [x for x in order if left[x]]
    return plan


def slot_table(plan: list[tuple[int, tuple[int, ...]]]) -> list[tuple[int, int, int, int]]:
    """(length, first rank, first bin, offset) for each run of equal slots.

    Slot s of a pattern with ``times`` bins takes ``times`` consecutive ranks of its length.
    """
    ranks: dict[int, int] = {}
    out, base = [], 0
    for times, bin_ in plan:
        offset = 0
        for x in bin_:
            out.append((x, ranks.get(x, 0), base, offset))
            ranks[x] = ranks.get(x, 0) + times
            offset += x
        base += times
    return out


def ranked(pieces: DataFrame, id_col: str) -> DataFrame:
    """0-based rank within each length, as column ``__rank``, without one task per length."""
    ident = F.xxhash64(F.col(id_col), "piece", "ids_crc32")
    per = pieces.groupBy("length").agg(F.count("*").alias("__n"))  # at most ``capacity`` rows
    rows = pieces.join(F.broadcast(per), "length").withColumn("__b", F.pmod(ident, F.ceil(F.sqrt("__n")).cast("long")))
    before = Window.partitionBy("length").orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)
    base = rows.groupBy("length", "__b").agg(F.count("*").alias("__c")).select("length", "__b", F.coalesce(F.sum("__c").over(before), F.lit(0)).alias("__base"))
    inside = Window.partitionBy("length", "__b").orderBy(id_col, "piece", "ids_crc32")
    return (
        rows.withColumn("__i", F.row_number().over(inside)).join(base, ["length", "__b"])
        .withColumn("__rank", F.col("__base") + F.col("__i") - 1).drop("__n", "__b", "__base", "__i")
    )


def assign_bins(pieces: DataFrame, capacity: int = CAPACITY, id_col: str = "doc_id") -> DataFrame:
    """Adds sequence_id and offset to materialised pieces."""
    counts = {r.length: r.n for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most ``capacity`` rows
    slots: dict[int, list] = {}
    for length, first, bin_, offset in slot_table(plan_bins(counts, capacity)):
        slots.setdefault(length, []).append((first, bin_, offset))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("__rank").to_numpy()
            seq, off = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for x in np.unique(length):
                own, run = length == x, np.array(slots[int(x)])
                k = np.searchsorted(run[:, 0], rank[own], side="right") - 1
                seq[own], off[own] = run[k, 1] + rank[own] - run[k, 0], run[k, 2]
            keep = [b.column(n) for n in b.schema.names if n != "__rank"]
            yield pa.RecordBatch.from_arrays([*keep, pa.array(seq), pa.array(off)], names=[*[n for n in b.schema.names if n != "__rank"], "sequence_id", "offset"])

    out = ranked(pieces, id_col)
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in out.drop("__rank").schema)
    return out.mapInArrow(place, f"{kinds}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, vocabulary: str | None = None, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text", encoder: Callable | None = None) -> DataFrame:
    """id_col, piece, start, length, ids_crc32, sequence_id, offset: one row per piece."""
    pieces = materialise(tokenised_pieces(docs, vocabulary, capacity, id_col, text_col, encoder), "pieces")
    return assign_bins(pieces, capacity, id_col).select(id_col, "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op9(spark, sf_dir):
    from bundlemv.sources.tables import load_table

    return pack_documents(load_table(spark, sf_dir, "documents"))
