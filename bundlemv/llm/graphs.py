"""Connected components of an edge table by alternating star contractions, and filters over sets of keys."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bundlemv.session import discard, materialise


def least_by(df: DataFrame, key: str, value: str, name: str) -> DataFrame:
    """key, name: the least ``value`` of each key.

    Grouped by one more column, which depends on the key, so that a join on the key deals
    both sides anew and may split a key that holds many rows.
    """
    return df.groupBy(key, F.pmod(F.hash(key), F.lit(2)).alias("__half")).agg(F.min(value).alias(name)).select(key, name)


#: Edges in one file of a round's table; rounds shrink, and so do their files.
FILE_EDGES = 250_000


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Edges (u long, v long) -> (node, root): root is the least node reachable.

    Each round hangs larger neighbours on the least one (large star), then smaller
    neighbours on the least one (small star); both shrink paths while the components
    stay. It ends when a round changes nothing: then every edge points at a root. The
    number of rounds grows with the logarithm of the longest path. Minima are
    pre-aggregated before the shuffle, and nothing but two sums reaches the driver.
    """
    cur = edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    cur, before = materialise(cur, "cc"), None
    for _ in range(max_rounds):
        now = _signature(cur)
        if now == before or now[0] == 0:
            break
        before = now
        both = cur.union(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = least_by(both, "u", "v", "m").select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        down = least_by(large, "u", "v", "m")
        small = large.join(down, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e"))
        files = max(4, -(-now[0] // FILE_EDGES))
        last, cur = cur, materialise(small.select("e.u", "e.v").where("u <> v").distinct().coalesce(files), "cc")
        discard(last)
    else:
        raise RuntimeError("components did not settle")
    roots = cur.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("root"))
    return cur.select(F.col("u").alias("node"), F.col("v").alias("root")).union(roots)


def _signature(cur: DataFrame) -> tuple:
    row = cur.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return row[0], row[1]


#: Size of a filter over keys, at most; it only spares shuffles, a join decides.
FILTER_BITS = 1 << 27


def key_filter(keys: DataFrame, key: str, n: int) -> np.ndarray:
    """A bit array in which each of the n distinct keys (long) has its two bits set; empty if it could not tell keys apart."""
    bits = 1 << max(10, min(FILTER_BITS.bit_length() - 1, (16 * n).bit_length()))
    if 4 * n > bits:
        return np.zeros(0, np.uint64)
    shift = 64 - (bits.bit_length() - 1)
    spots = keys.select(F.explode(F.array(F.shiftrightunsigned(key, shift), F.shiftright(key, 1).bitwiseAND(bits - 1))).alias("spot"))
    words = spots.groupBy(F.shiftright("spot", 6).alias("word")).agg(F.expr("bit_or(shiftleft(1L, cast(spot & 63 as int)))").alias("b")).toArrow()  # at most FILTER_BITS / 64 rows
    out = np.zeros(bits // 64, np.int64)
    out[words.column("word").to_numpy()] = words.column("b").to_numpy()
    return out.view(np.uint64)


def may_hold(bits: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Whether each key may be one of the filter's."""
    if not len(bits):
        return np.ones(len(keys), bool)
    u = np.uint64
    shift, out = u(64 - (len(bits) * 64).bit_length() + 1), np.ones(len(keys), bool)
    for spot in (keys >> shift, keys >> u(1) & u(len(bits) * 64 - 1)):
        out &= (bits[(spot >> u(6)).astype(np.int64)] >> (spot & u(63))) & u(1) == 1
    return out
