"""Graphs of vertices that share a link, folded: vertices with the same links are one class.

Pages that hold the same link targets have the same neighbours, but for themselves. Members,
classes and links between classes say all that the edges say, in rows that grow with the
vertices; the counters and ranks here are those of the edges, to the last one.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bundlemv.graph import dense_ids
from bundlemv.session import materialise


@dataclass(frozen=True)
class Twins:
    """An undirected graph without loops over vertices 0 .. n-1.

    members: id, cls (0 .. k-1, numbered by least member). sizes: cls, size. links: a, b, both
    ways; a row a, a stands for a class whose members are linked to each other. Members of a
    class have the same neighbours, but for themselves.
    """

    members: DataFrame
    sizes: DataFrame
    links: DataFrame
    n: int


#: Ids of a piece of a class: a row of two pieces stands for the square of it in edges.
PIECE = 1024


def key_sets(shared: DataFrame) -> DataFrame:
    """id, keys: the keys of each id, sorted, of those that others hold too."""
    common = shared.groupBy("key").agg(F.count("*").alias("c")).where("c > 1").select("key")
    return shared.join(common, "key").groupBy("id").agg(F.sort_array(F.collect_set("key")).alias("keys"))


def fold(shared: DataFrame, vertices: DataFrame, n: int) -> Twins:
    """From shared (id, key): vertices are linked that share a key. Vertices with the same keys, of those that others hold too, are a class."""
    keys = key_sets(shared)
    none = F.array().cast(keys.schema["keys"].dataType)
    own = materialise(vertices.select("id").join(keys, "id", "left").withColumn("keys", F.coalesce("keys", none)), "twins-keys")
    classes = dense_ids(own.groupBy("keys").agg(F.min("id").alias("least"), F.count("*").alias("size")), ["least"], "cls")
    members = materialise(own.join(classes.select("keys", "cls"), "keys").select("id", "cls"), "twins-members")
    links = linked(classes, "cls")
    return Twins(members, classes.select("cls", "size"), materialise(links, "twins-links"), n)


def linked(classes: DataFrame, name: str) -> DataFrame:
    """a, b: the classes (of that name, with keys and size) that share a key, both ways and each once; a row a, a if it has several members."""
    each = classes.select(F.col(name).alias("a"), "size", F.explode("keys").alias("key"))
    other = each.select("key", F.col("a").alias("b"))
    return each.join(other, "key").where("a <> b or size > 1").select("a", "b").distinct()


def pairs(shared: DataFrame) -> DataFrame:
    """src, dst: all ordered pairs of different ids that share a key, each once, from distinct rows of shared (id, key).

    Classes meet once, and their members in pieces: the pairs come out of rows of two pieces, so
    none is shuffled or compared with another. Ids are any numbers.
    """
    own = key_sets(shared.where("id is not null"))
    classes = own.groupBy("keys").agg(F.min("id").alias("least"), F.count("*").alias("size"))
    piece = F.pmod(F.xxhash64("id"), F.ceil(F.col("size") / PIECE))
    pieces = own.join(classes, "keys").groupBy("least", piece.alias("piece")).agg(F.collect_list("id").alias("ids"))
    side = lambda c: pieces.select(F.col("least").alias(c), F.col("piece").alias(f"{c}_piece"), F.col("ids").alias(f"{c}_ids"))
    met = linked(classes, "least").join(side("a"), "a").join(side("b"), "b")
    # rows are small for what they hold, so the number of tasks is not left to their bytes
    tasks = int(shared.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = met.repartition(tasks, "a", "a_piece", "b", "b_piece").select(F.explode("a_ids").alias("src"), "b_ids")
    # merges nothing, but parts the generated code: a task holds the rows of one src and piece, not of two pieces
    return met.coalesce(tasks).select("src", F.explode("b_ids").alias("dst")).where("src <> dst")


def class_degrees(t: Twins) -> DataFrame:
    """cls, deg: the neighbours of each member."""
    of = t.links.join(t.sizes.withColumnRenamed("cls", "b"), "b")
    return of.groupBy(F.col("a").alias("cls")).agg(F.sum(F.col("size") - (F.col("a") == F.col("b")).cast("long")).alias("deg"))


def degrees(t: Twins) -> DataFrame:
    """id, in_deg of every vertex."""
    deg = class_degrees(t)
    return t.members.join(deg, "cls", "left").select("id", F.coalesce("deg", F.lit(0)).cast("long").alias("in_deg"))


def least_neighbour(t: Twins, value: Column) -> DataFrame:
    """id, least: the least value (of ``id``) of each vertex's neighbours, null without any; a class's two least values tell those of all members."""
    own = t.members.select("cls", F.struct(value.alias("v"), "id").alias("x"))
    first = own.groupBy("cls").agg(F.min("x").alias("first"))
    second = own.join(first, "cls").where("x <> first").groupBy("cls").agg(F.min("x").alias("second"))
    both = first.join(second, "cls", "left").select(F.col("cls").alias("b"), F.explode(F.array_compact(F.array("first", "second"))).alias("x"))
    met = t.links.join(both, "b").groupBy(F.col("a").alias("cls"))
    near = met.agg(F.min("x").alias("one")).join(t.links.join(both, "b").select(F.col("a").alias("cls"), "x"), "cls")
    near = near.groupBy("cls", "one").agg(F.min(F.when(F.col("x") != F.col("one"), F.col("x"))).alias("two"))
    out = F.when(F.col("one.id") == F.col("id"), F.col("two.v")).otherwise(F.col("one.v"))
    return t.members.join(near, "cls", "left").select("id", out.alias("least"))


# --- counters ---------------------------------------------------------------------

#: Lines, and blocks, of a task that counts which lines meet which blocks.
LINES, BLOCKS = 1 << 16, 1 << 11
#: Bytes of the bit sets of a task; with more classes than these hold, lists of lines take their place.
BITS = 64 << 20


def near_blocks(t: Twins, perm: DataFrame, q: int) -> DataFrame:
    """a, blk, alone: the blocks of width q, under the labeling (old, new), that hold neighbours of class a, its own members among them; alone: a single one, which is in a."""
    at = t.members.join(perm.select(F.col("old").alias("id"), "new"), "id").select("cls", F.floor(F.col("new") / q).cast("long").alias("blk"))
    held = at.groupBy(F.col("cls").alias("b"), "blk").agg(F.count("*").alias("c"))
    own = F.when(F.col("a") == F.col("b"), F.col("c")).otherwise(0)
    met = t.links.join(held, "b").groupBy("a", "blk").agg(F.sum("c").alias("c"), F.sum(own).alias("own"))
    return met.select("a", "blk", ((F.col("c") == 1) & (F.col("own") == 1)).alias("alone"))


def compression(t: Twins, near: DataFrame) -> DataFrame:
    """One row: m, bundles, r, as ``cost.compression_ratio`` counts them. A vertex that is alone in a block is not its own neighbour there."""
    m = t.sizes.join(class_degrees(t), "cls").agg(F.coalesce(F.sum(F.col("size") * F.col("deg")), F.lit(0)).alias("m"))
    per = near.join(t.sizes.withColumnRenamed("cls", "a"), "a").groupBy("a", "size").agg(F.count("*").alias("blocks"), F.count_if("alone").alias("alone"))
    bundles = per.agg(F.coalesce(F.sum(F.col("size") * F.col("blocks") - F.col("alone")), F.lit(0)).alias("bundles"))
    return m.crossJoin(bundles).select("m", "bundles", (F.col("m") / F.col("bundles")).alias("r"))


def joined(bits: np.ndarray) -> int:
    """Bits that are set in any of the rows."""
    return int(np.bitwise_count(np.bitwise_or.reduce(bits, axis=0)).sum())


def lines_of(groups: list[np.ndarray], place: np.ndarray, at: np.ndarray, k: int) -> Iterator[int]:
    """How many lines the classes of each group (in order) have together; class place[i] of 0 .. k-1 has line at[i]. Blocks mostly see the same few sets of classes, and each set is joined once."""
    known: dict[bytes, int] = {}
    if dense := k * (LINES // 8) <= BITS:
        bits = np.zeros((k, LINES // 8), np.uint8)
        np.bitwise_or.at(bits, (place, at >> 3), (1 << (at & 7)).astype(np.uint8))
        bits = bits.view(np.uint64)
    else:
        order = np.argsort(place, kind="stable")
        starts, lines = np.searchsorted(place[order], np.arange(k + 1)), at[order]
    for g in groups:
        if (name := g.tobytes()) not in known:
            if not len(g):
                known[name] = 0
            else:
                known[name] = joined(bits[g]) if dense else len(np.unique(np.concatenate([lines[starts[c] : starts[c + 1]] for c in g])))
        yield known[name]


def met_lines(t: Twins, near: DataFrame, perm: DataFrame, q: int, width: int) -> DataFrame:
    """One row: lines, the pairs of a block of q ids and a line of ``width`` ids that an edge joins. Lines lie within blocks."""
    if q % width:
        raise ValueError("a block holds whole lines")
    line = t.members.join(perm.select(F.col("old").alias("id"), "new"), "id").select("cls", F.floor(F.col("new") / width).cast("long").alias("line")).distinct()
    parts = lambda n, of: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(max(0, -(-n // of) - 1)).cast("long")))
    n_lines, n_blocks = -(-t.n // width), -(-t.n // q)
    left = near.select("a", "blk", F.floor(F.col("blk") / BLOCKS).alias("bp")).select("*", parts(n_lines, LINES).alias("lp"))
    right = line.select("cls", "line", F.floor(F.col("line") / LINES).alias("lp")).select("*", parts(n_blocks, BLOCKS).alias("bp"))

    def count(blocks: pa.Table, lines: pa.Table) -> pa.Table:
        found = 0
        if blocks.num_rows and lines.num_rows:
            a, blk = (blocks.column(c).to_numpy() for c in ("a", "blk"))
            cls, at = lines.column("cls").to_numpy(), lines.column("line").to_numpy() % LINES
            names, place = np.unique(cls, return_inverse=True)
            known = np.isin(a, names)
            a, blk = np.searchsorted(names, a[known]), blk[known]
            order = np.lexsort((a, blk))
            groups = np.split(a[order], np.nonzero(np.diff(blk[order]))[0] + 1)
            found = sum(lines_of(groups, place, at, len(names)))
        return pa.table({"c": pa.array([found], pa.int64())})

    met = left.groupBy("bp", "lp").cogroup(right.groupBy("bp", "lp")).applyInArrow(count, "c long").agg(F.coalesce(F.sum("c"), F.lit(0)).alias("c"))
    # a line within the block that only reads itself is not read
    own = line.withColumn("blk", F.floor(F.col("line") / (q // width))).join(near.withColumnRenamed("a", "cls"), ["cls", "blk"])
    lonely = own.groupBy("line").agg(F.every("alone").alias("alone")).agg(F.count_if("alone").alias("own"))
    return met.crossJoin(lonely).select((F.col("c") - F.col("own")).alias("lines"))
