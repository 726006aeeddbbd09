"""What is built once: bundles, destination lists, write offsets, and the source-to-block layout."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from bundlemv.graph import Graph
from bundlemv.operators.blocks import block_count, block_of, blocked, parts_of, place
from bundlemv.session import setting

TOP = 1 << 63


def encode_flag(ident: Column, first: Column) -> Column:
    """An id with its top bit set if it starts a bundle."""
    return F.when(first, ident.bitwiseOR(-TOP)).otherwise(ident)


def decode_flag(code: Column) -> tuple[Column, Column]:
    """(id, whether it starts a bundle)."""
    return code.bitwiseAND(TOP - 1), F.getbit(code, F.lit(63)) == 1


def bundles(g: Graph, q: int) -> DataFrame:
    """src, src_block, dst_block, dsts (sorted): one row per message of the bundled method."""
    return blocked(g, q).groupBy("src_block", "dst_block", "src").agg(F.sort_array(F.collect_list("dst")).alias("dsts"))


def first_edges(g: Graph, q: int) -> DataFrame:
    """The first edge of each bundle, found by comparing neighbours in the sorted adjacency."""
    before = F.lag("dst_block").over(Window.partitionBy("src").orderBy("dst"))
    return blocked(g, q).withColumn("b", before).where("b is null or b <> dst_block").select("src", "dst", "src_block", "dst_block")


def dest_lists(g: Graph, q: int) -> DataFrame:
    """dst_block, src_block, src, dst, flag, code in the order (dst_block, src_block, src, dst); flag marks a bundle's first id."""
    rank = F.row_number().over(Window.partitionBy("src", "dst_block").orderBy("dst"))
    own = blocked(g, q).withColumn("flag", rank == 1)
    return own.select("dst_block", "src_block", "src", "dst", "flag", encode_flag(F.col("dst"), F.col("flag")).alias("code"))


def pair_counts(g: Graph, q: int) -> DataFrame:
    """src_block, dst_block, n_values, n_ids."""
    per = blocked(g, q).groupBy("src_block", "dst_block", "src").agg(F.count("*").alias("e"))
    return per.groupBy("src_block", "dst_block").agg(F.count("*").alias("n_values"), F.sum("e").alias("n_ids"))


def write_offsets(g: Graph, q: int, kind: str = "values") -> DataFrame:
    """src_block, dst_block, n, off: where each source block writes in a destination block's bin."""
    n = {"values": "n_values", "ids": "n_ids"}[kind]
    before = Window.partitionBy("dst_block").orderBy("src_block").rowsBetween(Window.unboundedPreceding, -1)
    return pair_counts(g, q).select("src_block", "dst_block", F.col(n).alias("n"), F.coalesce(F.sum(n).over(before), F.lit(0)).alias("off"))


def offsets_disjoint(offsets: DataFrame) -> DataFrame:
    """dst_block, size, disjoint: whether the written ranges follow each other without gap or overlap and fill the bin."""
    after = F.lead("off").over(Window.partitionBy("dst_block").orderBy("src_block"))
    ends = offsets.withColumn("end", F.col("off") + F.col("n")).withColumn("next", after)
    return ends.groupBy("dst_block").agg(F.sum("n").alias("size"), F.every(F.coalesce(F.col("next") == F.col("end"), F.lit(True))).alias("a"), F.max("end").alias("last"), F.min("off").alias("first")).select(
        "dst_block", "size", (F.col("a") & (F.col("last") == F.col("size")) & (F.col("first") == 0)).alias("disjoint"))


def block_layout(g: Graph, q: int) -> DataFrame:
    """src_block, dst_block, src: parallel edges into a block compressed to one."""
    return blocked(g, q).select("src_block", "dst_block", "src").distinct()


def transpose_layout(layout: DataFrame) -> DataFrame:
    """src_block, dst_block, srcs (sorted)."""
    return layout.groupBy("src_block", "dst_block").agg(F.sort_array(F.collect_list("src")).alias("srcs"))


def layout_csr(g: Graph, q: int) -> DataFrame:
    """src_block, dst_block (0 .. k), off: the offset array of each source block's transposed layout, empty rows included."""
    k = block_count(g.n, q)
    grid = g.spark.range(k * (k + 1)).select(F.floor(F.col("id") / (k + 1)).cast("int").alias("src_block"), (F.col("id") % (k + 1)).cast("int").alias("dst_block"))
    before = Window.partitionBy("src_block").orderBy("dst_block").rowsBetween(Window.unboundedPreceding, -1)
    return grid.join(pair_counts(g, q), ["src_block", "dst_block"], "left").select("src_block", "dst_block", F.coalesce(F.sum(F.coalesce("n_values", F.lit(0))).over(before), F.lit(0)).alias("off"))


def build_onepass(g: Graph, q: int) -> DataFrame:
    """src_block, dst_block, srcs, n_values, n_ids, value_off, id_off from one aggregation of the edges."""
    pairs = blocked(g, q).groupBy("src_block", "dst_block").agg(F.sort_array(F.collect_set("src")).alias("srcs"), F.count("*").alias("n_ids")).withColumn("n_values", F.size("srcs").cast("long"))
    before = Window.partitionBy("dst_block").orderBy("src_block").rowsBetween(Window.unboundedPreceding, -1)
    off = lambda c: F.coalesce(F.sum(c).over(before), F.lit(0))
    return pairs.select("src_block", "dst_block", "srcs", "n_values", "n_ids", off("n_values").alias("value_off"), off("n_ids").alias("id_off"))


def local_ids(g: Graph, q: int) -> DataFrame:
    """dst_block, src, dst, local: ids counted from their block's start, in the narrowest type that holds them."""
    kind = "byte" if q <= 1 << 7 else "short" if q <= 1 << 15 else "int"
    return blocked(g, q).select("dst_block", "src", "dst", (F.col("dst") - F.col("dst_block").cast("long") * q).cast(kind).alias("local"))


#: Edges of a destination block that one task gathers; blocks with more are cut into chunks by source.
CHUNK_EDGES = 1 << 22
#: Chunks of a block that are small against a task's share of the edges are dealt together, up to this part of the share.
SHARE = 4
#: Blocks that are cut may be broadcast up to this number (16 bytes each); there are at most m / CHUNK_EDGES of them.
BROADCAST_HUBS = 100_000


def hub_chunks(g: Graph, q: int, chunk_edges: int = CHUNK_EDGES) -> DataFrame:
    """dst_block, chunks, e: the destination blocks with more than ``chunk_edges`` edges, and their edges."""
    per = blocked(g, q).groupBy("dst_block").agg(F.count("*").alias("e")).where(F.col("e") > chunk_edges)
    return per.select("dst_block", F.ceil(F.col("e") / chunk_edges).cast("int").alias("chunks"), "e")


@dataclass
class Packed:
    """layout: src_block, dst_block, chunk[, slice], srcs; lists: dst_block, chunk[, slice], src_block, ids, pos (or codes)[, weights].

    srcs and ids count from their block's start. pos is the 0-based place of an id's value among
    the values of its row; it never changes and so is stored once. codes stand instead of both: an
    id, or -1 less the id if it starts a bundle. Rows stand for pairs of
    blocks; a hub block's pairs are cut into chunks by source, so no row holds more than about
    CHUNK_EDGES edges, nor does a task more than that or, if CHUNK_EDGES is far below it, a part of
    its share: then a chunk is dealt out whole and its rows are cut into slices. ``chunked``: whether
    there is such a block.
    """

    layout: DataFrame
    lists: DataFrame
    q: int
    weighted: bool
    chunked: bool

    @property
    def place(self) -> tuple[str, ...]:
        """By what messages are dealt."""
        return ("dst_block", "chunk") if self.chunked else ("dst_block",)

    @property
    def key(self) -> tuple[str, ...]:
        """What tells the rows apart."""
        return ("dst_block", "chunk", *(["slice"] if "slice" in self.lists.columns else []), "src_block")

    def placed(self) -> Packed:
        """Dealt out, sorted as later joins want it, and kept."""
        lists = place(self.lists, *self.place).sortWithinPartitions(*self.key).persist()
        layout = place(self.layout, "src_block").sortWithinPartitions("src_block").persist()
        return Packed(layout, lists, self.q, self.weighted, self.chunked)


def packed_pairs(g: Graph, q: int, chunk_edges: int = CHUNK_EDGES, flags: bool = False) -> Packed:
    """The kept form of the bundled method from one shuffle and one sort of the edges, and one shuffle of the bundles' sources.

    The lists come placed, sorted and kept, and the layout is read off them. With ``flags`` they
    hold codes, and no places.
    """
    w = ["weight"] if g.weighted else []
    e = blocked(g, q).select("dst_block", "src", "dst", *w)
    hubs = hub_chunks(g, q, chunk_edges).persist()
    n_hubs, held = hubs.agg(F.count("*"), F.coalesce(F.sum("e"), F.lit(0))).first()
    together = max(1, held // (SHARE * parts_of(g.spark) * chunk_edges))
    key = ["dst_block", "chunk", *(["slice"] if together > 1 else []), "src_block"]
    if n_hubs:
        cut = F.pmod(F.xxhash64("src"), F.coalesce("chunks", F.lit(1))).cast("int")
        e = e.join(F.broadcast(hubs.drop("e")) if n_hubs <= BROADCAST_HUBS else hubs.drop("e"), "dst_block", "left").withColumn(key[-2], cut).drop("chunks")
        if together > 1:
            e = e.withColumn("chunk", F.floor(F.col("slice") / together).cast("int"))
        e = place(e, "dst_block", "chunk")
    else:
        e = place(e, "dst_block").withColumn("chunk", F.lit(0))
    e = e.withColumn("src_block", block_of("src", q))  # what follows from the others is not dealt
    local = lambda c, b: (F.col(c) - F.col(b).cast("long") * q).cast("int")
    of_pair = Window.partitionBy(*key).orderBy("src")
    first = F.coalesce(F.lag("src").over(of_pair) != F.col("src"), F.lit(True))
    own = {"ids": local("dst", "dst_block"), "pos": F.dense_rank().over(of_pair) - 1}
    if flags:
        own = {"codes": F.when(first, -1 - own["ids"]).otherwise(own["ids"])}
    rows = e.select(*key, *[c.alias(k) for k, c in own.items()], F.when(first, local("src", "src_block")).alias("src"), *w)
    rows = rows.groupBy(*key).agg(F.collect_list(F.struct(*own, *w)).alias("e"), F.sort_array(F.collect_list("src")).alias("srcs"))
    lists = rows.select(*key, *[F.col(f"e.{k}").alias(k) for k in own], *([F.col("e.weight").alias("weights")] if w else []), "srcs")
    # the rows come in the order of their groups; a hash of many small groups would write and sort all of them once more
    with setting(g.spark, "spark.sql.execution.replaceHashWithSortAgg", "true"):
        lists = lists.sortWithinPartitions(*key).persist()
        layout = place(lists.select(*key, "srcs"), "src_block").sortWithinPartitions("src_block").persist()
        if n_hubs or not flags:
            layout.count()
    hubs.unpersist()
    return Packed(layout, lists, q, g.weighted, n_hubs > 0)


def packed_layout(g: Graph, q: int) -> DataFrame:
    """src_block, dst_block, srcs: one row per block pair with messages, placed by source block."""
    e = place(blocked(g, q).select("src_block", "dst_block", "src"), "src_block")
    return e.groupBy("src_block", "dst_block").agg(F.sort_array(F.collect_set("src")).alias("srcs"))


def packed_lists(g: Graph, q: int, flags: bool = False) -> DataFrame:
    """dst_block, src_block, ids, pos[, flags][, weights]: ids in the order of the bundles of a block pair, placed by destination block.

    pos is the 0-based place of an id's value among the pair's values: the number of bundles
    that start up to the id, less one. It never changes and so is stored once. The edges are
    dealt out once; both groupings keep that placement.
    """
    w = ["weight"] if g.weighted else []
    e = place(blocked(g, q).select("dst_block", "src_block", "src", "dst", *w), "dst_block")
    own = e.groupBy("dst_block", "src_block", "src").agg(F.sort_array(F.collect_list(F.struct("dst", *w))).alias("b"))
    rows = own.groupBy("dst_block", "src_block").agg(F.sort_array(F.collect_list(F.struct("src", "b"))).alias("l")).select("dst_block", "src_block", F.transform("l", lambda x: x["b"]).alias("l"))
    cols = [
        F.flatten(F.transform("l", lambda b: b["dst"])).alias("ids"),
        F.flatten(F.transform("l", lambda b, i: F.array_repeat(i, F.size(b)))).alias("pos"),
    ]
    if flags:
        cols.append(F.flatten(F.transform("l", lambda b: F.transform(b, lambda x, j: j == 0))).alias("flags"))
    if w:
        cols.append(F.flatten(F.transform("l", lambda b: b["weight"])).alias("weights"))
    return rows.select("dst_block", "src_block", *cols)
