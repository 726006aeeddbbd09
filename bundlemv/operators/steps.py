"""One product of every method: shares (block, id, share) -> sums (block, id, s).

A factory prepares what never changes, places it and keeps it; the returned step runs once per
iteration. What an iteration shuffles is the method's message stream and nothing else:
bundles for the bundled method, edges for per-edge binning, nothing (but a broadcast) for
pulling.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bundlemv.functions.blocks import gather_block, scatter_block
from bundlemv.graph import Graph, reverse
from bundlemv.operators.blocks import balanced_blocks, blocked, block_of, parts_of, place
from bundlemv.operators.layout import CHUNK_EDGES, Packed, bundles, packed_layout, packed_lists, packed_pairs

#: Vertices whose shares may be broadcast for pulling (16 bytes each, so 160 MB).
MAX_BROADCAST_IDS = 10_000_000

Step = Callable[[DataFrame], DataFrame]


@dataclass
class Method:
    """A prepared method: ``gather`` adds up what ``scatter`` sends; ``kept`` are its persisted inputs.

    Methods that store no messages have no scatter: their gather reads the shares.
    """

    gather: Step
    kept: list[DataFrame] = field(default_factory=list)
    scatter: Step | None = None

    def step(self, shares: DataFrame) -> DataFrame:
        return self.gather(self.scatter(shares) if self.scatter else shares)

    def release(self) -> None:
        for df in self.kept:
            df.unpersist()


def count_values(sent: DataFrame) -> Column:
    """Values in a message stream: a row each, or the lengths of its arrays."""
    return F.sum(F.size("vals")) if "vals" in sent.columns else F.count("*")


def allow_placement(spark: SparkSession) -> None:
    """Let joins and aggregates on (block, id) use a placement by block alone."""
    spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")


def summed(df: DataFrame, value: Column | str = "v") -> DataFrame:
    return df.groupBy("block", "id").agg(F.sum(value).alias("s"))


def _weight(g: Graph) -> list[str]:
    return ["weight"] if g.weighted else []


def _times_weight(g: Graph, value: str, weight: str = "weight") -> Column:
    return F.col(value) * F.col(weight) if g.weighted else F.col(value)


# --- bundled ------------------------------------------------------------------


def _lists(g: Graph, q: int) -> DataFrame:
    """dst_block, src, e: array of (dst[, weight]) of one bundle, in id order."""
    e = place(blocked(g, q).select("dst_block", "src", "dst", *_weight(g)), "dst_block")  # the grouping keeps this placement
    return e.groupBy("dst_block", "src").agg(F.sort_array(F.collect_list(F.struct("dst", *_weight(g)))).alias("e"))


def _apply_lists(updates: DataFrame, lists: DataFrame, g: Graph) -> DataFrame:
    met = updates.join(lists, ["dst_block", "src"]).select("dst_block", "share", F.explode("e").alias("e"))
    return summed(met.select(F.col("dst_block").alias("block"), F.col("e.dst").alias("id"), _times_weight(g, "share", "e.weight").alias("v")))


def bundled_rows(g: Graph, q: int) -> Method:
    """A row per bundle over the compressed layout; gather walks each bundle's list."""
    lists = _lists(g, q).persist()
    layout = place(lists.select(block_of("src", q).alias("src_block"), "dst_block", "src"), "src_block").persist()  # a list per bundle

    def scatter(shares: DataFrame) -> DataFrame:
        sent = shares.join(layout, (shares.block == layout.src_block) & (shares.id == layout.src)).select("dst_block", "src", "share")
        return place(sent, "dst_block")

    return Method(lambda sent: _apply_lists(sent, lists, g), [layout, lists], scatter)


def bundled_adjacency(g: Graph, q: int) -> Method:
    """The plain adjacency: every step scans all edges and keeps the first of each bundle."""
    edges = place(blocked(g, q).select("src_block", "dst_block", "src", "dst"), "src_block").sortWithinPartitions("src_block", "src", "dst").persist()
    lists = _lists(g, q).persist()

    def scatter(shares: DataFrame) -> DataFrame:
        near = F.lag("dst_block").over(Window.partitionBy("src_block", "src").orderBy("dst"))  # in the kept order: no sort
        first = edges.withColumn("before", near).where("before is null or before <> dst_block")
        return place(shares.join(first, (shares.block == first.src_block) & (shares.id == first.src)).select("dst_block", "src", "share"), "dst_block")

    return Method(lambda sent: _apply_lists(sent, lists, g), [edges, lists], scatter)


def bundled_resend(g: Graph, q: int) -> Method:
    """Destination lists travel with the values in every step: what reuse avoids."""
    both = place(bundles(g, q).select("src_block", "dst_block", "src", "dsts"), "src_block").persist()

    def scatter(shares: DataFrame) -> DataFrame:
        return place(shares.join(both, (shares.block == both.src_block) & (shares.id == both.src)).select("dst_block", "share", "dsts"), "dst_block")

    def gather(sent: DataFrame) -> DataFrame:
        return summed(sent.select(F.col("dst_block").alias("block"), F.explode("dsts").alias("id"), F.col("share").alias("v")))

    return Method(gather, [both], scatter)


def _block_vectors(shares: DataFrame) -> DataFrame:
    """block, vals: the share of every id of a block, in id order (0 where a vertex sends nothing)."""
    x = F.coalesce("share", F.lit(0).cast(shares.schema["share"].dataType))
    return shares.groupBy("block").agg(F.sort_array(F.collect_list(F.struct("id", x.alias("x")))).getField("x").alias("vals"))


def _scatter_packed(shares: DataFrame, layout: DataFrame, q: int) -> DataFrame:
    """dst_block, src_block, vals: at most one row per block pair, a value per bundle."""
    met = _block_vectors(shares).join(layout, F.col("block") == layout.src_block)
    base = F.col("src_block").cast("long") * q
    return place(met.select("dst_block", "src_block", F.transform("srcs", lambda s: F.get("vals", (s - base).cast("int"))).alias("vals")), "dst_block")


def bundled(g: Graph, q: int, chunk_edges: int = CHUNK_EDGES) -> Method:
    """Values of a block pair in one row; each id knows the place of its value, so gather has no branch."""
    return bundled_on(packed_pairs(g, q, chunk_edges))


def bundled_on(p: Packed) -> Method:
    """The bundled method on a layout that is placed.

    With chunks, a hub block's sums are made in two levels: by chunk, then by block.
    """
    w = ["weights"] if p.weighted else []
    flags = "codes" in p.lists.columns
    lists = p.lists.select(*p.key, *(["codes"] if flags else ["ids", "pos"]), *w)
    # built once, used in every iteration
    picked, near = F.transform("srcs", lambda s: F.get("vals", s)).alias("vals"), F.col("block") == p.layout.src_block
    value = F.get("vals", F.get("pos", F.col("i")))
    value = value * F.get("weights", F.col("i")) if w else value
    whole = (F.col("block").cast("long") * p.q + F.col("local")).alias("id")
    local = F.when(F.col("local") < 0, -1 - F.col("local")).otherwise(F.col("local")) if flags else F.col("local")
    unnested = [F.col("dst_block").alias("block"), "chunk", "vals", "pos", *w, F.posexplode("ids").alias("i", "local")]

    def scatter(shares: DataFrame) -> DataFrame:
        return place(_block_vectors(shares).join(p.layout, near).select(*p.key, picked), *p.place)

    def gather(sent: DataFrame) -> DataFrame:
        met = sent.join(lists, list(p.key))
        each = (_walked(met) if flags else met).select(*unnested).withColumn("local", local)
        if p.chunked:
            part = each.groupBy("block", "chunk", "local").agg(F.sum(value).alias("v"))
            sums = place(part.select("block", "local", "v"), "block").groupBy("block", "local").agg(F.sum("v").alias("s"))
        else:
            sums = each.groupBy("block", "local").agg(F.sum(value).alias("s"))
        return sums.select("block", whole, "s")

    return Method(gather, [p.layout, p.lists], scatter)


def bundled_nested(g: Graph, q: int) -> Method:
    """Values of a block pair in one row beside the pair's bundles: gather unnests a value with its list, then the list."""
    w = _weight(g)
    e = place(blocked(g, q).select("dst_block", "src_block", "src", "dst", *w), "dst_block")
    own = e.groupBy("dst_block", "src_block", "src").agg(F.sort_array(F.collect_list(F.struct("dst", *w) if w else F.col("dst"))).alias("b"))
    lists = own.groupBy("dst_block", "src_block").agg(F.sort_array(F.collect_list(F.struct("src", "b"))).alias("l")).select("dst_block", "src_block", F.transform("l", lambda x: x["b"]).alias("l")).persist()
    layout = packed_layout(g, q).persist()

    def gather(sent: DataFrame) -> DataFrame:
        met = sent.join(lists, ["dst_block", "src_block"])
        each = met.select(F.col("dst_block").alias("block"), "vals", F.posexplode("l").alias("i", "b"))
        each = each.select("block", F.get("vals", F.col("i")).alias("x"), F.explode("b").alias("d"))
        return summed(each.select("block", "d.dst", (F.col("x") * F.col("d.weight")).alias("v")).withColumnRenamed("dst", "id") if w else each.select("block", F.col("d").alias("id"), F.col("x").alias("v")))

    return Method(gather, [layout, lists], lambda shares: _scatter_packed(shares, layout, q))


def bundled_prefix(g: Graph, q: int, chunk_edges: int = CHUNK_EDGES) -> Method:
    """Gather by flags: the place of an id's value is the running sum of the flags up to it, less one, made anew in every step."""
    return bundled_on(packed_pairs(g, q, chunk_edges, flags=True))


def _walked(met: DataFrame) -> DataFrame:
    """``met`` with ids and pos, walked along the flags of its codes: the i-th flag's place holds until the next flag."""
    met = met.withColumn("at", F.filter(F.sequence(F.lit(0), F.size("codes") - 1), lambda i: F.get("codes", i) < 0))
    until = F.concat(F.slice("at", F.lit(2), F.size("at")), F.array(F.size("codes")))
    met = met.withColumn("pos", F.flatten(F.transform(F.zip_with("at", until, lambda a, b: b - a), lambda n, i: F.array_repeat(i, n))))
    return met.withColumnRenamed("codes", "ids")


def bundled_arrow(g: Graph, q: int) -> Method:
    """Packed rows, scattered and gathered by vectorised functions on whole blocks."""
    layout, lists = packed_layout(g, q).persist(), packed_lists(g, q, flags=True).persist()

    def scatter(shares: DataFrame) -> DataFrame:
        met = _block_vectors(shares).join(layout, F.col("block") == layout.src_block).select("dst_block", "src_block", "srcs", "vals")
        return place(scatter_block(met, q), "dst_block")

    return Method(lambda sent: gather_block(sent, lists, q, g.weighted), [layout, lists], scatter)


# --- baselines ----------------------------------------------------------------


def per_edge(g: Graph, q: int) -> Method:
    """A message (value, destination) per edge into the destination block's bin; ids travel each time."""
    edges = place(blocked(g, q), "src_block").persist()

    def scatter(shares: DataFrame) -> DataFrame:
        met = shares.join(edges, (shares.block == edges.src_block) & (shares.id == edges.src))
        return place(met.select(F.col("dst_block").alias("block"), F.col("dst").alias("id"), _times_weight(g, "share").alias("v")), "block")

    return Method(summed, [edges], scatter)


def per_edge_reuse(g: Graph, q: int) -> Method:
    """Per-edge messages whose destination ids are stored once, in the order in which values arrive."""
    w = ["weights"] if g.weighted else []
    per = blocked(g, q).groupBy("src_block", "dst_block").agg(F.sort_array(F.collect_list(F.struct("src", "dst", *_weight(g)))).alias("e"))
    out = place(per.select("src_block", "dst_block", F.col("e.src").alias("srcs")), "src_block").persist()
    ids = place(per.select("src_block", "dst_block", F.col("e.dst").alias("ids"), *([F.col("e.weight").alias("weights")] if g.weighted else [])), "dst_block").persist()

    def gather(sent: DataFrame) -> DataFrame:
        met = sent.join(ids, ["dst_block", "src_block"])
        each = met.select(F.col("dst_block").alias("block"), "vals", *w, F.posexplode("ids").alias("i", "id"))
        value = F.get("vals", F.col("i"))
        return summed(each.select("block", "id", (value * F.get("weights", F.col("i")) if w else value).alias("v")))

    return Method(gather, [out, ids], lambda shares: _scatter_packed(shares, out, q))


def pull(g: Graph, q: int, balanced: bool = False, max_broadcast: int = MAX_BROADCAST_IDS) -> Method:
    """Destinations read their in-neighbours' shares; nothing is stored in between.

    Shares of up to ``max_broadcast`` vertices go to every executor; beyond that the reads are
    a shuffled join. ``balanced`` deals destinations so that tasks get equal numbers of edges.
    """
    edges = blocked(g, q).select("src", "dst", F.col("dst_block").alias("block"), *_weight(g))
    if balanced:
        own = balanced_blocks(reverse(g), parts_of(g.spark)).select(F.col("id").alias("dst"), F.col("block").alias("task"))
        edges = place(edges.join(own, "dst"), "task").persist()
    else:
        edges = place(edges.withColumn("task", F.col("block")), "task").persist()

    def step(shares: DataFrame) -> DataFrame:
        own = shares.where("share is not null").select(F.col("id").alias("src"), "share")
        met = edges.join(F.broadcast(own) if g.n <= max_broadcast else own, "src")
        return met.groupBy("task", "block", F.col("dst").alias("id")).agg(F.sum(_times_weight(g, "share")).alias("s")).select("block", "id", "s")

    return Method(step, [edges])


def edge_scan(g: Graph, q: int) -> Method:
    """A scan of the plain pair list, which reads both ids of every edge."""
    edges = g.edges.persist()

    def step(shares: DataFrame) -> DataFrame:
        met = edges.join(shares.select(F.col("id").alias("src"), "share"), "src")
        return summed(met.select(block_of("dst", q).alias("block"), F.col("dst").alias("id"), _times_weight(g, "share").alias("v")))

    return Method(step, [edges])


def naive(g: Graph, q: int) -> Method:
    """Join and group as a general framework would: nothing is placed or kept."""

    def step(shares: DataFrame) -> DataFrame:
        met = g.edges.join(shares.select(F.col("id").alias("src"), "share"), "src")
        sums = met.groupBy(F.col("dst").alias("id")).agg(F.sum(_times_weight(g, "share")).alias("s"))
        return sums.select(block_of("id", q).alias("block"), "id", "s")

    return Method(step)


METHODS: dict[str, Callable[..., Method]] = {
    "bundled": bundled, "bundled_nested": bundled_nested, "bundled_rows": bundled_rows, "bundled_adjacency": bundled_adjacency, "bundled_prefix": bundled_prefix,
    "bundled_arrow": bundled_arrow, "bundled_resend": bundled_resend, "per_edge": per_edge_reuse, "per_edge_resend": per_edge,
    "pull": pull, "edge_scan": edge_scan, "naive": naive,
}


def buffer_flushes(g: Graph, q: int, rows: int) -> DataFrame:
    """dst_block, messages, flushes: write-combining buffers of ``rows`` messages per bin and source block."""
    per = blocked(g, q).groupBy("src_block", "dst_block").agg(F.count("*").alias("c"))
    return per.groupBy("dst_block").agg(F.sum("c").alias("messages"), F.sum(F.ceil(F.col("c") / rows)).alias("flushes"))
