"""Iterated rank by any method, with the options around it."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bundlemv.graph import Graph
from bundlemv.operators.blocks import block_of, place, width_for
from bundlemv.operators.steps import METHODS, Method, allow_placement
from bundlemv.operators.twins import Twins
from bundlemv.session import materialise

DAMPING = 0.85
#: Iterations between durable copies of the ranks; they bound what a lost executor costs and how long a plan grows.
#: Options that read the ranks between iterations make a copy each time: n rows, where an iteration handles m edges.
CHECKPOINT_EVERY = 5


@contextmanager
def settled_plans(spark: SparkSession) -> Iterator[None]:
    """Plans without adaptive changes: blocks are placed explicitly, and planning each stage of a long loop anew costs more than it runs."""
    name = "spark.sql.adaptive.enabled"
    old = spark.conf.get(name)
    spark.conf.set(name, "false")
    try:
        yield
    finally:
        spark.conf.set(name, old)


def with_sink_loops(g: Graph) -> Graph:
    """Sinks keep their rank: each gets an edge to itself."""
    own = g.vertices.join(g.edges.select(F.col("src").alias("id")), "id", "left_anti")
    loops = own.select(F.col("id").alias("src"), F.col("id").alias("dst"), *([F.lit(1.0).alias("weight")] if g.weighted else []))
    return g.with_edges(g.edges.unionByName(loops))


def vertex_table(g: Graph, q: int, teleport: DataFrame | None = None) -> DataFrame:
    """block, id, out (out-degree or sum of weights, null for sinks), tele; placed by block."""
    out = g.edges.groupBy(F.col("src").alias("id")).agg((F.sum("weight") if g.weighted else F.count("*").cast("double")).alias("out"))
    v = g.vertices.join(out, "id", "left")
    if teleport is None:
        v = v.withColumn("tele", F.lit(1.0 / max(g.n, 1)))
    else:
        v = v.join(teleport.select("id", F.col("tele").cast("double").alias("tele")), "id", "left").withColumn("tele", F.coalesce("tele", F.lit(0.0)))
    return place(v.select(block_of("id", q).alias("block"), "id", "out", "tele"), "block")


def apply_rank(vertices: DataFrame, sums: DataFrame, damping: float, spread: float = 0.0, value_type: str = "double") -> DataFrame:
    """block, id, rank, share: teleport, damping, and the division by what a vertex sends."""
    rank = (1 - damping) * F.col("tele") + damping * (F.coalesce("s", F.lit(0.0)) + F.lit(spread))
    return vertices.join(sums, ["block", "id"], "left").select("block", "id", rank.alias("rank"), (rank / F.col("out")).cast(value_type).alias("share"))


def first_ranks(n: int, vertices: DataFrame, start: DataFrame | None = None, value_type: str = "double") -> DataFrame:
    own = vertices.select("block", "id", "out", F.lit(1.0 / max(n, 1)).alias("rank"))
    if start is not None:
        own = vertices.join(start.select("id", "rank"), "id", "left").select("block", "id", "out", F.coalesce("rank", F.lit(0.0)).alias("rank"))
    return own.select("block", "id", "rank", (F.col("rank") / F.col("out")).cast(value_type).alias("share"))


@dataclass
class Prepared:
    """A graph whose layout stands already: ids 0 .. n-1, the width, block, id, out, tele by block, and the method on that layout."""

    n: int
    q: int
    vertices: DataFrame
    method: Method


def prepare(g: Graph, method: str = "bundled", q: int | None = None, personalization: DataFrame | None = None, **flags) -> Prepared:
    allow_placement(g.spark)
    q = q or width_for(g)
    vertices = vertex_table(g, q, personalization).sortWithinPartitions("block", "id").persist()
    return Prepared(g.n, q, vertices, METHODS[method](g, q, **flags))


def iterate(
    g: Graph | None, method: str = "bundled", q: int | None = None, iters: int = 20, damping: float = DAMPING, dangling: str = "drop",
    personalization: DataFrame | None = None, start: DataFrame | None = None, tol: float | None = None, value_type: str = "double",
    every: int = CHECKPOINT_EVERY, prepared: Prepared | None = None, kept: list | None = None, **flags,
) -> Iterator[DataFrame]:
    """The ranks (block, id, rank, share) before the first and after each iteration.

    dangling: "drop" lets the rank of sinks leak, "spread" deals it to all vertices, "self"
    lets sinks keep it. q: width of blocks, planned for the session if not given. tol: stop
    when the ranks move by less in sum. value_type: "float" sends values of 4 bytes. every:
    iterations between durable copies. prepared: a layout to run on, instead of ``g``. What is
    persisted is added to ``kept``, to be released when the ranks have been read.
    """
    if dangling not in ("drop", "spread", "self"):
        raise ValueError("dangling is drop, spread or self")
    if value_type not in ("double", "float"):
        raise ValueError("value_type is double or float")
    own = prepared is None
    if own:
        prepared = prepare(with_sink_loops(g) if dangling == "self" else g, method, q, personalization, **flags)
    elif dangling == "self":
        raise ValueError("a prepared layout has its loops or not")
    vertices, work, n = prepared.vertices, prepared.method, prepared.n
    allow_placement(vertices.sparkSession)
    if own and kept is not None:
        kept += [vertices, *work.kept]
    cur = first_ranks(n, vertices, start, value_type)
    yield cur
    watch = tol is not None or dangling == "spread"
    for i in range(1, iters + 1):
        spread = 0.0
        if dangling == "spread":
            lost = cur.where("share is null").agg(F.sum("rank")).first()[0]
            spread = (lost or 0.0) / n
        new = apply_rank(vertices, work.step(cur), damping, spread, value_type)
        if watch or i % every == 0 and i < iters:
            with settled_plans(vertices.sparkSession):
                new = place(materialise(new, "ranks"), "block")
        done = False
        if tol is not None:
            moved = new.select("id", "rank").join(cur.select("id", F.col("rank").alias("was")), "id").agg(F.sum(F.abs(F.col("rank") - F.col("was")))).first()[0]
            done = (moved or 0.0) < tol
        cur = new
        yield cur
        if done:
            return


def run(g: Graph | None, method: str = "bundled", **options) -> DataFrame:
    """id, rank after the last iteration; options as for ``iterate``. The ranks are written, and all that was kept for them is released, but for what came ``prepared``."""
    kept: list[DataFrame] = []
    last = None
    for last in iterate(g, method, kept=kept, **options):
        pass
    with settled_plans(last.sparkSession):
        out = materialise(last.select("id", "rank"), "ranks")
    for df in kept:
        df.unpersist()
    return out


def run_folded(t: Twins, method: str = "bundled", **options) -> DataFrame:
    """``run`` by classes of twins: a class's mass is dealt by the numbers of neighbours that its members have in each class, and shared out evenly. What sinks lose is dealt by vertex, not by class, so "spread" has no form here."""
    if options.get("dangling") == "spread":
        raise ValueError("by classes, dangling is drop or self")
    sizes = t.sizes.persist()
    w = (F.col("size") - (F.col("a") == F.col("b")).cast("long")).cast("double").alias("weight")
    edges = t.links.join(sizes.withColumnRenamed("cls", "b"), "b").select(F.col("a").alias("src"), F.col("b").alias("dst"), w)
    g = Graph(edges, sizes.count()).persist()
    even = sizes.select(F.col("cls").alias("id"), (F.col("size") / t.n).alias("tele"))
    out = run(g, method, personalization=even, start=even.withColumnRenamed("tele", "rank"), **options)
    g.release()
    own = out.withColumnRenamed("id", "cls").join(sizes, "cls").select("cls", (F.col("rank") / F.col("size")).alias("rank"))
    return t.members.join(own, "cls").select("id", "rank")


def masses(g: Graph, iters: int = 20, **options) -> DataFrame:
    """iteration, mass: the sum of ranks after each iteration; each is made from a written copy of the one before."""
    kept: list[DataFrame] = []
    rows = [(i, ranks.agg(F.sum("rank")).first()[0]) for i, ranks in enumerate(iterate(g, iters=iters, every=1, kept=kept, **options))]
    for df in kept:
        df.unpersist()
    return g.spark.createDataFrame(rows, "iteration long, mass double")
