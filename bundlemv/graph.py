"""Graphs and sparse matrices as DataFrames, dense ids, and plain graph algebra."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import cached_property
from typing import TYPE_CHECKING

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from bundlemv.session import materialise

if TYPE_CHECKING:
    from bundlemv.operators.twins import Twins

#: Rows that a sort by one task may take; beyond, ids are dealt by range partitions.
EDGE_SCHEMA = "src long, dst long"


@dataclass(frozen=True)
class Graph:
    """``edges`` (src long, dst long[, weight double]) over vertices 0 .. n-1; ``fold`` makes the same graph by classes of twins, if it can."""

    edges: DataFrame
    n: int
    fold: Callable[[], Twins | None] | None = field(default=None, compare=False)

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @property
    def weighted(self) -> bool:
        return "weight" in self.edges.columns

    @property
    def vertices(self) -> DataFrame:
        return self.spark.range(self.n)

    @cached_property
    def m(self) -> int:
        return self.edges.count()

    @cached_property
    def twins(self) -> Twins | None:
        return self.fold() if self.fold else None

    def with_edges(self, edges: DataFrame) -> Graph:
        return replace(self, edges=edges, fold=None)

    def persist(self) -> Graph:
        """Keep the edges where they were made; lost parts are computed again."""
        return replace(self, edges=self.edges.persist())

    def release(self) -> None:
        self.edges.unpersist()


@dataclass(frozen=True)
class Matrix:
    """``entries`` (i long, j long, w double) of an n_rows x n_cols matrix; a missing entry is 0."""

    entries: DataFrame
    n_rows: int
    n_cols: int

    def transpose(self) -> Matrix:
        return Matrix(self.entries.select(F.col("j").alias("i"), F.col("i").alias("j"), "w"), self.n_cols, self.n_rows)


def make_graph(edges: DataFrame, n: int, dedupe: bool = True) -> Graph:
    """A graph from any pairs; parallel edges merge (weights add up) unless ``dedupe`` is off."""
    if "weight" in edges.columns:
        edges = edges.select(F.col("src").cast("long"), F.col("dst").cast("long"), F.col("weight").cast("double"))
        return Graph(edges.groupBy("src", "dst").agg(F.sum("weight").alias("weight")) if dedupe else edges, n)
    edges = edges.select(F.col("src").cast("long"), F.col("dst").cast("long"))
    return Graph(edges.distinct() if dedupe else edges, n)


def check_ids(g: Graph) -> None:
    """Raise if an endpoint lies outside 0 .. n-1 or is null."""
    bad = g.edges.where("src is null or dst is null").limit(1).count() or g.edges.where(f"least(src, dst) < 0 or greatest(src, dst) >= {g.n}").limit(1).count()
    if bad:
        raise ValueError(f"an edge has an end outside 0 .. {g.n - 1}")


def dense_ids(rows: DataFrame, order: list[str | Column], name: str = "id") -> DataFrame:
    """``rows`` with 0-based places in the total order ``order``.

    A range-partitioned sort numbers rows within partitions; the partitions' counts, one row
    each, are summed up. No task sees all rows.
    """
    placed = rows.orderBy(*order).withColumn("__at", F.monotonically_increasing_id())
    placed = materialise(placed, "dense-ids").withColumn("__part", F.shiftright("__at", 33))
    counts = placed.groupBy("__part").agg(F.count("*").alias("__n"))
    before = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.select("__part", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__base"))
    inside = F.col("__at").bitwiseAND((1 << 33) - 1)
    return placed.join(F.broadcast(base), "__part").withColumn(name, inside + F.col("__base")).drop("__at", "__part", "__base")


# --- algebra ------------------------------------------------------------------


def degrees(g: Graph) -> DataFrame:
    """id, out_deg, in_deg of every vertex."""
    ends = g.edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("id"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("e"))
    per = ends.groupBy("e.id").agg(F.sum("e.o").alias("out_deg"), F.sum("e.i").alias("in_deg"))
    return g.vertices.join(per, "id", "left").select("id", F.coalesce("out_deg", F.lit(0)).cast("long").alias("out_deg"), F.coalesce("in_deg", F.lit(0)).cast("long").alias("in_deg"))


def degree_histogram(g: Graph) -> DataFrame:
    return degrees(g).groupBy("out_deg").agg(F.count("*").alias("vertices"))


def degree_percentiles(g: Graph, ps: tuple[float, ...]) -> DataFrame:
    own = degrees(g).agg(F.percentile("out_deg", F.array(*map(F.lit, ps))).alias("v"))
    return own.select(F.explode(F.arrays_zip(F.array(*map(F.lit, ps)).alias("p"), F.col("v"))).alias("x")).select(F.col("x.p").alias("p"), F.col("x.v").alias("out_deg"))


def summary(g: Graph) -> DataFrame:
    """One row: n, m, sinks, sources, isolated, largest degrees, mean degree."""
    some = lambda c: F.sum(F.when(c, 1).otherwise(0)).cast("long")
    return degrees(g).agg(
        F.count("*").alias("n"), F.sum("out_deg").alias("m"), some(F.col("out_deg") == 0).alias("sinks"), some(F.col("in_deg") == 0).alias("sources"),
        some((F.col("out_deg") == 0) & (F.col("in_deg") == 0)).alias("isolated"), F.max("out_deg").alias("max_out"), F.max("in_deg").alias("max_in"),
        F.round(F.sum("out_deg") / F.count("*"), 6).alias("mean_degree"),
    )


def sinks(g: Graph) -> DataFrame:
    return g.vertices.join(g.edges.select(F.col("src").alias("id")), "id", "left_anti")


def sources(g: Graph) -> DataFrame:
    return g.vertices.join(g.edges.select(F.col("dst").alias("id")), "id", "left_anti")


def targets(g: Graph) -> DataFrame:
    """Vertices with an in-edge."""
    return g.vertices.join(g.edges.select(F.col("dst").alias("id")), "id", "left_semi")


def reverse(g: Graph) -> Graph:
    return g.with_edges(g.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(["weight"] if g.weighted else [])))


def symmetrize(g: Graph) -> Graph:
    return make_graph(g.edges.unionByName(reverse(g).edges), g.n)


def reciprocal(g: Graph) -> DataFrame:
    """Edges whose reverse is an edge as well."""
    e = g.edges.select("src", "dst")
    return e.intersect(reverse(g.with_edges(e)).edges.select("src", "dst"))


def drop_loops(g: Graph) -> Graph:
    return g.with_edges(g.edges.where("src <> dst"))


def threshold(g: Graph, least: float) -> Graph:
    return g.with_edges(g.edges.where(F.col("weight") >= least))


def subgraph(g: Graph, keep: DataFrame) -> Graph:
    """Edges with both ends in ``keep`` (id); ids stay."""
    ids = keep.select("id").distinct()
    inside = g.edges.join(ids.withColumnRenamed("id", "src"), "src", "left_semi").join(ids.withColumnRenamed("id", "dst"), "dst", "left_semi")
    return g.with_edges(inside.select(g.edges.columns))


def contract(g: Graph, mapping: DataFrame, n: int) -> Graph:
    """Merge vertices by ``mapping`` (old, new); the weight of an edge is the number, or sum, of what it merges."""
    w = F.sum("weight") if g.weighted else F.count("*").cast("double")
    e = g.edges.join(mapping.select(F.col("old").alias("src"), F.col("new").alias("a")), "src").join(mapping.select(F.col("old").alias("dst"), F.col("new").alias("b")), "dst")
    return Graph(e.groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(w.alias("weight")), n)


def union(a: Graph, b: Graph) -> DataFrame:
    return a.edges.select("src", "dst").union(b.edges.select("src", "dst")).distinct()


def minus(a: Graph, b: Graph) -> DataFrame:
    return a.edges.select("src", "dst").exceptAll(b.edges.select("src", "dst"))


def sample_edges(g: Graph, keep: int, of: int) -> DataFrame:
    """A fixed share of the edges, picked by an integer hash of both ends."""
    h = (F.col("src") * 40503 + F.col("dst") * 9973 + 17) % 65521
    return g.edges.where(h % of < keep).select("src", "dst")
