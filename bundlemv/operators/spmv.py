"""Products of sparse matrices and vectors over a semiring, by the bundled method or per edge."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bundlemv.graph import Graph, Matrix
from bundlemv.operators.blocks import block_of, place
from bundlemv.operators.steps import allow_placement
from bundlemv.session import materialise


@dataclass(frozen=True)
class Semiring:
    add: Callable[[Column], Column]
    times: Callable[[Column, Column], Column]


SEMIRINGS = {
    "plus_times": Semiring(F.sum, lambda x, w: x * w),
    "min_plus": Semiring(F.min, lambda x, w: x + w),
    "max_times": Semiring(F.max, lambda x, w: x * w),
    "or_and": Semiring(lambda c: F.max(c), lambda x, w: F.when((x != 0) & (w != 0), 1.0).otherwise(0.0)),
}


class Product:
    """y = A^T x: values go from rows i to columns j; rows and columns have blocks of their own widths.

    The layout and the lists are placed once; each product shuffles one value per (row,
    column block).
    """

    def __init__(self, a: Matrix, q_in: int = 64, q_out: int | None = None, semiring: str = "plus_times", method: str = "bundled"):
        if method not in ("bundled", "per_edge"):
            raise ValueError("method is bundled or per_edge")
        self.ring, self.method, self.q_in = SEMIRINGS[semiring], method, q_in
        allow_placement(a.entries.sparkSession)
        e = a.entries.select("i", "j", "w", block_of("i", q_in).alias("src_block"), block_of("j", q_out or q_in).alias("dst_block"))
        if method == "bundled":
            self.layout = place(e.select("src_block", "dst_block", "i").distinct(), "src_block").persist()
            self.lists = place(e.groupBy("dst_block", "i").agg(F.sort_array(F.collect_list(F.struct("j", "w"))).alias("e")), "dst_block").persist()
        else:
            self.entries = place(e, "src_block").persist()

    def __call__(self, x: DataFrame) -> DataFrame:
        """x (id, x double) -> y (id, x); columns without entries are left out."""
        own = place(x.select(block_of("id", self.q_in).alias("src_block"), F.col("id").alias("i"), "x"), "src_block")
        if self.method == "bundled":
            sent = place(own.join(self.layout, ["src_block", "i"]).select("dst_block", "i", "x"), "dst_block")
            each = sent.join(self.lists, ["dst_block", "i"]).select("dst_block", "x", F.explode("e").alias("e")).select("dst_block", "x", "e.j", "e.w")
        else:
            each = place(own.join(self.entries, ["src_block", "i"]).select("dst_block", "j", "x", "w"), "dst_block")
        return each.groupBy("dst_block", "j").agg(self.ring.add(self.ring.times(F.col("x"), F.col("w"))).alias("x")).select(F.col("j").alias("id"), "x")


def spmv(a: Matrix, x: DataFrame, q_in: int = 64, q_out: int | None = None, semiring: str = "plus_times", method: str = "bundled") -> DataFrame:
    return Product(a, q_in, q_out, semiring, method)(x)


def power(a: Matrix, x: DataFrame, iters: int, normalize: bool = True, q: int = 64, method: str = "bundled") -> DataFrame:
    """A series of products with a square matrix; ``normalize`` scales the result by its largest magnitude each time."""
    product = Product(a, q, method=method)
    for _ in range(iters):
        x = product(x)
        if normalize:
            x = materialise(x, "power")
            top = x.agg(F.max(F.abs("x"))).first()[0] or 1.0
            x = x.select("id", (F.col("x") / top).alias("x"))
    return x


def relax(g: Graph, start: DataFrame, weight: float, q: int = 64, max_rounds: int = 10_000, every: int = 1) -> DataFrame:
    """Least fixed point of x = min(x, A^T x) over min-plus: distances for weight 1, component labels for weight 0."""
    product = Product(Matrix(g.edges.select(F.col("src").alias("i"), F.col("dst").alias("j"), F.lit(weight).alias("w")), g.n, g.n), q, semiring="min_plus")
    cur = materialise(start.select("id", F.col("x").cast("double").alias("x")), "relax")
    before = None
    for _ in range(max_rounds):
        now = cur.agg(F.count("*"), F.sum("x")).first()
        if now == before:
            return cur
        before = now
        for _ in range(every):
            cur = cur.union(product(cur)).groupBy("id").agg(F.min("x").alias("x"))
        cur = materialise(cur, "relax")
    raise RuntimeError("no fixed point within max_rounds")


def hops(g: Graph, root: int, q: int = 64) -> DataFrame:
    """id, x: edges from the root; vertices out of reach are left out."""
    return relax(g, g.vertices.where(F.col("id") == root).select("id", F.lit(0.0).alias("x")), 1.0, q)


def component_labels(g: Graph, q: int = 64) -> DataFrame:
    """id, x: least id that is linked over edges taken both ways."""
    both = g.with_edges(g.edges.select("src", "dst").union(g.edges.select(F.col("dst"), F.col("src"))).distinct())
    return relax(both, g.vertices.select("id", F.col("id").cast("double").alias("x")), 0.0, q)
