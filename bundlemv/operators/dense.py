"""The definition itself: power iteration with a full matrix, for graphs that are small enough to hold one."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from bundlemv.graph import Graph
from bundlemv.operators.rank import DAMPING

#: The matrix has n x n entries of 8 bytes on the driver, 32 MB at most.
MAX_N = 2048


def dense_rank(g: Graph, iters: int = 20, damping: float = DAMPING, dangling: str = "drop") -> DataFrame:
    """id, rank: the reference that the methods are held against."""
    if g.n > MAX_N:
        raise ValueError(f"a full matrix is made for up to {MAX_N} vertices")
    edges = g.edges.toPandas()  # at most n x n distinct pairs
    a = np.zeros((g.n, g.n))
    np.add.at(a, (edges["dst"].to_numpy(np.int64), edges["src"].to_numpy(np.int64)), edges["weight"].to_numpy(float) if g.weighted else 1.0)
    sinks = a.sum(axis=0) == 0
    if dangling == "self":
        a[sinks, sinks] = 1.0
    out, r = a.sum(axis=0), np.full(g.n, 1 / max(g.n, 1))
    for _ in range(iters):
        lost = r[sinks].sum() / g.n if dangling == "spread" else 0.0
        r = (1 - damping) / g.n + damping * (a @ np.divide(r, out, out=np.zeros(g.n), where=out > 0) + lost)
    return g.spark.createDataFrame([(i, float(x)) for i, x in enumerate(r)], "id long, rank double")
