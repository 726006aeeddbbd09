"""What methods keep, and what they shuffle to make it."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bundlemv.graph import Graph
from bundlemv.operators import steps
from bundlemv.operators.blocks import place
from bundlemv.plans import catalog
from bundlemv.sources import workloads as wl


def exchanges(df):
    return df._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")


@pytest.mark.parametrize("name, made", [("bundled_rows", [2, 1]), ("bundled_adjacency", [1, 1]), ("bundled_prefix", [2, 1])])
def test_edges_are_shuffled_once_for_each_kept_table(spark, name, made):
    """The layout is read off the lists: its plan holds theirs and one more shuffle, of the bundles."""
    steps.allow_placement(spark)
    method = steps.METHODS[name](wl.banded(spark, 300, 8), 16)
    assert [exchanges(df) for df in method.kept] == made
    method.release()


@pytest.mark.parametrize("weighted", [False, True])
def test_flags_are_walked_within_pairs_of_blocks(spark, weighted):
    """Before, each step sorted all edges to meet their values. A pair's flags are one array; small chunks and weights are met too."""
    steps.allow_placement(spark)
    rng = np.random.default_rng(5)
    edges = sorted({(i, 7) for i in range(100)} | {(int(a), int(b)) for a, b in rng.integers(0, 100, (900, 2))})
    g = Graph(spark.createDataFrame([(u, v, float(u % 3 + 1)) for u, v in edges], "src long, dst long, weight double"), 100)
    g = g if weighted else g.with_edges(g.edges.drop("weight"))
    want = np.zeros(100)
    for u, v in edges:
        want[v] += (u + 1) * (u % 3 + 1 if weighted else 1)
    shares = place(spark.range(100).select((F.col("id") / 16).cast("int").alias("block"), "id", (F.col("id") + 1.0).alias("share")), "block")
    for options in ({}, {"chunk_edges": 20}):
        method = steps.METHODS["bundled_prefix"](g, 16, **options)
        lists = method.kept[1]
        assert lists.count() == lists.select("dst_block", "chunk", *(["slice"] if "slice" in lists.columns else []), "src_block").distinct().count()
        sums = method.step(shares)
        got = {r.id: r.s for r in sums.collect()}
        assert np.allclose([got.get(i, 0.0) for i in range(100)], want)
        if not options:
            made = sums._jdf.queryExecution().sparkPlan().toString()
            assert "Window" not in made.split("InMemoryRelation")[0] and lists.count() < len(edges) / 5
        method.release()


def test_pairs_are_made_from_one_shuffle_of_the_rows(spark):
    """Before, members were made distinct and then dealt twice more, to be joined with themselves."""
    rows = spark.createDataFrame([(1, 5), (1, 5), (1, 6), (None, 5), (None, 7), (2, None), (2, 8), (2, 5), (3, 9)], "k long, m long")
    pairs = wl._pairs(rows, "k", "m")
    assert sorted(map(tuple, pairs.collect())) == [(5, 6), (5, 8), (6, 5), (8, 5)]
    pairs = wl._pairs(rows, "k", "m")
    assert exchanges(pairs) == 2 and "Join" not in pairs._jdf.queryExecution().executedPlan().toString()


def test_degrees_of_parts_deal_no_edges(spark, tiny):
    """Before, a row for nearly each edge was dealt to count the edges of a part."""
    g = wl.copurchase(spark, tiny)
    assert exchanges(g.edges.groupBy("src").count()) == exchanges(g.edges) == 2


def test_messages_sent_keeps_one_method_at_a_time(spark, monkeypatch):
    alive, most = set(), []

    def watched(make):
        def build(*a, **kw):
            m = make(*a, **kw)
            alive.add(id(m))
            most.append(len(alive))
            free = m.release
            m.release = lambda: (alive.discard(id(m)), free())
            return m

        return build

    monkeypatch.setattr(steps, "METHODS", {k: watched(f) for k, f in steps.METHODS.items()})
    assert catalog._sent(wl.banded(spark, 300, 8)).count() == 8
    assert max(most) == 1 and not alive
