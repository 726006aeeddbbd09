"""Vertices with the same links, folded, against the edges themselves."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bundlemv.graph import Graph
from bundlemv.operators import cost, labels, rank, twins
from bundlemv.plans import catalog
from bundlemv.sources import workloads as wl


def shared(spark):
    """Keys in classes of several, of two and of one, with a hub, a key of one vertex, two vertices without keys."""
    rows = [(i, "hub") for i in range(0, 60, 7)] + [(i, f"k{i % 5}") for i in range(60) if i % 4] + [(i, "pair") for i in (8, 12)]
    rows += [(i, f"m{i // 10}") for i in range(40) if i % 3 == 0] + [(4, "alone"), (44, "far"), (1, "far")]
    return spark.createDataFrame(rows, "id long, key string").distinct().persist()


@pytest.fixture(scope="module")
def both(spark):
    """The graph by its edges, and by its classes with edges that fail when they are read."""
    own = shared(spark)
    plain = Graph(wl._pairs(own, "key", "id"), 62).persist()
    unread = spark.range(1).select(F.raise_error(F.lit("edges are read")).cast("long").alias("src"), F.lit(0).cast("long").alias("dst"))
    return plain, Graph(unread, 62, lambda: twins.fold(own, spark.range(62), 62))


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_greedy_order_by_classes(both):
    """The driver holds links of classes; before, all edges and a heap of all scores."""
    plain, folded = both
    assert folded.twins.sizes.count() < 40
    assert rows(labels.shared_parents(folded)) == rows(labels.shared_parents(plain))


def test_greedy_order_by_classes_appends_the_rest(both, monkeypatch):
    monkeypatch.setattr(labels, "GREEDY_LIMIT", 5)
    perm = dict(rows(labels.shared_parents(both[1])))
    first = {r.id for r in both[1].twins.members.where("cls < 5").collect()}
    assert sorted(perm.values()) == list(range(62)) and {i for i in perm if perm[i] < len(first)} == first


def test_greedy_order_takes_all_classes(spark):
    """Before, classes beyond the first 50,000 followed by id, whatever their links."""
    n = 50_010
    members = spark.range(n).select("id", F.least("id", F.lit(n - 3)).alias("cls"))  # the last class has three members
    links = spark.createDataFrame([(n - 3, n - 3), (n - 3, n - 8), (n - 8, n - 3)], "a long, b long")
    unread = spark.range(1).select(F.raise_error(F.lit("edges are read")).cast("long").alias("src"), F.lit(0).cast("long").alias("dst"))
    g = Graph(unread, n, lambda: twins.Twins(members, members.groupBy("cls").agg(F.count("*").alias("size")), links, n))
    perm = dict(rows(labels.shared_parents(g)))
    assert sorted(perm.values()) == list(range(n)) and [perm[i] for i in (n - 8, n - 3, n - 2, n - 1, 0)] == [0, 1, 2, 3, 4]


def test_pages_fold_only_with_dense_ids(spark, tiny, tmp_path):
    assert wl.page_links(spark, tiny).twins is not None
    spark.read.parquet(f"{tiny}/pages.parquet").withColumn("page_id", F.col("page_id") * 2).write.parquet(f"{tmp_path}/pages.parquet")
    assert wl.page_links(spark, str(tmp_path)).twins is None


@pytest.mark.parametrize("piece", [1, 3, twins.PIECE])
def test_pairs_by_classes(spark, both, monkeypatch, piece):
    """Classes of several pieces, ids with gaps, an id that is null and a key that nobody shares."""
    monkeypatch.setattr(twins, "PIECE", piece)
    own = shared(spark).select((F.col("id") * 7 - 100).alias("id"), "key").union(spark.sql("select null, 'hub' union all select 5, 'own'"))
    want = [(a * 7 - 100, b * 7 - 100) for a, b in rows(both[0].edges)]
    assert rows(twins.pairs(own)) == want


def test_pairs_of_pages_are_not_shuffled(spark, tiny):
    """Before, every pair of pages was dealt out to be told from its copies."""
    node, kinds = wl.page_links(spark, tiny).edges._jdf.queryExecution().optimizedPlan(), []
    while (kind := node.getClass().getSimpleName()) in ("Filter", "Project", "Generate", "Repartition"):
        kinds.append(kind)
        node = node.children().head()
    assert kind == "RepartitionByExpression" and kinds.count("Generate") == 2


@pytest.mark.parametrize("bits", [twins.BITS, 0])
def test_counters_by_classes(both, monkeypatch, bits):
    plain, folded = both
    monkeypatch.setattr(twins, "BITS", bits)
    for make in (labels.original, labels.random, labels.by_degree, labels.parent_signature):
        perm = make(plain)
        assert rows(make(folded)) == rows(perm)
        for q in (8, 16):
            assert rows(cost.labelled_compression(folded, perm, q)) == rows(cost.compression_ratio(labels.relabel(plain, perm), q))
            assert rows(cost.labelled_params(folded, perm, q)) == rows(cost.measured_params(labels.relabel(plain, perm), q))


def test_counters_over_several_parts(both, monkeypatch):
    plain, folded = both
    monkeypatch.setattr(twins, "LINES", 64)
    monkeypatch.setattr(twins, "BLOCKS", 2)
    perm = labels.random(plain)
    assert rows(cost.labelled_params(folded, perm, 8)) == rows(cost.measured_params(labels.relabel(plain, perm), 8))


@pytest.mark.parametrize("method", ["bundled", "pull"])
@pytest.mark.parametrize("dangling", ["drop", "self"])
def test_ranks_by_classes(both, method, dangling):
    plain, folded = both
    got, want = (dict(rows(df)) for df in (rank.run_folded(folded.twins, method, iters=4, dangling=dangling), rank.run(plain, iters=4, dangling=dangling)))
    assert got.keys() == want.keys() == set(range(62)) and all(abs(got[i] - want[i]) < 1e-12 for i in want)


def test_compression_by_label_by_classes(both):
    plain, folded = both
    assert rows(catalog._by_label(folded)) == rows(catalog._by_label(plain))


def test_traffic_by_label_by_classes(both):
    plain, folded = both
    perms = {"original": labels.original(plain), "signature": labels.parent_signature(plain)}
    assert rows(cost.traffic_by_label(folded, perms, 16)) == rows(cost.traffic_by_label(plain, perms, 16))


def test_equal_sets_of_classes_are_joined_once(monkeypatch):
    """Blocks that see the same classes share one union of lines."""
    calls, own = [], twins.joined
    monkeypatch.setattr(twins, "joined", lambda bits: calls.append(len(bits)) or own(bits))
    place, at = np.array([0, 0, 1, 2, 2]), np.array([3, 9, 9, 3, 70])
    groups = [np.array(g, np.int64) for g in ([0, 1], [2], [0, 1], [0, 2], [], [0, 1], [2])]
    want = [2, 2, 2, 3, 0, 2, 2]
    assert list(twins.lines_of(groups, place, at, 3)) == want and len(calls) == 3
    monkeypatch.setattr(twins, "BITS", 0)
    assert list(twins.lines_of(groups, place, at, 3)) == want
