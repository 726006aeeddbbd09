"""The worked example, invariants of the methods, and odd graphs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from bundlemv import graph as ga
from bundlemv.graph import Graph, Matrix
from bundlemv.operators import blocks, cost, labels, layout, rank, results, spmv, steps
from bundlemv.sources import workloads as wl


def dense_rank(edges, n, iters, d=0.85, weights=None, dangling="drop"):
    """Power iteration with a full matrix."""
    a = np.zeros((n, n))
    for k, (u, v) in enumerate(edges):
        a[v, u] += 1 if weights is None else weights[k]
    out = a.sum(0)
    if dangling == "self":
        a[out == 0, out == 0] = 1
        out = a.sum(0)
    r = np.full(n, 1 / n)
    for _ in range(iters):
        share = np.divide(r, out, out=np.zeros(n), where=out > 0)
        r = (1 - d) / n + d * (a @ share + (r[out == 0].sum() / n if dangling == "spread" else 0))
    return r


def ranks_of(df, n):
    out = np.zeros(n)
    rows = df.collect()
    assert len(rows) == n
    for r in rows:
        out[r.id] = r.rank
    return out


def frame(spark, edges, n, schema="src long, dst long"):
    return Graph(spark.createDataFrame(edges, schema), n)


def test_worked_example(spark):
    g = wl.worked9(spark)
    assert cost.compression_ratio(g, 3).first().bundles == 6
    pairs = {(r.src_block, r.dst_block) for r in layout.pair_counts(g, 3).collect()}
    assert pairs == {(0, 2), (1, 1), (2, 0), (2, 1), (2, 2)}
    offs = {r.dst_block: r.off for r in layout.write_offsets(g, 3).where("src_block = 2").collect()}
    assert offs == {0: 0, 1: 1, 2: 1}
    lists = layout.dest_lists(g, 3).orderBy("dst_block", "src_block", "src", "dst").collect()
    assert [(r.dst, r.flag) for r in lists if r.dst_block == 1] == [(3, True), (5, False), (3, True), (4, False)]
    got = ranks_of(rank.run(g, q=3, iters=1), 9)
    want = [0.0638889] * 3 + [0.1111111] + [0.0638889] * 3 + [0.1111111, 0.0166667]
    assert np.allclose(got, want, atol=1e-7) and abs(got.sum() - 0.6222222) < 1e-7


@pytest.mark.parametrize("method", sorted(steps.METHODS))
def test_methods_agree_with_a_dense_matrix(spark, method):
    rng = np.random.default_rng(2)
    edges = sorted({(int(a), int(b)) for a, b in rng.integers(0, 50, (300, 2)) if a % 7})
    g = frame(spark, edges, 53)
    for q in (8, 5):  # a power of two, and not; the last block is short
        assert np.allclose(ranks_of(rank.run(g, method, q=q, iters=2), 53), dense_rank(edges, 53, 2), atol=1e-12)


@pytest.mark.parametrize("method", ["bundled", "bundled_nested", "bundled_rows", "bundled_prefix", "bundled_arrow", "per_edge", "per_edge_resend", "pull", "edge_scan", "naive"])
def test_weighted(spark, method):
    rng = np.random.default_rng(3)
    edges = sorted({(int(a), int(b)) for a, b in rng.integers(0, 20, (80, 2))})
    w = [float(x) for x in rng.uniform(0, 3, len(edges))]
    g = frame(spark, [(*e, x) for e, x in zip(edges, w)], 20, "src long, dst long, weight double")
    assert np.allclose(ranks_of(rank.run(g, method, q=8, iters=3), 20), dense_rank(edges, 20, 3, weights=w), atol=1e-12)
    ones = g.with_edges(g.edges.withColumn("weight", F.lit(1.0)))
    assert np.allclose(ranks_of(rank.run(ones, method, q=8, iters=3), 20), dense_rank(edges, 20, 3), atol=1e-12)


@pytest.mark.parametrize("mode", ["drop", "spread", "self"])
def test_sinks(spark, mode):
    edges = [(i, 0) for i in range(1, 6)] + [(1, 2)]
    got = ranks_of(rank.run(frame(spark, edges, 8), q=4, iters=5, dangling=mode), 8)
    assert np.allclose(got, dense_rank(edges, 8, 5, dangling=mode), atol=1e-12)
    assert got.sum() < 1 if mode == "drop" else abs(got.sum() - 1) < 1e-12


@pytest.mark.parametrize("edges,n", [([], 3), ([(0, 0)], 1), ([(0, 1), (1, 2), (2, 0)], 3), ([(2**31 + 5, 2**31 + 6)], 0)])
def test_odd_graphs(spark, edges, n):
    g = frame(spark, edges, n)
    if not n:  # ids beyond 31 bits: blocks and flags hold them
        row = layout.dest_lists(g, 64).first()
        ident, first = layout.decode_flag(F.lit(row.code))
        assert row.dst_block == (2**31 + 6) // 64 and spark.range(1).select(ident, first).first() == (2**31 + 6, True)
        return
    for method, q in (("bundled", 1), ("bundled", 16), ("bundled_arrow", 2), ("per_edge", 2), ("pull", 2), ("naive", 2)):
        if n:
            assert np.allclose(ranks_of(rank.run(g, method, q=q, iters=2), n), dense_rank(edges, n, 2), atol=1e-12)


def test_hub_blocks_are_cut(spark):
    """One vertex that all point at, and one that points at all: rows and tasks stay bounded, and the ranks are the same."""
    n = 3000
    rng = np.random.default_rng(8)
    edges = sorted({(i, 7) for i in range(n)} | {(9, i) for i in range(n)} | {(int(a), int(b)) for a, b in rng.integers(0, n, (2000, 2))})
    g = frame(spark, edges, n)
    p = layout.packed_pairs(g, 256, chunk_edges=500)
    assert p.chunked and p.place == ("dst_block", "chunk")
    tasks = [r.e for r in p.lists.groupBy("dst_block", "chunk").agg(F.sum(F.size("ids")).alias("e")).collect()]
    assert sum(tasks) == len(edges) and max(tasks) < 1000 < layout.packed_pairs(g, 256).lists.groupBy("dst_block").agg(F.sum(F.size("ids")).alias("e")).agg(F.max("e")).first()[0]
    assert np.allclose(ranks_of(rank.run(g, q=256, iters=3, chunk_edges=500), n), dense_rank(edges, n, 3), atol=1e-12)
    weighted = g.with_edges(g.edges.withColumn("weight", (F.col("src") % 3 + 1).cast("double")))
    assert np.allclose(ranks_of(rank.run(weighted, q=256, iters=2, chunk_edges=500), n), dense_rank(edges, n, 2, weights=[u % 3 + 1 for u, _ in edges]), atol=1e-12)


def test_four_byte_values(spark):
    edges = [(0, 1), (1, 2), (2, 0), (2, 1)]
    exact = dense_rank(edges, 4, 6)
    for method in ("bundled", "bundled_arrow", "bundled_nested", "per_edge", "per_edge_resend", "pull"):
        got = ranks_of(rank.run(frame(spark, edges, 4), method, q=2, iters=6, value_type="float"), 4)
        assert np.allclose(got, exact, rtol=1e-6) and (method == "pull" or not (got == exact).all())


def test_nothing_stays_kept(spark):
    before = spark.sparkContext._jsc.getPersistentRDDs().size()
    g = frame(spark, [(0, 1), (1, 2), (2, 0), (2, 1)], 4)
    rank.run(g, q=2, iters=2).collect()
    m = {r.iteration: r.mass for r in rank.masses(g, iters=3).collect()}
    assert len(m) == 4 and m[3] == pytest.approx(dense_rank([(0, 1), (1, 2), (2, 0), (2, 1)], 4, 3).sum())
    assert spark.sparkContext._jsc.getPersistentRDDs().size() == before


def test_options(spark):
    g = frame(spark, [(0, 1), (1, 2), (2, 0), (2, 1)], 4)
    settled = ranks_of(rank.run(g, q=2, iters=200, tol=1e-3, dangling="spread"), 4)
    assert np.allclose(settled, dense_rank([(0, 1), (1, 2), (2, 0), (2, 1)], 4, 300, dangling="spread"), atol=5e-3)
    warm = rank.run(g, q=2, iters=1, dangling="spread", start=spark.createDataFrame([(i, float(x)) for i, x in enumerate(settled)], "id long, rank double"))
    assert np.allclose(ranks_of(warm, 4), settled, atol=1e-3)
    long = ranks_of(rank.run(g, q=2, iters=12), 4)  # past a durable copy
    assert np.allclose(long, dense_rank([(0, 1), (1, 2), (2, 0), (2, 1)], 4, 12), atol=1e-12)


def test_invariants(spark):
    g = wl.kronecker(spark, 9, 8).persist()
    by = {r["shift"]: r for r in cost.compression_by_width(g, list(range(0, 11))).collect()}
    rs = [by[s].r for s in range(11)]
    active = g.edges.select("src").distinct().count()
    assert rs == sorted(rs) and rs[0] == 1 and by[9].bundles == active and rs[-1] <= g.m / active + 1e-12
    for q in (4, 64, 100):
        n = cost.compression_ratio(g, q).first().bundles
        assert n == layout.block_layout(g, q).count() == layout.first_edges(g, q).count() == layout.dest_lists(g, q).where("flag").count()
        assert all(r.disjoint for r in layout.offsets_disjoint(layout.write_offsets(g, q)).collect())
        one = {(r.src_block, r.dst_block): (r.value_off, r.srcs) for r in layout.build_onepass(g, q).collect()}
        two = {(r.src_block, r.dst_block): r.srcs for r in layout.packed_layout(g, q).collect()}
        assert {k: v[1] for k, v in one.items()} == two
        switches = {r.method: r.switches for r in cost.count_bin_switches(g, q).collect()}
        assert switches["bundled"] == cost.nonempty_pairs(g, q).first().pairs <= switches["per_edge"] <= g.m


def test_labels_move_the_compression(spark):
    g = wl.kronecker(spark, 10).persist()
    assert g.m == 11943 and g.edges.agg(F.sum(F.col("src") * 1024 + F.col("dst"))).first()[0] == 3438474020
    r = lambda perm: cost.compression_ratio(labels.relabel(g, perm), 16).first().r
    assert r(labels.random(g)) < r(labels.original(g)) < r(labels.by_degree(g))
    assert r(labels.shared_parents(g)) > r(labels.random(g))
    band = wl.banded(spark, 512, 8).persist()
    b = lambda perm: cost.compression_ratio(labels.relabel(band, perm), 16).first().r
    assert b(labels.random(band)) < 1.3 < 5 < b(labels.original(band)) and abs(b(labels.by_hops(band)) - b(labels.original(band))) < 0.2
    for perm in (labels.random(g), labels.by_degree(g), labels.parent_signature(g), labels.shared_parents(g)):
        assert sorted(r.new for r in perm.collect()) == list(range(1024))


def test_models(spark):
    p = cost.CURVE.frame(spark)
    acc = cost.random_accesses(p).first()
    assert acc.per_edge == 66_875_000 and acc.bundled == 262_144
    curve = {r.r: r.bytes / 1e9 for r in cost.curve(p, [1.0, 2.0, 3.06, 5.0, 10.0, 20.0]).collect()}
    assert [round(curve[x], 2) for x in (1.0, 2.0, 3.06, 5.0, 10.0, 20.0)] == [17.39, 10.97, 8.75, 7.12, 5.83, 5.19]
    whole = {r.method: r.bytes for r in cost.models(p).collect()}
    added = {r.method: r.s for r in cost.parts(p).groupBy("method").agg(F.sum("bytes").alias("s")).collect()}
    assert all(abs(whole[m] - added[m]) < 1 for m in whole) and round(whole["per_edge"] / 1e9, 2) == 17.52
    fast = cost.speedups(cost.published(spark)).agg(F.avg("over_per_edge"), F.min("over_per_edge"), F.max("over_per_edge"), F.max("over_pull")).first()
    assert [round(x, 1) for x in fast] == [2.7, 2.2, 3.9, 4.1]
    less = cost.traffic_reductions(cost.published(spark)).agg(F.avg("over_per_edge"), F.avg("over_pull"), F.avg("gb_per_s")).first()
    assert [round(x, 1) for x in less] == [1.7, 2.2, 42.5]
    assert all(1.1 < r.ratio < 1.4 for r in cost.model_vs_measured(cost.published(spark)).collect())


def test_products(spark):
    rng = np.random.default_rng(7)
    a = rng.integers(-3, 4, (13, 7)).astype(float)
    entries = [(i, j, float(a[i, j])) for i in range(13) for j in range(7) if a[i, j]]
    x = rng.normal(size=13)
    m = Matrix(spark.createDataFrame(entries, "i long, j long, w double"), 13, 7)
    xs = spark.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "id long, x double")
    for method in ("bundled", "per_edge"):
        for q_in, q_out in ((4, 2), (3, 64), (1, 1)):
            y = {r.id: r.x for r in spmv.spmv(m, xs, q_in, q_out, method=method).collect()}
            assert np.allclose([y.get(j, 0) for j in range(7)], a.T @ x)
    one = Matrix(spark.createDataFrame([(0, 0, 2.0), (1, 0, 3.0), (2, 0, -1.0)], "i long, j long, w double"), 3, 1)
    assert spmv.spmv(one, spark.createDataFrame([(0, 1.0), (1, 1.0), (2, 5.0)], "id long, x double")).first().x == 0.0
    assert {r.id: r.x for r in spmv.hops(frame(spark, [(0, 1), (1, 2), (3, 0)], 4), 0, q=2).collect()} == {0: 0, 1: 1, 2: 2}


def test_blocks(spark):
    assert blocks.plan_width(10**9, 128 << 20, 10) == 1 << 24 and blocks.plan_width(100, 1 << 30, 8) == 8
    with pytest.raises(ValueError):
        blocks.block_of("id", 0)
    with pytest.raises(ValueError):
        ga.check_ids(frame(spark, [(0, 9)], 5))
    ga.check_ids(frame(spark, [(0, 4)], 5))
    g = ga.make_graph(spark.createDataFrame([(0, 1, 2.0), (0, 1, 3.0)], "src int, dst int, weight double"), 2)
    assert [tuple(r) for r in g.edges.collect()] == [(0, 1, 5.0)]
    perm = blocks.custom_blocks(spark.range(6), F.col("id") % 2)
    assert {r.old: r.new for r in perm.collect()} == {0: 0, 2: 1, 4: 2, 1: 3, 3: 4, 5: 5}


def test_results(spark):
    a = spark.createDataFrame([(0, 0.5), (1, 0.3), (2, 0.2)], "id long, rank double")
    b = spark.createDataFrame([(0, 0.5), (2, 0.4)], "id long, rank double")
    d = results.delta(a, b).first()
    assert np.allclose((d.l1, d.l2, d.largest), (0.5, np.sqrt(0.13), 0.3))
    assert results.mass(a).first().mass == pytest.approx(1.0)


def test_knn_in_blocks(spark, tmp_path):
    x = np.random.default_rng(4).integers(-3, 4, (300, 6)) + 0.5
    spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(5).write.parquet(f"{tmp_path}/embeddings.parquet")
    unit = x / np.sqrt((x**2).sum(1))[:, None]
    cos = np.round(unit @ unit.T, 6)
    np.fill_diagonal(cos, -np.inf)
    want = {(i, int(j)) for i in range(len(x)) for j in np.lexsort((np.arange(len(x)), -cos[i]))[:8]}
    for block in (64, 4096):
        got = wl.knn(spark, str(tmp_path), block=block).edges.collect()
        assert len(got) == len(want) and {(r.src, r.dst) for r in got} == want


def test_knn_takes_many_vectors(spark, tmp_path):
    rows = spark.range(20_001).selectExpr("id as vec_id", "array(cos(id), sin(id)) as embedding")
    rows.repartition(8).write.parquet(f"{tmp_path}/embeddings.parquet")
    assert wl.knn(spark, str(tmp_path), k=1).edges.count() == 20_001


def test_greedy_order_appends_the_rest(spark, monkeypatch):
    g = wl.worked9(spark)
    monkeypatch.setattr(labels, "GREEDY_LIMIT", 5)
    perm = {r.old: r.new for r in labels.shared_parents(g).collect()}
    assert sorted(perm.values()) == list(range(9)) and [perm[i] for i in range(5, 9)] == [5, 6, 7, 8]


def test_greedy_order_takes_all(spark):
    """Before, vertices beyond the first 50,000 followed by id, whatever their links."""
    n = 50_010
    perm = dict(map(tuple, labels.shared_parents(frame(spark, [(n - 1, n - 4), (n - 9, n - 4), (n - 2, n - 6)], n)).collect()))
    assert sorted(perm.values()) == list(range(n))
    assert [perm[n - i] for i in (4, 9, 1, 6, 2)] == [0, 1, 2, 3, 4] and perm[0] == 5


@pytest.mark.parametrize("piece", [5, labels.PIECE_LINKS])
def test_greedy_order_is_that_of_its_definition(spark, monkeypatch, piece):
    """Against the scores of all vertices counted anew for each place, with loops, a hub and vertices without edges."""
    monkeypatch.setattr(labels, "PIECE_LINKS", piece)
    n, rng = 40, np.random.default_rng(3)
    edges = {(3, i) for i in range(30)} | {(4, 4)} | {(int(a), int(b)) for a, b in rng.integers(0, n - 4, (70, 2))}
    into, want = [{u for u, v in edges if v == i} for i in range(n)], []
    score = lambda v, last: sum(len(into[u] & into[v]) + ((u, v) in edges) + ((v, u) in edges) for u in last)
    while len(want) < n:
        want.append(min(set(range(n)) - set(want), key=lambda v: (-score(v, want[-3:]), -len(into[v]), v)))
    perm = dict(map(tuple, labels.shared_parents(frame(spark, sorted(edges), n), window=3).collect()))
    assert sorted(range(n), key=perm.get) == want


def test_small_chunks_are_dealt_together(spark):
    """With chunks far below a task's share the rows stay as small, but few sums of a vertex are dealt; small groups are neither hashed nor sorted again."""
    n = 400
    rng = np.random.default_rng(9)
    edges = sorted({(i, 7) for i in range(n)} | {(int(a), int(b)) for a, b in rng.integers(0, n, (9000, 2))})
    g = frame(spark, edges, n)
    p = layout.packed_pairs(g, 128, chunk_edges=20)
    size = F.size("ids")
    rows = p.lists.groupBy("dst_block", "slice").agg(F.sum(size).alias("e"), F.count_distinct("chunk").alias("c")).agg(F.max("e"), F.max("c"), F.sum("e")).first()
    assert p.chunked and rows[0] < 80 and rows[1:] == (1, len(edges))
    share = len(edges) / int(spark.conf.get("spark.sql.shuffle.partitions"))
    assert p.lists.groupBy(*p.place).agg(F.sum(size).alias("e")).agg(F.max("e")).first()[0] < share
    dealt, slices = (p.lists.select("dst_block", c).distinct().count() for c in ("chunk", "slice"))
    assert dealt * 5 < slices
    plan = p.lists._jdf.queryExecution().executedPlan().toString()
    assert "SortAggregate(key=[dst_block" in plan and "ObjectHashAggregate" not in plan
    for weights, h in ((None, g), ([u % 3 + 1 for u, _ in edges], g.with_edges(g.edges.withColumn("weight", (F.col("src") % 3 + 1).cast("double"))))):
        assert np.allclose(ranks_of(rank.run(h, q=128, iters=3, chunk_edges=20), n), dense_rank(edges, n, 3, weights=weights), atol=1e-12)
