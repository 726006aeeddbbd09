import duckdb
import numpy as np
import pytest

from bundlemv.llm import additive, topk, vectors

ROWS = "id long, v array<long>"


def plain_top(rows, queries, k):
    out = []
    for i, q in queries:
        scored = sorted((-sum(a * b for a, b in zip(q, v)), j) for j, v in rows if j != i)[:k]
        out += [(i, r + 1, j, -s) for r, (s, j) in enumerate(scored)]
    return sorted(out)


@pytest.mark.parametrize("groups", [1, 2, 3])
def test_exact_top_k(spark, groups, monkeypatch):
    monkeypatch.setattr(topk, "query_blocks", lambda q, w: vectors.query_blocks(q, w, block=20))
    rng = np.random.default_rng(4)
    data = [(i, rng.integers(-40, 40, 10).tolist()) for i in range(400)] + [(i, [1] * 10) for i in range(400, 420)] + [(500, [7, 7]), (501, []), (7, [3] * 10), (501, [])]
    rows = spark.createDataFrame(data, ROWS).repartition(5)
    got = topk.exact_top_k(rows, rows.where("id % 9 = 0"), 5, groups)
    queries = [(i, v) for i, v in data if i % 9 == 0]
    assert sorted(map(tuple, got.collect())) == plain_top(data, queries, 5)


def test_phases_spare_products(spark):
    rng = np.random.default_rng(6)
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.integers(-200, 200, (6000, 16)))], ROWS).repartition(3)
    (n,) = topk.products(rows, rows.where("id % 50 = 0"), 5).collect()
    assert n.lists == 6000 * 120 * 2 and n.resolved < n.lists / 40


def test_a_frequent_vector_is_folded(spark):
    data = [(i, [5, 5]) for i in range(900)] + [(i, [i - 950, 3]) for i in range(900, 1000)] + [(3, [5, 5])] * 40
    rows = spark.createDataFrame(data, ROWS).repartition(4)
    assert topk.fold_copies(rows, 5).where("id < 900").count() == 10  # ids 0 to 5, and five rows with id 3
    got = topk.exact_top_k(rows, rows.where("id % 50 = 0 or id = 3"), 5)
    queries = sorted({i: v for i, v in data if i % 50 == 0 or i == 3}.items())
    assert sorted(map(tuple, got.collect())) == plain_top(data, queries, 5)


def test_large_components(spark):
    data = [(i, [2**29 - i, -(2**28) + i * i]) for i in range(30)]
    rows = spark.createDataFrame(data, ROWS)
    assert sorted(map(tuple, topk.exact_top_k(rows, rows, 3).collect())) == plain_top(data, data, 3)
    with pytest.raises(ValueError):
        topk.exact_top_k(spark.createDataFrame([(1, [2**40]), (2, [1])], ROWS), rows, 3)


def test_few_rows(spark):
    rows = spark.createDataFrame([(0, [1, 2]), (50, [3, 4]), (51, [-1, -1])], ROWS)
    assert sorted(map(tuple, topk.exact_top_k(rows, rows.where("id < 51"), 5).collect())) == [(0, 1, 50, 11), (0, 2, 51, -3), (50, 1, 0, 11), (50, 2, 51, -7)]
    assert topk.exact_top_k(rows.limit(0), rows, 5).collect() == [] == topk.exact_top_k(rows, rows.limit(0), 5).collect()


def embeddings(spark, tmp_path, rows):
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int, id string, v int, score int").write.parquet(f"{tmp_path}/embeddings.parquet")
    return str(tmp_path)


def test_odd_vectors(spark, tmp_path):
    nan, inf = float("nan"), float("inf")
    odd = [None, [None, 1.0], [nan, 1.0], [inf, 0.0], [0.0, 0.0]]
    data = [(i, v, 0, "x", 1, 2) for i, v in enumerate(odd)] + [(i, [i / 100, 0.5], 0, "x", 1, 2) for i in range(20, 140)] + [(None, [1.0, 1.0], 0, "x", 1, 2)]
    sf = embeddings(spark, tmp_path, data)
    one, eight = topk.op1(spark, sf).collect(), additive.op8(spark, sf).collect()
    assert {r.query_id for r in one} == {50, 100} and {r.vec_id for r in one if r.query_id == 50} == {139, 138, 137, 136, 135}
    assert {r.query_id for r in eight} == {20, 40, 60, 80, 100, 120} and all(r.vec_id >= 20 for r in eight)
    assert [r.vec_id for r in sorted(eight, key=lambda r: r.rank) if r.query_id == 20] == list(range(139, 119, -1))


def test_op1_sql(spark, tiny):
    con = duckdb.connect()
    con.execute(f"create view embeddings as from '{tiny}/embeddings.parquet'")
    want = sorted(con.execute(topk.OP1_SQL).fetchall())
    assert want and want == sorted(map(tuple, topk.op1(spark, tiny).collect()))


def test_codes():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(3000, 16)) + 4 * rng.normal(size=(12, 16))[rng.integers(0, 12, 3000)]
    books = additive.fit_books(x, books=4, words=32)
    err = [((x - additive.decode(additive.encode(x, books[:m], b), books[:m])) ** 2).sum() for m, b in ((1, 1), (4, 1), (4, 4))]
    assert err[0] > err[1] > err[2]


@pytest.mark.parametrize("metric", additive.METRICS)
def test_recall(spark, metric):
    rng = np.random.default_rng(9)
    x = rng.normal(size=(3000, 32)) + 3 * rng.normal(size=(10, 32))[rng.integers(0, 10, 3000)]
    x[2000:2600] = x[0] + 0.01 * rng.normal(size=(600, 32))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, v array<double>").repartition(4)
    index = additive.build_index(rows)
    assert index.rows.count() == 3000
    got = additive.search(index, rows.where("id % 20 = 0"), 20, metric).collect()
    hits = total = 0
    for i in range(0, 3000, 20):
        score = x @ x[i] if metric == "inner_product" else -((x - x[i]) ** 2).sum(1)
        score[i] = -np.inf
        mine = [r for r in got if r.query_id == i]
        assert [r.rank for r in sorted(mine, key=lambda r: (-r.score, r.id))] == list(range(1, 21))
        assert np.allclose([score[r.id] for r in mine], [r.score for r in mine], rtol=1e-12)
        hits += len({r.id for r in mine} & set(np.argsort(-score, kind="stable")[:20].tolist()))
        total += 20
    assert hits / total >= 0.95


def test_copies_of_a_query(spark):
    """More copies than results, far from all words: the smallest ids come first, and no list is short."""
    rng = np.random.default_rng(3)
    x = rng.normal(size=(2000, 32))
    for i in range(12):
        x[100 * i : 100 * i + 40] = 1.5 * rng.normal(size=32)
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, v array<double>").repartition(4)
    got = {}
    for r in additive.search(additive.build_index(rows, books=3, words=16), rows.where("id % 20 = 0"), 20).collect():
        got.setdefault(r.query_id, {})[r.rank] = r.id
    assert len(got) == 100 and all(sorted(v) == list(range(1, 21)) for v in got.values())
    for i in range(0, 1200, 100):
        assert [got[i][r] for r in range(1, 21)] == list(range(i + 1, i + 21))


def test_few_pairs_are_reranked(spark):
    rng = np.random.default_rng(12)
    x = rng.normal(size=(6000, 24)) + 2 * rng.normal(size=(10, 24))[rng.integers(0, 10, 6000)]
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, v array<double>").repartition(4)
    index = additive.build_index(rows)
    assert additive.reranked(index, rows.where("id % 40 = 0"), 20) < 0.03


def test_op8_recall(spark):
    """The query itself on a given table, against all products."""
    path = "/root/testdata/sf0.01"
    table = spark.read.parquet(f"{path}/embeddings.parquet").select("vec_id", "embedding").toPandas().sort_values("vec_id")
    ids, x = table.vec_id.to_numpy(), np.array(table.embedding.tolist(), np.float64)
    got = {}
    for r in additive.op8(spark, path).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    hits = 0
    for i in np.nonzero(ids % 20 == 0)[0]:
        score = x @ x[i]
        score[i] = -np.inf
        hits += len(got[ids[i]] & set(ids[np.argsort(-score, kind="stable")[:20]].tolist()))
    assert hits >= 0.98 * 20 * len(got) and len(got) == (ids % 20 == 0).sum()


def test_repeated_ids(spark):
    data = [(i, v) for i, v in ((1, [20, 0]), (2, [20, 0]), (3, [19, 19]), (4, [0, 20]), (5, [0, 20]), (6, [18, 18])) for _ in range(2)] + [(9, [0, 0])]
    rows, queries = spark.createDataFrame(data, ROWS), spark.createDataFrame([(100, [1, 1])], ROWS)
    got = sorted(map(tuple, topk.exact_top_k(rows, queries, 5).collect()))
    assert [(r[2], r[3]) for r in got] == [(3, 38), (3, 38), (6, 36), (6, 36), (1, 20)]


def test_wide_vectors(spark, monkeypatch):
    monkeypatch.setattr(vectors, "BLOCK_BYTES", 5 * 8 * 6000)
    rng = np.random.default_rng(2)
    x = rng.integers(-9, 9, (60, 6000))
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], ROWS)
    queries = rows.where("id % 5 = 0")
    assert [len(i) for i, _ in vectors.query_blocks(queries, 6000)] and max(len(i) for i, _ in vectors.query_blocks(queries, 6000)) <= 12
    assert sorted(map(tuple, topk.exact_top_k(rows, queries, 3).collect())) == plain_top([(i, v.tolist()) for i, v in enumerate(x)], [(i, x[i].tolist()) for i in range(0, 60, 5)], 3)
    wide = rows.selectExpr("id", "cast(v as array<double>) as v")
    got = additive.search(additive.build_index(wide, books=4, words=32), wide.where("id % 5 = 0"), 3, margin=5.0)
    score = x @ x.T
    np.fill_diagonal(score, -(10**9))
    near = {(i, int(j)) for i in range(0, 60, 5) for j in np.argsort(-score[i], kind="stable")[:3]}
    assert len(near & {(r.query_id, r.id) for r in got.collect()}) >= 0.9 * len(near)
