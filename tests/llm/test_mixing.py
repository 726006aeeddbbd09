import duckdb
import pytest
from helpers import docs_frame, odd_texts

from bundlemv.llm import mixing


def taken(rows):
    return {r.doc_id: r for r in rows}


def brute_targets(sizes, weights, cap):
    """Clamp and reshare until none is above its cap."""
    names = sorted(sizes, key=lambda s: (s is None, s))
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    total, fixed = sum(sizes.values()), {}
    while True:
        free = [s for s in names if s not in fixed]
        left = total - sum(fixed.values())
        shares = {s: left * w[s] / sum(w[t] for t in free) for s in free}
        over = [s for s in free if shares[s] > cap * sizes[s]]
        if not over:
            return fixed | shares
        fixed |= {s: cap * sizes[s] for s in over}


def test_against_resharing(spark):
    texts = ["a " * (1 + (i * 37) % 50) for i in range(120)]
    sources = [None if i % 11 == 0 else f"s{min(i % 7, 4)}" if i % 3 else "big" for i in range(120)]
    docs = docs_frame(spark, texts, sources=sources)
    rows = mixing.mix_sources(docs, keep=("source",)).collect()
    sizes = {}
    for r in rows:
        assert r.size == len(texts[r.doc_id].split())
        sizes[r.source] = sizes.get(r.source, 0) + r.size
    want = brute_targets(sizes, (1, 2, 3), 3)
    for s, total in sizes.items():
        own = [r for r in rows if r.source == s]
        assert all(r.source_size == total and r.target == pytest.approx(want[s]) for r in own)
        assert sum(r.taken for r in own) == int(want[s] + 0.5)
        assert all(0 <= r.taken <= 3 * r.size for r in own)
    again = mixing.mix_sources(docs.repartition(5)).collect()
    assert {r.doc_id: r.taken for r in rows} == {r.doc_id: r.taken for r in again}


def test_odd_inputs(spark):
    docs = docs_frame(spark, odd_texts() + ["dup dup", "dup dup"], ids=[*range(12), None, None])
    rows = mixing.mix_sources(docs).collect()
    assert len(rows) == 14
    assert [r.size for r in sorted(rows, key=lambda r: (r.doc_id is None, r.doc_id)) if r.doc_id in (0, 1, 2, 3, 11)] == [0, 0, 0, 1, 2]
    assert mixing.mix_sources(docs.limit(0)).collect() == []
    blank = mixing.mix_sources(docs_frame(spark, [None, " "])).collect()
    assert [(r.target, r.taken) for r in blank] == [(0.0, 0), (0.0, 0)]


def test_repetitions(spark):
    docs = docs_frame(spark, ["a b c", " d  e f g", "h", None])
    mixed = spark.createDataFrame([(0, 7), (1, 2), (2, 0), (3, 0)], "doc_id long, __taken long")
    rows = docs.join(mixed, "doc_id").withColumn("__words", mixing.word_count(docs.text))
    got = sorted((r.doc_id, r.text) for r in mixing.repeat_rows(rows).collect())
    assert got == [(0, "a"), (0, "a b c"), (0, "a b c"), (1, "d e")]


def test_mixed_documents(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    out = mixing.mixed_documents(docs)
    assert out.columns == docs.columns and out.schema.simpleString() == docs.schema.simpleString()
    want = {r.doc_id: r.taken for r in mixing.mix_sources(docs).collect() if r.taken}
    got = {}
    for r in out.collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + len(r.text.split())
    assert got == want


def test_plain_plan(spark, tiny):
    plan = mixing.op7(spark, tiny)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_sql(spark, tiny):
    con = duckdb.connect()
    con.execute(f"create view documents as from '{tiny}/documents.parquet'")
    want = sorted(con.execute(f"select doc_id, size, source_size, target, taken from ({mixing.OP7_SQL})").fetchall())
    assert want == sorted(tuple(r) for r in mixing.op7(spark, tiny).select("doc_id", "size", "source_size", "target", "taken").collect())
