import corpus_pipeline as cp
from helpers import docs_frame, odd_texts
from test_packing import check_bins
from test_pii import plain_base


def shingles(text):
    w = text.lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))}


def test_stages(spark, tmp_path):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id < 400")
    columns, seen = docs.columns, {}
    for name, stage in cp.STAGES:
        out = stage(spark, docs, sf)
        assert name == "packing" or out.columns == columns
        out.write.parquet(path := f"{tmp_path}/{name}")
        docs = spark.read.parquet(path)
        seen[name] = docs.collect()
    kept = seen["quality"]
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    judged = [(r.doc_id, labels[r.doc_id]) for r in kept if r.doc_id in labels]
    assert sum(q for _, q in judged) / len(judged) > 0.95
    left = {r.doc_id for r in seen["near-duplicates"]}
    sets = {r.doc_id: shingles(r.text) for r in kept}
    pairs = {(i, j): len(sets[i] & sets[j]) / len(sets[i] | sets[j]) for i in sets for j in sets if i < j and sets[i] & sets[j]}
    for i in sets.keys() - left:  # what goes is like something that was there; what stays is not like another that stays
        assert any(v >= 0.7 for p, v in pairs.items() if i in p)
    assert not any(v >= 0.85 for (i, j), v in pairs.items() if i in left and j in left)
    assert {r.doc_id for r in seen["personal-data"]} == left
    assert not any(plain_base(r.text) for r in seen["personal-data"])
    rows = seen["packing"]
    assert check_bins(rows, 2048) and {r.doc_id for r in rows} == {r.doc_id for r in seen["mixing"]}


def test_run(spark, tiny):
    assert cp.run(spark, tiny).count() > 0


def test_odd_inputs(spark, tiny):
    texts = odd_texts() + ["dup one two three"] * 2
    docs = docs_frame(spark, texts, ids=[*range(12), None, None])
    for some in (docs, docs.limit(0)):
        cur = some
        for name, stage in cp.STAGES:
            cur = stage(spark, cur, tiny)
            assert name == "packing" or cur.columns == docs.columns
        cur.collect()


