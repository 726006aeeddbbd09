import itertools

import numpy as np
from helpers import docs_frame, odd_texts
from pyspark.sql import functions as F

from bundlemv.llm import langid


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    langs = {r.doc_id: r.lang for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = langid.op4(spark, sf).collect()
    assert len(rows) == len(langs)
    assert np.mean([r.lang_pred == langs[r.doc_id] for r in rows if r.held_out]) > 0.97
    assert all(0 <= r.score <= 1 for r in rows)


def test_mixture_proportions(spark, tiny):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = langid.train(docs)
    text = {lang: " ".join(r.text for r in docs.where(F.col("lang") == lang).limit(6).collect()).split() for lang in ("en", "de")}
    for share in (0.25, 0.5, 0.75):
        n = int(400 * share)
        mixed = " ".join(text["en"][:n] + text["de"][: 400 - n]).encode()
        mix, alone = langid.infer(model, [mixed, " ".join(text["de"][:400]).encode()], 2.0)
        en, de = (model.languages.index(x) for x in ("en", "de"))
        assert abs(mix[en] - share) < 0.12 and abs(mix[de] - 1 + share) < 0.12 and alone[de] > 0.95


def test_the_set_of_the_best_penalised_likelihood(spark):
    """Against all sets of languages, with many rounds of EM on the plain likelihoods."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = langid.train(docs)
    text = {x: " ".join(r.text for r in docs.where(F.col("lang") == x).limit(8).collect()).split() for x in model.languages}
    assert len(text) == 4
    for picked in (["en"], ["en", "fr"], list(model.languages)[:3], list(model.languages)):
        mixed = " ".join(w for x in picked for w in text[x][:150]).encode()
        _, ll = model.word_likelihoods(np.frombuffer(mixed, np.uint8))
        best = (-np.inf, ())
        for m in range(1, 5):
            for some in itertools.combinations(range(4), m):
                lik, share = np.exp(ll[:, some]), np.full(m, 1 / m)
                for _ in range(200):
                    share = (lik * share / (lik @ share)[:, None]).mean(axis=0)
                best = max(best, (np.log(lik @ share).sum() - 2.0 * (m - 1) * np.log(len(ll) + 1) / 2, some))
        (got,) = langid.infer(model, [mixed], 2.0)
        assert tuple(np.nonzero(got)[0]) == best[1] == tuple(sorted(map(model.languages.index, picked)))
    long = docs_frame(spark, [" ".join(w for x in text for w in text[x][:150])])
    (row,) = langid.identify(long, model).collect()
    assert set(row.languages) == set(model.languages) and abs(sum(row.proportions) - 1) < 1e-9 and row.score == max(row.proportions) and row.lang_pred == row.languages[0]


def test_em_raises_the_likelihood():
    rng = np.random.default_rng(3)
    lik = rng.random((200, 4))
    doc, first = np.repeat([0, 1], 100), np.array([0, 100])
    last = -np.inf
    for rounds in (1, 3, 9):
        share, total = langid._em(lik, doc, first, np.full((2, 4), 0.25), rounds)
        assert np.allclose(share.sum(1), 1) and (total >= last - 1e-9).all()
        last = total


def test_odd_inputs(spark):
    texts = odd_texts() + ["123 !!", "one two three"] * 2
    docs = docs_frame(spark, texts, ids=[*range(14), None, None])
    got = langid.identify(docs, langid.train(docs)).collect()
    by = {r.doc_id: r for r in got}
    assert len(got) == 16 and {by[i].lang_pred for i in (0, 1, 2, 12)} == {"und"} and by[8].lang_pred == "en"
    none = langid.train(docs.withColumn("lang", F.lit(None).cast("string")))
    assert {r.lang_pred for r in langid.identify(docs, none).collect()} == {"und"}
    assert langid.identify(docs.limit(0), none).collect() == []
