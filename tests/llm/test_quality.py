import numpy as np
import pytest
from helpers import docs_frame, odd_texts

from bundlemv.llm import quality


def auc(pairs):
    good, bad = [s for s, y in pairs if y], [s for s, y in pairs if not y]
    return np.mean([(g > b) + 0.5 * (g == b) for g in good for b in bad])


def test_discriminant_is_a_density_ratio():
    rng = np.random.default_rng(0)
    d = len(quality.NAMES)
    x0, x1 = rng.normal(size=(300, d)), rng.normal(0.8, 2.0, size=(900, d))
    one = lambda x: np.hstack([np.ones((len(x), 1)), x])
    model = quality.fit_discriminant({0: one(x0).T @ one(x0), 1: one(x1).T @ one(x1)}, shrink=0.0, ridge=0.0)
    w = [d / (d + n) for n in (300, 900)]
    covs = [np.cov(x.T, bias=True) for x in (x0, x1)]
    pooled = (300 * covs[0] + 900 * covs[1]) / 1200
    logs = []
    for x, cov, a in ((x0, covs[0], w[0]), (x1, covs[1], w[1])):
        cov = (1 - a) * cov + a * pooled + 1e-9 * np.eye(d)
        at = x1[:5] - x.mean(0)
        logs.append(-0.5 * np.einsum("ij,jk,ik->i", at, np.linalg.inv(cov), at) - 0.5 * np.linalg.slogdet(cov)[1])
    z = logs[1] - logs[0] + np.log(3)
    assert model.score(x1[:5]) == pytest.approx(1 / (1 + np.exp(-np.clip(z, -60, 60))), rel=1e-6)


def test_held_out(spark):
    sf = "/root/testdata/sf0.01"
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    rows = quality.op6(spark, sf).collect()
    assert len(rows) == spark.read.parquet(f"{sf}/documents.parquet").count()
    held = [(r.score, labels[r.doc_id]) for r in rows if r.held_out and r.doc_id in labels]
    assert auc(held) > 0.95 and np.mean([(s >= 0.5) == y for s, y in held]) > 0.9


def test_odd_inputs(spark):
    docs = docs_frame(spark, odd_texts() + ["dup"] * 2, ids=[*range(12), None, None])
    labels = spark.createDataFrame([(i, i % 2 if i < 9 else None, 0) for i in range(12)] + [(None, 1, 0)], "doc_id long, quality int, toxic int")
    rows = quality.quality_scores(docs, labels).collect()
    assert len(rows) == 14 and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in rows)
    lone = quality.quality_scores(docs, labels.limit(0)).collect()
    assert {r.score for r in lone} == {0.5}
    assert quality.filter_quality(docs, labels).columns == docs.columns
    assert quality.quality_scores(docs.limit(0), labels).collect() == []
