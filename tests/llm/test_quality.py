from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from vtask.llm.quality import LABELLERS, QualityModel, label_model, pattern_counts


def test_label_model_finds_accuracies():
    rng = np.random.default_rng(1)
    y = rng.random(40000) < 0.3
    right = np.array([0.9, 0.8, 0.75, 0.85, 0.7])
    votes = np.where(rng.random((y.size, 5)) < right, y[:, None], ~y[:, None]).astype(int)
    votes[rng.random(votes.shape) < 0.2] = 2
    pats, n = np.unique(votes, axis=0, return_counts=True)
    post, theta = label_model(dict(zip(map(tuple, pats.tolist()), n.tolist(), strict=True)))
    assert np.abs(theta[:, 1, 1] - right).max() < 0.05 and np.abs(theta[:, 0, 0] - right).max() < 0.05
    p = np.array([post[tuple(v)] for v in votes.tolist()])
    assert ((p > 0.5) == y).mean() > 0.88
    assert label_model({})[0] == {}


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet("/root/testdata/sf0.01/documents.parquet")


def test_held_out_labels(spark, docs):
    m = QualityModel(docs, sample=400)
    rows = m.score(docs).join(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"), "doc_id").collect()
    good, bad = [r for r in rows if r.quality == 1], [r for r in rows if r.quality == 0]
    assert sum(r.kept for r in good) >= 0.98 * len(good)
    assert sum(r.kept for r in bad) <= 0.15 * len(bad)
    toxic = [r for r in good if r.toxic == 1]
    assert sum(r.kept for r in toxic) >= 0.95 * len(toxic)
    again = QualityModel(docs.repartition(5), sample=400)
    assert np.array_equal(again.weights, m.weights) and again.post == m.post
    kept = m.keep(docs.withColumn("votes", F.lit(1)))
    assert kept.columns == [*docs.columns, "votes"]
    assert {r.doc_id for r in kept.collect()} == {r.doc_id for r in m.score(docs).filter("kept").collect()}


def test_awkward(awkward):
    m = QualityModel(awkward, sample=5)
    rows = m.score(awkward.withColumn("score", F.lit("x"))).collect()
    assert len(rows) == 12 and all(r.kept and r.n_words == 0 and r.votes == "2" * len(LABELLERS) for r in rows if r.doc_id in (2, 3, 4))
    empty = awkward.limit(0)
    m = QualityModel(empty)
    assert m.score(empty).count() == 0 and m.keep(empty).count() == 0 and pattern_counts(empty) == {}
