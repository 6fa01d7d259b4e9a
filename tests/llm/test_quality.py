import numpy as np
import pytest

from runstore.llm import base
from runstore.llm import quality as q


def test_held_out(spark):
    d = "/root/testdata/sf0.01"
    got = q.query(spark, d).join(base.table(spark, d, "labels"), "doc_id").collect()
    held = [r for r in got if r["held_out"]]
    good, bad = ([r["score"] for r in held if r["quality"] == k] for k in (1, 0))
    assert len(held) > 50 and np.mean([g > b for g in good for b in bad]) >= 0.97
    assert np.mean([g >= 0.3 for g in good]) >= 0.95 and np.mean([b >= 0.3 for b in bad]) <= 0.2
    assert q.query(spark, d).count() == 1000


def test_prior():
    rng = np.random.default_rng(1)
    p, n = rng.normal(2, 1, 5000), rng.normal(-2, 1, 5000)
    for share in (0.2, 0.5, 0.8):
        u = np.where(rng.random(5000) < share, rng.permutation(p), n)
        assert q.class_prior(p, u) == pytest.approx(share, abs=0.08)


def test_slopes_are_those_of_the_risk():
    rng = np.random.default_rng(2)
    is_p = np.arange(30) < 12
    seen = set()
    for scale, prior in ((1.0, 0.3), (3.0, 0.9), (0.2, 0.99)):
        z = rng.normal(0, scale, 30) + np.where(is_p, 2 * scale, 0)
        low = q.negative_risk(z, is_p, prior) < 0
        seen.add(low)

        def risk(y):
            negative = q.negative_risk(y, is_p, prior)
            return -negative if low else prior * np.logaddexp(0, -y[is_p]).mean() + negative

        got = q.slopes(z, is_p, prior)
        for k in range(30):
            step = np.zeros(30)
            step[k] = 1e-6
            assert got[k] == pytest.approx((risk(z + step) - risk(z - step)) / 2e-6, abs=1e-6)
    assert seen == {False, True}


def test_scores_are_a_plain_recomputation(spark):
    d = "/root/testdata/sf0.001"
    docs = base.table(spark, d, "documents")
    model = q.fit_on_tables(docs, base.table(spark, d, "labels"))
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in q.query(spark, d).collect():
        x = np.clip((q.features(texts[r["doc_id"]]) - model.mean) / model.scale, -6, 6)
        logit = model.shift + np.mean([sum(w[2][j] * np.tanh(x @ w[0][:, j] + w[1][j]) for j in range(len(w[2]))) + w[3][0] for w in model.networks])
        assert r["score"] == pytest.approx(1 / (1 + np.exp(-np.clip(logit, -40, 40))), abs=1e-9)
        assert r["predicted"] == int(r["score"] >= 0.3)


def test_edges(spark):
    docs = spark.createDataFrame([(1, None, 0.5), (2, "", 0.5), (3, "Some plain text. " * 9000, 1.0), (None, "| | |", 2.0), (3, "again", 1.0)], "doc_id long, text string, score double")
    none = spark.createDataFrame([], "doc_id long, quality int")
    model = q.train(docs, none)
    assert {r["score"] for r in q.score(docs, model).collect()} == {0.5}
    one = q.train(docs, spark.createDataFrame([(3, 1), (1, None), (None, 1)], "doc_id long, quality int"))
    got = q.score(docs, one).collect()
    assert len(got) == 5 and all(0 <= r["score"] <= 1 for r in got)
    assert q.score(docs.limit(0), one).count() == 0
