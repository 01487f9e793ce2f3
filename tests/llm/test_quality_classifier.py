import numpy as np
from lexfold.llm import quality_classifier as Q


def test_learns_from_positives_and_unlabelled():
    rng = np.random.default_rng(0)
    good, bad = rng.normal(1, 1, (3000, Q.N_FEATURES)), rng.normal(-1, 1, (1000, Q.N_FEATURES))
    m = Q.PuNetwork(0.6).fit(good[:1000], np.concatenate((good[1000:2500], bad)), rounds=400)
    assert (m.score(good[2500:]) >= 0.5).mean() > 0.95 and (m.score(bad) < 0.5).mean() > 0.95


def test_fit_reaches_the_least_risk():
    """Against a brute-force minimiser: full-batch descent of the same risk, by finite differences of a linear scorer."""
    rng = np.random.default_rng(1)
    good, bad = rng.normal(0.8, 1, (500, Q.N_FEATURES)), rng.normal(-0.8, 1, (300, Q.N_FEATURES))
    positive, unlabelled, prior = good[:250], np.concatenate((good[250:], bad)), 250 / 550
    w = np.zeros(Q.N_FEATURES + 1)
    value = lambda w: Q.risk(positive @ w[:-1] + w[-1], unlabelled @ w[:-1] + w[-1], prior)
    step = np.eye(len(w)) * 1e-5
    for _ in range(150):
        w -= 0.3 * np.array([(value(w + e) - value(w - e)) / 2e-5 for e in step])
    m = Q.PuNetwork(prior).fit(positive, unlabelled)
    of_fit = Q.risk(m._forward(positive)[1], m._forward(unlabelled)[1], prior)
    assert of_fit <= value(w) + 0.03
    assert ((m.score(np.concatenate((good, bad))) >= 0.5) == (np.arange(800) < 500)).mean() > 0.97


def test_prior_is_found_without_negatives():
    rng = np.random.default_rng(2)
    for share in (0.15, 0.5, 0.8):
        good, bad = rng.normal(0.9, 1, (4000, Q.N_FEATURES)), rng.normal(-0.9, 1, (4000, Q.N_FEATURES))
        n = int(4000 * share)
        found = Q.estimated_prior(good[:2000], rng.permutation(np.concatenate((good[2000 : 2000 + min(n, 2000)], bad[: int(min(n, 2000) * (1 - share) / share)]))))
        assert abs(found - share) < 0.06
    assert Q.least_ratio(np.array([1.0, 2, 3, 4] * 500), np.array([0.0, 0, 3, 4] * 500)) == 0.5


def test_samples_keep_to_their_bound(spark):
    docs = spark.createDataFrame([(1, f"text {k % 7}") for k in range(600)] + [(k, "other") for k in range(2, 40)], "doc_id long, text string")
    assert len(Q._sampled(docs, docs, 50)) == 50
    labels = spark.createDataFrame([(1, 1)] * 5 + [(None, 1), (2, None), (3, 0)], "doc_id long, quality int")
    assert 0 < Q.train(docs, labels, 20, 20).prior <= 1


def test_risk_is_never_negative():
    z = np.full(10, 5.0)
    assert Q.risk(z, -z, 0.9) >= 0
    assert abs(Q.risk(z, -z, 0.9) - 0.9 * np.logaddexp(0, -5.0)) < 1e-12


def test_features_of_odd_texts():
    x = Q.features([b"", b" ", b"one", b"a b a b", "é".encode() * 9])
    assert np.isfinite(x).all() and x[3, len(Q.CLASSES) + 4] == 0.5
    assert np.allclose(Q.features([b"a b a b"])[0], x[3])


def test_held_out_quality(spark):
    sf = "/root/testdata/sf0.01"
    d = Q.op2_quality_classifier(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").collect()
    right = sum(r.predicted == r.quality for r in d)
    assert right >= 0.95 * len(d), (right, len(d))
    share = sum(r.quality for r in d) / len(d)
    model = Q.train(spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet"))
    assert abs(model.prior - share) < 0.15, (model.prior, share)


def test_cases(spark):
    docs = spark.createDataFrame([(None, None, 1.0), (1, "", 1.0), (1, "x y", 2.0)], "doc_id long, text string, score double")
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert [r.score for r in Q.score(docs, Q.train(docs, none)).collect()] == [0.5] * 3
    assert Q.score(docs.limit(0), Q.train(docs.limit(0), none)).count() == 0
