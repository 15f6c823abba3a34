import tracemalloc
import zlib

import numpy as np
import pytest

from suffix_engine.llm import mixing, quality

SF = "/root/testdata/sf0.01"


def test_quality_on_held_out_labels(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    truth = {r.doc_id: r.quality for r in labels.collect()}
    rows = quality.quality_scores(docs, labels).collect()
    assert len(rows) == 1000 and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    out = [(r.predicted, truth[r.doc_id]) for r in rows if r.held_out and r.doc_id in truth]
    assert np.mean([p == q for p, q in out]) > 0.95
    good = [p for p, q in out if q == 1]
    assert np.mean(good) > 0.97


def test_labels_of_the_held_out_fold_are_not_read(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    other = labels.where(~quality.held_out(labels.doc_id))
    assert np.array_equal(quality.fit(docs, labels).weights, quality.fit(docs, other).weights)


def test_quality_edges(spark):
    docs = spark.createDataFrame([(1, "", 0.0), (2, None, 1.0), (None, "abc " * 50000, 2.0), (1, "", 0.0)], "doc_id long, text string, score double")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert quality.quality_scores(docs, labels).count() == 4
    assert quality.quality_scores(docs.limit(0), labels).collect() == []


def test_nonnegative_risk_separates():
    r = np.random.default_rng(0)
    p = r.normal(1, 0.5, (500, 3)).astype(np.float32)
    u = np.vstack([r.normal(1, 0.5, (800, 3)), r.normal(-1, 0.5, (200, 3))]).astype(np.float32)
    m = quality.fit_nnpu(p, u, 0.8)
    assert (m.score(u[:800]) > 0.5).mean() > 0.95 and (m.score(u[800:]) < 0.5).mean() > 0.9


def test_mixing_meets_targets(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    for targets in [(0.6, 0.3, 0.1), (0.9, 0.07, 0.03)]:
        rows = mixing.mix(docs.select("doc_id", "text"), labels, targets).collect()
        n, p, r = np.array([x.n_tokens for x in rows]), np.array([x.posteriors for x in rows]), np.array([x.rate for x in rows])
        assert (r >= 0).all() and np.allclose(p.sum(axis=1), 1)
        assert np.allclose((r * n) @ p / n.sum(), targets, atol=2e-3)


def test_mixing_rates_equal_plain_descent(spark):
    r = np.random.default_rng(1)
    p, n = r.dirichlet((1, 1, 1), 300), r.integers(0, 200, 300)
    df = spark.createDataFrame([(int(a), b.tolist()) for a, b in zip(n, p, strict=True)], "n_tokens long, posteriors array<double>")
    steps = mixing.descend(df, (0.8, 0.15, 0.05))
    rates = np.ones(300)
    weight = np.linalg.inv((p * n[:, None]).T @ p / n.sum() + mixing.RIDGE * np.eye(3))
    for _ in range(len(steps)):
        rates = np.maximum(0, rates - p @ (weight @ ((rates * n) @ p / n.sum() - np.array([0.8, 0.15, 0.05]))))
    got = np.array([x.rate for x in mixing.with_rates(df, steps).collect()])
    assert np.allclose(got, rates, atol=1e-9)


def test_production_mix_holds_domains_to_their_shares(spark):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    known = {r.doc_id: (r.quality, r.toxic) for r in labels.collect()}
    rows = mixing.mixing_rates(docs, labels).collect()
    n, p, r = np.array([x.n_tokens for x in rows]), np.array([(x.p_good, x.p_poor, x.p_toxic) for x in rows]), np.array([x.rate for x in rows])
    was, got = n @ p / n.sum(), (r * n) @ p / n.sum()
    assert all(x.targets_met for x in rows)
    over = mixing.over_bounds(was)
    assert np.allclose(got[over], np.array(mixing.AT_MOST)[over], rtol=2e-3) and abs(got.sum() - 1) < 2e-3 and over[2] and not over[0]
    rates = {k: np.mean([x.rate for x in rows if known.get(x.doc_id) == k]) for k in ((0, 0), (1, 0), (1, 1))}
    assert rates[1, 0] > 0.9 and rates[1, 0] > 2 * rates[1, 1] and rates[1, 0] > 1.3 * rates[0, 0]


def test_rates_equal_a_plain_version_from_text_to_rate(spark):
    """The classifier is run on one machine over the same texts, and the least change of rates that meets the targets is found by brute force."""
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    targets = (0.9, 0.08, 0.02)
    rows = mixing.mix(docs.select("doc_id", "text"), labels, targets).collect()
    model = mixing.fit(docs, labels)
    texts = [(r.text or "").encode() for r in rows]
    data, bounds = np.frombuffer(b"".join(texts), np.uint8), np.r_[0, np.cumsum([len(t) for t in texts])]
    p, n = model.posteriors(data, bounds)
    assert np.allclose(p, [r.posteriors for r in rows], atol=1e-5) and n.tolist() == [r.n_tokens for r in rows]
    # of all rates from 0 on that meet the targets those nearest to 1 (weighted by tokens) are max(0, 1 - p @ x)
    x, share = np.zeros(3), n / n.sum()
    for _ in range(200):
        rate = np.maximum(0, 1 - p @ x)
        hessian = (p * (share * (rate > 0))[:, None]).T @ p + 1e-9 * np.eye(3)
        x += 0.5 * np.linalg.solve(hessian, (rate * share) @ p - np.array(targets))
    assert np.allclose((np.array([r.rate for r in rows]) * share) @ p, targets, rtol=2e-3)
    assert np.abs(np.array([r.rate for r in rows]) - np.maximum(0, 1 - p @ x)).mean() < 0.15


def test_columns_that_clash_and_repeated_rows(spark):
    rows = [(1, "good text here " * 20, 5, "x"), (1, "good text here " * 20, 5, "x"), (None, None, None, None), (3, "w " * 60_000, 1, "y")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_tokens int, rate string")
    labels = spark.createDataFrame([(1, 1, 0), (1, 0, 0), (3, 0, 1)], "doc_id long, quality int, toxic int")
    out = mixing.mix(docs, labels)
    assert out.columns == ["doc_id", "text", "n_tokens", "posteriors", "rate", "targets_met"] and sorted(r.n_tokens for r in out.collect()) == [0, 60, 60, 60_000]
    scored = quality.with_score(docs.withColumn("score", docs.text), quality.fit(docs, labels))
    assert scored.columns == [*docs.columns, "score"] and all(0 <= r.score <= 1 for r in scored.collect())


def test_domains_over_their_bounds():
    over = lambda *a: mixing.over_bounds(*map(np.array, a)).tolist()
    assert over([7.0, 1.0, 2.0], (1, 0.5, 0.1)) == [False, False, True]
    assert over([0.8, 0.1, 0.1], (1, 0.105, 0.01)) == [False, True, True]  # over it once the other is down
    assert over([0.96, 0.03, 0.01], mixing.AT_MOST) == [False, False, False]
    assert over([0.0, 1.0, 0.0], mixing.AT_MOST) == [False, True, False]


@pytest.mark.parametrize("prior", [0.2, 0.5, 0.85])
def test_prior_is_estimated_without_negatives(prior):
    r = np.random.default_rng(4)
    make = lambda n, m: r.normal(m, 0.6, (n, 5)).astype(np.float32)
    n = 4000
    u = np.vstack([make(int(n * prior), 1), make(n - int(n * prior), -1)])
    assert abs(quality.estimated_prior(make(2000, 1), r.permutation(u)) - prior) < 0.06


def test_quality_equals_a_plain_version(spark):
    """Fitting and scoring on one machine, from the same samples."""
    docs, labels = spark.read.parquet("/root/testdata/sf0.001/documents.parquet"), spark.read.parquet("/root/testdata/sf0.001/labels.parquet")
    text = {r.doc_id: (r.text or "").encode() for r in docs.collect()}
    fold = lambda d: zlib.crc32(str(d).encode()) % 3 != 1
    features = lambda ids: np.vstack([quality.shape_features(np.frombuffer(text[d], np.uint8), np.array([0, len(text[d])])) for d in ids])
    p = features(sorted(r.doc_id for r in labels.collect() if r.quality == 1 and fold(r.doc_id))).astype(np.float16).astype(np.float32)
    u = features(sorted(d for d in text if fold(d))).astype(np.float16).astype(np.float32)
    model = quality.fit_nnpu(p, u, quality.estimated_prior(p, u))
    got = {r.doc_id: r.score for r in quality.quality_scores(docs, labels).collect()}
    assert np.allclose([got[d] for d in sorted(text)], model.score(features(sorted(text))), atol=2e-3)


def _made(spark, shares, n=20000):
    """(n_tokens, posteriors) of documents that are nearly pure, so many of each domain."""
    y = np.repeat(np.arange(3), [n - sum(int(n * s) for s in shares), *(int(n * s) for s in shares)])
    p = np.full((n, 3), 5e-5)
    p[np.arange(n), y] = 0.9999
    tokens = np.random.default_rng(3).integers(50, 150, n)
    return spark.createDataFrame([(int(a), b.tolist()) for a, b in zip(tokens, p, strict=True)], "n_tokens long, posteriors array<double>"), tokens, p, y


@pytest.mark.parametrize("shares", [(0.1, 0.001), (0.1, 0.002), (0.0004, 0.0004)])
def test_scarce_domains_meet_their_targets(spark, shares):
    df, n, p, y = _made(spark, shares)
    was = n @ p / n.sum()
    found = mixing.plan(df, np.r_[1 - was[1:].sum() / 2, was[1:] / 2])
    rates = np.array([x.rate for x in mixing.with_rates(df, found.steps).collect()])
    got = (rates * n) @ p / n.sum()
    assert found.met and np.allclose(list(found.reached.values()), got)
    assert np.allclose(got[1:], was[1:] / 2, rtol=1e-3) and abs(got.sum() - 1) < 1e-3
    assert rates[y == 0].min() > 0.99 and rates[y == 2].max() < 0.51


def test_unmet_targets_are_reported(spark):
    df = spark.createDataFrame([(10, [0.6, 0.2, 0.2]), (20, [0.5, 0.3, 0.2])], "n_tokens long, posteriors array<double>")
    with pytest.warns(UserWarning, match=r"toxic 0\.\d+ of 0\.01"):
        found = mixing.plan(df, (0.9, 0.09, 0.01))
    assert not found.met and found.reached["toxic"] > 0.01


@pytest.mark.parametrize("rows", [[], [(1, None), (None, ""), (2, "a b")]])
def test_mixing_edges(spark, rows):
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(2, None, None), (None, 1, 0)], "doc_id long, quality int, toxic int")
    assert mixing.mixing_rates(docs, labels).count() == len(rows)


def test_fitting_takes_little_of_the_driver():
    # half of the columns say nothing, as most pairs of classes never occur; whole copies on the way took twice the samples' own size
    r = np.random.default_rng(3)
    x = (r.random((1800, 1200)) * (np.arange(1200) % 2)).astype(np.float32)
    positive, unlabelled = x[:600] ** 2, x[600:]
    tracemalloc.start()
    try:
        quality.fit_nnpu(positive, unlabelled, quality.estimated_prior(positive, unlabelled))
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert peak < 1.6 * x.nbytes, peak / x.nbytes
