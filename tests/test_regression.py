"""Losses, solvers, conditioning, coresets and the comparison of methods."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from lpstream.functions import losses
from lpstream.operators import baselines as bl, coreset, leverage, measures, solvers, subspace
from lpstream.plans import experiments
from lpstream.sources import features


@pytest.fixture(scope="module")
def events(spark, sf):
    return features.w3_events(spark, sf).persist()


def test_loss_values(spark):
    zero = np.zeros(1)
    assert losses.value_numpy("logistic", zero)[0] == pytest.approx(math.log(2)) == losses.value_numpy("probit", zero, 2.0)[0]
    t = np.linspace(-8, 8, 81)
    normal = np.array([-math.log(0.5 * math.erfc(x / math.sqrt(2))) for x in t])
    assert np.allclose(losses.value_numpy("probit", t, 2.0), normal, rtol=1e-9)
    laplace = np.where(t > 0, t + math.log(2), -np.log1p(-0.5 * np.exp(np.minimum(t, 0))))
    assert np.allclose(losses.value_numpy("probit", t, 1.0), laplace, rtol=1e-9)
    for name in losses.LOSSES:
        v = losses.value_numpy(name, np.array([-700.0, 700.0]), 1.0)
        assert np.isfinite(v).all() and (name == "lp" or v[0] < 1e-9)
        for p in (1.0, 1.5, 2.0):
            h = 1e-6
            x = np.array([-2.3, -0.4, 0.7, 3.1])
            slope = (losses.value_numpy(name, x + h, p) - losses.value_numpy(name, x - h, p)) / (2 * h)
            assert np.allclose(losses.slope_numpy(name, x, p), slope, rtol=1e-4, atol=1e-6)
    df = spark.createDataFrame([(float(x),) for x in t], "t double")
    for name, p in (("lp", 1.5), ("relu", 2.0), ("logistic", 1.0), ("probit", 1.0), ("probit", 1.5)):
        got = np.array([r[0] for r in df.select(losses.value(name, F.col("t"), p)).collect()])
        assert np.allclose(got, losses.value_numpy(name, t, p), rtol=1e-8)


def test_solvers(spark):
    rng = np.random.default_rng(0)
    a = rng.normal(size=(300, 4))
    b = a @ np.array([1.0, -2, 0.5, 3]) + rng.laplace(size=300)
    x, w = np.c_[a, b], np.ones(300)
    z2 = solvers.solve(x, w, "lp", 2.0, last=-1.0)
    assert np.allclose(z2[:-1], np.linalg.lstsq(a, b, rcond=None)[0], atol=1e-6)
    z1 = solvers.solve(x, w, "lp", 1.0, last=-1.0)
    best = solvers.objective(x, w, z1, "lp", 1.0)
    assert all(solvers.objective(x, w, z1 + np.r_[rng.normal(size=4) * 0.05, 0], "lp", 1.0) >= best * (1 - 1e-4) for _ in range(50))
    y = np.where(a[:, 0] + rng.normal(size=300) > 0, 1.0, -1.0)
    g = -a * y[:, None]
    for loss, p in (("logistic", 1.0), ("probit", 2.0), ("relu", 2.0)):
        z = solvers.solve(g, w, loss, p)
        grad = g.T @ losses.slope_numpy(loss, g @ z, p) / 300
        assert np.abs(grad).max() < 1e-3, loss
    rows = spark.createDataFrame([(i, [float(v) for v in r]) for i, r in enumerate(g)], "row_id long, vec array<double>")
    full = solvers.solve_full(rows, 4, "logistic")
    assert solvers.objective(g, w, full, "logistic", 1.0) <= solvers.objective(g, w, solvers.solve(g, w, "logistic"), "logistic", 1.0) * (1 + 1e-6)
    assert solvers.best_of(rows, [np.zeros(4), full], "logistic")[0] is full


def test_conditioning(events):
    d = 6
    m = subspace.exact_conditioner(events, d)
    c = measures.conditioning(events, m, d, 2.0)
    assert c["beta"] == pytest.approx(1, abs=0.05) and c["alpha"] == pytest.approx(math.sqrt(d), rel=0.05)
    lev = leverage.exact_l2(events, d).agg(F.sum("score"), F.max("score")).first()
    assert lev[0] == pytest.approx(d, rel=1e-3) and lev[1] <= 1.0001
    x = np.array([r.vec for r in events.orderBy("row_id").collect()])
    q, _ = np.linalg.qr(x)
    got = np.array([r.score for r in leverage.exact_l2(events, d).orderBy("row_id").collect()])
    assert np.allclose(got, (q**2).sum(1), atol=1e-5)
    dense = subspace.conditioner(subspace.to_numpy(subspace.dense(leverage.long_rows(events), 240, 2.0), 240, d))
    e = measures.conditioning(events, dense, d, 2.0)
    # Up to the common scale of the embedding, the product is what matters.
    assert math.sqrt(d) * 0.9 < e["alpha"] * e["beta"] < 2.5 * math.sqrt(d)
    lo, hi = measures.distortion(events, subspace.to_numpy(subspace.dense(leverage.long_rows(events), 200, 1.0), 200, d), 1.0, d)
    assert 0.2 < lo <= hi < 5  # of the norm itself, no common scale taken out
    lo, hi = measures.distortion(events, subspace.to_numpy(subspace.sparse(leverage.long_rows(events), 200, 1.0), 200, d), 1.0, d, kind="sparse")
    assert 0.2 < lo and hi < 25 * lo  # heavy tails may stretch all norms together


@pytest.mark.parametrize("p", [1.0, 1.5, 2.0])
def test_embeddings_of_both_engines(events, p):
    log = leverage.long_rows(events)
    a, b = (subspace.to_numpy(subspace.dense(log, 15, p, engine=e), 15, 6) for e in ("arrow", "sql"))
    assert np.allclose(a, b, rtol=1e-8, atol=1e-8 * np.abs(a).max())


def test_rank_deficient_embedding():
    e = np.random.default_rng(0).normal(size=(30, 3))
    p = subspace.conditioner(np.c_[e, e[:, 0]])
    assert np.isfinite(p).all()


def test_coreset_error(events):
    rows = events
    x, w = coreset.to_numpy(coreset.build(leverage.long_rows(rows), rows, "logistic", 1.0, 400, 6, rows.count()))
    err = measures.panel_error(rows, x, w, measures.default_panel(6), "logistic")
    assert np.median(err) < 0.25
    s = leverage.sample_stream(leverage.long_rows(rows), rows.select("row_id"), __import__("lpstream.functions.params", fromlist=["practical"]).practical(60, 1.0, 6), 60)
    back = coreset.refetch(leverage.long_rows(rows), s, 6)
    true = {r.row_id: r.vec for r in rows.collect()}
    assert all(np.allclose(r.vec, true[r.row_id]) for r in back.collect())


def test_offline_modes(events):
    scored = leverage.with_embedding(events, 6, 1.0).persist()
    n = events.count()
    for mode in ("poisson", "priority", "multinomial"):
        s = bl.offline_sample(scored, 100, mode).agg(F.count("*"), F.sum("weight")).first()
        assert 60 <= s[0] <= 140 and 0.3 * n < s[1] < 3 * n, mode
    assert bl.offline_sample(scored, 100, "priority").count() == 100
    reduced = bl.merge_reduce(events, 300, 80).agg(F.count("*"), F.sum("weight")).first()
    assert 50 <= reduced[0] <= 110 and 0.5 * n < reduced[1] < 2 * n


def test_convexity(events):
    x, w = coreset.to_numpy(coreset.build(leverage.long_rows(events), events, "lp", 1.0, 100, 6, events.count()))
    assert measures.convexity_gap(lambda z: solvers.objective(x, w, z, "lp", 1.0), 6) < 1e-9
    e = subspace.to_numpy(subspace.dense(leverage.long_rows(events), 21, 1.0), 21, 6)
    assert measures.convexity_gap(lambda z: float(bl.median_lp(e, z[:, None], 1.0)[0]), 6) > 0


def test_methods_rank_as_reported(spark):
    """Skewed rows, k far below n: the oblivious sketch is worst, the sampler stays near off-line leverage."""
    res = experiments.run(spark, "/root/testdata/sf0.01", "w3", "logistic", sizes=(100,), seeds=range(5), methods=("oblivious", "sampler", "offline"))
    med = {r.method: r.median_ratio for r in experiments.summary(res).collect()}
    assert all(v > 0.999 for v in med.values())
    assert med["sampler"] <= med["oblivious"] * 1.02 and med["sampler"] - 1 <= 4 * (med["offline"] - 1) + 0.1


def test_probit_optimum_takes_all_rows(spark, monkeypatch):
    """Ratios divide by the optimum of all rows, of many rows too."""
    rng = np.random.default_rng(3)
    x = np.c_[np.ones(25_000), rng.normal(size=(25_000, 2))] * rng.choice([-1.0, 1.0], 25_000, p=[0.7, 0.3])[:, None]
    rows = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "row_id long, vec array<double>").persist()
    monkeypatch.setitem(experiments.WORKLOADS, "many", lambda spark, sf, problem: rows)
    got = experiments.run(spark, "", "many", "probit", 2.0, (50,), range(1), ("uniform",)).first().ratio
    few, w = coreset.to_numpy(bl.uniform_rows(rows, 50, len(x), 50))
    one = np.ones(len(x))
    best = solvers.objective(x, one, solvers.solve(x, one, "probit", 2.0), "probit", 2.0)
    assert got == pytest.approx(solvers.objective(x, one, solvers.solve(few, w, "probit", 2.0), "probit", 2.0) / best, rel=1e-7)
