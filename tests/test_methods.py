"""Sketch algebra, hashing, recovery and sampling."""

import math
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from lpstream.functions import params
from lpstream.functions.hashing import FIELD, PRIME, Hashes, coefficients, field_numpy
from lpstream.functions.params import SketchSpec, practical
from lpstream.operators import baselines as bl, diagnostics, measures, recover, sampler, sketch as sk
from lpstream.plans import rules
from lpstream.sources import formats, updates as up

SPEC = SketchSpec(p=1.0, r=300, s=7, d=7)


def cells(df):
    return {(r.rep, r.bucket, r.col_id): r.val for r in df.collect()}


@pytest.fixture(scope="module")
def log(spark, sf):
    return up.orders(spark, sf).persist()


# --- linearity ------------------------------------------------------------------


@pytest.mark.parametrize("p", [1.0, 1.5, 2.0])
def test_sums_differences_and_retractions_are_exact(log, p):
    spec = replace(SPEC, p=p)
    whole = cells(sk.build(log, spec))
    assert cells(sk.merge(*[sk.build(log.filter(F.col("site") == s), spec) for s in range(4)])) == whole
    assert cells(sk.build(log.repartition(13, "delta"), spec)) == whole
    assert cells(sk.build(log, spec, engine="arrow")) == whole
    late = log.filter("ts >= timestamp_ntz'1997-01-01'")
    assert cells(sk.diff(sk.build(log, spec), sk.build(log.filter("ts < timestamp_ntz'1997-01-01'"), spec))) == cells(sk.build(late, spec))
    assert cells(sk.build(log.unionByName(up.retract(log)), spec)) == {}
    assert sk.build(log.limit(0), spec).count() == 0


def test_small_updates_add_up(spark):
    """A thousand updates of 0.001 are one of 1.0; nothing is rounded away before the sum."""
    many = spark.range(1000).selectExpr("5L as row_id", "0 as col_id", "0.001D as delta")
    one = spark.range(1).selectExpr("5L as row_id", "0 as col_id", "1.0D as delta")
    for p in (1.0, 1.5, 2.0):
        spec = SketchSpec(p=p, r=50, s=3, d=1)
        for engine in ("sql", "arrow"):
            a, b = (cells(sk.values(sk.build(x, spec, engine), spec)) for x in (many, one))
            assert a.keys() == b.keys() and all(abs(a[k] / b[k] - 1) < 1e-9 for k in a)


def test_sketch_against_a_float_twin(spark, sf):
    """Cells of the skewed event features equal sums in doubles, in both engines."""
    from lpstream.operators import leverage
    from lpstream.sources import features

    log = leverage.long_rows(features.w3_events(spark, sf)).persist()
    spec = SketchSpec(p=1.0, r=100, s=3, d=6)
    h, want = Hashes(spec.seed), {}
    rows = np.array([(r.row_id, r.col_id, r.delta) for r in log.select("row_id", "col_id", "delta").collect()])
    ids = rows[:, 0].astype(np.int64)
    z = rows[:, 2] / h.uniform_numpy(ids)
    for j in range(spec.s):
        at, sg = h.place_numpy(ids, j, spec.r)
        for b, c, v in zip(at.tolist(), rows[:, 1].astype(int).tolist(), (sg * z).tolist()):
            want[j, b, c] = want.get((j, b, c), 0.0) + v
    scale = max(map(abs, want.values()))
    for engine in ("sql", "arrow"):
        got = cells(sk.values(sk.build(log, spec, engine), spec))
        assert all(abs(got.get(k, 0.0) - v) <= 1e-9 * max(1.0, abs(v)) + 1e-13 * scale for k, v in want.items())


def test_wide_ids_large_sums_and_bad_updates(spark):
    spec = SketchSpec(p=1.0, r=40, s=3, d=2)
    ids = [2**34 + 5, 2**60, 2**60 + 1, FIELD - 1, 2**31 - 1, 2**31 - 2]
    log = spark.createDataFrame([(i, k % 2, v) for k, i in enumerate(ids) for v in (1e9, -3.25, 1e-7)], "row_id long, col_id int, delta double")
    a, b = cells(sk.build(log, spec, "sql")), cells(sk.build(log, spec, "arrow"))
    assert a == b and len(a) >= 2 * len(ids)
    h = Hashes(spec.seed)
    got = log.select("row_id", h.uniform(F.col("row_id")).alias("t"), h.bucket_at(F.col("row_id"), F.lit(1), 40, 3).alias("b"), h.sign_at(F.col("row_id"), F.lit(1), 3).alias("s")).distinct().collect()
    at, sign = h.place_numpy(np.array([r.row_id for r in got]), 1, 40)
    assert [r.b for r in got] == at.tolist() and [r.s for r in got] == sign.tolist() and [r.t for r in got] == h.uniform_numpy(np.array([r.row_id for r in got])).tolist()
    # the field: the same polynomial in plain integers
    coef = coefficients(1, "x")
    for i in ids:
        x, y, u, v = i % PRIME, i // PRIME, coef[0], coef[1]
        for c, e in zip(coef[2::2], coef[3::2]):
            u, v = (u * x - v * y + c) % PRIME, (u * y + v * x + e) % PRIME
        assert tuple(int(p[0]) for p in field_numpy(np.array([i]), coef)) == (u, v)
    large = spark.createDataFrame([(1, 0, 1e24)] * 3, "row_id long, col_id int, delta double")
    val = next(iter(cells(sk.build(large, replace(spec, scale=False), "sql")).values()))
    assert abs(abs(float(val)) / 2**40 / 3e24 - 1) < 1e-12
    for bad in [(1, 2, 1.0), (-1, 0, 1.0), (1, 0, float("nan")), (None, 0, 1.0), (FIELD, 0, 1.0)]:
        one = spark.createDataFrame([bad], "row_id long, col_id int, delta double")
        for engine in ("sql", "arrow"):
            with pytest.raises(Exception, match="invalid update"):
                sk.build(one, spec, engine).collect()


def test_projection_commutes(spark, log):
    m = np.random.default_rng(0).normal(size=(7, 3))
    got = cells(sk.project(sk.build(log, SPEC), SPEC, m))
    coef = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in m])
    long = log.select("row_id", F.posexplode(F.get(coef, F.col("col_id"))).alias("j", "c"), "delta").select("row_id", F.col("j").alias("col_id"), (F.col("c") * F.col("delta")).alias("delta"))
    want = cells(sk.values(sk.build(long, replace(SPEC, d=3)), SPEC))
    scale = max(abs(v) for v in want.values())
    assert all(abs(got.get(k, 0) - v) <= 1e-5 * scale for k, v in want.items())


def test_rewrites(spark, log):
    log_ = rules.Log("a")
    ident = tuple(tuple(float(i == j) for j in range(7)) for i in range(7))
    plan = rules.Sketch(rules.MapRows(rules.Union((log_, rules.Log("b"))), ident))
    best = rules.optimise(plan)
    assert best == rules.Project(rules.Sum((rules.Sketch(log_), rules.Sketch(rules.Log("b")))), ident)
    logs = {"a": log.filter("site < 2"), "b": log.filter("site >= 2")}
    got, want = cells(rules.execute(best, logs, SPEC)), cells(sk.values(sk.build(log, SPEC), SPEC))
    assert got.keys() == want.keys() and all(math.isclose(got[k], v) for k, v in want.items())
    between = rules.Sketch(rules.Log("a", "1997-01-01", "1998-01-01"))
    kept = {"a": {"1997-01-01", "1998-01-01"}}
    assert rules.optimise(between, kept) == rules.Minus(rules.Stored("a", "1998-01-01"), rules.Stored("a", "1997-01-01"))
    prefix = {("a", t): sk.build(logs["a"].filter(F.col("ts") < F.lit(t).cast("timestamp_ntz")), SPEC) for t in kept["a"]}
    assert cells(rules.execute(rules.optimise(between, kept), logs, SPEC, prefix)) == cells(rules.execute(between, logs, SPEC))


def test_store_refuses_other_specifications(spark, log, tmp_path):
    formats.save_sketch(sk.build(log, SPEC), SPEC, str(tmp_path))
    back, spec = formats.load_sketch(spark, str(tmp_path), SPEC)
    assert spec == SPEC and cells(back) == cells(sk.build(log, SPEC))
    with pytest.raises(ValueError):
        formats.load_sketch(spark, str(tmp_path), replace(SPEC, seed=1))


def test_validation(spark):
    bad = spark.createDataFrame([(1, 0, 1.0), (2, 0, float("nan"))], "row_id long, col_id int, delta double")
    with pytest.raises(Exception, match="invalid update"):
        up.validate(bad, 7).collect()


def test_history_to_deltas(spark):
    h = spark.createDataFrame([(1, 0, 5.0, 1), (1, 0, 2.0, 2), (1, 1, 7.0, 1)], "r long, c int, v double, t int")
    assert sorted(r.delta for r in up.from_history(h, "r", "c", "v", ["t"]).collect()) == [-3.0, 5.0, 7.0]


# --- hashing ------------------------------------------------------------------------


def test_polynomial_hashes(spark):
    h = Hashes(42)
    ids = np.arange(15_000)
    t = h.uniform_numpy(ids)
    assert np.allclose(np.quantile(t, [0.1, 0.25, 0.5, 0.75, 0.9]), [0.1, 0.25, 0.5, 0.75, 0.9], atol=0.02) and t.min() > 0
    b = h.bucket_numpy(ids, 2, 500)
    pairs = (np.bincount(b).astype(float) * (np.bincount(b) - 1)).sum() / (15_000 * 14_999)
    assert abs(pairs * 500 - 1) < 0.1
    row = spark.range(100).select(F.col("id").alias("row_id"))
    got = row.select("row_id", h.uniform(F.col("row_id")).alias("t"), h.bucket_at(F.col("row_id"), F.lit(2), 500, 7).alias("b")).orderBy("row_id").collect()
    assert [r.b for r in got] == b[:100].tolist() and np.allclose([r.t for r in got], t[:100])
    fast = Hashes(1, "fast")
    u = [r[0] for r in spark.range(20_000).select(fast.uniform(F.col("id"))).collect()]
    assert abs(np.mean(u) - 0.5) < 0.01 and min(u) > 0 and max(u) <= 1
    signs = [r[0] for r in spark.range(20_000).select(fast.sign_at(F.col("id"), F.lit(0), 7)).collect()]
    assert abs(np.mean(signs)) < 0.03


# --- recovery and sampling -------------------------------------------------------------


def planted_log(spark, n=600, d=7, heavy=5, seed=0):
    rng = np.random.default_rng(seed)
    a = rng.normal(size=(n, d))
    a[:heavy] *= 1000
    rows = [(i, j, float(a[i, j])) for i in range(n) for j in range(d)]
    return a, spark.createDataFrame(rows, "row_id long, col_id int, delta double").persist()


def test_heavy_rows_are_listed_and_close(spark):
    a, log = planted_log(spark)
    eps = 0.5
    spec = SketchSpec(p=1.0, r=1200, s=101, d=7, scale=False, list_multiplier=12 / eps)  # the guarantee needs many repetitions: of 11, most may miss every row in the fixed bucket
    norms = recover.bucket_norms(sk.values(sk.build(log, spec), spec), 1.0).persist()
    found = recover.representatives(recover.candidates(up.ids(log), norms, spec, recover.threshold_value(norms, spec)), sk.build(log, spec), spec).collect()
    assert {r.row_id for r in found} >= set(range(5))
    for r in found:
        err = np.abs(np.array(r.vec) - a[r.row_id]).sum() / np.abs(a[r.row_id]).sum()
        assert err <= eps / 3


def test_pruned_list_equals_plain_medians(spark, log):
    norms = recover.bucket_norms(sk.values(sk.build(log, SPEC), SPEC), 1.0).persist()
    m0 = recover.threshold_value(norms, SPEC)
    plain = {r.row_id: r.est_norm for r in recover.estimates(up.ids(log), norms, SPEC).collect() if r.est_norm >= m0 and r.est_norm > 0}
    assert {r.row_id: r.est_norm for r in recover.candidates(up.ids(log), norms, SPEC, m0).collect()} == plain
    assert {r.row_id: r.est_norm for r in recover.candidates_narrow(up.ids(log), norms, SPEC, m0).collect()} == plain


@pytest.mark.parametrize("p", [1.0, 1.5, 2.0])
def test_sampler_agrees_with_the_exact_twin(spark, log, p):
    k = 50
    spec = practical(4 * k, p, 7)
    got = sampler.sample(sk.build(log, spec).persist(), up.ids(log), spec, k).collect()
    rows = up.exact_rows(log, 7)
    t = sk.hashes(spec).uniform(F.col("row_id"))
    exact = sampler.with_cut(rows.withColumn("norm_p", sampler.norm_of(F.col("vec"), p)).withColumn("scaled", F.col("norm_p") / t), k).collect()
    assert len(got) == k and len({r.row_id for r in got} & {r.row_id for r in exact}) >= 0.85 * k
    alpha = [max(r.norm_p / r.prob for r in s) for s in (got, exact)]
    assert abs(alpha[0] / alpha[1] - 1) < 0.15 and all(r.weight >= 1 and r.prob <= 1 for r in got)


@pytest.mark.parametrize("p", [1.0, 1.5, 2.0])
@pytest.mark.parametrize("seed", [1, 2])
def test_pruned_sample_is_the_whole_lists(spark, log, p, seed):
    """Rows left out by their estimates never belong to the sample, with a conditioning matrix or without."""
    k, r = (5, 60) if seed == 1 else (40, 400)
    matrix = None if seed == 1 else np.random.default_rng(seed).normal(size=(7, 7))
    spec = SketchSpec(p=p, r=r, s=7, d=7, seed=seed)
    c, ids = sk.build(log, spec).persist(), up.ids(log)
    few = sampler.sample(c, ids, spec, k, matrix=matrix)
    every = sampler.with_cut(sampler.scaled_rows(c, ids, spec, k, matrix, floor=0.0), k)
    assert sorted((r.row_id, r.weight) for r in few.collect()) == sorted((r.row_id, r.weight) for r in every.collect())


def test_two_runs_of_few_rows(spark):
    """Fewer rows than the cut's rank: all of them, certain."""
    log = spark.createDataFrame([(i, 0, 1.0 + i) for i in range(20)], "row_id long, col_id int, delta double")
    spec = SketchSpec(p=1.0, r=4000, s=7, d=1)
    other = sampler.second(spec)
    got = sampler.sample_two_run(sk.build(log, spec).persist(), spec, sk.build(log, other).persist(), other, up.ids(log), 40).collect()
    assert len(got) == 20 and all(r.weight == 1 for r in got)


def test_multinomial_and_levels(spark):
    """Draws are binomial with the right mean and spread; levels weigh one in expectation."""
    rows = spark.range(20_000).selectExpr("id as row_id", "array(1.0D) as vec", "cast(1 + id % 4 as double) as score")
    got = bl.offline_sample(rows, 5000, "multinomial").collect()
    draws = [round(r.weight * 5000 * r.norm_p / 50_000, 6) for r in got]
    assert all(d == round(d) for d in draws) and abs(sum(draws) - 5000) < 300 and max(draws) >= 3
    log = spark.range(20_000).selectExpr("id as row_id", "0 as col_id", "1.0D as delta")
    total = bl.oblivious(log, 500, d=1).selectExpr("sum(vec[0] * weight) as s").first()[0]
    assert abs(total / 20_000 - 1) < 0.1


def test_two_run_size(spark, log):
    k, spec = 40, practical(160, 1.0, 7)
    other = sampler.second(spec)
    s = sampler.sample_two_run(sk.build(log, spec).persist(), spec, sk.build(log, other).persist(), other, up.ids(log), k).count()
    assert k <= s <= 2 * k


@pytest.mark.parametrize("rows", [[], [(3, 0, 2.0)], [(3, 0, 2.0), (3, 0, -2.0)], [(i, 0, 1.0) for i in range(5)]])
def test_edge_matrices(spark, rows):
    log = spark.createDataFrame(rows, "row_id long, col_id int, delta double")
    spec = SketchSpec(p=1.0, r=400, s=5, d=1)
    got = sampler.sample(sk.build(log, spec).persist(), up.ids(log), spec, 50).collect()
    live = {i for i in {r[0] for r in rows} if sum(r[2] for r in rows if r[0] == i)}
    assert {r.row_id for r in got} == live and all(r.weight == 1 for r in got)


def test_inclusion_frequencies():
    """Exact norms, many scalings: inclusion reaches the guarantee, the weighted norm is near the total."""
    rng = np.random.default_rng(0)
    norm = rng.pareto(1.5, 150) + 0.1
    k, runs = 20, 400
    hit, totals = np.zeros(150), []
    for _ in range(runs):
        scaled = norm / rng.random(150)
        top = np.argsort(-scaled)[: k + 1]
        alpha = scaled[top[k]]
        hit[top[:k]] += 1
        totals.append(np.maximum(norm[top[:k]], alpha).sum())
    floor = np.minimum(1, k * norm / norm.sum())
    assert (hit / runs >= 0.85 * floor - 3 * np.sqrt(floor * (1 - floor) / runs) - 1e-9).all()
    assert abs(np.mean(totals) / norm.sum() - 1) < 0.05


def test_mixture_probabilities(spark):
    lp = spark.createDataFrame([(1, [1.0], 1.0, 0.5, 2.0), (2, [2.0], 2.0, 1.0, 1.0)], "row_id long, vec array<double>, norm_p double, prob double, weight double")
    uni = spark.createDataFrame([(1, [9.0]), (3, [3.0]), (4, [-1.0])], "row_id long, vec array<double>")
    got = {r.row_id: (r.vec, round(r.prob, 6), r.origin) for r in sampler.mix_uniform(lp, uni, 1, 10).collect()}
    # The cut is 2: the uniform row of norm 3 is certain, and one of norm 1 has probability one half.
    assert got == {1: ([9.0], 0.55, "both"), 2: ([2.0], 1.0, "lp"), 3: ([3.0], 1.0, "uniform"), 4: ([-1.0], 0.55, "uniform")}
    rng = np.random.default_rng(1)
    t = rng.random(200_000)  # one scalar for both parts: the larger probability
    assert abs(((t <= 0.1) | (t <= 0.3)).mean() - 0.3) < 0.01
    a, b = rng.random(200_000) < 0.3, rng.random(200_000) < 0.1
    assert abs((a | b).mean() - (1 - 0.7 * 0.9)) < 0.01


def test_threshold_sandwich(spark):
    a, log = planted_log(spark, n=800)
    rows = up.exact_rows(log, 7).persist()
    hold = 0
    for seed in range(6):
        spec = SketchSpec(p=1.0, r=400, s=101, d=7, scale=False, seed=seed)
        s = diagnostics.sandwich(rows, sk.build(log, spec, engine="arrow").persist(), spec)
        hold += s["lower"] <= s["m0"] * 1.02 and s["m0"] <= s["upper"]
    assert hold >= 5


def test_harmonic_and_truncation(spark, log):
    n = 20_000
    total = diagnostics.harmonic_total(spark, n)
    assert 0.5 < total / (n * math.log(n)) < 3
    assert all(0.3 < r.ratio < 3 for r in diagnostics.harmonic(spark, n).collect() if r.k >= 10)
    t = diagnostics.truncate(up.exact_rows(log, 7), 1.0, 20).agg(F.max("capped"), F.sum("capped")).first()
    assert t[0] <= t[1] / 20 * 1.001


def test_norm_sketches(spark, log):
    exact = up.exact_rows(log, 7)
    two = exact.agg(F.sum(sampler.norm_of(F.col("vec"), 2.0))).first()[0]
    one = exact.agg(F.sum(sampler.norm_of(F.col("vec"), 1.0))).first()[0]
    assert 0.5 < bl.ams_norm(log).first()[0] / two < 2
    assert 0.6 < bl.stable_norm(log, 1.0).first()[0] / one < 1.6
    p = 1.5
    mid = exact.agg(F.sum(sampler.norm_of(F.col("vec"), p))).first()[0] ** (1 / p)
    assert 0.6 < bl.stable_norm(log, p).first()[0] / mid < 1.6


def test_measures(spark, log):
    spec = practical(200, 1.0, 7)
    s = sampler.sample(sk.build(log, spec).persist(), up.ids(log), spec, 100).persist()
    exact = up.exact_rows(log, 7)
    err = measures.summary(measures.row_error(s, exact, 1.0)).first()
    assert err.n == 100 and err.median_error < 0.1 and abs(err.median_norm_ratio - 1) < 0.1
    assert abs(measures.norm_ratio(s, exact, 1.0).first()[0] - 1) < 0.5
    alpha = s.agg(F.max(F.col("norm_p") / F.col("prob"))).first()[0]
    assert measures.weight_error(s, exact, 1.0, float(alpha)).agg(F.expr("percentile(abs(ratio - 1), 0.5)")).first()[0] < 0.1


# --- calculators ---------------------------------------------------------------------


def test_sizes():
    s = params.sampler(None, 0.05, 0.05, 60_000, 1.0)
    assert s["k"] == 877 and 4.4e8 < s["r"] < 4.6e8 and 3.3e6 < s["s"] < 3.5e6
    h, g = params.heavy_rows(1 / (4 * 877 * math.log(60_000)), 0.05 / 6, 0.05 / 6, 60_000, 1.0), s
    assert math.isclose(h["r"], g["r"], rel_tol=1e-9) and math.isclose(h["s"], g["s"], rel_tol=1e-9)
    assert params.conditioning(2.0, 10)["power"] == 10 and params.conditioning(1.0, 10, "spanning")["power"] < params.conditioning(1.0, 10)["power"]
    with pytest.raises(ValueError):
        params.check_p(3)
    assert params.check_p(3, allow_large_p=True) == 3.0 and params.large_p_rows(10**6, 4) > 1000
    with pytest.raises(ValueError):
        SketchSpec(s=4)


def test_cut_is_exact(spark):
    from lpstream.operators.baselines import cap_level

    v = np.random.default_rng(3).pareto(0.7, 500) + 0.01
    rows = spark.createDataFrame([(float(x),) for x in v], "norm_p double")
    for k in (1, 7, 100, 499):
        assert np.minimum(1, v / cap_level(rows, k)).sum() == pytest.approx(k, rel=1e-11)
    assert cap_level(rows, 500) == 0.0


def test_conditioner_has_positive_diagonal():
    from lpstream.operators import subspace

    e = np.random.default_rng(4).normal(size=(30, 4)) * [1, 10, 0.1, 5]
    m = subspace.conditioner(e)
    assert (np.diag(m) > 0).all() and np.allclose((e @ m).T @ (e @ m), np.eye(4))


def test_beta_of_pinned_fits(spark):
    from lpstream.operators import measures

    a = np.array([[1.0, 0.0], [0.0, 2.0], [1.0, 1.0]])
    u = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(a)], "row_id long, vec array<double>")
    grid = np.linspace(-1, 1, 2001)
    least = min(np.abs(a @ z).sum() / np.abs(z).max() for g in grid for z in (np.array([1.0, g]), np.array([g, 1.0])))
    assert max(measures.pinned_fits(u, 2)) == pytest.approx(1 / least, rel=1e-3)


def test_inclusion_bands(spark):
    from lpstream.operators import measures

    norms = spark.createDataFrame([(1, 6.0), (2, 1.0), (3, 1.0), (4, 0.0)], "row_id long, norm_p double")
    drawn = spark.createDataFrame([(1,), (1,), (2,)], "row_id long")
    got = {r.band: (r.rows, r.frequency, r.floor) for r in measures.inclusion_bands(drawn, norms, 1, 2).collect()}
    assert got == {-1: (1, 1.0, 0.75), -3: (2, 0.25, 0.125)}
