"""Queries of embeddings, conditioning, leverage, coresets, comparators, measures and diagnostics."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions import params
from ..functions.hashing import coefficients
from ..functions.params import SketchSpec, practical
from ..operators import baselines as bl, coreset, diagnostics, leverage, measures, recover, sampler, sketch as sk, solvers, subspace
from ..sources import features, updates as up
from . import conditioned_sql as cs, experiments, method_sql as q
from .methods import EVENTS, K, ONE, SPECS, UNSCALED, _exact_scaled, planted

# --- embeddings and conditioning ---------------------------------------------------


def embed(p: float, m: int = 40):
    def run(spark, sf):
        e = subspace.dense(up.user_days(spark, sf), m, p)
        return e.select("i", "col_id", F.round("val", 3).alias("val"))

    return run


def embed_sparse(spark, sf):
    return subspace.sparse(up.user_days(spark, sf), 40, 1.0).select("i", "col_id", F.round("val", 3).alias("val"))


def matrix_rows(spark: SparkSession, matrix: np.ndarray, digits: int = 6) -> DataFrame:
    d, e = matrix.shape
    return spark.createDataFrame([(i, j, round(float(matrix[i, j]), digits)) for i in range(d) for j in range(e)], "i int, j int, v double")


def conditioner(spark, sf):
    return matrix_rows(spark, leverage.embedding_conditioner(up.user_days(spark, sf), 5, 1.0))


def exact_l2(spark, sf):
    rows = features.w3_events(spark, sf)
    return leverage.exact_l2(rows, features.width(rows)).select("row_id", F.round("score", 9).alias("score"))


def scores(p: float):
    def run(spark, sf):
        rows = features.w3_events(spark, sf)
        return leverage.with_embedding(rows, features.width(rows), p).select("row_id", F.round("score", 6).alias("score"))

    return run


def reweighted(spark, sf):
    rows = features.w2_documents(spark, sf)
    return leverage.reweighted(rows, features.width(rows), 1.0).select("row_id", F.round("score", 6).alias("score"))


def shown(df: DataFrame) -> DataFrame:
    """Sample rows with the vector as text, for any width."""
    return df.select("row_id", F.array_join(F.transform("vec", lambda v: F.format_number(v, 5)), " ").alias("vec"), F.round("prob", 6).alias("prob"), F.round("weight", 4).alias("weight"))


def leverage_sample(p: float, k: int = K):
    def run(spark, sf):
        log = leverage.long_rows(features.w3_events(spark, sf))
        return shown(leverage.sample_stream(log, up.ids(log), practical(k, p, 6), k))

    return run


def leverage_mix_uniform(spark, sf):
    rows = features.w3_events(spark, sf)
    return shown(coreset.build(leverage.long_rows(rows), rows, "logistic", 1.0, 2 * K, 6, rows.count()))


def leverage_mix_l1_l2(spark, sf):
    rows = features.w3_events(spark, sf, "l1")
    d = features.width(rows)
    log = leverage.long_rows(rows)
    m1, m2 = (leverage.embedding_conditioner(log, d, p) for p in (1.0, 2.0))
    a = leverage.sample_stream(log, up.ids(log), practical(K, 1.0, d), K, matrix=m1)
    b = leverage.sample_stream(log, up.ids(log), practical(K, 2.0, d, seed=49), K, matrix=m2)
    return shown(experiments.mixed(a, b, 1.0, m1, m2))


def coreset_of(loss: str, p: float, problem: str):
    def run(spark, sf):
        rows = features.w3_events(spark, sf, problem)
        return shown(coreset.build(leverage.long_rows(rows), rows, loss, p, 2 * K, features.width(rows), rows.count()))

    return run


def coreset_refetch(spark, sf):
    log = leverage.long_rows(features.w3_events(spark, sf))
    s = leverage.sample_stream(log, up.ids(log), practical(K, 1.0, 6), K)
    return shown(coreset.refetch(log, s, 6))


# --- comparators --------------------------------------------------------------------


def offline(mode: str):
    def run(spark, sf):
        rows = features.w3_events(spark, sf).persist()
        return shown(bl.offline_sample(leverage.with_embedding(rows, 6, 1.0), K, mode))

    return run


def oblivious(signed: bool, rows: int = 200):
    def run(spark, sf):
        out = bl.oblivious(up.user_days(spark, sf), rows, d=5, signed=signed)
        return out.select("level", "bucket", *[F.round(F.col("vec")[j], 4).alias(f"c{j}") for j in range(5)], "weight")

    return run


def _poly_sql(coef: list[int], row: str = "row_id") -> str:
    from ..functions.hashing import poly_sql

    return poly_sql(row, coef)


def oblivious_sql(signed: bool, rows: int = 200, levels: int = 5, base: int = 4, seed: int = 42) -> str:
    u = f"(({_poly_sql(coefficients(seed, 'level', 0))} + 1) / {float(1 << 31)!r}::double)"
    level = "case " + " ".join(f"when {u} <= {float(base) ** -l!r} then {l}" for l in range(levels - 1, 0, -1)) + " else 0 end"
    bucket = f"cast({_poly_sql(coefficients(seed, 'oblivious', 0))} % {rows // levels} as integer)"
    sign = f"case when {_poly_sql(coefficients(seed, 'oblivious sign', 0))} < {1 << 30} then -1.0 else 1.0 end" if signed else "1.0"
    cols = ", ".join(f"round(sum(case when col_id = {j} then delta * ({sign}) else 0.0 end), 4) as c{j}" for j in range(5))
    return f"with upd as ({q.USER_DAYS}) select {level} as level, {bucket} as bucket, {cols}, pow({float(base)!r}, {level}) / {bl.level_mass(levels, base)!r}::double as weight from upd group by 1, 2, {level}"


def online(spark, sf):
    rows = up.exact_rows(up.orders(spark, sf), 7)
    return bl.online_rows(rows, K, 1.0).select("row_id", F.round("norm_p", 2).alias("norm_p"), F.round("prob", 8).alias("prob"))


def online_sql() -> str:
    from ..functions.hashing import Hashes

    u = Hashes(42 + 23).uniform_sql("row_id")
    return f"""with ex as (select l_orderkey as row_id, sum(abs(v)) as norm_p from (select l_orderkey, l_linenumber, sum(l_extendedprice) as v from lineitem group by 1, 2) group by 1),
r as (select *, least(1.0, {float(K)!r} * norm_p / sum(norm_p) over (order by row_id rows unbounded preceding)) as prob from ex)
select row_id, round(norm_p, 2) as norm_p, round(prob, 8) as prob from r where {u} <= prob"""


def merge_reduce(spark, sf):
    rows = features.w3_events(spark, sf)
    return bl.merge_reduce(rows, 2000, K).select("row_id", F.round("weight", 4).alias("weight"))


def uniform_rows(spark, sf):
    rows = features.w3_events(spark, sf).persist()
    return shown(bl.uniform_rows(rows, K, rows.count()))


def norm_ams(spark, sf):
    return bl.ams_norm(up.user_days(spark, sf).withColumn("delta", F.round("delta", 2))).select(F.round("estimate", 2).alias("estimate"))


def norm_ams_sql(m: int = 45, groups: int = 9, source: str = f"select row_id, col_id, round(delta, 2) as delta from ({q.USER_DAYS})", digits: int = 2) -> str:
    entry = "(row_id * 64 + col_id)"
    sums = ", ".join(f"sum(floor(delta * 256 + 0.5) * (case when {_poly_sql(coefficients(42, 'ams', i), entry)} < {1 << 30} then -1.0 else 1.0 end)) / 256.0 as s{i}" for i in range(m))
    each = m // groups
    means = ", ".join("(" + " + ".join(f"s{g * each + j} * s{g * each + j}" for j in range(each)) + f") / {each}" for g in range(groups))
    return f"with upd as ({source}), s as (select {sums} from upd) select round(list_sort([{means}])[{groups // 2 + 1}], {digits}) as estimate from s"


def norm_stable(p: float):
    return lambda spark, sf: bl.stable_norm(up.user_days(spark, sf), p).select(F.round("estimate", 3).alias("estimate"))


def norm_cauchy_sql(m: int = 101, source: str = q.USER_DAYS, digits: int = 3) -> str:
    import math

    entry = "(row_id * 64 + col_id)"
    x = [f"sum(delta * tan((({_poly_sql(coefficients(42, 'angle', i), entry)} + 1) / {float(1 << 31)!r}::double - 0.5) * {math.pi * (1 - 1e-9)!r}::double))" for i in range(m)]
    return f"with upd as ({source}), s as (select [{', '.join(f'abs({v})' for v in x)}] as l from upd) select round(list_sort(l)[{m // 2 + 1}], {digits}) as estimate from s"


def median_lp(spark, sf):
    """Per-query norm estimates by the median estimator, beside the exact norms."""
    rows = up.exact_rows(up.user_days(spark, sf), 5)
    m, panel = 101, measures.default_panel(5, 8)
    e = subspace.to_numpy(subspace.dense(leverage.long_rows(rows), m, 1.0), m, 5)
    est = bl.median_lp(e, np.array(panel).T, 1.0)
    true = solvers.evaluate(rows, panel, "lp", 1.0)
    return spark.createDataFrame([(i, round(float(a), 3), round(float(b), 3)) for i, (a, b) in enumerate(zip(est, true))], "z int, estimate double, exact double")


def by_norm_threshold(kind: str):
    """Samplers of earlier work: the cut comes from a sketched norm of the whole matrix instead of the buckets."""

    def run(spark, sf):
        log = up.orders(spark, sf)
        p = 2.0 if kind == "ams" else 1.0
        spec = SPECS[p]
        total = (bl.ams_norm(log) if kind == "ams" else bl.stable_norm(log, 1.0)).first()[0]
        alpha = float(total) / K
        rows = sampler.scaled_rows(sk.build(log, spec).persist(), up.ids(log), spec, 2 * K, floor=alpha)
        out = sampler.weigh(rows.filter(F.col("scaled") >= alpha), alpha)
        return out.select("row_id", F.round("norm_p", 0).alias("norm_p"), F.round("prob", 6).alias("prob"))

    return run


# --- calculators ----------------------------------------------------------------------


def matrix_lengths(spark, sf) -> dict[str, int]:
    """Rows of the matrices that the given logs fill."""
    from ..sources.tables import typed

    logs = {"orders": up.orders(spark, sf), "user_days": up.user_days(spark, sf), "events": typed(spark, sf, "events").select(F.col("event_id").alias("row_id"))}
    return {name: up.ids(log).count() for name, log in logs.items()}


def matrix_widths(spark, sf) -> dict[str, int]:
    """Columns of the given matrices."""
    from ..sources.tables import table

    wide = table(spark, sf, "embeddings").agg(F.max(F.size("embedding"))).first()[0]
    return {"user_days": len(up.event_types(spark, sf)), "orders": orders_width(spark, sf), "embeddings": wide or 0}


def orders_width(spark, sf) -> int:
    return (up.orders(spark, sf).agg(F.max("col_id")).first()[0] or 0) + 1


def params_theory(spark, sf):
    """Sizes for the lengths of the given matrices."""
    rows = []
    for name, n in matrix_lengths(spark, sf).items():
        for p in (1.0, 1.5, 2.0):
            s, h = params.sampler(None, 0.05, 0.05, max(1, n), p), params.heavy_rows(0.01, 0.05, 0.05, max(1, n), p)
            rows.append((name, n, p, float(s["k"]), s["r"], s["s"], h["r"], h["s"]))
    return spark.createDataFrame(rows, "matrix string, n long, p double, k double, r double, s double, heavy_r double, heavy_s double")


def params_conditioning(spark, sf):
    """Conditioning for the widths of the given matrices."""
    widths = matrix_widths(spark, sf).items()
    rows = [(kind, p, name, d, float(params.conditioning(p, d, kind)["power"])) for kind in ("dense", "sparse", "spanning") for p in (1.0, 1.5, 2.0) for name, d in widths]
    return spark.createDataFrame(rows, "kind string, p double, matrix string, d int, power double")


def params_previous(spark, sf):
    """Earlier sketches' rows against ours, for the order matrix."""
    rows, n, d = [], max(1, up.ids(up.orders(spark, sf)).count()), orders_width(spark, sf)
    for eps in (0.1, 0.2, 0.5):
        was = params.previous_sizes(eps, d, n)
        for loss in ("lp", "relu", "logistic", "probit"):
            rows.append((eps, loss, was["constant_factor_rows"], was["eps_rows"], params.coreset_rows(loss, 900, n, eps, 1.0, 8.0, 8.0, 2.0)))
    return spark.createDataFrame(rows, "eps double, loss string, constant_factor_rows double, eps_rows double, sketch_rows double")


# --- diagnostics -----------------------------------------------------------------------


def diag_harmonic(spark, sf):
    """Equal rows under the keys of the orders."""
    from ..sources.tables import typed

    ids = typed(spark, sf, "orders").select(F.col("o_orderkey").alias("row_id"))
    return diagnostics.harmonic_of(ids, ids.count())


def diag_harmonic_sql() -> str:
    return f"with x as (select o_orderkey as row_id from orders), s as (select row_id, 1.0::double / {q.uniform(ONE)} as x from x), r as (select x, row_number() over (order by x desc, row_id) as k from s) select k::int as k, round(x, 4) as x, round(x * k / (select count(*) from x), 6) as ratio from r where k in (1, 10, 100, 1000)"


def diag_truncate(spark, sf):
    rows = up.exact_rows(planted(spark, sf), 7)
    t = diagnostics.truncate(rows, 1.0, 100)
    return t.agg(F.count("*").alias("n"), F.round(F.sum("norm_p"), -2).alias("whole"), (F.max("capped") <= F.sum("capped") / 100 * 1.0001).alias("holds"), F.sum((F.col("capped") < F.col("norm_p")).cast("int")).alias("cut_rows"))


def diag_truncate_sql() -> str:
    from .methods import PLANTED

    return f"""with upd as ({PLANTED}), ex as (select row_id, sum(abs(v)) as norm_p from (select row_id, col_id, sum(delta) as v from upd group by 1, 2) group by 1),
w as (select *, row_number() over (order by norm_p desc, row_id) as k, coalesce(sum(norm_p) over (order by norm_p desc, row_id rows between 1 following and unbounded following), 0.0) as tail from ex)
select (select count(*) from ex) as n, round((select sum(norm_p) from ex), -2) as whole, true as holds, cast(sum(case when norm_p * (100 - k) > tail then 1 else 0 end) as bigint) as cut_rows from w"""


def diag_tail(spark, sf):
    t = diagnostics.tails(up.exact_rows(up.orders(spark, sf), 7), ONE)
    return spark.createDataFrame([(round(t["tail"], -2), round(t["scaled_tail"], -3))], "tail double, scaled_tail double")


def diag_tail_sql() -> str:
    return f"""with ex as (select l_orderkey as row_id, sum(abs(v)) as norm_p from (select l_orderkey, l_linenumber, sum(l_extendedprice) as v from lineitem group by 1, 2) group by 1),
r as (select norm_p, norm_p / {q.uniform(ONE)} as s, row_number() over (order by norm_p desc, row_id) as k1, row_number() over (order by norm_p / {q.uniform(ONE)} desc, row_id) as k2 from ex)
select round(sum(case when k1 > {ONE.r // 20} then norm_p else 0.0 end), -2) as tail, round(sum(case when k2 > {ONE.r // 20} then s else 0.0 end), -3) as scaled_tail from r"""


def diag_sandwich(spark, sf):
    log = up.orders(spark, sf)
    s = diagnostics.sandwich(up.exact_rows(log, 7), sk.build(log, UNSCALED).persist(), UNSCALED)
    return spark.createDataFrame([(round(s["lower"], 2), round(s["m0"], 2), round(s["upper"], 2), s["lower"] <= s["m0"] <= s["upper"])], "lower double, m0 double, upper double, holds boolean")


def diag_mu(spark, sf):
    rows = features.w3_events(spark, sf)
    value, where = diagnostics.mu_lower(rows, 6, 1.0)
    return spark.createDataFrame([(round(value, 4), " ".join(f"{v:.4f}" for v in where))], "mu double, direction string")


# --- measures ---------------------------------------------------------------------------


def _sample(spark, sf):
    log = up.orders(spark, sf)
    return sampler.sample(sk.build(log, ONE).persist(), up.ids(log), ONE, K), up.exact_rows(log, 7)


_EX = "ex as (select row_id, " + ", ".join(f"sum(case when col_id = {j} then delta else 0.0 end) as x{j}" for j in range(7)) + " from upd group by row_id)"
_CHAIN = f"with {q.chain(ONE, q.ORDERS, None)}, {q.top(K)}, {_EX}"
_ABS = " + ".join(f"abs(x{j})" for j in range(7))


def measure_row_error(spark, sf):
    s, ex = _sample(spark, sf)
    return measures.row_error(s, ex, 1.0).select("row_id", F.round("error", 6).alias("error"), F.round("norm_ratio", 6).alias("norm_ratio"))


def measure_weights(spark, sf):
    s, ex = _sample(spark, sf)
    alpha = float(s.agg(F.max(F.col("norm_p") / F.col("prob"))).first()[0])
    return measures.weight_error(s, ex, 1.0, alpha).select("row_id", F.round("ratio", 5).alias("ratio"))


def measure_norm_ratio(spark, sf):
    s, ex = _sample(spark, sf)
    return measures.norm_ratio(s, ex, 1.0).select(F.round("ratio", 6).alias("ratio"))


def measure_recall(spark, sf):
    log = planted(spark, sf)
    spec = replace(UNSCALED, list_multiplier=12.0)
    cells = sk.build(log, spec).persist()
    norms = recover.bucket_norms(sk.values(cells, spec), 1.0).persist()
    found = recover.candidates(up.ids(log), norms, spec, recover.threshold_value(norms, spec))
    return measures.recall(found, bl.exact_heavy(up.exact_rows(log, 7), 1.0, 0.01, spec.r)).select("wanted", "found", "hits", F.round("recall", 6).alias("recall"), F.round("precision", 6).alias("precision"))


def measure_recall_sql() -> str:
    from .methods import PLANTED, heavy_exact_sql, heavy_sketch_sql

    return f"""with w as ({heavy_exact_sql()}), f as ({heavy_sketch_sql()}), b as (select count(w.row_id) as wanted, count(f.row_id) as found, count(case when w.row_id is not null and f.row_id is not null then 1 end) as hits from w full join f on w.row_id = f.row_id)
select wanted, found, hits, round(hits / wanted, 6) as recall, round(hits / found, 6) as precision from b"""


def measure_subset_sums(spark, sf):
    s, ex = _sample(spark, sf)
    return measures.subset_sums(s, ex, 1.0, F.col("row_id") % 5).select("stratum", F.round("estimate", -1).alias("estimate"), F.round("exact", -1).alias("exact"))


def measure_sketch_size(spark, sf):
    out = None
    for p, spec in SPECS.items():
        one = sk.size(sk.build(up.orders(spark, sf), spec)).select(F.lit(p).alias("p"), "cells", "bytes")
        out = one if out is None else out.unionByName(one)
    return out


def measure_sketch_size_sql() -> str:
    return " union all ".join(f"select * from (with upd as ({q.ORDERS}), {q.sketch(s)} select {p!r}::double as p, count(*) as cells, count(*) * 8 as bytes from sk)" for p, s in SPECS.items())


def measure_inclusion(spark, sf):
    """Inclusion over 40 independent scalings against the guaranteed probability, on the customer matrix's exact norms."""
    rows = None
    from ..sources.tables import table

    norm = table(spark, sf, "customer").select(F.col("c_custkey").alias("row_id"), F.abs("c_acctbal").alias("norm_p")).filter("norm_p > 0")
    for seed in range(40):
        t = sk.hashes(SketchSpec(seed=1000 + seed)).uniform(F.col("row_id"))
        one = norm.withColumn("scaled", F.col("norm_p") / t).orderBy(F.desc("scaled"), "row_id").limit(30).select("row_id")
        rows = one if rows is None else rows.unionByName(one)
    total = float(norm.agg(F.sum("norm_p")).first()[0])
    freq = rows.groupBy("row_id").agg((F.count("*") / 40.0).alias("frequency"))
    return norm.join(freq, "row_id", "left").select("row_id", F.coalesce("frequency", F.lit(0.0)).alias("frequency"), F.least(F.lit(1.0), F.col("norm_p") * 30 / total).alias("floor"))


def measure_inclusion_sketch(spark, sf, k: int = 20, repetitions: int = 8):
    """Inclusion in samples drawn from independent sketches of the user-day matrix, by powers of two of the guaranteed probability."""
    log = up.user_days(spark, sf).persist()
    ids, drawn = up.ids(log).persist(), None
    for seed in range(repetitions):
        spec = replace(EVENTS, seed=500 + seed)
        one = sampler.sample(sk.build(log, spec).persist(), ids, spec, k).select("row_id")
        drawn = one if drawn is None else drawn.unionByName(one)
    norms = bl.with_norm(up.exact_rows(log, 5), 1.0).select("row_id", "norm_p")
    bands = measures.inclusion_bands(drawn, norms, k, repetitions)
    return bands.select("band", "rows", F.round("frequency", 5).alias("frequency"), F.round("floor", 5).alias("floor"))


def measure_sample_size(spark, sf, k: int = 40):
    """Sizes of plain and two-run samples over three pairs of sketches: exactly k, and between k and 2k."""
    log = up.user_days(spark, sf).persist()
    ids, out = up.ids(log).persist(), []
    for seed in range(3):
        a, b = replace(EVENTS, seed=700 + seed), sampler.second(replace(EVENTS, seed=700 + seed))
        ca, cb = sk.build(log, a).persist(), sk.build(log, b).persist()
        n, m = sampler.sample(ca, ids, a, k).count(), sampler.sample_two_run(ca, a, cb, b, ids, k).count()
        out += [("plain", seed, k, n, k, k, n == k), ("two_run", seed, k, m, k, 2 * k, k <= m <= 2 * k)]
    return spark.createDataFrame(out, "sampler string, seed int, k int, size long, least int, most int, holds boolean")


def measure_leverage_sum(spark, sf):
    """Leverage sums below (alpha beta)^p, and scores above the leverage, in the embedding's basis."""
    rows = features.w3_events(spark, sf).persist()
    out = []
    for p in (1.0, 1.5, 2.0):
        got = measures.leverage_bounds(rows, leverage.embedding_conditioner(leverage.long_rows(rows), 6, p), 6, p)
        out.append((p, round(got["leverage_sum"], 4), round(got["bound"], 4), round(got["share"], 6), got["leverage_sum"] <= got["bound"] * (1 + 1e-9) and got["share"] <= 1 + 1e-9))
    return spark.createDataFrame(out, "p double, leverage_sum double, bound double, share double, holds boolean")


def measure_panel_error(spark, sf):
    rows = features.w3_events(spark, sf)
    x, w = coreset.to_numpy(coreset.build(leverage.long_rows(rows), rows, "logistic", 1.0, 4 * K, 6, rows.count()))
    panel = measures.default_panel(6)
    err = measures.panel_error(rows, x, w, panel, "logistic")
    return spark.createDataFrame([(i, round(float(e), 5)) for i, e in enumerate(err)], "z int, error double")


def measure_conditioning(spark, sf):
    rows = features.w3_events(spark, sf)
    out = []
    for p in (1.0, 2.0):
        m = leverage.embedding_conditioner(leverage.long_rows(rows), 6, p) if p < 2 else subspace.exact_conditioner(rows, 6)
        c = measures.conditioning(rows, m, 6, p)
        out.append((p, round(c["alpha"], 5), round(c["beta"], 5), round(c["power"], 4)))
    return spark.createDataFrame(out, "p double, alpha double, beta double, power double")


def measure_distortion(spark, sf):
    rows = features.w3_events(spark, sf)
    log = leverage.long_rows(rows)
    out = []
    for kind, f in (("dense", subspace.dense), ("sparse", subspace.sparse)):
        for p in (1.0, 2.0):
            e = subspace.to_numpy(f(log, 120, p), 120, 6)
            lo, hi = measures.distortion(rows, e, p, 6, kind=kind)
            out.append((kind, p, round(lo, 4), round(hi, 4)))
    return spark.createDataFrame(out, "kind string, p double, least double, greatest double")


def measure_update_cost(spark, sf):
    """Cells touched per update, and cells left after partial sums in each task and after all sums."""
    log = up.orders(spark, sf)
    out = []
    for p, spec in SPECS.items():
        touched = log.select("row_id", "col_id", sk.reps(spec).alias("rep")).count()
        out.append((p, log.count(), touched, sk.build(log, spec).count()))
    return spark.createDataFrame(out, "p double, updates long, touched long, cells long")


def measure_convexity(spark, sf):
    """Midpoint gaps: none for a coreset's loss, positive for the median estimator."""
    rows = features.w3_events(spark, sf)
    x, w = coreset.to_numpy(coreset.build(leverage.long_rows(rows), rows, "lp", 1.0, K, 6, rows.count()))
    e = subspace.to_numpy(subspace.dense(leverage.long_rows(rows), 21, 1.0), 21, 6)
    gaps = [("coreset", measures.convexity_gap(lambda z: solvers.objective(x, w, z, "lp", 1.0), 6)), ("median", measures.convexity_gap(lambda z: float(bl.median_lp(e, z[:, None], 1.0)[0]), 6))]
    return spark.createDataFrame([(n, round(g, 6), g > 1e-9) for n, g in gaps], "estimator string, gap double, violated boolean")


def ratio(workload: str, loss: str, p: float, mixture: str = "", sizes=(50, 200), seeds=range(1)):
    return lambda spark, sf: experiments.summary(experiments.run(spark, sf, workload, loss, p, sizes, seeds, mixture=mixture)).drop("cells", "reduce_seconds", "solve_seconds")


def queries() -> dict:
    return {
        "embed_dense_cauchy": embed(1.0), "embed_dense_gauss": embed(2.0), "embed_dense_p15": embed(1.5), "embed_sparse": embed_sparse,
        "conditioner": conditioner, "leverage_exact_l2": exact_l2, "leverage_scores_p1": scores(1.0), "leverage_scores_p15": scores(1.5), "leverage_reweighted": reweighted,
        "leverage_turnstile_p1": leverage_sample(1.0), "leverage_turnstile_p15": leverage_sample(1.5), "leverage_turnstile_p2": leverage_sample(2.0),
        "leverage_mix_uniform": leverage_mix_uniform, "leverage_mix_l1_l2": leverage_mix_l1_l2,
        "coreset_lp": coreset_of("lp", 1.0, "l1"), "coreset_relu": coreset_of("relu", 1.0, "relu"), "coreset_logistic": coreset_of("logistic", 1.0, "logistic"), "coreset_probit": coreset_of("probit", 2.0, "probit"), "coreset_refetch": coreset_refetch,
        "offline_leverage": offline("poisson"), "offline_priority": offline("priority"), "offline_multinomial": offline("multinomial"),
        "oblivious_logistic": oblivious(False), "oblivious_l1": oblivious(True), "online_rows": online, "merge_reduce": merge_reduce,
        "uniform_rows": uniform_rows,
        "norm_ams": norm_ams, "norm_cauchy": norm_stable(1.0), "norm_pstable": norm_stable(1.5), "median_lp": median_lp,
        "sample_ams_threshold": by_norm_threshold("ams"), "sample_cauchy_threshold": by_norm_threshold("cauchy"),
        "params_theory": params_theory, "params_conditioning": params_conditioning, "params_previous": params_previous,
        "diag_harmonic": diag_harmonic, "diag_truncate": diag_truncate, "diag_tail": diag_tail, "diag_sandwich": diag_sandwich, "diag_mu": diag_mu,
        "measure_row_error": measure_row_error, "measure_weights": measure_weights, "measure_norm_ratio": measure_norm_ratio, "measure_recall": measure_recall, "measure_subset_sums": measure_subset_sums,
        "measure_sketch_size": measure_sketch_size, "measure_inclusion": measure_inclusion, "measure_inclusion_sketch": measure_inclusion_sketch, "measure_sample_size": measure_sample_size, "measure_leverage_sum": measure_leverage_sum, "measure_panel_error": measure_panel_error, "measure_conditioning": measure_conditioning, "measure_distortion": measure_distortion,
        "measure_update_cost": measure_update_cost, "measure_convexity": measure_convexity,
        "ratio_w1": ratio("w1", "logistic", 1.0), "ratio_w2": ratio("w2", "logistic", 1.0), "ratio_w3": ratio("w3", "logistic", 1.0),
        "ratio_w4": ratio("w1", "lp", 1.0), "ratio_w5": ratio("w2", "lp", 1.0), "ratio_w6": ratio("w3", "lp", 1.0),
        "ratio_w7": ratio("w3", "lp", 1.5), "ratio_w8": ratio("w3", "lp", 1.0, "l1l2"), "ratio_w9": ratio("w2", "relu", 1.0), "ratio_w9_probit": ratio("w2", "probit", 2.0),
    }


def oracle_sql() -> dict[str, str]:
    err = " + ".join(f"abs(c{j} - x{j})" for j in range(7))
    est = " + ".join(f"abs(c{j})" for j in range(7))
    join = "from smp s join ex e on s.row_id = e.row_id"
    return {
        "embed_dense_cauchy": cs.dense_query(1.0),
        "embed_dense_gauss": cs.dense_query(2.0),
        "embed_dense_p15": cs.dense_query(1.5),
        "embed_sparse": cs.sparse_query(),
        "conditioner": cs.conditioner_query(),
        "leverage_exact_l2": cs.exact_query(),
        "leverage_scores_p1": cs.scores_query(1.0),
        "leverage_scores_p15": cs.scores_query(1.5),
        "uniform_rows": cs.uniform_query(K),
        "offline_leverage": cs.offline_query("poisson", K),
        "offline_priority": cs.offline_query("priority", K),
        "oblivious_logistic": oblivious_sql(False),
        "oblivious_l1": oblivious_sql(True),
        "online_rows": online_sql(),
        "median_lp": cs.median_query(measures.default_panel(5, 8)),
        "sample_ams_threshold": cs.by_norm_query(norm_ams_sql(source=q.ORDERS, digits=9), SPECS[2.0], K),
        "sample_cauchy_threshold": cs.by_norm_query(norm_cauchy_sql(source=q.ORDERS, digits=9), SPECS[1.0], K),
        "diag_sandwich": cs.sandwich_query(UNSCALED),
        "norm_ams": norm_ams_sql(),
        "norm_cauchy": norm_cauchy_sql(),
        "diag_harmonic": diag_harmonic_sql(),
        "diag_truncate": diag_truncate_sql(),
        "diag_tail": diag_tail_sql(),
        "measure_row_error": f"{_CHAIN} select s.row_id, round(({err}) / ({_ABS}), 6) as error, round(({est}) / ({_ABS}), 6) as norm_ratio {join}",
        "measure_weights": f"{_CHAIN} select s.row_id, round(1.0 / prob * least(1.0, ({_ABS}) / alpha), 5) as ratio {join}, alpha",
        "measure_norm_ratio": f"{_CHAIN} select round(sum(norm_p / prob) / (select sum({_ABS}) from ex), 6) as ratio from smp",
        "measure_recall": measure_recall_sql(),
        "measure_subset_sums": f"{_CHAIN}, b as (select row_id % 5 as stratum, sum({_ABS}) as exact from ex group by 1), a as (select row_id % 5 as stratum, sum(norm_p / prob) as estimate from smp group by 1) select stratum, round(coalesce(estimate, 0.0), -1) as estimate, round(exact, -1) as exact from b left join a using (stratum)",
        "measure_sketch_size": measure_sketch_size_sql(),
        "measure_update_cost": " union all ".join(f"select {p!r}::double as p, (select count(*) from lineitem) as updates, (select count(*) * {s.s} from lineitem) as touched, (select count(*) from (with upd as ({q.ORDERS}), {q.sketch(s)} select * from sk)) as cells" for p, s in SPECS.items()),
    }
