"""Method queries on the given tables, each beside its DuckDB text."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.hashing import abs_pow, abs_pow_sql
from ..functions.params import SketchSpec
from ..operators import recover, sampler, sketch as sk
from ..sources import updates as up
from . import method_sql as q

K = 100
SPECS = {p: SketchSpec(p=p, r=2000, s=11, d=7) for p in (1.0, 1.5, 2.0)}
EVENTS = SketchSpec(p=1.0, r=2000, s=11, d=5)


def tag(p: float) -> str:
    return f"p{str(p).replace('.0', '').replace('.', '')}"


def spread(df: DataFrame, d: int) -> DataFrame:
    """Sample rows with the vector as rounded columns."""
    cols = [F.round(F.col("vec")[j], 2).alias(f"c{j}") for j in range(d)]
    return df.select("row_id", *cols, F.round("norm_p", 2).alias("norm_p"), F.round("prob", 6).alias("prob"), F.round("weight", 4).alias("weight"))


def orders_sketch(spark, sf, spec=SPECS[1.0], log=None) -> DataFrame:
    return sk.build(log if log is not None else up.orders(spark, sf), spec)


def turnstile(spec: SketchSpec, source, k: int = K):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        log = source(spark, sf)
        cells = sk.build(log, spec).persist()
        return spread(sampler.sample(cells, up.ids(log), spec, k), spec.d)

    return run


def _exact_scaled(log: DataFrame, spec: SketchSpec) -> DataFrame:
    """Rows as they are, with the scaled norms that the sketch would see."""
    rows = up.exact_rows(log, spec.d)
    t = sk.hashes(spec).uniform(F.col("row_id"))
    return rows.withColumn("norm_p", sampler.norm_of(F.col("vec"), spec.p)).filter("norm_p > 0").withColumn("scaled", F.col("norm_p") / t)


def exact_sample(spec: SketchSpec, k: int = K):
    return lambda spark, sf: spread(sampler.with_cut(_exact_scaled(up.orders(spark, sf), spec), k), spec.d)


def exact_sql(spec: SketchSpec, source: str, k: int) -> str:
    cols = ", ".join(f"sum(case when col_id = {j} then delta else 0.0 end) as c{j}" for j in range(spec.d))
    norm = " + ".join(abs_pow_sql(f"c{j}", spec.p) for j in range(spec.d))
    return f"""with upd as ({source}), ex as (select row_id, {cols} from upd group by row_id),
srows as (select *, ({norm}) as norm_p, ({norm}) / {q.uniform(spec)} as scaled from ex where ({norm}) > 0),
{q.top(k)}
{q.rows_out(spec.d)}"""


def exact(cells: DataFrame) -> DataFrame:
    """Cells with their exact integers as text."""
    return cells.withColumn("val", F.col("val").cast("string"))


def sketch_query(spec: SketchSpec):
    if spec.p not in (1.0, 2.0):  # powers differ in the last place between engines
        return lambda spark, sf: sk.values(sk.build(up.orders(spark, sf), spec), spec).withColumn("val", F.round("val", 2))
    return lambda spark, sf: exact(sk.build(up.orders(spark, sf), spec))


def sketch_sql(spec: SketchSpec, source: str = q.ORDERS) -> str:
    val = "cast(val as varchar)" if spec.p in (1.0, 2.0) else f"round({q.number(spec)}, 2)"
    return f"with upd as ({source}), {q.sketch(spec)} select rep, bucket, col_id, {val} as val from sk"


ONE = SPECS[1.0]


def merge_sites(spark, sf):
    log = up.orders(spark, sf)
    return exact(sk.merge(*[sk.build(log.filter(F.col("site") == s), ONE) for s in range(4)]))


def time_diff(spark, sf):
    log = up.orders(spark, sf)
    later = sk.build(log.filter("ts < timestamp_ntz'1998-01-01'"), ONE)
    earlier = sk.build(log.filter("ts < timestamp_ntz'1997-01-01'"), ONE)
    return exact(sk.diff(later, earlier))


PROJECTION = [[1.0 if i == j else 0.5 if j == i + 1 else 0.0 for j in range(3)] for i in range(7)]


def project(spark, sf):
    return sk.project(orders_sketch(spark, sf), ONE, PROJECTION).filter("val <> 0").withColumn("val", F.round("val", 0))


def project_sql() -> str:
    p = ", ".join(f"({i}, {j}, {PROJECTION[i][j]})" for i in range(7) for j in range(3) if PROJECTION[i][j])
    return f"with upd as ({q.ORDERS}), {q.sketch(ONE)}, pm(col_id, out_col, coef) as (values {p}) select rep, bucket, out_col as col_id, round(sum({q.number(ONE)} * coef), 0) as val from sk join pm using (col_id) group by rep, bucket, out_col having sum({q.number(ONE)} * coef) <> 0"


def retracted(spark, sf):
    log = up.orders(spark, sf)
    return exact(sk.build(log.unionByName(up.retract(log.filter("flag = 'R'"))), ONE))


def bucket_threshold(at: int = 0):
    def run(spark, sf):
        cells = sk.values(orders_sketch(spark, sf), ONE)
        return recover.threshold(recover.bucket_norms(cells, 1.0), ONE, at).select(F.round("m0", 4).alias("m0"))

    return run


def _norms(spark, sf, spec=ONE):
    return recover.bucket_norms(sk.values(orders_sketch(spark, sf, spec), spec), spec.p)


def row_estimates(spark, sf):
    return recover.estimates(up.ids(up.orders(spark, sf)), _norms(spark, sf), ONE).select("row_id", F.round("est_norm", 1).alias("est_norm"))


def candidate_list(spark, sf):
    norms = _norms(spark, sf).persist()
    found = recover.candidates(up.ids(up.orders(spark, sf)), norms, ONE, recover.threshold_value(norms, ONE))
    return found.select("row_id", F.round("est_norm", 1).alias("est_norm"))


def representative_rows(spark, sf):
    cells = orders_sketch(spark, sf).persist()
    norms = recover.bucket_norms(sk.values(cells, ONE), 1.0).persist()
    listed = recover.candidates(up.ids(up.orders(spark, sf)), norms, ONE, recover.threshold_value(norms, ONE))
    rows = recover.representatives(listed, cells, ONE)
    return rows.select("row_id", "rep", *[F.round(F.col("vec")[j], 2).alias(f"c{j}") for j in range(7)])


def two_run(spark, sf):
    log = up.orders(spark, sf)
    other = sampler.second(ONE)
    a, b = sk.build(log, ONE).persist(), sk.build(log, other).persist()
    return spread(sampler.sample_two_run(a, ONE, b, other, up.ids(log), K), 7)


def two_run_sql() -> str:
    other = sampler.second(ONE)
    return f"""with upd as ({q.ORDERS}), {q.chain(ONE, '', None)}, {q.chain(other, '', None, tag='2')},
al as (select case when count(*) < {3 * K // 2} then 0.0 else min(scaled) end as alpha from (select scaled from srows order by scaled desc, row_id limit {3 * K // 2})),
smp as (select s.*, case when alpha > 0 then least(1.0, norm_p / alpha) else 1.0 end as prob from srows2 s, al where scaled >= alpha)
{q.rows_out(7)}"""


# --- heavy rows ----------------------------------------------------------------

PLANT = 1000.0
UNSCALED = replace(ONE, scale=False)


def planted(spark, sf):
    """The order log with five rows made a thousand times larger."""
    log = up.orders(spark, sf).select("row_id", "col_id", "delta")
    return log.unionByName(log.filter("row_id % 300 = 7 and row_id < 1500").withColumn("delta", F.col("delta") * (PLANT - 1)))


PLANTED = f"select row_id, col_id, delta from ({q.ORDERS}) union all select row_id, col_id, delta * {PLANT - 1} from ({q.ORDERS}) where row_id % 300 = 7 and row_id < 1500"
GAMMA = 0.01


def heavy_exact(spark, sf):
    from ..operators.baselines import exact_heavy

    return exact_heavy(up.exact_rows(planted(spark, sf), 7), 1.0, GAMMA, UNSCALED.r).select("row_id", F.round("norm_p", 2).alias("norm_p"))


def heavy_exact_sql() -> str:
    return f"""with upd as ({PLANTED}), ex as (select row_id, sum(abs(v)) as norm_p from (select row_id, col_id, sum(delta) as v from upd group by 1, 2) group by 1),
rk as (select *, row_number() over (order by norm_p desc, row_id) as k from ex), m as (select sum(norm_p) as tail from rk where k > {UNSCALED.r // 20})
select row_id, round(norm_p, 2) as norm_p from ex, m where norm_p >= {GAMMA} * tail"""


def heavy_sketch(spark, sf):
    log = planted(spark, sf)
    spec = replace(UNSCALED, list_multiplier=12.0)
    cells = sk.build(log, spec).persist()
    norms = recover.bucket_norms(sk.values(cells, spec), 1.0).persist()
    listed = recover.candidates(up.ids(log), norms, spec, recover.threshold_value(norms, spec))
    return recover.representatives(listed, cells, spec).select("row_id", "rep", *[F.round(F.col("vec")[j], 2).alias(f"c{j}") for j in range(7)])


def heavy_sketch_sql() -> str:
    spec = replace(UNSCALED, list_multiplier=12.0)
    cols = ", ".join(f"round(c{j}, 2) as c{j}" for j in range(7))
    return f"with {q.chain(spec, PLANTED, None)} select row_id, rep, {cols} from rep_rows"


# --- norms, uniform parts, mixtures ----------------------------------------------


def norm_estimate(spark, sf):
    log = up.orders(spark, sf)
    s = sampler.sample(sk.build(log, ONE).persist(), up.ids(log), ONE, K)
    return sampler.norm_estimate(s).select(F.round("norm_estimate", 0).alias("norm_estimate"))


def domain(spark, sf) -> int:
    """Rows of the order matrix, known before its updates: the keys of `orders`."""
    from ..sources.tables import table

    return table(spark, sf, "orders").count()


RATE = f"least(1.0, {K}.0::double / (select count(*) from orders))"


def uniform_sample(spark, sf):
    s = sampler.uniform(up.orders(spark, sf), K, domain(spark, sf))
    return s.select("row_id", *[F.round(F.col("vec")[j], 2).alias(f"c{j}") for j in range(7)], F.round("prob", 9).alias("prob"), F.round("weight", 6).alias("weight"))


_U = SketchSpec(seed=42 + 17)
UNI = f"uni as (select row_id, {', '.join(f'sum(case when col_id = {j} then delta else 0.0 end) as u{j}' for j in range(7))} from upd where {q.uniform(_U)} <= {RATE} group by row_id)"


def uniform_sql() -> str:
    return f"with upd as ({q.ORDERS}), {UNI} select row_id, {', '.join(f'round(u{j}, 2) as c{j}' for j in range(7))}, round({RATE}, 9) as prob, round(1.0 / {RATE}, 6) as weight from uni"


def mix_union(spark, sf):
    log = up.orders(spark, sf)
    lp = sampler.sample(sk.build(log, ONE).persist(), up.ids(log), ONE, K)
    n = domain(spark, sf)
    m = sampler.mix_uniform(lp, sampler.uniform(log, K, n), K, n)
    return m.select("row_id", *[F.round(F.col("vec")[j], 2).alias(f"c{j}") for j in range(7)], F.round("prob", 6).alias("prob"), F.round("weight", 4).alias("weight"), "origin")


def mix_union_sql() -> str:
    cols = ", ".join(f"round(coalesce(u{j}, c{j}), 2) as c{j}" for j in range(7))
    own = f"least(1.0, ({' + '.join(f'abs(u{j})' for j in range(7))}) / (select max(case when prob < 1 then norm_p / prob end) from smp))"
    prob = f"(1.0::double - (1.0::double - coalesce(prob, {own})) * (1.0::double - {RATE}))"
    return f"""with {q.chain(ONE, q.ORDERS, None)}, {q.top(K)}, {UNI}
select coalesce(s.row_id, u.row_id) as row_id, {cols}, round({prob}, 6) as prob, round(1.0 / {prob}, 4) as weight,
 case when s.row_id is not null and u.row_id is not null then 'both' when u.row_id is not null then 'uniform' else 'lp' end as origin
from smp s full join uni u on s.row_id = u.row_id"""


def mix_carved(spark, sf):
    """Scalars at most c/n are diverted to an exact uniform part, the rest is hashed; both share the scalars."""
    log, n = up.orders(spark, sf), domain(spark, sf)
    carved = replace(ONE, uniform_cut=float(K), n=n)
    t = sk.hashes(carved).uniform(F.col("row_id"))
    low = up.exact_rows(log.filter(t <= K / n), 7).withColumn("norm_p", sampler.norm_of(F.col("vec"), 1.0)).withColumn("origin", F.lit("uniform"))
    high = sampler.scaled_rows(sk.build(log, carved).persist(), up.ids(log.filter(t > K / n)), carved, K)
    top = sampler.top_rows(high, K).persist()
    alpha = sampler.cut_at(top, K)
    rows = low.select("row_id", "vec", "norm_p", "origin").unionByName(top.select("row_id", "vec", "norm_p", F.lit("lp").alias("origin")))
    prob = sampler.carve_probability(F.col("norm_p"), alpha, float(K), n)
    return rows.select("row_id", *[F.round(F.col("vec")[j], 2).alias(f"c{j}") for j in range(7)], F.round(prob, 6).alias("prob"), F.round(1.0 / prob, 4).alias("weight"), "origin")


def mix_carved_sql() -> str:
    t = q.uniform(ONE)
    exact = ", ".join(f"sum(case when col_id = {j} then delta else 0.0 end) as c{j}" for j in range(7))
    cols = ", ".join(f"c{j}" for j in range(7))
    prob = f"greatest({RATE}, case when alpha > 0 then least(1.0, norm_p / alpha) else 1.0 end)"
    return f"""with upd as ({q.ORDERS}), hi as (select * from upd where {t} > {RATE}), {q.chain(ONE, '', None, source='hi')},
top as (select * from srows order by scaled desc, row_id limit {K}), al as (select case when count(*) < {K} then 0.0 else min(scaled) end as alpha from top),
low as (select row_id, {exact} from upd where {t} <= {RATE} group by row_id),
al_rows as (select row_id, {cols}, {' + '.join(f'abs(c{j})' for j in range(7))} as norm_p, 'uniform' as origin from low union all select row_id, {cols}, norm_p, 'lp' from top)
select row_id, {', '.join(f'round(c{j}, 2) as c{j}' for j in range(7))}, round({prob}, 6) as prob, round(1.0 / {prob}, 4) as weight, origin from al_rows, al"""


def mix_l1_l2(spark, sf):
    log = up.orders(spark, sf)
    two = replace(SPECS[2.0], seed=ONE.seed + 7)
    parts, ids = [], up.ids(log).persist()
    for spec, cells in zip((ONE, two), sk.build_many(log, [ONE, two])):
        rows = sampler.top_rows(sampler.scaled_rows(cells, ids, spec, K), K).persist()
        parts.append((rows, sampler.cut_at(rows, K), spec.p))
    m = sampler.mix_many(parts)
    return m.select("row_id", *[F.round(F.col("vec")[j], 2).alias(f"c{j}") for j in range(7)], F.round("prob", 5).alias("prob"), "origin")


def mix_l1_l2_sql() -> str:
    two = replace(SPECS[2.0], seed=ONE.seed + 7)
    c = lambda a: ", ".join(f"{a}.c{j}" for j in range(7))
    n1, n2 = " + ".join(f"abs(c{j})" for j in range(7)), " + ".join(f"c{j} * c{j}" for j in range(7))
    return f"""with upd as ({q.ORDERS}), {q.chain(ONE, '', None)}, {q.chain(two, '', None, tag='2')},
t1 as (select * from srows order by scaled desc, row_id limit {K}), t2 as (select * from srows2 order by scaled desc, row_id limit {K}),
a1 as (select case when count(*) < {K} then 0.0 else min(scaled) end as alpha1 from t1), a2 as (select case when count(*) < {K} then 0.0 else min(scaled) end as alpha2 from t2),
u as (select t1.row_id, {c('t1')}, case when t2.row_id is null then '0' else '0+1' end as origin from t1 left join t2 on t1.row_id = t2.row_id
 union all select t2.row_id, {c('t2')}, '1' from t2 where row_id not in (select row_id from t1))
select row_id, {', '.join(f'round(c{j}, 2) as c{j}' for j in range(7))}, round(1.0 - (1.0 - least(1.0, ({n1}) / alpha1)) * (1.0 - least(1.0, ({n2}) / alpha2)), 5) as prob, origin from u, a1, a2"""


def queries() -> dict:
    out = {f"turnstile_sample_{tag(p)}": turnstile(s, up.orders) for p, s in SPECS.items()}
    out |= {f"exact_sample_{tag(p)}": exact_sample(s) for p, s in SPECS.items()}
    out |= {f"sketch_{tag(p)}": sketch_query(s) for p, s in SPECS.items()}
    return out | {
        "turnstile_sample_events_p1": turnstile(EVENTS, up.user_days),
        "turnstile_two_run": two_run,
        "sketch_unscaled": sketch_query(UNSCALED),
        "map_dense_sketch": lambda spark, sf: exact(sk.build(up.orders(spark, sf), ONE, engine="arrow")),
        "sketch_merge_sites": merge_sites,
        "sketch_time_diff": time_diff,
        "sketch_project": project,
        "sketch_drop_cols": lambda spark, sf: exact(sk.drop_cols(orders_sketch(spark, sf), [0, 6])),
        "sketch_retract": retracted,
        "bucket_threshold": bucket_threshold(),
        "bucket_threshold_other": bucket_threshold(7),
        "row_estimates": row_estimates,
        "candidate_list": candidate_list,
        "representative_rows": representative_rows,
        "heavy_rows_exact": heavy_exact,
        "heavy_rows_sketch": heavy_sketch,
        "norm_estimate": norm_estimate,
        "uniform_sample": uniform_sample,
        "mix_union_uniform": mix_union,
        "mix_carved_uniform": mix_carved,
        "mix_l1_l2": mix_l1_l2,
    }


def oracle_sql() -> dict[str, str]:
    out = {f"turnstile_sample_{tag(p)}": f"with {q.chain(s, q.ORDERS, None)}, {q.top(K)} {q.rows_out(7)}" for p, s in SPECS.items()}
    out |= {f"exact_sample_{tag(p)}": exact_sql(s, q.ORDERS, K) for p, s in SPECS.items()}
    out |= {f"sketch_{tag(p)}": sketch_sql(s) for p, s in SPECS.items()}
    full = f"with upd as ({q.ORDERS}), {q.sketch(ONE)}, {q.norms(ONE)}, {q.threshold(ONE)}, {q.estimates(ONE)}"
    cols = ", ".join(f"round(c{j}, 2) as c{j}" for j in range(7))
    return out | {
        "turnstile_sample_events_p1": f"with {q.chain(EVENTS, q.USER_DAYS, None)}, {q.top(K)} {q.rows_out(5)}",
        "turnstile_two_run": two_run_sql(),
        "sketch_unscaled": sketch_sql(UNSCALED),
        "map_dense_sketch": sketch_sql(ONE),
        "sketch_merge_sites": sketch_sql(ONE),
        "sketch_time_diff": sketch_sql(ONE, f"select * from ({q.ORDERS}) where ts >= timestamp '1997-01-01' and ts < timestamp '1998-01-01'"),
        "sketch_project": project_sql(),
        "sketch_drop_cols": sketch_sql(ONE) + " where col_id not in (0, 6)",
        "sketch_retract": sketch_sql(ONE, f"select * from ({q.ORDERS}) where flag <> 'R'"),
        "bucket_threshold": f"{full} select round(m0, 4) as m0 from thr",
        "bucket_threshold_other": f"with upd as ({q.ORDERS}), {q.sketch(ONE)}, {q.norms(ONE)}, {q.threshold(ONE, at=7)} select round(m0, 4) as m0 from thr",
        "row_estimates": f"{full} select row_id, round(est_norm, 1) as est_norm from est",
        "candidate_list": f"{full}, {q.candidates(ONE, None)} select row_id, round(est_norm, 1) as est_norm from cand",
        "representative_rows": f"with {q.chain(ONE, q.ORDERS, None)} select row_id, rep, {cols} from rep_rows",
        "heavy_rows_exact": heavy_exact_sql(),
        "heavy_rows_sketch": heavy_sketch_sql(),
        "norm_estimate": f"with {q.chain(ONE, q.ORDERS, None)}, {q.top(K)} select round(sum(norm_p / prob), 0) as norm_estimate from smp",
        "uniform_sample": uniform_sql(),
        "mix_union_uniform": mix_union_sql(),
        "mix_carved_uniform": mix_carved_sql(),
        "mix_l1_l2": mix_l1_l2_sql(),
    }
