"""DuckDB text of the sketch chain, built from the same constants as the Spark plans."""

from __future__ import annotations

from ..functions.hashing import Hashes, abs_pow_sql, field_sql, inv_scale_sql
from ..functions.params import SketchSpec

ORDERS = "select l_orderkey as row_id, l_linenumber - 1 as col_id, l_extendedprice as delta, l_shipdate as ts, l_suppkey % 4 as site, l_returnflag as flag from lineitem"
USER_DAYS = """select user_id * 100000 + date_diff('day', date '1970-01-01', cast(ts as date)) as row_id, cast(k.pos as integer) as col_id, value as delta, ts
  from events join (select event_type, row_number() over (order by event_type) - 1 as pos from (select distinct event_type from events)) k using (event_type)"""


PARTS = [f"b{k}" for k in range(8)]


def rep_table(spec: SketchSpec, name: str = "reps") -> str:
    h = Hashes(spec.seed)
    rows = ", ".join("(" + ", ".join(map(str, [j, *h.place_coef(j)])) + ")" for j in range(spec.s))
    return f"{name}(rep, {', '.join(PARTS)}) as (values {rows})"


def bucket(spec: SketchSpec, row: str = "row_id") -> str:
    return f"cast({field_sql(row, PARTS)[0]} % {spec.r} as integer)"


def sign(row: str = "row_id") -> str:
    return f"(case when {field_sql(row, PARTS)[1]} < {2147483647 // 2} then -1 else 1 end)"


def uniform(spec: SketchSpec, row: str = "row_id") -> str:
    return Hashes(spec.seed).uniform_sql(row)


def sketch(spec: SketchSpec, source: str = "upd", tag: str = "") -> str:
    """CTEs reps, log, sk over a CTE `source` (row_id, col_id, delta)."""
    cut = f" where {uniform(spec)} > {spec.uniform_cut / spec.n!r}" if spec.uniform_cut and spec.n else ""
    return f"""{rep_table(spec, 'reps' + tag)},
{limbs(spec, source + cut, 'log' + tag)},
sk{tag} as materialized (select rep, bucket, col_id, {VAL} as val
  from (select rep, {bucket(spec)} as bucket, col_id, {sign()} as sg, h2, h1, h0 from log{tag}, reps{tag})
  group by rep, bucket, col_id having {VAL} <> 0)"""


#: The exact integer of a cell, from sums of signed limbs.
VAL = f"(sum(sg * h2)::hugeint * {1 << 60} + sum(sg * h1)::hugeint * {1 << 30} + sum(sg * h0)::hugeint)"


def limbs(spec: SketchSpec, source: str, name: str, more: str = "") -> str:
    """CTE of the scaled updates in fixed point, as three limbs."""
    z = f"delta * {inv_scale_sql(uniform(spec), spec.p)}" if spec.scale else "delta"
    return f"""{name} as (select row_id, col_id{more}, cast(sz * z2 as bigint) as h2, cast(sz * floor(rest / {float(1 << 30)!r}) as bigint) as h1, cast(sz * (rest - floor(rest / {float(1 << 30)!r}) * {float(1 << 30)!r}) as bigint) as h0
  from (select *, floor(abs(z) * {float(spec.fixed)!r} - z2 * {float(1 << 60)!r} + 0.5) as rest from (select *, case when z < 0 then -1 else 1 end as sz, floor(abs(z) * {spec.fixed / (1 << 60)!r}) as z2 from (select *, {z} as z from {source}))))"""


def number(spec: SketchSpec, val: str = "val") -> str:
    """A cell as a double."""
    return f"((case when {val} < 0 then -cast(-{val} as double) else cast({val} as double) end) / {float(spec.fixed)!r}::double)"


def norms(spec: SketchSpec, tag: str = "") -> str:
    return f"norms{tag} as materialized (select rep, bucket, sum({abs_pow_sql(number(spec), spec.p)}) as norm from sk{tag} group by rep, bucket)"


def threshold(spec: SketchSpec, tag: str = "", at: int = 0) -> str:
    return f"thr{tag} as materialized (select quantile_cont(coalesce(norm, 0.0), {spec.quantile}) as m0 from reps{tag} r left join (select * from norms{tag} where bucket = {at}) n on r.rep = n.rep)"


def estimates(spec: SketchSpec, source: str = "upd", tag: str = "") -> str:
    return f"""ids{tag} as (select distinct row_id from {source}),
probe{tag} as materialized (select row_id, rep, {bucket(spec)} as bucket, {sign()} as sg from ids{tag}, reps{tag}),
est{tag} as materialized (select row_id, median(coalesce(norm, 0.0)) as est_norm from probe{tag} p left join norms{tag} n on p.rep = n.rep and p.bucket = n.bucket group by row_id)"""


def candidates(spec: SketchSpec, limit: int | None, tag: str = "") -> str:
    top = f" order by est_norm desc, row_id limit {limit}" if limit else ""
    return f"cand{tag} as materialized (select row_id, est_norm from est{tag}, thr{tag} where est_norm >= m0 * {float(spec.list_multiplier**spec.p)!r} and est_norm > 0{top})"


def representatives(spec: SketchSpec, tag: str = "") -> str:
    d = range(spec.d)
    cols = ", ".join(f"sum(case when col_id = {j} then {number(spec)} else 0.0 end) as c{j}" for j in d)
    mine = ", ".join(f"sg * coalesce(c{j}, 0.0) as c{j}" for j in d)
    dist = " + ".join(abs_pow_sql(f"(a.c{j} - b.c{j})", spec.p) for j in d)
    return f"""pk{tag} as (select rep, bucket, {cols} from sk{tag} group by rep, bucket),
mine{tag} as materialized (select p.row_id, p.rep, {mine} from cand{tag} c join probe{tag} p on c.row_id = p.row_id left join pk{tag} k on p.rep = k.rep and p.bucket = k.bucket),
med{tag} as (select a.row_id, a.rep, quantile_disc({dist}, 0.5) as m from mine{tag} a join mine{tag} b on a.row_id = b.row_id and a.rep <> b.rep group by a.row_id, a.rep),
rep_rows{tag} as materialized (select m.* from mine{tag} m join (select row_id, rep, row_number() over (partition by row_id order by round(m, 6), rep) as rk from med{tag}) w on m.row_id = w.row_id and m.rep = w.rep where w.rk = 1)"""


def scaled_rows(spec: SketchSpec, tag: str = "") -> str:
    norm = " + ".join(abs_pow_sql(f"c{j}", spec.p) for j in range(spec.d))
    factor = inv_scale_sql(uniform(spec), spec.p) if spec.scale else "1.0"
    t = uniform(spec) if spec.scale else "1.0"
    cols = ", ".join(f"c{j} / {factor} as c{j}" for j in range(spec.d))
    return f"srows{tag} as materialized (select row_id, rep, {cols}, ({norm}) as scaled, ({norm}) * {t} as norm_p from rep_rows{tag})"


def chain(spec: SketchSpec, source_sql: str, budget: int | None, source: str = "upd", tag: str = "") -> str:
    """All CTEs from the log to the scaled rows."""
    head = f"{source} as ({source_sql}),\n" if source_sql else ""
    return head + ",\n".join([sketch(spec, source, tag), norms(spec, tag), threshold(spec, tag), estimates(spec, source, tag), candidates(spec, budget, tag), representatives(spec, tag), scaled_rows(spec, tag)])


def top(k: int, tag: str = "") -> str:
    """CTE smp: the k rows of largest scaled norm with probability and weight."""
    return f"""top{tag} as (select *, row_number() over (order by scaled desc, row_id) as rk, count(*) over () as n from srows{tag}),
alpha{tag} as (select case when max(n) < {k} then 0.0 else max(case when rk = {k} then scaled end) end as alpha from top{tag}),
smp{tag} as (select t.*, case when alpha <= 0 then 1.0 else least(1.0, norm_p / alpha) end as prob from top{tag} t, alpha{tag} where rk <= {k})"""


def rows_out(d: int, source: str = "smp") -> str:
    cols = ", ".join(f"round(c{j}, 2) as c{j}" for j in range(d))
    return f"select row_id, {cols}, round(norm_p, 2) as norm_p, round(prob, 6) as prob, round(1.0 / prob, 4) as weight from {source}"
