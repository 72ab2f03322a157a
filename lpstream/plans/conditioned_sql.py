"""DuckDB text of embeddings, conditioning matrices, leverage scores and the samples drawn by them.

Streams of coefficients are rows of a small table; orthogonalisation is a chain of
one-row tables, a column of the embedding at a time.
"""

from __future__ import annotations

import math

from ..functions.hashing import Hashes, abs_pow_sql, coefficients, field_sql, poly_sql
from . import method_sql as q


def events(problem: str = "logistic") -> str:
    """Rows of the event matrix: row_id, a0 ... ."""
    past = "coalesce(sum(value) over (partition by user_id order by ts, event_id rows between 20 preceding and 1 preceding), 0.0)"
    base = f"(select event_id as row_id, hour(ts) / 24.0 as h, coalesce(cast(json_extract_string(props, '$.k') as double), 0.0) / 100 as k, {past} / 1000 as past, value, event_type, case when event_type = 'error' then -1.0::double else 1.0::double end as y from events)"
    if problem == "l1":
        return f"select row_id, 1.0::double as a0, h as a1, k as a2, past as a3, cast(event_type = 'click' as integer)::double as a4, cast(event_type = 'purchase' as integer)::double as a5, value / 100 as a6 from {base}"
    return f"select row_id, y as a0, y * h as a1, y * k as a2, y * past as a3, y * (value / 100) as a4, y * (value * value / 1e5) as a5 from {base}"


def stable(p: float, row: str = "row_id") -> str:
    """The p-stable variable of a row from one stream's coefficients (a0..a7, e0..e7 of the stream table)."""
    parts = lambda s: [f"{s}{k}" for k in range(8)]
    theta = f"((({field_sql(row, parts('sa'))[0]} + 1) / {float(1 << 31)!r}::double - 0.5) * {math.pi * (1 - 1e-9)!r}::double)"
    if p == 1:
        return f"tan({theta})"
    w = f"(({field_sql(row, parts('se'))[0]} + 1) / {float((1 << 31) + 1)!r}::double)"
    if p == 2:
        return f"(sqrt(-2.0::double * ln({w})) * sin({theta} * 2.0::double))"
    return f"(sin({theta} * {p!r}::double) / pow(cos({theta}), {1 / p!r}::double) * pow(cos({theta} * {1 - p!r}::double) / (-ln({w})), {(1 - p) / p!r}::double))"


def streams(m: int, seed: int) -> str:
    rows = ", ".join("(" + ", ".join(map(str, [i, *coefficients(seed, "angle", i), *coefficients(seed, "exponential", i)])) + ")" for i in range(m))
    return f"streams(i, {', '.join(f'sa{k}' for k in range(8))}, {', '.join(f'se{k}' for k in range(8))}) as (values {rows})"


def dense(m: int, p: float, source: str = "upd", seed: int = 42) -> str:
    """CTEs streams, var, emb over a log."""
    return f"""{streams(m, seed + 101)},
var as materialized (select row_id, i, {stable(p)} as x from (select distinct row_id from {source}), streams),
emb as materialized (select i, col_id, sum(x * delta) as val from {source} join var using (row_id) group by i, col_id)"""


def dense_query(p: float, m: int = 40) -> str:
    return f"with upd as ({q.USER_DAYS}), {dense(m, p)} select i, col_id, round(val, 3) as val from emb"


def sparse_query(m: int = 40, seed: int = 42) -> str:
    at = lambda s: poly_sql("row_id", coefficients(seed, s, 0))
    sign = f"(case when {at('sparse sign')} < {1 << 30} then -1.0::double else 1.0::double end)"
    scale = f"pow(({at('sparse scale')} + 1) / {float(1 << 31)!r}::double, -1.0::double)"
    return f"with upd as ({q.USER_DAYS}) select cast({at('sparse place')} % {m} as integer) as i, cast(col_id as integer) as col_id, round(sum({sign} * {scale} * delta), 3) as val from upd group by 1, 2"


def triangular(d: int) -> str:
    """CTE tri: the upper triangular factor r_jk of emb, columns orthogonalised one after the other."""
    wide = ", ".join(f"sum(case when col_id = {j} then val else 0.0 end) as c0_{j}" for j in range(d))
    out = [f"w0 as materialized (select i, {wide} from emb group by i)"]
    for j in range(d):
        c = [f"c{j}_{k}" for k in range(d)]
        inner = "".join(f", sum({c[j]} * {c[k]}) / sqrt(sum({c[j]} * {c[j]})) as r{j}_{k}" for k in range(j + 1, d))
        out.append(f"t{j} as materialized (select sqrt(sum({c[j]} * {c[j]})) as r{j}_{j}{inner} from w{j})")
        if j + 1 < d:
            rest = ", ".join(f"{c[k]} - {c[j]} / r{j}_{j} * r{j}_{k} as c{j + 1}_{k}" for k in range(j + 1, d))
            out.append(f"w{j + 1} as materialized (select i, {rest} from w{j}, t{j})")
    return ",\n".join([*out, f"tri as materialized (select * from {', '.join(f't{j}' for j in range(d))})"])


def cholesky(d: int, source: str = "mat") -> str:
    """CTE tri from the Gram matrix of rows a0 ..., its trace lifting the diagonal a little."""
    sums = ", ".join(f"sum(a{i} * a{j}) as g{i}_{j}" for i in range(d) for j in range(i, d))
    trace = " + ".join(f"g{i}_{i}" for i in range(d))
    cols = []
    for i in range(d):
        for j in range(i, d):
            less = "".join(f" - r{k}_{i} * r{k}_{j}" for k in range(i))
            cols.append(f"sqrt(g{i}_{i} + lift{less}) as r{i}_{i}" if i == j else f"(g{i}_{j}{less}) / r{i}_{i} as r{i}_{j}")
    return f"""gram as materialized (select *, 1e-12 * ({trace}) as lift from (select {sums} from {source})),
tri as materialized (select {', '.join(cols)} from gram)"""


def solved(d: int, row: str = "a") -> str:
    """Columns z0 ...: a row times the inverse of the factor, by substitution."""
    return ", ".join(f"({row}{j}{''.join(f' - z{k} * r{k}_{j}' for k in range(j))}) / r{j}_{j} as z{j}" for j in range(d))


def conditioner_query(d: int = 5, p: float = 1.0) -> str:
    unit = " union all ".join("select " + f"{i} as i, " + ", ".join(f"{float(i == j)!r}::double as a{j}" for j in range(d)) for i in range(d))
    cells = " union all ".join(f"select i, {j} as j, round(z{j}, 6) as v from inv" for j in range(d))
    return f"with upd as ({q.USER_DAYS}), {dense(max(40, 8 * d), p)}, {triangular(d)}, inv as (select i, {solved(d)} from ({unit}), tri) {cells}"


def score_tables(p: float, d: int = 6) -> str:
    """CTEs up to scored: row_id, a0 ..., score by an embedding of the event matrix."""
    long = " union all ".join(f"select row_id, {j} as col_id, a{j} as delta from mat" for j in range(d))
    score = " + ".join(abs_pow_sql(f"z{j}", p) for j in range(d))
    cols = ", ".join(f"a{j}" for j in range(d))
    return f"mat as materialized ({events()}), upd as materialized ({long}), {dense(max(40, 8 * d), p)}, {triangular(d)},\nscored as materialized (select row_id, {cols}, {score} as score from (select *, {solved(d)} from mat, tri))"


def scores_query(p: float) -> str:
    return f"with {score_tables(p)} select row_id, round(score, 6) as score from scored"


def exact_query(d: int = 6) -> str:
    score = " + ".join(f"z{j} * z{j}" for j in range(d))
    return f"with mat as materialized ({events()}), {cholesky(d)} select row_id, round({score}, 9) as score from (select *, {solved(d)} from mat, tri)"


def shown(d: int, source: str, prob: str = "prob") -> str:
    vec = " || ' ' || ".join(f"format('{{:,.5f}}', a{j})" for j in range(d))
    return f"select row_id, {vec} as vec, round({prob}, 6) as prob, round(1.0 / ({prob}), 4) as weight from {source}"


def uniform_query(k: int, d: int = 6, seed: int = 42) -> str:
    share = f"({float(k)!r}::double / (select count(*) from mat))"
    return f"with mat as materialized ({events()}) {shown(d, 'mat', f'least(1.0, {share})')} where {Hashes(seed + 17).uniform_sql('row_id')} <= {share}"


def offline_query(mode: str, k: int, d: int = 6, p: float = 1.0, seed: int = 0) -> str:
    u = Hashes(seed + 5).uniform_sql("row_id")
    if mode == "priority":
        return f"""with {score_tables(p, d)}, keyed as (select *, score / {u} as key from scored where score > 0), ranked as (select *, row_number() over (order by key desc, row_id) as rk from keyed),
cut as (select coalesce(max(case when rk = {k + 1} then key end), 0.0) as cut from ranked), drawn as (select *, case when cut > 0 then least(1.0, score / cut) else 1.0 end as prob from ranked, cut where rk <= {k}) {shown(d, 'drawn')}"""
    # The cut: the least number of certain rows for which the rest, spread evenly, exceeds none of them.
    return f"""with {score_tables(p, d)}, ranked as (select score, row_number() over (order by score desc, row_id) - 1 as above, sum(score) over (order by score desc, row_id rows between current row and unbounded following) as rest from scored where score > 0),
cut as (select case when count(*) <= {k} then 0.0 else min(rest / ({k} - above)) filter (above < {k} and score * ({k} - above) <= rest) end as cut from ranked),
drawn as (select *, case when cut > 0 then least(1.0, score / cut) else 1.0 end as prob from scored, cut where score > 0) {shown(d, 'drawn')} where {u} <= prob"""


def fold_query() -> str:
    return f"select row_id, {', '.join(f'round(a{j}, 5) as x{j}' for j in range(7))} from ({events('l1')})"


def documents_query() -> str:
    kept = lambda c: f"length(regexp_replace(text, '[^{c}]', '', 'g'))"
    x = ["1.0::double", "ln(1.0 + words) / 10", "ln(1.0 + lines) / 5", f"{kept('0-9')} / (chars + 1) * 20", f"{kept('!-/:-@|')} / (chars + 1) * 5", f"{kept('A-Z')} / (chars + 1) * 5"]
    base = r"select doc_id, text, cast(len(regexp_split_to_array(text, '[ \t\n\x0B\f\r]+')) as double) as words, cast(len(string_split(text, chr(10))) as double) as lines, cast(length(text) as double) as chars from documents"
    cols = ", ".join(f"round(case when quality = 1 then -1.0::double else 1.0::double end * ({v}), 5) as x{j}" for j, v in enumerate(x))
    return f"select d.doc_id as row_id, {cols} from ({base}) d join labels l on d.doc_id = l.doc_id"


def pages_query() -> str:
    tags = ", ".join(f"len(regexp_extract_all(html, '<{t}[ >]'))::double as x{j + 3}" for j, t in enumerate(("p", "a", "li", "div")))
    return f"select page_id as row_id, 1.0::double as x0, (length(url) - length(replace(url, '/', '')))::double as x1, round(length(html) / 1000.0, 5) as x2, {tags} from pages"


def median_query(panel: list, m: int = 101, d: int = 5) -> str:
    z = ", ".join("(" + ", ".join([str(i), *[f"{float(v)!r}::double" for v in row]]) + ")" for i, row in enumerate(panel))
    dot = lambda t: " + ".join(f"{t}.c{j} * z{j}" for j in range(d))
    wide = ", ".join(f"sum(case when col_id = {j} then {{v}} else 0.0 end) as c{j}" for j in range(d))
    return f"""with upd as ({q.USER_DAYS}), {dense(m, 1.0)}, zs(z, {', '.join(f'z{j}' for j in range(d))}) as (values {z}),
e as (select i, {wide.format(v='val')} from emb group by i), x as (select row_id, {wide.format(v='delta')} from upd group by row_id),
a as (select z, median(abs({dot('e')})) as estimate from e, zs group by z), b as (select z, sum(abs({dot('x')})) as exact from x, zs group by z)
select cast(z as integer) as z, round(estimate, 3) as estimate, round(exact, 3) as exact from a join b using (z)"""


def sandwich_query(spec) -> str:
    norm = " + ".join(f"abs(x{j})" for j in range(spec.d))
    cols = ", ".join(f"sum(case when col_id = {j} then delta else 0.0 end) as x{j}" for j in range(spec.d))
    return f"""with upd as ({q.ORDERS}), {q.sketch(spec)}, {q.norms(spec)}, {q.threshold(spec)},
every as (select coalesce(norm, 0.0) as norm from (select rep, b from reps, range({spec.r}) g(b)) s left join norms n on n.rep = s.rep and n.bucket = s.b),
ex as (select {norm} as norm, row_number() over (order by {norm} desc, row_id) as rk from (select row_id, {cols} from upd group by row_id)),
v as (select (select quantile_cont(norm, 0.6) from every) as lower, m0, (select 4 * sum(norm) / {spec.r} from ex where rk > {spec.r // 20}) as upper from thr)
select round(lower, 2) as lower, round(m0, 2) as m0, round(upper, 2) as upper, lower <= m0 and m0 <= upper as holds from v"""


def by_norm_query(total: str, spec, k: int) -> str:
    """Sample by a cut from a sketched norm; `total` gives one value `estimate`."""
    return f"""with {q.chain(spec, q.ORDERS, None)}, al as (select estimate / {k} as alpha from ({total}))
select row_id, round(norm_p, 0) as norm_p, round(least(1.0, norm_p / alpha), 6) as prob from srows, al where scaled >= alpha"""
