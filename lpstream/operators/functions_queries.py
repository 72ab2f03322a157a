"""Scalar, array, map, JSON and hash functions on the tables that the methods read, features, UDFs and stores."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions import losses
from ..functions.hashing import Hashes
from ..functions.params import SketchSpec
from ..plans import conditioned_sql as cs, method_sql as q
from ..sources import features, formats, updates as up
from ..sources.tables import sql, table, typed
from . import recover, sampler, sketch as sk, udfs
from .baselines import merge_reduce

ONE = SketchSpec(p=1.0, r=2000, s=11, d=7)
H = Hashes(42)

SHARED = {
    "fn_text_features": r"select doc_id, length(text) as n, lower(substr(text, 1, 20)) as head, upper(source) as src, length(replace(text, 'e', '')) as no_e, length(regexp_replace(trim(text), '[aeiou]', '', 'g')) as vowels, concat(lang, '-', source) as tag, instr(text, 'the') as at from documents",
    "fn_date_parts": "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, day(o_orderdate) as d, quarter(o_orderdate) as q, cast(datediff(day, timestamp '1995-01-01 00:00:00', o_orderdate) as bigint) as since from orders",
    "fn_math": "select l_orderkey, l_linenumber, l_partkey, round(pow(l_quantity, 1.5), 4) as a, round(sqrt(l_extendedprice), 6) as b, round(ln(l_quantity + 1), 8) as c, round(exp(-l_discount), 8) as d, round(sin(l_tax) + cos(l_tax) + tan(l_discount), 8) as e, cast(sign(l_discount - 0.05) as int) as f, abs(l_quantity - 25) as g, cast(floor(l_extendedprice / 1000) as bigint) as h, greatest(l_tax, l_discount) as i, least(l_tax, l_discount) as j, l_partkey % 7 as k from lineitem",
    "fn_fixed_point": "select l_orderkey, cast(sum(cast(round(l_extendedprice * 256, 0) as bigint)) as bigint) as total, cast(sum(cast(l_tax as decimal(12, 2))) as decimal(18, 2)) as tax from lineitem group by l_orderkey",
}


def text_features(spark, sf):
    df = sql(spark, sf, SHARED["fn_text_features"].replace(", 'g')", ")"))
    return df.withColumns({c: F.col(c).cast("bigint") for c in ("n", "no_e", "vowels", "at")})


def hash_poly(spark, sf):
    row = F.col("o_orderkey")
    return typed(spark, sf, "orders").select("o_orderkey", H.uniform(row).alias("t"), H.bucket_at(row, F.lit(3), 2000, 11).alias("b"), H.sign_at(row, F.lit(3), 11).alias("s"))


HASH_SQL = f"select o_orderkey, {H.uniform_sql('o_orderkey')} as t, cast({H.bucket_sql('o_orderkey', 3, 2000)} as integer) as b, {H.sign_sql('o_orderkey', 3)} as s from orders"


def hash_fast(spark, sf):
    fast = Hashes(42, "fast")
    return typed(spark, sf, "orders").select("o_orderkey", fast.uniform(F.col("o_orderkey")).alias("t"), fast.bucket_at(F.col("o_orderkey"), F.lit(1), 2000, 11).alias("b"))


def loss_columns(spark, sf):
    t = (F.col("l_discount") - 0.05) * 40
    return typed(spark, sf, "lineitem").agg(*[F.round(F.sum(losses.value(name, t, 1.0)), 2).alias(name) for name in losses.LOSSES], F.round(F.sum(losses.value("relu", t, 2.0)), 2).alias("relu2"))


LOSS_SQL = """with x as (select (l_discount - 0.05) * 40 as t from lineitem) select round(sum(abs(t)), 2) as lp, round(sum(greatest(t, 0.0)), 2) as relu, round(sum(greatest(t, 0.0) + ln(1 + exp(-abs(t)))), 2) as logistic,
round(sum(case when t > 0 then t + ln(2.0) else -ln(1 - 0.5 * exp(t)) end), 2) as probit, round(sum(greatest(t, 0.0) * greatest(t, 0.0)), 2) as relu2 from x"""


def array_norms(spark, sf):
    v = F.transform("embedding", lambda x: x.cast("double"))
    e = table(spark, sf, "embeddings").select("vec_id", v.alias("v"))
    dot = F.aggregate(F.zip_with("v", F.reverse("v"), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return e.select("vec_id", *[F.round(sampler.norm_of(F.col("v"), p), 4).alias(n) for n, p in (("l1", 1.0), ("l15", 1.5), ("l2", 2.0))], F.round(dot, 4).alias("dot"))


ARRAY_SQL = """with e as (select vec_id, i, embedding[i]::double as x, embedding[65 - i]::double as y from embeddings, range(1, 65) r(i))
select vec_id, round(sum(abs(x)), 4) as l1, round(sum(pow(abs(x), 1.5::double)), 4) as l15, round(sum(x * x), 4) as l2, round(sum(x * y), 4) as dot from e group by vec_id"""


def array_misc(spark, sf):
    e = typed(spark, sf, "lineitem").groupBy("l_orderkey").agg(F.sort_array(F.collect_list("l_linenumber")).alias("a"))
    j = lambda c: F.array_join(c.cast("array<string>"), ",")
    return e.select("l_orderkey", j(F.slice("a", 1, 2)).alias("two"), F.array_position("a", 3).cast("int").alias("at3"), j(F.filter("a", lambda x: x > 4)).alias("high"), F.exists("a", lambda x: x == 7).alias("seven"), F.array_max("a").alias("top"), j(F.array_distinct("a")).alias("set"), F.size(F.flatten(F.array("a", "a"))).alias("double"))


ARRAY_MISC_SQL = """with e as (select l_orderkey, list_sort(list(l_linenumber)) as a from lineitem group by 1)
select l_orderkey, array_to_string(a[1:2], ',') as two, coalesce(list_position(a, 3), 0)::int as at3, coalesce((select string_agg(x::varchar, ',') from unnest(a) u(x) where x > 4), '') as high, list_contains(a, 7) as seven, list_max(a) as top, array_to_string(list_sort(list_distinct(a)), ',') as set, (len(a) * 2)::int as double from e"""


def map_sparse(spark, sf):
    cells = up.orders(spark, sf).groupBy("row_id", "col_id").agg(F.round(F.sum("delta"), 2).alias("v"))
    m = cells.groupBy("row_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("col_id", "v")))).alias("m"))
    return m.select("row_id", F.coalesce(F.try_element_at("m", F.lit(2)), F.lit(0.0)).alias("c2"), F.size(F.map_filter("m", lambda k, v: v > 50_000)).alias("big"), F.size(F.map_entries("m")).alias("nnz"))


MAP_SQL = "with c as (select l_orderkey as row_id, l_linenumber - 1 as col_id, round(sum(l_extendedprice), 2) as v from lineitem group by 1, 2) select row_id, coalesce(max(case when col_id = 2 then v end), 0.0) as c2, sum(case when v > 50000 then 1 else 0 end)::int as big, count(*)::int as nnz from c group by row_id"


def json_props(spark, sf):
    e = typed(spark, sf, "events")
    return e.select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k1"), F.from_json("props", "k int")["k"].alias("k2"), F.to_json(F.struct(F.col("event_type").alias("t"))).alias("j"))


def struct_spec(spark, sf):
    s = F.struct(F.col("o_orderkey").alias("row_id"), F.struct(F.col("o_totalprice").alias("norm_p"), F.lit("lp").alias("origin")).alias("sample"))
    return typed(spark, sf, "orders").select(s.alias("s")).select(F.col("s.row_id").alias("row_id"), F.col("s")["sample"]["norm_p"].alias("norm_p"), F.col("s.sample").getField("origin").alias("origin"))


def url_html(spark, sf):
    p = table(spark, sf, "pages")
    return p.select("page_id", (F.length("url") - F.length(F.replace("url", F.lit("/"), F.lit("")))).alias("depth"), F.regexp_count("html", F.lit("<p>")).alias("n_p"), F.try_parse_url("url", F.lit("HOST")).alias("host"))


# --- features -------------------------------------------------------------------


def shown(rows: DataFrame, d: int, digits: int = 5) -> DataFrame:
    return rows.select("row_id", *[F.round(F.col("vec")[j], digits).alias(f"x{j}") for j in range(d)])


def features_events(spark, sf):
    return shown(features.w3_events(spark, sf), 6)


EVENTS_SQL = """with e as (select event_id, ts, event_type, value, coalesce(cast(json_extract_string(props, '$.k') as double), 0.0) as k, coalesce(sum(value) over (partition by user_id order by ts, event_id rows between 20 preceding and 1 preceding), 0.0) as past from events),
s as (select *, case when event_type = 'error' then -1.0::double else 1.0::double end as y from e)
select event_id as row_id, round(y, 5) as x0, round(y * (hour(ts) / 24.0), 5) as x1, round(y * (k / 100), 5) as x2, round(y * (past / 1000), 5) as x3, round(y * (value / 100), 5) as x4, round(y * (value * value / 1e5), 5) as x5 from s"""


def hash_tokens(spark, sf):
    """Tokens of a text in 16 counts, by a hash that any engine repeats: length and first-letter code."""
    d = table(spark, sf, "documents").select("doc_id", F.explode(F.split("text", " ")).alias("w")).filter("w <> ''")
    b = (F.length("w") * 31 + F.ascii("w")) % 16
    return d.groupBy("doc_id", b.cast("int").alias("bucket")).agg(F.count("*").alias("n"))


HASH_TOKENS_SQL = "with t as (select doc_id, unnest(string_split(text, ' ')) as w from documents) select doc_id, cast((length(w) * 31 + unicode(w)) % 16 as integer) as bucket, count(*) as n from t where w <> '' group by 1, 2"


def pages_matrix(spark, sf):
    return shown(features.w15_pages(spark, sf), 7)


def conversations_matrix(spark, sf):
    return shown(features.w15_conversations(spark, sf), 4)


CONV_SQL = "select conv_id as row_id, count(*)::double as x0, " + ", ".join(f"coalesce(sum(case when role = '{r}' then length(text) end), 0)::double as x{i + 1}" for i, r in enumerate(("system", "user", "assistant"))) + " from conversations group by 1"


def label_fold(spark, sf):
    return shown(features.w3_events(spark, sf, "l1"), 7)


def carve_uniform(spark, sf):
    t = H.uniform(F.col("row_id"))
    return up.orders(spark, sf).select(F.when(t <= 100 / 20_000, "uniform").otherwise("hashed").alias("part"), "delta").groupBy("part").agg(F.count("*").alias("n"), F.round(F.sum("delta"), 0).alias("mass"))


CARVE_SQL = f"with upd as ({q.ORDERS}) select case when {H.uniform_sql('row_id')} <= {100 / 20_000!r} then 'uniform' else 'hashed' end as part, count(*) as n, round(sum(delta), 0) as mass from upd group by 1"


# --- joins inside the recovery -----------------------------------------------------


def _norms(spark, sf):
    return recover.bucket_norms(sk.values(sk.build(up.orders(spark, sf), ONE), ONE), 1.0)


_FULL = f"with upd as ({q.ORDERS}), {q.sketch(ONE)}, {q.norms(ONE)}, {q.threshold(ONE)}, {q.estimates(ONE)}"


def zero_buckets(spark, sf):
    every = spark.range(ONE.s).select(F.col("id").cast("int").alias("rep"), F.explode(F.sequence(F.lit(0), F.lit(49))).alias("bucket"))
    return every.join(_norms(spark, sf), ["rep", "bucket"], "left").select("rep", "bucket", F.round(F.coalesce("norm", F.lit(0.0)), 4).alias("norm"))


def heavy_buckets(spark, sf):
    norms = _norms(spark, sf).persist()
    cut = recover.threshold_value(norms, ONE)
    heavy = norms.filter(F.col("norm") >= cut).select("rep", "bucket")
    return recover.probes(up.ids(up.orders(spark, sf)), ONE).join(heavy, ["rep", "bucket"], "left_semi").groupBy("row_id").agg(F.count("*").alias("heavy"))


def missed_heavy(spark, sf):
    """Rows of the largest scaled norms that the list misses."""
    from ..plans.methods import _exact_scaled

    log = up.orders(spark, sf)
    norms = _norms(spark, sf).persist()
    listed = recover.candidates(up.ids(log), norms, ONE, recover.threshold_value(norms, ONE))
    top = sampler.top_rows(_exact_scaled(log, ONE), 500)
    return top.select("row_id").join(listed, "row_id", "left_anti")


def missed_sql() -> str:
    return f"""{_FULL}, {q.candidates(ONE, None)}, ex as (select row_id, sum(abs(v)) as norm_p from (select row_id, col_id, sum(delta) as v from upd group by 1, 2) group by 1),
top as (select row_id from ex where norm_p > 0 order by norm_p / {q.uniform(ONE)} desc, row_id limit 500) select row_id from top where row_id not in (select row_id from cand)"""


def rep_pairs(spark, sf):
    """Distances between the repetitions of listed rows as a theta join (the recovery compares in place)."""
    cells = sk.build(up.orders(spark, sf), ONE).persist()
    norms = recover.bucket_norms(sk.values(cells, ONE), 1.0).persist()
    few = recover.candidates(up.ids(up.orders(spark, sf)), norms, ONE, recover.threshold_value(norms, ONE))
    rows = few.select("row_id", sk.reps(ONE).alias("rep")).select("row_id", "rep", sk.bucket(ONE).alias("bucket"), sk.sign(ONE).alias("sg")).join(sk.packed(cells, ONE), ["rep", "bucket"]).select("row_id", "rep", F.transform("vec", lambda x: x * F.col("sg")).alias("vec"))
    a, b = rows.alias("a"), rows.alias("b")
    pairs = a.join(b, (F.col("a.row_id") == F.col("b.row_id")) & (F.col("a.rep") != F.col("b.rep")))
    dist = F.aggregate(F.zip_with("a.vec", "b.vec", lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x)
    return pairs.groupBy(F.col("a.row_id").alias("row_id"), F.col("a.rep").alias("rep")).agg(F.array_sort(F.collect_list(dist)).alias("all")).select("row_id", "rep", F.round(F.get("all", F.floor((F.size("all") - 1) / 2).cast("int")), 2).alias("m"))


def full_outer_mixture(spark, sf):
    a = typed(spark, sf, "orders").filter("o_totalprice > 250000").select(F.col("o_orderkey").alias("row_id"), F.lit(0.5).alias("pa"))
    b = typed(spark, sf, "orders").filter(H.uniform(F.col("o_orderkey")) <= 0.02).select(F.col("o_orderkey").alias("row_id"), F.lit(0.02).alias("pb"))
    prob = 1.0 - (1.0 - F.coalesce("pa", F.lit(0.0))) * (1.0 - F.coalesce("pb", F.lit(0.0)))
    return a.join(b, "row_id", "full").select("row_id", F.round(prob, 6).alias("prob"))


FULL_SQL = f"with a as (select o_orderkey as row_id, 0.5::double as pa from orders where o_totalprice > 250000), b as (select o_orderkey as row_id, 0.02::double as pb from orders where {H.uniform_sql('o_orderkey')} <= 0.02) select row_id, round(1.0 - (1.0 - coalesce(pa, 0.0)) * (1.0 - coalesce(pb, 0.0)), 6) as prob from a full join b using (row_id)"


# --- UDFs, sources and stores --------------------------------------------------------


def probit_udf(spark, sf):
    return typed(spark, sf, "lineitem").agg(F.round(F.sum(udfs.probit_logcdf(1.0)((F.col("l_discount") - 0.05) * 40)), 3).alias("logcdf"))


PROBIT_SQL = "with x as (select (l_discount - 0.05) * 40 as t from lineitem) select round(sum(case when t < 0 then t - ln(2.0) else ln(1 - 0.5 * exp(-t)) end), 3) as logcdf from x"


def medoid_udaf(spark, sf):
    cells = sk.build(up.orders(spark, sf), ONE).persist()
    norms = recover.bucket_norms(sk.values(cells, ONE), 1.0).persist()
    few = recover.candidates(up.ids(up.orders(spark, sf)), norms, ONE, recover.threshold_value(norms, ONE))
    rows = few.select("row_id", sk.reps(ONE).alias("rep")).select("row_id", "rep", sk.bucket(ONE).alias("bucket"), sk.sign(ONE).alias("sg")).join(sk.packed(cells, ONE), ["rep", "bucket"]).select("row_id", "rep", F.transform("vec", lambda x: x * F.col("sg")).alias("vec"))
    return rows.groupBy("row_id").agg(udfs.medoid(1.0)("rep", "vec").alias("rep"))


def udtf_updates(spark, sf):
    from pyspark.sql.functions import col

    udfs.register(spark)
    table(spark, sf, "lineitem").select("l_partkey", "l_quantity", "l_discount", "l_tax").createOrReplaceTempView("wide_lines")
    out = spark.sql("select u.row_id, u.col_id, u.delta from wide_lines w, lateral explode_updates(w.l_partkey, array(w.l_quantity, w.l_discount, w.l_tax)) u")
    return out.select(col("row_id"), col("col_id"), F.round("delta", 4).alias("delta"))


UDTF_SQL = " union all ".join(f"select l_partkey as row_id, {i} as col_id, round({c}, 4) as delta from lineitem where {c} <> 0" for i, c in enumerate(("l_quantity", "l_discount", "l_tax")))


def grouped_reduce(spark, sf):
    rows = features.w2_documents(spark, sf)
    return merge_reduce(rows, 100, 60).select("row_id", F.round("weight", 4).alias("weight"))


def sql_functions(spark, sf):
    udfs.register(spark)
    up.exact_rows(up.orders(spark, sf), 7).createOrReplaceTempView("order_rows")
    return spark.sql("select row_id, round(lp_norm(vec, 1.0D), 2) as l1, poly_bucket(row_id, 42, 3, 2000) as b from order_rows")


SQL_FUNCTIONS_SQL = f"select l_orderkey as row_id, round(sum(abs(v)), 2) as l1, cast({H.bucket_sql('l_orderkey', 3, 2000)} as integer) as b from (select l_orderkey, l_linenumber, sum(l_extendedprice) as v from lineitem group by 1, 2) group by l_orderkey"


def python_source(spark, sf):
    """The updates of events replayed by number: a Python source deals the numbers, the table has the updates."""
    from ..sources.replay import NumberSource
    from ..sources.tables import typed
    from ..streaming.streams import user_day_updates

    spark.dataSource.register(NumberSource)
    log = user_day_updates(typed(spark, sf, "events"), up.event_types(spark, sf))
    lo, hi = log.agg(F.min("event_id"), F.max("event_id")).first()
    numbers = spark.read.format("replay_numbers").options(start=lo or 0, stop=-1 if hi is None else hi + 1).load()
    return log.join(numbers, F.col("event_id") == F.col("number")).groupBy("row_id", "col_id").agg(F.round(F.sum("delta"), 4).alias("v"))


def sketch_store(spark, sf):
    path = formats.scratch(spark, "sketch")
    formats.save_sketch(sk.build(up.orders(spark, sf), ONE), ONE, path)
    cells, _ = formats.load_sketch(spark, path, ONE)
    return cells


def bucketed_updates(spark, sf):
    t = formats.bucketed(up.orders(spark, sf).select("row_id", "col_id", "delta"), "lpstream_updates")
    return t.groupBy("row_id").agg(F.round(F.sum("delta"), 2).alias("v"))


DATE_SQL = SHARED["fn_date_parts"].replace("datediff(day,", "datediff('day',")

PAIRS = {
    "fn_date_parts": (lambda spark, sf: sql(spark, sf, SHARED["fn_date_parts"]).withColumns({c: F.col(c).cast("bigint") for c in "ymdq"}), DATE_SQL),
    "fn_text_features": (text_features, SHARED["fn_text_features"]),
    "fn_hash_poly": (hash_poly, HASH_SQL),
    "fn_loss_columns": (loss_columns, LOSS_SQL),
    "fn_array_norms": (array_norms, ARRAY_SQL),
    "fn_array_misc": (array_misc, ARRAY_MISC_SQL),
    "fn_map_sparse": (map_sparse, MAP_SQL),
    "fn_json_props": (json_props, "select event_id, cast(json_extract_string(props, '$.k') as int) as k1, cast(json_extract_string(props, '$.k') as int) as k2, concat('{\"t\":\"', event_type, '\"}') as j from events"),
    "fn_struct_spec": (struct_spec, "select o_orderkey as row_id, o_totalprice as norm_p, 'lp' as origin from orders"),
    "fn_url_html": (url_html, "select page_id, (length(url) - length(replace(url, '/', '')))::int as depth, len(string_split(html, '<p>'))::int - 1 as n_p, regexp_extract(url, '://([^/?#]*)', 1) as host from pages"),
    "prj_features_events": (features_events, EVENTS_SQL),
    "prj_features_conversations": (conversations_matrix, CONV_SQL),
    "prj_label_fold": (label_fold, cs.fold_query()),
    "prj_features_pages": (pages_matrix, cs.pages_query()),
    "prj_features_documents": (lambda s, d: shown(features.w2_documents(s, d), 6), cs.documents_query()),
    "prj_hash_tokens": (hash_tokens, HASH_TOKENS_SQL),
    "flt_carve_uniform": (carve_uniform, CARVE_SQL),
    "join_left_outer_zero_buckets": (zero_buckets, f"{_FULL} select r.rep, b.bucket, round(coalesce(n.norm, 0.0), 4) as norm from reps r cross join (select range::int as bucket from range(50)) b left join norms n on n.rep = r.rep and n.bucket = b.bucket"),
    "join_semi_heavy_buckets": (heavy_buckets, f"{_FULL} select row_id, count(*) as heavy from probe p where exists (select 1 from norms n, thr where n.rep = p.rep and n.bucket = p.bucket and n.norm >= m0) group by row_id"),
    "join_anti_missed_heavy": (missed_heavy, missed_sql()),
    "join_theta_rep_pairs": (rep_pairs, f"{_FULL}, {q.candidates(ONE, None)}, {q.representatives(ONE)} select row_id, rep, round(m, 2) as m from med"),
    "join_full_outer_mixture": (full_outer_mixture, FULL_SQL),
    "udf_probit_logcdf": (probit_udf, PROBIT_SQL),
    "udaf_medoid": (medoid_udaf, f"{_FULL}, {q.candidates(ONE, None)}, {q.representatives(ONE)} select row_id, rep from rep_rows"),
    "udtf_explode_updates": (udtf_updates, UDTF_SQL),
    "sql_functions": (sql_functions, SQL_FUNCTIONS_SQL),
    "src_updates_python_source": (python_source, f"select row_id, col_id, round(sum(delta), 4) as v from ({q.USER_DAYS}) group by row_id, col_id"),
    "src_sketch_store": (sketch_store, f"with upd as ({q.ORDERS}), {q.sketch(ONE)} select rep, bucket, col_id, val from sk"),
    "src_bucketed_updates": (bucketed_updates, "select l_orderkey as row_id, round(sum(l_extendedprice), 2) as v from lineitem group by 1"),
}
ROWS_ONLY = {
    "fn_hash_fast": hash_fast,
    "prj_features_lineitem": lambda s, d: shown(features.w1_lineitem(s, d), 7),
    "prj_features_embeddings": lambda s, d: shown(features.w13_embeddings(s, d), 64),
    "grouped_reduce": grouped_reduce,
}


def queries() -> dict:
    shared = {k: (lambda spark, sf, t=t: sql(spark, sf, t)) for k, t in SHARED.items()}
    return shared | {k: f for k, (f, _) in PAIRS.items()} | ROWS_ONLY


def oracle_sql() -> dict[str, str]:
    return SHARED | {k: t for k, (_, t) in PAIRS.items()}
