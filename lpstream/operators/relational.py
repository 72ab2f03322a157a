"""The relational operators around the methods: scans, projections, joins,
aggregates, windows, sorts and sets, each on the table it serves.

`SHARED` holds texts that Spark SQL and DuckDB read alike; `PAIRS` holds DataFrame
plans beside their DuckDB text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..sources import updates as up
from ..sources.tables import sql, table, typed

SHARED: dict[str, str] = {
    # --- projections and filters
    "src_parquet_scan": "select l_orderkey, l_linenumber, l_extendedprice from lineitem where l_quantity > 45",
    "flt_pushdown_dates": "select l_orderkey as row_id, l_linenumber - 1 as col_id, l_extendedprice as delta from lineitem where l_shipdate >= timestamp '1997-01-01 00:00:00' and l_shipdate < timestamp '1997-03-01 00:00:00'",
    "flt_in_like_null": "select o_orderkey, o_orderstatus from orders where o_orderstatus in ('O', 'F') and o_orderpriority like '1%' and o_totalprice between 1000 and 200000 and o_custkey is not null and not (o_orderstatus is not distinct from 'P')",
    "flt_having_heavy": "select l_orderkey, round(sum(l_extendedprice), 2) as norm from lineitem group by l_orderkey having sum(l_extendedprice) > 300000",
    "prj_onehot": "select l_orderkey, l_linenumber, cast(l_returnflag = 'A' as int) as flag_a, cast(l_returnflag = 'N' as int) as flag_n, cast(l_returnflag = 'R' as int) as flag_r, cast(l_linestatus = 'O' as int) as status_o from lineitem",
    "prj_case_cast": "select o_orderkey, case when o_totalprice > 150000 then 'big' when o_totalprice > 50000 then 'mid' else 'small' end as size, cast(o_totalprice as decimal(18, 2)) as price, coalesce(nullif(o_orderstatus, 'P'), 'none') as status, cast(o_custkey as varchar(20)) as cust from orders",
    # --- joins
    "join_inner_features": "select n_name, count(*) as n, round(sum(l_quantity), 2) as quantity, round(avg(p_size), 4) as size from lineitem join part on l_partkey = p_partkey join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by n_name",
    "join_right_outer_labels": "select d.doc_id, l.quality, l.toxic from labels l right join documents d on l.doc_id = d.doc_id",
    "join_semi_orders": "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 100000)",
    "join_anti_orders": "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)",
    "join_range_windows": "select w.k, count(*) as n, round(sum(value), 2) as mass from events join (select 1 as k, timestamp '2024-01-02 00:00:00' as a, timestamp '2024-01-09 00:00:00' as b union all select 2, timestamp '2024-01-05 00:00:00', timestamp '2024-01-20 00:00:00') w on ts >= w.a and ts < w.b group by w.k",
    "join_interval_events": "select c.event_id as click, p.event_id as purchase from events c join events p on c.user_id = p.user_id and p.ts >= c.ts and p.ts < c.ts + interval '1' hour where c.event_type = 'click' and p.event_type = 'purchase'",
    # --- aggregates
    "agg_two_phase": "select row_id, cast(sum(part) as bigint) as n from (select l_orderkey as row_id, l_suppkey % 4 as site, count(*) as part from lineitem group by l_orderkey, l_suppkey % 4) s group by row_id",
    "agg_distinct_exact": "select count(distinct l_orderkey) as n_rows, count(distinct l_orderkey * 8 + l_linenumber) as nnz, count(*) as n_updates from lineitem",
    "agg_grouping_sets": "select l_returnflag, l_linestatus, grouping(l_returnflag) as g1, grouping(l_linestatus) as g2, round(sum(l_extendedprice), 0) as mass from lineitem group by grouping sets ((l_returnflag, l_linestatus), (l_returnflag), ())",
    "agg_cube": "select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)",
    "agg_rollup": "select year(l_shipdate) as y, month(l_shipdate) as m, count(*) as n, round(sum(l_quantity), 2) as q from lineitem group by rollup (year(l_shipdate), month(l_shipdate))",
    "agg_filter_clause": "select user_id, sum(value) filter (where event_type = 'click') as clicks, count(*) filter (where event_type = 'error') as errors from events group by user_id",
    "agg_norm_table": "select count(*) as n, round(sum(abs(v)), 0) as l1, round(sum(pow(abs(v), 1.5)), -3) as l15, round(sum(v * v), -6) as l2 from (select l_orderkey, l_linenumber, sum(l_extendedprice) as v from lineitem group by l_orderkey, l_linenumber) m",
    "agg_hash_vs_sort": "select l_suppkey, max(l_returnflag) as f, min(l_linestatus) as s, count(*) as n from lineitem group by l_suppkey",
    "agg_moments_corr": "select round(stddev_samp(l_extendedprice), 3) as sd, round(var_pop(l_discount), 8) as vp, round(corr(l_quantity, l_extendedprice), 6) as c, round(covar_pop(l_quantity, l_tax), 6) as cv from lineitem",
    # --- windows
    "win_rank_scaled": "select o_orderkey, row_number() over (order by o_totalprice desc, o_orderkey) as rn, rank() over (order by o_orderpriority) as rk, dense_rank() over (order by o_orderpriority) as dr from orders",
    "win_percent_rank_ntile": "select c_custkey, round(percent_rank() over (partition by c_mktsegment order by c_acctbal), 8) as pr, round(cume_dist() over (partition by c_mktsegment order by c_acctbal), 8) as cd, ntile(7) over (partition by c_mktsegment order by c_acctbal, c_custkey) as nt from customer",
    "win_lag_lead_delta": "select event_id, round(value - coalesce(lag(value) over (partition by user_id, event_type order by ts, event_id), 0), 6) as delta, lead(event_id) over (partition by user_id, event_type order by ts, event_id) as next_id from events",
    "win_running_norm": "select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row), 4) as running from events",
    "win_rows_frame": "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 5 preceding and 1 preceding), 4) as mean5 from events",
    "win_first_last_nth": "select event_id, first_value(event_type) over w as f, last_value(event_type) over w as l, nth_value(event_type, 2) over w as n2 from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)",
    # --- sorts and sets
    "top_k_scaled": "select l_orderkey, l_linenumber, l_extendedprice from lineitem order by l_extendedprice desc, l_orderkey, l_linenumber, l_suppkey limit 50",
    "top_k_per_site": "select site, row_id, norm from (select site, row_id, norm, row_number() over (partition by site order by norm desc, row_id) as k from (select l_suppkey % 4 as site, l_orderkey as row_id, round(sum(l_extendedprice), 2) as norm from lineitem group by l_suppkey % 4, l_orderkey) a) b where k <= 20",
    "sort_nulls_multi": "select doc_id, quality from (select d.doc_id, l.quality from documents d left join labels l on d.doc_id = l.doc_id) x order by quality desc nulls last, doc_id",
    "limit_offset": "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 25 offset 40",
    "set_union_all_sites": "select l_orderkey as row_id, l_linenumber as col_id from lineitem where l_suppkey % 4 = 0 union all select l_orderkey, l_linenumber from lineitem where l_suppkey % 4 = 1 union all select l_orderkey, l_linenumber from lineitem where l_suppkey % 4 = 2 union all select l_orderkey, l_linenumber from lineitem where l_suppkey % 4 = 3",
    "set_union_distinct_ids": "select o_custkey as id from orders where o_totalprice > 200000 union select c_custkey from customer where c_acctbal > 9000",
    "set_intersect_samples": "select o_custkey as id from orders where o_totalprice > 100000 intersect select c_custkey from customer where c_acctbal > 5000",
    "set_except_samples": "select c_custkey as id from customer except select o_custkey from orders",
    "set_except_all_replay": "select l_orderkey, l_linenumber from lineitem except all select l_orderkey, l_linenumber from lineitem where l_returnflag = 'R'",
    "set_intersect_all": "select l_orderkey, l_linenumber from lineitem where l_suppkey % 2 = 0 intersect all select l_orderkey, l_linenumber from lineitem where l_returnflag <> 'R'",
}


def formats_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    """The update log through CSV, JSON lines and ORC; counts and sums by format."""
    from ..sources.formats import roundtrip

    return roundtrip(up.orders(spark, sf).select("row_id", "col_id", "delta"))


def from_table(spark, sf):
    return up.from_wide(typed(spark, sf, "lineitem").select("l_partkey", "l_quantity", "l_discount", "l_tax"), "l_partkey", ["l_quantity", "l_discount", "l_tax"])


def row_sums(spark, sf):
    return up.orders(spark, sf).groupBy("row_id", "col_id").agg(F.round(F.sum("delta"), 2).alias("v"))


def pivot_matrix(spark, sf):
    log = up.orders(spark, sf)
    wide = log.groupBy("row_id").pivot("col_id", list(range(7))).agg(F.round(F.sum("delta"), 2))
    return wide.select("row_id", *[F.col(str(j)).alias(f"c{j}") for j in range(7)])


PIVOT_SQL = "select l_orderkey as row_id, " + ", ".join(f"round(sum(case when l_linenumber = {j + 1} then l_extendedprice end), 2) as c{j}" for j in range(7)) + " from lineitem group by l_orderkey"


def gram(spark, sf):
    x = [F.lit(1.0).cast("double"), F.col("l_quantity") / 50, F.col("l_discount") * 10, F.col("l_tax") * 10]
    return typed(spark, sf, "lineitem").agg(*[F.round(F.sum(x[i] * x[j]), 3).alias(f"g{i}{j}") for i in range(4) for j in range(i, 4)])


_X = ["1.0::double", "l_quantity / 50", "l_discount * 10", "l_tax * 10"]
GRAM_SQL = "select " + ", ".join(f"round(sum(({_X[i]}) * ({_X[j]})), 3) as g{i}{j}" for i in range(4) for j in range(i, 4)) + " from lineitem"


def pack_row(spark, sf):
    cells = up.orders(spark, sf).groupBy("row_id", "col_id").agg(F.round(F.sum("delta"), 2).alias("v"))
    packed = cells.groupBy("row_id").agg(F.array_sort(F.collect_list(F.struct("col_id", "v"))).alias("r"))
    return packed.select("row_id", F.array_join(F.transform("r", lambda x: x["col_id"].cast("string")), ",").alias("cols"), F.size("r").alias("nnz"))


def unpack_row(spark, sf):
    return table(spark, sf, "embeddings").select("vec_id", F.posexplode("embedding").alias("pos", "v")).select("vec_id", "pos", F.round(F.col("v").cast("double"), 5).alias("v"))


def broadcast_conditioner(spark, sf):
    log = up.orders(spark, sf)
    p = spark.createDataFrame([(j, 0.5**j) for j in range(7)], "col_id int, coef double")
    return log.join(F.broadcast(p), "col_id").groupBy("row_id").agg(F.round(F.sum(F.col("delta") * F.col("coef")) * 6400, 0).alias("v"))


def sortmerge_rows(spark, sf):
    rows = up.exact_rows(up.orders(spark, sf), 7)
    few = typed(spark, sf, "orders").filter("o_totalprice > 150000").select(F.col("o_orderkey").alias("row_id"))
    return rows.hint("merge").join(few, "row_id").select("row_id", *[F.round(F.col("vec")[j], 2).alias(f"c{j}") for j in range(7)])


SORTMERGE_SQL = "select l_orderkey as row_id, " + ", ".join(f"round(sum(case when l_linenumber = {j + 1} then l_extendedprice else 0.0 end), 2) as c{j}" for j in range(7)) + " from lineitem where l_orderkey in (select o_orderkey from orders where o_totalprice > 150000) group by l_orderkey"


def shuffle_hash(spark, sf):
    lines = typed(spark, sf, "lineitem").select("l_orderkey", "l_quantity")
    o = typed(spark, sf, "orders").select("o_orderkey", "o_orderpriority")
    return lines.join(o.hint("shuffle_hash"), lines.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.sum("l_quantity").alias("q"))


def nested_loop_panel(spark, sf):
    """Rows against a panel of query vectors: one scan for all of them (the panel is a literal)."""
    panel = F.explode(F.array(*[F.struct(F.lit(k).alias("z"), F.lit(float(k)).alias("a"), F.lit(1.0 - k / 4).alias("b")) for k in range(5)]))
    t = F.col("z.a") * F.col("l_discount") + F.col("z.b") * F.col("l_tax")
    return typed(spark, sf, "lineitem").select("l_discount", "l_tax", panel.alias("z")).groupBy(F.col("z.z").alias("z")).agg(F.round(F.sum(F.abs(t)), 3).alias("loss"))


def asof_snapshot(spark, sf):
    """Latest order at or before each event's instant shifted into the orders' years, by union and a running last value."""
    o = typed(spark, sf, "orders").select(F.col("o_custkey").alias("k"), F.unix_seconds(F.col("o_orderdate").cast("timestamp")).alias("t"), F.col("o_orderkey").alias("key"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("event_id"))
    e = typed(spark, sf, "events").select(F.col("user_id").alias("k"), (F.unix_seconds(F.col("ts").cast("timestamp")) - 86400 * 365 * 25).alias("t"), F.lit(None).cast("long").alias("key"), F.lit(1).alias("side"), "event_id")
    w = Window.partitionBy("k").orderBy("t", "side", F.col("key").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    return o.unionByName(e).withColumn("latest", F.last("key", ignorenulls=True).over(w)).filter("side = 1").select("event_id", "latest")


ASOF_SQL = """with o as (select o_custkey as k, epoch(o_orderdate)::bigint as t, max(o_orderkey) as key from orders group by 1, 2),
e as (select event_id, user_id as k, floor(epoch(ts))::bigint - 86400 * 365 * 25 as t from events)
select e.event_id, o.key as latest from e asof left join o on e.k = o.k and e.t >= o.t"""


def median_estimates(spark, sf):
    return typed(spark, sf, "events").groupBy("user_id").agg(F.round(F.median("value"), 6).alias("m"), F.round(F.percentile("value", F.lit(0.65)), 6).alias("q65"))


def collect_rows(spark, sf):
    e = typed(spark, sf, "events")
    order = F.struct("ts", "event_id")
    return e.groupBy("user_id").agg(F.max_by("event_type", order).alias("last_type"), F.min_by("event_id", order).alias("first_id"), F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("types"))


def histogram(spark, sf):
    """Counts of row norms by equal widths (floor arithmetic, so that other engines agree)."""
    normed = up.orders(spark, sf).groupBy("row_id").agg(F.sum("delta").alias("norm"))
    return normed.groupBy(F.least(F.floor(F.col("norm") / 50_000), F.lit(19)).cast("int").alias("bin")).count().withColumnRenamed("count", "n")


def range_frame(spark, sf):
    e = typed(spark, sf, "events").withColumn("t", F.unix_seconds(F.col("ts").cast("timestamp")))
    w = Window.partitionBy("user_id").orderBy("t").rangeBetween(-86400, 0)
    return e.select("event_id", F.round(F.sum("value").over(w), 4).alias("day_sum"))


def tail_window(spark, sf):
    n = up.orders(spark, sf).groupBy("row_id").agg(F.sum("delta").alias("norm"))
    w = Window.orderBy(F.desc("norm"), "row_id")
    return n.withColumn("k", F.row_number().over(w)).agg(F.round(F.sum(F.when(F.col("k") > 100, F.col("norm")).otherwise(0.0)), 0).alias("tail"), F.round(F.sum("norm"), 0).alias("whole"))


def waterfill(spark, sf):
    """Capped norms by cumulative sums: the tail after each rank, and whether the row exceeds its cap."""
    n = table(spark, sf, "customer").filter("c_acctbal > 0").select(F.col("c_custkey").alias("row_id"), F.col("c_acctbal").alias("norm"))
    return waterfilled(n)


def waterfilled(n: DataFrame, level: int = 20, parts: int = 64) -> DataFrame:
    """(row_id, norm) with rank, tail after the rank and whether the row is capped.

    Ranks and tails are those inside ranges of norms plus what the ranges above and
    below hold, so no task sorts all rows; a frame that only grows is one pass, one
    that shrinks is summed anew for every row.  Tails are exact decimals.
    """
    n = n.withColumn("exact", F.col("norm").cast("decimal(28,10)"))
    at = [float(x) for x in (n.agg(F.percentile_approx("norm", [i / parts for i in range(1, parts)], 10_000)).first()[0] or [])]
    ranged = n.withColumn("range", sum((F.when(F.col("norm") > x, 1).otherwise(0) for x in sorted(set(at))), F.lit(0)))
    sums = ranged.groupBy("range").agg(F.count("*").alias("c"), F.sum("exact").alias("mass"))
    low, high = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1), Window.orderBy(F.desc("range")).rowsBetween(Window.unboundedPreceding, -1)
    around = sums.select("range", F.coalesce(F.sum("c").over(high), F.lit(0)).alias("above"), F.coalesce(F.sum("mass").over(low), F.lit(0)).alias("below"))  # a row a range
    down = Window.partitionBy("range").orderBy(F.desc("norm"), "row_id")
    up_ = Window.partitionBy("range").orderBy("norm", F.desc("row_id")).rowsBetween(Window.unboundedPreceding, -1)
    inside = ranged.withColumns({"rk": F.row_number().over(down), "rest": F.coalesce(F.sum("exact").over(up_), F.lit(0))})
    whole = inside.join(F.broadcast(around), "range").withColumns({"k": (F.col("above") + F.col("rk")).cast("bigint"), "after": F.col("below") + F.col("rest")})
    return whole.select("row_id", "k", F.round(F.col("after").cast("double"), 2).alias("tail"), (F.col("norm") * (level - F.col("k")) >= F.col("after").cast("double")).alias("capped"))


WATERFILL_SQL = """with n as (select c_custkey as row_id, c_acctbal as norm from customer where c_acctbal > 0),
w as (select *, row_number() over (order by norm desc, row_id) as k, coalesce(sum(norm) over (order by norm desc, row_id rows between 1 following and unbounded following), 0.0) as tail from n)
select row_id, k, round(tail, 2) as tail, norm * (20 - k) >= tail as capped from w"""

PAIRS: dict[str, tuple] = {
    "src_formats_roundtrip": (formats_roundtrip, "select f as format, count(*) as n, round(sum(l_extendedprice), 0) as mass from lineitem, (values ('csv'), ('json'), ('orc')) v(f) group by f"),
    "src_updates_from_table": (from_table, " union all ".join(f"select l_partkey as row_id, {i} as col_id, {c} as delta from lineitem" for i, c in enumerate(("l_quantity", "l_discount", "l_tax")))),
    "agg_row_sums": (row_sums, "select l_orderkey as row_id, l_linenumber - 1 as col_id, round(sum(l_extendedprice), 2) as v from lineitem group by 1, 2"),
    "agg_pivot_matrix": (pivot_matrix, PIVOT_SQL),
    "agg_gram": (gram, GRAM_SQL),
    "prj_pack_row": (pack_row, "select row_id, string_agg(col_id::varchar, ',' order by col_id) as cols, count(*)::int as nnz from (select distinct l_orderkey as row_id, l_linenumber - 1 as col_id from lineitem) group by row_id"),
    "prj_unpack_row": (unpack_row, "select vec_id, (i - 1)::int as pos, round(embedding[i]::double, 5) as v from (select vec_id, embedding, unnest(range(1, 65)) as i from embeddings)"),
    "join_broadcast_conditioner": (broadcast_conditioner, "select l_orderkey as row_id, round(sum(l_extendedprice * pow(0.5::double, l_linenumber - 1)) * 6400, 0) as v from lineitem group by 1"),
    "join_sortmerge_rows": (sortmerge_rows, SORTMERGE_SQL),
    "join_shuffle_hash": (shuffle_hash, "select o_orderpriority, sum(l_quantity) as q from lineitem join orders on l_orderkey = o_orderkey group by 1"),
    "join_nested_loop_panel": (nested_loop_panel, "select z, round(sum(abs(z * l_discount + (1.0 - z / 4.0) * l_tax)), 3) as loss from lineitem, (values (0), (1), (2), (3), (4)) p(z) group by z"),
    "join_asof_snapshot": (asof_snapshot, ASOF_SQL),
    "agg_median_estimates": (median_estimates, "select user_id, round(median(value), 6) as m, round(quantile_cont(value, 0.65), 6) as q65 from events group by 1"),
    "agg_percentile_threshold": (lambda s, d: typed(s, d, "orders").agg(F.round(F.percentile("o_totalprice", F.lit(0.65)), 6).alias("q")), "select round(quantile_cont(o_totalprice, 0.65), 6) as q from orders"),
    "agg_collect_rows": (collect_rows, "select user_id, arg_max(event_type, (ts, event_id)) as last_type, arg_min(event_id, (ts, event_id)) as first_id, string_agg(distinct event_type, ',' order by event_type) as types from events group by 1"),
    "agg_histogram": (histogram, "select least(floor(norm / 50000), 19)::int as bin, count(*) as n from (select sum(l_extendedprice) as norm from lineitem group by l_orderkey) group by 1"),
    "win_range_frame": (range_frame, "select event_id, round(sum(value) over (partition by user_id order by floor(epoch(ts))::bigint range between 86400 preceding and current row), 4) as day_sum from events"),
    "win_tail_mass": (tail_window, "select round(sum(case when k > 100 then norm else 0.0 end), 0) as tail, round(sum(norm), 0) as whole from (select norm, row_number() over (order by norm desc, row_id) as k from (select l_orderkey as row_id, sum(l_extendedprice) as norm from lineitem group by 1))"),
    "win_waterfill": (waterfill, WATERFILL_SQL),
}

#: Approximate twins, without an exact SQL equal.
APPROXIMATE = {
    "agg_distinct_approx": lambda s, d: typed(s, d, "lineitem").agg(F.approx_count_distinct("l_orderkey", 0.01).alias("n_rows")),
    "agg_percentile_approx": lambda s, d: typed(s, d, "orders").agg(F.percentile_approx("o_totalprice", 0.65, 10_000).alias("q")),
}


#: Whole numbers that the two engines type differently; both give 64 bits.
WIDE = {"agg_grouping_sets": ["g1", "g2"], "agg_rollup": ["y", "m"], "win_rank_scaled": ["rn", "rk", "dr"], "win_percent_rank_ntile": ["nt"]}


def queries() -> dict:
    shared = {k: (lambda spark, sf, k=k, t=t: sql(spark, sf, t).withColumns({c: F.col(c).cast("bigint") for c in WIDE.get(k, [])})) for k, t in SHARED.items()}
    return shared | {k: f for k, (f, _) in PAIRS.items()} | APPROXIMATE


def oracle_sql() -> dict[str, str]:
    return SHARED | {k: t for k, (_, t) in PAIRS.items()}
