"""Queries that once made their data up read the given tables."""

import math

from lpstream.functions import params
from lpstream.operators import functions_queries
from lpstream.plans import numeric
from lpstream.streaming import streams


def rows(spark, sf, name, column):
    return spark.read.parquet(f"{sf}/{name}.parquet").select(column).distinct().count()


def test_harmonic_counts_orders(spark, sf):
    n = rows(spark, sf, "orders", "o_orderkey")
    got = numeric.diag_harmonic(spark, sf).collect()
    assert all(math.isclose(r.ratio, r.x * r.k / n, rel_tol=1e-3, abs_tol=1e-4) for r in got) and len(got) == 4


def test_conditioning_has_the_tables_widths(spark, sf):
    got = {r.matrix: r.d for r in numeric.params_conditioning(spark, sf).collect()}
    assert got == {"user_days": rows(spark, sf, "events", "event_type"), "orders": 7, "embeddings": 64}


def test_previous_sizes_are_of_the_order_matrix(spark, sf):
    n = rows(spark, sf, "lineitem", "l_orderkey")
    got = numeric.params_previous(spark, sf).collect()
    assert len(got) == 12 and {r.constant_factor_rows for r in got} == {params.previous_sizes(0.1, 7, n)["constant_factor_rows"]}


def test_theory_takes_the_tables_lengths(spark, sf):
    got = numeric.params_theory(spark, sf).collect()
    assert {r.n for r in got if r.matrix == "orders"} == {rows(spark, sf, "lineitem", "l_orderkey")} and len(got) == 9
    assert {r.n for r in got if r.matrix == "events"} == {rows(spark, sf, "events", "event_id")}


def test_rate_stream_reads_every_file(spark, sf, tmp_path):
    e = spark.read.parquet(f"{sf}/events.parquet")
    e.repartition(3, "event_id").write.parquet(f"{tmp_path}/events.parquet")
    a, b = (sorted(map(tuple, streams.rate_stream(spark, d).collect())) for d in (sf, str(tmp_path)))
    assert a == b and len(a) == e.select("event_type").distinct().count()


def test_python_source_replays_events(spark, sf):
    got = functions_queries.python_source(spark, sf).agg({"v": "sum"}).first()[0]
    want = spark.read.parquet(f"{sf}/events.parquet").agg({"value": "sum"}).first()[0]
    assert math.isclose(got, want, rel_tol=1e-9)
