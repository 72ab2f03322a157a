"""Work that must stay small on large tables, against the plain form of the same result."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from lpstream.functions.params import SketchSpec
from lpstream.operators import baselines, leverage, recover, sampler, sketch as sk, solvers, subspace
from lpstream.sources import features, updates as up


def tops(df, k):
    return [(r.row_id, [round(x, 6) for x in r.vec], round(r.scaled, 6), round(r.norm_p, 6)) for r in sampler.top_rows(df, k).collect()]


def test_conditioned_list_leaves_no_task_whole(spark, sf, monkeypatch):
    """Under a conditioning matrix at p = 2 hardly a row is ruled out by its estimate: tasks hand on k + 1 rows each, not the list."""
    log, k = leverage.long_rows(features.w3_events(spark, sf, "probit")).persist(), 5
    spec = SketchSpec(p=2.0, r=40, s=11, d=6)
    matrix, cells = leverage.embedding_conditioner(log, 6, 2.0), sk.build(log, spec).persist()
    ids = up.ids(log).repartition(3)
    got = sampler.scaled_rows(cells, ids, spec, k, matrix).persist()
    assert got.count() <= 3 * (k + 1)
    monkeypatch.setattr(recover, "NARROW_CELLS", 0)
    whole = sampler.scaled_rows(cells, ids, spec, k, matrix)
    assert whole.count() > 3 * (k + 1)
    assert tops(got, k + 1) == tops(whole, k + 1)


@pytest.mark.parametrize("p", [1.0, 2.0])
def test_mixture_parts_are_short(spark, sf, p):
    """Both parts of a mixture leave the tasks as k + 1 rows each."""
    log, k, spec = up.orders(spark, sf), 5, SketchSpec(p=p, r=60, s=11, d=7)
    got = sampler.scaled_rows(sk.build(log, spec).persist(), up.ids(log).repartition(2), spec, k)
    assert k + 1 <= got.count() <= 2 * (k + 1)


def test_sketches_of_a_mixture_share_a_scan(spark, sf):
    """Several sketches of one log read it once, and are those that the plain sums make."""
    read = spark.sparkContext.accumulator(0)

    def counted(batches):
        for b in batches:
            read.add(b.num_rows)
            yield b

    log = up.orders(spark, sf).select("row_id", "col_id", "delta").localCheckpoint()
    seen = log.mapInArrow(counted, log.schema)
    specs = [SketchSpec(p=1.0, r=60, s=5, d=7), SketchSpec(p=2.0, r=40, s=3, d=7, seed=49)]
    cells = lambda df: sorted((r.rep, r.bucket, r.col_id, int(r.val)) for r in df.collect())
    got = [cells(x) for x in sk.build_many(seen, specs)]
    assert read.value == log.count()
    assert got == [cells(sk.build(log, x, "sql")) for x in specs]


@pytest.mark.parametrize("p", [1.0, 1.5, 2.0])
@pytest.mark.parametrize("s", [1, 2, 5, 6])
def test_medoids_are_the_representatives(spark, p, s):
    """The numpy form picks the repetition that the array expressions pick: lower medians, ties to the first."""
    n, d = 40, 3
    vecs = np.random.default_rng(s).integers(-2, 3, (s, n, d)).astype(float)  # many ties
    cells = spark.createDataFrame([(j, b, c, float(vecs[j, b, c])) for j in range(s) for b in range(n) for c in range(d)], "rep int, bucket int, col_id int, val double")
    spec = SketchSpec(p=p, r=n, s=s | 1, d=d)
    found = spark.range(n).select(F.col("id").alias("row_id"), F.explode(F.sequence(F.lit(0), F.lit(s - 1))).alias("rep"))
    rows = found.join(cells.groupBy("rep", F.col("bucket").cast("long").alias("row_id")).agg(F.transform(F.array_sort(F.collect_list(F.struct("col_id", "val"))), lambda x: x["val"]).alias("vec")), ["rep", "row_id"])
    got = recover.medoids(vecs, spec.p)
    want = {r.row_id: r.rep for r in recover.nearest(rows, spec.p).collect()}
    assert [want[i] for i in range(n)] == got.tolist()


def test_blocks_solve_and_value_like_rows(spark, sf):
    """A logistic optimum and losses from blocks are those from rows."""
    rows = features.w3_events(spark, sf).persist()
    packed = solvers.blocks(rows, 6, 16).persist()
    a, b = solvers.solve_full(rows, 6, "logistic"), solvers.solve_full(packed, 6, "logistic")
    assert np.allclose(a, b, rtol=1e-6, atol=1e-8)
    for loss, p in (("logistic", 1.0), ("lp", 1.5), ("relu", 2.0), ("probit", 2.0)):
        assert np.allclose(solvers.evaluate(rows, [a, -a], loss, p), solvers.evaluate_blocks(packed, [a, -a], loss, p))
    assert not solvers.evaluate_blocks(solvers.blocks(rows.limit(0), 6), [a], "lp")[0]


@pytest.mark.parametrize("p", [1.0, 1.5])
def test_lp_blocks_fit_like_rows(spark, sf, p):
    rows = features.w1_lineitem(spark, sf, "lp").persist()
    a, b = (solvers.solve_full(x, 7, "lp", p, -1.0) for x in (rows, solvers.blocks(rows, 7)))
    assert np.allclose(*(solvers.evaluate(rows, [z], "lp", p) for z in (a, b)), rtol=1e-9)


@pytest.mark.parametrize("p", [1.0, 1.5, 2.0])
def test_sketch_of_rows_is_that_of_entries(spark, sf, p):
    """Bit by bit (powers may differ in the last place between engines), with ids on both sides of 2^31."""
    rows = features.w1_lineitem(spark, sf).withColumn("row_id", F.when(F.col("row_id") % 2 == 0, F.col("row_id")).otherwise(F.col("row_id") % 1000)).persist()
    spec = SketchSpec(p=p, r=50, s=3, d=7)
    cells = lambda df: {(r.rep, r.bucket, r.col_id): int(r.val) for r in df.collect()}
    a, b = cells(sk.build(leverage.long_rows(rows), spec)), cells(sk.build_rows(rows, spec))
    assert a.keys() == b.keys() and all(a[k] == b[k] if p != 1.5 else abs(a[k] - b[k]) <= 1e-9 * abs(a[k]) + 1e6 for k in a)
    odd = spark.createDataFrame([(1, [float("nan"), 1.0])], "row_id long, vec array<double>")
    with pytest.raises(Exception, match="invalid update"):
        sk.build_rows(odd, SketchSpec(d=2)).collect()


def test_mixture_parts_of_rows_are_those_of_entries(spark, sf):
    """Conditioners of both norms and the oblivious sketch, from rows and from entries."""
    rows = features.w3_events(spark, sf, "lp").persist()
    log = leverage.long_rows(rows)
    for p in (1.0, 2.0):
        assert np.allclose(leverage.rows_conditioner(rows, 7, p), leverage.embedding_conditioner(log, 7, p), rtol=1e-6)
    put = lambda df: {(r.level, r.bucket): [*r.vec, r.weight] for r in df.collect()}
    for signed in (False, True):
        a, b = put(baselines.oblivious(log, 50, d=7, signed=signed)), put(baselines.oblivious_rows(rows, 50, d=7, signed=signed))
        assert a.keys() == b.keys() and all(np.allclose(a[k], b[k]) for k in a)
