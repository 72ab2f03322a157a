"""The packed scans of an experiment against the operators on rows."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from lpstream.functions.hashing import FIELD, PRIME, Hashes
from lpstream.functions.params import SketchSpec
from lpstream.operators import baselines as bl, leverage, packed, sketch as sk, solvers, subspace
from lpstream.plans import experiments
from lpstream.sources import features

SF = "/root/testdata/sf0.001"


def sorted_rows(df, *cols):
    return sorted((r.row_id, *[round(float(r[c]), 9) for c in cols]) for r in df.collect())


def pairs(row, value):
    return sorted((int(i), round(float(v), 9)) for i, v in zip(row, value))


@pytest.mark.parametrize("workload, p", [("w1", 1.0), ("w3", 1.5)])
def test_packed_samples_are_those_of_rows(spark, workload, p):
    rows = experiments.WORKLOADS[workload](spark, SF, "lp").persist()
    table = packed.pack(rows).persist()
    d = packed.width(table)
    n, least = packed.extent(table, d)
    assert (n, least, d) == (*rows.agg(F.count("*"), F.min("row_id")).first(), features.width(rows))
    m = subspace.conditioner(packed.embedding(table, d, p))
    assert np.allclose(m, leverage.rows_conditioner(rows, d, p), rtol=1e-6)
    (row, _, prob), _ = packed.uniform(table, d, n, [(50, 3), (200, 4)])
    assert pairs(row, prob) == sorted_rows(bl.uniform_rows(rows, 50, n, 3), "prob")
    (row, x, _, prob), _ = packed.priority(table, d, [(60, 5, p, m), (20, 6, p, m)])
    assert pairs(row, 1 / prob) == sorted_rows(bl.offline_sample(leverage.scores(rows, p, m), 60, "priority", 5), "weight")
    (row, _, prob), _ = packed.online(table, d, p, least, [(9, 7), (25, 8)])
    assert pairs(row, prob) == sorted_rows(bl.online_rows(rows, 9, p, seed=7), "prob")
    if workload == "w3":  # more than 256 batches: two stages of the tree
        (row, _, weight), _ = packed.merge_reduce(table, d, n, 3, [(20, 2), (30, 1)], p)
        assert np.allclose(pairs(row, weight), sorted_rows(bl.merge_reduce(rows, 3, 20, p, 2), "weight"), rtol=1e-6)
    spec = SketchSpec(p=p, r=60, s=3, d=d)
    cells = lambda df: {(r.rep, r.bucket, r.col_id): int(r.val) for r in df.collect()}
    assert cells(packed.sketches(table, [spec])[0]) == cells(sk.build_rows(rows, spec))
    rows.unpersist(), table.unpersist()


def test_an_experiment_reads_its_table_once(spark, monkeypatch):
    """Both sizes of a method share their scans: the source is computed once, and the coreset tree's batches are dealt once."""
    seen = []
    deal = packed.merge_reduce
    monkeypatch.setattr(packed, "merge_reduce", lambda *a: seen.append(a[4]) or deal(*a))
    got = experiments.run(spark, SF, "w3", "lp", 1.0, (50, 200), range(1), ("merge_reduce", "uniform"))
    assert got.count() == 4 and len(seen) == 1 and len(seen[0]) == 2


def test_packed_rows_that_no_sketch_takes(spark):
    bad = spark.createDataFrame([(1, [1.0, float("nan")])], "row_id long, vec array<double>")
    with pytest.raises(Exception, match="invalid update"):
        packed.pack(bad).collect()
    nulls = packed.pack(spark.createDataFrame([(1, [1.0, None])], "row_id long, vec array<double>"))
    assert packed.sketches(nulls, [SketchSpec(r=2, s=1, d=2)])[0].count() == 1
    (row, x, _), = packed.uniform(nulls, 2, 1, [(1, 1)])
    assert len(row) == 1 and np.isnan(x[0, 1])


@pytest.mark.parametrize("sf, workload, p", [("/root/testdata/sf0.01", "w1", 1.0), (SF, "w3", 1.0), (SF, "w3", 1.5)])
def test_full_optimum_takes_few_scans(spark, monkeypatch, sf, workload, p):
    """The optimum over all rows starts from that of a sample: a third of the scans, and no larger a loss."""
    scans, summed = [], solvers.summed
    monkeypatch.setattr(solvers, "summed", lambda *a: scans.append(a[1]) or summed(*a))
    found, evaluate = [], solvers.evaluate_blocks
    monkeypatch.setattr(solvers, "evaluate_blocks", lambda blocks, panel, *a: found.append(panel[0]) or evaluate(blocks, panel, *a))
    assert experiments.run(spark, sf, workload, "lp", p, (50,), range(1), ("uniform",)).count() == 1
    assert len(scans) <= 16
    blocks = solvers.blocks(experiments.WORKLOADS[workload](spark, sf, "lp"), len(found[0])).persist()
    new, old = evaluate(blocks, [found[0], solvers.solve_full(blocks, len(found[0]), "lp", p, -1.0)], "lp", p)
    assert new <= old * (1 + 1e-7)
    blocks.unpersist()


def test_polynomials_of_many_lists():
    """All repetitions at once: the same buckets and signs to the last bit, up to the ends of the field."""
    rng = np.random.default_rng(5)
    for top in (1000, PRIME, PRIME + 5, FIELD):
        row = np.r_[0, 1, top - 1, top // 2, rng.integers(0, top, 3000)]
        h = Hashes(11)
        bucket, sign = h.places_numpy(row, 997, 11)
        for j in range(11):
            a, b = h.place_numpy(row, j, 997)
            assert (a == bucket[j]).all() and (b == sign[j]).all()
        assert (h.buckets_numpy(row, 4000, 3) == [h.bucket_numpy(row, j, 4000) for j in range(3)]).all()
        for p in (1.0, 1.5, 2.0):
            got = np.concatenate([c for _, c in bl.stables_numpy(row, 4, p, 9)], axis=1)
            assert np.allclose(got, [bl.stable_numpy(row, i, p, 9) for i in range(4)], rtol=1e-9, atol=1e-12)
