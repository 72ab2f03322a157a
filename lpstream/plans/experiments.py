"""The experiment grid: reduce, solve the reduced problem, compare losses on the full data.

Every ratio is f(z of the reduced problem) / f(z of the full problem), both on the
full data; the summary takes the median over the repetitions of each size.  The
denominator is the least loss found, so no ratio is below one.  ReLU problems pin
the first coordinate to one: without that, zero solves them and ratios mean nothing.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.params import practical
from ..operators import packed, recover, sampler, solvers, subspace
from ..sources import features

METHODS = ("uniform", "oblivious", "sampler", "offline", "merge_reduce", "online")
WORKLOADS = {"w1": features.w1_lineitem, "w2": features.w2_documents, "w3": features.w3_events}


def _reductions(method: str, table: DataFrame, loss: str, p: float, grid: list, d: int, n: int, least: int, mixture: str, shared: dict) -> list:
    """(rows, weights, cells) of the reduced problems of one method at the driver, about k rows for each (k, seed) of the grid, from packed rows."""
    q = 1.0 if loss == "logistic" else p
    plain = lambda got: [(x, 1.0 / prob, 0) for _, x, prob in got]
    if method == "uniform":
        return plain(packed.uniform(table, d, n, grid))
    if method == "online":
        return plain(packed.online(table, d, q, least, [(max(1, k // 8), seed) for k, seed in grid]))
    if method == "oblivious":
        return [(x, w, k * d) for (x, w), (k, _) in zip(packed.oblivious(table, d, grid, loss == "lp"), grid)]
    if method == "merge_reduce":
        out = {}
        for batch in {max(2000, 4 * k) for k, _ in grid}:
            mine = [g for g in grid if max(2000, 4 * g[0]) == batch]
            out |= dict(zip(mine, packed.merge_reduce(table, d, n, batch, mine, q)))
        return [(out[g][1], out[g][2], 0) for g in grid]
    share = [max(1, k // 2) if loss != "lp" or mixture == "l1l2" else k for k, _ in grid]
    two = loss == "lp" and mixture == "l1l2"
    if "matrix" not in shared:
        shared["matrix"] = subspace.conditioner(packed.embedding(table, d, q))
        shared["matrix2"] = subspace.conditioner(packed.embedding(table, d, 2.0)) if two else None
    matrix, matrix2 = shared["matrix"], shared["matrix2"]
    if method == "offline":
        wanted = [(s, seed, q, matrix) for s, (_, seed) in zip(share, grid)] + [(s, seed + 7, 2.0, matrix2) for s, (_, seed) in zip(share, grid) if two]
        found = packed.priority(table, d, wanted)
        cells = [0] * len(grid)
    else:
        specs = [practical(s, q, d, seed) for s, (_, seed) in zip(share, grid)] + [practical(s, 2.0, d, seed + 1) for s, (_, seed) in zip(share, grid) if two]
        ids = packed.live_ids(table, d).persist()
        found = []
        for i, (spec, sketch) in enumerate(zip(specs, packed.sketches(table, specs))):
            s = share[i % len(grid)]
            narrow = spec.r * spec.s * d <= recover.NARROW_CELLS
            top = sampler.scaled_rows(sketch, ids if narrow else ids.distinct(), spec, s, matrix if i < len(grid) else matrix2)
            got = sampler.with_cut(top.dropDuplicates(["row_id"]), s).toPandas()
            found.append((got["row_id"].to_numpy(), np.array(list(got["vec"]), float).reshape(-1, d), got["norm_p"].to_numpy(float), got["prob"].to_numpy(float)))
        ids.unpersist()
        cells = [spec.r * spec.s * d for spec in specs[: len(grid)]]
    if two:
        return [(*_mixed(a, b, q, matrix, matrix2), c) for a, b, c in zip(found[: len(grid)], found[len(grid) :], cells)]
    if loss != "lp":
        if "share" not in shared:
            shared["share"] = packed.uniform(table, d, n, [(s, seed) for s, (_, seed) in zip(share, grid)])
        return [(*_mix_uniform(a, u, s, n, q, matrix), c) for a, u, s, c in zip(found, shared["share"], share, cells)]
    return [(x, 1.0 / prob, c) for (_, x, _, prob), c in zip(found, cells)]


def _cut(norm: np.ndarray, prob: np.ndarray) -> float:
    """`sampler.cut_of` of arrays."""
    return float((norm / prob)[prob < 1].max(initial=0.0))


def _own(x: np.ndarray, alpha: float, p: float, matrix: np.ndarray) -> np.ndarray:
    """`sampler.own_probability` of arrays."""
    return np.minimum(1.0, recover.size_numpy(x @ matrix, p).sum(axis=1) / alpha) if alpha > 0 else np.ones(len(x))


def _mix_uniform(lp, uni, k: int, n: int, p: float, matrix: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """`sampler.mix_uniform` of arrays: rows and weights."""
    row, x, norm, prob = lp
    known = dict(zip(row.tolist(), prob.tolist()))
    own = _own(uni[1], _cut(norm, prob), p, matrix)
    first = np.array([known.get(i, o) for i, o in zip(uni[0].tolist(), own.tolist())], float)
    alone = ~np.isin(row, uni[0])
    miss = 1.0 - np.r_[first, prob[alone]]
    return np.concatenate([uni[1], x[alone]]), 1.0 / (1.0 - miss * (1.0 - min(1.0, k / n)))


def _mixed(a, b, p: float, matrix_a: np.ndarray, matrix_b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """`mixed` of arrays: rows and weights."""
    _, at = np.unique(np.r_[a[0], b[0]], return_index=True)
    x = np.concatenate([a[1], b[1]])[at]
    miss = (1.0 - _own(x, _cut(a[2], a[3]), p, matrix_a)) * (1.0 - _own(x, _cut(b[2], b[3]), 2.0, matrix_b))
    return x, 1.0 / (1.0 - miss)


def mixed(a: DataFrame, b: DataFrame, p: float, matrix_a: np.ndarray, matrix_b: np.ndarray) -> DataFrame:
    """Union of an lp and an l2 leverage sample, each row's two probabilities from the row itself."""
    a, b = a.persist(), b.persist()
    rows = a.select("row_id", "vec", F.lit(0).alias("part")).unionByName(b.select("row_id", "vec", F.lit(1).alias("part")))
    one = rows.groupBy("row_id").agg(F.min_by("vec", "part").alias("vec"))
    miss = (1.0 - sampler.own_probability(F.col("vec"), sampler.cut_of(a), p, matrix_a)) * (1.0 - sampler.own_probability(F.col("vec"), sampler.cut_of(b), 2.0, matrix_b))
    return one.withColumn("prob", 1.0 - miss).withColumn("weight", 1.0 / F.col("prob"))


START = 20_000  # rows of the problem whose solution the full optimum is sought from


def _optimum(table: DataFrame, blocks: DataFrame, d: int, n: int, p: float) -> np.ndarray:
    """Minimiser of lp regression on all rows; a uniform sample gives its start only."""
    (_, x, _), = packed.uniform(table, d, n, [(START, 0)])
    x = x[np.isfinite(x).all(axis=1)]
    if len(x) <= d:
        return solvers.solve_full(blocks, d, "lp", p, -1.0)
    start = solvers.solve(x, np.ones(len(x)), "lp", p, last=-1.0)
    scale = float(np.abs(x @ start).mean()) + 1e-12
    return solvers.polish(blocks, start, 0.05 * scale, 1e-6 * scale, p, -1.0)


def run(spark: SparkSession, sf: str, workload: str, loss: str = "logistic", p: float = 1.0, sizes=(50, 200), seeds=range(3), methods=METHODS, mixture: str = "") -> DataFrame:
    """One row a (method, size, seed): ratio, cells, seconds of reduction and of solving."""
    problem = "lp" if loss == "lp" else loss
    rows = WORKLOADS[workload](spark, sf, problem)
    table = packed.pack(rows, "sampler" in methods).persist()
    d = packed.width(table)
    n, least = packed.extent(table, d)
    last = -1.0 if loss == "lp" else None
    first = 1.0 if loss == "relu" else None
    blocks = table.select("block")
    opt = _optimum(table, blocks, d, n, p) if loss == "lp" else solvers.solve_full(blocks, d, loss, p, last) if loss == "logistic" else solvers.solve_rows(packed.unpack(table, d), d, loss, p, first=first)
    shared: dict = {}
    found, meta = [opt], []
    grid = [(k, seed) for k in sizes for seed in seeds]
    drawn, seconds = {}, {}
    for m in methods:
        t0 = time.perf_counter()
        drawn[m] = _reductions(m, table, loss, p, [(k, 1000 * seed + k) for k, seed in grid], d, n, least, mixture, shared)
        seconds[m] = (time.perf_counter() - t0) / len(grid)
    for i, (k, seed) in enumerate(grid):
        for m in methods:
            x, w, cells = drawn[m][i]
            t1 = time.perf_counter()
            z = solvers.solve(x, w, loss, p, last=last, first=first) if len(x) else solvers._start(d, first)
            found.append(z)
            meta.append((workload, loss, float(p), m, k, seed, len(x), cells, seconds[m], time.perf_counter() - t1))
    # One scan for the losses of all solutions.
    vals = np.concatenate([solvers.evaluate_blocks(blocks, found[i : i + 60], loss, p) for i in range(0, len(found), 60)])
    best = float(vals.min())
    out = [(*a[:6], float(v / best), *a[6:]) for a, v in zip(meta, vals[1:])]
    table.unpersist()
    return spark.createDataFrame(out, "workload string, loss string, p double, method string, k int, seed int, ratio double, rows int, cells long, t_reduce double, t_solve double")


def summary(results: DataFrame) -> DataFrame:
    """Median ratio over the repetitions, by method and size."""
    return results.groupBy("workload", "loss", "p", "method", "k").agg(F.round(F.median("ratio"), 4).alias("median_ratio"), F.count("*").alias("repetitions"), F.max("cells").alias("cells"), F.round(F.median("t_reduce"), 3).alias("reduce_seconds"), F.round(F.median("t_solve"), 3).alias("solve_seconds"))
