"""Sampling rows in proportion to their norms, from a sketch alone.

A row's scaled norm is its norm over its own uniform scalar; the rows of the k
largest scaled norms are the sample, the k-th is the cut alpha, the inclusion
probability is min(1, norm / alpha) and the weight its inverse.
"""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from ..functions.hashing import abs_pow, inv_scale
from ..functions.params import SketchSpec
from . import recover, sketch as sk

#: A representative's norm is at most this many times its row's estimate (lp distances are a metric up to the p-th power): more than half
#: of the repetitions have norms of the median E at least, the least median distance is at most 2 E; a little more for rounded distances.
REACH = 3.001
SHORT = 16  # lists up to so many times k are represented whole


def norm_of(vec: Column, p: float) -> Column:
    return F.aggregate(vec, F.lit(0.0), lambda s, x: s + abs_pow(x, p))


def scaled_rows(cells: DataFrame, ids: DataFrame, spec: SketchSpec, k: int, matrix=None, budget: int | None = None, floor: float | None = None) -> DataFrame:
    """(row_id, vec, scaled, norm_p): un-scaled rows with their scaled norms, among them the k + 1 listed rows of largest scaled norm (or all at or above `floor`).

    With a conditioning matrix the norms are those of vec times the matrix, the
    rows are still those of the sketched matrix, from the same repetition.

    Rows that can't be among these are left out by their estimates alone: the
    2k + 2 best estimates give a lower bound of the (k+1)-th scaled norm, and a
    representative's is at most REACH^p times its estimate.  `budget` caps the
    list at so many times k instead (not exact).  Sketches that fit in one task
    are read there as arrays, and each task hands on its own k + 1 best rows.
    """
    view = sk.project(cells, spec, matrix) if matrix is not None else sk.values(cells, spec)
    d = np.asarray(matrix).shape[1] if matrix is not None else spec.d
    norms = recover.bucket_norms(view, spec.p).persist()
    m0 = recover.threshold_value(norms, spec)
    t = sk.hashes(spec).uniform(F.col("row_id")) if spec.scale else F.lit(1.0)
    factor = inv_scale(t, spec.p) if spec.scale else F.lit(1.0)
    if not budget and spec.family == "poly" and spec.r * spec.s * max(d, spec.d) <= recover.NARROW_CELLS:
        near = recover.dense_cells(view, spec, d)
        plain = near if matrix is None else recover.dense_cells(sk.values(cells, spec), spec, spec.d)
        out = recover.top_narrow(ids, near, plain, recover.dense_norms(norms, spec), spec, m0, REACH**spec.p, k + 1, floor)
        return out.select("row_id", F.transform("vec", lambda x: x / factor).alias("vec"), "scaled", (F.col("scaled") * t).alias("norm_p"))
    listed = recover.candidates_narrow(ids, norms, spec, m0)
    if budget:
        listed = recover.best_candidates(listed, budget * k)
    else:
        listed = listed.persist()
        if floor is None and listed.count() <= SHORT * k:
            floor = 0.0  # the same rows: a short list isn't worth the first look
        elif floor is None:
            first = recover.representatives(recover.best_candidates(listed, 2 * k + 2), view, spec, d, fixed=False)
            floor = cut_at(first.select("row_id", norm_of(F.col("vec"), spec.p).alias("scaled")).orderBy(F.desc("scaled"), "row_id").limit(k + 1), k + 1)
        listed = listed.filter((F.col("est_norm") + 1e-6) * REACH**spec.p >= floor)
    rows = recover.representatives(listed, view, spec, d, fixed=False)
    out = rows.withColumn("scaled", norm_of(F.col("vec"), spec.p)).withColumn("norm_p", F.col("scaled") * t)
    if matrix is None:
        return out.select("row_id", F.transform("vec", lambda x: x / factor).alias("vec"), "scaled", "norm_p")
    # The row of the sketched matrix in the chosen repetition.
    here = out.withColumn("bucket", sk.bucket(spec)).withColumn("sg", sk.sign(spec))
    plain = sk.packed(cells, spec)
    return here.drop("vec").join(plain, ["rep", "bucket"]).select("row_id", F.transform("vec", lambda x: x * F.col("sg") / factor).alias("vec"), "scaled", "norm_p")


def weigh(rows: DataFrame, alpha: Column | float, origin: str = "lp") -> DataFrame:
    """row_id, vec, norm_p, prob, weight, origin for a cut alpha (0: everything is certain)."""
    a = F.lit(float(alpha)) if not isinstance(alpha, Column) else alpha
    prob = F.when(a <= 0, 1.0).otherwise(F.least(F.lit(1.0), F.col("norm_p") / a))
    return rows.withColumn("prob", prob).select("row_id", "vec", "norm_p", "prob", (1.0 / F.col("prob")).alias("weight"), F.lit(origin).alias("origin"))


def cut_at(top: DataFrame, k: int) -> float:
    """The least scaled norm of k rows; 0 if there are fewer."""
    n, least = top.agg(F.count("*"), F.min("scaled")).first()
    return float(least) if n >= k else 0.0


def top_rows(rows: DataFrame, k: int) -> DataFrame:
    return rows.orderBy(F.desc("scaled"), "row_id").limit(k)


def with_cut(rows: DataFrame, k: int, rank: str = "k") -> DataFrame:
    """The k rows of largest scaled norm weighed by the k-th (or, `rank='k+1'`, by the next) scaled norm.

    At most k+1 rows are left when the cut is taken, so it is a window over them.
    """
    from pyspark.sql import Window

    few = rows.orderBy(F.desc("scaled"), "row_id").limit(k + 1)
    order = Window.orderBy(F.desc("scaled"), "row_id")
    ranked = few.withColumn("rk", F.row_number().over(order)).withColumn("n", F.count("*").over(Window.partitionBy()))
    at = k if rank == "k" else k + 1
    cut = F.max(F.when(F.col("rk") == F.least(F.lit(at), F.col("n")), F.col("scaled"))).over(Window.partitionBy())
    # All live rows listed and none left over: certain, weight one.
    alpha = F.when((F.col("n") < at) | (F.lit(rank == "k+1") & (F.col("n") <= k)), 0.0).otherwise(cut)
    return weigh(ranked.withColumn("alpha", alpha).filter(F.col("rk") <= k), F.col("alpha"))


def sample(cells: DataFrame, ids: DataFrame, spec: SketchSpec, k: int, matrix=None, budget: int | None = None, rank: str = "k") -> DataFrame:
    """Plain sampler: exactly k rows (fewer if fewer are listed)."""
    return with_cut(scaled_rows(cells, ids, spec, k, matrix, budget), k, rank)


def sample_two_run(cells_a: DataFrame, spec_a: SketchSpec, cells_b: DataFrame, spec_b: SketchSpec, ids: DataFrame, k: int, matrix=None) -> DataFrame:
    """One run fixes the cut at rank 1.5 k, the other, independent one gives the sample: k to 2k rows."""
    rank = -(-3 * k // 2)
    alpha = cut_at(top_rows(scaled_rows(cells_a, ids, spec_a, rank, matrix), rank), rank)
    return weigh(scaled_rows(cells_b, ids, spec_b, 2 * k, matrix, floor=alpha).filter(F.col("scaled") >= alpha), alpha)


def second(spec: SketchSpec) -> SketchSpec:
    """An independent sketch of the same shape."""
    return replace(spec, seed=spec.seed + 1_000_003)


def norm_estimate(sampled: DataFrame) -> DataFrame:
    """Estimate of the whole matrix's norm: weighted norms of the sample."""
    return sampled.agg(F.sum(F.col("weight") * F.col("norm_p")).alias("norm_estimate"))


def uniform(updates: DataFrame, k: int, n: int, seed: int = 42, d: int = 7) -> DataFrame:
    """Uniform sample of a turnstile stream: the rows of ids whose scalar is at most k/n, kept exactly."""
    u = sk.hashes(SketchSpec(seed=seed + 17)).uniform(F.col("row_id"))
    rows = updates.filter(u <= k / n).groupBy("row_id").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("col_id") == j, F.col("delta"))), F.lit(0.0)) for j in range(d)]).alias("vec"))
    return rows.select("row_id", "vec", F.lit(min(1.0, k / n)).alias("prob"), F.lit(max(1.0, n / k)).alias("weight"), F.lit("uniform").alias("origin"))


def cut_of(lp: DataFrame) -> float:
    """The cut of a sample: norm over probability of any row that isn't certain (0 if all are)."""
    return float(lp.agg(F.max(F.when(F.col("prob") < 1, F.col("norm_p") / F.col("prob")))).first()[0] or 0.0)


def own_probability(vec: Column, alpha: float, p: float, matrix=None) -> Column:
    """Inclusion probability of a row under a cut, from the row itself (in the conditioned basis if there is a matrix)."""
    if alpha <= 0:
        return F.lit(1.0)
    if matrix is not None:
        m = np.asarray(matrix, float)
        vec = F.array(*[sum((vec[i] * F.lit(float(m[i, j])) for i in range(1, m.shape[0])), vec[0] * F.lit(float(m[0, j]))) for j in range(m.shape[1])])
    return F.least(F.lit(1.0), norm_of(vec, p) / F.lit(float(alpha)))


def mix_uniform(lp: DataFrame, uni: DataFrame, k: int, n: int, p: float = 1.0, matrix=None, alpha: float | None = None) -> DataFrame:
    """Union of a norm sample and a uniform one: probability 1-(1-p)(1-q); the exact row is preferred.

    A row of the uniform part alone gets its p from its own norm and the sample's cut.
    """
    q = min(1.0, k / n)
    lp = lp.persist()
    alpha = cut_of(lp) if alpha is None else alpha
    a = lp.select("row_id", F.col("vec").alias("va"), F.col("norm_p"), F.col("prob").alias("pa"))
    b = uni.select("row_id", F.col("vec").alias("vb"), own_probability(F.col("vec"), alpha, p, matrix).alias("pb"))
    both = a.join(b, "row_id", "full")
    prob = 1.0 - (1.0 - F.coalesce("pa", "pb")) * (1.0 - q)
    origin = F.when(F.col("va").isNotNull() & F.col("vb").isNotNull(), "both").when(F.col("vb").isNotNull(), "uniform").otherwise("lp")
    return both.select("row_id", F.coalesce("vb", "va").alias("vec"), "norm_p", prob.alias("prob"), (1.0 / prob).alias("weight"), origin.alias("origin"))


def mix_many(samples: list[tuple[DataFrame, float, float]]) -> DataFrame:
    """Union of samples (rows, alpha, p) with different norms: probability 1 - product of misses, each from the row itself."""
    out = None
    for k, (rows, _, _) in enumerate(samples):
        part = rows.select("row_id", "vec", F.lit(k).alias("part"))
        out = part if out is None else out.unionByName(part)
    one = out.groupBy("row_id").agg(F.min_by("vec", "part").alias("vec"), F.array_sort(F.collect_set("part")).alias("parts"))
    miss = F.lit(1.0)
    for _, alpha, p in samples:
        miss = miss * (1.0 - own_probability(F.col("vec"), alpha, p))
    return one.withColumn("prob", 1.0 - miss).select("row_id", "vec", "prob", (1.0 / F.col("prob")).alias("weight"), F.concat_ws("+", F.transform("parts", lambda x: x.cast("string"))).alias("origin"))


def carve_probability(norm_p: Column, alpha: float, cut: float, n: int) -> Column:
    """Inclusion when the uniform part is carved out of the same scalars: the larger of the two."""
    return F.greatest(F.lit(cut / n), F.least(F.lit(1.0), norm_p / F.lit(alpha)) if alpha > 0 else F.lit(1.0))
