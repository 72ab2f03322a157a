"""Quantities of the analysis: truncation, tails, the threshold's bounds, the harmonic demonstration, mu."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions.params import SketchSpec
from . import recover, sketch as sk
from .baselines import cap_level, tail_mass, with_norm
from .sampler import norm_of


def truncate(rows: DataFrame, p: float, k: int) -> DataFrame:
    """(row_id, norm_p, capped): norms scaled down so that none exceeds the capped total over k."""
    normed = with_norm(rows, p)
    cut = cap_level(normed, k)
    return normed.select("row_id", "norm_p", (F.least(F.col("norm_p"), F.lit(cut)) if cut > 0 else F.col("norm_p")).alias("capped"))


def scaled_norms(rows: DataFrame, spec: SketchSpec) -> DataFrame:
    t = sk.hashes(spec).uniform(F.col("row_id"))
    return rows.select("row_id", (norm_of(F.col("vec"), spec.p) / t).alias("norm_p"))


def tails(rows: DataFrame, spec: SketchSpec) -> dict:
    """Tail outside the r/20 largest rows before and after scaling, and the growth between them."""
    plain = tail_mass(with_norm(rows, spec.p), spec.r // 20)
    scaled = tail_mass(scaled_norms(rows, spec), spec.r // 20)
    return {"tail": plain, "scaled_tail": scaled, "growth": scaled / max(plain, 1e-300)}


def sandwich(rows: DataFrame, cells: DataFrame, spec: SketchSpec) -> dict:
    """Lower percentile of all buckets <= threshold <= 4 tail / r, of one sketch of the unscaled matrix."""
    norms = recover.bucket_norms(sk.values(cells, spec), spec.p).persist()
    m0 = recover.threshold_value(norms, spec)
    empty = spec.r * spec.s - norms.count()
    # The .6 percentile over all buckets, empty ones included, by rank among those in use.
    want = 0.6 * (spec.r * spec.s - 1) - empty
    low = 0.0 if want < 0 else float(norms.agg(F.percentile("norm", F.lit(max(0.0, min(1.0, want / max(1, spec.r * spec.s - empty - 1)))))).first()[0])
    tail = tail_mass(with_norm(rows, spec.p), spec.r // 20)
    return {"lower": low, "m0": m0, "upper": 4 * tail / spec.r}


def harmonic(spark: SparkSession, n: int, seed: int = 42) -> DataFrame:
    """n equal rows: k-th largest of the scaled norms, against n/k."""
    return harmonic_of(spark.range(n).select(F.col("id").alias("row_id")), n, seed)


def harmonic_of(ids: DataFrame, n: int, seed: int = 42) -> DataFrame:
    """The same for n given ids of equal rows."""
    t = sk.hashes(SketchSpec(seed=seed)).uniform(F.col("row_id"))
    scaled = ids.select("row_id", (1.0 / t).alias("x"))
    ranked = scaled.orderBy(F.desc("x"), "row_id").limit(1000)
    from pyspark.sql import Window

    top = ranked.withColumn("k", F.row_number().over(Window.orderBy(F.desc("x"), "row_id")))
    return top.filter(F.col("k").isin(1, 10, 100, 1000)).select("k", F.round("x", 4).alias("x"), F.round(F.col("x") * F.col("k") / max(1, n), 6).alias("ratio"))


def harmonic_total(spark: SparkSession, n: int, seed: int = 42) -> float:
    t = sk.hashes(SketchSpec(seed=seed)).uniform(F.col("row_id"))
    return float(spark.range(n).select(F.col("id").alias("row_id")).agg(F.sum(1.0 / t)).first()[0])


def mu_lower(rows: DataFrame, d: int, p: float, starts: int = 24, rounds: int = 6, seed: int = 0) -> tuple[float, np.ndarray]:
    """A lower bound of mu: the largest ratio of positive to negative p-mass over searched directions, a batch a scan."""
    from .solvers import dot

    rng = np.random.default_rng(seed)
    panel = [*rng.normal(size=(starts, d)), *np.eye(d), *(-np.eye(d))]
    best, where = 0.0, panel[0]
    for r in range(rounds):
        pos = [F.sum(F.pow(F.greatest(dot(z), F.lit(0.0)), F.lit(float(p)))) for z in panel]
        neg = [F.sum(F.pow(F.greatest(-dot(z), F.lit(0.0)), F.lit(float(p)))) for z in panel]
        got = np.array(rows.agg(*pos, *neg).first(), float)
        a, b = got[: len(panel)], got[len(panel) :]
        ratio = np.maximum(a, b) / np.maximum(np.minimum(a, b), 1e-300)
        ratio = np.where(np.minimum(a, b) > 0, ratio, 0)  # one-sided directions bound nothing
        k = int(np.argmax(ratio))
        if ratio[k] > best:
            best, where = float(ratio[k]), panel[k]
        panel = [where + rng.normal(size=d) * np.abs(where).max() * 0.5 ** (r + 1) for _ in range(starts)]
    return best, where
