"""Coresets for regression losses by turnstile leverage-score samples."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, functions as F

from ..functions.params import SketchSpec, practical
from . import leverage, sampler
from .baselines import uniform_rows

#: p of the leverage scores that each loss asks for; all but lp add a uniform part.
NEEDS_UNIFORM = {"lp": False, "relu": True, "logistic": True, "probit": True}


def build(updates: DataFrame, rows: DataFrame | None, loss: str, p: float, k: int, d: int, n: int, seed: int = 42, spec: SketchSpec | None = None) -> DataFrame:
    """Weighted coreset (row_id, vec, prob, weight, origin) of about k rows from an update log.

    Logistic takes p = 1. Half of k goes to the leverage sample, half to a uniform
    one, where the loss needs both; `rows` are the current rows for the uniform
    part (None: collected from the log).
    """
    p = 1.0 if loss == "logistic" else p
    mixed = NEEDS_UNIFORM[loss]
    share = max(1, k // 2) if mixed else k
    spec = spec or practical(share, p, d, seed)
    matrix = leverage.embedding_conditioner(updates, d, p, seed=seed)
    lp = leverage.sample_stream(updates, updates.select("row_id").distinct(), spec, share, matrix=matrix)
    if not mixed:
        return lp.select("row_id", "vec", "prob", "weight", "origin")
    uni = uniform_rows(rows, share, n, seed) if rows is not None else sampler.uniform(updates, share, n, seed, d)
    return sampler.mix_uniform(lp, uni, share, n, p, matrix).select("row_id", "vec", "prob", "weight", "origin")


def refetch(updates: DataFrame, sampled: DataFrame, d: int) -> DataFrame:
    """The sample with its exact rows: a second pass over the log for the sampled ids only.

    The sample's size is fixed by k, so its ids are broadcast.
    """
    few = F.broadcast(sampled.select("row_id"))
    exact = updates.join(few, "row_id", "left_semi").groupBy("row_id").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("col_id") == j, F.col("delta"))), F.lit(0.0)) for j in range(d)]).alias("vec"))
    return sampled.drop("vec").join(exact, "row_id")


def to_numpy(coreset: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Rows and weights at the driver (about k of them)."""
    got = coreset.select("vec", "weight").collect()
    return np.array([r.vec for r in got]), np.array([r.weight for r in got])
