"""lp leverage scores and the turnstile leverage-score sampler."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F

from ..functions.hashing import abs_pow
from ..functions.params import SketchSpec
from . import sampler, sketch as sk, subspace


def projected(matrix: np.ndarray, vec: str = "vec") -> Column:
    """vec times a literal matrix, as an array column."""
    return F.array(*_products(matrix, vec))


def _products(matrix: np.ndarray, vec: str = "vec") -> list[Column]:
    m = np.asarray(matrix, float)
    return [sum((F.col(vec)[i] * F.lit(float(m[i, j])) for i in range(1, m.shape[0])), F.col(vec)[0] * F.lit(float(m[0, j]))) for j in range(m.shape[1])]


def scores(rows: DataFrame, p: float, matrix: np.ndarray, beta: float = 1.0) -> DataFrame:
    """(row_id, vec, score): beta^p times the p-norm of the row in the conditioned basis; one narrow pass."""
    raw = sum((abs_pow(c, p) for c in _products(matrix)), F.lit(0.0))  # a plain sum is compiled, a lambda over an array is not
    return rows.select("row_id", "vec", raw.alias("raw")).withColumn("score", F.col("raw") * float(beta**p)).drop("raw")


def exact_l2(rows: DataFrame, d: int) -> DataFrame:
    """Exact l2 leverage scores: two scans, d(d+1)/2 sums at the driver between them."""
    return scores(rows, 2.0, subspace.exact_conditioner(rows, d))


def with_embedding(rows: DataFrame, d: int, p: float, m: int | None = None, seed: int = 42) -> DataFrame:
    """Approximate lp scores by a dense embedding of the rows."""
    return scores(rows, p, embedding_conditioner(long_rows(rows), d, p, m, seed))


def long_rows(rows: DataFrame) -> DataFrame:
    return rows.select("row_id", F.posexplode("vec").alias("col_id", "delta"))


def embedding_conditioner(updates: DataFrame, d: int, p: float, m: int | None = None, seed: int = 42) -> np.ndarray:
    m = m or max(40, 8 * d)
    return subspace.conditioner(subspace.to_numpy(subspace.dense(updates, m, p, seed), m, d))


def rows_conditioner(rows: DataFrame, d: int, p: float, m: int | None = None, seed: int = 42) -> np.ndarray:
    """The conditioner of whole rows (row_id, vec)."""
    return subspace.conditioner(subspace.dense_rows(rows, m or max(40, 8 * d), d, p, seed))


def sample_stream(updates: DataFrame, ids: DataFrame, spec: SketchSpec, k: int, m: int | None = None, rank: str = "k", budget: int | None = None, matrix: np.ndarray | None = None) -> DataFrame:
    """Turnstile leverage-score sample: sketch and embedding of one log, conditioned after sketching."""
    matrix = embedding_conditioner(updates, spec.d, spec.p, m, spec.seed) if matrix is None else matrix
    cells = sk.build(updates, spec).persist()
    return sampler.sample(cells, ids, spec, k, matrix=matrix, budget=budget, rank=rank)


def reweighted(rows: DataFrame, d: int, p: float, rounds: int = 8) -> DataFrame:
    """Scores of the iteratively reweighted l2 basis (off-line only): w = leverage^(1-2/p) until it settles."""
    now = rows.select("row_id", "vec", F.lit(1.0).alias("w"))
    for _ in range(rounds):
        scaled = now.select("row_id", F.transform("vec", lambda x: x * F.sqrt("w")).alias("vec"), F.col("vec").alias("orig"), "w")
        matrix = subspace.exact_conditioner(scaled, d)
        lev = F.aggregate(projected(matrix), F.lit(0.0), lambda s, x: s + x * x)
        now = scaled.select("row_id", F.col("orig").alias("vec"), F.greatest(F.pow(F.greatest(lev, F.lit(1e-12)) / F.col("w"), F.lit(p / 2 - 1)), F.lit(1e-12)).alias("w"), (lev).alias("score"))
    return now.select("row_id", "vec", "score")
