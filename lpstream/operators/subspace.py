"""Oblivious lp subspace embeddings and the conditioning matrix they give.

A dense embedding has p-stable entries made from hashed uniforms, a sparse one a
single heavy-tailed entry a row; both are sums over the update log, so they are
kept beside the sampler's sketch and never need a second pass.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import coefficients, poly
from .baselines import stable_at, stable_numpy
from .sketch import stacked


def dense(updates: DataFrame, m: int, p: float, seed: int = 42, engine: str = "auto") -> DataFrame:
    """(i, col_id, val): m rows of p-stable combinations of the matrix's rows.

    `arrow` (the choice for batch logs): each task adds into its own m x columns
    array and emits it once; `sql`: one term for each update and row, summed.
    """
    if engine == "sql" or updates.isStreaming:
        cells = updates.select("row_id", "col_id", "delta", F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("i"))
        return cells.groupBy("i", "col_id").agg(F.sum(stable_at(F.col("row_id"), F.col("i"), m, p, seed + 101) * F.col("delta")).alias("val"))

    def run(batches):
        acc = np.zeros((m, 0))
        for b in batches:
            row, col, delta = (b.column(k).to_numpy(zero_copy_only=False) for k in range(3))
            if not len(row):
                continue
            if (width := int(col.max()) + 1) > acc.shape[1]:
                acc = np.pad(acc, ((0, 0), (0, width - acc.shape[1])))
            ids, place = np.unique(row, return_inverse=True)
            for i in range(m):
                acc[i, :] += np.bincount(col, stable_numpy(ids, i, p, seed + 101)[place] * delta, minlength=acc.shape[1])
        i, j = np.nonzero(acc)
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(acc[i, j])], names=["i", "col_id", "val"])

    log = updates.select(F.col("row_id").cast("long").alias("row_id"), F.col("col_id").cast("int").alias("col_id"), F.col("delta").cast("double").alias("delta"))
    return log.mapInArrow(run, "i int, col_id int, val double").groupBy("i", "col_id").agg(F.sum("val").alias("val"))


def dense_rows(rows: DataFrame, m: int, d: int, p: float, seed: int = 42) -> np.ndarray:
    """The dense embedding of whole rows (row_id, vec), as an m x d array at the driver: one product of matrices a batch."""

    def run(batches):
        acc = np.zeros((m, d))
        for b in batches:
            row, x = b.column(0).to_numpy(zero_copy_only=False), stacked(b.column(1), d, 0.0)
            for i in range(m):
                acc[i] += stable_numpy(row, i, p, seed + 101) @ x
        i, j = np.nonzero(acc)
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(acc[i, j])], names=["i", "col_id", "val"])

    found = rows.select(F.col("row_id").cast("long").alias("row_id"), "vec").mapInArrow(run, "i int, col_id int, val double")
    return to_numpy(found.groupBy("i", "col_id").agg(F.sum("val").alias("val")), m, d)


def sparse(updates: DataFrame, m: int, p: float, seed: int = 42) -> DataFrame:
    """The same from one non-zero a row: a hashed place, a sign and, below p = 2, a heavy-tailed scale."""
    row = F.col("row_id")
    place = (poly(row, coefficients(seed, "sparse place", 0)) % m).cast("int")
    sign = F.when(poly(row, coefficients(seed, "sparse sign", 0)) < (1 << 30), -1.0).otherwise(1.0)
    u = (poly(row, coefficients(seed, "sparse scale", 0)) + 1) / F.lit(float(1 << 31))
    scale = F.lit(1.0) if p == 2 else F.pow(u, F.lit(-1.0 / p))
    return updates.groupBy(place.alias("i"), "col_id").agg(F.sum(sign * scale * F.col("delta")).alias("val"))


def to_numpy(embedded: DataFrame, m: int, d: int) -> np.ndarray:
    """The m x d embedding at the driver: fixed by its own size, not by the data's."""
    out = np.zeros((m, d))
    for r in embedded.collect():
        out[r.i, r.col_id] = r.val
    return out


def conditioner(embedded: np.ndarray, ridge: float = 1e-9) -> np.ndarray:
    """P = R^-1 from a QR of the embedding, R with a positive diagonal; dependent columns are lifted by a small ridge."""
    d = embedded.shape[1]
    scale = max(np.abs(embedded).max(), 1e-300)
    _, r = np.linalg.qr(embedded)
    if np.abs(np.diag(r)).min(initial=scale) < 1e-10 * scale:
        _, r = np.linalg.qr(np.vstack([embedded, np.sqrt(ridge) * scale * np.eye(d)]))
    return np.linalg.inv(np.where(np.diag(r) < 0, -1.0, 1.0)[:, None] * r)


def gram(rows: DataFrame, d: int) -> np.ndarray:
    """A'A of rows (vec): d(d+1)/2 sums in one scan."""
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    got = rows.agg(*[F.sum(F.col("vec")[i] * F.col("vec")[j]) for i, j in pairs]).first()
    g = np.zeros((d, d))
    for (i, j), v in zip(pairs, got):
        g[i, j] = g[j, i] = v or 0.0
    return g


def exact_conditioner(rows: DataFrame, d: int) -> np.ndarray:
    """R^-1 from the Cholesky factor of the Gram matrix: the exact one for p = 2."""
    g = gram(rows, d)
    g += 1e-12 * max(np.trace(g), 1e-300) * np.eye(d)
    return np.linalg.inv(np.linalg.cholesky(g).T)
