"""Linear CountSketch of a randomly scaled matrix, and its algebra.

A sketch is a DataFrame (rep, bucket, col_id, val) of fixed-point integers
(DECIMAL(38,0), 2^40 units in one): every update is rounded once, far below any
value of interest, and none is dropped; sums are exact, so merging sites,
differencing times and retracting rows are exact in any order.  Sums run over
three limbs of 30 bits, in 64-bit integers; an overflow raises.  Missing cells are
zero.
"""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from ..functions.hashing import FIELD, Hashes, inv_scale
from ..functions.params import SketchSpec


DENSE_CELLS = 4_000_000  # 96 MB in a task
LIMB = 1 << 30
VAL = "decimal(38,0)"
LIMBS = ("h2", "h1", "h0")


def hashes(spec: SketchSpec) -> Hashes:
    return Hashes(spec.seed, spec.family)


def validated(updates: DataFrame, d: int) -> DataFrame:
    """The log as typed triples (and its other columns); a null, a NaN, an infinity, a column out of range or an id out of range raises where it is read."""
    row, col, delta = F.col("row_id").cast("long"), F.col("col_id").cast("int"), F.col("delta").cast("double")
    bad = row.isNull() | col.isNull() | delta.isNull() | F.isnan(delta) | (F.abs(delta) == float("inf")) | (col < 0) | (col >= d) | (row < 0) | (row >= F.lit(FIELD).cast("long"))
    return updates.withColumns({"row_id": row, "col_id": col, "delta": F.when(bad, F.raise_error(F.lit("invalid update"))).otherwise(delta)})


def limbs(log: DataFrame, spec: SketchSpec) -> DataFrame:
    """The log with its scaled updates as three limbs; rounding is odd, so a retraction cancels exactly."""
    t = hashes(spec).uniform(F.col("row_id"))
    z = log.withColumn("z", F.col("delta") * inv_scale(t, spec.p) if spec.scale else F.col("delta"))
    top = z.withColumns({"sz": F.when(F.col("z") < 0, -1).otherwise(1), "z2": F.floor(F.abs("z") * (spec.fixed / LIMB**2))})
    rest = top.withColumn("rest", F.floor(F.abs("z") * float(spec.fixed) - F.col("z2") * float(LIMB**2) + 0.5))
    low = {"h2": F.col("sz") * F.col("z2"), "h1": F.col("sz") * F.shiftright("rest", 30), "h0": F.col("sz") * F.col("rest").bitwiseAND(F.lit(LIMB - 1).cast("long"))}
    return rest.withColumns(low).drop("z", "sz", "z2", "rest")


def joined(h2: Column, h1: Column, h0: Column) -> Column:
    """One exact integer from sums of limbs."""
    return (h2.cast(VAL) * F.lit(LIMB**2).cast("decimal(19,0)") + h1.cast(VAL) * F.lit(LIMB).cast("decimal(10,0)") + h0.cast(VAL)).cast(VAL)


def summed(cells: DataFrame, *keys) -> DataFrame:
    """Signed limbs (h2, h1, h0) summed by cell."""
    sums = cells.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in LIMBS])
    names = [c for c in sums.columns if c not in LIMBS]
    return sums.select(*names, joined(*[F.col(c) for c in LIMBS]).alias("val"))


def reps(spec: SketchSpec) -> Column:
    """One row for each repetition."""
    return F.explode(F.sequence(F.lit(0), F.lit(spec.s - 1)))


def bucket(spec: SketchSpec, row: str = "row_id", rep: str = "rep") -> Column:
    return hashes(spec).bucket_at(F.col(row), F.col(rep), spec.r, spec.s)


def sign(spec: SketchSpec, row: str = "row_id", rep: str = "rep") -> Column:
    return hashes(spec).sign_at(F.col(row), F.col(rep), spec.s)


def build(updates: DataFrame, spec: SketchSpec, engine: str = "auto") -> DataFrame:
    """Sketch of an update log (row_id, col_id, delta).

    `sql`: explode the repetitions, sum by cell; partial sums leave each task with
    at most r*s*d rows.  `arrow`: each task adds into one dense array and emits it
    once, for logs far longer than the sketch.  `auto` takes the latter for batch
    logs while that array has at most DENSE_CELLS cells.
    """
    if engine == "auto":
        engine = "arrow" if spec.family == "poly" and spec.r * spec.s * spec.d <= DENSE_CELLS and not updates.isStreaming else "sql"
    log = validated(updates.select("row_id", "col_id", "delta"), spec.d)
    if spec.uniform_cut and spec.n:
        log = log.filter(hashes(spec).uniform(F.col("row_id")) > spec.uniform_cut / spec.n)
    if engine == "arrow":
        if spec.scale and spec.p not in (1, 2):  # powers are the engine's own
            log = log.withColumn("delta", F.col("delta") * inv_scale(hashes(spec).uniform(F.col("row_id")), spec.p))
            return _dense(log, [replace(spec, scale=False)], [spec])[0]
        return _dense(log, [spec])[0]
    return summed(signed_cells(limbs(log, spec), spec), "rep", "bucket", "col_id").filter("val <> 0")


def build_many(updates: DataFrame, specs: list[SketchSpec]) -> list[DataFrame]:
    """`build` for each of several specifications, by one scan of the log where their arrays fit in a task."""
    plain = all(s.family == "poly" and not s.uniform_cut and s.p in (1, 2) and s.d == specs[0].d for s in specs)
    if not plain or updates.isStreaming or sum(s.r * s.s * s.d for s in specs) > DENSE_CELLS:
        return [build(updates, s) for s in specs]
    return _dense(validated(updates.select("row_id", "col_id", "delta"), specs[0].d), specs)


def signed_cells(log: DataFrame, spec: SketchSpec, *more: str) -> DataFrame:
    """(rep, bucket, col_id, signed limbs, more) of every update in every repetition, before any sum."""
    cells = log.select("row_id", "col_id", *LIMBS, *more, reps(spec).alias("rep")).withColumns({"bucket": bucket(spec), "sg": sign(spec)})
    return cells.select("rep", "bucket", "col_id", *[(F.col("sg") * F.col(c)).alias(c) for c in LIMBS], *more)


def _dense(log: DataFrame, specs: list[SketchSpec], placed: list[SketchSpec] | None = None) -> list[DataFrame]:
    """Sketches of a valid log (row_id, col_id, delta), one for each specification; each task adds into arrays and emits them once.  `placed` hash the rows where `specs` only scale."""
    placed = placed or specs
    if any(spec.family != "poly" for spec in placed):
        raise ValueError("the dense builder knows the polynomial family")

    def run(batches):
        sums = [np.zeros((3, spec.s, spec.r * spec.d), np.int64) for spec in placed]
        seen, size = 0, [0.0] * len(placed)
        for b in batches:
            row, col, delta = (b.column(k).to_numpy(zero_copy_only=False) for k in range(3))
            seen += len(row)
            for k, (scaled, spec) in enumerate(zip(specs, placed)):
                parts = [x[:, 0] for x in limbs_numpy(row, delta[:, None], scaled)]
                size[k] += _checked(seen, size[k], parts)
                h = hashes(spec)
                for j in range(spec.s):
                    at, sign = h.place_numpy(row, j, spec.r)
                    _add(sums[k], j, at * spec.d + col, sign, parts)
        for k, spec in enumerate(placed):
            cells = _in_use(sums[k], spec)
            yield cells.add_column(0, "sketch", pa.array(np.full(cells.num_rows, k, np.int32)))

    cells = log.select("row_id", "col_id", "delta").mapInArrow(run, f"sketch int, {_PARTS}")
    if len(placed) == 1:
        return [summed(cells, "rep", "bucket", "col_id").filter("val <> 0")]
    every = summed(cells, "sketch", "rep", "bucket", "col_id").filter("val <> 0").persist()
    return [every.filter(F.col("sketch") == k).drop("sketch") for k in range(len(placed))]


def _checked(seen: int, size: float, parts: list[np.ndarray]) -> float:
    """What the parts of some updates add to a task's size; sums that may leave 64 bits raise."""
    more = float(np.abs(parts[0].astype(float)).sum())
    if seen >= 1 << 32 or size + more >= 2.0**62:
        raise OverflowError("the sums of a task leave 64 bits: more partitions or a coarser accumulator")
    return more


def _add(sums: np.ndarray, rep: int, at: np.ndarray, sign: np.ndarray, parts: list[np.ndarray]) -> None:
    """Signed limbs of some updates into their cells of one repetition; the top limb is mostly zero."""
    top = np.flatnonzero(parts[0])
    np.add.at(sums[0, rep], at[top], sign[top] * parts[0][top])
    for limb, part in zip(sums[1:], parts[1:]):
        np.add.at(limb[rep], at, sign * part)


_PARTS = "rep int, bucket int, col_id int, h2 long, h1 long, h0 long"


def _in_use(acc: np.ndarray, spec: SketchSpec) -> pa.RecordBatch:
    """The cells in use of a task's limbs."""
    rep, cell = np.nonzero(acc.any(axis=0))
    place = [rep.astype(np.int32), (cell // spec.d).astype(np.int32), (cell % spec.d).astype(np.int32)]
    return pa.RecordBatch.from_arrays([pa.array(x) for x in [*place, *(limb[rep, cell] for limb in acc)]], names=["rep", "bucket", "col_id", *LIMBS])


def build_rows(rows: DataFrame, spec: SketchSpec) -> DataFrame:
    """The sketch of whole rows (row_id, vec), equal to `build` of their entries: a row is hashed once, not once an entry."""
    if spec.family != "poly" or spec.uniform_cut or spec.r * spec.s * spec.d > DENSE_CELLS:
        return build(rows.select("row_id", F.posexplode("vec").alias("col_id", "delta")).filter("delta <> 0"), spec)
    h = hashes(spec)

    def run(batches):
        acc = np.zeros((3, spec.s, spec.r * spec.d), np.int64)
        seen, size = 0, 0.0
        for b in batches:
            if b.num_rows and (b.column(0).null_count or b.column(1).null_count):
                raise ValueError("invalid update")
            row, x = b.column(0).to_numpy(zero_copy_only=False), stacked(b.column(1), spec.d, 0.0)
            if len(row) and (row.min() < 0 or row.max() >= FIELD or not np.isfinite(x).all()):
                raise ValueError("invalid update")
            parts = limbs_numpy(row, x, spec)
            seen += x.size
            size += _checked(seen, size, parts)
            parts = [part.ravel() for part in parts]
            for j in range(spec.s):
                at, sign = h.place_numpy(row, j, spec.r)
                _add(acc, j, (at[:, None] * spec.d + np.arange(spec.d)).ravel(), np.repeat(sign, spec.d), parts)
        yield _in_use(acc, spec)

    return summed(rows.select("row_id", "vec").mapInArrow(run, _PARTS), "rep", "bucket", "col_id").filter("val <> 0")


def limbs_numpy(row: np.ndarray, x: np.ndarray, spec: SketchSpec) -> list[np.ndarray]:
    """`limbs` of whole rows (rows x columns)."""
    t = hashes(spec).uniform_numpy(row)[:, None]
    z = x * (1.0 / t if spec.p == 1 else 1.0 / np.sqrt(t) if spec.p == 2 else t ** (-1.0 / spec.p)) if spec.scale else x
    sign, size = np.where(z < 0, -1, 1), np.abs(z)
    top = np.floor(size * (spec.fixed / LIMB**2))
    rest = np.floor(size * float(spec.fixed) - top * float(LIMB**2) + 0.5).astype(np.int64)
    return [sign * top.astype(np.int64), sign * (rest >> 30), sign * (rest & (LIMB - 1))]


def stacked(vecs: pa.Array, d: int, null: float = np.nan) -> np.ndarray:
    """A column of arrays of equal width as one matrix."""
    flat = vecs.flatten()
    x = (flat.fill_null(null) if flat.null_count else flat).to_numpy(zero_copy_only=False).astype(float, copy=False)
    if x.size != len(vecs) * d:
        raise ValueError("rows of different widths")
    return x.reshape(-1, d)


def merge(*sketches: DataFrame) -> DataFrame:
    """Sketch of the sum of the logs (sites, shards, times)."""
    return reduce(DataFrame.unionByName, sketches).groupBy("rep", "bucket", "col_id").agg(F.sum("val").cast(VAL).alias("val")).filter("val <> 0")


def scale(sketch: DataFrame, factor: int) -> DataFrame:
    return sketch.withColumn("val", (F.col("val") * F.lit(factor).cast("decimal(19,0)")).cast(VAL)).filter("val <> 0")


def diff(later: DataFrame, earlier: DataFrame) -> DataFrame:
    """Sketch of what came between two instants."""
    return merge(later, scale(earlier, -1))


def select_cols(sketch: DataFrame, cols: list[int]) -> DataFrame:
    return sketch.filter(F.col("col_id").isin(cols))


def drop_cols(sketch: DataFrame, cols: list[int]) -> DataFrame:
    return sketch.filter(~F.col("col_id").isin(cols))


def values(sketch: DataFrame, spec: SketchSpec) -> DataFrame:
    """Cells as numbers."""
    return sketch.withColumn("val", F.col("val").cast("double") / float(spec.fixed))


def project(sketch: DataFrame, spec: SketchSpec, matrix) -> DataFrame:
    """(S T A) P without touching A: cells times a d x e matrix, which is a literal of d*e numbers."""
    m = np.asarray(matrix, float)
    spark = sketch.sparkSession
    p = spark.createDataFrame([(i, j, float(m[i, j])) for i in range(m.shape[0]) for j in range(m.shape[1]) if m[i, j]], "col_id int, out_col int, coef double")
    cells = values(sketch, spec).join(F.broadcast(p), "col_id")  # d*e rows, fixed by the spec
    return cells.groupBy("rep", "bucket", F.col("out_col").alias("col_id")).agg(F.sum(F.col("val") * F.col("coef")).alias("val"))


def packed(sketch: DataFrame, spec: SketchSpec, d: int | None = None, fixed: bool = True) -> DataFrame:
    """(rep, bucket, vec): one row a bucket."""
    cells = values(sketch, spec) if fixed else sketch
    return cells.groupBy("rep", "bucket").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("col_id") == j, F.col("val"))), F.lit(0.0)) for j in range(d or spec.d)]).alias("vec"))


def size(sketch: DataFrame) -> DataFrame:
    """Cells in use, bytes of a dense copy of them."""
    return sketch.agg(F.count("*").alias("cells"), (F.count("*") * 8).alias("bytes"))
