"""What post-processing reads out of a sketch: bucket norms, the threshold, norm
estimates, the candidate list and one representative row a candidate."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from ..functions.hashing import abs_pow
from ..functions.params import SketchSpec
from .sketch import bucket, hashes, packed, reps, sign, values

NARROW_CELLS = 8_000_000  # 64 MB of bucket norms at most are broadcast


def bucket_norms(cells: DataFrame, p: float) -> DataFrame:
    """(rep, bucket, norm): sum of |val|^p over the columns of each bucket in use; cells hold numbers, not fixed point."""
    return cells.groupBy("rep", "bucket").agg(F.sum(abs_pow(F.col("val"), p)).alias("norm"))


def threshold(norms: DataFrame, spec: SketchSpec, at: int = 0) -> DataFrame:
    """One row (m0): the percentile, over the repetitions, of one fixed bucket's norm; an empty bucket counts as zero."""
    one = norms.sparkSession.range(spec.s).select(F.col("id").cast("int").alias("rep"))
    fixed = one.join(norms.filter(F.col("bucket") == at).select("rep", "norm"), "rep", "left")
    return fixed.agg(F.percentile(F.coalesce("norm", F.lit(0.0)), F.lit(spec.quantile)).alias("m0"))


def threshold_value(norms: DataFrame, spec: SketchSpec, at: int = 0) -> float:
    return float(threshold(norms, spec, at).first()[0])


def probes(ids: DataFrame, spec: SketchSpec) -> DataFrame:
    """(row_id, rep, bucket): where each row sits in each repetition."""
    return ids.select("row_id", reps(spec).alias("rep")).select("row_id", "rep", bucket(spec).alias("bucket"))


def estimates(ids: DataFrame, norms: DataFrame, spec: SketchSpec) -> DataFrame:
    """(row_id, est_norm): the median, over the repetitions, of the norm of the row's bucket."""
    met = probes(ids, spec).join(norms, ["rep", "bucket"], "left")
    return met.groupBy("row_id").agg(F.median(F.coalesce("norm", F.lit(0.0))).alias("est_norm"))


def cut_value(m0: float, spec: SketchSpec) -> float:
    return m0 * spec.list_multiplier**spec.p


def candidates(ids: DataFrame, norms: DataFrame, spec: SketchSpec, m0: float) -> DataFrame:
    """(row_id, est_norm) of the rows whose estimate reaches the cut.

    A median reaches a cut only if more than half of the repetitions do, so ids
    first meet the heavy buckets alone (at most r*s short rows), are counted, and
    only the survivors' medians are computed: exact pruning.
    """
    cut = cut_value(m0, spec)
    heavy = norms.filter((F.col("norm") >= cut) & (F.col("norm") > 0)).select("rep", "bucket")
    enough = probes(ids, spec).join(heavy, ["rep", "bucket"], "left_semi").groupBy("row_id").count().filter(F.col("count") >= spec.s // 2 + 1).select("row_id")
    return estimates(enough, norms, spec).filter((F.col("est_norm") >= cut) & (F.col("est_norm") > 0))


def candidates_narrow(ids: DataFrame, norms: DataFrame, spec: SketchSpec, m0: float) -> DataFrame:
    """The same list by one narrow pass over the ids: no join, no shuffle.

    The bucket norms are r*s numbers, fixed by the specification and checked here;
    they are broadcast, and each batch of ids is hashed and looked up in numpy.
    """
    if spec.family != "poly" or spec.r * spec.s > NARROW_CELLS:
        return candidates(ids, norms, spec, m0)
    shared = norms.sparkSession.sparkContext.broadcast(dense_norms(norms, spec))
    h, cut, r = hashes(spec), cut_value(m0, spec), spec.r

    def run(batches):
        for b in batches:
            row = b.column(0).to_numpy(zero_copy_only=False)
            est = np.median(np.stack([shared.value[j, h.bucket_numpy(row, j, r)] for j in range(spec.s)]), axis=0) if len(row) else np.zeros(0)
            keep = (est >= cut) & (est > 0)
            yield pa.RecordBatch.from_arrays([pa.array(row[keep]), pa.array(est[keep])], names=["row_id", "est_norm"])

    return ids.select(F.col("row_id").cast("long").alias("row_id")).mapInArrow(run, "row_id long, est_norm double")


def dense_norms(norms: DataFrame, spec: SketchSpec) -> np.ndarray:
    """Bucket norms as one array (repetitions x buckets) at the driver."""
    out = np.zeros((spec.s, spec.r))
    found = norms.toPandas()
    out[found["rep"].to_numpy(), found["bucket"].to_numpy()] = found["norm"].to_numpy()
    return out


def best_candidates(listed: DataFrame, budget: int | None) -> DataFrame:
    """The `budget` rows of highest estimate (all if None); ties by id."""
    return listed if budget is None else listed.orderBy(F.desc("est_norm"), "row_id").limit(budget)


def _distance(a: Column, b: Column, p: float) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: abs_pow(x - y, p)), F.lit(0.0), lambda s, x: s + x)


def _median(values_: Column) -> Column:
    """Median of an array, the lower of the middle two if even."""
    return F.get(F.array_sort(values_), F.floor((F.size(values_) - 1) / 2).cast("int"))


def representatives(listed: DataFrame, sketch: DataFrame, spec: SketchSpec, d: int | None = None, fixed: bool = True) -> DataFrame:
    """(row_id, rep, vec): the sign-corrected bucket of the repetition with the least median distance to the others.

    The s bucket rows of a candidate are gathered once (s is fixed by the spec)
    and compared in place, so the only shuffle is that of the listed ids.
    """
    d = d or spec.d
    rows = listed.select("row_id", reps(spec).alias("rep")).select("row_id", "rep", bucket(spec).alias("bucket"), sign(spec).alias("sg"))
    zero = F.array(*[F.lit(0.0)] * d)
    met = rows.join(packed(sketch, spec, d, fixed), ["rep", "bucket"], "left")
    vec = F.transform(F.coalesce("vec", zero), lambda x: x * F.col("sg"))
    return nearest(met.select("row_id", "rep", vec.alias("vec")), spec.p)


def nearest(rows: DataFrame, p: float) -> DataFrame:
    """Of each row_id's (rep, vec) the one with the least median distance to the others."""
    gathered = rows.groupBy("row_id").agg(F.array_sort(F.collect_list(F.struct("rep", "vec"))).alias("all"))
    others = lambda x: F.filter("all", lambda y: y["rep"] != x["rep"])
    spread = F.transform("all", lambda x: F.struct(F.when(F.size("all") > 1, _median(F.transform(others(x), lambda y: _distance(x["vec"], y["vec"], p)))).otherwise(0.0).alias("m"), x["rep"].alias("rep"), x["vec"].alias("vec")))
    best = F.array_min(F.transform(spread, lambda x: F.struct(F.round(x["m"], 6).alias("m"), x["rep"].alias("rep"))))
    chosen = F.filter("all", lambda x: x["rep"] == F.col("best.rep"))[0]
    return gathered.withColumn("best", best).select("row_id", chosen["rep"].alias("rep"), chosen["vec"].alias("vec"))


def dense_cells(cells: DataFrame, spec: SketchSpec, d: int) -> np.ndarray:
    """Number cells as one array (repetitions x buckets x columns) at the driver; its size is fixed by the specification."""
    out = np.zeros((spec.s, spec.r, d))
    found = cells.select("rep", "bucket", "col_id", "val").toPandas()
    out[found["rep"].to_numpy(), found["bucket"].to_numpy(), found["col_id"].to_numpy()] = found["val"].to_numpy()
    return out


def medoids(vecs: np.ndarray, p: float) -> np.ndarray:
    """For each row of vecs (repetitions x rows x columns) the repetition with the least median distance to the others, as `representatives` has it: sums in the same order, lower medians, six digits, ties to the first."""
    s, n, d = vecs.shape
    if s == 1:
        return np.zeros(n, np.int64)
    apart = np.zeros((s, s, n))
    for a in range(s):
        for b in range(a + 1, s):
            for j in range(d):
                apart[a, b] += size_numpy(vecs[a, :, j] - vecs[b, :, j], p)
            apart[b, a] = apart[a, b]
    middle = np.stack([np.partition(np.delete(apart[a], a, axis=0), (s - 2) // 2, axis=0)[(s - 2) // 2] for a in range(s)])
    # Beyond 2^52 units a number has no sixth digit to round.
    return np.where(middle < 2.0**52 / 1e6, np.floor(middle * 1e6 + 0.5) / 1e6, middle).argmin(axis=0)


def size_numpy(x: np.ndarray, p: float) -> np.ndarray:
    return np.abs(x) if p == 1 else x * x if p == 2 else np.abs(x) ** p


def top_narrow(ids: DataFrame, view: np.ndarray, plain: np.ndarray, norms: np.ndarray, spec: SketchSpec, m0: float, reach: float, k: int, floor: float | None) -> DataFrame:
    """(row_id, vec, scaled) of the k listed rows of largest scaled norm of each task (or of all at or above `floor`), by one narrow pass over the ids.

    Listing, representatives and norms as in `candidates_narrow` and `representatives`, in numpy on arrays
    fixed by the specification; `vec` is the signed bucket of `plain` in the representative's repetition.
    A row whose estimate times `reach` stays below the least of k rows at hand (or `floor`) can't be among them.
    """
    sc = ids.sparkSession.sparkContext
    shared = sc.broadcast((view, plain, norms))
    h, cut, r, s, p = hashes(spec), cut_value(m0, spec), spec.r, spec.s, spec.p

    def run(batches):
        view, plain, norms = shared.value
        best, least = [(np.zeros(0, np.int64), np.zeros((0, plain.shape[2])), np.zeros(0))], 0.0 if floor is None else floor
        for b in batches:
            every = b.column(0).to_numpy(zero_copy_only=False)
            for at in range(0, len(every), 16384):
                row = every[at : at + 16384]
                place = h.buckets_numpy(row, r, s)
                mine = np.stack([norms[j, q] for j, q in enumerate(place)])
                # A median reaches a cut only if half of the repetitions at least do (more, if their number is odd).
                some = np.flatnonzero(2 * np.count_nonzero(mine >= max(cut, (least / reach - 1e-6) * (1 - 1e-12)), axis=0) >= s)
                est = np.median(mine[:, some], axis=0)
                keep = some[(est >= cut) & (est > 0) & ((est + 1e-6) * reach >= least)]
                if not len(keep):
                    continue
                place, signs = place[:, keep], h.places_numpy(row[keep], r, s)[1]
                vecs = np.stack([view[j, q] * sg[:, None] for j, (q, sg) in enumerate(zip(place, signs))])
                rep, each = medoids(vecs, p), np.arange(len(keep))
                scaled = np.zeros(len(keep))
                for j in range(vecs.shape[2]):
                    scaled += size_numpy(vecs[rep, each, j], p)
                q, sg = place[rep, each], signs[rep, each]
                found = (row[keep], plain[rep, q] * sg[:, None], scaled)
                if floor is not None:
                    yield _rows(*(x[scaled >= floor] for x in found))
                    continue
                found = [np.concatenate(x) for x in zip(best[0], found)]
                order = np.lexsort((found[0], -found[2]))
                order = order[np.r_[True, found[0][order[1:]] != found[0][order[:-1]]]][:k]  # an id that comes twice counts once
                best = [tuple(x[order] for x in found)]
                least = float(best[0][2][-1]) if len(order) == k else 0.0
        if floor is None:
            yield _rows(*best[0])

    return ids.select(F.col("row_id").cast("long").alias("row_id")).mapInArrow(run, "row_id long, vec array<double>, scaled double")


def _rows(row: np.ndarray, vec: np.ndarray, scaled: np.ndarray) -> pa.RecordBatch:
    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(vec) + 1, dtype=np.int32) * vec.shape[1], pa.int32()), pa.array(np.ascontiguousarray(vec).ravel()))
    return pa.RecordBatch.from_arrays([pa.array(row), lists, pa.array(scaled)], names=["row_id", "vec", "scaled"])


def cells_of(sketch: DataFrame, spec: SketchSpec) -> DataFrame:
    return values(sketch, spec)
