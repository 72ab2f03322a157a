"""What the sampler is compared with: exact twins, off-line leverage sampling, oblivious sketches, uniform and on-line sampling, Merge & Reduce, norm sketches."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.hashing import Hashes, Many, chosen, coefficients, poly, poly_numpy
from .sampler import norm_of


def with_norm(rows: DataFrame, p: float) -> DataFrame:
    return rows.withColumn("norm_p", norm_of(F.col("vec"), p))


def exact_heavy(rows: DataFrame, p: float, gamma: float, r: int) -> DataFrame:
    """Rows with at least a gamma share of the tail, the norms outside the r/20 largest."""
    normed = with_norm(rows, p)
    tail = tail_mass(normed, r // 20)
    return normed.filter(F.col("norm_p") >= gamma * tail)


def tail_mass(normed: DataFrame, top: int) -> float:
    """Sum of the norms outside the `top` largest: all minus a top-k, no sort of all rows."""
    head = normed.orderBy(F.desc("norm_p"), "row_id").limit(top)
    whole = normed.agg(F.sum("norm_p")).first()[0] or 0.0
    return float(whole - (head.agg(F.sum("norm_p")).first()[0] or 0.0))


def cap_level(normed: DataFrame, k: float, column: str = "norm_p", rounds: int = 60) -> float:
    """The cut alpha with sum of min(1, norm/alpha) = k, by bisection on one-row aggregates; 0 if fewer than k rows live."""
    live, whole, most = normed.filter(F.col(column) > 0).agg(F.count("*"), F.sum(column), F.max(column)).first()
    if not live or live <= k:
        return 0.0
    lo, hi = 0.0, float(whole) / k
    # Each round asks for sixteen levels at once: few scans.
    for _ in range(max(1, rounds // 15)):
        grid = [lo + (hi - lo) * (i + 1) / 17 for i in range(16)]
        sums = normed.agg(*[F.sum(F.least(F.lit(1.0), F.col(column) / F.lit(a))) for a in grid]).first()
        below = [a for a, s in zip(grid, sums) if s >= k]
        above = [a for a, s in zip(grid, sums) if s < k]
        lo, hi = max(below, default=lo), min(above, default=hi)
    # From a cut that is not too low, spreading the rest evenly leads down to the exact one in a few steps.
    for _ in range(rounds):
        certain, rest = normed.filter(F.col(column) > 0).agg(F.count_if(F.col(column) >= F.lit(hi)), F.sum(F.when(F.col(column) < F.lit(hi), F.col(column)))).first()
        if certain >= k or not rest or rest / (k - certain) >= hi * (1 - 1e-13):
            break
        hi = float(rest / (k - certain))
    return hi


def offline_sample(scored: DataFrame, k: int, mode: str = "poisson", seed: int = 0) -> DataFrame:
    """Rows (row_id, vec, score) sampled by score: row_id, vec, prob, weight.

    poisson: independent coins with expected size k; priority: the k+1 largest
    score/u, weights by the cut; multinomial: draws with replacement, merged, each
    row's number of draws binomial out of k (k draws together in expectation).
    """
    u = Hashes(seed + 5).uniform(F.col("row_id"))
    if mode != "priority":
        scored = scored.persist()  # read once for the cut and once for the draw
    if mode == "priority":
        few = scored.filter("score > 0").withColumn("key", F.col("score") / u).orderBy(F.desc("key"), "row_id").limit(k + 1)
        order = Window.orderBy(F.desc("key"), "row_id")
        ranked = few.withColumn("rk", F.row_number().over(order)).withColumn("n", F.count("*").over(Window.partitionBy())).withColumn("cut", F.when(F.max(F.col("rk")).over(Window.partitionBy()) > k, F.min("key").over(Window.partitionBy())).otherwise(0.0))
        kept = ranked.filter(F.col("rk") <= k).withColumn("prob", F.when(F.col("cut") > 0, F.least(F.lit(1.0), F.col("score") / F.col("cut"))).otherwise(1.0))
    elif mode == "poisson":
        cut = cap_level(scored, k, "score")
        prob = F.least(F.lit(1.0), F.col("score") / F.lit(cut)) if cut > 0 else F.lit(1.0)
        kept = scored.filter("score > 0").withColumn("prob", prob).filter(u <= F.col("prob"))
    else:
        whole = scored.agg(F.sum("score")).first()[0]
        mean = F.col("score") * F.lit(k / whole) if whole else F.lit(0.0)
        draws = _draws(k)(F.col("score") / F.lit(whole or 1.0), u)
        kept = scored.withColumn("draws", draws).filter("draws > 0").withColumn("prob", mean / F.col("draws"))
    return kept.select("row_id", "vec", F.col("score").alias("norm_p"), "prob", (1.0 / F.col("prob")).alias("weight"))


def _draws(k: int):
    """Binomial(k, share) by inversion of the row's uniform."""

    @F.pandas_udf("long")
    def draws(share: pd.Series, u: pd.Series) -> pd.Series:
        q, u = np.minimum(share.to_numpy(float), 1 - 1e-12), u.to_numpy(float)
        term = np.exp(k * np.log1p(-q))
        below, out = term.copy(), np.zeros(len(q), np.int64)
        for j in range(1, k + 1):
            more = u > below
            if not more.any():
                break
            out[more] = j
            term = term * (k - j + 1) / j * q / (1 - q)
            below = below + term
        return pd.Series(out)

    return draws


def level(row: Column, levels: int, base: int, seed: int) -> Column:
    """Geometric level of a row: level l with probability about base^-l, the last takes the rest."""
    u = (poly(row, coefficients(seed, "level", 0)) + 1) / F.lit(float(1 << 31))
    out = F.lit(0)
    for l in range(1, levels):
        out = F.when(u <= float(base) ** -l, l).otherwise(out)
    return out


def level_mass(levels: int, base: int) -> float:
    """Expected base^level of a row: 1 - 1/base from each level but the last, 1 from that; weights are divided by it, so a row weighs one in expectation."""
    return (levels - 1) * (1 - 1 / base) + 1


def oblivious(updates: DataFrame, rows: int, levels: int = 5, base: int = 4, seed: int = 42, d: int = 7, signed: bool = False, entry: Column | None = None) -> DataFrame:
    """Plain oblivious sketch: each row falls into a level, is hashed into a bucket of it, bucket sums weigh base^level over the expected weight.

    Signs only for symmetric losses: a flipped row would turn g(t) into g(-t).
    """
    each = max(1, rows // levels)
    lev = level(F.col("row_id"), levels, base, seed)
    bucket = poly(F.col("row_id"), coefficients(seed, "oblivious", 0)) % each
    value = F.col("delta")
    if signed:
        value = value * F.when(poly(F.col("row_id"), coefficients(seed, "oblivious sign", 0)) < (1 << 30), -1.0).otherwise(1.0)
    cells = updates.select(lev.alias("level"), bucket.cast("int").alias("bucket"), "col_id", value.alias("v"))
    packed = cells.groupBy("level", "bucket").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("col_id") == j, F.col("v"))), F.lit(0.0)) for j in range(d)]).alias("vec"))
    weight = F.pow(F.lit(float(base)), F.col("level")) / level_mass(levels, base)
    return packed.select("level", "bucket", "vec", weight.alias("weight"))


def oblivious_rows(rows: DataFrame, count: int, levels: int = 5, base: int = 4, seed: int = 42, d: int = 7, signed: bool = False) -> DataFrame:
    """`oblivious` of whole rows (row_id, vec): a row is hashed once, not once an entry."""
    u = poly(F.col("row_id"), coefficients(seed, "oblivious sign", 0))
    sign = F.when(u < (1 << 30), -1.0).otherwise(1.0) if signed else F.lit(1.0)
    bucket = poly(F.col("row_id"), coefficients(seed, "oblivious", 0)) % max(1, count // levels)
    cells = rows.filter(F.exists("vec", lambda x: x != 0)).select(level(F.col("row_id"), levels, base, seed).alias("level"), bucket.cast("int").alias("bucket"), sign.alias("sg"), "vec")
    packed = cells.groupBy("level", "bucket").agg(F.array(*[F.coalesce(F.sum(F.col("vec")[j] * F.col("sg")), F.lit(0.0)) for j in range(d)]).alias("vec"))
    return packed.select("level", "bucket", "vec", (F.pow(F.lit(float(base)), F.col("level")) / level_mass(levels, base)).alias("weight"))


def uniform_rows(rows: DataFrame, k: int, n: int, seed: int = 42) -> DataFrame:
    """Uniform control: rows whose scalar is at most k/n."""
    u = Hashes(seed + 17).uniform(F.col("row_id"))
    return rows.filter(u <= k / n).select("row_id", "vec", F.lit(min(1.0, k / n)).alias("prob"), F.lit(max(1.0, n / k)).alias("weight"))


def online_rows(rows: DataFrame, k: int, p: float, order: str = "row_id", seed: int = 42, parts: int = 64) -> DataFrame:
    """Insert-only sampling at arrival: a row is kept with probability min(1, k norm / running total).

    The running total is a prefix over ranges of the arrival order plus a prefix
    inside each range, so no task sees the whole stream.
    """
    running = running_totals(rows, p, order, parts)
    prob = F.least(F.lit(1.0), F.lit(float(k)) * F.col("norm_p") / F.col("running"))
    u = Hashes(seed + 23).uniform(F.col("row_id"))
    return running.withColumn("prob", prob).filter(u <= F.col("prob")).select("row_id", "vec", "norm_p", "prob", (1.0 / F.col("prob")).alias("weight"))


def running_totals(rows: DataFrame, p: float, order: str = "row_id", parts: int = 64) -> DataFrame:
    """The rows with norm_p and the sum of norms up to each in the order of arrival (`running`)."""
    normed = with_norm(rows, p).withColumn("range", F.floor(F.col(order) / F.lit(_range_width(rows, order, parts))))
    totals = normed.groupBy("range").agg(F.sum("norm_p").alias("mass"))
    before = totals.select("range", (F.sum("mass").over(Window.orderBy("range")) - F.col("mass")).alias("before"))
    inside = F.sum("norm_p").over(Window.partitionBy("range").orderBy(order).rowsBetween(Window.unboundedPreceding, 0))
    whole = normed.withColumn("inside", inside).join(F.broadcast(before), "range")  # `parts` short rows
    return whole.withColumn("running", F.col("before") + F.col("inside")).drop("range", "before", "inside")


def _range_width(rows: DataFrame, order: str, parts: int) -> int:
    lo, hi = rows.agg(F.min(order), F.max(order)).first()
    return max(1, -(-(int(hi or 0) + 1) // parts))


# --- Merge & Reduce -----------------------------------------------------------------


def reduce_rows(vec: np.ndarray, weight: np.ndarray, k: int, p: float, rng) -> tuple[np.ndarray, np.ndarray]:
    """A weighted set of rows to about k by leverage of the weighted rows: (kept row numbers, new weights)."""
    if len(vec) <= k:
        return np.arange(len(vec)), weight
    scaled = vec * (weight ** (1 / p))[:, None]
    _, rr = np.linalg.qr(scaled)
    u = scaled @ np.linalg.pinv(rr)
    score = (np.abs(u) ** p).sum(1)
    score = score + score.mean()  # half leverage, half uniform
    lo, hi = 0.0, float(score.sum())
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if np.minimum(1, score / max(mid, 1e-300)).sum() >= k else (lo, mid)
    prob = np.minimum(1.0, score / hi)
    kept = np.flatnonzero(rng.random(len(vec)) < prob)
    return kept, weight[kept] / prob[kept]


def merge_reduce(rows: DataFrame, batch: int, k: int, p: float = 1.0, seed: int = 0) -> DataFrame:
    """Coreset tree: batches are reduced, pairs are merged and reduced, up to one set of about k rows."""

    def reduce_group(table: pa.Table) -> pa.Table:
        table = table.take(pa.array(np.argsort(table["row_id"].to_numpy(), kind="stable")))
        rng = np.random.default_rng([seed, table["node"][0].as_py(), table.num_rows])
        vec = table["vec"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(table.num_rows, -1)
        kept, weights = reduce_rows(vec, table["weight"].to_numpy(), k, p, rng)
        return table.take(pa.array(kept)).set_column(3, "weight", pa.array(weights)).select(["node", "row_id", "vec", "weight"])

    leaves = max(1, math.ceil(rows.count() / batch))
    schema = "node long, row_id long, vec array<double>, weight double"
    now = rows.select(F.pmod(F.xxhash64("row_id"), F.lit(leaves)).alias("node"), "row_id", "vec", F.lit(1.0).alias("weight")).groupBy("node").applyInArrow(reduce_group, schema)
    while leaves > 1:
        leaves = -(-leaves // 2)
        now = now.withColumn("node", F.floor(F.col("node") / 2)).groupBy("node").applyInArrow(reduce_group, schema)
    return now.select("row_id", "vec", "weight")


# --- norm sketches of earlier samplers ------------------------------------------------


def stable_at(row: Column, i: Column, count: int, p: float, seed: int) -> Column:
    """p-stable variables made from two hashed uniforms by the trigonometric formula; `i` numbers independent streams.

    Coefficients come from literal arrays, so the expression stays small however many streams there are.
    """

    def at(stream):
        return poly(row, chosen([coefficients(seed, stream, j) for j in range(count)], i))

    u = (at("angle") + 1) / F.lit(float(1 << 31))
    theta = (u - 0.5) * F.lit(math.pi * (1 - 1e-9))
    if p == 1:
        return F.tan(theta)
    w = (at("exponential") + 1) / F.lit(float((1 << 31) + 1))
    if p == 2:
        return F.sqrt(-2.0 * F.log(w)) * F.sin(theta * 2.0)
    return F.sin(theta * p) / F.pow(F.cos(theta), F.lit(1.0 / p)) * F.pow(F.cos(theta * (1 - p)) / (-F.log(w)), F.lit((1.0 - p) / p))


def stable_numpy(row: np.ndarray, i: int, p: float, seed: int) -> np.ndarray:
    """The same variables in numpy."""
    u = (poly_numpy(row, coefficients(seed, "angle", i)) + 1) / float(1 << 31)
    theta = (u - 0.5) * (math.pi * (1 - 1e-9))
    if p == 1:
        return np.tan(theta)
    w = (poly_numpy(row, coefficients(seed, "exponential", i)) + 1) / float((1 << 31) + 1)
    if p == 2:
        return np.sqrt(-2.0 * np.log(w)) * np.sin(theta * 2.0)
    return np.sin(theta * p) / np.cos(theta) ** (1 / p) * (np.cos(theta * (1 - p)) / -np.log(w)) ** ((1.0 - p) / p)


def stables_numpy(row: np.ndarray, count: int, p: float, seed: int):
    """(slice, variables): those of the streams 0 to count - 1 (count x ids), some ids at a time; the tangent as a quotient."""
    streams = ["angle"] if p == 1 else ["angle", "exponential"]
    for at, (h,) in Many([coefficients(seed, s, i) for s in streams for i in range(count)], 1)(row):
        theta = h[:count] + (1 - (1 << 30))
        theta *= math.pi * (1 - 1e-9) / (1 << 31)
        if p == 1:
            sine = np.sin(theta)
            sine /= np.cos(theta)
            yield at, sine
            continue
        w = (h[count:] + 1) / float((1 << 31) + 1)
        if p == 2:
            yield at, np.sqrt(-2.0 * np.log(w)) * np.sin(2 * theta)
        else:
            yield at, np.sin(theta * p) / np.cos(theta) ** (1 / p) * (np.cos(theta * (1 - p)) / -np.log(w)) ** ((1.0 - p) / p)


def stable_scale(p: float, draws: int = 200_001) -> float:
    """Median of |X| for the p-stable variable of `_stable`, by a quadrature over both uniforms."""
    if p == 1:
        return 1.0
    m = int(math.isqrt(draws))
    g = (np.arange(m) + 0.5) / m
    u, w = np.meshgrid(g, g)
    theta = (u - 0.5) * math.pi
    x = np.sqrt(-2 * np.log(w)) * np.sin(2 * theta) if p == 2 else np.sin(p * theta) / np.cos(theta) ** (1 / p) * (np.cos((1 - p) * theta) / -np.log(w)) ** ((1 - p) / p)
    return float(np.median(np.abs(x)))


def ams_norm(updates: DataFrame, m: int = 45, groups: int = 9, seed: int = 42) -> DataFrame:
    """Entry-wise squared l2 norm by random signs: median of group means of squared sums."""
    signs = [F.when(poly(F.col("row_id") * 64 + F.col("col_id"), coefficients(seed, "ams", i)) < (1 << 30), -1.0).otherwise(1.0) for i in range(m)]
    sums = updates.agg(*[F.sum(F.floor(F.col("delta") * 256 + 0.5) * s).alias(f"s{i}") for i, s in enumerate(signs)])
    square = [(F.col(f"s{i}") / 256.0) * (F.col(f"s{i}") / 256.0) for i in range(m)]
    each = m // groups
    means = F.array(*[sum(square[g * each + 1 : (g + 1) * each], square[g * each]) / each for g in range(groups)])
    return sums.select(F.get(F.array_sort(means), F.lit(groups // 2)).alias("estimate"))


def stable_norm(updates: DataFrame, p: float, m: int = 101, seed: int = 42) -> DataFrame:
    """Entry-wise lp norm by a p-stable sketch: median of the absolute sums over the variable's median."""
    entries = updates.select((F.col("row_id") * 64 + F.col("col_id")).alias("e"), "delta", F.explode(F.sequence(F.lit(0), F.lit(m - 1))).alias("i"))
    sums = entries.groupBy("i").agg(F.abs(F.sum(F.col("delta") * stable_at(F.col("e"), F.col("i"), m, p, seed))).alias("s"))
    return sums.agg((F.median("s") / F.lit(stable_scale(p))).alias("estimate"))


def median_lp(embedded: np.ndarray, z: np.ndarray, p: float) -> np.ndarray:
    """|A z| for each column of z from a p-stable embedding: the median of the absolute projections (not convex in z)."""
    return np.median(np.abs(embedded @ z), axis=0) / stable_scale(p)
