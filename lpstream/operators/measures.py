"""Accuracy and cost measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import abs_pow
from .sampler import norm_of
from .solvers import dot, evaluate, objective, solve_full


def row_error(sampled: DataFrame, exact: DataFrame, p: float) -> DataFrame:
    """(row_id, error, norm_ratio): perturbation of each sampled row against its exact row, and norm ratio."""
    diff = F.zip_with("vec", "true", lambda x, y: x - y)
    joined = sampled.select("row_id", "vec").join(exact.select("row_id", F.col("vec").alias("true")), "row_id")
    own, true = norm_of(F.col("vec"), p), norm_of(F.col("true"), p)
    return joined.select("row_id", F.pow(norm_of(diff, p) / true, F.lit(1.0 / p)).alias("error"), (own / true).alias("norm_ratio"))


def summary(errors: DataFrame) -> DataFrame:
    return errors.agg(F.count("*").alias("n"), F.max("error").alias("max_error"), F.median("error").alias("median_error"), F.median("norm_ratio").alias("median_norm_ratio"))


def weight_error(sampled: DataFrame, exact: DataFrame, p: float, alpha: float) -> DataFrame:
    """weight times the inclusion probability of the exact row under the same cut: 1 up to the norm error."""
    true = exact.select("row_id", F.least(F.lit(1.0), norm_of(F.col("vec"), p) / F.lit(alpha)).alias("true_prob"))
    return sampled.join(true, "row_id").select("row_id", (F.col("weight") * F.col("true_prob")).alias("ratio"))


def norm_ratio(sampled: DataFrame, exact: DataFrame, p: float) -> DataFrame:
    """Estimated over exact norm of the whole matrix."""
    whole = exact.agg(F.sum(norm_of(F.col("vec"), p))).first()[0]
    return sampled.agg((F.sum(F.col("weight") * F.col("norm_p")) / F.lit(float(whole))).alias("ratio"))


def recall(found: DataFrame, wanted: DataFrame) -> DataFrame:
    """wanted, found, hits, recall, precision over row ids; a share of none is NaN."""
    both = wanted.select("row_id", F.lit(1).alias("w")).join(found.select("row_id", F.lit(1).alias("f")), "row_id", "full")
    sums = both.agg(F.count("w").alias("wanted"), F.count("f").alias("found"), F.count(F.when(F.col("w").isNotNull() & F.col("f").isNotNull(), 1)).alias("hits"))
    share = lambda n: F.when(F.col(n) > 0, F.col("hits") / F.col(n)).otherwise(F.lit(float("nan")))
    return sums.select("*", share("wanted").alias("recall"), share("found").alias("precision"))


def subset_sums(sampled: DataFrame, exact: DataFrame, p: float, stratum) -> DataFrame:
    """Estimated and exact norm by stratum of the row id."""
    a = sampled.groupBy(stratum.alias("stratum")).agg(F.sum(F.col("weight") * F.col("norm_p")).alias("estimate"))
    b = exact.groupBy(stratum.alias("stratum")).agg(F.sum(norm_of(F.col("vec"), p)).alias("exact"))
    return b.join(a, "stratum", "left").select("stratum", F.coalesce("estimate", F.lit(0.0)).alias("estimate"), "exact")


def panel_error(rows: DataFrame, x: np.ndarray, w: np.ndarray, panel: list[np.ndarray], loss: str, p: float = 1.0) -> np.ndarray:
    """Relative error of the coreset's loss for every z of a panel; one scan of the data."""
    full = evaluate(rows, panel, loss, p)
    return np.array([abs(objective(x, w, z, loss, p) - f) / max(f, 1e-300) for z, f in zip(panel, full)])


def default_panel(d: int, count: int = 24, seed: int = 0) -> list[np.ndarray]:
    rng = np.random.default_rng(seed)
    v = rng.normal(size=(count, d))
    return [*(v / np.linalg.norm(v, axis=1, keepdims=True)), *np.eye(d), *(-np.eye(d))]


def conditioning(rows: DataFrame, matrix: np.ndarray, d: int, p: float, panel: int = 64, seed: int = 0) -> dict:
    """Measured alpha and beta of U = A P: alpha is the entry-wise norm; beta exact for p = 2, by d l1 fits (each coordinate pinned once) for p = 1, else the worst of a panel."""
    from .leverage import projected
    from .subspace import gram

    u = rows.select("row_id", projected(matrix).alias("vec")).persist()
    alpha = float(u.agg(F.sum(norm_of(F.col("vec"), p))).first()[0]) ** (1 / p)
    if p == 2:
        beta = 1 / float(np.sqrt(np.linalg.eigvalsh(gram(u, d))[0]))
    else:
        zs = default_panel(d, panel, seed)
        vals = evaluate(u, zs, "lp", p) ** (1 / p)
        beta = max(np.linalg.norm(z, _dual(p)) / v for z, v in zip(zs, vals))
        if p == 1:
            beta = max(beta, *pinned_fits(u, d))
    return {"alpha": alpha, "beta": float(beta), "power": float((alpha * beta) ** p)}


def _dual(p: float) -> float:
    return np.inf if p == 1 else p / (p - 1)


def pinned_fits(u: DataFrame, d: int) -> list[float]:
    """For each coordinate, 1 over the least l1 norm of U z with that coordinate at one in size: their largest is beta for p = 1."""
    out = []
    for j in range(d):
        order = [i for i in range(d) if i != j] + [j]
        turned = u.select("row_id", F.array(*[F.col("vec")[i] for i in order]).alias("vec"))
        z = solve_full(turned, d, "lp", 1.0, -1.0)
        out.append(float(np.abs(z).max() / evaluate(turned, [z], "lp", 1.0)[0]))
    return out


def leverage_bounds(rows: DataFrame, matrix: np.ndarray, d: int, p: float, panel: int = 64, seed: int = 0) -> dict:
    """Leverage against its bounds in U = A P: the sum of the leverage scores, (alpha beta)^p above it, and the largest share that a row's leverage has of beta^p times its norm in U.

    Leverage is exact for p = 2 and else the supremum over a panel of directions, a lower bound; the rows are read three times and never sorted or joined.
    """
    from .leverage import projected
    from .subspace import exact_conditioner

    u = rows.select("row_id", projected(matrix).alias("vec"))
    known = conditioning(rows, matrix, d, p, panel, seed)
    if p == 2:
        lev = norm_of(projected(exact_conditioner(u, d)), 2.0)
    else:
        zs = default_panel(d, panel, seed)
        lev = F.greatest(*[abs_pow(dot(z), p) / F.lit(float(v)) for z, v in zip(zs, evaluate(u, zs, "lp", p))])
    bound = norm_of(F.col("vec"), p) * F.lit(known["beta"] ** p)
    whole, share = u.select(lev.alias("lev"), bound.alias("bound")).agg(F.sum("lev"), F.max(F.when(F.col("bound") > 0, F.col("lev") / F.col("bound")))).first()
    return {"leverage_sum": float(whole), "bound": known["power"], "share": float(share)}


def inclusion_bands(drawn: DataFrame, norms: DataFrame, k: int, repetitions: int) -> DataFrame:
    """(band, rows, frequency, floor): mean inclusion of the rows (row_id, one row a draw) against the guaranteed min(1, k norm / total), by powers of two of the floor."""
    total = float(norms.agg(F.sum("norm_p")).first()[0])
    floor = F.least(F.lit(1.0), F.col("norm_p") * F.lit(k / total))
    seen = drawn.groupBy("row_id").agg((F.count("*") / F.lit(float(repetitions))).alias("frequency"))
    both = norms.filter("norm_p > 0").join(seen, "row_id", "left").select(F.coalesce("frequency", F.lit(0.0)).alias("frequency"), floor.alias("floor"))
    return both.groupBy(F.floor(F.log2("floor")).cast("int").alias("band")).agg(F.count("*").alias("rows"), F.avg("frequency").alias("frequency"), F.avg("floor").alias("floor"))


def distortion(rows: DataFrame, embedded: np.ndarray, p: float, d: int, count: int = 32, kind: str = "dense") -> tuple[float, float]:
    """Least and greatest ratio of the embedded to the true norm over a panel: dense, by the median over the stable variable's (p < 2) or the root mean square; sparse, by the lp norm."""
    from .baselines import stable_scale

    zs = default_panel(d, count)
    true = evaluate(rows, zs, "lp", p) ** (1 / p)
    size = (lambda v: np.linalg.norm(v, p)) if kind == "sparse" else (lambda v: np.median(np.abs(v)) / stable_scale(p)) if p < 2 else (lambda v: np.linalg.norm(v) / np.sqrt(len(v)))
    ratio = np.array([size(embedded @ z) for z in zs]) / true
    return float(ratio.min()), float(ratio.max())


def convexity_gap(f, d: int, pairs: int = 200, seed: int = 0) -> float:
    """Largest f(midpoint) - mean(f at the ends) over random pairs, relative: positive means not convex."""
    rng = np.random.default_rng(seed)
    worst = -np.inf
    for _ in range(pairs):
        a, b = rng.normal(size=(2, d))
        m = (f(a) + f(b)) / 2
        worst = max(worst, (f((a + b) / 2) - m) / max(abs(m), 1e-300))
    return float(worst)
