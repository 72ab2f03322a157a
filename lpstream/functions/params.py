"""Sizes that the guarantees ask for, and what earlier methods need: calculators, no data.

All constants are explicit arguments where the statement has only an order.
"""

from __future__ import annotations

import math
from dataclasses import dataclass


def check_p(p: float, allow_large_p: bool = False) -> float:
    """p in [1, 2]; beyond 2 a sketch of about n^(1-2/p) rows is unavoidable, so it must be asked for."""
    if p < 1 or (p > 2 and not allow_large_p):
        raise ValueError(f"p must lie in [1, 2], not {p}: for p > 2 the sketch grows as n^(1-2/p)")
    return float(p)


def large_p_rows(n: int, p: float) -> float:
    """Order of the least sketch size for p > 2 (1 up to 2)."""
    return max(1.0, n ** (1 - 2 / p) * math.log(n)) if p > 2 else 1.0


def heavy_rows(gamma: float, eps: float, delta: float, n: int, p: float) -> dict:
    """Sketch that lists every row with at least a gamma share of the tail, with row error eps/3."""
    return {"r": 8 / gamma * (12 / eps) ** p, "s": 3 * math.log(6 * n / delta) / 0.025**3, "list_multiplier": (12 / eps) ** p, "row_error": eps / 3}


def sampler(k: int | None, eps: float, delta: float, n: int, p: float) -> dict:
    """Sketch of a sampler of k rows; the heavy-row sketch at eps/6, delta/6 and gamma = 1/(4 k ln n)."""
    least_k = 160 * math.log(12 / delta)
    k = max(k or 0, math.ceil(least_k))
    return {"k": k, "r": 32 * k * math.log(n) * (72 / eps) ** p, "s": 3 * math.log(36 * n / delta) / 0.025**3, "least_k": least_k}


def coreset_rows(loss: str, k: int, n: int, eps: float, p: float, alpha: float, beta: float, mu: float = 1.0, constant: float = 1.0) -> float:
    """Sketch rows r for a coreset of the loss, up to the constant."""
    ab = alpha**p * beta**p
    base = {"lp": (ab / eps) ** p, "relu": (mu * ab / eps) ** p, "logistic": mu * alpha * beta / eps, "probit": (p * mu**2 * ab / eps) ** p}[loss]
    return constant * k * math.log(n) * base


def conditioning(p: float, d: int, kind: str = "dense", constant: float = 1.0) -> dict:
    """alpha, beta and (alpha beta)^p of a well-conditioned basis, up to the constant."""
    log_d = max(1.0, math.log(max(d, 2)))
    loglog = max(1.0, math.log(log_d) if log_d > 1 else 1.0)
    if kind == "spanning":
        return {"alpha": None, "beta": None, "power": constant * d * loglog}
    if kind == "sparse":
        return {"alpha": None, "beta": None, "power": constant * d ** (2 + p / 2) * log_d ** (1 + p / 2)}
    if p == 2:
        return {"alpha": constant * math.sqrt(2 * d), "beta": constant * math.sqrt(2), "power": constant * d}
    return {
        "alpha": constant * d ** (2 / p - 0.5) * log_d ** (1 / p - 0.5),
        "beta": constant * (d * log_d * loglog) ** (1 / p),
        "power": constant * d ** (3 - p / 2) * log_d ** (2 - p / 2) * loglog,
    }


def previous_sizes(eps: float, d: int, n: int) -> dict:
    """Earlier turnstile sketches for logistic regression: constant factor at polynomial size, or eps at exponential size."""
    return {"constant_factor_rows": d * math.log(max(n, 2)), "eps_rows": math.exp(1 / eps)}


@dataclass(frozen=True)
class SketchSpec:
    """Everything two sketches must share to be added: p, sizes, seed, hash family, carved share, accumulator."""

    p: float = 1.0
    r: int = 2000
    s: int = 11
    d: int = 7
    n: int | None = None
    seed: int = 42
    family: str = "poly"
    scale: bool = True
    uniform_cut: float = 0.0
    fixed: int = 1 << 40  # units of the accumulator in one; a power of two
    list_multiplier: float = 1.0
    quantile: float = 0.65
    allow_large_p: bool = False

    def __post_init__(self):
        check_p(self.p, self.allow_large_p)
        if self.s % 2 == 0:
            raise ValueError("an odd number of repetitions makes every median an element")
        if self.fixed & (self.fixed - 1):
            raise ValueError("the accumulator's unit is a power of two, so that scaling is exact")


def practical(k: int, p: float, d: int, seed: int = 42, **more) -> SketchSpec:
    """Runnable sizes: 20 k buckets, 11 repetitions, list multiplier 1; the guarantees' constants are not met."""
    return SketchSpec(p=p, r=20 * k, s=11, d=d, seed=seed, **more)
