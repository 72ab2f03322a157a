"""Losses of the dot product t = a z, as Columns and in numpy: |t|^p, max(0,t)^p, logistic, p-generalised probit."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, functions as F

from .hashing import abs_pow

LOSSES = ("lp", "relu", "logistic", "probit")


def gamma_p(a: float, x: np.ndarray) -> np.ndarray:
    """Regularised lower incomplete gamma: series below a+1, continued fraction above."""
    x = np.asarray(x, float)
    out = np.zeros_like(x)
    low = (x < a + 1) & (x > 0)
    if low.any():
        v = x[low]
        term = np.full_like(v, 1 / a)
        total = term.copy()
        for n in range(1, 400):
            term = term * v / (a + n)
            total += term
            if term.max() < 1e-17 * total.min():
                break
        out[low] = total * np.exp(-v + a * np.log(v) - math.lgamma(a))
    high = x >= a + 1
    if high.any():
        out[high] = 1 - np.exp(log_gamma_q(a, x[high]))
    return out


def log_gamma_q(a: float, x: np.ndarray) -> np.ndarray:
    """log of the regularised upper incomplete gamma for x >= a+1 (Lentz)."""
    x = np.asarray(x, float)
    if not x.size:
        return x
    b = x + 1 - a
    c = np.full_like(x, 1e300)
    d = 1 / b
    h = d.copy()
    for i in range(1, 300):
        an = -i * (i - a)
        b = b + 2
        d = 1 / np.where(np.abs(an * d + b) < 1e-300, 1e-300, an * d + b)
        c = np.where(np.abs(b + an / c) < 1e-300, 1e-300, b + an / c)
        step = d * c
        h = h * step
        if np.abs(step - 1).max() < 1e-15:
            break
    return -x + a * np.log(np.maximum(x, 1e-300)) - math.lgamma(a) + np.log(h)


def log_cdf(x: np.ndarray, p: float) -> np.ndarray:
    """log of the p-generalised normal's distribution function (p=2 normal, p=1 Laplace), density ~ exp(-|x|^p / p)."""
    x = np.asarray(x, float)
    a, y = 1 / p, np.abs(x) ** p / p
    out = np.empty_like(x)
    pos = x >= 0
    out[pos] = np.log1p(-0.5 * (1 - gamma_p(a, y[pos])))
    neg = ~pos
    if neg.any():
        v = y[neg]
        tail = np.empty_like(v)
        far = v >= a + 1
        tail[far] = log_gamma_q(a, v[far])
        tail[~far] = np.log1p(-gamma_p(a, v[~far]))
        out[neg] = tail - math.log(2)
    return out


def value_numpy(loss: str, t: np.ndarray, p: float = 1.0) -> np.ndarray:
    if loss == "lp":
        return np.abs(t) ** p
    if loss == "relu":
        return np.maximum(t, 0) ** p
    if loss == "logistic":
        return np.maximum(t, 0) + np.log1p(np.exp(-np.abs(t)))
    return -log_cdf(-t, p)


def slope_numpy(loss: str, t: np.ndarray, p: float = 1.0) -> np.ndarray:
    """Derivative in t (a subgradient where there is none)."""
    if loss == "lp":
        return p * np.abs(t) ** (p - 1) * np.sign(t)
    if loss == "relu":
        return np.where(t > 0, p * np.maximum(t, 0) ** (p - 1), 0.0)
    if loss == "logistic":
        return 0.5 * (1 + np.tanh(t / 2))
    # density over distribution function at -t
    log_density = -(np.abs(t) ** p) / p - math.log(2) - math.lgamma(1 + 1 / p) - math.log(p) / p
    return np.exp(log_density - log_cdf(-t, p))


def value(loss: str, t: Column, p: float = 1.0) -> Column:
    if loss == "lp":
        return abs_pow(t, p)
    if loss == "relu":
        return abs_pow(F.greatest(t, F.lit(0.0)), p)
    if loss == "logistic":
        return F.greatest(t, F.lit(0.0)) + F.log1p(F.exp(-F.abs(t)))
    if p == 1:  # Laplace: closed form, stable on both sides
        return F.when(t > 0, t + F.log(F.lit(2.0))).otherwise(-F.log1p(F.lit(-0.5) * F.exp(t)))
    return _probit(p)(t)


def _probit(p: float):
    @F.pandas_udf("double")
    def probit(t: pd.Series) -> pd.Series:
        return pd.Series(-log_cdf(-t.to_numpy(float), p))

    return probit
