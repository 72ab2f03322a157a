"""Minimisers of weighted losses: at the driver for coresets, by one aggregate a step for full data."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from ..functions.losses import slope_numpy, value, value_numpy
from .sketch import stacked


def objective(x: np.ndarray, w: np.ndarray, z: np.ndarray, loss: str, p: float) -> float:
    return float((w * value_numpy(loss, x @ z, p)).sum())


def _quasi_newton(f, z0: np.ndarray, rounds: int = 300, memory: int = 12, tol: float = 1e-10, halvings: int = 40) -> np.ndarray:
    """Limited-memory quasi-Newton with backtracking; returns the best point seen."""
    z = z0.copy()
    v, g = f(z)
    best, best_v = z.copy(), v
    pairs: list = []
    for _ in range(rounds):
        if np.abs(g).max() < tol * max(1.0, abs(v)):
            break
        d = -g
        a = []
        for s, y in reversed(pairs):
            c = (s @ d) / (s @ y)
            a.append(c)
            d = d - c * y
        if pairs:
            s, y = pairs[-1]
            d = d * (s @ y) / (y @ y)
        else:
            d = d / max(np.abs(g).sum(), 1e-300)
        for (s, y), c in zip(pairs, reversed(a)):
            d = d + s * (c - (y @ d) / (s @ y))
        if g @ d >= 0:
            d, pairs = -g / max(np.abs(g).sum(), 1e-300), []
        step, ok = 1.0, False
        for _ in range(halvings):
            nz = z + step * d
            nv, ng = f(nz)
            if np.isfinite(nv) and nv <= v + 1e-4 * step * (g @ d):
                ok = True
                break
            step /= 2
        if not ok:
            break
        s, y = nz - z, ng - g
        if s @ y > 1e-14 * np.linalg.norm(s) * np.linalg.norm(y):
            pairs = (pairs + [(s, y)])[-memory:]
        done = abs(v - nv) <= tol * max(1e-300, abs(nv))
        z, v, g = nz, nv, ng
        if v < best_v:
            best, best_v = z.copy(), v
        if done:
            break
    return best


def solve(x: np.ndarray, w: np.ndarray, loss: str, p: float = 1.0, ridge: float = 1e-8, last: float | None = None, first: float | None = None) -> np.ndarray:
    """argmin of the weighted loss; `last` fixes the last coordinate (-1 for regression onto an appended target), `first` the first (a ReLU problem without it has the solution zero)."""
    x, w = np.asarray(x, float), np.asarray(w, float)
    keep = np.isfinite(x).all(1)
    x, w = x[keep], w[keep]
    d = x.shape[1]
    if last is not None and loss == "lp":
        return np.r_[_irls(x[:, :-1], -last * x[:, -1], w, p), last]
    total = max(w.sum(), 1e-300)

    def f(z):
        t = x @ z
        g = x.T @ (w * slope_numpy(loss, t, p)) / total + 2 * ridge * z
        return float((w * value_numpy(loss, t, p)).sum() / total + ridge * (z @ z)), _pinned(g, first)

    return _quasi_newton(f, _start(d, first))


def _start(d: int, first: float | None) -> np.ndarray:
    z = np.zeros(d)
    z[0] = first or 0.0
    return z


def _pinned(g: np.ndarray, first: float | None) -> np.ndarray:
    """The slope without the pinned coordinate, which then never moves."""
    return g if first is None else np.r_[0.0, g[1:]]


def _irls(a: np.ndarray, b: np.ndarray, w: np.ndarray, p: float, rounds: int = 80) -> np.ndarray:
    """lp regression by smoothed reweighted least squares, best point seen; near p = 1 optimality isn't certified."""
    best, best_v = None, np.inf
    scale = np.abs(b).mean() + 1e-12
    weight = w.copy()
    for r in range(rounds):
        m = a * weight[:, None]
        g = m.T @ a
        z = np.linalg.solve(g + 1e-12 * max(np.trace(g), 1e-300) * np.eye(a.shape[1]), m.T @ b)
        res = np.abs(a @ z - b)
        v = float((w * res**p).sum())
        if v < best_v:
            best, best_v = z, v
        eps = scale * max(1e-7, 0.5**r)
        weight = w * (res**2 + eps**2) ** (p / 2 - 1)
    return best


def dot(z: np.ndarray, vec: str = "vec") -> Column:
    out = F.col(vec)[0] * F.lit(float(z[0]))
    for i in range(1, len(z)):
        out = out + F.col(vec)[i] * F.lit(float(z[i]))
    return out


def blocks(rows: DataFrame, d: int, size: int = 128) -> DataFrame:
    """(block): the vectors of up to `size` rows each as the bytes of one matrix; rows with a null or no finite number are left out, as `solve` does.

    A solver reads a table some dozens of times: as blocks that costs little more than moving the bytes.
    """

    def run(batches):
        for b in batches:
            x = stacked(b.column(0), d)
            x = np.ascontiguousarray(x[np.isfinite(x).all(1)])
            yield pa.RecordBatch.from_arrays([pa.array([x[i : i + size].tobytes() for i in range(0, len(x), size)], pa.binary())], names=["block"])

    return rows.select("vec").mapInArrow(run, "block binary")


def summed(packed: DataFrame, d: int, f, size: int) -> np.ndarray:
    """Sums of f(rows) -> `size` numbers over all blocks; each task sends one row of them."""
    names = [f"s{k}" for k in range(size)]

    def run(batches):
        total = np.zeros(size)
        for b in batches:
            col = b.column(0)
            if not len(col):
                continue
            ends = np.frombuffer(col.buffers()[1], np.int64 if pa.types.is_large_binary(col.type) else np.int32)[col.offset : col.offset + len(col) + 1]
            x = np.frombuffer(col.buffers()[2], np.uint8)[ends[0] : ends[-1]].view(np.float64).reshape(-1, d)
            for i in range(0, len(x), 16384):
                y = x[i : i + 16384]
                total += f(y if np.isfinite(y).all() else y[np.isfinite(y).all(1)])
        yield pa.RecordBatch.from_arrays([pa.array([v]) for v in total], names=names)

    got = packed.mapInArrow(run, ", ".join(f"{c} double" for c in names)).collect()
    return np.array([math.fsum(c) for c in zip(*got)]) if got else np.zeros(size)


def evaluate_blocks(packed: DataFrame, panel: list[np.ndarray], loss: str, p: float = 1.0) -> np.ndarray:
    """`evaluate` on blocks."""
    z = np.array(panel, float).T
    return summed(packed, len(z), lambda x: value_numpy(loss, x @ z, p).sum(axis=0), z.shape[1])


def evaluate(rows: DataFrame, panel: list[np.ndarray], loss: str, p: float = 1.0) -> np.ndarray:
    """Full-data loss of every z of a panel, one scan for all."""
    got = rows.agg(*[F.sum(value(loss, dot(z), p)) for z in panel]).first()
    return np.array([float(v or 0.0) for v in got])


def solve_full(rows: DataFrame, d: int, loss: str, p: float = 1.0, last: float | None = None, rounds: int = 40) -> np.ndarray:
    """Full-data optimum by reweighted normal equations: one aggregate of d(d+1)/2 + d sums a step, best point seen.

    `rows` have a column vec, or are `blocks`.  Logistic steps are damped Newton, lp and ReLU steps smoothed reweighting;
    only numbers of order d^2 reach the driver.
    """
    m = d - 1 if last is not None else d
    z = np.zeros(m)
    best, best_v = None, np.inf
    pairs = [(i, j) for i in range(m) for j in range(i, m)]
    full = lambda v: np.r_[v, last] if last is not None else v
    packed = "block" in rows.columns
    rows = rows if packed else rows.persist()
    for r in range(rounds):
        if packed:
            got = _step(rows, full(z), m, loss, p, 10.0 * 0.5**r + 1e-7)
            h, g, v = got[: m * m].reshape(m, m), got[m * m : -1], float(got[-1])
            if v < best_v * (1 - 1e-10):
                best, best_v, stale = z.copy(), v, 0
            else:
                stale += 1
                if loss == "logistic" or stale > 3:
                    break
            z = z - np.linalg.solve(h + 1e-10 * max(np.trace(h), 1e-300) * np.eye(m), g)
            continue
        t = dot(full(z))
        if loss == "logistic":
            s = 1.0 / (1.0 + F.exp(-t))
            curve, slope = s * (1.0 - s) + 1e-9, s
        elif loss == "lp":
            eps = F.lit(10.0 * 0.5**r + 1e-7)
            curve = F.pow(t * t + eps * eps, F.lit(p / 2 - 1))
            slope = curve * t
        else:
            pos = F.when(t > 0, 1.0).otherwise(0.0)
            curve, slope = pos * max(p, 1.0) + 1e-9, pos * F.pow(F.abs(t), F.lit(float(p - 1)))
        got = rows.agg(*[F.sum(curve * F.col("vec")[i] * F.col("vec")[j]) for i, j in pairs], *[F.sum(slope * F.col("vec")[i]) for i in range(m)], F.sum(value(loss, t, p))).first()
        h = np.zeros((m, m))
        for (i, j), v in zip(pairs, got):
            h[i, j] = h[j, i] = v
        g, v = np.array(got[len(pairs) : len(pairs) + m]), float(got[-1])
        if v < best_v * (1 - 1e-10):
            best, best_v, stale = z.copy(), v, 0
        else:
            stale += 1
            if loss == "logistic" or stale > 3:
                break
        z = z - np.linalg.solve(h + 1e-10 * max(np.trace(h), 1e-300) * np.eye(m), g)
    return full(best)


def _step(packed: DataFrame, z: np.ndarray, m: int, loss: str, p: float, eps: float) -> np.ndarray:
    """Curvature (m x m), slope (m) and value of one step of `solve_full`, over blocks."""

    def f(x):
        t = x @ z
        if loss == "logistic":
            s = 0.5 * (1 + np.tanh(t / 2))
            curve, slope = s * (1.0 - s) + 1e-9, s
        elif loss == "lp":
            curve = 1.0 / np.sqrt(t * t + eps * eps) if p == 1 else (t * t + eps * eps) ** (p / 2 - 1)
            slope = curve * t
        else:
            pos = (t > 0).astype(float)
            curve, slope = pos * max(p, 1.0) + 1e-9, pos * np.abs(t) ** (p - 1)
        a = x[:, :m]
        return np.r_[((a * curve[:, None]).T @ a).ravel(), slope @ a, value_numpy(loss, t, p).sum()]

    return summed(packed, len(z), f, m * m + m + 1)


def polish(packed: DataFrame, start: np.ndarray, eps: float, least: float, p: float, last: float, rounds: int = 40) -> np.ndarray:
    """Full-data optimum of lp regression over `blocks` from a good start: Newton steps on (t^2 + eps^2)^(p/2), eps falling to `least`, best point seen.

    A step is one scan.  Where it made the smoothed loss larger, it is shortened, then replaced by
    a reweighting step from the point before, which never does.
    """
    z, m = start[:-1], len(start) - 1
    base, tries, same, best, best_v, stale = None, 0, 0, z.copy(), np.inf, 0
    ridge = lambda h: h + 1e-10 * max(np.trace(h), 1e-300) * np.eye(m)
    for _ in range(rounds):
        old = eps if base is None else base[1]

        def f(x):
            t = x @ np.r_[z, last]
            two = t * t + eps * eps
            power = 1.0 / np.sqrt(two) if p == 1 else two ** (p / 2 - 1)
            curve = power / two * (eps * eps + (p - 1) * t * t)
            a = x[:, :m]
            smooth = np.sqrt(t * t + old * old) if p == 1 else (t * t + old * old) ** (p / 2)
            return np.r_[(a.T @ (a * curve[:, None])).ravel(), (a.T @ (a * power[:, None])).ravel(), (power * t) @ a, value_numpy("lp", t, p).sum(), smooth.sum(), (power * two).sum()]

        got = summed(packed, m + 1, f, 2 * m * m + m + 3)
        newton, major, g = got[: m * m].reshape(m, m), got[m * m : 2 * m * m].reshape(m, m), got[2 * m * m : -3]
        v, smooth, here = got[-3:]
        stale = stale + 1 if v >= best_v * (1 - 1e-10) else 0
        if v < best_v:
            best, best_v = z.copy(), v
        if stale > 8 or stale and eps <= least and not tries:
            break
        if base is not None and smooth > base[2] * (1 + 1e-13):
            tries += 1
            if tries > 3:
                break
            z, eps = base[0] - (0.3**tries * base[3] if tries < 3 else base[4]), base[1]
            continue
        step = np.linalg.solve(ridge(newton), g)
        base, tries = (z, eps, here, step, np.linalg.solve(ridge(major), g)), 0
        z = z - step
        if g @ step < 1e-6 * here or same == 3:
            eps, same = max(least, eps / 5), 0
        else:
            same += 1
    return np.r_[best, last]


def solve_rows(rows: DataFrame, d: int, loss: str, p: float = 1.0, ridge: float = 1e-8, first: float | None = None) -> np.ndarray:
    """The minimiser that `solve` finds with unit weights, on all rows of a table: each step sums value and slopes in the tasks, d + 2 numbers each."""
    names = ["n", "v", *[f"g{j}" for j in range(d)]]
    schema = ", ".join(f"{c} double" for c in names)

    def f(z):
        def part(batches):
            total = np.zeros(d + 2)
            for b in batches:
                x = b.column(0).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(-1, d)
                x = x[np.isfinite(x).all(1)]
                t = x @ z
                total += np.r_[len(x), value_numpy(loss, t, p).sum(), x.T @ slope_numpy(loss, t, p)]
            yield pa.RecordBatch.from_arrays([pa.array([v]) for v in total], names=names)

        n, v, *g = (x or 0.0 for x in rows.select("vec").mapInArrow(part, schema).agg(*[F.sum(c) for c in names]).first())
        n = max(n, 1e-300)
        return float(v / n + ridge * (z @ z)), _pinned(np.array(g) / n + 2 * ridge * z, first)

    # A step is a scan; where slopes jump (ReLU at p = 1) the last digits aren't worth hundreds.
    return _quasi_newton(f, _start(d, first), *((60, 12, 1e-7, 12) if loss == "relu" else ()))


def best_of(rows: DataFrame, found: list[np.ndarray], loss: str, p: float = 1.0) -> tuple[np.ndarray, float]:
    """The best of several solutions on the full data."""
    v = evaluate(rows, found, loss, p)
    k = int(np.argmin(v))
    return found[k], float(v[k])
