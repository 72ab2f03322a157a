"""Seeded hash functions of row ids: buckets, signs and uniform scalars.

`poly` is a polynomial over the field of (2^31-1)^2 elements, pairs u + v i with
i^2 = -1, with coefficients drawn from a seeded generator: bounded independence
for ids below 2^62 - 2^32, in products that fit 64-bit integers, so any SQL engine
repeats it.  One value gives a bucket (u) and a sign (v), or 62 bits of a uniform.
`fast` is xxhash64 with 53-bit uniforms.  Nothing is stored per row; the same value
is made again wherever it is needed, before and after sketching.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, functions as F

PRIME = (1 << 31) - 1


#: Ids are below this.
FIELD = PRIME * PRIME


def coefficients(seed: int, stream: str, index: int = 0, degree: int = 3) -> list[int]:
    """Random polynomial coefficients, highest power first, each as its two parts, for one independent stream."""
    tag = sum((i + 1) * ord(c) for i, c in enumerate(stream))
    rng = np.random.default_rng([seed, tag, index])
    return [int(x) for x in rng.integers(1, PRIME, 2 * (degree + 1))]


def field(row, coef, prime=PRIME, whole=lambda x: x // PRIME):
    """Both parts of the polynomial by Horner's rule; every product sum stays below 2^63."""
    x, y = row % prime, whole(row)
    u, v = coef[0], coef[1]
    for c, e in zip(coef[2::2], coef[3::2]):
        u, v = (u * x + (prime - v) * y + c) % prime, (u * y + v * x + e) % prime
    return u, v


def field_sql(column: str, coef: list) -> tuple[str, str]:
    """The same as SQL text; coefficients may be column names."""
    x, y = f"({column} % {PRIME})", f"({column} // {PRIME})"
    u, v = str(coef[0]), str(coef[1])
    for c, e in zip(coef[2::2], coef[3::2]):
        u, v = f"(({u} * {x} + ({PRIME} - {v}) * {y} + {c}) % {PRIME})", f"(({u} * {y} + {v} * {x} + {e}) % {PRIME})"
    return u, v


def poly_sql(column: str, coef: list[int]) -> str:
    return field_sql(column, coef)[0]


def _long(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x).cast("long")


def field_columns(row: Column, coef: list) -> tuple[Column, Column]:
    """The same as columns; coefficients may be columns."""
    p = F.lit(PRIME).cast("long")
    return field(row.cast("long"), [_long(c) for c in coef], p, lambda x: F.call_function("div", x, p))


def poly(x: Column, coef: list[int]) -> Column:
    """One part, uniform below the prime."""
    return field_columns(x, coef)[0]


def chosen(rows: list[list[int]], index: Column) -> list[Column]:
    """The coefficients of the stream that a column numbers, from literal arrays: expressions stay small however many streams there are."""
    return [F.array(*[F.lit(r[k]).cast("long") for r in rows])[index] for k in range(len(rows[0]))]


def field_numpy(row: np.ndarray, coef: list[int]) -> tuple[np.ndarray, np.ndarray]:
    row = np.asarray(row, np.int64)
    if not len(row) or row.min() < 0:
        return field(row, [np.int64(c) for c in coef])
    if row.max() < PRIME:  # the second part of every id is zero
        u, v = np.int64(coef[0]), np.int64(coef[1])
        for c, e in zip(coef[2::2], coef[3::2]):
            u, v = _rest(u * row + c), _rest(v * row + e)
        return u, v
    y = row // PRIME
    x = row - y * PRIME
    u, v = np.int64(coef[0]), np.int64(coef[1])
    for c, e in zip(coef[2::2], coef[3::2]):
        u, v = _rest(u * x + (PRIME - v) * y + c), _rest(u * y + v * x + e)
    return u, v


def _rest(x: np.ndarray) -> np.ndarray:
    """Remainder by the prime of numbers from 0, by shifts: 2^31 leaves one."""
    x = (x & PRIME) + (x >> 31)
    x = (x & PRIME) + (x >> 31)
    x -= PRIME * (x >= PRIME)
    return x


def poly_numpy(x: np.ndarray, coef: list[int]) -> np.ndarray:
    return field_numpy(x, coef)[0]


class Many:
    """The polynomials of many coefficient lists at once, as `field_numpy`: powers of the ids in limbs of 16 bits, times a matrix of limbs; every sum stays below 2^53."""

    def __init__(self, coefs: list, parts: int = 2):
        rows = []
        for part in range(parts):
            for c in coefs:
                row = []
                for u, v in list(zip(c[0::2], c[1::2]))[-2::-1]:  # from the lowest power
                    row += [u, PRIME - v] if part == 0 else [v, u]
                rows.append([x * y % PRIME for x in row for y in (1, 1 << 16)] + [c[-2 + part]])
        whole = np.array(rows, np.int64)
        self.shape, self.low, self.high = (parts, len(coefs)), (whole & 0xFFFF).astype(float), (whole >> 16).astype(float)

    def __call__(self, row: np.ndarray):
        """(slice, values): of some ids at a time, as many as stay in a core's cache, (parts x coefficient lists x ids) as whole floating-point numbers."""
        degree = self.low.shape[1] // 4
        y = row // PRIME
        x = row - y * PRIME
        u, v = x, y
        limbs = np.ones((4 * degree + 1, len(row)))
        for k in range(degree):
            if k:
                u, v = _rest(u * x + (PRIME - v) * y), _rest(u * y + v * x)
            for i, z in enumerate((u & 0xFFFF, u >> 16, v & 0xFFFF, v >> 16)):
                limbs[4 * k + i] = z
        size = max(128, (1 << 15) // len(self.low))
        for i in range(0, len(row), size):
            mine = limbs[:, i : i + size]
            out = self.high @ mine
            out *= 65536.0
            out += self.low @ mine
            whole = out * (1.0 / PRIME - 2.0**-80)  # never above the quotient, hardly below
            np.floor(whole, out=whole)
            whole *= PRIME
            out -= whole
            np.subtract(out, PRIME, out=out, where=out >= PRIME)
            yield slice(i, i + size), out.reshape(*self.shape, -1)


@dataclass(frozen=True)
class Hashes:
    """The hash functions of one sketch: t by row, bucket and sign by row and repetition."""

    seed: int
    family: str = "poly"

    def t_coef(self) -> list[int]:
        return coefficients(self.seed, "scale", 0, 3)

    def place_coef(self, rep: int) -> list[int]:
        return coefficients(self.seed, "place", rep, 3)

    # --- Column forms
    def uniform(self, row: Column) -> Column:
        """t in (0, 1]."""
        if self.family == "poly":
            u, v = field_columns(row, self.t_coef())
            return (u * F.lit(PRIME).cast("long") + v + 1).cast("double") / F.lit(float(FIELD))
        return self._fast_uniform(row, "scale")

    def _fast_uniform(self, row: Column, stream: str) -> Column:
        h = F.xxhash64(F.lit(self.seed), F.lit(stream), row)
        return (F.shiftrightunsigned(h, 11).cast("double") + 1.0) / F.lit(float(1 << 53))

    def _place(self, row: Column, rep: Column, reps: int) -> tuple[Column, Column]:
        return field_columns(row, chosen([self.place_coef(j) for j in range(reps)], rep))

    def bucket_at(self, row: Column, rep: Column, r: int, reps: int) -> Column:
        if self.family == "poly":
            return (self._place(row, rep, reps)[0] % F.lit(r).cast("long")).cast("int")
        return F.pmod(F.xxhash64(F.lit(self.seed), F.lit("bucket"), rep, row), F.lit(r).cast("long")).cast("int")

    def sign_at(self, row: Column, rep: Column, reps: int) -> Column:
        if self.family == "poly":
            return F.when(self._place(row, rep, reps)[1] < PRIME // 2, -1).otherwise(1)
        return F.when(F.xxhash64(F.lit(self.seed), F.lit("sign"), rep, row) < 0, -1).otherwise(1)

    # --- numpy forms of the polynomial family
    def bucket_numpy(self, row: np.ndarray, rep: int, r: int) -> np.ndarray:
        return poly_numpy(row, self.place_coef(rep)) % r

    def place_numpy(self, row: np.ndarray, rep: int, r: int) -> tuple[np.ndarray, np.ndarray]:
        """Buckets and signs from one evaluation."""
        u, v = field_numpy(row, self.place_coef(rep))
        return u % r, np.where(v < PRIME // 2, -1, 1)

    def places_numpy(self, row: np.ndarray, r: int, reps: int) -> tuple[np.ndarray, np.ndarray]:
        """`place_numpy` for all repetitions: buckets and signs (repetitions x ids)."""
        bucket, sign = np.empty((reps, len(row)), np.int64), np.empty((reps, len(row)), np.int64)
        for at, (u, v) in Many([self.place_coef(j) for j in range(reps)])(row):
            bucket[:, at] = u - np.floor((u + 0.5) * (1.0 / r)) * r
            sign[:, at] = np.where(v < PRIME // 2, -1, 1)
        return bucket, sign

    def buckets_numpy(self, row: np.ndarray, r: int, reps: int) -> np.ndarray:
        """`bucket_numpy` for all repetitions."""
        bucket = np.empty((reps, len(row)), np.int64)
        for at, (u,) in Many([self.place_coef(j) for j in range(reps)], 1)(row):
            bucket[:, at] = u - np.floor((u + 0.5) * (1.0 / r)) * r
        return bucket

    def uniform_numpy(self, row: np.ndarray) -> np.ndarray:
        u, v = field_numpy(row, self.t_coef())
        return (u * PRIME + v + 1).astype(float) / float(FIELD)

    # --- SQL forms of the polynomial family
    def uniform_sql(self, row: str) -> str:
        u, v = field_sql(row, self.t_coef())
        return f"(cast({u} * {PRIME} + {v} + 1 as double) / {float(FIELD)!r}::double)"

    def bucket_sql(self, row: str, rep: int, r: int) -> str:
        return f"({field_sql(row, self.place_coef(rep))[0]} % {r})"

    def sign_sql(self, row: str, rep: int) -> str:
        return f"(case when {field_sql(row, self.place_coef(rep))[1]} < {PRIME // 2} then -1 else 1 end)"


def inv_scale(t: Column, p: float) -> Column:
    """t^(-1/p), without pow where a cheaper exact form exists."""
    if p == 1:
        return F.lit(1.0) / t
    if p == 2:
        return F.lit(1.0) / F.sqrt(t)
    return F.pow(t, F.lit(-1.0 / p).cast("double"))


def inv_scale_sql(t: str, p: float) -> str:
    return f"(1.0::double / {t})" if p == 1 else f"(1.0::double / sqrt({t}))" if p == 2 else f"pow({t}, {-1.0 / p!r}::double)"


def abs_pow(x: Column, p: float) -> Column:
    """|x|^p."""
    return F.abs(x) if p == 1 else x * x if p == 2 else F.pow(F.abs(x), F.lit(float(p)))


def abs_pow_sql(x: str, p: float) -> str:
    return f"abs({x})" if p == 1 else f"(({x}) * ({x}))" if p == 2 else f"pow(abs({x}), {float(p)!r}::double)"


def root(x: Column, p: float) -> Column:
    return x if p == 1 else F.sqrt(x) if p == 2 else F.pow(x, F.lit(1.0 / p).cast("double"))
