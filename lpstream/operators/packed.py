"""Tables of rows (row_id, vec) as bytes: what the methods of an experiment read, for all sizes and seeds by one scan each.

A reduction of a few rows out of millions costs what moving the rows costs.  Here a
task reads them as numpy arrays without a copy.  Samples are those of the
operators on rows; sums may differ in their last digits.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import FIELD, Hashes, coefficients, poly_numpy
from . import baselines, sketch as sk
from .baselines import level_mass, reduce_rows, stables_numpy
from .recover import size_numpy
from .sketch import stacked

SLICE = 16384  # rows whose arrays stay in a core's cache
SUBTREE = 6  # levels of a coreset tree inside one task: 64 batches, so that many tasks share the work
FEW_CANDIDATES = 1_000_000


def pack(rows: DataFrame, strict: bool = True, size: int = 128) -> DataFrame:
    """(ids, block): up to `size` rows as the bytes of their ids and of their vectors, a null number as NaN; `strict`: a null row or a number that isn't finite raises."""

    def run(batches):
        for b in batches:
            if strict and (b.column(0).null_count or b.column(1).null_count):
                raise ValueError("invalid update")
            widths = pc.unique(pc.list_value_length(b.column(1)))
            if not b.num_rows:
                continue
            if len(widths) > 1:
                raise ValueError("rows of different widths")
            row, x = b.column(0).to_numpy(zero_copy_only=False), np.ascontiguousarray(stacked(b.column(1), widths[0].as_py()))
            if strict and (len(row) and (row.min() < 0 or row.max() >= FIELD) or np.count_nonzero(~np.isfinite(x)) > b.column(1).flatten().null_count):
                raise ValueError("invalid update")
            cut = range(0, len(row), size)
            yield pa.RecordBatch.from_arrays([pa.array([a[i : i + size].tobytes() for i in cut], pa.binary()) for a in (row, x)], names=["ids", "block"])

    return rows.select(F.col("row_id").cast("long").alias("row_id"), "vec").mapInArrow(run, "ids binary, block binary")


def _bytes(col) -> np.ndarray:
    ends = np.frombuffer(col.buffers()[1], np.int64 if pa.types.is_large_binary(col.type) else np.int32)[col.offset : col.offset + len(col) + 1]
    return np.frombuffer(col.buffers()[2], np.uint8)[ends[0] : ends[-1]]


def slices(batches, d: int, size: int = SLICE):
    """(ids, rows) of packed batches, as views."""
    for b in batches:
        if len(b.column(0)):
            row, x = _bytes(b.column(0)).view(np.int64), _bytes(b.column(1)).view(np.float64)
            if len(x) != d * len(row):
                raise ValueError("rows of different widths")
            x = x.reshape(-1, d)
            for i in range(0, len(row), size):
                yield row[i : i + size], x[i : i + size]


def width(packed: DataFrame) -> int:
    first = packed.first()
    return len(first.block) // len(first.ids)


def zeroed(x: np.ndarray) -> np.ndarray:
    """Nulls count as zero in sums."""
    return np.nan_to_num(x, nan=0.0, posinf=np.inf, neginf=-np.inf) if np.isnan(x).any() else x


def unpack(packed: DataFrame, d: int) -> DataFrame:
    def run(batches):
        for row, x in slices(batches, d):
            yield _vectors(row, x)

    return packed.mapInArrow(run, "row_id long, vec array<double>")


def live_ids(packed: DataFrame, d: int) -> DataFrame:
    """Ids of the rows that aren't all zero; repeated ids stay repeated."""

    def run(batches):
        for row, x in slices(batches, d, 1 << 20):
            yield pa.RecordBatch.from_arrays([pa.array(row[(zeroed(x) != 0).any(axis=1)])], names=["row_id"])

    return packed.mapInArrow(run, "row_id long")


def _vectors(row: np.ndarray, x: np.ndarray, **more) -> pa.RecordBatch:
    lists = pa.ListArray.from_arrays(pa.array(np.arange(len(row) + 1, dtype=np.int32) * x.shape[1], pa.int32()), pa.array(np.ascontiguousarray(x).ravel()))
    return pa.RecordBatch.from_arrays([pa.array(row), lists, *[pa.array(v) for v in more.values()]], names=["row_id", "vec", *more])


def _state(packed: DataFrame, d: int, start, step, size: int = SLICE) -> list:
    """Arrays that each task fills by step(arrays, ids, rows), one list of them a task at the driver."""

    def run(batches):
        arrays = start()
        for row, x in slices(batches, d, size):
            step(arrays, row, x)
        yield pa.RecordBatch.from_arrays([pa.array([a.tobytes()], pa.binary()) for a in arrays], names=[f"a{k}" for k in range(len(arrays))])

    like = start()
    got = packed.mapInArrow(run, ", ".join(f"a{k} binary" for k in range(len(like)))).collect()
    return [[np.frombuffer(r[k], a.dtype).reshape(a.shape) for k, a in enumerate(like)] for r in got]


def extent(packed: DataFrame, d: int) -> tuple[int, int]:
    """(rows, least id)."""

    def step(arrays, row, x):
        arrays[0] += [len(row), 0]
        arrays[1][:] = min(arrays[1][0], row.min())

    got = _state(packed, d, lambda: [np.zeros(2, np.int64), np.full(1, 1 << 62)], step, 1 << 20)
    return int(sum(g[0][0] for g in got)), int(min((g[1][0] for g in got), default=0))


def embedding(packed: DataFrame, d: int, p: float, m: int | None = None, seed: int = 42) -> np.ndarray:
    """`subspace.dense_rows`."""
    m = m or max(40, 8 * d)

    def step(arrays, row, x):
        x = zeroed(x)
        for at, c in stables_numpy(row, m, p, seed + 101):
            arrays[0] += c @ x[at]

    return np.sum([g[0] for g in _state(packed, d, lambda: [np.zeros((m, d))], step)] or [np.zeros((m, d))], axis=0)


def uniform(packed: DataFrame, d: int, n: int, wanted: list) -> list:
    """`baselines.uniform_rows` for each wanted (k, seed): (ids, rows, probability)."""
    hashed = [Hashes(seed + 17) for _, seed in wanted]

    def run(batches):
        for row, x in slices(batches, d):
            for w, ((k, _), h) in enumerate(zip(wanted, hashed)):
                at = np.flatnonzero(h.uniform_numpy(row) <= k / n)
                if len(at):
                    yield _vectors(row[at], x[at], part=np.full(len(at), w))

    got = _gathered(packed.mapInArrow(run, "row_id long, vec array<double>, part long"), d, len(wanted))
    return [(row, x, np.full(len(row), min(1.0, k / n))) for (k, _), (row, x, *_) in zip(wanted, got)]


def _gathered(found: DataFrame, d: int, parts: int) -> list:
    """Of each part (ids, rows, other columns), in the order of ids, at the driver."""
    got = found.toPandas()
    out = []
    for w in range(parts):
        g = got[got["part"] == w].sort_values("row_id", kind="stable")
        out.append((g["row_id"].to_numpy(), np.array(list(g["vec"]), float).reshape(-1, d), *[g[c].to_numpy() for c in g.columns if c not in ("row_id", "vec", "part")]))
    return out


def oblivious(packed: DataFrame, d: int, wanted: list, signed: bool, levels: int = 5, base: int = 4) -> list:
    """`baselines.oblivious_rows` for each wanted (count, seed): (rows, weights)."""
    each = [max(1, count // levels) for count, _ in wanted]

    def step(arrays, row, x):
        live = (zeroed(x) != 0).any(axis=1)
        for w, (_, seed) in enumerate(wanted):
            u = (poly_numpy(row, coefficients(seed, "level", 0)) + 1) / float(1 << 31)
            lev = np.zeros(len(row), np.int64)
            for l in range(1, levels):
                lev[u <= float(base) ** -l] = l
            cell = lev * each[w] + poly_numpy(row, coefficients(seed, "oblivious", 0)) % each[w]
            y = zeroed(x)
            if signed:
                y = y * np.where(poly_numpy(row, coefficients(seed, "oblivious sign", 0)) < (1 << 30), -1.0, 1.0)[:, None]
            cells = levels * each[w]
            arrays[w][:, d] += np.bincount(cell[live], minlength=cells)
            for j in range(d):
                arrays[w][:, j] += np.bincount(cell, y[:, j], minlength=cells)

    start = lambda: [np.zeros((levels * e, d + 1)) for e in each]
    got = _state(packed, d, start, step)
    out = []
    for w, e in enumerate(each):
        whole = np.sum([g[w] for g in got] or [start()[w]], axis=0)
        used = np.flatnonzero(whole[:, d])
        out.append((whole[used, :d], float(base) ** (used // e) / level_mass(levels, base)))
    return out


def sketches(packed: DataFrame, specs: list) -> list[DataFrame]:
    """`sketch.build_rows` for each specification, by one scan."""
    d = specs[0].d
    if any(s.family != "poly" or s.uniform_cut for s in specs) or sum(s.r * s.s * s.d for s in specs) > sk.DENSE_CELLS:
        return [sk.build_rows(unpack(packed, d), s).persist() for s in specs]

    def run(batches):
        sums = [np.zeros((3, s.s, s.r * d), np.int64) for s in specs]
        seen, size = 0, [0.0] * len(specs)
        for row, x in slices(batches, d):
            seen += x.size
            for w, spec in enumerate(specs):
                parts = sk.limbs_numpy(row, zeroed(x), spec)
                size[w] += sk._checked(seen, size[w], parts)
                parts = [part.ravel() for part in parts]
                for j, (at, sign) in enumerate(zip(*sk.hashes(spec).places_numpy(row, spec.r, spec.s))):
                    sk._add(sums[w], j, (at[:, None] * d + np.arange(d)).ravel(), np.repeat(sign, d), parts)
        for w, spec in enumerate(specs):
            cells = sk._in_use(sums[w], spec)
            yield cells.add_column(0, "sketch", pa.array(np.full(cells.num_rows, w, np.int32)))

    cells = packed.mapInArrow(run, f"sketch int, {sk._PARTS}")
    every = sk.summed(cells, "sketch", "rep", "bucket", "col_id").filter("val <> 0").persist()
    return [every.filter(F.col("sketch") == w).drop("sketch") for w in range(len(specs))]


def priority(packed: DataFrame, d: int, wanted: list) -> list:
    """`baselines.offline_sample` by priority for each wanted (k, seed, p, matrix): (ids, rows, norms, probability)."""
    hashed = [Hashes(seed + 5) for _, seed, _, _ in wanted]

    def run(batches):
        best = [None] * len(wanted)
        for row, x in slices(batches, d):
            for w, ((k, _, p, m), h) in enumerate(zip(wanted, hashed)):
                score = size_numpy(x @ m, p).sum(axis=1)
                key = score / h.uniform_numpy(row)
                at = np.flatnonzero((score > 0) & (key >= (best[w][3][-1] if best[w] is not None and len(best[w][3]) > k else 0.0)))
                found = (row[at], x[at], score[at], key[at])
                if best[w] is not None:
                    found = tuple(np.concatenate(y) for y in zip(best[w], found))
                order = np.lexsort((found[0], -found[3]))[: k + 1]
                best[w] = tuple(y[order] for y in found)
        for w, found in enumerate(best):
            if found is not None:
                yield _vectors(found[0], found[1], score=found[2], key=found[3], part=np.full(len(found[0]), w))

    got = _gathered(packed.mapInArrow(run, "row_id long, vec array<double>, score double, key double, part long"), d, len(wanted))
    out = []
    for (k, *_), (row, x, score, key) in zip(wanted, got):
        order = np.lexsort((row, -key))[: k + 1]
        cut = key[order[k]] if len(order) > k else 0.0
        at = order[:k]
        out.append((row[at], x[at], score[at], np.minimum(1.0, score[at] / cut) if cut > 0 else np.ones(len(at))))
    return out


def _cell(row: np.ndarray, least: int) -> np.ndarray:
    """Cells of ids above the least: growing, each about a thousandth of what lies before it or narrower."""
    x = row - least
    over = np.maximum(np.frexp(x.astype(float))[1] - 11, 0)  # bits below the leading eleven; a float that was rounded up has one more
    return (over << 11) + (x >> over)


CELLS = 54 << 11


def online(packed: DataFrame, d: int, p: float, least: int, wanted: list) -> list:
    """`baselines.online_rows` in the order of ids for each wanted (k, seed): (ids, rows, probability).

    No row is sorted: the norms of the cells before a row's own bound its running
    total from below, so few rows can be kept; a second scan sums the norms up to each of them.
    Rows of equal id count as one arrival.
    """
    norm = lambda x: size_numpy(zeroed(x), p).sum(axis=1)

    def mass(arrays, row, x):
        arrays[0] += np.bincount(_cell(row, least), norm(x), minlength=CELLS)

    cells = np.sum([g[0] for g in _state(packed, d, lambda: [np.zeros(CELLS)], mass, 1 << 17)] or [np.zeros(CELLS)], axis=0)
    before = (np.cumsum(cells) - cells) * (1 - 1e-9)
    shared = packed.sparkSession.sparkContext.broadcast(before)
    hashed = [Hashes(seed + 23) for _, seed in wanted]

    def listed(batches):
        for row, x in slices(batches, d):
            size = norm(x)
            reach = size / np.maximum(shared.value[_cell(row, least)] + size, 1e-300)
            for w, ((k, _), h) in enumerate(zip(wanted, hashed)):
                u = h.uniform_numpy(row)
                at = np.flatnonzero((u <= k * reach) & ~np.isnan(x).any(axis=1))
                if len(at):
                    yield _vectors(row[at], x[at], size=size[at], u=u[at], part=np.full(len(at), w))

    found = packed.mapInArrow(listed, "row_id long, vec array<double>, size double, u double, part long").persist(StorageLevel.MEMORY_AND_DISK)
    if found.count() > FEW_CANDIDATES:  # ids far from the least and close together
        found.unpersist()
        rows = unpack(packed, d).persist()
        got = [baselines.online_rows(rows, k, p, seed=seed).select("row_id", "vec", "prob").toPandas() for k, seed in wanted]
        rows.unpersist()
        return [(g["row_id"].to_numpy(), np.array(list(g["vec"]), float).reshape(-1, d), g["prob"].to_numpy()) for g in got]
    few = _gathered(found, d, len(wanted))
    found.unpersist()
    ends = np.unique(np.concatenate([f[0] for f in few] or [np.zeros(0, np.int64)]))

    def between(arrays, row, x):
        arrays[0] += np.bincount(np.searchsorted(ends, row), norm(x), minlength=len(ends) + 1)

    running = np.cumsum(np.sum([g[0] for g in _state(packed, d, lambda: [np.zeros(len(ends) + 1)], between)] or [np.zeros(len(ends) + 1)], axis=0))
    out = []
    for (k, _), (row, x, size, u) in zip(wanted, few):
        prob = np.minimum(1.0, k * size / np.maximum(running[np.searchsorted(ends, row)], 1e-300))
        keep = (u <= prob) & (size > 0)
        out.append((row[keep], x[keep], prob[keep]))
    return out


def merge_reduce(packed: DataFrame, d: int, n: int, batch: int, wanted: list, p: float) -> list:
    """`baselines.merge_reduce` for each wanted (k, seed) over the same batches: (ids, rows, weights).

    The rows are dealt once, as bytes, to the subtrees of 2^SUBTREE batches; each is reduced in one task for all wanted.
    """
    leaves = max(1, math.ceil(n / batch))
    depth = max(0, math.ceil(math.log2(leaves)))
    first = min(depth, SUBTREE)

    def deal(batches):
        for row, x in slices(batches, d, 1 << 20):
            node = spark_xxhash64(row).view(np.int64) % leaves
            order = np.lexsort((row, node))
            row, x, node = row[order], x[order], node[order]
            tree = node >> first
            edge = np.flatnonzero(np.r_[True, tree[1:] != tree[:-1]])
            for a, b in zip(edge, np.r_[edge[1:], len(row)]):
                yield pa.RecordBatch.from_arrays([pa.array([int(tree[a])]), *[pa.array([v[a:b].tobytes()], pa.binary()) for v in (node, row, x)]], names=["tree", "nodes", "ids", "block"])

    def climb(node, row, x, weight, seed, k, levels, fresh):
        """Sets of rows by node, up so many levels; `fresh`: the batches themselves are reduced first."""
        for l in range(0 if fresh else 1, levels + 1):
            node = node >> 1 if l else node
            order = np.lexsort((row, node))
            node, row, x, weight = node[order], row[order], x[order], weight[order]
            edge = np.flatnonzero(np.r_[True, node[1:] != node[:-1]]) if len(node) else np.zeros(0, np.int64)
            kept, weights = [], []
            for a, b in zip(edge, np.r_[edge[1:], len(node)]):
                at, w = reduce_rows(x[a:b], weight[a:b], k, p, np.random.default_rng([seed, int(node[a]), int(b - a)]))
                kept.append(a + at)
                weights.append(w)
            at = np.concatenate(kept) if kept else np.zeros(0, np.int64)
            node, row, x, weight = node[at], row[at], x[at], np.concatenate(weights) if weights else np.zeros(0)
        return node, row, x, weight

    def subtree(table: pa.Table) -> pa.Table:
        node, row, x = (np.frombuffer(b"".join(table[c].to_pylist()), t) for c, t in (("nodes", np.int64), ("ids", np.int64), ("block", np.float64)))
        order = np.lexsort((row, node))  # once for all wanted: what is in order already is sorted again in no time
        node, row, x = node[order], row[order], x.reshape(-1, d)[order]
        out = []
        for w, (k, seed) in enumerate(wanted):
            nodes, ids, vec, weight = climb(node, row, x, np.ones(len(row)), seed, k, first, True)
            out.append(_vectors(ids, vec, node=nodes, weight=weight, part=np.full(len(ids), w)))
        return pa.Table.from_batches(out)

    def upper(up: int):
        def run(key, table):
            w = int(key[1].as_py())
            k, seed = wanted[w]
            x = table["vec"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            node, ids, vec, weight = climb(table["node"].to_numpy(), table["row_id"].to_numpy(), x, table["weight"].to_numpy(), seed, k, up, False)
            return pa.Table.from_batches([_vectors(ids, vec, node=node, weight=weight, part=np.full(len(ids), w))])

        return run

    schema = "row_id long, vec array<double>, node long, weight double, part long"
    now = packed.mapInArrow(deal, "tree long, nodes binary, ids binary, block binary").groupBy("tree").applyInArrow(subtree, schema)
    done = first
    while done < depth:
        up = min(SUBTREE, depth - done)
        now = now.groupBy(F.shiftright("node", up).alias("tree"), "part").applyInArrow(upper(up), schema)
        done += up
    got = _gathered(now, d, len(wanted))
    return [(row, x, weight) for row, x, _, weight in got]


def spark_xxhash64(x: np.ndarray, seed: int = 42) -> np.ndarray:
    """xxhash64 of a long column."""
    p1, p2, p3, p4, p5 = (np.uint64(v) for v in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turn = lambda v, r: (v << np.uint64(r)) | (v >> np.uint64(64 - r))
    with np.errstate(over="ignore"):
        h = np.uint64(seed) + p5 + np.uint64(8)
        h = h ^ (turn(x.astype(np.int64).view(np.uint64) * p2, 31) * p1)
        h = turn(h, 27) * p1 + p4
        h ^= h >> np.uint64(33)
        h *= p2
        h ^= h >> np.uint64(29)
        h *= p3
        h ^= h >> np.uint64(32)
    return h
