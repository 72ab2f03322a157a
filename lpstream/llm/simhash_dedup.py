"""Near-duplicate groups by SimHash with a byte-position inverted index.

A fingerprint is eight positional bytes.  Two fingerprints that differ in at
most three bits differ in at most three bytes, so they share at least five of
the eight (position, byte) postings: the guaranteed minimum of the count
filter.  Of any six positions they therefore share three, hence the index is
probed with the 20 position triples of the first six bytes (24-bit keys: random
fingerprints hardly meet).  Inside a posting list the shared bytes of a pair are
tallied, pairs with fewer than five are dropped, the rest is verified by XOR and
bit count.

The same index finds looser copies with longer fingerprints.  `NEAR` (256 bits of
the set of five-word shingles) links by 48 bits alone, without a guarantee: its
lists of 64 pairs of positions miss a few in a hundred pairs at a similarity of
0.8, and it links pairs below.  `keep_one_similar` is exact in what it links: its
candidates come from the postings of 64 positional bytes (`WIDE`: 512 bits) and are
verified by their similarity.

Scale: copies collapse to one fingerprint before anything is indexed; the index
holds 20 short rows a fingerprint; lists are scanned inside a sorted partition,
so no list becomes a group in memory beyond `heavy` entries.  A longer list is
passed on and split by the two further bytes it must share (five bytes fixed,
24 bits free: at most 2^24 entries, a proven bound).  A list emits a spanning
star of each of its linked groups, never all its pairs, so a group of near
copies costs rows in proportion to its members.

Defined cases: null or blank text has fingerprint zero and links like any
other; null ids are kept, and a component of null ids only has a null id;
repeated rows stay repeated in `groups`, and are one row for `keep_one`, which knows
a row by its content alone, so columns may have any name; an empty table gives an empty result.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

from .common import checkpointed, mix64, pick, ragged, row_key

SEED = 42
HEAVY = 2048


@dataclass(frozen=True)
class Scheme:
    """Shingles, fingerprint length in 64-bit blocks, greatest distance, least shared bytes, and the positions of the lists.

    `lists` are tuples of byte positions that make a key; `more` is how many
    further bytes a long list is split by: one finer list for each choice of them.
    """

    width: int
    distinct: bool
    blocks: int
    max_bits: int
    shared: int
    lists: tuple
    more: int

    def splits(self, t: int) -> list[tuple]:
        return list(itertools.combinations([p for p in range(8 * self.blocks) if p not in self.lists[t]], self.more))


#: 64 bits of three-word shingles, three bits apart: five of eight bytes are shared, three of any six.
CLOSE = Scheme(3, False, 1, 3, 5, tuple(itertools.combinations(range(6), 3)), 2)
#: 256 bits of the set of five-word shingles: a similarity of about 0.8 and more.
NEAR = Scheme(5, True, 4, 48, 2, tuple((i, (i + o) % 32) for o in (1, 2) for i in range(32)), 1)
#: 512 bits of the same sets, one list for each byte position. A pair at a similarity of 0.8 differs in 78 bits on average, and in more than 120 with a probability of 2e-7.
WIDE = Scheme(5, True, 8, 120, 2, tuple((i,) for i in range(64)), 1)


def fingerprint(text: str | None, width: int = 3, seed: int = SEED) -> int:
    """64-bit SimHash of the word shingles of one text; 0 where there is no word."""
    return int(fingerprints(text, CLOSE if width == 3 else replace(CLOSE, width=width), seed)[0])


def shingles(text: str | None, width: int, seed: int = SEED) -> np.ndarray:
    """Hashes of the word shingles in their order; a text of up to `width` words is one shingle."""
    words = (text or "").encode().lower().split()  # bytes: A-Z and ASCII white space only
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64)
    joined = b" ".join(words)
    if n <= width:
        return np.array([xxhash.xxh64_intdigest(joined, seed)], np.uint64)
    length = np.fromiter(map(len, words), np.int64, n)
    start = np.cumsum(length + 1) - length - 1
    stop = start + length
    digest = xxhash.xxh64_intdigest
    return np.array([digest(joined[a:b], seed) for a, b in zip(start[: n - width + 1].tolist(), stop[width - 1 :].tolist())], np.uint64)


def fingerprints(text: str | None, scheme: Scheme, seed: int = SEED) -> np.ndarray:
    """The blocks of a fingerprint; the first is that of the shingles' own hashes, the others mix them again."""
    return _fingerprints(shingles(text, scheme.width, seed), scheme)


def _fingerprints(hashes: np.ndarray, scheme: Scheme) -> np.ndarray:
    if not len(hashes):
        return np.zeros(scheme.blocks, np.uint64)
    if scheme.distinct:
        hashes = np.unique(hashes)
    counts = np.zeros((scheme.blocks, 64), np.int64)
    for i in range(0, len(hashes), 65536):  # bounded memory for very long texts
        block = hashes[i : i + 65536]
        for k in range(scheme.blocks):
            counts[k] += np.unpackbits(block.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
            block = mix64(block)
    return np.packbits((2 * counts > len(hashes)).astype(np.uint8), axis=1, bitorder="little").view(np.uint64).ravel()


def signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def names(scheme: Scheme) -> list[str]:
    return ["fp"] if scheme.blocks == 1 else [f"fp{k}" for k in range(scheme.blocks)]


def with_fingerprint(docs: DataFrame, text: str = "text", scheme: Scheme = CLOSE) -> DataFrame:
    """Every row with its fingerprint as signed longs (`fp`, or `fp0`...); other columns pass through untouched, the text is dropped."""
    keep = [c for c in docs.columns if c != text]
    cols = names(scheme)
    schema = T.StructType([*docs.select(*keep).schema.fields, *[T.StructField(c, T.LongType()) for c in cols]])

    def run(batches):
        for b in batches:
            found = np.array([fingerprints(t, scheme) for t in b.column(text).to_pylist()], np.uint64).reshape(-1, scheme.blocks).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(c) for c in keep] + [pa.array(np.ascontiguousarray(found[:, k])) for k in range(scheme.blocks)], names=[*keep, *cols])

    return docs.mapInArrow(run, schema)


# --- links -----------------------------------------------------------------


def _bytes(fp: np.ndarray) -> np.ndarray:
    """Positional bytes (entries x 8 blocks)."""
    return np.ascontiguousarray(fp).view(np.uint8).reshape(len(fp), -1)


def _linked(x: np.ndarray, scheme: Scheme) -> np.ndarray:
    """Of XORed pairs: which pass the count filter and the verification."""
    out = np.zeros(len(x), bool)
    tally = np.flatnonzero((_bytes(x) == 0).sum(axis=1) >= scheme.shared)
    out[tally] = np.bitwise_count(x[tally]).sum(axis=1, dtype=np.int64) <= scheme.max_bits
    return out


def _stars(fp: np.ndarray, scheme: Scheme) -> tuple[np.ndarray, np.ndarray]:
    """Spanning stars of the linked groups in one posting list: each entry meets only what is not yet reached."""
    left = np.arange(1, len(fp))
    queue, hub, a, b = [0], 0, [], []
    while True:
        while queue and len(left):
            i = queue.pop()
            hit = _linked(fp[left] ^ fp[i], scheme)
            found = left[hit]
            if len(found):
                left = left[~hit]
                queue.extend(found.tolist())
                a.append(np.full(len(found), hub))
                b.append(found)
        if not len(left):
            break
        hub = int(left[0])
        queue, left = [hub], left[1:]
    if not a:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate(a), np.concatenate(b)


def _scan_lists(key: np.ndarray, fp: np.ndarray, node: np.ndarray, heavy: int, last: bool, scheme: Scheme):
    """Links of the whole lists in sorted arrays, and a mask of the entries in lists that are too long."""
    start = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
    size = np.diff(np.r_[start, len(key)])
    over = np.zeros(len(key), bool)
    a, b = [], []
    small = np.repeat(size <= 8, size)
    for shift in range(1, 8):  # short lists: neighbours at each distance, all lists at once
        i = np.flatnonzero((key[:-shift] == key[shift:]) & small[:-shift]) if len(key) > shift else np.zeros(0, np.int64)
        if not len(i):
            break
        i = i[_linked(fp[i] ^ fp[i + shift], scheme)]
        a.append(node[i])
        b.append(node[i + shift])
    for k in np.flatnonzero(size > 8):
        s, n = start[k], size[k]
        if n > heavy and not last:
            over[s : s + n] = True
            continue
        x, y = _stars(fp[s : s + n], scheme)
        a.append(node[s + x])
        b.append(node[s + y])
    none = [np.zeros(0, np.int64)]
    return np.concatenate(a or none), np.concatenate(b or none), over


def list_keys(fp: np.ndarray, scheme: Scheme) -> np.ndarray:
    """Keys (entries x lists): the number of the list's positions, then their bytes."""
    byte = _bytes(fp).astype(np.int64)
    out = np.zeros((len(fp), len(scheme.lists)), np.int64)
    for t, places in enumerate(scheme.lists):
        out[:, t] = t
        for p in places:
            out[:, t] = (out[:, t] << 8) | byte[:, p]
    return out


def split_keys(key: np.ndarray, fp: np.ndarray, scheme: Scheme) -> np.ndarray:
    """Finer keys of a long list: its own key and further positional bytes that linked pairs share."""
    width = 8 * len(scheme.lists[0])
    list_of = key >> width
    byte = _bytes(fp).astype(np.int64)
    out = np.zeros((len(key), len(scheme.splits(0))), np.int64)
    for t in np.unique(list_of):
        i = np.flatnonzero(list_of == t)
        for n, places in enumerate(scheme.splits(int(t))):
            k = (t * out.shape[1] + n) << width | key[i] & ((1 << width) - 1)
            for p in places:
                k = k << 8 | byte[i, p]
            out[i, n] = k
    return out


def _probe(batches, heavy: int, last: bool, scheme: Scheme):
    """Sorted (key, node, blocks) batches to rows (kind, key, a, b, blocks): 0 a link of nodes a and b, 1 an entry (node a) of a long list, passed on under each of its finer keys.

    The list that is open at a batch's end waits for the next batch; when it
    outgrows `heavy` it is passed on at once, so memory stays bounded.
    """
    cols = names(scheme)

    def rows(kind, key, a, b, fp):
        arrays = [pa.array(np.full(len(a), kind, np.int8)), pa.array(key), pa.array(a), pa.array(b)]
        return pa.RecordBatch.from_arrays(arrays + [pa.array(np.ascontiguousarray(fp[:, k]).view(np.int64)) for k in range(scheme.blocks)], names=["kind", "key", "a", "b", *cols])

    def link_rows(a, b):
        zero = np.zeros(len(a), np.int64)
        return rows(0, zero, np.minimum(a, b), np.maximum(a, b), np.zeros((len(a), scheme.blocks), np.uint64))

    def long_rows(key, fp, node):
        for i in range(0, len(key), 4096):
            finer = split_keys(key[i : i + 4096], fp[i : i + 4096], scheme)
            n = finer.shape[1]
            again = np.repeat(node[i : i + 4096], n)
            yield rows(1, finer.ravel(), again, again, np.repeat(fp[i : i + 4096], n, axis=0))

    wait = [np.zeros(0, np.int64), np.zeros((0, scheme.blocks), np.uint64), np.zeros(0, np.int64)]
    passing = None  # key of a long list whose entries are passed on as they come
    for batch in itertools.chain(batches, [None]):
        if batch is None:
            now, done = wait, True
        else:
            key, node, *blocks = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            new = [key, np.stack(blocks, axis=1).view(np.uint64), node]
            now, done = [np.concatenate(p) for p in zip(wait, new)], False
        key, fp, node = now
        if not len(key):
            continue
        if passing is not None:
            n = int(np.searchsorted(key, passing, "right"))
            yield from long_rows(key[:n], fp[:n], node[:n])
            key, fp, node = key[n:], fp[n:], node[n:]
            if len(key):
                passing = None
        cut = len(key) if done or not len(key) else int(np.searchsorted(key, key[-1], "left"))
        if cut:
            a, b, over = _scan_lists(key[:cut], fp[:cut], node[:cut], heavy, last, scheme)
            if len(a):
                yield link_rows(a, b)
            if over.any():
                yield from long_rows(key[:cut][over], fp[:cut][over], node[:cut][over])
        key, fp, node = key[cut:], fp[cut:], node[cut:]
        if len(key) > heavy and not last:
            yield from long_rows(key, fp, node)
            passing, key, fp, node = key[0], key[:0], fp[:0], node[:0]
        wait = [key, fp, node]


def links(prints: DataFrame, heavy: int | None = None, scheme: Scheme = CLOSE) -> DataFrame:
    """Distinct fingerprints (blocks, node) to links (a, b) that span the same groups as all links of the lists."""
    cols, heavy = names(scheme), heavy or HEAVY
    blocks = ", ".join(f"{c} long" for c in cols)

    def index(batches):
        for b in batches:
            for at in range(0, b.num_rows, 4096):
                part = b.slice(at, 4096)
                fp = np.stack([part.column(c).to_numpy(zero_copy_only=False) for c in cols], axis=1).view(np.uint64)
                key = list_keys(fp, scheme)
                n = key.shape[1]
                again = np.repeat(fp, n, axis=0).view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(key.ravel()), pa.array(np.repeat(part.column("node").to_numpy(zero_copy_only=False), n))] + [pa.array(np.ascontiguousarray(again[:, k])) for k in range(len(cols))], names=["key", "node", *cols])

    def probed(entries: DataFrame, last: bool) -> DataFrame:
        dealt = entries.select("key", "node", *cols).repartition("key").sortWithinPartitions("key")
        return dealt.mapInArrow(lambda it: _probe(it, heavy, last, scheme), f"kind byte, key long, a long, b long, {blocks}")

    first = checkpointed(probed(prints.select(*cols, "node").mapInArrow(index, f"key long, node long, {blocks}"), False))
    second = probed(first.filter("kind = 1").withColumnRenamed("a", "node"), True)
    return first.filter("kind = 0").select("a", "b").union(second.filter("kind = 0").select("a", "b")).distinct()


# --- components --------------------------------------------------------------


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Connected components of links (a, b) as (node, root), root the smallest node; nodes without a link are absent.

    Alternating large-star and small-star rounds; every round is checkpointed in
    the shared folder, only its row count and a checksum reach the driver.
    """
    e = checkpointed(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct())
    seen = None
    for _ in range(max_rounds):
        n, s = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if (n, s) == seen or not n:
            break
        seen = (n, s)
        both = e.union(e.select("v", "u"))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(low, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").union(least.select("u", F.col("m").alias("v")))
        e = checkpointed(small.distinct())
    else:
        raise RuntimeError("components did not settle")
    return e.select(F.col("u").alias("node"), F.col("v").alias("root"))


def groups(docs: DataFrame, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """One row a document: id, fingerprint (16 hex digits), component_id (smallest id reachable), links not expanded.

    Nodes of the graph are fingerprints, so that null and repeated ids need no
    care; ids enter only as the minimum of each component.
    """
    named = docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text"))
    rows = checkpointed(with_fingerprint(named))
    return _grouped(rows)


def _grouped(rows: DataFrame) -> DataFrame:
    """(doc_id, fp, ...) with component_id and the component's root fingerprint."""
    prints = rows.groupBy("fp").agg(F.min("doc_id").alias("least_id"))
    roots = components(links(prints.select("fp", F.col("fp").alias("node"))))
    placed = prints.join(roots.withColumnRenamed("node", "fp"), "fp", "left").withColumn("root", F.coalesce("root", "fp"))
    named = placed.join(placed.groupBy("root").agg(F.min("least_id").alias("component_id")), "root").select("fp", "component_id")
    return rows.join(named, "fp").withColumn("fingerprint", F.lower(F.lpad(F.hex("fp"), 16, "0")))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text: str = "text", scheme: Scheme = CLOSE) -> DataFrame:
    """The documents without all but one of each group: the row with the smallest id stays (of tied rows, the least by a hash of their content; of equal rows, one)."""
    cols = names(scheme)
    k0, k1 = row_key(docs)
    rows = with_fingerprint(docs.select(k0.alias("k0"), k1.alias("k1"), F.col(id_col).alias("doc_id"), F.col(text).alias("text")), scheme=scheme)
    best = _numbered(rows.groupBy(*cols).agg(_least("doc_id", "k0", "k1"), _several()))
    roots = components(links(best.select(*cols, "node"), scheme=scheme))
    return _survivors(docs, best, roots)


def _least(*order: str):
    """The smallest of some rows: nulls of the first column last."""
    return F.min(F.struct(F.col(order[0]).isNull().alias("z"), *order)).alias("best")


def _several():
    return (F.count("*") > 1).alias("several")


def _numbered(best: DataFrame) -> DataFrame:
    """The rows with a number each, written down: a number never changes when something is computed again."""
    return checkpointed(best.withColumn("node", F.monotonically_increasing_id()))


def _survivors(docs: DataFrame, best: DataFrame, roots: DataFrame) -> DataFrame:
    """The best row of each component."""
    placed = best.select("best", "several", "node").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    kept = placed.groupBy("root").agg(F.min(F.struct("best", "several")).alias("m")).select("m.best.k0", "m.best.k1", "m.several")
    return pick(docs, kept, docs.columns)


# --- near copies by exact similarity -----------------------------------------------

#: Linked pairs have two equal bytes at most so many positions apart (around the end): a pair at similarity 0.8 has none with a probability of 6e-7.
REACH = 16
#: Bytes after a posting's own that its entries carry, and the bits that may differ in them: a pair at 0.8 differs in 39 on average, in more with a probability of 2e-7.
WINDOW, WINDOW_BITS = 32, 68
TINY, TINY_BITS = 12, 90  # sets up to this size, whose bits vary more, may differ in more bits of the window, and in any of the fingerprint
FEW = 16  # linked groups up to this size leave a posting list as all their pairs
SIMILAR = 0.8


def jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Similarity of two sets of distinct hashes."""
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / max(1, len(a) + len(b) - both)


def _mixed_pairs(batches, heavy: int, last: bool, least: float):
    """Sorted (key, node, root, size, codes, blocks) batches to rows (kind, key, a, b): 0 a pair of one list that may be similar (key: how much its sets differ), of different roots, 1 an entry (node a) of a list longer than `heavy`, passed on as it comes.

    Fingerprints within WIDE.max_bits and fitting sizes go on to the codes, 16 bits of each shingle: the
    shingles of one set whose code the other has are at least those they share,
    so no similar pair is refused, and hardly one that isn't leaves the task.
    """

    def rows(kind, key, a, b):
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(a), kind, np.int8)), pa.array(np.broadcast_to(np.asarray(key, np.int64), len(a))), pa.array(a), pa.array(b)], names=["kind", "key", "a", "b"])

    def compared(*columns):
        order = np.argsort(columns[1], kind="stable")
        node, root, size, codes, fp = (c[order] for c in columns)
        n = len(node)
        flat = np.frombuffer(b"".join(codes), np.uint16)
        start = np.cumsum(size) - size
        has = np.zeros(1 << 16, bool)
        for i in range(0, n, 256):
            mine = slice(i, min(n, i + 256))
            close = [[] for _ in range(mine.stop - i)]
            for j in range(0, n, 4096):
                theirs = slice(j, min(n, j + 4096))
                if root[mine.start] == root[theirs.stop - 1] and root[mine.stop - 1] == root[theirs.start]:
                    continue  # all of one root
                bits = np.bitwise_count(fp[mine, None] ^ fp[None, theirs]).sum(axis=2, dtype=np.int64)
                near = (bits <= WIDE.max_bits) | (np.maximum(size[mine, None], size[None, theirs]) <= TINY)
                near &= root[mine, None] < root[None, theirs]
                near &= least * np.maximum(size[mine, None], size[None, theirs]) <= np.minimum(size[mine, None], size[None, theirs]) + 1e-9
                for p in np.flatnonzero(near.any(axis=1)):
                    close[p].append(j + np.flatnonzero(near[p]))
            for p, found in enumerate(close):
                if not found:
                    continue
                other, own = np.concatenate(found), flat[start[i + p] : start[i + p] + size[i + p]]
                has[own] = True
                shared = np.add.reduceat(has[flat[ragged(start[other], size[other])]], np.cumsum(size[other]) - size[other], dtype=np.int64)
                has[own] = False
                differ = len(own) + size[other] - 2 * np.minimum(shared, len(own))
                similar = np.flatnonzero(shared >= least * (len(own) + size[other] - shared) - 1e-9)
                if len(similar):
                    yield rows(0, differ[similar], np.full(len(similar), node[i + p]), node[other[similar]])

    wait, open_, passing = None, None, None
    for batch in itertools.chain(batches, [None]):
        if batch is not None:
            key, node, root, size, codes, *blocks = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            fp = np.stack(blocks, axis=1).view(np.uint64)
            edges = np.r_[0, np.flatnonzero(key[1:] != key[:-1]) + 1, len(key)] if len(key) else np.zeros(1, np.int64)
            runs = [(int(key[a]), [node[a:b], root[a:b], size[a:b], codes[a:b], fp[a:b]]) for a, b in zip(edges[:-1].tolist(), edges[1:].tolist())]
        else:
            runs = [(None, None)]
        for k, part in runs:
            if k != open_:
                if wait is not None and len(wait[0]) > 1:
                    yield from compared(*wait)
                open_, wait, passing = k, None, None
            if k is None:
                continue
            if passing is not None:
                yield rows(1, k, part[0], part[0])
                continue
            wait = part if wait is None else [np.concatenate(x) for x in zip(wait, part)]
            if len(wait[0]) > heavy and not last:
                yield rows(1, k, wait[0], wait[0])
                wait, passing = None, k


def postings(fp: np.ndarray, node: np.ndarray, tiny: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Entries of the byte index: keys (position and byte), twice the node plus one for a tiny set, and the bytes that follow (entries x WINDOW)."""
    byte = _bytes(fp)
    n, places = byte.shape
    key = (np.arange(places, dtype=np.int64) << 8) | byte
    after = np.lib.stride_tricks.sliding_window_view(np.concatenate([byte, byte[:, :WINDOW]], axis=1)[:, 1:], WINDOW, axis=1)
    return key.ravel(), np.repeat(2 * node + tiny, places), np.ascontiguousarray(after).reshape(n * places, WINDOW)


def _close(x: np.ndarray, tiny: np.ndarray) -> np.ndarray:
    """Of XORed windows (pairs x blocks): which differ in few bits."""
    return np.bitwise_count(x).sum(axis=-1, dtype=np.int64) <= np.where(tiny, TINY_BITS, WINDOW_BITS)


def _reached(window: np.ndarray, tiny: np.ndarray) -> np.ndarray:
    """The first entry that each entry of a list is reached from by close windows; each entry meets only what is not yet reached."""
    label, left = np.arange(len(window)), np.arange(len(window))
    while len(left):
        hub, left = int(left[0]), left[1:]
        queue = [hub]
        while queue and len(left):
            i = queue.pop()
            hit = _close(window[left] ^ window[i], tiny[left] & tiny[i])
            found, left = left[hit], left[~hit]
            label[found] = hub
            queue.extend(found.tolist())
    return label


def _scan_postings(key: np.ndarray, node: np.ndarray, tiny: np.ndarray, window: np.ndarray, few: int):
    """Whole posting lists to candidate pairs (a, b) and groups (group, node) whose pairs are too many.

    An entry meets those that share a further byte at most REACH positions on: with
    the list's own that makes the two bytes of the count filter.  A pair is
    met at the first such byte alone.
    """
    byte, blocks = window.view(np.uint8).reshape(len(key), -1), window
    pairs = [(np.zeros(0, np.int64), np.zeros(0, np.int64))]
    top, large = np.arange(len(key)), np.zeros(len(key), bool)  # the large group of an entry, over all further bytes of its list

    def find(x):
        while (top[x] != x).any():
            x = top[x]
        return x

    for o in range(REACH):
        order = np.lexsort((node, byte[:, o], key))
        sub = key[order] << 8 | byte[order, o]
        start = np.flatnonzero(np.r_[True, sub[1:] != sub[:-1]])
        size = np.diff(np.r_[start, len(sub)])
        small = np.repeat(size <= few, size)
        at = np.flatnonzero((sub[:-1] == sub[1:]) & small[:-1])
        for shift in range(1, few):  # short lists: neighbours at each distance, all lists at once
            at = at[at + shift < len(sub)]
            at = at[sub[at] == sub[at + shift]]
            if not len(at):
                break
            i, j = order[at], order[at + shift]
            hit = _close(blocks[i] ^ blocks[j], tiny[i] & tiny[j])
            i, j = i[hit], j[hit]
            first = ~(byte[i, :o] == byte[j, :o]).any(axis=1)
            pairs.append((i[first], j[first]))
        for k in np.flatnonzero(size > few):
            mine = order[start[k] : start[k] + size[k]]
            _, index, count = np.unique(_reached(blocks[mine], tiny[mine]), return_inverse=True, return_counts=True)
            for members in np.split(np.argsort(index, kind="stable"), np.cumsum(count)[:-1]):
                own = mine[members]
                if len(own) > few:
                    tops = np.unique(find(own))
                    top[tops] = tops[0]
                    large[own] = True
                elif len(own) > 1:
                    i, j = (own[x] for x in np.triu_indices(len(own), 1))
                    hit = _close(blocks[i] ^ blocks[j], tiny[i] & tiny[j])
                    pairs.append((i[hit], j[hit]))
    i, j = (np.concatenate(x) for x in zip(*pairs))
    apart = ~(large[i] & large[j]) | (find(i) != find(j))  # what a large group holds is asked for by the group
    own = np.flatnonzero(large)
    order = own[np.lexsort((node[own], find(own)))]
    group = find(order)
    start = np.flatnonzero(np.r_[True, group[1:] != group[:-1]]) if len(order) else np.zeros(0, np.int64)
    hub = np.repeat(order[start], np.diff(np.r_[start, len(order)]))
    named = mix64(mix64(node[hub]) ^ key[hub].astype(np.uint64)).view(np.int64)
    return [(np.r_[node[i[apart]], node[hub]], np.r_[node[j[apart]], node[order]]), (named, node[order])]


def _probe_postings(batches, few: int, chunk: int = 1 << 16):
    """Sorted (key, node, window blocks) batches to rows (kind, a, b): 0 a candidate pair, 1 a node (b) in a group (a) whose pairs are too many."""
    wait, held = [], 0

    def rows(kind, a, b):
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(a), kind, np.int8)), pa.array(a), pa.array(b)], names=["kind", "a", "b"])

    def scanned(key, mark, window):
        (a, b), (g, m) = _scan_postings(key, mark >> 1, (mark & 1).astype(bool), window, few)
        once = np.unique(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1)[a != b], axis=0)
        yield rows(0, np.ascontiguousarray(once[:, 0]), np.ascontiguousarray(once[:, 1]))
        if len(g):
            yield rows(1, g, m)

    for batch in itertools.chain(batches, [None]):
        if batch is not None:
            key, mark, *blocks = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
            wait.append((key, mark, np.stack(blocks, axis=1).view(np.uint64)))
            held += len(key)
            if held < chunk:
                continue
        if not held:
            continue
        key, mark, window = (np.concatenate(x) for x in zip(*wait))
        cut = len(key) if batch is None else int(np.searchsorted(key, key[-1], "left"))
        if cut:
            yield from scanned(key[:cut], mark[:cut], window[:cut])
        wait, held = [(key[cut:], mark[cut:], window[cut:])], len(key) - cut
        if batch is not None and held >= chunk:
            chunk = 2 * held  # a list longer than a chunk: look again when there is as much more


def keep_one_similar(docs: DataFrame, id_col: str = "doc_id", text: str = "text", least: float = SIMILAR, heavy: int | None = None) -> DataFrame:
    """The documents without all but one of each group linked by a Jaccard similarity of five-word shingle sets of at least `least`: the smallest id stays.

    Equal sets collapse first.  Candidates come from the byte index of fingerprints
    and are verified on their sets of 64-bit shingle hashes.  Small groups of a
    posting list give all their pairs; of a larger one a hub meets the others.
    Groups whose nodes then are still apart are compared by 16-bit codes of
    their shingles: pairs that seem similar leave the task and are verified, so a
    large group is linked before its pairs are asked for.  A group beyond
    `heavy` is split by each further group that its entries share.
    """
    cols, heavy = names(WIDE), heavy or HEAVY
    k0, k1 = row_key(docs)
    kind = docs.schema[id_col].dataType
    schema = T.StructType([T.StructField("k0", T.LongType()), T.StructField("k1", T.LongType()), T.StructField("doc_id", kind), *[T.StructField(c, T.LongType()) for c in ("set0", "set1", "size", *cols)]])

    def run(batches):
        for b in batches:
            sets = [np.unique(shingles(t, WIDE.width)) for t in b.column(3).to_pylist()]
            fp = np.array([_fingerprints(x, WIDE) for x in sets], np.uint64).reshape(-1, WIDE.blocks).view(np.int64)
            whole = np.array([[xxhash.xxh64_intdigest(x.tobytes(), k) for k in (0, 1)] for x in sets], np.uint64).reshape(-1, 2).view(np.int64)
            count = np.array([[len(x)] for x in sets], np.int64).reshape(-1, 1)
            longs = [pa.array(np.ascontiguousarray(m[:, k])) for m in (whole, count, fp) for k in range(m.shape[1])]
            yield pa.RecordBatch.from_arrays([*b.columns[:3], *longs], names=schema.names)

    rows = docs.select(k0.alias("k0"), k1.alias("k1"), F.col(id_col).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, schema)
    best = _numbered(rows.groupBy("set0", "set1").agg(_least("doc_id", "k0", "k1"), _several(), *[F.first(c).alias(c) for c in ("size", *cols)]))
    window = [f"w{k}" for k in range(WINDOW // 8)]
    longs = ", ".join(f"{c} long" for c in ("key", "mark", *window))

    def index(batches):
        for b in batches:
            for at in range(0, b.num_rows, 1024):
                node, size, *blocks = [c.to_numpy(zero_copy_only=False) for c in b.slice(at, 1024).columns]
                key, mark, after = postings(np.stack(blocks, axis=1).view(np.uint64), node, size <= TINY)
                after = after.view(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(mark), *[pa.array(np.ascontiguousarray(after[:, k])) for k in range(len(window))]], names=["key", "mark", *window])

    entries = best.filter("size > 0").select("node", "size", *cols).mapInArrow(index, longs)
    few = min(FEW, heavy)
    met = checkpointed(entries.repartition("key").sortWithinPartitions("key").mapInArrow(lambda it: _probe_postings(it, few), "kind byte, a long, b long").distinct())
    first, grouped = met.filter("kind = 0").select("a", "b"), met.filter("kind = 1").select(F.col("a").alias("key"), F.col("b").alias("node"))
    nodes = first.select(F.explode(F.array("a", "b")).alias("node")).union(grouped.select("node")).distinct()
    wanted = best.select("best.k0", "best.k1", "several", "node").join(nodes, "node", "left_semi")
    texts = checkpointed(pick(docs, wanted, [text]).toDF("text", "node"))
    prints = best.select("node", "size", *cols)

    def verified(pairs: DataFrame, compared: bool) -> DataFrame:
        def side(d: DataFrame, end: str) -> DataFrame:
            return d.select(*[F.col(c).alias(end if c == "node" else f"{end}_{c}") for c in d.columns])

        bits = sum((F.bit_count(F.col(f"a_{c}").bitwiseXOR(F.col(f"b_{c}"))) for c in cols[1:]), F.bit_count(F.col(f"a_{cols[0]}").bitwiseXOR(F.col(f"b_{cols[0]}"))))
        fits = F.lit(least) * F.greatest("a_size", "b_size") <= F.least("a_size", "b_size") + F.lit(1e-9)
        loose = pairs.distinct()
        if not compared:  # by their fingerprints
            loose = loose.join(side(prints, "a"), "a").join(side(prints, "b"), "b").filter(fits & ((bits <= WIDE.max_bits) | (F.greatest("a_size", "b_size") <= TINY))).select("a", "b")

        def check(batches):
            last, x = None, None
            for b in batches:
                hit = []
                for i, t, u in zip(*(b.column(k).to_pylist() for k in (0, 2, 3))):
                    if i != last:
                        last, x = i, np.unique(shingles(t, WIDE.width))
                    hit.append(jaccard(x, np.unique(shingles(u, WIDE.width))) >= least)
                yield b.select(["a", "b"]).filter(pa.array(hit, pa.bool_()))

        return checkpointed(loose.join(side(texts, "a"), "a").join(side(texts, "b"), "b").select("a", "b", "a_text", "b_text").mapInArrow(check, "a long, b long"))

    def coded(batches):
        for b in batches:
            found = [np.unique(shingles(t, WIDE.width)).astype(np.uint16).tobytes() for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, pa.binary())], names=["node", "codes"])

    def mixed(lists: DataFrame, last: bool) -> DataFrame:
        # A node meets its fingerprint and codes once, not once a group.
        whole = lists.groupBy("node", "root").agg(F.collect_set("key").alias("keys")).join(prints, "node").join(codes, "node")
        dealt = whole.select(F.explode("keys").alias("key"), "node", "root", "size", "codes", *cols).repartition("key").sortWithinPartitions("key")
        return dealt.mapInArrow(lambda it: _mixed_pairs(it, heavy, last, least), "kind byte, key long, a long, b long")

    found = verified(first, False)
    rooted = checkpointed(prints.select("node").join(components(found), "node", "left").select("node", F.coalesce("root", "node").alias("root")))
    # A node is in at most 64 groups: one for each of its bytes.
    placed = grouped.groupBy("node").agg(F.collect_set("key").alias("keys")).join(rooted, "node").select("node", "root", F.explode("keys").alias("key"))
    several = placed.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).filter("lo < hi").select("key")
    open_ = checkpointed(placed.join(several, "key").select("key", "node", "root"))
    codes = checkpointed(texts.join(open_.select("node").distinct(), "node", "left_semi").select("node", "text").mapInArrow(coded, "node long, codes binary"))
    close = checkpointed(mixed(open_, False))
    pairs = close.filter("kind = 0").select("a", "b")
    if not close.filter("kind = 1").isEmpty():
        finer = close.filter("kind = 1").select("key", F.col("a").alias("node")).join(open_.select("node", F.col("key").alias("other")), "node").filter("other <> key").select(F.xxhash64("key", "other").alias("key"), "node")
        pairs = pairs.union(mixed(finer.join(rooted, "node"), True).select("a", "b"))
    more = verified(pairs, True)
    # Links of groups: what the first round joined stays joined, so only its roots meet the new links.
    roots = components(more.join(rooted.select(F.col("node").alias("a"), F.col("root").alias("ra")), "a").join(rooted.select(F.col("node").alias("b"), F.col("root").alias("rb")), "b").select(F.col("ra").alias("a"), F.col("rb").alias("b")))
    final = rooted.join(roots.select(F.col("node").alias("root"), F.col("root").alias("top")), "root", "left").select("node", F.coalesce("top", "root").alias("root"))
    return _survivors(docs, best, final)
