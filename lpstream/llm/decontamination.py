"""Benchmark decontamination by spaced seeds.

A mask keeps some positions of a window of words and ignores the others, so its
hash survives a substituted word at an ignored position.  The masks are complete:
a best run never falls below its start, so its first r matches stand in one of a
few patterns (1428 for r = 12), and every one of these has a seed of some mask.
Items whose least evidence is less than twelve matches get shorter masks.  Hashes of the benchmark items are
joined to the hashes of every document window, and each meeting is verified: item
and document are laid side by side at that offset, and the best run of matching
words (a substitution costs more than a match earns) is the overlap.

The documents are read once a block of the benchmark.  A block holds at most
`block_chars` characters of items (8 MB unless set otherwise; a single item may be
longer), counted before anything is collected, the proven bound of what is
broadcast: a larger benchmark takes more passes, nothing is cut.  The
join happens inside the scan, so neither texts nor windows are shuffled, and a
passage shared by many documents is just as cheap as a rare one.

Defined cases: null and empty texts overlap nothing; an item with fewer
than six words can't be evidence and is never reported; an item that
repeats in a document is reported once an offset; repeated items and rows are
reported each; empty tables give an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F, types as T

#: Masks by the least number of matches they are complete for. 1 counts, 0 is ignored.
MASKS = {
    12: ("1110101001", "110100110001", "1111000001001", "11101101", "101100111", "1101100101"),
    10: ("11101001", "1100111", "11010000011"),
    6: ("11101", "1101001"),
    4: ("1101",),
}
MIN_ITEM = 6
MIN_WORDS = 12
MIN_SHARE = 0.6
SUBSTITUTION = 2
BLOCK_CHARS = 8_000_000
BITMAP_BITS = 20
SCAN_WORDS = 32_768
_TABLE = bytes(c if chr(c).isalnum() or c >= 128 else 32 for c in range(256))


def words(text: str | None) -> list[bytes]:
    """Lower-case words without ASCII punctuation."""
    return (text or "").lower().encode().translate(_TABLE).split()


def word_hashes(text: str | None) -> np.ndarray:
    return np.array([xxhash.xxh64_intdigest(w) for w in words(text)], np.uint64)


def seeds(h: np.ndarray, mask: str) -> np.ndarray:
    """Hash of every window under one mask."""
    n = len(h) - len(mask) + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        out = np.full(n, np.uint64(hash_of(mask)))
        for k, kept in enumerate(mask):
            if kept == "1":
                out = (out ^ h[k : k + n]) * np.uint64(0x9FB21C651E98DF25)
                out ^= out >> np.uint64(29)
    return out


def hash_of(mask: str) -> int:
    return xxhash.xxh64_intdigest(mask)


def least_matches(n_words: int) -> int:
    """Matches that an overlap with an item of so many words has at least."""
    return min(MIN_WORDS, math.ceil(MIN_SHARE * n_words - 1e-9))


def masks_of(n_words: int) -> tuple:
    """The masks that meet every overlap the verifier accepts of an item of so many words."""
    return MASKS[max(r for r in MASKS if r <= least_matches(n_words))] if n_words >= MIN_ITEM else ()


class Index:
    """Seeds of a block of items, sorted, with a bitmap in front."""

    def __init__(self, items: list[tuple]):
        self.ids = [i for i, _ in items]
        self.hashes = [word_hashes(t) for _, t in items]
        found, item, pos = [], [], []
        for k, h in enumerate(self.hashes):
            for m in masks_of(len(h)):
                s = seeds(h, m)
                found.append(s)
                item.append(np.full(len(s), k, np.int32))
                pos.append(np.arange(len(s), dtype=np.int32))
        self.masks = sorted({m for h in self.hashes for m in masks_of(len(h))})
        seed = np.concatenate(found or [np.zeros(0, np.uint64)])
        order = np.argsort(seed, kind="stable")
        self.seed = seed[order]
        self.item = np.concatenate(item or [np.zeros(0, np.int32)])[order]
        self.pos = np.concatenate(pos or [np.zeros(0, np.int32)])[order]
        self.bits = min(BITMAP_BITS + 6, max(BITMAP_BITS, (16 * len(seed)).bit_length()))
        self.bitmap = np.zeros(1 << self.bits, bool)
        self.bitmap[self.seed >> np.uint64(64 - self.bits)] = True

    def meetings(self, h: np.ndarray, start: np.ndarray, stop: np.ndarray) -> set[tuple[int, int, int]]:
        """(document, item, offset in the document of the item's first word) wherever a seed is shared; h holds the documents one after the other."""
        out: set[tuple[int, int, int]] = set()
        for m in self.masks:
            s = seeds(h, m)
            at = np.flatnonzero(self.bitmap[s >> np.uint64(64 - self.bits)])
            lo = np.searchsorted(self.seed, s[at], "left")
            hi = np.searchsorted(self.seed, s[at], "right")
            doc = np.searchsorted(stop, at, "right")
            met = (hi > lo) & (at + len(m) <= stop[np.minimum(doc, len(stop) - 1)])  # no window over a document's end
            for d, p, a, b in zip(doc[met].tolist(), (at - start[np.minimum(doc, len(stop) - 1)])[met].tolist(), lo[met].tolist(), hi[met].tolist()):
                out.update((d, i, p - q) for i, q in zip(self.item[a:b].tolist(), self.pos[a:b].tolist()))
        return out

    def overlaps(self, h: np.ndarray) -> list[tuple[int, int, int, int, int]]:
        """Verified (item, first document word, words, matching words, words of the item)."""
        return self.overlaps_of([h])[0]

    def overlaps_of(self, docs: list[np.ndarray], first: bool = False) -> list[list[tuple[int, int, int, int, int]]]:
        """The verified overlaps of each document; with `first` one of them is enough."""
        out: list[list] = [[] for _ in docs]
        length = np.array([len(h) for h in docs], np.int64)
        stop = np.cumsum(length)
        if not len(docs) or not stop[-1]:
            return out
        for d, item, offset in sorted(self.meetings(np.concatenate(docs), stop - length, stop)):
            if first and out[d]:
                continue
            h, target = docs[d], self.hashes[item]
            a, b = max(0, offset), min(len(h), offset + len(target))
            equal = h[a:b] == target[a - offset : b - offset]
            begin, last, matches = best_run(equal)
            if matches >= MIN_WORDS or matches >= MIN_SHARE * len(target):
                out[d].append((item, a + begin, last - begin, matches, len(target)))
        return out

    def overlaps_in(self, texts, first: bool = False):
        """The verified overlaps of each text, in their order; many short texts are scanned at once."""
        wait, size = [], 0
        for t in texts:
            wait.append(word_hashes(t))
            size += len(wait[-1])
            if size >= SCAN_WORDS:
                yield from self.overlaps_of(wait, first)
                wait, size = [], 0
        yield from self.overlaps_of(wait, first)


def best_run(equal: np.ndarray) -> tuple[int, int, int]:
    """The run with the highest score, a match counting 1 and a substitution -2: (start, stop, matches)."""
    total = np.r_[0, np.cumsum(np.where(equal, 1, -SUBSTITUTION))]
    low = np.minimum.accumulate(total)
    stop = int(np.argmax(total - low))
    start = int(np.argmin(total[: stop + 1]))
    return start, stop, int(equal[start:stop].sum())


def _blocks(benchmark: DataFrame, item_col: str, text: str, block_chars: int):
    """Indexes of the benchmark, one block at a time; each is collected under the size bound."""
    items = benchmark.select(F.col(item_col).alias("item"), F.col(text).alias("text")).filter(F.col("text").isNotNull())
    size = items.agg(F.sum(F.length("text"))).first()[0] or 0
    n, h = -(-size // block_chars), F.xxhash64("text", F.col("item").cast("string"))
    while n > 1:  # finer until every block is small, or one item (and its copies)
        sizes = items.groupBy(F.pmod(h, F.lit(n)).alias("k")).agg(F.sum(F.length("text")).alias("size"), F.min(h).alias("lo"), F.max(h).alias("hi"))
        if sizes.filter((F.col("size") > block_chars) & (F.col("lo") < F.col("hi"))).isEmpty():
            break
        n *= 2
    for k in range(n):
        part = items if n == 1 else items.filter(F.pmod(h, F.lit(n)) == k)
        yield Index([(r.item, r.text) for r in part.orderBy("item", "text").collect()])


def overlaps(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text: str = "text", item_col: str = "item_id", item_text: str = "text", block_chars: int = BLOCK_CHARS) -> DataFrame:
    """One row for each verified overlap: doc_id, item_id, start_word, n_words, matched_words, item_words."""
    spark = docs.sparkSession
    schema = T.StructType(
        [T.StructField("doc_id", docs.schema[id_col].dataType), T.StructField("item_id", benchmark.schema[item_col].dataType)]
        + [T.StructField(c, T.LongType()) for c in ("start_word", "n_words", "matched_words", "item_words")]
    )
    out = None
    for index in _blocks(benchmark, item_col, item_text, block_chars):
        shared = spark.sparkContext.broadcast(index)

        def run(batches, shared=shared):
            index = shared.value
            for b in batches:
                where, rows = [], []
                for i, found in enumerate(index.overlaps_in(b.column(1).to_pylist())):
                    where += [i] * len(found)
                    rows += found
                if rows:
                    cols = list(zip(*rows))
                    yield pa.RecordBatch.from_pydict({"doc_id": b.column(0).take(pa.array(where)), "item_id": pa.array([index.ids[k] for k in cols[0]]), **{c: pa.array(v, pa.int64()) for c, v in zip(schema.names[2:], cols[1:])}})

        found = docs.select(id_col, text).mapInArrow(run, schema)
        out = found if out is None else out.unionByName(found)
    return out if out is not None else spark.createDataFrame([], schema)


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, text: str = "text", item_col: str = "item_id", item_text: str = "text", block_chars: int = BLOCK_CHARS) -> DataFrame:
    """The rows without a verified overlap, with all their columns; a block of the benchmark after the other."""
    for index in _blocks(benchmark, item_col, item_text, block_chars):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        def run(batches, shared=shared):
            for b in batches:
                clean = [not found for found in shared.value.overlaps_in(b.column(text).to_pylist(), True)]
                yield b.filter(pa.array(clean, pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs
