"""Quality rules by repetition coverage.

Words are numbered per document, n-grams of several lengths get rolling
polynomial hashes in numpy (differences of one running sum serve every length),
and the measure is the share of characters (code points) that lie inside an n-gram
seen more than once, or inside a repeated line.  Overlapping n-grams cover a
character once.

Defined cases: null or empty text has no words and fails the base rule; lines
without a word never count as repeated; a text of any length is read whole;
repeated rows are judged alike; other columns pass through untouched.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, types as T

from .common import mix64

SYMBOLS = b"#*$%&|<>"
SPACES = b"\x20\x09\x0a\x0b\x0c\x0d"
BASE = 0x9E3779B97F4A7C15
_powers = {"up": np.ones(1, np.uint64), "down": np.ones(1, np.uint64)}


@dataclass(frozen=True)
class Limits:
    """Largest shares that a kept document may have."""

    min_words: int = 50
    repeat_words_percent: int = 50
    line_chars: float = 0.30
    #: n-gram length -> share of word characters inside n-grams found again
    ngram_chars: dict[int, float] = field(default_factory=lambda: {n: 0.40 for n in (5, 6, 7, 8, 9, 10)})
    symbols_per_word: float = 0.25


@dataclass(frozen=True)
class Measures:
    n_words: int
    word_chars: int
    n_symbols: int
    n_dup_lines: int
    n_repeat_words: int
    dup_line_chars: float
    dup_ngram_chars: dict[int, float]



def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """BASE^k and BASE^-k (mod 2^64) for k below n; kept, and doubled when outgrown."""
    if len(_powers["up"]) < n:
        size = 1 << n.bit_length()
        for name, base in (("up", BASE), ("down", pow(BASE, -1, 1 << 64))):
            steps = np.full(size, base, np.uint64)
            steps[0] = 1
            _powers[name] = np.cumprod(steps, dtype=np.uint64)
    return _powers["up"][:n], _powers["down"][:n]


def running(values: np.ndarray) -> np.ndarray:
    """Sums of values times BASE^k (mod 2^64) before each place."""
    return np.r_[np.zeros(1, np.uint64), np.cumsum(values * powers(len(values))[0], dtype=np.uint64)]


def rolling(sums: np.ndarray, n: int) -> np.ndarray:
    """Polynomial hash (mod 2^64) of every window of n values, from their running sums."""
    count = max(0, len(sums) - n)
    return (sums[n : n + count] - sums[:count]) * powers(count)[1]


def found_again(codes: np.ndarray) -> np.ndarray:
    """Mask of the entries whose value occurs at least twice."""
    order = np.argsort(codes, kind="stable")
    s = codes[order]
    same = s[1:] == s[:-1]
    mask = np.zeros(len(codes), bool)
    mask[order[1:][same]] = True
    mask[order[:-1][same]] = True
    return mask


def spread(hits: np.ndarray, n: int, total: int) -> np.ndarray:
    """Words covered by the windows of n words that start at the hits."""
    edge = np.zeros(total + 1, np.int64)
    np.add.at(edge, np.flatnonzero(hits), 1)
    np.add.at(edge, np.flatnonzero(hits) + n, -1)
    return np.cumsum(edge[:total]) > 0


def measure(text: str | None, lengths=(5, 6, 7, 8, 9, 10)) -> Measures:
    data = (text or "").encode()
    words = data.split()
    n = len(words)
    symbols = len(data) - len(data.translate(None, SYMBOLS))
    word_chars = len(text or "") - (len(data) - len(data.translate(None, SPACES)))
    chars = len if len(data) == len(text or "") else lambda b: len(b.decode())  # code points of a piece
    seen: set[bytes] = set()
    dup_lines = dup_line_chars = line_chars = 0
    for line in data.split(b"\n"):
        if size := chars(line.strip()):
            line_chars += size
            if line in seen:
                dup_lines += 1
                dup_line_chars += size
            else:
                seen.add(line)
    number: dict[bytes, int] = {}
    ids = np.fromiter((number.setdefault(w, len(number)) for w in words), np.uint64, n)
    # Three-word windows are compared exactly: word numbers packed without loss where they fit.
    v = len(number) + 1
    windows = n - 2
    repeat_words = 0
    shares = dict.fromkeys(lengths, 0.0)
    if windows > 1:
        if v < 1 << 21:
            code = (ids[:-2] << np.uint64(42)) | (ids[1:-1] << np.uint64(21)) | ids[2:]
        else:
            _, pair = np.unique(ids[:-1] * np.uint64(v) + ids[1:], return_inverse=True)
            code = pair[:-1].astype(np.uint64) * np.uint64(v) + ids[2:]
        again = found_again(code)
        repeat_words = int(spread(again, 3, n).sum())
        if again.any():
            size = np.fromiter(map(chars, words), np.int64, n)
            sums = running(mix64(ids))
            whole = int(size.sum())
            for k in lengths:
                h = rolling(sums, k)
                hit = found_again(h) if len(h) > 1 else np.zeros(0, bool)
                if not hit.any():
                    break  # a longer n-gram that occurs twice holds a shorter one that does
                shares[k] = float(size[spread(hit, k, n)].sum() / whole)
    return Measures(n, word_chars, symbols, dup_lines, repeat_words, dup_line_chars / line_chars if line_chars else 0.0, shares)


def verdict(m: Measures, limits: Limits) -> tuple[bool, bool]:
    """(base_failed, kept)"""
    failed = m.n_words < limits.min_words or 100 * m.n_repeat_words > limits.repeat_words_percent * m.n_words
    kept = (
        not failed
        and m.dup_line_chars <= limits.line_chars
        and m.n_symbols <= limits.symbols_per_word * m.n_words
        and all(m.dup_ngram_chars[k] <= most for k, most in limits.ngram_chars.items())
    )
    return failed, kept


COLUMNS = [
    ("n_words", T.LongType(), pa.int64()),
    ("word_chars", T.LongType(), pa.int64()),
    ("n_symbols", T.LongType(), pa.int64()),
    ("n_dup_lines", T.LongType(), pa.int64()),
    ("n_repeat_words", T.LongType(), pa.int64()),
    ("dup_line_chars", T.DoubleType(), pa.float64()),
    ("dup_ngram_chars", T.DoubleType(), pa.float64()),
    ("base_failed", T.BooleanType(), pa.bool_()),
    ("kept", T.BooleanType(), pa.bool_()),
]


def judge(docs: DataFrame, id_col: str = "doc_id", text: str = "text", limits: Limits = Limits()) -> DataFrame:
    """Measures and verdict of every document; one row in, one row out, no shuffle."""
    schema = T.StructType([T.StructField("doc_id", docs.schema[id_col].dataType)] + [T.StructField(n, t) for n, t, _ in COLUMNS])
    lengths = tuple(sorted(limits.ngram_chars))

    def run(batches):
        for b in batches:
            rows = []
            for t in b.column(1).to_pylist():
                m = measure(t, lengths)
                rows.append((m.n_words, m.word_chars, m.n_symbols, m.n_dup_lines, m.n_repeat_words, m.dup_line_chars, max(m.dup_ngram_chars.values(), default=0.0), *verdict(m, limits)))
            cols = list(zip(*rows)) if rows else [[] for _ in COLUMNS]
            yield pa.RecordBatch.from_arrays([b.column(0)] + [pa.array(c, k) for c, (_, _, k) in zip(cols, COLUMNS)], names=schema.names)

    return docs.select(id_col, text).mapInArrow(run, schema)


def keep(docs: DataFrame, text: str = "text", limits: Limits = Limits()) -> DataFrame:
    """The rows whose document is kept, with all their columns."""
    lengths = tuple(sorted(limits.ngram_chars))

    def run(batches):
        for b in batches:
            mask = [verdict(measure(t, lengths), limits)[1] for t in b.column(text).to_pylist()]
            yield b.filter(pa.array(mask, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
