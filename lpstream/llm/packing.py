"""Packing of token streams into sequences by order-preserving dynamic programming.

Documents keep their order.  The cost of a set of cuts is its padding plus a
penalty for each cut inside a document: small at a sentence end, larger between
other tokens, none at a document's end.  With f(j) the least cost of the first j
tokens, windows of more than half the sequence length give

    f(j) = penalty(j) + L - j + min { f(i) + i : j - L <= i < j - L/2 }

and a window of exactly L/2 tokens (a power of two, hence unpadded) gives
f(j - L/2) + penalty(j).  The minimum over the sliding range is what a monotone
queue keeps; here the queue is laid out in blocks of L/2 positions, whose suffix
minima (older block) and prefix minima (newer block) are its fronts, so every
token position is a possible cut at the price of a few array operations a block.
The tail takes either padding or unpadded power-of-two sequences.

Scale: a stream is one input partition in its own order, packed in spans of
about `span` tokens that end with a document; no shuffle, memory by span (or by
the longest document).

Defined cases: null text is an empty document, so its end id is one piece;
null and repeated ids are separate documents; an empty table gives no rows.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, functions as F

from .tokens import encoder, slices, with_end

SENTENCE_CUT = 4
WORD_CUT = 16
SPAN = 1 << 20
REMEMBERED = 500_000  # words, in a worker
SLICE = 4 << 20  # bytes of text encoded at once
FAR = np.int64(1 << 40)


def cuts(penalty: np.ndarray, length: int = 2048, word_cut: int = WORD_CUT) -> np.ndarray:
    """Ends of the sequences of a stream; penalty[j-1] is the price of a cut after token j (0 at the stream's end)."""
    n, half = len(penalty), length // 2
    blocks = n // half + 1
    back = np.zeros(blocks * half, np.int16)
    f = np.full((blocks + 1) * half, FAR, np.int64)  # f[half + j]: cost of the first j tokens; the block before 0 is out of reach
    f[half] = 0
    price = np.zeros(blocks * half, np.int64)
    price[1 : n + 1] = penalty[: blocks * half - 1]
    t = np.arange(half, dtype=np.int64)
    for b in range(1, blocks):
        lo = b * half
        # key = (f(i) + i) * 2^12 + window length, so that a minimum carries its window along
        old = ((f[lo - half : lo] + (lo - 2 * half) + t) << 12) | (2 * half)
        new = ((f[lo : lo + half] + (lo - half) + t) << 12) | half
        oldest = np.minimum.accumulate((old - t)[::-1])[::-1]  # i = t' >= t in the older block: window 2*half + t - t'
        newest = np.r_[FAR << 12, np.minimum.accumulate(new - t)[:-1]]  # t' < t in the newer block: window half + t - t'
        best = np.minimum(oldest, newest) + t
        window = best & 4095
        cost = (best >> 12) + length - (lo + t)
        equal = f[lo : lo + half]
        shorter = equal < cost
        cost = np.where(shorter, equal, cost) + price[lo : lo + half]
        f[lo + half : lo + 2 * half] = np.minimum(cost, FAR)
        back[lo : lo + half] = np.where(shorter, half, window)
    # The tail: padded once, or in unpadded sequences by the powers of two in its length.
    starts = np.arange(max(0, n - length), n + 1)
    rest = n - starts
    split = np.maximum(np.bitwise_count(rest).astype(np.int64) - 1, 0) * word_cut
    padded = np.where(rest == 0, 0, length - rest)
    total = f[half + starts] + np.minimum(split, padded)
    k = int(np.argmin(total))
    at, rest = int(starts[k]), int(rest[k])
    out = []
    if rest:
        if split[k] < padded[k]:
            p = n
            for bit in range(rest.bit_length()):
                if rest >> bit & 1:
                    out.append(p)
                    p -= 1 << bit
        else:
            out.append(n)
    while at > 0:
        out.append(at)
        at -= int(back[at])
    return np.array(out[::-1], np.int64)


def pieces(lengths: np.ndarray, ends: np.ndarray):
    """Documents of these lengths, cut at the ends: (document, start, length, sequence, offset) of each piece."""
    stop = np.cumsum(lengths)
    marks = np.union1d(stop, ends)
    begin = np.r_[0, marks[:-1]]
    doc = np.searchsorted(stop, begin, "right")
    seq = np.searchsorted(ends, begin, "right")
    first = np.r_[0, ends[:-1]]
    return doc, begin - (stop - lengths)[doc], marks - begin, seq, begin - first[seq]


@lru_cache(maxsize=4)
def sentence_ends(vocabulary: str) -> np.ndarray:
    """Which ids end a sentence: tokens of closing punctuation only."""
    tok = encoder(vocabulary, True, REMEMBERED).tok
    n = tok.get_vocab_size()
    out = np.zeros(n, bool)
    for word, i in tok.get_vocab().items():
        core = word.removesuffix("</w>")
        out[i] = bool(core) and word.endswith("</w>") and set(core) <= set(".!?")
    return out


SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, sequence_tokens long"
KINDS = [pa.int64()] * 8


def pack(docs: DataFrame, vocabulary: str, id_col: str = "doc_id", text: str = "text", length: int = 2048, end_id: int = 1, span: int = SPAN, sentence_cut: int = SENTENCE_CUT, word_cut: int = WORD_CUT, with_ids: bool = False) -> DataFrame:
    """One row a piece; `with_ids` adds the ids themselves.  sequence_id is unique over the partitions, offsets in it are gapless."""
    schema = SCHEMA + (", ids array<int>" if with_ids else "")
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches):
        enc = encoder(vocabulary, True, REMEMBERED)
        closing = sentence_ends(vocabulary)
        base = TaskContext.get().partitionId() << 40
        seen, ids, sizes, kept, total = 0, [], [], [], 0

        def flush():
            nonlocal seen, ids, sizes, kept, total
            lengths = np.concatenate(sizes)
            stream = np.concatenate(kept).astype("<u4")
            price = np.where(closing[np.minimum(stream, len(closing) - 1)], sentence_cut, word_cut)
            price[np.cumsum(lengths) - 1] = 0
            ends = cuts(price, length, word_cut)
            doc, start, size_of, seq, offset = pieces(lengths, ends)
            begin = np.cumsum(size_of) - size_of
            raw = stream.tobytes()
            view = memoryview(raw)
            crc = [zlib.crc32(view[4 * a : 4 * (a + k)]) for a, k in zip(begin.tolist(), size_of.tolist())]
            whole = np.diff(np.r_[0, ends])
            columns = [[ids[d] for d in doc.tolist()], start, size_of, crc, lengths[doc], base + seen + seq, offset, whole[seq]]
            arrays = [pa.array(c, k) for c, k in zip(columns, KINDS)]
            if with_ids:
                arrays.append(pa.array([stream[a : a + k].astype(np.int32) for a, k in zip(begin.tolist(), size_of.tolist())], pa.list_(pa.int32())))
            seen += len(ends)
            ids, sizes, kept, total = [], [], [], 0
            return pa.RecordBatch.from_arrays(arrays, names=names)

        for b in batches:
            for piece in slices(b, 1, SLICE):
                flat, size = with_end(*enc.encode_column(piece.column(1)), end_id)
                ids += piece.column(0).to_pylist()
                sizes.append(size)
                kept.append(flat)
                total += len(flat)
                if total >= span:
                    yield flush()
        if ids:
            yield flush()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, schema)
