"""Document quality from a linear-chain conditional random field over lines.

Every line with a word is labelled good or bad.  A line's features are binned
surface measures (case, symbols, repetition, lengths) of itself and of its two
neighbours; the chain's transitions tie neighbouring labels.  Forward-backward
gives each line's probability of being good, and the document's score is their
mean weighted by line length.

Training takes the document's label for its lines, on a bounded sample of
labelled documents, each read whole: at most `sample_docs` (expected number, twice
that is a hard bound), in the order of a hash of the id, as long as they have
`sample_lines` lines together.  Everything is computed from the text alone: labels,
language, source and id never enter a score.  Scoring is one narrow pass, no
shuffle.

Defined cases: a text without words (null, empty, blank) scores the share of
good documents in the training sample; without any labelled document the model is
neutral (0.5 for every text); null ids pass through, never held out; of rows that
repeat a labelled id the least text is learned from, of repeated labels the larger;
a text of any length is read whole, memory is by line features.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import checkpointed

SAMPLE_DOCS = 6000
SAMPLE_LINES = 4_000_000  # of all training documents together
THRESHOLD = 0.3
UPPER = bytes(range(65, 91))
DIGIT = b"0123456789"
SYMBOL = b"#*$%&<>{}[]\\^~@=_+"
RATIOS = np.array([0.005, 0.02, 0.05, 0.1, 0.2, 0.35, 0.6, 0.9])
LENGTHS = np.array([2, 4, 8, 16, 32, 64, 128, 256, 512])
WORD = np.array([2.0, 3.0, 4.0, 5.0, 6.0, 8.0, 11.0, 16.0])
N_BINS = 10
OWN = 10  # binned measures of a line
N_FEATURES = OWN * N_BINS * 3 + 1
EDGE = N_BINS - 1  # bin of a neighbour that does not exist


def line_bins(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Bins (lines x OWN) and character lengths of the lines that have a word."""
    rows, sizes = [], []
    seen: set[bytes] = set()
    for line in (text or "").encode().split(b"\n"):
        words = line.split()
        if not words:
            continue
        n, k = len(line), len(words)
        cut = line.translate
        distinct = len(set(words))
        rows.append(
            (
                (n - len(cut(None, UPPER))) / n,
                (n - len(cut(None, SYMBOL))) / n,
                line.count(b"!") / n,
                line.count(b"|") / n,
                (n - len(cut(None, DIGIT))) / n,
                1 - distinct / k,
                k,
                n / k,
                (line in seen) * 1.0,
                (line[-1:] in b".!?") * 1.0,
            )
        )
        seen.add(line)
        sizes.append(n)
    if not rows:
        return np.zeros((0, OWN), np.int64), np.zeros(0)
    v = np.array(rows, float)
    bins = np.zeros((len(v), OWN), np.int64)
    for c in (0, 1, 2, 3, 4, 5):
        bins[:, c] = np.searchsorted(RATIOS, v[:, c], "right")
    # Long lines repeat words by nature: the repetition bin is read beside the length bin's half.
    bins[:, 6] = np.minimum(np.searchsorted(LENGTHS, v[:, 6], "right"), N_BINS - 2)
    bins[:, 7] = np.searchsorted(WORD, v[:, 7], "right")
    bins[:, 8], bins[:, 9] = v[:, 8], v[:, 9]
    return np.minimum(bins, N_BINS - 2), np.array(sizes, float)


def features(bins: np.ndarray) -> np.ndarray:
    """Feature numbers of each line: its own bins, its neighbours' bins, a constant."""
    n = len(bins)
    before = np.full_like(bins, EDGE)
    after = np.full_like(bins, EDGE)
    before[1:], after[:-1] = bins[:-1], bins[1:]
    place = np.arange(OWN) * N_BINS
    block = OWN * N_BINS
    return np.concatenate([bins + place, before + place + block, after + place + 2 * block, np.full((n, 1), N_FEATURES - 1)], axis=1).astype(np.int16)


@dataclass(frozen=True)
class Model:
    weights: np.ndarray  # log odds of good, by feature
    pair: np.ndarray  # 2 x 2 transition scores
    start: np.ndarray
    prior: float


def marginals(unary: np.ndarray, first: np.ndarray, count: np.ndarray, pair: np.ndarray, start: np.ndarray, pairs: bool = False):
    """P(good) of every line by forward-backward, all documents abreast; with `pairs` also expected transitions and log Z."""
    order = np.argsort(-count, kind="stable")
    first, count = first[order], count[order]
    top = int(count[0]) if len(count) else 0
    active = np.searchsorted(-count, -np.arange(1, top + 1), "right")
    e = np.exp(np.clip(np.stack([np.zeros_like(unary), unary], 1), -30, 30))
    step = np.exp(pair)
    alpha = np.zeros((len(unary), 2))
    scale = np.ones(len(unary))
    for t in range(top):
        i = first[: active[t]] + t
        a = (np.exp(start) if t == 0 else alpha[i - 1] @ step) * e[i]
        s = a.sum(1)
        alpha[i], scale[i] = a / s[:, None], s
    beta = np.ones((len(unary), 2))
    expected = np.zeros((2, 2))
    for t in range(top - 2, -1, -1):
        i = first[: active[t + 1]] + t
        nxt = e[i + 1] * beta[i + 1] / scale[i + 1][:, None]
        beta[i] = nxt @ step.T
        if pairs:
            expected += (alpha[i].T @ nxt) * step
    p = alpha * beta
    good = p[:, 1] / p.sum(1)
    return (good, expected, float(np.log(scale).sum())) if pairs else good


def train(docs: list[tuple[int, np.ndarray]], rounds: int = 240, rate: float = 0.15, ridge: float = 5e-5) -> Model:
    """Penalised conditional likelihood by adaptive gradient steps; docs are (label, bins)."""
    labels = np.array([y for y, b in docs], float)
    if not len(docs):
        return Model(np.zeros(N_FEATURES), np.zeros((2, 2)), np.zeros(2), 0.5)
    prior = float((labels.sum() + 1) / (len(labels) + 2))
    used = [(y, b) for y, b in docs if len(b)]
    if not used:
        return Model(np.zeros(N_FEATURES), np.zeros((2, 2)), np.zeros(2), prior)
    x = np.concatenate([features(b) for _, b in used])
    count = np.array([len(b) for _, b in used])
    first = np.cumsum(count) - count
    y = np.repeat(np.array([v for v, _ in used], float), count)
    begins = y[first]
    # A document's lines share one label: transitions stay within it.
    stay = np.array([[((count - 1) * (begins == 0)).sum(), 0], [0, ((count - 1) * (begins == 1)).sum()]])
    # Each document weighs as a document and not by its number of lines.
    w, pair, start = np.zeros(N_FEATURES), np.zeros((2, 2)), np.zeros(2)
    state = [[np.zeros_like(v), np.zeros_like(v)] for v in (w, pair, start)]
    n = len(used)
    for r in range(1, rounds + 1):
        unary = w[x].sum(1)
        good, expected, _ = marginals(unary, first, count, pair, start, pairs=True)
        g_w = np.bincount(x.ravel(), np.repeat(y - good, x.shape[1]), minlength=N_FEATURES) / len(x) - ridge * w
        g_p = (stay - expected) / max(1, len(x) - n) - ridge * pair
        opened = good[first]
        g_s = np.array([((1 - begins) - (1 - opened)).sum(), (begins - opened).sum()]) / n - ridge * start
        for v, g, (m1, m2) in zip((w, pair, start), (g_w, g_p, g_s), state):
            m1 += 0.1 * (g - m1)
            m2 += 0.01 * (g * g - m2)
            v += rate * (m1 / (1 - 0.9**r)) / (np.sqrt(m2 / (1 - 0.99**r)) + 1e-8)
    return Model(w, pair, start, prior)


def score(model: Model, texts: list[str | None]) -> np.ndarray:
    """Score of each text, 0 to 1."""
    parts = [line_bins(t) for t in texts]
    count = np.array([len(s) for _, s in parts], np.int64)
    out = np.full(len(texts), model.prior)
    has = np.flatnonzero(count)
    if len(has):
        x = np.concatenate([features(parts[i][0]) for i in has])
        size = np.concatenate([parts[i][1] for i in has])
        c = count[has]
        first = np.cumsum(c) - c
        good = marginals(model.weights[x].sum(1), first, c, model.pair, model.start)
        out[has] = np.add.reduceat(good * size, first) / np.add.reduceat(size, first)
    return np.clip(out, 0.0, 1.0)


def held_out(id_col: str = "doc_id"):
    """Rows never learned from: crc32 of the id as text, by 5."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, sample_docs: int = SAMPLE_DOCS, sample_lines: int = SAMPLE_LINES, id_col: str = "doc_id", text: str = "text") -> Model:
    """Fit on a bounded sample of the labelled documents outside the held-out fold: `sample_docs` expected, twice that and `sample_lines` lines at most."""
    usable = labels.select(F.col("doc_id").alias("__id"), F.col("quality").alias("__y")).filter(F.col("__id").isNotNull() & F.col("__y").isNotNull() & ~held_out("__id")).groupBy("__id").agg(F.max("__y").alias("__y"))
    share = min(1.0, sample_docs / max(1, usable.count()))
    order = F.xxhash64("__id", F.lit("quality sample"))
    place = F.shiftrightunsigned(order, 11).cast("double") / float(1 << 53)
    chosen = usable.withColumn("__h", order).filter(place < share).limit(2 * sample_docs)

    def run(batches):
        for b in batches:
            found = [line_bins(t)[0].astype(np.uint8) for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1).cast(pa.int64()), pa.array([len(m) for m in found], pa.int64()), pa.array([m.tobytes() for m in found], pa.binary())], names=["h", "y", "n", "bins"])

    # One text for each id, whatever repeats, so that the rows below are as many as the sample.
    joined = docs.select(F.col(id_col).alias("__id"), F.col(text).alias("text")).join(F.broadcast(chosen), "__id").groupBy("__h", "__y").agg(F.min("text").alias("text"))
    found = checkpointed(joined.select("__h", "__y", "text").mapInArrow(run, "h long, y long, n long, bins binary"))
    sizes = sorted((r.h, r.n) for r in found.select("h", "n").collect())
    whole = np.cumsum([n for _, n in sizes])
    used = int(np.searchsorted(whole, sample_lines, "right")) if len(sizes) else 0
    rows = sorted((int(r.y), bytes(r.bins)) for r in found.filter(F.col("h") <= sizes[used - 1][0]).select("y", "bins").collect()) if used else []
    return train([(y, np.frombuffer(m, np.uint8).reshape(-1, OWN).astype(np.int64)) for y, m in rows])


def classify(docs: DataFrame, model: Model, id_col: str = "doc_id", text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    schema = T.StructType([T.StructField("doc_id", docs.schema[id_col].dataType), T.StructField("held_out", T.BooleanType()), T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])

    def run(batches):
        for b in batches:
            s = np.concatenate([score(model, b.column(2).slice(at, 512).to_pylist()) for at in range(0, b.num_rows, 512)] or [np.zeros(0)])
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(s), pa.array((s >= threshold).astype(np.int32))], names=schema.names)

    return docs.select(F.col(id_col).alias("doc_id"), held_out(id_col).alias("held_out"), F.col(text).alias("text")).mapInArrow(run, schema)


def keep(docs: DataFrame, model: Model, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows whose document scores at least the threshold, with all their columns."""

    def run(batches):
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                yield part.filter(pa.array(score(model, part.column(text).to_pylist()) >= threshold))

    return docs.mapInArrow(run, docs.schema)
