"""Tokenizer front end, token files and packing against plain versions."""

import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from lpstream.llm import packing, queries, token_files as tf, tokens as tk

BYTE, WORD = tk.vocabulary("byte_bpe_50k.json"), tk.vocabulary("word_bpe_49k.json")
BITS = ["a", "'s", " ", " ", "Foo", "bar", "  ", "\n", "\t", "é", "É", "ß", "!", "!!", "12", "3.4", " \n", " ", "\x1c", "<|endoftext|>", "<|startoftext|>", "<|EndOfText|>", "<|", "|>", "Σας", "ΟΔΟΣ", "é", " ́", "…", "日本", "\r\n", "don't", "'LL", "_", "$", " "]


def plain_tokenizer(path):
    return Tokenizer.from_file(path)


@pytest.mark.parametrize("path,lossy", [(BYTE, False), (WORD, True)])
def test_same_ids_as_the_library(path, lossy, spark, sf):
    rng = random.Random(3)
    texts = ["".join(rng.choice(BITS) for _ in range(rng.randint(0, 25))) for _ in range(6000)]
    texts += [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect()] + [None, "", "x " * 30000]
    e = tk.Encoder(path, lossy, remembered=3000)
    want = [x.ids for x in plain_tokenizer(path).encode_batch([t or "" for t in texts], add_special_tokens=False)]
    flat, size = e.encode_column(pa.array(texts))
    assert np.split(flat, np.cumsum(size)[:-1]) and [p.tolist() for p in np.split(flat, np.cumsum(size)[:-1])] == want
    assert [x.tolist() for x in e.encode_all(texts)] == want


def test_codes_give_random_access():
    rng = np.random.default_rng(0)
    for bits in (4, 8, 12):
        ids = np.r_[rng.integers(0, 70_000, 3000), rng.integers(0, 3, 1000), [0, 1 << 20]]
        im = tf.Image(tf.image(np.array([7]), np.array([0, len(ids)]), ids, bits))
        assert [im[i] for i in range(len(ids))] == ids.tolist()
        for _ in range(200):
            a, b = sorted(rng.integers(0, len(ids) + 1, 2))
            assert im.slice(a, b).tolist() == ids[a:b].tolist()
    with pytest.raises(ValueError):
        tf.Image(b"nope")


def test_token_file_query(spark, sf):
    tok = plain_tokenizer(BYTE)
    docs = sorted((r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect())
    start, want = 0, {}
    for i, t in docs:
        ids = tok.encode(t or "", add_special_tokens=False).ids + [0]
        want[i] = (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in queries.op4_token_files(spark, sf).collect()}
    assert got == want


def test_token_file_edges(spark, tmp_path):
    rows = [(5, "b b", 1), (None, "x", 2), (5, "a", 3), (1, None, 4), (9, "", 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, start int")
    tf.write(docs, f"{tmp_path}/t", BYTE)
    got = [(r.doc_id, r.start, r.n_tokens) for r in sorted(tf.read(spark, f"{tmp_path}/t").collect(), key=lambda r: r.start)]
    assert [g[0] for g in got] == [None, 1, 5, 5, 9]
    assert [g[1] for g in got] == np.cumsum([0] + [g[2] for g in got[:-1]]).tolist()
    every = [i for r in sorted(tf.read(spark, f"{tmp_path}/t").collect(), key=lambda r: r.start) for i in r.ids]
    asked = spark.createDataFrame([(p,) for p in [0, 3, len(every) - 1, 3, len(every) + 5]], "position long")
    assert sorted((r.position, r.token) for r in tf.lookup(spark, f"{tmp_path}/t", asked).collect()) == sorted((p, every[p]) for p in (0, 3, 3, len(every) - 1))
    tf.write(docs.limit(0), f"{tmp_path}/e", BYTE)
    assert tf.digests(spark, f"{tmp_path}/e").count() == 0


def plain_cost(pen, length, word_cut):
    """Least cost by the quadratic recurrence."""
    n = len(pen)
    f = [0] + [10**9] * n
    for j in range(1, n + 1):
        for i in range(max(0, j - length), j):
            w = j - i
            if w >= length // 2:
                f[j] = min(f[j], f[i] + (0 if w == length // 2 else length - w) + int(pen[j - 1]))
    tail = lambda r: 0 if r == 0 else min(length - r, (r.bit_count() - 1) * word_cut)
    return min(f[p] + tail(n - p) for p in range(max(0, n - length), n + 1))


@pytest.mark.parametrize("length", [8, 16, 64])
def test_cuts_are_optimal(length):
    rng = np.random.default_rng(length)
    for _ in range(150):
        n = int(rng.integers(1, 300))
        pen = rng.choice([0, 2, 5], n, p=[0.1, 0.2, 0.7])
        pen[-1] = 0
        ends = packing.cuts(pen, length, 5)
        size = np.diff(np.r_[0, ends])
        assert ends[-1] == n and (size > 0).all() and (size <= length).all()
        pad = sum(0 if int(w).bit_count() == 1 else length - int(w) for w in size)
        best = plain_cost(pen, length, 5)
        # Cuts inside the power-of-two tail are charged a word cut each.
        k = next((i for i in range(len(size)) if size[i] < length // 2), len(size))
        charged = sum(int(pen[e - 1]) for e in ends[:k][ends[:k] < n])
        assert pad + charged <= best <= pad + charged + 5 * (len(size) - k + 1)


def test_packing_query(spark, sf):
    tok = plain_tokenizer(WORD)
    docs = {r.doc_id: np.array(tok.encode(r.text or "", add_special_tokens=False).ids + [1], "<u4") for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = queries.op6_packing(spark, sf).collect()
    by_doc, by_seq = {}, {}
    for r in got:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append(r)
        assert r.ids_crc32 == zlib.crc32(docs[r.doc_id][r.start : r.start + r.length].tobytes()) and r.doc_tokens == len(docs[r.doc_id])
    assert by_doc.keys() == docs.keys()
    for i, rs in by_doc.items():
        rs.sort(key=lambda r: r.start)
        assert [r.start for r in rs] == np.cumsum([0] + [r.length for r in rs[:-1]]).tolist() and sum(r.length for r in rs) == len(docs[i])
    padded = whole = 0
    for rs in by_seq.values():
        rs.sort(key=lambda r: r.offset)
        assert [r.offset for r in rs] == np.cumsum([0] + [r.length for r in rs[:-1]]).tolist()
        n = sum(r.length for r in rs)
        assert n <= 2048
        whole += n
        padded += 0 if n.bit_count() == 1 else 2048 - n
    assert padded <= 0.01 * whole


def test_packing_edges(spark):
    docs = spark.createDataFrame([(1, None, 0), (None, "", 1), (1, "one two. three", 2), (2, "w " * 5000, 3)], "doc_id long, text string, length int")
    got = packing.pack(docs, WORD, with_ids=True).collect()
    assert sum(r.length for r in got) == 1 + 1 + 5 + 5001 and all(len(r.ids) == r.length for r in got)
    assert packing.pack(docs.limit(0), WORD).count() == 0
