"""SimHash groups against brute force."""

import re
from itertools import product

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from lpstream.llm import queries, simhash_dedup as s


def plain_fingerprint(text, width=3):
    text = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    if not w:
        return 0
    shingles = [" ".join(w[i : i + width]) for i in range(max(1, len(w) - width + 1))]
    h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def plain_components(fps):
    """Component root (smallest index) of each fingerprint, by comparing all."""
    n = len(fps)
    root = list(range(n))

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    f = np.array(fps, np.uint64)
    for i in range(n):
        for j in np.flatnonzero(np.bitwise_count(f[i + 1 :] ^ f[i]) <= 3) + i + 1:
            a, b = find(i), find(int(j))
            if a != b:
                root[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


@pytest.mark.parametrize("text", [None, "", " \n\t", "One", "one Two", "ONE two three", "Ünï É b", "a b c d a b c d e f g", "x\x1cy z\x0bq   w"])
def test_fingerprint(text):
    assert s.fingerprint(text) == plain_fingerprint(text)


def clustered(rng, n, flips=12):
    """Fingerprints around a few centres: dense posting lists and chains."""
    centres = rng.integers(0, 1 << 63, 3, dtype=np.uint64)
    out = []
    for i in range(n):
        x = int(centres[i % 3]) if i % 2 else int(rng.integers(0, 1 << 63, dtype=np.uint64))
        for b in rng.choice(24, rng.integers(0, 6), replace=False):
            x ^= 1 << int(b * 2 + 3)
        out.append(x)
    return sorted(set(out))


@pytest.mark.parametrize("heavy", [10, 40, 2048])
def test_links_span_all_groups(spark, heavy):
    rng = np.random.default_rng(heavy)
    fps = clustered(rng, 700)
    want = plain_components(fps)
    nodes = spark.createDataFrame([(s.signed(f), i) for i, f in enumerate(fps)], "fp long, node long")
    got = dict(s.components(s.links(nodes, heavy)).collect())
    assert [got.get(i, i) for i in range(len(fps))] == want
    assert len(set(want)) < len(fps)


def test_query_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()
    docs.sort()
    fps = [plain_fingerprint(d.text) for d in docs]
    root = plain_components(fps)
    want = {d.doc_id: (f"{f:016x}", docs[r].doc_id) for d, f, r in zip(docs, fps, root)}
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op10_simhash_dedup(spark, sf).collect()}
    assert got == want


def test_edge_cases(spark):
    rows = [(1, None, "x"), (2, "", "y"), (None, "a b c d", "z"), (4, "a b c d", None), (4, "a b c d", None), (7, "q " * 50_000, "k")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, fp string")
    got = sorted(((r.doc_id, r.component_id) for r in s.groups(docs).collect()), key=str)
    assert got == sorted([(1, 1), (2, 1), (None, 4), (4, 4), (4, 4), (7, 7)], key=str)
    kept = s.keep_one(docs.withColumns({"__row": F.lit(1), "node": F.lit("n"), "k0": F.lit(0), "several": F.lit(True), "body": F.create_map(F.lit(1), F.lit(2))}))
    assert kept.columns == [*docs.columns, "__row", "node", "k0", "several", "body"]
    assert sorted(r.doc_id for r in kept.collect()) == [1, 4, 7]
    assert s.groups(docs.limit(0)).count() == 0 and s.keep_one(docs.limit(0)).count() == 0


def test_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(400)], "a long, b long")
    got = dict(s.components(edges).collect())
    assert got == {i: 0 for i in range(1, 401)}


def jaccard(a, b):
    a, b = (({tuple(w[i : i + 5]) for i in range(len(w) - 4)}) for w in (a, b))
    return len(a & b) / len(a | b)


@pytest.mark.parametrize("heavy", [30, 2048])
def test_near_copies_of_five_word_shingles(spark, heavy, monkeypatch):
    """Copies at similarity 0.8 and more meet, unrelated texts stay apart."""
    monkeypatch.setattr(s, "HEAVY", heavy)
    rng = np.random.default_rng(heavy)
    vocab = [f"w{i}" for i in range(3000)]
    rows, pairs = [], []
    for i in range(120):
        base = [str(x) for x in rng.choice(vocab, 300)]
        copy = list(base)
        for k in rng.choice(300, 5, replace=False):
            copy[k] = "other"
        assert jaccard(base, copy) >= 0.8
        rows += [(2 * i, " ".join(base)), (2 * i + 1, " ".join(copy))]
    hot = [str(x) for x in rng.choice(vocab, 300)]
    for i in range(400):  # one large group
        copy = list(hot)
        copy[int(rng.integers(300))] = f"x{i}"
        rows.append((1000 + i, " ".join(copy)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = {r.doc_id for r in s.keep_one(docs, scheme=s.NEAR).collect()}
    assert {2 * i for i in range(120)} <= kept and len([k for k in kept if k < 1000 and k % 2]) <= 4
    assert [k for k in kept if k >= 1000] == [1000]


def test_pipeline_links_by_exact_similarity(spark):
    """Pairs at 0.82 lose one document, pairs at 0.70 and 0.78 none."""
    import corpus_pipeline

    rows = []
    for n, sim in enumerate((0.82, 0.78, 0.70)):
        common = round(2 * 400 * sim / (1 + sim))
        for k in range(40):
            for side in range(2):
                words = [f"c{n}x{k}x{i}" for i in range(common + 4)] + [f"o{n}x{k}x{side}x{i}" for i in range(400 - common)]
                rows.append((1000 * n + 2 * k + side, " ".join(words)))
    kept = sorted(r.doc_id for r in corpus_pipeline.near_dedup(spark, spark.createDataFrame(rows, "doc_id long, text string"), "").collect())
    assert kept == sorted([2 * k for k in range(40)] + [1000 * n + k for n in (1, 2) for k in range(80)])


@pytest.mark.parametrize("few", [4, 32])
def test_byte_index_finds_similar_fingerprints(few):
    """Candidates come from the postings of fingerprint bytes: pairs as far apart as a similarity of 0.8 makes them all meet, strangers hardly, a large group by its hub."""
    rng = np.random.default_rng(few)
    pairs, group, strangers = 1500, 60, 800
    base = rng.integers(0, 2, (pairs, 512), dtype=np.uint8)
    hub = rng.integers(0, 2, (1, 512), dtype=np.uint8)
    bits = np.concatenate([base, base ^ (rng.random(base.shape) < 0.1516), hub ^ (rng.random((group, 512)) < 0.05), rng.integers(0, 2, (strangers, 512), dtype=np.uint8)])
    fp = np.packbits(bits, axis=1).view(np.uint64)
    node = np.arange(len(fp))
    key, mark, after = s.postings(fp, node, np.zeros(len(fp), bool))
    assert len(key) == 64 * len(fp) and (mark >> 1 == np.repeat(node, 64)).all()
    order = np.lexsort((mark, key))
    window = after.view(np.uint64)[order]
    (a, b), (groups, members) = s._scan_postings(key[order], mark[order] >> 1, np.zeros(len(key), bool), window, few)
    got = {(min(x), max(x)) for x in zip(a.tolist(), b.tolist())}
    assert {(i, pairs + i) for i in range(pairs)} <= got
    inside = set(range(2 * pairs, 2 * pairs + group))
    assert sum(b - a != pairs and not {a, b} <= inside for a, b in got) < 20
    roots = {i: i for i in inside}
    for x, y in sorted(p for p in got if set(p) <= inside):
        roots = {i: roots[x] if r == roots[y] else r for i, r in roots.items()}
    assert len(set(roots.values())) == 1
    byte = s._bytes(fp)
    assert all((byte[x] == byte[y]).sum() >= 2 for x, y in got if x != y)
    assert set(members.tolist()) == inside


def plain_similar(rows):
    """Smallest ids of the groups chained by a similarity of five-word shingle sets of at least 0.8."""

    def grams(t):
        w = re.findall(r"[^\x20\t-\r]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) > 5 else {tuple(w)} if w else set()

    roots = []
    for i, t in sorted(rows):
        x = grams(t)
        near = [g for g in roots if any(x == y or x and y and len(x & y) >= 0.8 * len(x | y) for y in g[1])]
        roots = [g for g in roots if not any(g is n for n in near)] + [(min([i, *[g[0] for g in near]]), [x, *[y for g in near for y in g[1]]])]
    return sorted(g[0] for g in roots)


@pytest.mark.parametrize("heavy", [6, 2048])
def test_similar_against_brute_force(spark, heavy):
    """Texts that share a long passage, linked and not; short lists and split ones give the same groups."""
    rng = np.random.default_rng(heavy)
    common = [f"c{i}" for i in range(120)]
    rows = []
    for i in range(90):
        own = [f"o{i // 3}x{k}" for k in range(int(rng.integers(5, 60)))]
        words = common + own
        for _ in range(int(rng.integers(0, 3))):
            words[int(rng.integers(len(words)))] = f"x{i}"
        rows.append((i, " ".join(words)))
    rows += [(200, None), (201, ""), (202, "a b"), (203, "A b"), (204, "word " * 40_000)]
    docs = spark.createDataFrame(rows + rows[:2], "doc_id long, text string").repartition(5)
    kept = s.keep_one_similar(docs.withColumn("__row", F.lit(0)), heavy=heavy)
    assert kept.columns == ["doc_id", "text", "__row"]
    assert sorted(r.doc_id for r in kept.collect()) == plain_similar(rows)


def test_nodes_of_large_groups_meet_their_codes_once(spark, monkeypatch):
    """What is still apart in large groups is joined with its codes by node: a join's rows don't grow with the groups a node is in."""
    rng = np.random.default_rng(3)
    common = [f"c{i}" for i in range(120)]
    rows = [(i, " ".join(common + [f"o{i // 3}x{k}" for k in range(int(rng.integers(5, 60)))])) for i in range(90)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    met, join = [], type(docs).join

    def counted(self, other, *args, **kwargs):
        if "codes" in other.columns:
            met.append((self.count(), self.select("node").distinct().count()))
        return join(self, other, *args, **kwargs)

    monkeypatch.setattr(type(docs), "join", counted)
    kept = s.keep_one_similar(docs, heavy=20)
    assert met and all(n == nodes for n, nodes in met)
    assert sorted(r.doc_id for r in kept.collect()) == plain_similar(rows)
