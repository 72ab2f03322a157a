"""Quality rules, classifier, decontamination, URL filters and licences against plain versions."""

import re
import sys
import zlib
from collections import Counter
from pathlib import Path

import numpy as np
import pytest

sys.path.insert(0, str(Path(__file__).parents[1]))
import parity  # noqa: E402
from lpstream.llm import decontamination as dc, licenses, line_crf, quality_rules as qr, queries, url_filters as uf  # noqa: E402

WORDS = re.compile(r"[^\x20\x09-\x0D]+")


# --- quality rules -----------------------------------------------------------


def plain_measures(text):
    text = text or ""
    w = WORDS.findall(text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORDS.search(line):
            dup += line in seen
            seen.add(line)
    grams = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    hit = set()
    for i in range(len(w) - 2):
        if grams[tuple(w[i : i + 3])] > 1:
            hit.update((i, i + 1, i + 2))
    shares = {}
    for n in (5, 8):
        g = Counter(tuple(w[i : i + n]) for i in range(len(w) - n + 1))
        cover = set()
        for i in range(len(w) - n + 1):
            if g[tuple(w[i : i + n])] > 1:
                cover.update(range(i, i + n))
        whole = sum(map(len, w))
        shares[n] = sum(len(w[i]) for i in cover) / whole if whole else 0.0
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(hit), shares


@pytest.mark.parametrize("text", [None, "", "\n \n", "a b c a b c", "x\nx\n\ny\n y", "é # $ é", "one\x1ctwo\x0bthree", "a b c d e " * 7 + "z", "w\u00a0v w\u00a0v", "ééééé a b c d ééééé a b c d xyz", "日本 語 x y z é " * 30_000])
def test_measures(text):
    m = qr.measure(text, (5, 8))
    want = plain_measures(text)
    assert (m.n_words, m.word_chars, m.n_symbols, m.n_dup_lines, m.n_repeat_words) == want[:5]
    assert all(abs(m.dup_ngram_chars[n] - want[5][n]) < 1e-12 for n in (5, 8))


def test_rules_query(spark, sf):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = queries.op7_quality_rules(spark, sf).collect()
    assert len(got) == len(docs)
    for r in got:
        want = plain_measures(docs[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want[:5]
        assert r.base_failed == (want[0] < 50 or 100 * want[4] > 50 * want[0]) and not (r.base_failed and r.kept)


def test_rules_edges(spark):
    good = " ".join(f"word{i}" for i in range(80))
    rows = [(1, good, 1), (None, good, None), (2, None, 3), (2, "a b c d e f " * 30, 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, kept int")
    assert [r.doc_id for r in qr.keep(docs).collect()] == [1, None] and qr.keep(docs).columns == docs.columns
    assert qr.judge(docs).count() == 4 and qr.judge(docs.limit(0)).count() == 0


# --- classifier -----------------------------------------------------------------


def test_marginals_against_enumeration():
    rng = np.random.default_rng(0)
    count = np.array([1, 4, 3])
    first = np.cumsum(count) - count
    unary, pair, start = rng.normal(size=8), rng.normal(size=(2, 2)), rng.normal(size=2)
    good, expected, log_z = line_crf.marginals(unary, first, count, pair, start, pairs=True)
    total_pairs, total_z = np.zeros((2, 2)), 0.0
    for f, c in zip(first, count):
        z, p, e = 0.0, np.zeros(c), np.zeros((2, 2))
        for code in range(2**c):
            y = [code >> k & 1 for k in range(c)]
            s = start[y[0]] + sum(unary[f + k] * y[k] for k in range(c)) + sum(pair[y[k], y[k + 1]] for k in range(c - 1))
            w = np.exp(s)
            z += w
            p += w * np.array(y)
            for k in range(c - 1):
                e[y[k], y[k + 1]] += w
        assert np.allclose(good[f : f + c], p / z)
        total_pairs += e / z
        total_z += np.log(z)
    assert np.allclose(expected, total_pairs) and np.isclose(log_z, total_z)


def test_classifier_query(spark):
    sf = "/root/testdata/sf0.01"
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    got = queries.op3_quality_classifier(spark, sf).collect()
    assert len(got) == spark.read.parquet(f"{sf}/documents.parquet").count()
    for r in got:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == (r.score >= 0.3)
    held = [(labels[r.doc_id], r.score, r.predicted) for r in got if r.held_out and r.doc_id in labels]
    good = [s for y, s, _ in held if y == 1]
    bad = [s for y, s, _ in held if y == 0]
    auc = np.mean([(g > b) + 0.5 * (g == b) for g in good for b in bad])
    assert auc > 0.97 and np.mean([p == y for y, _, p in held]) > 0.93


def test_classifier_edges(spark):
    docs = spark.createDataFrame([(1, None, 0.5), (None, "a plain line here.", 0.1), (3, " \n", 0.2)], "doc_id long, text string, score double")
    empty = spark.createDataFrame([], "doc_id long, quality int")
    model = line_crf.fit(docs, empty)
    assert {r.score for r in line_crf.classify(docs, model).collect()} == {0.5}
    assert line_crf.keep(docs, model).columns == docs.columns and line_crf.keep(docs.limit(0), model).count() == 0
    fitted = line_crf.fit(docs, spark.createDataFrame([(1, 1), (1, 1), (3, None), (None, 0)], "doc_id long, quality int"))
    assert all(0 < r.score <= 1 for r in line_crf.classify(docs, fitted).collect())


# --- decontamination --------------------------------------------------------------


def plain_overlaps(doc, item):
    """Best run at every offset, by comparing all words."""
    out = []
    d, t = dc.words(doc), dc.words(item)
    for off in range(-len(t) + 1, len(d)):
        a, b = max(0, off), min(len(d), off + len(t))
        equal = np.array([d[k] == t[k - off] for k in range(a, b)])
        s, e, m = dc.best_run(equal)
        if m >= dc.MIN_WORDS or m >= dc.MIN_SHARE * len(t):
            out.append((a + s, e - s, m, len(t)))
    return out


def test_substituted_passages_are_found():
    rng = np.random.default_rng(1)
    vocab = [f"w{i}" for i in range(5000)]
    item = [str(x) for x in rng.choice(vocab, 40)]
    index = dc.Index([(7, " ".join(item))])
    for _ in range(200):
        changed = list(item)
        for k in rng.choice(40, 5, replace=False):
            changed[k] = "changed"
        doc = [str(x) for x in rng.choice(vocab, 100)] + changed + [str(x) for x in rng.choice(vocab, 50)]
        found = index.overlaps(dc.word_hashes(" ".join(doc)))
        assert [f[1:] for f in found] == plain_overlaps(" ".join(doc), " ".join(item)) and found
    assert not index.overlaps(dc.word_hashes(" ".join(str(x) for x in rng.choice(vocab, 5000))))


def test_masks_meet_every_accepted_run():
    """Every order of a run's first matches that the verifier can accept holds a seed, so periodic substitutions are found too."""

    def orders(r, run="1", score=1):
        if run.count("1") == r:
            return [run]
        return orders(r, run + "1", score + 1) + (orders(r, run + "0", score - 2) if score >= 2 else [])

    for n in range(dc.MIN_ITEM, 60):
        if n > dc.MIN_ITEM and dc.least_matches(n) == dc.least_matches(n - 1):
            continue
        for run in orders(dc.least_matches(n)):
            assert any(all(run[k + i] == "1" for i, c in enumerate(m) if c == "1") for m in dc.masks_of(n) for k in range(len(run) - len(m) + 1)), (n, run)
    for n in (15, 38, 59):
        item = [f"w{i}" for i in range(n)]
        index = dc.Index([(1, " ".join(item))])
        for phase in range(4):
            doc = [f"x{i}" if i % 4 == phase else w for i, w in enumerate(item)]
            assert index.overlaps(dc.word_hashes("a b c " + " ".join(doc) + " d e"))


def test_decontamination_query(spark, sf):
    items = {r.item_id: r.text for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = {(r.doc_id, r.item_id, r.start_word, r.n_words, r.matched_words, r.item_words) for r in queries.op1_decontamination(spark, sf).collect()}
    verbatim = {(d, i) for d, t in docs.items() for i, b in items.items() if " ".join(map(bytes.decode, dc.words(b))) in " ".join(map(bytes.decode, dc.words(t)))}
    assert verbatim <= {g[:2] for g in got} and verbatim
    for d, i, *rest in got:
        assert tuple(rest) in plain_overlaps(docs[d], items[i])


def test_decontamination_blocks_and_edges(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    one = sorted(map(tuple, dc.overlaps(docs, bench).collect()))
    assert sorted(map(tuple, dc.overlaps(docs, bench, block_chars=1500).collect())) == one
    clean = dc.drop_contaminated(docs, bench, block_chars=1500)
    assert clean.columns == docs.columns and {r.doc_id for r in clean.collect()} == {r.doc_id for r in docs.collect()} - {o[0] for o in one}
    odd = spark.createDataFrame([(None, None, 1), (1, "", 2)], "doc_id long, text string, item_id int")
    none = spark.createDataFrame([(None, None), (3, "short")], "item_id long, text string")
    assert dc.overlaps(odd, none).count() == 0 and dc.overlaps(odd, none.limit(0)).count() == 0 and dc.drop_contaminated(odd, none).count() == 2


# --- URL filters -------------------------------------------------------------------


def plain_verdict(url):
    host = path = ""
    if url and "://" in url:
        rest = url.split("://", 1)[1]
        host = re.match(r"[^/?#]*", rest)[0]
        path = re.match(r"[^?#]*", rest[len(host) :])[0]
        host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
    best = None
    for r in uf.HOST_RULES:
        h, p = r.pattern.split("/", 1)
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p) and (best is None or len(r.pattern) > len(best.pattern)):
            best = r
    return host, path, best.pattern if best else None, best.verdict if best else None


URLS = ["http://example.com/en/x", "HTTP://WWW.Example.COM/en/", "https://a.www.example.com/en/1?x", "https://notexample.com/en/", "http://com/", "http://x.com", "http://x.com?y=/", "http://net/es/1", "http://a.net/fr/x#z", "http://a.net/frx", "x", None, "", "://", "http://é.NET/es/", "a://b://c.com/", "http://spam-farm.example.org/en/1", "http://u@a.com:80/p", "http://a.com/e\nn/"]


def test_url_rules(spark):
    rows = spark.createDataFrame([(i, u, "x") for i, u in enumerate(URLS * 2)] + [(None, URLS[0], "y")], "page_id long, url string, rule string")
    got = uf.judge(rows, uf.HOST_RULES + uf.PATTERN_RULES).collect()
    assert len(got) == 2 * len(URLS) + 1
    for r in got:
        host, path, rule, verdict = plain_verdict(URLS[(r.page_id or 0) % len(URLS)])
        assert (r.host, r.path, r.rule) == (host, path, rule), r
        if verdict:
            assert r.verdict == verdict
    assert {r.verdict for r in got if r.host == "spam-farm.example.org"} == {"block"}
    assert uf.judge(rows.limit(0), uf.HOST_RULES).count() == 0 and {r.verdict for r in uf.judge(rows, []).collect()} == {"allow"}


def test_tokens_stand_whole():
    assert uf.tokens(uf.Rule("example.com/en/", "block")) == ["example", "com", "en"]
    assert uf.tokens(uf.Rule("*^spam-farm^*", "block", False)) == ["spam", "farm"] and uf.tokens(uf.Rule("ads*", "block", False)) == []


@pytest.mark.parametrize("key", sorted(queries.oracle_sql()))
def test_sql_parity(key, spark):
    assert parity.compare(spark, "/root/testdata/sf0.01", queries.queries()[key], queries.oracle_sql()[key]) is None


# --- licences ------------------------------------------------------------------------


def test_license_inheritance(spark):
    rows = [
        (1, "a/LICENSE", "This work is licensed under the GNU General Public License, version 3.\nTerms and conditions follow."),
        (2, "a/b/c/x.py", "print(1)"),
        (3, "a/b/LICENSE.txt", "Released under the MIT License."),
        (4, "a/b/c/y.py", "# Licensed under the Apache License, Version 2.0.\n" + "print(2)\n" * 20),
        (5, "other/z.py", "nothing"),
        (6, None, "Released under the MIT License.\nwords " + "more " * 50),
        (7, "a/q.py", None),
        (7, "a/q.py", ""),
        (8, "a/b/same.py", "licenses are mentioned here in a sentence about cooking and gardens"),
    ]
    files = spark.createDataFrame(rows, "doc_id long, path string, text string")
    got = {(r.doc_id, r.license, r.how) for r in licenses.scan(files).collect()}
    assert got == {(1, "GPL-3.0", "header"), (2, "MIT", "inherited"), (3, "MIT", "header"), (4, "Apache-2.0", "header"), (5, None, "none"), (6, "MIT", "header"), (7, "GPL-3.0", "inherited"), (8, "MIT", "inherited")}
    assert licenses.scan(files).count() == len(rows) and licenses.scan(files.limit(0)).count() == 0


def test_license_query_finds_every_statement(spark, sf):
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    got = {r.doc_id: r for r in queries.op5_license_scan(spark, sf).collect()}
    assert got.keys() == docs.keys()
    stated = {"Licensed under the Apache License, Version 2.0.": "Apache-2.0", "Released under the MIT License.": "MIT", "This work is licensed under the GNU General Public License, version 3.": "GPL-3.0", "Licensed under CC BY-NC 4.0.": "CC-BY-NC-4.0"}
    seen = 0
    for i, t in docs.items():
        found = {v for k, v in stated.items() if k in t.split("\n")}
        if found:
            seen += 1
            assert got[i].how == "header" and got[i].license in found
        elif not re.search(licenses.TRIGGER, t):
            assert got[i].how != "header"
    assert seen
