"""HTML wrappers, chat repair and the pipeline."""

import html
import itertools
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from lpstream.llm import chat_format as cf, decontamination as dc, html_wrappers as hw, line_crf, queries, quality_rules as qr, simhash_dedup as sd


# --- HTML ----------------------------------------------------------------------


def test_blocks_and_references():
    page = "<html><body><nav><a>Home</a></nav><article><header><h1>A &amp; B</h1></header><p>one\n  <b>two</b>&nbsp;three<p>four<ul><li>x<li>y</ul><aside>ad</aside><div class='comments'>hi</div></article><footer>f</footer></body>"
    assert hw.extract(page) == "A & B\none two three\nfour\nx\ny"
    assert hw.extract(None) == "" and hw.extract("") == "" and hw.extract("plain <") == "plain <"
    assert hw.extract("<script>var a='<p>no</p>'</script><p>yes</p><style>p{}</style><!-- <p>no</p> -->") == "yes"
    assert hw.extract("<div class=ad><p>buy<article><p>text</p></article>") == "text"


def test_wrapper_shapes():
    pages = [f"<div id=m><ul>{''.join(f'<li>{w}</li>' for w in words)}</ul><p>same</p>{extra}<p>{words[0]}</p></div>" for words, extra in ((["a", "b"], ""), (["c", "d", "e"], "<hr>"), (["f", "g"], ""))]
    w = hw.infer(pages)
    text = w.expression()
    assert "(<li> #TEXT </li>)+" in text and "<div id=m>" in text and ")?" in text and "<hr>" in text


def test_template_without_article():
    """Furniture of the host goes by the wrapper's constants, the varying part stays."""
    page = lambda t: f"<html><body><div id=top>Site name</div><div id=c><p>{t}</p><p>{t[::-1]} more</p></div><div id=b>All rights reserved</div></body></html>"
    texts = [f"text number {i} of the host " * 5 for i in range(5)]
    w = hw.infer([page(t) for t in texts])
    assert hw.extract(page(texts[0]), w) == f"{' '.join(texts[0].split())}\n{' '.join((texts[0][::-1] + ' more').split())}"


def test_html_query(spark, sf):
    pages = {r.page_id: r for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    got = {r.page_id: r for r in queries.op8_html_extraction(spark, sf).collect()}
    assert got.keys() == pages.keys()
    for i, r in got.items():
        body = re.search(r"<article>(.*?)</article>", pages[i].html, re.S)[1]
        lines = re.sub(r"<[^>]*>", "", re.sub(r"</?(p|h1|br)>", "\n", body)).split("\n")
        assert r.text == "\n".join(x for x in (" ".join(html.unescape(s).split()) for s in lines) if x) and r.n_chars == len(r.text)


def test_html_is_parsed_in_small_parts():
    """A task holds the blocks of at most 512 pages, and of 4 MB of html unless one page has more."""
    texts = [None, "", "x" * (5 << 20), *["<p>y</p>" * 100] * 10_000, "é" * (3 << 20)]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array(texts, pa.string())], names=["page_id", "html"])
    parts = list(hw.slices([batch.slice(0, 0), batch], 1))
    assert [i for b in parts for i in b.column(0).to_pylist()] == list(range(len(texts)))
    assert all(b.num_rows == 1 or b.num_rows <= 512 and sum(len((t or "").encode()) for t in b.column(1).to_pylist()) <= 4 << 20 for b in parts)
    assert len(parts) < 30


def test_html_edges(spark):
    rows = spark.createDataFrame([(1, None, None, "a"), (1, None, "", "b"), (None, "http://h/", "<p>x" * 3000, "c")], "page_id long, url string, html string, text string")
    got = hw.run_host(rows).collect()
    assert sorted(r.n_chars for r in got) == [0, 0, 5999] and hw.run_host(rows.limit(0)).count() == 0


def test_wrapper_takes_all_pages_of_a_host(spark):
    """One wrapper a host from its distinct whole pages, whatever the partitions."""
    bodies = [f"<p>{' '.join(f'w{i}x{k}' for k in range(9))}</p>" for i in range(12)]
    rows = [(i, "http://h.org/", f"<body><div id=a>Site</div><div id=c>{b}</div>{'<br>' * 4500}<div id=z>All rights reserved</div></body>") for i, b in enumerate(bodies)]
    copies = [(100 + i, "http://copies.org/", "<body><h1>Title</h1><p>only paragraph</body>") for i in range(9)]
    for parts in (1, 5, 16):
        got = {r.page_id: r.text for r in hw.run_host(spark.createDataFrame(rows + copies, "page_id long, url string, html string").repartition(parts)).collect()}
        assert all(got[i] == b[3:-4] for i, b in enumerate(bodies))
        assert all(got[100 + i] == "Title\nonly paragraph" for i in range(9))


def test_wrapper_decides_inside_articles(spark):
    """A host's repeated furniture goes inside the article too."""
    rows = [(i, "http://h.org/", f"<body><article><p>Follow us everywhere</p><p>story {'abcdef'[i] * 30}</p></article></body>") for i in range(6)]
    got = hw.run_host(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert all(r.text == f"story {'abcdef'[r.page_id] * 30}" for r in got) and len(got) == 6


def test_all_parts_of_an_article_stay():
    page = "<body><article><p>first part</p></article><div class=ad>buy</div><article><p>the second and longer part</p></article></body>"
    assert hw.extract(page) == "first part\nthe second and longer part"


# --- chat -----------------------------------------------------------------------


def legal(roles):
    return re.fullmatch("s?(ua)*", "".join(r[0] for r in roles)) is not None or not roles


def plain_cost(roles, costs):
    """Least cost over all labellings, merges and insertions, by enumeration."""
    best = None
    for labels in itertools.product((1, 2, 3), repeat=len(roles)):
        base = sum(0 if a == b else costs.name if b == 0 else costs.relabel for a, b in zip(labels, roles))
        for merges in itertools.product((False, True), repeat=len(roles)):
            if any(m and (i == 0 or labels[i] != labels[i - 1]) for i, m in enumerate(merges)):
                continue
            seq = [a for a, m in zip(labels, merges) if not m]
            cost, state = base + costs.merge * sum(merges), cf.START
            for a in seq:
                if (state, a) not in cf.BRIDGE:
                    cost = None
                    break
                cost += costs.insert * len(cf.BRIDGE[state, a])
                state = a
            if cost is None:
                continue
            cost += costs.insert * len(cf.ENDING[state])
            best = cost if best is None else min(best, cost)
    return best


@pytest.mark.parametrize("costs", [cf.Costs(), cf.Costs(5, 1, 2, 1)])
def test_repairs_are_cheapest(costs):
    table, final = cf.step_table(costs), cf.ending(costs)
    for n in range(1, 5):
        for roles in itertools.product(range(4), repeat=n):
            path = cf.repair(list(roles), table, final)
            out, cost = [], 0
            for (s, merged, inserted), r in zip(path, roles):
                out += [cf.ROLES[x - 1] for x in inserted] + ([] if merged else [cf.ROLES[s - 1]])
                cost += costs.merge * merged + costs.insert * len(inserted) + (0 if s == r else costs.name if r == 0 else costs.relabel)
            tail = cf.ENDING[path[-1][0]]
            assert legal(out + [cf.ROLES[x - 1] for x in tail])
            assert cost + costs.insert * len(tail) == plain_cost(roles, costs)


@pytest.mark.parametrize("parts", [1, 3, 7])
def test_conversations_across_partitions(spark, parts):
    rng = random.Random(parts)
    rows = [(c, t, rng.choice(["user", "assistant", "system", "human", None, "odd"]), f"{c}-{t}") for c in range(6) for t in range(rng.choice([1, 2, 5, 90]))]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = cf.format_chat(df, parts=parts).collect()
    assert {(r.conv_id, r.turn) for r in got if r.op != "insert"} == {r[:2] for r in rows} and sum(r.op != "insert" for r in got) == len(rows)
    table, final = cf.step_table(cf.Costs()), cf.ending(cf.Costs())
    for c in range(6):
        mine = sorted((r for r in got if r.conv_id == c), key=lambda r: (r.position, r.op.startswith("merge"), r.turn if r.turn is not None else -1))
        turns = [r for r in mine if not r.op.startswith("merge")]
        assert [r.position for r in turns] == list(range(1, len(turns) + 1)) and legal([r.role for r in turns])
        roles = [cf.role_code(r[2]) for r in sorted(x for x in rows if x[0] == c)]
        path = cf.repair(roles, table, final)
        assert len(turns) == sum(len(i) + (not m) for _, m, i in path) + len(cf.ENDING[path[-1][0]])
        assert all(r.rendered.lstrip("\n").startswith(f"<|{r.role}|>\n") for r in turns)


def test_chat_order_and_ties(spark):
    """Rendered pieces in order of (position, source_order) are the conversation, from a shuffled input with ties, and null beside a conversation named None."""
    rows = [("None", 1, "user", "a"), (None, 1, "user", "b"), ("c", 1, "user", "y"), ("c", 1, "user", "x"), ("c", 1, "user", "x"), ("c", 2, "assistant", "long " * 50_000)]
    df = spark.createDataFrame(rows, "conv_id string, turn long, role string, text string").repartition(5)
    for parts in (1, 4):
        got = sorted(cf.format_chat(df, parts=parts).filter("conv_id = 'c'").collect(), key=lambda r: (r.position, r.source_order or 0))
        assert [r.op for r in got] == ["keep", "merge", "merge", "keep"] and len({r.source_order for r in got}) == 4
        body = [t for _, t in sorted([(spark.range(1).select(F.xxhash64(F.lit(t))).first()[0], t) for t in ("x", "x", "y")])]
        assert "".join(r.rendered for r in got) == f"<|user|>\n{body[0]}\n{body[1]}\n{body[2]}\n<|assistant|>\n" + "long " * 50_000
        whole = cf.format_chat(df, parts=parts).collect()
        assert sorted((r.conv_id or "", r.rendered) for r in whole if r.conv_id != "c" and r.op != "insert") == [("", "<|user|>\nb"), ("None", "<|user|>\na")]


def test_chat_edges(spark, sf):
    odd = spark.createDataFrame([(None, None, None, None, "x"), (None, 1, "user", "hi", "y"), (2, 1, "user", "a", "z"), (2, 1, "user", "a", "z")], "conv_id long, turn long, role string, text string, position string")
    got = cf.format_chat(odd).collect()
    assert sum(r.op != "insert" for r in got) == 4 and cf.format_chat(odd.limit(0)).count() == 0
    n = spark.read.parquet(f"{sf}/conversations.parquet").count()
    assert queries.op9_chat_formatting(spark, sf).filter("op <> 'insert'").count() == n


# --- pipeline ----------------------------------------------------------------------


def test_pipeline_against_plain_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").orderBy("doc_id").collect()
    model = line_crf.fit(spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet"))
    left = [d for d in docs if line_crf.score(model, [d.text])[0] >= 0.3]
    left = [d for d in left if qr.verdict(qr.measure(d.text), qr.Limits())[1]]
    roots = []
    for d in left:  # groups by chains of five-word shingle sets at a similarity of 0.8 and more
        x = np.unique(sd.shingles(d.text, 5))
        near = [g for g in roots if any(sd.jaccard(x, y) >= 0.8 or not len(x) and not len(y) for y in g[1])]
        merged = (min([d, *[g[0] for g in near]], key=lambda x: x.doc_id), [x, *[y for g in near for y in g[1]]])
        roots = [g for g in roots if not any(g is n for n in near)] + [merged]
    kept = {g[0].doc_id for g in roots}
    index = dc.Index([(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()])
    want = {d.doc_id for d in left if d.doc_id in kept and not index.overlaps(dc.word_hashes(d.text))}
    out = corpus_pipeline.run(spark, sf)
    got = out.groupBy("doc_id").agg(F.sum("length").alias("n"), F.max("doc_tokens").alias("t")).collect()
    assert {r.doc_id for r in got} == want and all(r.n == r.t for r in got)


def test_stages_take_odd_tables(spark, sf, tmp_path):
    rows = [(1, "text", None, "s", 4, 1), (None, None, "en", None, None, 2), (1, "text", None, "s", 4, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, __row int")
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        for d in (docs, docs.limit(0)):
            out = stage(spark, d, sf)
            out.count()
            assert k == 4 or out.columns == docs.columns
