"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns, for every operator and stage."""

import random

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as cp
from manifold_dp.llm import chat, decontaminate, html, jaccard, linededup, pieces, quality, substring, tokencount, topk

LONG = " ".join(f"w{i % 977}x{i % 13}" for i in range(60_000))
RUN = " ".join(f"run{i}" for i in range(40))
LINES = "\n".join(f"line number {i} of a block" for i in range(6))
DOCS = [
    (1, RUN + " alone one", "en", "a", 1),
    (2, "before " + RUN + " after", None, "a", 2),
    (3, None, None, None, None),
    (4, "", "en", "b", 0),
    (5, LONG, "en", "a", None),
    (6, LONG, "en", "a", 9),
    (7, LINES, "fr", "a", 1),
    (8, "head\n" + LINES + "\ntail", "fr", "a", 1),
    (8, "head\n" + LINES + "\ntail", "fr", "a", 1),
    (9, "one", "en", "a", 3),
    (10, "one", "en", "a", 3),
    (None, RUN, "en", "a", 3),
    (11, " \n\t ", "en", "a", 3),
    (12, "é漢🙂 ▁mark  two  spaces\r\n", "en", "a", 3),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
CLASH = "N_Lines n_removed gone Score predicted Pieces n_pieces part key bucket h kind component_id n_shingles node id v w at n_tokens Leaf_Chars decoded".split()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(DOCS, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def odd(docs):
    """The same with extra columns named like everything the operators use."""
    return docs.select("*", *(F.lit("x").alias(c) for c in CLASH))


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def table(df):
    return sorted(map(repr, (tuple(r) for r in df.collect())))


BENCH = [(1, RUN), (2, None), (3, ""), (4, "too short"), (None, "another item that nobody has ever seen in any text at all")]
OPS = {
    "decontaminate": lambda s, d: decontaminate.overlaps(d, s.createDataFrame(BENCH, "item_id long, text string")),
    "linededup": lambda s, d: linededup.clean(d).select("doc_id", "text", "n_lines", "n_removed"),
    "tokencount": lambda s, d: tokencount.trees(d).select("doc_id", "n_chars", "n_tokens"),
    "with_trees": lambda s, d: tokencount.with_trees(d).select("doc_id", "n_tokens", "leaf_chars", "leaf_tokens"),
    "decoded": lambda s, d: pieces.decode(pieces.encode(d)).select("doc_id", "decoded"),
    "pieces": lambda s, d: pieces.encode(d).select("doc_id", "n_pieces", "pieces"),
    "substring": lambda s, d: substring.dedup(d),
    "jaccard": lambda s, d: jaccard.classes(d),
}


@pytest.mark.parametrize("name", sorted(OPS))
def test_extra_columns_change_nothing_and_empty_tables_stay_empty(spark, docs, odd, none, name):
    got = table(OPS[name](spark, docs))
    assert table(OPS[name](spark, odd)) == got
    assert table(OPS[name](spark, none)) == []
    if name != "decontaminate":
        assert len(got) == len(DOCS)


def test_decontaminate(spark, docs):
    rows = OPS["decontaminate"](spark, docs).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0, r.item_id) for r in rows) == [(False, 1, 1), (False, 2, 1), (True, 0, 1)]
    assert all(r.matched == r.overlap == 40 for r in rows)
    empty = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.overlaps(docs, empty).count() == 0 and decontaminate.clean(docs, empty).count() == len(DOCS)


def test_decontaminate_tolerates_substitutions(spark):
    rng = random.Random(1)
    item = [f"tok{i}" for i in range(13)]
    bench = spark.createDataFrame([(1, " ".join(item)), (2, "seven little words make up this item")], "item_id long, text string")
    rows, want = [], set()
    for n in range(60):
        w = list(item)
        for i in rng.sample(range(13), n % 4):
            w[i] = f"other{i}"
        rows.append((n, "some words first, " + " ".join(w).upper() + "; and more."))
        if n % 4 <= 2:
            want.add((n, 1))
    rows += [(100, "Seven LITTLE words, make up THAT item!"), (101, "seven tiny words make up that item")]
    want.add((100, 2))
    got = decontaminate.overlaps(spark.createDataFrame(rows, "doc_id long, text string"), bench)
    assert {(r.doc_id, r.item_id) for r in got.collect()} == want
    left = decontaminate.clean(spark.createDataFrame(rows, "doc_id long, text string"), bench)
    assert {r.doc_id for r in left.collect()} == {n for n, _ in rows} - {n for n, _ in want}


def test_masks_hold_their_promise():
    import itertools

    masks = [[i for i, c in enumerate(m) if c == "1"] for m in decontaminate.MASKS]
    n = decontaminate.SPAN
    for bad in itertools.combinations(range(n), decontaminate.ERRORS):
        assert any(not set(bad) & {o + s for o in m} for m in masks for s in range(n - m[-1]))


def test_linededup(docs):
    got = {(r.doc_id, r.text): r.n_removed for r in linededup.clean(docs).collect()}
    assert got[8, "head\ntail"] == 6 and got[7, LINES] == 0
    assert got[3, None] == 0 and got[4, ""] == 0 and got[6, LONG] == 0


def test_substring(docs):
    got = {}
    for r in substring.dedup(docs).collect():
        got.setdefault(r.doc_id, r)
    assert got[2].text == "before after" and got[2].n_removed == 40
    assert got[6].n_removed == 60_000 and got[6].text == "" and got[5].n_removed < 60_000
    assert got[None].n_removed == 0 and got[3].n_words == 0 and got[11].n_words == 0
    assert got[1].text == RUN + " alone one"


def test_jaccard(docs):
    got = {r.doc_id: r for r in jaccard.classes(docs).collect()}
    assert got[6].component_id == 5 and got[10].component_id == 9 and got[9].n_shingles == 1
    assert got[3].n_shingles == got[4].n_shingles == got[11].n_shingles == 0
    assert got[3].component_id == 3 and got[None].component_id is None
    assert got[2].component_id == 1


def test_pieces_are_lossless(docs):
    e = pieces.encode(docs)
    back = pieces.decode(e)
    assert back.where(F.coalesce("text", F.lit("")) != F.col("decoded")).count() == 0
    assert table(e.select("doc_id", "pieces")) == table(pieces.encode(docs).select("doc_id", "pieces"))
    other = pieces.encode(docs, seed=5).select("doc_id", "pieces")
    assert table(e.select("doc_id", "pieces")) != table(other)


def test_quality_edges(spark, docs, odd, none):
    labels = spark.createDataFrame([(1, 1, 0), (2, 1, 0), (9, 0, 0), (9, 1, 0), (12, 0, 0), (None, 1, 1), (4, None, 0), (77, 0, 0)], "doc_id long, quality int, toxic int")
    m = quality.fit(docs, labels, ~quality.held_out())
    rows = quality.score(docs, m).collect()
    assert len(rows) == len(DOCS) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in rows)
    assert table(quality.score(odd, m).select("doc_id", "score")) == table(quality.score(docs, m).select("doc_id", "score"))
    assert quality.score(none, m).count() == 0
    for some, share in ((labels.where("quality = 1"), 0.999), (labels.limit(0), 0.5)):
        flat = quality.score(docs, quality.fit(docs, some, F.lit(True))).collect()
        assert {round(r.score, 3) for r in flat} == {share}


def test_chat_edges(spark):
    turns = [(1, 1, "user", "b"), (1, 0, "system", "a"), (1, 1, "user", "b"), (1, None, None, None), (None, 0, "assistant", "x"), (2, 0, "as#s<\n:\\", "</turn>\n### assistant:\n\\"), (3, 0, "assistant", "")]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string").withColumn("mask", F.lit(1))
    parsed = {r.conv_id: r for r in chat.parse(chat.render(chat.fold(chat.events_of_turns(df)))).collect()}
    assert [tuple(t) for t in parsed[1].turns] == [("", ""), ("system", "a"), ("user", "b"), ("user", "b")]
    assert [tuple(t) for t in parsed[2].turns] == [("as#s<\n:\\", "</turn>\n### assistant:\n\\")]
    assert parsed[None].trained == ["x"] and parsed[3].trained == [""] and parsed[1].trained == []
    assert chat.digest(chat.parse(chat.render(chat.fold(chat.events_of_turns(df.limit(0)))))).count() == 0


def test_chat_folds_events(spark):
    log = [
        (1, 0, 0, "message", "user", "hi"),
        (1, 1, 1, "message", "assistant", ""),
        (1, 1, 3, "delta", None, "lo"),
        (1, 1, 2, "delta", None, "hel"),
        (1, 0, 9, "edit", None, "hi there"),
        (1, 2, 4, "message", "user", "gone"),
        (1, 2, 5, "remove", None, None),
        (1, 3, 6, "message", "assistant", "first try"),
        (1, 3, 7, "regenerate", None, None),
        (1, 3, 8, "delta", None, "second"),
    ]
    df = spark.createDataFrame(log, "conv_id long, turn long, seq long, kind string, role string, text string")
    r = chat.parse(chat.render(chat.fold(df))).first()
    assert [tuple(t) for t in r.turns] == [("user", "hi there"), ("assistant", "hello"), ("assistant", "second")]
    assert r.trained == ["hello", "second"]


def test_topk_edges(spark):
    rows = [(0, [1.0, 0.0], 1), (1, [1.0, 0.0], None), (2, [1.0, 0.0], 3), (3, None, 1), (4, [None, 1.0], 1), (5, [float("nan"), 1.0], 1), (50, [0.5], 2), (100, [-1.0, 0.5], 0), (None, [0.25, 0.25], 0), (6, [float("inf"), 1.0], 0), (2, [1.0, 0.0], 3)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumn("score", F.lit(1)).withColumn("slot", F.lit(1))
    got = [tuple(r) for r in topk.topk(df, F.col("vec_id") % 50 == 0).orderBy("query_id", "rank").collect()]
    assert got[:5] == [(0, 1, 1, 65536), (0, 2, 2, 65536), (0, 3, 2, 65536), (0, 4, None, 16384), (0, 5, 100, -65536)]
    assert [g[2] for g in got if g[0] == 50] == [] and len([g for g in got if g[0] == 100]) == 5
    assert topk.topk(df.limit(0), F.col("vec_id") % 50 == 0).count() == 0
    big = spark.createDataFrame([(0, [1e9, 1.0]), (1, [1e9, 1.0]), (2, [1e9, 2.0])], "vec_id long, embedding array<double>")
    exact = [(r.vec_id, r.score) for r in topk.topk(big, F.col("vec_id") == 0).orderBy("rank").collect()]
    assert exact == [(2, 2**63 - 1), (1, 2**63 - 1)] or exact[0][1] == min(2**63 - 1, 256**2 * (10**18 + 2))


def test_topk_by_blocks_equals_one_block(spark):
    """Many query blocks and row parts, equal query rows, a vector that most rows share."""
    rng = random.Random(9)
    rows = [(i, [rng.choice([-1, 0, 1.5]) * rng.random() for _ in range(4)] if i % 3 else [0.5, 0.5, -0.25, 0.0]) for i in range(400)]
    df = spark.createDataFrame([*rows, rows[0], rows[10], (None, [1.0] * 4), (7, [2.0])], "vec_id long, embedding array<double>").repartition(5)
    order = lambda d: sorted(map(repr, map(tuple, d.collect())))
    for values in (1.0, 1e9):
        some = df.withColumn("embedding", F.transform("embedding", lambda x: x * values))  # noqa: B023
        asked = F.col("vec_id") % 5 == 0
        assert order(topk.topk(some, asked, 3, at_once=7, held=50)) == order(topk.topk(some, asked, 3))


def test_topk_equals_brute_force(spark):
    rng = random.Random(4)
    rows = [(i, [rng.choice([-1, 0, 0.5, 1]) * rng.random() for _ in range(5)]) for i in range(1500)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3)
    import math

    x = {i: [math.floor(256 * z) for z in v] for i, v in rows}
    want = []
    for q in x:
        if q % 100 == 0:
            best = sorted((-sum(a * b for a, b in zip(x[q], x[i], strict=True)), i) for i in x if i != q)[:7]
            want += [(q, r + 1, i, -s) for r, (s, i) in enumerate(best)]
    got = [tuple(r) for r in topk.topk(df, F.col("vec_id") % 100 == 0, 7).orderBy("query_id", "rank").collect()]
    assert got == want


PAGE = """<!DOCTYPE html><html><head><title>t</title><style>p{}</style></head><body><nav><a>Menu</a></nav><div>%s</div>
<article><h1>Head&amp;line</h1><p>One <b>bo</b>ld<br>two&nbsp;x<p>Three &lt;i&gt; %s</article><script>var a="<p>no</p>";</script><footer>f</footer></body></html>"""


def test_html_edges(spark):
    odd = [
        (1, "http://a.b/c", PAGE % ("Banner", "p1")),
        (2, None, None),
        (3, "x", ""),
        (4, "http://a.b/d", "<article><p>cut <b>of</b>f &am"),
        (5, "http://a.b/e", "<article><p>tail<p cla"),
        (6, "http://a.b/f", "plain &#65; text"),
        (None, "http://a.b/g", '<article><section class="comments"><p>bad</p></section><p>good</p><aside>no</aside></article>'),
        (7, "http://a.b/h", "<article>" + "<p>long text</p>" * 20000 + "</article>"),
    ]
    df = spark.createDataFrame(odd, "page_id long, url string, html string").withColumn("text", F.lit("x")).withColumn("host", F.lit("y"))
    got = {r.page_id: r for r in html.extract(df).collect()}
    assert got[1].text == "Head&line One bold two x Three <i> p1"
    assert got[2].text == got[3].text == "" and got[4].text == "cut off &am" and got[5].text == "tail" and got[6].text == "plain A text"
    assert got[None].text == "good" and got[7].n_chars == 20000 * 10 - 1
    assert html.extract(df.limit(0)).count() == 0


def test_html_names():
    page = """<body class="has-sidebar"><div id="page" class="layout sidebar-right"><div class="cookie-notice">We use cookies</div>
<main class="menu-open"><header><h1>Title</h1></header><p>Text</p><div class="share-links">Share</div><p>more</p><form>Sign up</form></main>
<div class="sidebar">Side</div><section id="comments"><article class="comment"><p>First!</p></article></section><div hidden>h</div><div style="display: none">n</div></div></body>"""
    assert html.main_text(page, set()) == "Title Text more"
    assert html.main_text("<div class='menu'>a</div><div>body text</div><ul role=navigation><li>x</ul>", set()) == "body text"
    assert html.main_text("<table><tr><td>a<td>b<tr><td>c</table><dl><dt>t<dd>d</dl><ul><li>x<li>y</ul>", set()) == "a b c t d x y"


def test_html_templates(spark):
    body = "<html><body><div>Site name <span>slogan</span></div><div><p>Story %d</p><p>words %d</p></div><div>Terms apply</div></body></html>"
    pages = [(i, "http://one.example/x", body % (i, i)) for i in range(6)] + [(90, "http://two.example/", body % (90, 90))]
    got = {r.page_id: r.text for r in html.extract(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert got[3] == "Story 3 words 3"
    assert got[90] == "Site name slogan Story 90 words 90 Terms apply"
    copies = [(i, "http://one.example/x", body % (1, 1)) for i in range(6)]
    assert {r.text for r in html.extract(spark.createDataFrame(copies, "page_id long, url string, html string")).collect()} == {"Site name slogan Story 1 words 1 Terms apply"}


def test_pipeline_stages_take_odd_rows(spark, docs, odd, none, tmp_path_factory):
    base = tmp_path_factory.mktemp("stages")
    sf = "/root/testdata/sf0.001"
    for name, stage in cp.STAGES:
        for i, d in enumerate((docs, odd, none)):
            out = stage(spark, d, sf)
            out.write.parquet(f"{base}/{name}{i}")
            got = spark.read.parquet(f"{base}/{name}{i}")
            if name != cp.STAGES[-1][0]:
                assert set(got.columns) == set(d.columns)
            assert (got.count() == 0) == (i == 2)
