"""The operators and the pipeline against brute force, exact round trips and held-out accuracy."""

import collections
import hashlib
import html as stdhtml
import re

import duckdb
import numpy as np
import pytest

import corpus_pipeline as cp
from manifold_dp.llm import chat, decontaminate, html, jaccard, linededup, pieces, quality, queries, substring, tokencount
from manifold_dp.llm import words as W
from manifold_dp.llm.common import table

SF = "/root/testdata/sf0.001"
SPACE = re.compile(r"[^\x20\x09-\x0D]+")


def rows_of(name, cols, sf=SF):
    return duckdb.sql(f"SELECT {cols} FROM '{sf}/{name}.parquet' ORDER BY 1").fetchall()


@pytest.fixture(scope="module")
def texts():
    return rows_of("documents", "doc_id, text")


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_query_equals_sql(spark, name):
    c = duckdb.connect()
    for t in ("documents", "embeddings", "conversations", "benchmark"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = c.execute(queries.ORACLES[name]).df()
    got = queries.QUERIES[name](spark, SF).toPandas()
    key = lambda d: sorted(map(tuple, d[sorted(d.columns)].astype(str).values.tolist()))
    assert sorted(got.columns) == sorted(want.columns) and key(got) == key(want)


def brute_windows(texts, k=13):
    seen, out = set(), []
    for i, t in texts:
        w = SPACE.findall(t or "")
        gone, new = [False] * len(w), []
        for p in range(len(w) - k + 1):
            x = tuple(w[p : p + k])
            if x in seen:
                gone[p : p + k] = [True] * k
            new.append(x)
        seen.update(new)
        kept = " ".join(x for x, g in zip(w, gone, strict=True) if not g)
        out.append((i, len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out


@pytest.mark.parametrize("kw", [{}, {"batches": 4, "max_runs": 1}, {"bits": 12}, {"lanes": 2}])
def test_substring(spark, texts, kw):
    """Compaction, colliding hashes and two lanes give what comparing all windows gives."""
    docs = table(spark, SF, "documents").select("doc_id", "text")
    got = substring.dedup(docs, want_text=False, **kw).select("doc_id", "n_words", "n_removed", "kept_sha256")
    assert sorted(map(tuple, got.collect())) == brute_windows(texts)


def shingles(text, k=5):
    w = SPACE.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return frozenset(tuple(w[p : p + k]) for p in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])


def brute_classes(texts, percent=80):
    sets = {i: shingles(t) for i, t in texts}
    root = {i: i for i in sets}

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    by = collections.defaultdict(list)
    for i, x in sets.items():
        both = collections.Counter(j for g in x for j in by[g])
        for j, n in both.items():
            if 100 * n >= percent * (len(x) + len(sets[j]) - n):
                a, b = top(i), top(j)
                root[max(a, b)] = min(a, b)
        for g in x:
            by[g].append(i)
    return sorted((i, len(x), top(i)) for i, x in sets.items())


@pytest.mark.parametrize(("limits", "percent"), [(jaccard.Limits(), 80), (jaccard.Limits(2, 2, 6, 4), 80), (jaccard.Limits(3, 4, 48, 8), 50)])
def test_jaccard(spark, texts, limits, percent):
    """Hot groups, combinations and blocks are forced by small limits."""
    docs = table(spark, SF, "documents").select("doc_id", "text")
    assert sorted(map(tuple, jaccard.classes(docs, percent=percent, limits=limits).collect())) == brute_classes(texts, percent)


def norm(t):
    return re.findall(r"[a-z0-9\x80-\U0010ffff]+", (t or "").lower())


def brute_overlaps(texts, items):
    want = set()
    for i, x in items.items():
        n = min(13, len(x))
        allowed = 2 if len(x) >= 13 else len(x) * 2 // 13
        by_word = collections.defaultdict(set)  # one of an overlap's first ``allowed + 1`` words is right
        for a in range(len(x) - n + 1):
            for o in range(min(allowed + 1, n)):
                by_word[o, x[a + o]].add(a)
        for d, t in texts:
            w = norm(t)
            starts = range(len(w) - n + 1)
            if n < 5:
                lines = [norm(y) for y in (t or "").split("\n")]
                edges = {0}
                for y in lines:
                    edges.add(max(edges) + len(y))
                starts = [p for p in starts if p in edges and p + n in edges]
            if n and any(sum(u != v for u, v in zip(w[p : p + n], x[a : a + n], strict=True)) <= allowed for p in starts for o in range(min(allowed + 1, n)) for a in by_word[o, w[p + o]]):
                want.add((d, i))
    return want


def test_decontaminate(spark, texts):
    items = {i: norm(t) for i, t in rows_of("benchmark", "item_id, text")}
    got = {(r.doc_id, r.item_id) for r in decontaminate.query(spark, SF).collect()}
    assert got == brute_overlaps(texts, items) and got


def test_decontaminate_by_shuffle_equals_broadcast(spark, texts, monkeypatch):
    """Beyond the size that may be sent, seeds meet by a shuffle join; equal rows and short items too."""
    docs = table(spark, SF, "documents").select("doc_id", "text")
    docs = docs.unionByName(docs.where("doc_id % 50 = 0"))
    short = spark.createDataFrame([(900, "ok then"), (901, "one two three four five six"), (900, "another text of the same id"), (None, "null id but a text of six")], "item_id long, text string")
    more = spark.createDataFrame([(700, "intro\nOk, then!\nrest"), (701, "ok then again"), (702, "say one two three four five six"), (703, "another text of the same id"), (None, "here null id but a text of six")], "doc_id long, text string")
    items, docs = table(spark, SF, "benchmark").unionByName(short), docs.unionByName(more)
    order = lambda df: sorted(map(repr, map(tuple, df.collect())))
    found, kept = order(decontaminate.overlaps(docs, items)), order(decontaminate.clean(docs, items))
    assert "(700, 900, 2, 2, 2, 1)" in found and not any(r.startswith("(701") for r in found)
    monkeypatch.setattr(decontaminate, "ITEM_BYTES", 0)
    assert order(decontaminate.overlaps(docs, items)) == found
    assert order(decontaminate.clean(docs, items)) == kept


def test_decontaminate_of_repeated_words_is_bounded():
    """A seed at 20,000 places of a text and 1,000 of an item makes marks, not pairs."""
    import resource

    s = decontaminate.Seeds([1, 2], [" ".join(["again"] * 1000), " ".join(["again"] * 20 + ["other"] * 5)])
    before = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
    ((_, _, w),) = decontaminate._words(__import__("pyarrow").array([" ".join(["again"] * 20_000)]))
    got = s.overlaps(w)
    assert [(r[1], r[2], r[3], r[4]) for r in got] == [(0, 1000, 1000, 1000), (1, 25, 20, 22)]
    assert resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before < 400_000  # KB


def test_token_counts(spark, texts):
    count = tokencount.counter()
    for r in tokencount.query(spark, SF).collect():
        t = dict(texts)[r.doc_id] or ""
        n = len(t)
        assert r.n_tokens == count(t)
        for p, d, s in ((n // 3, 12, " revised passage, 2nd draft"), (n // 2, n // 50, ""), (n + 100, 0, "\nEnd of revision.")):
            t = t[:p] + s + t[p + d :]
        assert (r.n_tokens_edited, r.n_chars_edited) == (count(t), len(t))


def test_token_tree_follows_any_edit():
    import random

    rng = random.Random(2)
    count = tokencount.counter()
    text = " ".join(rng.choice(["alpha", "b", "don't", "12", "  ", "\n", "é", "x,y"]) for _ in range(400))
    tree = tokencount.Tree.of(text, count, 32)
    for _ in range(200):
        p, d = rng.randrange(len(text) + 1), rng.choice([0, 1, 2, 40])
        s = rng.choice(["", " ", "z", " new words here", "\n\n", "'s"])
        want = text[:p] + s + text[p + d :]
        text, _ = tree.edit(text, p, d, s, count, 32)
        assert text == want and tree.total == count(text) and tree.length == len(text)


def test_apply_edits(spark):
    docs = spark.createDataFrame([(1, "one two three " * 50), (2, None), (3, "same")], "doc_id long, text string")
    edits = spark.createDataFrame([(1, 1, 0, 4, None), (1, 0, 4, 0, "and "), (2, 0, 5, 5, "new text"), (9, 0, 0, 0, "x")], "doc_id long, seq long, pos long, deleted long, inserted string")
    got = {r.doc_id: r for r in tokencount.apply_edits(docs, tokencount.trees(docs), edits).collect()}
    assert set(got) == {1, 2} and got[2].text == "new text" and got[1].text.startswith("and two three one")
    assert all(r.n_tokens == tokencount.counter()(r.text) for r in got.values())


def test_pieces_equal_the_library(texts):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=pieces.MODEL)
    p = pieces.pieces()
    some = [t for _, t in texts if t][:80] + ["", " ", "a  b\n c", "x" * 200 + "   " * 30]
    ids, count = pieces.encode_texts(p, some, np.arange(len(some)))
    cut = np.r_[0, np.cumsum(count)]
    assert all(ids[a:b].tolist() == sp.encode(t) for a, b, t in zip(cut[:-1], cut[1:], some, strict=True))
    out, n = pieces.encode_texts(p, some, np.arange(len(some)), 0.2)
    data, end = pieces.decode_ids(p, out, n)
    assert [data.tobytes()[a:b].decode() for a, b in zip(end[:-1], end[1:], strict=True)] == some
    assert len(out) > len(ids)


def test_agenda_equals_rounds():
    p = pieces.pieces()
    for k, word in enumerate(["▁internationalisation", "▁the", "▁éclair", "▁aaaaaaaaaaaaaaaa"]):
        s = p.of_char[[ord(c) for c in word]]
        for rate in (0.0, 0.3):
            a = pieces._rounds(p, s[None, :].astype(np.int32), np.array([k], W.U64), rate)[0]
            assert a[a >= 0].tolist() == pieces._agenda(p, s.tolist(), k, rate)


def test_token_edits_touch_only_their_paths(monkeypatch):
    """Edits that change the number of leaves add up a few sums, not the tree."""
    count = tokencount.counter()
    text = " ".join(f"word{i}" for i in range(20_000))
    tree = tokencount.Tree.of(text, count)
    added = []
    add_up = tokencount.Tree._add_up
    monkeypatch.setattr(tokencount.Tree, "_add_up", lambda self, i: added.append(i) or add_up(self, i))
    text, _ = tree.edit(text, 50_000, 0, "new words " * 200, count)
    text, _ = tree.edit(text, 90_000, 3000, "", count)
    assert len(added) < 6 * tree.width.bit_length() and tree.width > 256
    assert (tree.total, tree.length) == (count(text), len(text)) and sum(tree.chars) == len(text)


def test_measures_equal_plain_compression():
    """Block-wise sizes with each dictionary, normalised by the text's size."""
    import zstandard

    good, bad = (("plain words of a calm text " + str(i)).encode() for i in range(2)), (b"BUY NOW $$$ " * 9 for _ in range(2))
    model = quality.Model(b"".join(good), b"".join(bad), np.zeros(2), np.ones(2), np.zeros(3), 0.5)
    for text in (b"", b"plain words of a calm text", b"BUY NOW $$$ cheap " * 400, b"x" * 5000):
        size = []
        for d in (model.good, model.bad):
            z = zstandard.ZstdCompressor(level=quality.LEVEL, dict_data=zstandard.ZstdCompressionDict(d), write_content_size=False)
            size.append(sum(len(z.compress(text[i : i + 2048])) for i in range(0, max(1, len(text)), 2048)))
        n = max(1, len(text))
        assert quality._measures(text, *quality._packers(model)) == pytest.approx([(size[1] - size[0]) / n, min(2.0, size[0] / n)])


def test_the_difference_ranks_by_itself(spark):
    """Ablation: without the ratio the compressed-size difference still tells good from bad."""
    docs = table(spark, "/root/testdata/sf0.1", "documents").select("doc_id", "text")
    model = quality.fitted(spark, docs, "/root/testdata/sf0.1")
    known = dict(rows_of("labels", "doc_id, quality", "/root/testdata/sf0.1"))
    held = docs.where(quality.held_out())
    got = held.mapInArrow(quality._measurer(model, ["doc_id"], "text", True), "doc_id long, diff double, ratio double")
    rows = [(r["diff"], known[r.doc_id]) for r in got.collect() if known.get(r.doc_id) in (0, 1)]
    score, y = np.array([r[0] for r in rows]), np.array([r[1] for r in rows])
    auc = (score[y == 1][:, None] > score[y == 0][None, :]).mean() + 0.5 * (score[y == 1][:, None] == score[y == 0][None, :]).mean()
    assert auc > 0.97


def test_quality_on_held_out_labels(spark):
    sf = "/root/testdata/sf0.1"
    known = dict(rows_of("labels", "doc_id, quality", sf))
    rows = [(r.predicted, known[r.doc_id]) for r in quality.query(spark, sf).collect() if r.held_out and r.doc_id in known]
    assert np.mean([p == y for p, y in rows]) > 0.95
    assert np.mean([p for p, y in rows if y == 1]) > 0.98
    assert np.mean([p for p, y in rows if y == 0]) < 0.25


def test_page_text(spark):
    def reference(page):
        m = re.search(r"<article>(.*?)(</article>|\Z)", page or "", re.S)
        x = re.sub(r"</?b>", "", re.sub(r"<[^>]*\Z", "", m[1])) if m else ""
        return " ".join(stdhtml.unescape(re.sub(r"<[^>]*>", " ", x)).split())

    want = {i: reference(h) for i, h in rows_of("pages", "page_id, html")}
    assert {r.page_id: r.text for r in html.query(spark, SF).collect()} == want


SOUP = """<html><body><div>Daily %s site</div><div><a href=x>One</a> <a href=y>Two</a></div><div><h1>Story %d</h1><p>%s</p><div>Share this story</div></div><div>Printed by hand on page %d of many</div></body></html>"""


def soup_pages(n, hosts=("a.example", "b.example")):
    """Pages without article or telling names: only the host's other pages show what is a template."""
    text = lambda h, i: " ".join(f"w{h}{i}x{j}" for j in range(60))
    return [(1000 * k + i, f"http://{h}/{i}", SOUP % (h, i, text(k, i), i)) for k, h in enumerate(hosts) for i in range(n)]


def test_page_text_is_decided_by_host_counts(spark):
    pages = soup_pages(12) + [(9000, "http://lonely.example/1", SOUP % ("lonely.example", 1, "alone here", 1))]
    df = spark.createDataFrame(pages, "page_id long, url string, html string")
    got = {r.page_id: r for r in html.extract(df).collect()}
    for i, _, page in pages[:-1]:
        want = re.search(r"<h1>(.*?)</h1><p>(.*?)</p>", page)
        assert got[i].text == f"{want[1]} {want[2]}" and got[i].n_template >= 3
    assert got[9000].text.startswith("Daily lonely.example site One Two Story 1 alone here")
    # ablation: with what the counts judged left in, the site's parts come back
    off = {r.page_id: r.text for r in html.extract(df, spared=True).collect()}
    assert all(off[i].startswith("Daily") and off[i].endswith("of many") for i, *_ in pages)


def test_templates_carry_the_given_pages(spark):
    """Ablation on the given pages: hosts of several pages lose their boilerplate to counts, and without them it stays."""
    pages = table(spark, "/root/testdata/sf0.01", "pages")
    on = {r.page_id: r for r in html.extract(pages).collect()}
    off = {r.page_id: r for r in html.extract(pages, spared=True).collect()}
    hosts = collections.Counter(re.sub(r"^https?://([^/]*).*", r"\1", r.url) for r in on.values())
    big = [i for i, r in on.items() if hosts[re.sub(r"^https?://([^/]*).*", r"\1", r.url)] >= 6]
    changed = [i for i in big if off[i].text != on[i].text]
    assert len(big) > 80 and len(changed) > 0.6 * len(big)
    assert sum(on[i].n_template for i in big) > sum(on[i].n_rule for i in big)


def test_page_reader_is_linear_in_nesting():
    import time

    for page in ("<div>" * 40_000, "<div>" * 20_000 + "</p>" * 20_000, "<div>" * 20_000 + "<li></li>" * 20_000):
        began = time.time()
        html.main_text(page)
        assert time.time() - began < 5


def test_chat_folds_a_real_log(spark):
    """The query's log has deltas, edits, regenerations and removals; it folds to the turns themselves."""
    turns = chat.with_odd_conversation(spark, table(spark, SF, "conversations"))
    log = chat.streamed_events(turns)
    assert {r.kind for r in log.select("kind").distinct().collect()} == {"message", "delta", "edit", "regenerate", "remove"}
    order = lambda df: sorted(map(tuple, df.select("conv_id", "turn", "role", "text").collect()))
    assert order(chat.fold(log)) == order(chat.fold(chat.events_of_turns(turns)))


def test_chat_folds_like_one_event_after_another(spark):
    import random

    rng = random.Random(6)
    rows, want = [], {}
    for turn in range(300):
        live, role, text = False, "", ""
        for seq in range(rng.randrange(1, 9)):
            kind, r, t = rng.choice(["message", "edit", "delta", "delta", "regenerate", "remove", "seen"]), rng.choice([None, "user", "bot"]), rng.choice([None, "", "a", "bc"])
            rows.append((1, turn, seq, kind, r, t))
            live, role = kind != "remove", r if r is not None else role
            text = (t or "") if kind in ("message", "edit") else text + (t or "") if kind == "delta" else "" if kind in ("regenerate", "remove") else text
        if live:
            want[turn] = (role, text)
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "conv_id long, turn long, seq long, kind string, role string, text string")
    assert {r.turn: (r.role, r.text) for r in chat.fold(df).collect()} == want


def test_chat_of_many_deltas_and_turns(spark):
    """Linear in deltas and turns: one turn of 20,000 deltas, one conversation of 20,000 turns."""
    import time

    from pyspark.sql import functions as F

    lit = lambda c, t="string": F.lit(c).cast(t)
    deltas = spark.range(20_000).select(lit(1, "long").alias("conv_id"), lit(0, "long").alias("turn"), F.col("id").alias("seq"), lit("delta").alias("kind"), lit("bot").alias("role"), lit("0123456789" * 5).alias("text"))
    turns = spark.range(20_000).select(lit(2, "long").alias("conv_id"), F.col("id").alias("turn"), lit(0, "long").alias("seq"), lit("message").alias("kind"), lit("assistant").alias("role"), lit("<hi>").alias("text"))
    began = time.time()
    got = {r.conv_id: r for r in chat.digest(chat.parse(chat.render(chat.fold(deltas.unionByName(turns))))).collect()}
    assert time.time() - began < 60
    assert got[2].n_turns == 20_000 and got[2].loss_chars == 80_000
    assert got[1].turns_sha256 == hashlib.sha256(("bot\n" + "0123456789" * 100_000 + "\n").encode()).hexdigest()


def test_chat_reads_itself_back(spark):
    turns = chat.with_odd_conversation(spark, table(spark, SF, "conversations"))
    got = {r.conv_id: [tuple(t) for t in r.turns] for r in chat.parse(chat.render(chat.fold(chat.events_of_turns(turns)))).collect()}
    want = collections.defaultdict(list)
    for c, _, r, t in sorted(map(tuple, turns.select("conv_id", "turn", "role", "text").collect())):
        want[c].append((r, t or ""))
    assert got == want


def test_words_of_any_text():
    import pyarrow as pa

    texts = ["", " a  b ", "x\ty\nz", None, "é 漢字", "end", "\x0b", "A b"]
    (_, _, data, bounds), = W.chunks(pa.array(texts))
    w = W.Words(data, bounds)
    want = [SPACE.findall(t or "") for t in texts]
    assert [w.bytes_of(i, i + 1).decode() for i in range(len(w.hash))] == [x for t in want for x in t]
    assert np.diff(w.first).tolist() == [len(t) for t in want]
    values = np.sort(w.hash)
    assert (W.unpack_sorted(W.pack_sorted(values)) == values).all()
    assert (W.unpack(W.pack(np.array([-5, 0, 7]))) == [-5, 0, 7]).all()


def test_pipeline(spark):
    """Stage by stage against brute force; run() gives what the stages give."""
    base = table(spark, SF, "documents")
    docs = base
    for name, stage in cp.STAGES:
        before = sorted(tuple(r) for r in docs.select("doc_id", "text").collect())
        docs = spark.createDataFrame(stage(spark, docs, SF).collect(), stage(spark, docs, SF).schema)
        after = {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}
        if name == "line_dedup":
            seen: set = set()
            want = {}
            for i, t in before:
                rows = (t or "").split("\n")
                at = [p for p, x in enumerate(rows) if x.strip(" \t\r")]
                gone = set()
                for a in range(len(at) - 2):
                    key = tuple(rows[p] for p in at[a : a + 3])
                    if key in seen:
                        gone |= set(at[a : a + 3])
                    seen.add(key)
                left = "\n".join(x for p, x in enumerate(rows) if p not in gone)
                if not gone or left.strip(" \t\r\n"):
                    want[i] = left if gone else t
            assert after == want
        elif name == "ngram_jaccard_join":
            assert set(after) == {i for i, _, c in brute_classes(before) if i == c}
        elif name == "sentencepiece":
            back = pieces.decode(docs)
            assert back.where("decoded <> text").count() == 0
            assert after == dict(before)
        else:
            assert set(after.items()) <= set(before)
    assert {r.doc_id: r.text for r in cp.run(spark, SF).collect()} == after


def test_line_windows_elect_like_brute_force(spark):
    df = spark.createDataFrame([(1, "a\nb\n\nc\nd\na\nb\nc"), (2, "x\na\nb\nc\ny")], "doc_id long, text string")
    got = {r.doc_id: (r.text, r.n_removed) for r in linededup.clean(df).collect()}
    assert got == {1: ("a\nb\n\nc\nd", 3), 2: ("x\ny", 3)}


def test_jaccard_marks_the_least_copy(spark):
    """Copies with larger ids are read first; what two sets share is frequent."""
    common = " ".join(f"c{i}" for i in range(60))
    some = [(101, common + " a")]
    some += [(i, common + " " + " ".join(f"u{i}x{j}" for j in range(200))) for i in range(90, 60, -1)]
    some += [(2, common + " b"), (1, common + " a")]
    docs = spark.createDataFrame(some, "doc_id long, text string").coalesce(1)
    assert sorted(map(tuple, jaccard.classes(docs).collect())) == brute_classes(some[1:]) + [(101, 57, 1)]


def test_jaccard_links_all_versions_of_a_document(spark):
    """Three texts of one id, each of them a copy of another document."""
    text = {i: " ".join(f"w{i}x{j}" for j in range(30)) for i in range(1, 4)}
    docs = spark.createDataFrame([*text.items(), *((9, t) for t in text.values())], "doc_id long, text string")
    assert {r.component_id for r in jaccard.classes(docs).collect()} == {1}


def test_pieces_drop_by_occurrence():
    """One word many times: shared rows equal each occurrence by itself, and every merge is dropped at about the rate."""
    p = pieces.pieces()
    n = 4000
    out, count = pieces.encode_texts(p, [" ".join(["segmentation"] * n)] * 2, np.arange(2), 0.1)
    at = np.r_[0, np.cumsum(np.isin(out, [i for i in range(p.size) if bytes(p.text[p.text_at[i] : p.text_at[i] + p.text_len[i]])[:1] == b" "]))]
    words = collections.Counter(tuple(out[np.searchsorted(at, k, "right") - 1 : np.searchsorted(at, k + 1, "right") - 1].tolist()) for k in range(2 * n))
    assert len(words) > 8
    assert sum(words.values()) == 2 * n
    word = np.array([p.of_char[pieces.MARK], *(p.of_char[ord(c)] for c in "segmentation")], np.int32)
    key = W.mix(np.arange(3000, dtype=W.U64))
    done, which = pieces._outcomes(p, word[None, :], np.zeros(len(key), int), key, 0.1)
    for x in range(0, len(key), 50):
        a = done[which[x]]
        assert a[a >= 0].tolist() == pieces._agenda(p, word.tolist(), int(key[x]), 0.1)
    whole = pieces._agenda(p, word.tolist(), 0, 0.0)
    share = np.mean([done[w][done[w] >= 0].tolist() == whole for w in which])
    assert 0.1 < share < 1 - 0.1 + 0.03


def test_pieces_with_dropout_equal_each_occurrence_by_itself(texts):
    """Brute force with full keys: every segment of every text by the agenda alone, keyed by seed, document and occurrence."""
    p = pieces.pieces()
    some = [t for _, t in texts if t and len(t) < 3000][:25] + ["aa aa aa  aa", "▁ x", "日本 é", "word " * 40]
    ids = np.arange(100, 100 + len(some))
    out, count = pieces.encode_texts(p, some, ids, 0.15, 77)
    cut = np.r_[0, np.cumsum(count)]
    step, mask = int(pieces._STEP), 2**64 - 1
    mix = lambda x: int(W.mix(np.array([x & mask], W.U64))[0])
    for k, t in enumerate(some):
        chars = [pieces.MARK] + [pieces.LITERAL if ord(c) == pieces.MARK else pieces.MARK if c == " " else ord(c) for c in t]
        segments, now = [], []
        for i, c in enumerate(chars):
            alone = p.of_char[c] < 0
            if now and (alone or p.of_char[chars[i - 1]] < 0 or c == pieces.MARK and chars[i - 1] != pieces.MARK):
                segments.append(now)
                now = []
            now.append(c)
        segments.append(now)
        want = []
        for nth, seg in enumerate(segments):
            if p.of_char[seg[0]] < 0:
                want += [int(p.byte[b]) for b in pieces._utf8(seg[0])]
                continue
            key = mix(mix(mix(int(ids[k]) + 77) + nth * step) ^ 77)
            want += pieces._agenda(p, [int(p.of_char[c]) for c in seg], key, 0.15)
        assert out[cut[k] : cut[k + 1]].tolist() == want


def test_scratch_belongs_to_its_maker(spark):
    """Two lazy results outlive each other; what an owned block made goes with it."""
    import pathlib

    from manifold_dp.llm.common import Scratch, shared_dir

    here = pathlib.Path(shared_dir(spark).removeprefix("file://"))
    pages = table(spark, SF, "pages")
    a, b = html.extract(pages), html.extract(pages.limit(20))
    docs = cp.keep_good(spark, table(spark, SF, "documents"), SF)
    assert a.count() == pages.count() and b.count() == 20 and docs.count() > 0
    before = {f.name for f in here.iterdir()}
    with Scratch.owned():
        assert html.extract(pages).count() == a.count()
        assert {f.name for f in here.iterdir()} > before
    assert {f.name for f in here.iterdir()} == before
    assert cp.run(spark, SF).count() > 0
    after = [f for f in here.iterdir() if f.name not in before]
    assert len(after) == 1 and len(list(after[0].iterdir())) == 1  # the last stage's table
    assert a.count() == pages.count()


def test_pipeline_keeps_texts_that_share_an_id(spark):
    """Different texts of one id are documents of their own; equal rows are one."""
    text = {k: " ".join(f"{k}{j}" for j in range(40)) for k in "abcd"}
    rows = [(5, text["a"], "en"), (5, text["b"], "en"), (5, text["b"], "de"), (7, text["b"] + " more", "en"), (8, text["c"], "en"), (None, text["c"], "en"), (9, text["d"], "en"), (9, text["d"], "en")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    want = [(5, text["a"], "en"), (5, text["b"], "de"), (8, text["c"], "en"), (9, text["d"], "en"), (None, text["c"], "en")]
    for n in (1, 5):
        got = [tuple(r) for r in cp.drop_near_copies(spark, docs.repartition(n), SF).collect()]
        assert sorted(got, key=repr) == sorted(want, key=repr)


def test_line_dedup_of_a_long_text_is_linear(spark):
    import time

    line = "\n".join(f"line {i}" for i in range(60_000))
    df = spark.createDataFrame([(1, line), (2, "head\n" + line + "\ntail")], "doc_id long, text string")
    began = time.time()
    got = {r.doc_id: (r.text, r.n_removed) for r in linededup.clean(df).collect()}
    assert got[2] == ("head\ntail", 60_000) and got[1] == (line, 0)
    assert time.time() - began < 60


def test_join_hot_equals_a_join(spark, monkeypatch):
    """Sent whole, or only its frequent keys."""
    from manifold_dp.llm import common

    left = spark.createDataFrame([(i % 7 if i % 2 else 3, i) for i in range(400)], "k long, v long")
    right = left.groupBy("k").count().where("k <> 5").withColumnRenamed("count", "n")
    want = sorted(map(tuple, left.where("k <> 5").collect()))
    for small, keys in ((1000, 2000), (0, 4), (0, 1)):
        monkeypatch.setattr(common, "SMALL", small)
        monkeypatch.setattr(common, "HOT_KEYS", keys)
        assert sorted(map(tuple, common.join_hot(left, right, ["k"], "n", 400).select("k", "v").collect())) == want
