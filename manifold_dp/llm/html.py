"""Main text of web pages by removing what recurs on a site.

A page is read once into a flat list of elements and texts (an own tolerant reader:
unclosed and stray tags, truncated pages, raw scripts). Two hashes of a block element's
subtree are made bottom-up: its *content* (tags, classes, normalised text) and its *slot*
(path, tag, class and the kinds of its block children, without text). Spark counts per
host on how many *different* articles' pages each stands, and what share of the page's
text it holds; copies of one article count once, so what recurs because a page was copied
is no template.

1. Host counts decide first. Contents on ``MIN_PAGES`` different pages that hold no more
   than half of a page's text are templates; so are slots on ``SLOT_SHARE`` of the host's
   different pages (``MIN_PAGES`` at least) that hold little text (``LITTLE``), even if
   their words change from page to page, on pages where it is known what holds the text:
   a marked article, or a slot that holds most of it. Nothing inside the innermost such
   slot is a template by its slot. Paragraphs,
   headings and list items of an article are text and never templates.
2. Rules decide what the counts leave open (hosts of few pages, rare parts): menus,
   headers, footers, asides, forms, hidden parts, elements whose class, id or role names an
   advert, notice, comment list and the like, and what lies outside of a marked article
   (``article`` or ``main``). Heads, scripts and styles are no text anywhere.

``n_template`` and ``n_rule`` tell how many subtrees each of the two took off a page.

Text: character references decoded, white space inside a block made one space, trimmed,
blocks in page order joined by one space. Inline elements do not part words.

Defined results: null html is an empty page; a null or odd url has the empty host; rows
of one ``page_id`` are handled each by its own html; other columns are ignored; an empty
table gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Collection, Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, join_hot, table

#: Different pages that make a template; share of a host's pages that a slot needs; shares of a page's text.
MIN_PAGES, SLOT_SHARE, LITTLE, MOST = 3, 0.5, 0.25, 0.5

# Names of HTML elements by kind, and words in class, id or role that name boilerplate.
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
RAW = set("script style textarea title xmp iframe noembed noframes".split())
INLINE = set("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
DROPPED = set("head script style noscript template iframe nav footer aside form button select option textarea input svg math canvas object embed audio video dialog menu title noembed noframes xmp map".split())
MAIN = {"article", "main"}
WHOLE = {"html", "body", "head"}
NO_TEXT = RAW | set("head noscript template svg math canvas object audio video map".split())
PROSE = set("p h1 h2 h3 h4 h5 h6 li blockquote pre dd dt td th figcaption".split())
CLOSES_P = set("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"tr", "td", "th"}, "tbody": {"thead", "tr", "td", "th"}, "tfoot": {"tbody", "tr", "td", "th"}}
WALLS = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "option": {"select"}, "thead": {"table"}, "tbody": {"table"}, "tfoot": {"table"}}
SAYS = set("ad adslot adunit ads advert adverts advertisement advertising adbox adsense sponsor sponsored promo promotion cookie cookies consent gdpr notice popup modal overlay newsletter subscribe signup share sharing social sidebar menu nav navbar navigation breadcrumb breadcrumbs comment comments disqus respond replies related recommended pagination pager login skip promoted outbrain taboola".split())
SAYS_OUTSIDE = SAYS | set("header footer banner masthead topbar bottom widget legal copyright search".split())
ROLES = set("navigation banner contentinfo complementary search alert alertdialog dialog form status menu menubar toolbar".split())

_TOKEN = re.compile(r"""<!--.*?(?:-->|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*"|'[^']*')*+)>|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>|</?[a-zA-Z][^>]*\Z""", re.S)
_ATTR = re.compile(r"""([^\s=/"'>]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
_DIGITS = re.compile(r"[0-9]+")
_WORD = re.compile(r"[a-z]+")
_HIDDEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)


class _Element:
    __slots__ = ("blocks", "class_", "drop", "hash", "kinds", "main", "named", "parent", "path", "prose", "size", "slot", "tag")

    def __init__(self, tag: str, parent: _Element | None, drop: bool = False, named: bool = False, class_: str = ""):
        self.tag, self.parent, self.class_ = tag, parent, class_
        self.drop, self.named = drop, named  # by what it is, by what it is called
        self.main = tag in MAIN or bool(parent and parent.main)
        self.prose = self.main and (tag in PROSE or bool(parent and parent.prose))
        self.hash: int | None = None
        self.slot: int | None = None
        self.size = 0  # characters of its text
        self.kinds: set[str] = set()  # of its block children
        self.path = _short(f"{parent.path}/{tag}.{class_}") if parent and tag not in INLINE else parent.path if parent else ""


def _number(s: str) -> int:
    return int.from_bytes(hashlib.blake2b(s.encode("utf-8", "surrogatepass"), digest_size=8).digest(), "big", signed=True)


def _short(s: str) -> str:
    return s if len(s) <= 64 else f"{_number(s):x}"


def _attributes(text: str) -> dict[str, str]:
    return {m[1].lower(): unescape(m[2] or m[3] or m[4] or "") for m in _ATTR.finditer(text)} if text else {}


def _dropped(tag: str, attr: dict[str, str], in_main: bool) -> bool:
    if tag in DROPPED or tag == "header" and not in_main:
        return True
    if not attr or tag in ("html", "body"):
        return False
    return "hidden" in attr or attr.get("aria-hidden") == "true" or attr.get("role", "").lower() in ROLES or bool(_HIDDEN.search(attr.get("style", "")))


def _named(tag: str, attr: dict[str, str], in_main: bool) -> bool:
    if not attr or tag in ("html", "body"):
        return False
    words = set(_WORD.findall(f"{attr.get('class', '')} {attr.get('id', '')}".lower()))
    return bool(words & (SAYS if in_main or tag in MAIN else SAYS_OUTSIDE))


def read(html: str) -> tuple[list[tuple], list[_Element], int]:
    """Items ``(element, text)`` in page order (text None: a block starts or ends), the block elements, and the characters of all text."""
    root = _Element("", None)
    article: _Element | None = None
    items: list[tuple] = []
    blocks: list[_Element] = []
    stack, content = [root], [[]]
    open_: dict[str, int] = {}  # tags on the stack

    def close() -> None:
        e, inner = stack.pop(), content.pop()
        open_[e.tag] -= 1
        digest = hashlib.blake2b("\x00".join([e.tag, *inner]).encode("utf-8", "surrogatepass"), digest_size=8).digest()
        content[-1].append(digest.hex())
        up = e.parent
        if e.tag not in RAW:
            up.size += e.size
        if e.tag in INLINE:
            up.kinds |= e.kinds
        else:
            e.hash = int.from_bytes(digest, "big", signed=True)
            kind = _short(f"{e.tag}.{e.class_}{sorted(e.kinds) if e.kinds else ''}")
            up.kinds.add(kind)
            if not e.main and e.tag not in PROSE and e.tag not in WHOLE:
                e.slot = _number(f"{up.path}>{kind}")
            items.append((stack[-1], None))

    def close_to(tag: str) -> None:
        while stack[-1].tag != tag:
            close()
        close()

    def said(text: str) -> None:
        if text:
            items.append((stack[-1], text))
            if not text.isspace():
                words = " ".join(text.split())
                content[-1].append(words)
                stack[-1].size += len(words)

    at = 0
    while m := _TOKEN.search(html, at):
        said(unescape(html[at : m.start()]))
        at = m.end()
        tag = (m[2] or m[5] or "").lower()
        if not tag:
            continue
        if m[1] or m[4]:
            if open_.get(tag):
                close_to(tag)
            continue
        if tag in CLOSES_P and open_.get("p"):
            close_to("p")
        if tag in ENDS and any(open_.get(t) for t in ENDS[tag]):
            for i in range(len(stack) - 1, 0, -1):
                if stack[i].tag in WALLS[tag]:
                    break
                if stack[i].tag in ENDS[tag]:
                    while len(stack) > i:
                        close()
        if tag == "br":
            items.append((stack[-1], " "))
            continue
        up = stack[-1]
        attr = _attributes(m[3] or m[6])
        e = _Element(tag, up, _dropped(tag, attr, up.main), _named(tag, attr, up.main), _DIGITS.sub("", attr.get("class", "")) if attr else "")
        if attr.get("role", "").lower() == "main":
            e.main = True
        if e.main and article is None:  # what holds the page's first article is not boilerplate, whatever its name
            article = e
            while e is not None:
                e.named = False
                e = e.parent
            e = article
        if tag not in INLINE:
            items.append((up, None))
        if tag in VOID:
            continue
        if tag not in INLINE:
            blocks.append(e)
        stack.append(e)
        open_[tag] = open_.get(tag, 0) + 1
        content.append([attr.get("class", "")])
        if tag in RAW:
            end = re.compile(rf"</{tag}\b[^>]*>?", re.I).search(html, at)
            at = end.end() if end else len(html)
            close()
    said(unescape(html[at:]))
    while len(stack) > 1:
        close()
    return items, blocks, root.size


def _candidate(e: _Element) -> bool:
    """May be a template by its content: neither part of an article's prose nor a container of the page or article."""
    return e.hash is not None and not e.prose and e.tag not in WHOLE and e.tag not in MAIN and e.tag not in NO_TEXT


def _judged(blocks: list[_Element], templates: Collection[int], contents: Collection[int]) -> set[_Element]:
    """The elements that host counts call templates."""
    if not templates:
        return set()
    inner = {e for e in blocks if e.slot in contents}
    for e in list(inner):  # the innermost content slots
        up = e.parent
        while up is not None and up not in inner:
            up = up.parent
        inner.discard(up)
    safe: dict[_Element | None, bool] = {None: False}
    for e in blocks:  # parents come first
        up = e.parent
        while up not in safe:
            up = up.parent
        safe[e] = safe[up] or e in inner
    sure = bool(inner) or any(e.main for e in blocks)  # it is known where the page's text is
    return {e for e in blocks if (sure and e.slot in templates and not safe[e]) or (e.hash in templates and _candidate(e))}


def _text(items: list[tuple], gone: set[_Element], spared: bool = False) -> tuple[str, int, int]:
    """The text without ``gone``, and how many subtrees counts and rules took off. ``spared``: what the counts judged stays."""
    state: dict[_Element, int] = {}  # 0: kept, 1: inside a template, 2: taken by a rule, 3: no text

    def state_of(e: _Element) -> int:
        path = []
        while e is not None and e not in state:
            path.append(e)
            e = e.parent
        s = 0 if e is None else state[e]
        for x in reversed(path):
            if not s:
                if x in gone:
                    s = 0 if spared else 1
                elif x.tag in NO_TEXT:
                    s = 3
                elif x.drop or x.named:
                    s = 2
            state[x] = s
        return s

    marked = any(t is not None and e.main and not state_of(e) for e, t in items)
    out: list[str] = []
    block: list[str] = []
    outside: set[_Element] = set()

    def beside(e: _Element) -> bool:
        """Outside of a marked article, and not spared."""
        if not marked or e.main:
            return False
        up = e if spared else None
        while up is not None and up not in gone:
            up = up.parent
        return up is None

    for e, text in [*items, (None, None)]:
        if text is None:
            if block and (s := " ".join("".join(block).split())):
                out.append(s)
            block = []
        elif not state_of(e):
            if beside(e):
                if not text.isspace():
                    outside.add(e)
            else:
                block.append(text)
    tops = [s for e, s in state.items() if s and not (e.parent is not None and state.get(e.parent))]
    return " ".join(out), sum(s == 1 for s in tops), sum(s == 2 for s in tops) + len(outside)


def main_text(html: str, templates: Collection[int] = (), contents: Collection[int] = (), spared: bool = False) -> str:
    """The text of a page, given hashes of its host's templates and of the slots that hold its content."""
    items, blocks, _ = read(html)
    return _text(items, _judged(blocks, templates, contents), spared=spared)[0]


_SUBTREES = "host long, page long, subtree long, slot boolean, share int, article long"
_KINDS = (pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.int32(), pa.int64())


def _hasher(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows: list[list] = [[] for _ in _KINDS]
        for host, page, html in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
            items, blocks, size = read(html or "")
            article, number = _number(_text(items, set())[0]), _number(host or "")
            held: dict[tuple[int, bool], int] = {}
            for e in filter(_candidate, blocks):
                held[e.hash, False] = held.get((e.hash, False), 0) + e.size
                if e.slot is not None:
                    held[e.slot, True] = held.get((e.slot, True), 0) + e.size
            for (h, slot), n in held.items():
                for col, x in zip(rows, (number, page, h, slot, min(1000, 1000 * n // max(1, size)), article), strict=True):
                    col.append(x)
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(rows, _KINDS, strict=True)], ["host", "page", "subtree", "slot", "share", "article"])


def _extractor(spared: bool):
    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = []
            for html, hits, contents in zip(*(b.column(i).to_pylist() for i in (2, 3, 4)), strict=True):
                items, blocks, _ = read(html or "")
                found.append(_text(items, _judged(blocks, set(hits or ()), set(contents or ())), spared=spared))
            text, templates, rules = zip(*found, strict=True) if found else ((), (), ())
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64()), pa.array(templates, pa.int64()), pa.array(rules, pa.int64())],
                ["page_id", "url", "text", "n_chars", "n_template", "n_rule"],
            )

    return extract


def with_keys(pages: DataFrame) -> DataFrame:
    host = F.regexp_extract(F.lower(F.coalesce("url", F.lit(""))), r"^[a-z][a-z0-9+.\-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)
    return pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", host.alias("host"), F.xxhash64("page_id", "url", "html").alias("page"))


def templates(pages: DataFrame, min_pages: int = MIN_PAGES) -> DataFrame:
    """``(page, hits, contents)``: hashes of the templates on each page that has any, and of its host's content slots."""
    scratch = Scratch(pages.sparkSession)
    found = scratch.keep(with_keys(pages).select("host", "page", "html").mapInArrow(_hasher, _SUBTREES), "subtrees")
    size = found.groupBy("host", "article").agg(F.lit(1).alias("x")).groupBy("host").agg(F.count(F.lit(1)).alias("of"))
    once = found.groupBy("host", "subtree", "slot", "article").agg(F.count(F.lit(1)).alias("rows"), F.max("share").alias("share"))
    seen = once.groupBy("host", "subtree", "slot").agg(F.count(F.lit(1)).alias("n"), F.sum("rows").alias("rows"), (F.avg("share") / 1000).alias("share")).where(F.col("n") >= min_pages)
    usual = F.col("slot") & (F.col("n") >= SLOT_SHARE * F.col("of"))
    content, template = usual & (F.col("share") > MOST), ~F.col("slot") & (F.col("share") <= MOST) | usual & (F.col("share") <= LITTLE)
    judged = seen.join(size, "host").where(content | template).select("host", "subtree", content.alias("content"), "rows")
    both = join_hot(found.select("host", "page", "subtree"), scratch.keep(judged, "judged"), ["host", "subtree"], "rows", found.count())
    hits = both.groupBy("page").agg(F.collect_set(F.when(~F.col("content"), F.col("subtree"))).alias("hits"), F.collect_set(F.when(F.col("content"), F.col("subtree"))).alias("contents"))
    hits = scratch.keep(hits.where(F.size("hits") > 0), "hits")
    scratch.drop_but(hits)
    return hits


def extract(pages: DataFrame, min_pages: int = MIN_PAGES, spared: bool = False) -> DataFrame:
    """``(page_id, url, text, n_chars, n_template, n_rule)`` of every page. ``spared`` leaves in what host counts judged, which shows their part."""
    hits = templates(pages, min_pages).withColumnRenamed("page", "_page")
    own = with_keys(pages)
    # a shuffle at every size: what a hit list weighs grows with the pages
    j = own.join(hits.hint("merge"), F.col("page") == F.col("_page"), "left").select("page_id", "url", "html", "hits", "contents")
    return j.mapInArrow(_extractor(spared), "page_id long, url string, text string, n_chars long, n_template long, n_rule long")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
