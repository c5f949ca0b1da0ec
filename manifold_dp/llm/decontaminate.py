"""Benchmark decontamination with spaced seeds.

Texts are lower-cased and cut into words of letters and digits. A seed is a fixed mask
laid over consecutive words; it hashes the selected ones and ignores the others, so a
substituted word at an ignored place does not hide a match. The masks below are such that
every stretch of ``SPAN`` words with at most ``ERRORS`` substitutions holds a seed free of
them. Test seeds and training seeds are joined on their hash; each hit aligns a document
and an item, and the words along that diagonal are compared: a window of ``SPAN`` words
with at most ``ERRORS`` differing words is an overlap. Items shorter than ``SPAN`` words
must match as a whole, with ``n * ERRORS // SPAN`` differing words at most; items shorter
than ``LEAST`` words, which any text may hold by chance, match where they are all words of
one or more whole lines of a document.

The join: items of ``ITEM_BYTES`` of text at most (so of a proven size) are sent to all
documents, which are read once and never shuffled. More items meet the documents by shuffle:
seeds of documents that pass a bit filter of the items' seeds are joined with those by
hash, the distinct diagonals go to their documents and items, and the words are compared
there. A seed that stands at many places of a document and an item makes a mark for each
diagonal, not a row for each pair of places.

Defined results: null or empty texts have no words and match nothing; a null ``item_id``
or ``doc_id`` stays null in the result; items of one id and different texts are items of
their own, equal item rows count once; of equal documents each has its result; other columns
pass through ``clean`` untouched.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import words as W
from .common import table

SPAN, ERRORS = 13, 2
#: 1 selects a word, 0 ignores it.
MASKS = ("110101111", "11110010011", "11101111")
#: Items of fewer words match whole lines only.
LEAST = 5
ITEM_BYTES = 8 << 20
_FILTER_BITS = 23
#: Pairs of places that are laid out together, and of one seed from which diagonals are marked instead.
PAIRS_AT_ONCE, MANY = 1 << 21, 1 << 14

SEPARATORS = np.ones(256, bool)
SEPARATORS[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False
PAIRS = "doc_id long, item_id long, item_words long, matched long, overlap long, doc_from long"


def _words(texts: pa.Array) -> Iterator[tuple[int, int, W.Words]]:
    for i, j, data, bounds in W.chunks(pa.compute.utf8_lower(texts.fill_null(""))):
        yield i, j, W.Words(data, bounds, SEPARATORS)


def _seeds(w: W.Words, offsets: np.ndarray, number: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of a mask at every place where it fits in one text, and the places."""
    n = len(w.hash) - int(offsets[-1])
    if n <= 0:
        return np.empty(0, W.U64), np.empty(0, np.int64)
    at = np.flatnonzero(w.text[:n] == w.text[int(offsets[-1]) :])
    h = np.full(len(at), number + 1, W.U64)
    for o in offsets.tolist():
        h = h * W.U64(0x9E3779B97F4A7C15) + w.hash[at + o]
    return W.mix(h), at


def _masks(lengths: set[int]) -> list[tuple[int, np.ndarray, int]]:
    """``(number, places, words of an item)``: the masks, and for each shorter length that occurs a stretch that one error cannot hit twice, or all of it."""
    long = [(i, np.flatnonzero([c == "1" for c in m]), SPAN) for i, m in enumerate(MASKS)]
    return long + [(SPAN + n, np.arange(n if n < LEAST else n // 2), n) for n in sorted(lengths) if n < SPAN]


def _line_edges(w: W.Words) -> np.ndarray:
    """Whether a line of words begins at each word, and at the end of all words."""
    line = np.r_[0, np.cumsum(w.data == 10)]
    edge = np.ones(len(w.hash) + 1, bool)
    if len(w.hash):
        edge[1:-1] = (line[w.start[1:]] != line[w.end[:-1]]) | (w.text[1:] != w.text[:-1])
    return edge


def _best(doc: np.ndarray, item: np.ndarray, shifts: list[int], edge: np.ndarray) -> tuple[int, int, int] | None:
    """(matched words, words of the overlap, first word in the document) of the best diagonal; ``edge``: line edges of the document."""
    n = len(item)
    span, allowed = min(SPAN, n), ERRORS if n >= SPAN else n * ERRORS // SPAN
    best = (0, 0, 0)
    for shift in shifts:
        lo, hi = max(0, -shift), min(n, len(doc) - shift)
        if hi - lo < span or n < LEAST and not (edge[shift] and edge[shift + n]):
            continue
        same = doc[lo + shift : hi + shift] == item[lo:hi]
        run = np.r_[0, np.cumsum(same)]
        good = np.flatnonzero(run[span:] - run[:-span] >= span - allowed)
        if not len(good):
            continue
        cover = np.zeros(len(same) + 1, np.int32)
        np.add.at(cover, good, 1)
        np.add.at(cover, good + span, -1)
        inside = np.cumsum(cover[:-1]) > 0
        best = max(best, (int((same & inside).sum()), int(inside.sum()), int(lo + shift + good[0])))
    return best if best[1] else None


class Seeds:
    """Seeds of a block of items, for lookups by sorted hash behind a bit filter."""

    def __init__(self, ids: list, texts: list[str]):
        self.ids = ids
        parts = list(_words(pa.array(texts, pa.string())))
        self.hash = np.concatenate([w.hash for _, _, w in parts]) if parts else np.empty(0, W.U64)
        sizes = np.concatenate([np.diff(w.first) for _, _, w in parts]) if parts else np.empty(0, np.int64)
        self.first = np.r_[0, np.cumsum(sizes)]
        self.lengths = set(sizes.tolist()) - {0}
        self.masks = _masks(self.lengths)
        seeds, place = [np.empty(0, W.U64)], [np.empty(0, np.int64)]
        base = 0
        for _, _, w in parts:
            own = np.diff(w.first)
            for number, m, length in self.masks:
                h, at = _seeds(w, m, number)
                use = own[w.text[at]] >= SPAN if length == SPAN else own[w.text[at]] == length
                seeds.append(h[use])
                place.append(at[use] + base)
            base += len(w.hash)
        self.seed, self.place = np.concatenate(seeds), np.concatenate(place)
        order = np.argsort(self.seed, kind="stable")
        self.seed, self.place = self.seed[order], self.place[order]
        self.filter = np.zeros(1 << _FILTER_BITS, bool)
        self.filter[(self.seed >> W.U64(64 - _FILTER_BITS)).astype(np.int64)] = True

    def _diagonals(self, w: W.Words) -> dict[tuple[int, int], set[int]]:
        """Distinct (first place in the text less place in the item) by text and item."""
        out: dict[tuple[int, int], set[int]] = {}
        for number, m, _ in self.masks:
            h, at = _seeds(w, m, number)
            some = np.flatnonzero(self.filter[(h >> W.U64(64 - _FILTER_BITS)).astype(np.int64)])
            h, at = h[some], at[some]
            lo, hi = np.searchsorted(self.seed, h, "left"), np.searchsorted(self.seed, h, "right")
            found = hi > lo
            at, lo, n = at[found], lo[found], (hi - lo)[found]
            if not len(at):
                continue
            text = w.text[at]
            order = np.lexsort((at, lo, text))
            at, lo, n, text = at[order], lo[order], n[order], text[order]
            cut = np.flatnonzero((lo[1:] != lo[:-1]) | (text[1:] != text[:-1])) + 1
            begin, end = np.r_[0, cut], np.r_[cut, len(at)]
            often = (end - begin) * n[begin] > MANY
            for b, e in zip(begin[often].tolist(), end[often].tolist(), strict=True):
                self._mark(out, w, int(text[b]), at[b:e], self.place[lo[b] : lo[b] + n[b]])
            rest = ~np.repeat(often, end - begin)
            at, lo, n, text = at[rest], lo[rest], n[rest], text[rest]
            total = np.cumsum(n)
            cuts = np.searchsorted(total, np.arange(PAIRS_AT_ONCE, total[-1] if len(total) else 0, PAIRS_AT_ONCE))
            for x in np.split(np.arange(len(at)), np.unique(cuts)):
                if len(x):
                    each = n[x]
                    place = self.place[np.repeat(lo[x] - np.r_[0, np.cumsum(each)[:-1]], each) + np.arange(each.sum())]
                    item = np.searchsorted(self.first, place, "right") - 1
                    t = np.repeat(text[x], each)
                    shift = np.repeat(at[x], each) - w.first[t] - place + self.first[item]
                    for t_, i, s in np.unique(np.stack([t, item, shift], 1), axis=0).tolist():
                        out.setdefault((t_, i), set()).add(s)
        return out

    def _mark(self, out: dict, w: W.Words, text: int, at: np.ndarray, place: np.ndarray) -> None:
        """Diagonals of one seed at many places, by marks."""
        place = np.sort(place)
        item = np.searchsorted(self.first, place, "right") - 1
        at = at - w.first[text]
        for i in np.unique(item).tolist():
            p = place[item == i] - self.first[i]
            size = int(self.first[i + 1] - self.first[i])
            mark = np.zeros(int(w.first[text + 1] - w.first[text]) + size + 1, bool)
            few, many = (p, at) if len(p) <= len(at) else (at, p)
            for x in few.tolist():
                mark[(many - x if few is p else x - many) + size] = True
            out.setdefault((text, i), set()).update((np.flatnonzero(mark) - size).tolist())

    def overlaps(self, w: W.Words) -> list[tuple[int, int, int, int, int, int]]:
        """(text, item, words of the item, matched words, words of the overlap, first word in the text)."""
        if not len(self.seed):
            return []
        edge = _line_edges(w) if min(self.lengths) < LEAST else np.ones(len(w.hash) + 1, bool)
        rows = []
        for (t, i), shifts in sorted(self._diagonals(w).items()):
            a, b = int(w.first[t]), int(w.first[t + 1])
            item = self.hash[self.first[i] : self.first[i + 1]]
            if best := _best(w.hash[a:b], item, sorted(shifts), edge[a : b + 1]):
                rows.append((t, i, len(item), *best))
        return rows


def _known(items: DataFrame) -> DataFrame:
    """Items that have words, each once."""
    return items.where(F.length("text") > 0).select(F.col("item_id").cast("long").alias("item_id"), "text").distinct()


def sent(items: DataFrame) -> Seeds | None:
    """The seeds of all items if their texts are of a size to be sent to all tasks."""
    known = _known(items)
    if (known.agg(F.sum(F.octet_length("text"))).first()[0] or 0) > ITEM_BYTES:
        return None
    rows = known.orderBy("item_id", "text").collect()
    return Seeds([r.item_id for r in rows], [r.text for r in rows])


def _finder(seeds):
    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = seeds.value
        for b in batches:
            ids = b.column(0)
            rows: list[list] = [[], [], [], [], [], []]
            for i, _, w in _words(b.column(1)):
                for t, item, *rest in s.overlaps(w):
                    for c, x in zip(rows, (ids[i + t].as_py(), s.ids[item], *rest), strict=True):
                        c.append(x)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in rows], ["doc_id", "item_id", "item_words", "matched", "overlap", "doc_from"])

    return find


def _cleaner(seeds, text: int):
    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = np.ones(b.num_rows, bool)
            for i, _, w in _words(b.column(text)):
                ok[[i + row[0] for row in seeds.value.overlaps(w)]] = False
            yield b.filter(pa.array(ok))

    return keep


def _item_seeds(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        s = Seeds(b.column(0).to_pylist(), b.column(1).to_pylist())
        item = np.searchsorted(s.first, s.place, "right") - 1
        yield pa.RecordBatch.from_arrays([pa.array(s.seed.view(np.int64)), pa.array(np.array(s.ids, np.int64)[item]), pa.array((s.place - s.first[item]).astype(np.int64))], ["h", "item", "place"])


def _doc_seeds(masks, bits):
    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            keys = b.column(0).to_numpy()
            for i, _, w in _words(b.column(1)):
                for number, m, _ in masks:
                    h, at = _seeds(w, m, number)
                    some = np.flatnonzero(bits.value[(h >> W.U64(64 - _FILTER_BITS)).astype(np.int64)])
                    t = w.text[at[some]]
                    yield pa.RecordBatch.from_arrays([pa.array(h[some].view(np.int64)), pa.array(keys[i + t]), pa.array(at[some] - w.first[t])], ["h", "doc", "at"])

    return emit


def _verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows: list[list] = [[] for _ in range(6)]
        for key, item_id, text, item, shifts in zip(*(b.column(c).to_pylist() for c in range(5)), strict=True):
            (_, _, d), (_, _, i) = (next(iter(_words(pa.array([x])))) for x in (text, item))
            if best := _best(d.hash, i.hash, sorted(shifts), _line_edges(d)):
                for c, x in zip(rows, (key, item_id, len(i.hash), *best), strict=True):
                    c.append(x)
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in rows], ["doc", *PAIRS.replace(" long", "").split(", ")[1:]])


def _doc() -> Column:
    return F.xxhash64("doc_id", "text")


def _joined(docs: DataFrame, items: DataFrame) -> DataFrame:
    """``overlaps`` by shuffle, ``(doc, item_id, ...)``; ``doc``: a hash of each distinct document."""
    spark = docs.sparkSession
    known = _known(items).withColumn("item", F.xxhash64("item_id", "text"))
    seeds = known.select("item", "text").mapInArrow(_item_seeds, "h long, item long, place long")
    prefix = F.shiftrightunsigned("h", 64 - _FILTER_BITS)
    marked = np.zeros(1 << _FILTER_BITS, bool)
    marked[[r.p for r in seeds.select(prefix.cast("int").alias("p")).distinct().collect()]] = True  # 2^23 numbers at most
    own = F.filter(F.split(F.lower("text"), "[^a-z0-9\\x{80}-\\x{10FFFF}]+"), lambda x: x != "")
    lengths = {r.n for r in known.select(F.size(own).alias("n")).where(F.col("n").between(1, SPAN - 1)).distinct().collect()}
    each = docs.where(F.length("text") > 0).select(_doc().alias("doc"), "text")
    found = each.mapInArrow(_doc_seeds(_masks(lengths), spark.sparkContext.broadcast(marked)), "h long, doc long, at long")
    lines = found.join(seeds, "h").select("doc", "item", (F.col("at") - F.col("place")).alias("shift")).distinct()
    hits = lines.groupBy("doc", "item").agg(F.collect_list("shift").alias("shifts"))
    texts = hits.join(each.dropDuplicates(["doc"]), "doc").join(known.withColumnRenamed("text", "_item"), "item")
    return texts.select("doc", "item_id", "text", "_item", "shifts").mapInArrow(_verify, PAIRS.replace("doc_id", "doc"))


def overlaps(docs: DataFrame, items: DataFrame) -> DataFrame:
    """A row for each document and item that overlap: the best diagonal of theirs."""
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if (seeds := sent(items)) is not None:
        return ids.mapInArrow(_finder(docs.sparkSession.sparkContext.broadcast(seeds)), PAIRS)
    return ids.select("doc_id", _doc().alias("doc")).join(_joined(ids, items), "doc").select(*PAIRS.replace(" long", "").split(", "))


def clean(docs: DataFrame, items: DataFrame) -> DataFrame:
    """``docs`` without those that overlap any item."""
    if (seeds := sent(items)) is not None:
        return docs.mapInArrow(_cleaner(docs.sparkSession.sparkContext.broadcast(seeds), docs.columns.index("text")), docs.schema)
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    key = F.xxhash64(F.col("doc_id").cast("long"), "text")
    return docs.withColumn("_doc", key).join(_joined(ids, items).select(F.col("doc").alias("_doc")).distinct(), "_doc", "left_anti").select(*docs.columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contaminated documents with the items they overlap."""
    return overlaps(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
