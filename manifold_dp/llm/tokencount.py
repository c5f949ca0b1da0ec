"""Edit-aware token counts with a segment tree per document.

A document's text is cut into leaves of some ``LEAF`` characters at places where the
tokenizer's pre-tokens always part (a single space between two word characters), so the
tokens of the text are the tokens of its leaves. A binary tree over the leaves sums their
characters and tokens. An edit ``(pos, deleted, inserted)`` descends to the leaves it
touches, takes a neighbour too where it touches the characters that made the boundary,
re-encodes that stretch alone and updates the sums above it.

The tree is kept as its leaves' sizes and counts (two integer arrays a document).

Defined results: null text counts as empty, with one leaf of no tokens; positions beyond
the text mean its end; edits apply in the order of ``seq``; a null ``inserted`` is empty;
an edit without document is ignored; repeated rows of one ``doc_id`` are each their own
document; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Callable, Iterator
from functools import cache

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import others, table

LEAF = 256
#: Fixed value: the pre-token pattern of the vocabulary.
PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
_SEAM = re.compile(r"(?<=\w) (?=\w)")
EDITS = "array<struct<seq:long,pos:long,deleted:long,inserted:string>>"


@cache
def counter(vocabulary: str = VOCABULARY) -> Callable[[str], int]:
    import tiktoken

    with open(vocabulary, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    code = tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
    return lambda text: len(code.encode_ordinary(text))


def cut(text: str, leaf: int = LEAF) -> list[str]:
    out, at = [], 0
    while m := _SEAM.search(text, at + leaf):
        out.append(text[at : m.start()])
        at = m.start()
    return [*out, text[at:]]


#: Leaves that one slot of a tree may hold before the tree is laid out anew.
CROWD = 32


class Tree:
    """Sums of characters and tokens over slots of leaves, as a heap-ordered binary tree.

    A slot begins with one leaf. An edit that makes more or fewer leaves deals them over the
    slots it touches, so only the sums above those change; a crowded slot has the tree laid
    out anew, which its leaves have paid for.
    """

    def __init__(self, chars: list[int], tokens: list[int]):
        self._lay([[x] for x in zip(chars, tokens, strict=True)])

    @classmethod
    def of(cls, text: str, count: Callable[[str], int], leaf: int = LEAF) -> Tree:
        parts = cut(text, leaf)
        return cls([len(p) for p in parts], [count(p) for p in parts])

    def _lay(self, slots: list[list[tuple[int, int]]]) -> None:
        self.slots = slots
        self.width = 1 << max(0, len(slots) - 1).bit_length()
        self.sums = [(0, 0)] * (2 * self.width)
        self.sums[self.width : self.width + len(slots)] = [self._sum(x) for x in slots]
        for i in range(self.width - 1, 0, -1):
            self._add_up(i)

    @staticmethod
    def _sum(leaves: list[tuple[int, int]]) -> tuple[int, int]:
        return sum(x[0] for x in leaves), sum(x[1] for x in leaves)

    def _add_up(self, i: int) -> None:
        a, b = self.sums[2 * i], self.sums[2 * i + 1]
        self.sums[i] = a[0] + b[0], a[1] + b[1]

    @property
    def chars(self) -> list[int]:
        return [x[0] for s in self.slots for x in s]

    @property
    def tokens(self) -> list[int]:
        return [x[1] for s in self.slots for x in s]

    @property
    def total(self) -> int:
        return self.sums[1][1]

    @property
    def length(self) -> int:
        return self.sums[1][0]

    def _beside(self, slot: int, leaf: int, step: int) -> tuple[int, int] | None:
        """The leaf before or after one."""
        leaf += step
        while not 0 <= leaf < len(self.slots[slot]):
            slot += step
            if not 0 <= slot < len(self.slots):
                return None
            leaf = 0 if step > 0 else len(self.slots[slot]) - 1
        return slot, leaf

    def find(self, pos: int) -> tuple[tuple[int, int], int]:
        """The leaf that holds character ``pos`` (the last one for the end), and where it starts."""
        if pos >= self.length:
            slot = len(self.slots) - 1
            while not self.slots[slot]:
                slot -= 1
            return (slot, len(self.slots[slot]) - 1), self.length - self.slots[slot][-1][0]
        i, start = 1, 0
        while i < self.width:
            i *= 2
            if pos - start >= self.sums[i][0]:
                start += self.sums[i][0]
                i += 1
        leaf = 0
        while pos - start >= self.slots[i - self.width][leaf][0]:
            start += self.slots[i - self.width][leaf][0]
            leaf += 1
        return (i - self.width, leaf), start

    def edit(self, text: str, pos: int, deleted: int, inserted: str, count: Callable[[str], int], leaf: int = LEAF) -> tuple[str, int]:
        """The new text, and how many characters were encoded again."""
        pos = min(max(pos, 0), len(text))
        end = min(pos + max(deleted, 0), len(text))
        a, start = self.find(pos)
        while pos <= start + 1 and (up := self._beside(*a, -1)):
            a = up
            start -= self.slots[a[0]][a[1]][0]
        b, b_start = self.find(end)
        stop = b_start + self.slots[b[0]][b[1]][0]
        while end >= stop - 1 and (up := self._beside(*b, 1)):
            b = up
            stop += self.slots[b[0]][b[1]][0]
        piece = text[start:pos] + inserted + text[end:stop]
        self._replace(a, b, [(len(p), count(p)) for p in cut(piece, leaf)])
        return text[:start] + piece + text[stop:], len(piece)

    def _replace(self, a: tuple[int, int], b: tuple[int, int], new: list[tuple[int, int]]) -> None:
        leaves = self.slots[a[0]][: a[1]] + new + self.slots[b[0]][b[1] + 1 :]
        n = b[0] - a[0] + 1
        dirty = set()
        for k in range(n):
            own = leaves[len(leaves) * k // n : len(leaves) * (k + 1) // n]
            self.slots[a[0] + k], self.sums[self.width + a[0] + k] = own, self._sum(own)
            dirty.add((self.width + a[0] + k) // 2)
        if len(leaves) > CROWD * n:
            self._lay([[x] for s in self.slots for x in s])
            return
        while dirty := dirty - {0}:
            for i in dirty:
                self._add_up(i)
            dirty = {i // 2 for i in dirty}


_TREE = "doc_id long, n_chars long, n_tokens long, leaf_chars array<int>, leaf_tokens array<int>"
_EDITED = f"{_TREE}, n_edits long, reencoded_chars long, text string"


def _ids(batch: pa.RecordBatch) -> pa.Array:
    return batch.column(0).cast(pa.int64())


def _builder(vocabulary: str, leaf: int):
    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(vocabulary)
        for b in batches:
            trees = [Tree.of(t or "", count, leaf) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [_ids(b), pa.array([t.length for t in trees], pa.int64()), pa.array([t.total for t in trees], pa.int64()), pa.array([t.chars for t in trees], pa.list_(pa.int32())), pa.array([t.tokens for t in trees], pa.list_(pa.int32()))],
                ["doc_id", "n_chars", "n_tokens", "leaf_chars", "leaf_tokens"],
            )

    return build


def _editor(vocabulary: str, leaf: int, keep_text: bool):
    def edit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(vocabulary)
        for b in batches:
            rows = []
            for i, text, chars, tokens, edits in zip(*(b.column(c).to_pylist() for c in range(5)), strict=True):
                text = text or ""
                tree = Tree(list(chars), list(tokens)) if chars is not None else Tree.of(text, count, leaf)
                again = 0
                todo = sorted(edits or [], key=lambda e: (e["seq"] is not None, e["seq"] or 0))
                for e in todo:
                    text, n = tree.edit(text, e["pos"] or 0, e["deleted"] or 0, e["inserted"] or "", count, leaf)
                    again += n
                rows.append((i, tree.length, tree.total, tree.chars, tree.tokens, len(todo), again, text if keep_text else None))
            cols = list(zip(*rows, strict=True)) if rows else [()] * 8
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.int64(), pa.int64(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "n_chars", "n_tokens", "leaf_chars", "leaf_tokens", "n_edits", "reencoded_chars", "text"])

    return edit


def trees(docs: DataFrame, vocabulary: str = VOCABULARY, leaf: int = LEAF) -> DataFrame:
    """The tree of every document: ``(doc_id, n_chars, n_tokens, leaf_chars, leaf_tokens)``."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_builder(vocabulary, leaf), _TREE)


def apply_edits(docs: DataFrame, known: DataFrame, edits: DataFrame, vocabulary: str = VOCABULARY, leaf: int = LEAF, keep_text: bool = True) -> DataFrame:
    """Trees and texts after ``edits (doc_id, seq, pos, deleted, inserted)``; only edited documents are returned.

    A document's edits are gathered with it; a document without a tree gets one.
    """
    todo = edits.groupBy("doc_id").agg(F.collect_list(F.struct(*(F.col(c).cast(t).alias(c) for c, t in (("seq", "long"), ("pos", "long"), ("deleted", "long"), ("inserted", "string"))))).alias("edits"))
    j = docs.select("doc_id", "text").join(todo, "doc_id").join(known.select("doc_id", "leaf_chars", "leaf_tokens"), "doc_id", "left")
    return edit_rows(j, vocabulary, leaf, keep_text)


def edit_rows(rows: DataFrame, vocabulary: str = VOCABULARY, leaf: int = LEAF, keep_text: bool = True) -> DataFrame:
    """The same for rows that already hold ``text``, ``leaf_chars``, ``leaf_tokens`` and ``edits``."""
    return rows.select(F.col("doc_id").cast("long"), "text", "leaf_chars", "leaf_tokens", F.col("edits").cast(EDITS)).mapInArrow(_editor(vocabulary, leaf, keep_text), _EDITED)


def with_trees(docs: DataFrame, vocabulary: str = VOCABULARY, leaf: int = LEAF) -> DataFrame:
    """``docs (doc_id, text, ...)`` with its tree beside it, without a join; columns named like the tree's are replaced."""
    docs = docs.select(*others(docs.columns, "n_tokens", "leaf_chars", "leaf_tokens"))
    names = docs.columns

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = counter(vocabulary)
        for b in batches:
            made = [Tree.of(t or "", count, leaf) for t in b.column(names.index("text")).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([t.total for t in made], pa.int64()), pa.array([t.chars for t in made], pa.list_(pa.int32())), pa.array([t.tokens for t in made], pa.list_(pa.int32()))], [*names, "n_tokens", "leaf_chars", "leaf_tokens"])

    return docs.mapInArrow(build, _schema_with(docs))


def _schema_with(docs: DataFrame):
    from pyspark.sql import types as T

    ints = T.ArrayType(T.IntegerType())
    return T.StructType([*docs.schema.fields, T.StructField("n_tokens", T.LongType()), T.StructField("leaf_chars", ints), T.StructField("leaf_tokens", ints)])


def sample_edits():
    """Three edits a document, as the query makes them: reword a third in, cut a stretch, append."""
    n = F.char_length(F.coalesce("text", F.lit("")))
    e = lambda seq, pos, deleted, inserted: F.struct(F.lit(seq).cast("long").alias("seq"), pos.cast("long").alias("pos"), deleted.cast("long").alias("deleted"), F.lit(inserted).alias("inserted"))
    return F.array(e(0, F.floor(n / 3), F.lit(12), " revised passage, 2nd draft"), e(1, F.floor(n / 2), F.floor(n / 50), ""), e(2, n + 100, F.lit(0), "\nEnd of revision."))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of every document, and its counts after three edits."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    before = with_trees(docs.withColumn("edits", sample_edits()))
    names = before.columns

    def both(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        edit = _editor(VOCABULARY, LEAF, False)
        for b in batches:
            col = lambda n, b=b: b.column(names.index(n))
            after = next(iter(edit(iter([pa.RecordBatch.from_arrays([col("doc_id"), col("text"), col("leaf_chars"), col("leaf_tokens"), col("edits")], ["doc_id", "text", "leaf_chars", "leaf_tokens", "edits"])]))))
            yield pa.RecordBatch.from_arrays([col("doc_id"), col("n_tokens"), after.column(2), after.column(1), after.column(6)], ["doc_id", "n_tokens", "n_tokens_edited", "n_chars_edited", "reencoded_chars"])

    return before.mapInArrow(both, "doc_id long, n_tokens long, n_tokens_edited long, n_chars_edited long, reencoded_chars long")
