"""N-gram Jaccard join with token-combination prefixes.

A document is the set of its distinct k-word shingles (``A-Z`` lower-cased; fewer words:
the whole sequence as one). Two documents link if their sets' Jaccard similarity is at
least ``percent`` / 100. Documents with equal sets are one node from the start.

1. Count: shingles are counted over the corpus, in packed sorted arrays by hash range;
   those of more than ``Limits.frequent`` sets are the frequent class. Documents learn which of
   theirs are.
2. Order: each set is ordered rare before frequent, by hash within a class. Similar sets
   share the first shared shingle within their first ``n - t + 1`` (``t``: least
   overlap), and a second one within one more. Rare ones there are indexed singly. If the
   first shared one is frequent, so are all, so frequent ones in the extended prefix are
   indexed as two-shingle combinations. A prefix of over ``Limits.combine`` frequent shingles
   would make too many: it is indexed by single ones, as are the prefixes of all sets so
   long that a partner of theirs may be such.
3. Candidates: nodes with an index key in common. Short lists give their pairs; a list
   over ``Limits.list`` nodes joins its nodes to one hot group instead.
4. Verify: pairs by a 16-bit sketch of one set sent to the other (an upper bound of the
   overlap), then by whole sets. A hot group is cut into blocks: links within blocks,
   between the blocks' representatives, and then only of the nodes that are still apart
   from their group's main component with all others; what is linked already needs no
   further comparison.
5. Components of the links.

Classes only decide what is compared, never whether a link counts, so results are exact
but for collisions of 64-bit shingle hashes. Sets of different documents never meet in a
task but for verification, in pieces of bounded size.

Defined results: null or empty text has the empty set, which links with nothing; rows of
one ``doc_id`` are versions of one document, linked by any; a null ``doc_id`` has its size
and no component; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import words as W
from .common import Scratch, join_hot, odd_at_least, partitions_for, table, total_chars
from .components import components

K, PERCENT = 5, 80


@dataclass(frozen=True)
class Limits:
    """What is compared how; none of them drops anything.

    ``frequent``: a shingle of more sets is frequent; ``list``: nodes of a list whose pairs
    are made; ``combine``: frequent shingles of a prefix that are combined; ``block``: sets
    of a hot group that are compared with each other at once, of ``cell`` bytes at most on
    average.
    """

    frequent: int = 16
    list: int = 32
    combine: int = 48
    block: int = 256
    cell: int = 16 << 20


#: Shingles that a task sorts together; expected ones of a bucket; bytes of text of a part; pairs laid out at once.
EMIT, BUCKET, PART, PAIRS = 500_000, 1_000_000, 4 << 20, 1 << 19

PACKED = "bucket long, kind string, part long, h binary, d binary, n binary"
_PACKED = pa.schema([("bucket", pa.int64()), ("kind", pa.string()), ("part", pa.int64()), *((c, pa.binary()) for c in "hdn")])


def sets(data: np.ndarray, bounds: np.ndarray, k: int = K) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes of all texts, ascending and distinct in each, and their bounds."""
    w = W.Words(data, bounds, lower=True)
    h, at = w.windows(k)
    text = w.text[at]
    size = np.diff(w.first)
    for n in range(1, k):
        some = np.flatnonzero(size == n)
        if len(some):
            g, where = w.windows(n)
            use = np.isin(w.text[where], some)
            h, text = np.r_[h, g[use]], np.r_[text, w.text[where][use]]
    if len(h) and (text[1:] < text[:-1]).any():  # short texts came last
        order = np.argsort(text, kind="stable")
        h, text = h[order], text[order]
    ends = np.searchsorted(text, np.arange(len(bounds)))
    for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True):
        h[a:b].sort()
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (text[1:] != text[:-1])
    return h[new], np.searchsorted(text[new], np.arange(len(bounds)))


def _set_keys(h: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """128 bits for each set."""
    out = []
    for c in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F):
        total = np.r_[W.U64(0), np.cumsum(W.mix(h ^ W.U64(c)), dtype=W.U64)]
        out.append(total[b[1:]] - total[b[:-1]])
    return out[0], out[1]


def _bucket_of(h: np.ndarray, n: int) -> np.ndarray:
    return (((h >> W.U64(32)) * W.U64(n)) >> W.U64(32)).astype(np.int64)


def _cuts(x: np.ndarray) -> Iterator[tuple[int, int]]:
    """Stretches of equal values."""
    if len(x):
        c = np.flatnonzero(x[1:] != x[:-1]) + 1
        yield from zip(np.r_[0, c].tolist(), np.r_[c, len(x)].tolist(), strict=True)


def _by_bucket(kind: str, h: np.ndarray, d: np.ndarray, n: np.ndarray | None, buckets: int) -> list[dict]:
    order = np.argsort(h)
    h, d = h[order], d[order]
    n = n[order] if n is not None else None
    b = _bucket_of(h, buckets)
    return [{"bucket": int(b[s]), "kind": kind, "part": None, "h": W.pack_sorted(h[s:e]), "d": W.pack(d[s:e]), "n": W.pack(n[s:e]) if n is not None else None} for s, e in _cuts(b)]


def _by_part(kind: str, d: np.ndarray, h: np.ndarray, parts: int, n: np.ndarray | None = None) -> list[dict]:
    """``h`` any 64-bit values beside ``d``."""
    p = W.spread(d, parts)
    order = np.lexsort((h, p))
    p, d, h = p[order], d[order], h[order]
    n = n[order] if n is not None else None
    return [{"bucket": None, "kind": kind, "part": int(p[s]), "h": W.pack_sorted(h[s:e]), "d": W.pack(d[s:e]), "n": W.pack(n[s:e]) if n is not None else None} for s, e in _cuts(p)]


def _unpacked(t: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    none = np.empty(0, np.int64)
    h = np.concatenate([none.view(W.U64), *map(W.unpack_sorted, t["h"].to_pylist())])
    d = np.concatenate([none, *map(W.unpack, t["d"].to_pylist())])
    n = np.concatenate([none, *(W.unpack(x) for x in t["n"].to_pylist() if x is not None)])
    return h, d, n


def _members(k: int):
    """Sizes and keys of the sets of all rows."""

    def sizes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, j, data, bounds in W.chunks(b.column(1)):
                h, at = sets(data, bounds, k)
                k1, k2 = _set_keys(h, at)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.array(np.diff(at)), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64))], ["doc_id", "n_shingles", "k1", "k2"])

    return sizes


def _node_rows(docs: pa.Table, right: pa.Table) -> pa.Table:
    """The rows of a part that are nodes, as rows of kind ``node`` name them."""
    nodes = right.filter(pa.compute.equal(right["kind"].combine_chunks(), "node"))["d"].to_pylist()
    return docs.filter(pa.compute.is_in(docs["doc_id"].combine_chunks(), pa.array(np.frombuffer(b"".join(nodes), ">i8").astype(np.int64))))


def _shingles(k: int, buckets: int):
    """Per part: every shingle of each node, once if its row is repeated. What is marked is what is indexed."""

    def shingles(key, docs, right):
        docs = _node_rows(docs, right)
        ids = docs["doc_id"].combine_chunks().to_numpy(zero_copy_only=False)
        held: list[tuple[np.ndarray, np.ndarray]] = []
        seen: set[tuple[int, int, int]] = set()
        total, out = 0, []
        for i, j, data, bounds in W.chunks(docs["text"]):
            h, at = sets(data, bounds, k)
            use = np.zeros(j - i, bool)
            for t, row in enumerate(zip(ids[i:j].tolist(), *(x.tolist() for x in _set_keys(h, at)), strict=True)):
                if row not in seen:
                    seen.add(row)
                    use[t] = True
            own = np.repeat(np.arange(j - i), np.diff(at))
            held.append((h[use[own]], ids[i:j][own[use[own]]].astype(np.int64)))
            total += len(held[-1][0])
            if total >= EMIT:
                out += _by_bucket("set", *map(np.concatenate, zip(*held, strict=True)), None, buckets)
                held, total = [], 0
        if held:
            out += _by_bucket("set", *map(np.concatenate, zip(*held, strict=True)), None, buckets)
        return pa.Table.from_pylist(out, _PACKED)

    return shingles


def _frequent(parts: int, most: int):
    """Per bucket: shingles of more than ``Limits.frequent`` sets, for each document that sent them."""

    def count(key, t):
        h, d, _ = _unpacked(t)
        order = np.argsort(h)
        h, d = h[order], d[order]
        start = np.flatnonzero(np.r_[True, h[1:] != h[:-1]]) if len(h) else np.empty(0, np.int64)
        size = np.diff(np.r_[start, len(h)])
        use = np.repeat(size > most, size)
        out = pa.Table.from_pylist(_by_part("frequent", d[use], h[use], parts), _PACKED)
        del h, d, order, use
        W.trim()
        return out

    return count


def least_overlap(n: np.ndarray, percent: int = PERCENT) -> np.ndarray:
    """The least overlap of a set of size n with any partner."""
    return -(-n * percent // 100)


def _indexer(k: int, percent: int, buckets: int, combine: int):
    """Index keys of each node: rare single shingles, combinations of frequent ones."""

    def keys_of(h: np.ndarray, frequent: np.ndarray) -> np.ndarray:
        n = len(h)
        prefix = n - int(least_overlap(np.array(n), percent)) + 1
        rare, often = h[~frequent], h[frequent]
        out = [W.mix(rare[:prefix])]
        m = max(0, prefix + 1 - len(rare))  # frequent ones in the extended prefix
        some = often[:m]
        if len(some) > 1 and len(some) <= combine:
            i, j = np.triu_indices(len(some), 1)
            out.append(W.mix(some[i] * W.U64(3) + W.mix(some[j] ^ W.U64(0xC0))))
        largest = n * 100 // percent  # of a partner
        if len(some) and (len(some) > combine or largest - largest * percent // 100 + 2 > combine):
            out.append(W.mix(some[: max(1, m - 1)] ^ W.U64(0x51_6E_61_4C)))
        return np.unique(np.concatenate(out))

    def index(key, docs, right):
        kind = right["kind"].combine_chunks()
        fh, fd, _ = _unpacked(right.filter(pa.compute.equal(kind, "frequent")))
        docs = _node_rows(docs, right)
        ids = docs["doc_id"].combine_chunks().to_numpy(zero_copy_only=False)
        tags = np.sort(W.mix(fh ^ W.mix(fd.view(W.U64))))
        out: list[dict] = []
        held, total = [], 0
        for i, j, data, bounds in W.chunks(docs["text"]):
            h, at = sets(data, bounds, k)
            own = np.repeat(ids[i:j], np.diff(at))
            t = W.mix(h ^ W.mix(own.view(W.U64)))
            found = np.searchsorted(tags, t)
            often = np.zeros(len(h), bool) if not len(tags) else tags[np.minimum(found, len(tags) - 1)] == t
            for x in range(j - i):
                a, b = int(at[x]), int(at[x + 1])
                if b > a:
                    keys = keys_of(h[a:b], often[a:b])
                    held.append((keys, np.full(len(keys), ids[i + x]), np.full(len(keys), b - a)))
                    total += len(keys)
        if held:
            out = _by_bucket("key", *map(np.concatenate, zip(*held, strict=True)), buckets)
        return pa.Table.from_pylist(out, _PACKED)

    return index


class _Pairs:
    """Distinct numbers of many arrays, of which few are held beside them."""

    def __init__(self):
        self.known, self.new, self.size = np.empty(0, np.int64), [], 0

    def add(self, numbers: np.ndarray) -> None:
        self.new.append(np.unique(numbers))
        self.size += len(self.new[-1])
        if self.size > PAIRS + len(self.known):
            self.all()

    def all(self) -> np.ndarray:
        self.known, self.new, self.size = np.unique(np.concatenate([self.known, *self.new])), [], 0
        return self.known


def _lister(percent: int, parts: int, short: int):
    """Per bucket: pairs of short lists, stars of long ones."""

    def lists(key, t):
        h, d, n = _unpacked(t)
        order = np.lexsort((d, h))
        h, d, n = h[order], d[order], n[order]
        new = np.ones(len(h), bool)
        new[1:] = (h[1:] != h[:-1]) | (d[1:] != d[:-1])
        h, d, n = h[new], d[new], n[new]
        start = np.flatnonzero(np.r_[True, h[1:] != h[:-1]]) if len(h) else np.empty(0, np.int64)
        size = np.diff(np.r_[start, len(h)])
        nodes, code = np.unique(d, return_inverse=True)
        found = _Pairs()
        for length in range(2, short + 1):
            at = start[size == length]
            i, j = np.triu_indices(length, 1)
            for some in np.array_split(at, -(-len(at) * len(i) // PAIRS)) if len(at) else []:
                a, b = (some[:, None] + i[None, :]).ravel(), (some[:, None] + j[None, :]).ravel()
                ok = np.minimum(n[a], n[b]) * 100 >= np.maximum(n[a], n[b]) * percent
                found.add((code[a[ok]].astype(np.int64) << 32) | code[b[ok]])
        p = found.all()
        rows = [{**r, "kind": "pair"} for r in _pair_rows(np.stack([nodes[p >> 32], nodes[p & 0xFFFFFFFF]], 1), parts)] if len(p) else []
        long = np.repeat(size > short, size)
        if long.any():
            first = np.repeat(d[start], size)
            star = np.unique(np.stack([first[long], d[long]], 1), axis=0)
            rows += [{**r, "kind": "star"} for r in _pair_rows(star, parts)]
        out = pa.Table.from_pylist(rows, _PACKED)
        del h, d, n, code, rows
        W.trim()
        return out

    return lists


def _pair_rows(p: np.ndarray, parts: int) -> list[dict]:
    """Pairs by the part of their first node; both as signed integers in ``d`` and ``n``."""
    order = np.lexsort((p[:, 1], p[:, 0], W.spread(p[:, 0], parts)))
    p = p[order]
    return [{"bucket": None, "kind": "", "part": int(p[s, 0] % parts), "h": None, "d": W.pack(p[s:e, 0]), "n": W.pack(p[s:e, 1])} for s, e in _cuts(W.spread(p[:, 0], parts))]


def _pairs_of(t: pa.Table) -> np.ndarray:
    none = np.empty(0, np.int64)
    return np.stack([np.concatenate([none, *map(W.unpack, t[c].to_pylist())]) for c in "dn"], 1)


SENT = "part long, a long, sketch binary, whole binary, b binary"
_SENT = pa.schema([("part", pa.int64()), ("a", pa.int64()), ("sketch", pa.binary()), ("whole", pa.binary()), ("b", pa.binary())])


def _node_sets(docs: pa.Table, wanted: np.ndarray, k: int) -> Iterator[tuple[int, np.ndarray]]:
    docs = docs.filter(pa.compute.is_in(docs["doc_id"].combine_chunks(), pa.array(wanted)))
    ids = docs["doc_id"].combine_chunks().to_numpy(zero_copy_only=False)
    for i, j, data, bounds in W.chunks(docs["text"]):
        h, at = sets(data, bounds, k)
        for x in range(j - i):
            yield int(ids[i + x]), h[at[x] : at[x + 1]]


def _sketch(h: np.ndarray) -> np.ndarray:
    return np.sort((h >> W.U64(13)).astype(np.uint16))


def _meet(x: np.ndarray, y: np.ndarray) -> int:
    """Size of the intersection of two ascending arrays, as multisets."""
    if len(x) > len(y):
        x, y = y, x
    rank = np.arange(len(x)) - np.searchsorted(x, x, "left")
    return int((np.searchsorted(y, x, "right") - np.searchsorted(y, x, "left") > rank).sum())


def _similar(both: int, n: int, m: int, percent: int) -> bool:
    return 100 * both >= percent * (n + m - both)


def _sender(k: int, parts: int, whole: bool):
    """Sends the set of each pair's first node to the second's part: its sketch, or all of it."""

    def send(key, docs, right):
        p = np.unique(_pairs_of(right), axis=0)
        ends = np.searchsorted(p[:, 0], p[:, 0], "right")
        rows = []
        for i, h in _node_sets(docs, p[:, 0], k):
            s = int(np.searchsorted(p[:, 0], i))
            b = p[s : int(ends[s]), 1]
            b = b[np.argsort(W.spread(b, parts), kind="stable")]
            for u, v in _cuts(W.spread(b, parts)):
                rows.append({"part": int(b[u] % parts), "a": i, "sketch": None if whole else _sketch(h).tobytes(), "whole": h.tobytes() if whole else None, "b": W.pack(b[u:v])})
        return pa.Table.from_pylist(rows, _SENT)

    return send


def _judge(k: int, percent: int, parts: int, whole: bool):
    """Pairs that pass: by the sketch's bound, or for certain."""

    def judge(key, docs, right):
        by: dict[int, list] = {}
        for a, sketch, full, b in zip(*(right[c].to_pylist() for c in ("a", "sketch", "whole", "b")), strict=True):
            x = np.frombuffer(full, W.U64) if whole else np.frombuffer(sketch, np.uint16)
            for i in W.unpack(b).tolist():
                by.setdefault(i, []).append((a, x))
        good = []
        for i, h in _node_sets(docs, np.array(list(by), np.int64), k):
            y = h if whole else _sketch(h)
            good += [(a, i) for a, x in by[i] if _similar(_meet(x, y), len(x), len(y), percent)]
        p = np.array(good, np.int64).reshape(-1, 2)
        return pa.Table.from_pylist([{**r, "kind": "pair"} for r in _pair_rows(p, parts)], _PACKED)

    return judge


def _fetch(k: int):
    def fetch(key, docs, right):
        rows = [{"node": i, "whole": h.tobytes()} for i, h in _node_sets(docs, right["node"].to_numpy(), k)]
        return pa.Table.from_pylist(rows, pa.schema([("node", pa.int64()), ("whole", pa.binary())]))

    return fetch


def _overlap_matrix(x: list[np.ndarray], y: list[np.ndarray]) -> np.ndarray:
    """Intersection sizes of every set of x with every set of y, over the shingles that both sides have."""
    out = np.zeros((len(x), len(y)), np.int32)
    both = np.intersect1d(np.unique(np.concatenate(x)), np.unique(np.concatenate(y)))
    where = [[np.flatnonzero(np.isin(both, s, assume_unique=True)) if len(s) < len(both) else np.searchsorted(both, s[np.isin(s, both)]) for s in side] for side in (x, y)]
    for lo in range(0, len(both), 4096):
        m = []
        for side in where:
            z = np.zeros((len(side), min(4096, len(both) - lo)), np.float32)
            for r, w in enumerate(side):
                w = w[np.searchsorted(w, lo) : np.searchsorted(w, lo + 4096)] - lo
                z[r, w] = 1
            m.append(z)
        out += (m[0] @ m[1].T).astype(np.int32)
    return out


def _block_links(percent: int, block: int):
    """Links within a cell: among its rows of side 0, and of those with side 1; a forest of them is enough."""

    def link(key, t):
        rows = sorted(zip(t["side"].to_pylist(), t["node"].to_pylist(), t["whole"].to_pylist(), strict=True), key=lambda r: r[:2])
        nodes = [r[1] for r in rows]
        found = [np.frombuffer(r[2], W.U64) for r in rows]
        x = [s for r, s in zip(rows, found, strict=True) if r[0] == 0]
        root = list(range(len(rows)))

        def top(i: int) -> int:
            while root[i] != i:
                root[i] = root[root[i]]
                i = root[i]
            return i

        edges = []
        if x:
            size = np.array([len(s) for s in found])
            for lo in range(0, len(rows), block):
                both = _overlap_matrix(x, found[lo : lo + block])
                ok = 100 * both >= percent * (size[: len(x), None] + size[None, lo : lo + block] - both)
                for i, j in zip(*(c.tolist() for c in np.nonzero(ok)), strict=True):
                    a, b = top(i), top(lo + j)
                    if a != b:
                        root[max(a, b)] = min(a, b)
                        edges.append((nodes[i], nodes[lo + j]))
        return pa.Table.from_arrays([pa.array([e[c] for e in edges], pa.int64()) for c in (0, 1)], ["a", "b"])

    return link


_CELL = "cell string, side int, node long, whole binary"


def _links_of(cells: DataFrame, percent: int, block: int) -> DataFrame:
    return cells.groupBy("cell").applyInArrow(_block_links(percent, block), "a long, b long")


def _hot_links(stars: DataFrame, parted: DataFrame, parts: int, k: int, percent: int, limits: Limits, scratch: Scratch, partitions: int) -> DataFrame:
    """Links among the nodes of hot groups, enough to connect all that are connected."""
    block = limits.block
    blocks_of = F.greatest(F.ceil(F.count(F.lit(1)) / block), F.ceil(F.sum(F.octet_length("whole")) / limits.cell))
    groups = scratch.keep(components(stars, scratch), "groups")
    asked = groups.select("node", F.pmod("node", F.lit(parts)).cast("long").alias("part"))
    found = parted.groupBy("part").cogroup(asked.groupBy("part")).applyInArrow(_fetch(k), "node long, whole binary")
    members = scratch.keep(found.join(groups, "node"), "members", partitions)
    size = members.groupBy("component").agg(blocks_of.alias("blocks"))
    cut = members.join(size, "component").withColumn("block", F.pmod(F.xxhash64("node"), "blocks"))
    cell = F.concat_ws(":", "component", "block")
    links = scratch.keep(_links_of(cut.select(cell.alias("cell"), F.lit(0).alias("side"), "node", "whole"), percent, block), "links")
    # representatives: one node of each block's components
    while True:
        label = components(links, scratch).withColumnRenamed("component", "label")
        state = scratch.keep(cut.join(label, "node", "left").withColumn("label", F.coalesce("label", "node")), "state")
        reps = state.where(F.col("blocks") > 1).where(F.col("node") == F.col("label"))
        n = reps.groupBy("component").agg(F.count(F.lit(1)).alias("reps"), blocks_of.alias("cells"))
        again = reps.join(n.where("reps > 1"), "component").withColumn("block", F.pmod(F.xxhash64("node", F.lit(7)), "cells"))
        more = scratch.keep(_links_of(again.select(cell.alias("cell"), F.lit(0).alias("side"), "node", "whole"), percent, block), "links")
        if not more.head(1):
            break
        links = scratch.keep(links.unionByName(more), "links")
    # what is still apart from the main component is compared with all others of the group
    label_size = state.where(F.col("blocks") > 1).groupBy("component", "label").agg(F.count(F.lit(1)).alias("n"))
    main = label_size.groupBy("component").agg(F.max(F.struct("n", "label")).alias("main")).select("component", F.col("main.label").alias("main"))
    apart = state.join(main, "component").where(F.col("label") != F.col("main"))
    strays = apart.groupBy("component").agg((blocks_of - 1).alias("last"))
    apart = apart.join(strays, "component").select("component", F.pmod(F.xxhash64("node", F.lit(9)), F.col("last") + 1).alias("stray"), "node", "whole")
    others = state.join(strays, "component").select("component", "block", "node", "whole", F.explode(F.sequence(F.lit(0).cast("long"), F.col("last"))).alias("stray"))
    blocks = size.join(strays, "component").select("component", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"))
    here = F.concat_ws(":", "component", "block", "stray").alias("cell")
    left = apart.join(blocks, "component").select(here, F.lit(0).alias("side"), "node", "whole")
    crossed = _links_of(left.unionByName(others.select(here, F.lit(1).alias("side"), "node", "whole")), percent, block)
    return links.unionByName(crossed)


def links(docs: DataFrame, k: int = K, percent: int = PERCENT, limits: Limits = Limits()) -> tuple[DataFrame, DataFrame]:
    """``(doc_id, n_shingles, node)`` of every row, and links ``(a, b)`` between nodes.

    A node stands for all documents of one set: the least ``doc_id`` of them. Links
    connect all nodes that similarity connects; within hot groups not every single link is
    returned.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark)
    size = total_chars(docs)
    buckets, parts, partitions = max(8, round(size / 6.5 / BUCKET)), odd_at_least(size / PART + 7), partitions_for(size)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    real = docs.where(F.col("doc_id").isNotNull() & (F.length("text") > 0))
    members = scratch.keep(docs.mapInArrow(_members(k), "doc_id long, n_shingles long, k1 long, k2 long"), "members")
    with_set = "n_shingles > 0 AND doc_id IS NOT NULL"
    full, key = members.where(with_set), ["k1", "k2", "n_shingles"]
    node = scratch.keep(full.groupBy(*key).agg(F.min("doc_id").alias("node"), F.count(F.lit(1)).alias("rows")), "equal", partitions)
    known = join_hot(full, node, key, "rows", members.count())  # no task gets all copies of one set
    known = known.select("doc_id", "n_shingles", "node").unionByName(members.where(f"NOT ({with_set})").select("doc_id", "n_shingles", F.lit(None).cast("long").alias("node")))
    known = scratch.keep(known, "nodes", partitions)
    parted = real.select(F.pmod("doc_id", F.lit(parts)).cast("long").alias("part"), "doc_id", "text")

    own = known.where("node = doc_id").select("node").distinct()
    to_node = own.select(F.lit(None).cast("long").alias("bucket"), F.lit("node").alias("kind"), F.pmod("node", F.lit(parts)).cast("long").alias("part"), F.lit(None).cast("binary").alias("h"), F.to_binary(F.lpad(F.hex("node"), 16, "0"), F.lit("hex")).alias("d"), F.lit(None).cast("binary").alias("n"))
    shingles = parted.groupBy("part").cogroup(to_node.groupBy("part")).applyInArrow(_shingles(k, buckets), PACKED)
    frequent = scratch.keep(shingles.groupBy("bucket").applyInArrow(_frequent(parts, limits.frequent), PACKED), "frequent", partitions)
    scratch.free()
    right = frequent.unionByName(to_node)
    keys = parted.groupBy("part").cogroup(right.groupBy("part")).applyInArrow(_indexer(k, percent, buckets, limits.combine), PACKED)
    lists = scratch.keep(keys.groupBy("bucket").applyInArrow(_lister(percent, parts, limits.list), PACKED), "lists", partitions)
    scratch.drop(frequent)

    pairs = lists.where("kind = 'pair'")
    for whole in (False, True):
        sent = parted.groupBy("part").cogroup(pairs.groupBy("part")).applyInArrow(_sender(k, parts, whole), SENT)
        pairs = scratch.keep(parted.groupBy("part").cogroup(sent.groupBy("part")).applyInArrow(_judge(k, percent, parts, whole), PACKED), "pairs", partitions)
        scratch.free()
    found = pairs.mapInArrow(_unpack_pairs, "a long, b long")
    stars = lists.where("kind = 'star'").mapInArrow(_unpack_pairs, "a long, b long")
    if stars.head(1):
        found = found.unionByName(_hot_links(stars, parted, parts, k, percent, limits, scratch, partitions))
    several = known.where("node IS NOT NULL").groupBy("doc_id").agg(F.min("node").alias("a"), F.max("node").alias("most")).where("a <> most")
    versions = known.join(several, "doc_id").where("node <> a").select("a", F.col("node").alias("b"))
    found = scratch.keep(found.unionByName(versions).distinct(), "links")
    scratch.drop_but(known, found)
    return known, found


def _unpack_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        p = _pairs_of(pa.Table.from_batches([b]))
        yield pa.RecordBatch.from_arrays([pa.array(p[:, 0]), pa.array(p[:, 1])], ["a", "b"])


def classes(docs: DataFrame, k: int = K, percent: int = PERCENT, limits: Limits = Limits()) -> DataFrame:
    """``(doc_id, n_shingles, component_id)`` of every row."""
    known, found = links(docs, k, percent, limits)
    label = components(found, Scratch(docs.sparkSession))
    return known.join(label, "node", "left").select("doc_id", "n_shingles", F.coalesce("component", "node", "doc_id").alias("component_id"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classes(table(spark, sf_dir, "documents").select("doc_id", "text"))
