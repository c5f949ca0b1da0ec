"""Substring dedup on a log-structured index of window hashes.

A window is ``k`` consecutive words of one document. A word goes if a window that covers
it also occurs in an older document: one of an earlier batch, or one of the same batch
with a smaller ``doc_id``. Windows are judged on the input, not on what is left.

The index holds sorted immutable runs, one file per hash range ("bucket") and run: each
distinct window hash with the first document that had it. ``ingest`` takes a batch:

1. every task hashes its windows, settles repeats among its own rows, and sends the first
   holder of each hash to the hash's bucket, packed as sorted arrays (so a passage that a
   third of all rows share is sent once a task, not once a document);
2. per bucket the arrays are merge-joined with the runs: hashes met before become hits of
   their documents, new ones the next run. Beyond ``max_runs`` runs, the merge writes the
   union of old and new instead, and the old runs go (compaction);
3. hits go to their documents, which mark the covered words.

Every stretch of hits is then verified: documents send the SHA-256 of its words to the
older document, which must have the same words at a window of that hash (or each of its
windows somewhere: those few stretches are compared word by word). One failure (two word sequences with one 64-bit hash) has the whole ingest redone with 128-bit keys
(``lanes=2``) and verified again; ``lanes=2`` can be set at once where hashes of 64 bits
are known to collide (beyond some 10^9 windows).

Defined results: null or empty text has no words; a null ``doc_id`` is kept as it is and
takes no part; rows of one id do not repeat each other; columns beyond ``doc_id`` and
``text`` are ignored; an empty batch gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import words as W
from .common import Scratch, odd_at_least, partitions_for, table, writing

K = 13
#: Windows that a task settles among themselves before it sends them.
EMIT = 1_000_000
#: Expected windows of a bucket, and bytes of text of a part of the documents.
BUCKET, PART = 1_000_000, 8 << 20

SENT = "bucket long, kind string, part long, h binary, h2 binary, d binary, f binary"
_SENT = pa.schema([("bucket", pa.int64()), ("kind", pa.string()), ("part", pa.int64()), *((c, pa.binary()) for c in ("h", "h2", "d", "f"))])
OUT = "kind string, doc_id long, n_words long, n_removed long, text string, kept_sha256 string, f long, h long, n long, digest binary"
BAD = "f long, h long, n long, digest binary, d long"
_BAD = pa.schema([("f", pa.int64()), ("h", pa.int64()), ("n", pa.int64()), ("digest", pa.binary()), ("d", pa.int64())])
_OUT = pa.schema([("kind", pa.string()), ("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("text", pa.string()), ("kept_sha256", pa.string()), ("f", pa.int64()), ("h", pa.int64()), ("n", pa.int64()), ("digest", pa.binary())])


def _narrow(h: np.ndarray, bits: int) -> np.ndarray:
    """``bits`` below 64 make hashes collide; tests use that."""
    return h if bits >= 64 else (h >> W.U64(64 - bits)) << W.U64(64 - bits)


def _second(w: W.Words, at: np.ndarray, k: int) -> np.ndarray:
    h = np.zeros(len(at), W.U64)
    for j in range(k):
        h = W.mix(h + w.hash[at + j])
    return h


def _bucket_of(h: np.ndarray, n: int) -> np.ndarray:
    return (((h >> W.U64(32)) * W.U64(n)) >> W.U64(32)).astype(np.int64)


def _groups(keys: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """An order that brings equal keys together, and where each new key starts in it."""
    order = np.argsort(keys[0]) if len(keys) == 1 else np.lexsort(keys[::-1])
    new = np.ones(len(order), bool)
    if len(order):
        new[1:] = np.logical_or.reduce([x[order][1:] != x[order][:-1] for x in keys])
    return order, np.flatnonzero(new)


def _hit_rows(keys: list[np.ndarray], d: np.ndarray, f: np.ndarray, parts: int, buckets: int) -> list[dict]:
    rows = []
    order = np.argsort(W.spread(d, parts), kind="stable")
    part = W.spread(d, parts)[order]
    for idx in np.split(order, np.flatnonzero(np.diff(part)) + 1) if len(order) else []:
        p = int(d[idx[0]] % parts)
        idx = idx[np.argsort(keys[0][idx])]
        rows.append({"bucket": p % buckets, "kind": "hit", "part": p, "h": W.pack_sorted(keys[0][idx]), "h2": W.pack(keys[1][idx].view(np.int64)) if len(keys) > 1 else None, "d": W.pack(d[idx]), "f": W.pack(f[idx])})
    return rows


def _key_rows(keys: list[np.ndarray], d: np.ndarray, buckets: int) -> list[dict]:
    """``keys`` ascending by the first."""
    b = _bucket_of(keys[0], buckets)
    cut = np.flatnonzero(np.diff(b)) + 1
    rows = []
    for s, e in zip(np.r_[0, cut].tolist(), np.r_[cut, len(b)].tolist(), strict=True):
        if e > s:
            rows.append({"bucket": int(b[s]), "kind": "key", "part": None, "h": W.pack_sorted(keys[0][s:e]), "h2": W.pack(keys[1][s:e].view(np.int64)) if len(keys) > 1 else None, "d": W.pack(d[s:e]), "f": None})
    return rows


def _sender(k: int, lanes: int, bits: int, parts: int, buckets: int):
    def settle(found: list[list[np.ndarray]]) -> pa.RecordBatch:
        keys, d = [np.concatenate(x) for x in list(zip(*found, strict=True))[:-1]], np.concatenate([x[-1] for x in found])
        order, start = _groups(keys)
        keys, d = [x[order] for x in keys], d[order]
        first = np.minimum.reduceat(d, start)
        f = np.repeat(first, np.diff(np.r_[start, len(d)]))
        again = np.flatnonzero(d > f)
        rows = _hit_rows([x[again] for x in keys], d[again], f[again], parts, buckets) + _key_rows([x[start] for x in keys], first, buckets)
        return pa.RecordBatch.from_pylist(rows, _SENT)

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, n = [], 0
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for i, j, data, bounds in W.chunks(batch.column(1)):
                w = W.Words(data, bounds)
                h, at = w.windows(k)
                if len(h):
                    found.append([_narrow(h, bits), *([_second(w, at, k)] if lanes > 1 else []), ids[i:j][w.text[at]].astype(np.int64)])
                    n += len(h)
                if n >= EMIT:
                    yield settle(found)
                    found, n = [], 0
        if found:
            yield settle(found)

    return send


def _read_keys(t: pa.Table, lanes: int) -> tuple[list[np.ndarray], np.ndarray]:
    none = np.empty(0, np.int64)
    h = [W.unpack_sorted(x) for x in t["h"].to_pylist()]
    h2 = [W.unpack(x).view(W.U64) for x in t["h2"].to_pylist()] if lanes > 1 else []
    d = [W.unpack(x) for x in t["d"].to_pylist()]
    return [np.concatenate([none.view(W.U64), *x]) for x in ([h, h2] if lanes > 1 else [h])], np.concatenate([none, *d])


def _merger(lanes: int, parts: int, buckets: int, compact: bool):
    """Merge-join of a bucket's new hashes with its runs."""

    def merge(key, old, new):
        passed = new.filter(pa.compute.equal(new["kind"], "hit"))
        was, was_d = _read_keys(old, lanes)
        keys, d = _read_keys(new.filter(pa.compute.equal(new["kind"], "key")), lanes)
        age = np.r_[np.zeros(len(was_d), np.int8), np.ones(len(d), np.int8)]
        keys, d = [np.concatenate(x) for x in zip(was, keys, strict=True)], np.concatenate([was_d, d])
        rows: list[dict] = []
        if len(d):
            order, start = _groups(keys)
            keys, d, age = [x[order] for x in keys], d[order], age[order]
            size = np.diff(np.r_[start, len(d)])
            known = np.minimum.reduceat(age, start) == 0  # a run has it
            least = np.where(np.repeat(known, size) & (age == 1), np.iinfo(np.int64).max, d)
            first = np.minimum.reduceat(least, start)
            f = np.repeat(first, size)
            hit = np.flatnonzero((age == 1) & (d != f))
            rows = _hit_rows([x[hit] for x in keys], d[hit], f[hit], parts, buckets)
            keep = np.ones(len(start), bool) if compact else ~known
            rows += _key_rows([x[start][keep] for x in keys], first[keep], buckets)
        return pa.concat_tables([pa.Table.from_pylist(rows, _SENT), passed.select(_SENT.names).cast(_SENT)])

    return merge


def _first_run(merge):
    def alone(key, new):
        return merge(key, new.slice(0, 0), new)

    return alone


def _marker(k: int, lanes: int, bits: int, want_text: bool):
    """Marks the words that hits cover; returns documents and what is to be verified."""

    def mark(key, docs, hits):
        h, d = _read_keys(hits, lanes)
        f = np.concatenate([np.empty(0, np.int64), *(W.unpack(x) for x in hits["f"].to_pylist())])
        tag = W.mix(h[0] ^ W.mix(d.view(W.U64)))
        order = np.argsort(tag)
        tag, d, f, h = tag[order], d[order], f[order], [x[order] for x in h]
        ids = docs["doc_id"].combine_chunks()
        known = ids.is_valid().to_numpy(zero_copy_only=False)
        ids = ids.fill_null(0).to_numpy(zero_copy_only=False)
        out: list[pa.Table] = []
        asked: list[dict] = []
        for i, j, data, bounds in W.chunks(docs["text"]):
            w = W.Words(data, bounds)
            g, at = w.windows(k)
            g = _narrow(g, bits)
            own = ids[i:j][w.text[at]]
            t = W.mix(g ^ W.mix(own.view(W.U64)))
            found = np.searchsorted(tag, t)
            found[found == len(tag)] = 0
            hit = np.flatnonzero((tag[found] == t) & (d[found] == own) & (h[0][found] == g) & known[i:j][w.text[at]]) if len(tag) else np.empty(0, np.int64)
            if lanes > 1 and len(hit):
                hit = _both_lanes(hit, found, tag, h[1], _second(w, at, k))
            at, src = at[hit], f[found[hit]]
            cover = np.zeros(len(w.hash) + 1, np.int32)
            np.add.at(cover, at, 1)
            np.add.at(cover, at + k, -1)
            keep = np.cumsum(cover[:-1]) == 0
            cut = np.flatnonzero((np.diff(at) != 1) | (np.diff(src) != 0) | (np.diff(w.text[at]) != 0)) + 1
            if len(at):
                for s, e in zip(np.r_[0, cut].tolist(), np.r_[cut, len(at)].tolist(), strict=True):
                    asked.append({"kind": "ask", "doc_id": int(own[hit[s]]), "f": int(src[s]), "h": int(g[hit[s]].view(np.int64)), "n": e - s, "digest": hashlib.sha256(w.bytes_of(int(at[s]), int(at[e - 1]) + k)).digest()})
            text, ends = kept_text(w, keep)
            view = text.tobytes()
            pieces = [view[s:e] for s, e in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)]
            n_words = np.diff(w.first)
            left = np.r_[0, np.cumsum(keep)]
            m = j - i
            out.append(
                pa.table(
                    [pa.array(["doc"] * m), docs["doc_id"].combine_chunks()[i:j], pa.array(n_words), pa.array(n_words - (left[w.first[1:]] - left[w.first[:-1]])), pa.array([x.decode() for x in pieces] if want_text else [None] * m, pa.string()), pa.array([hashlib.sha256(x).hexdigest() for x in pieces]), *[pa.nulls(m, pa.int64())] * 3, pa.nulls(m, pa.binary())],
                    schema=_OUT,
                )
            )
        return pa.concat_tables([*out, pa.Table.from_pylist(asked, _OUT)])

    return mark


def _both_lanes(hit: np.ndarray, found: np.ndarray, tag: np.ndarray, h2: np.ndarray, g2: np.ndarray) -> np.ndarray:
    """Hits whose second lane is met by one of the entries with the same first; moves ``found`` there."""
    good = []
    for x in hit.tolist():
        i = int(found[x])
        while i < len(tag) and tag[i] == tag[found[x]]:
            if h2[i] == g2[x]:
                found[x] = i
                good.append(x)
                break
            i += 1
    return np.array(good, np.int64)


def kept_text(w: W.Words, keep: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of each text's kept words joined by one space, and their bounds."""
    i = np.flatnonzero(keep)
    text = w.text[i]
    more = np.r_[text[1:] == text[:-1], np.zeros(min(1, len(i)), bool)]  # another kept word follows in its text
    data = w.data.copy()
    inside = np.zeros(len(data) + 2, np.int8)
    np.add.at(inside, w.start[i], 1)
    np.add.at(inside, w.end[i] + more, -1)
    data[w.end[i[more]]] = 32
    mask = np.cumsum(inside[: len(data)], dtype=np.int8) > 0
    size = np.bincount(text, (w.end[i] - w.start[i] + more).astype(np.float64), len(w.bounds) - 1).astype(np.int64)
    return data[mask], np.r_[0, np.cumsum(size)]


def _checker(k: int, bits: int):
    """Stretches that the older document does not have at any window of that hash."""

    def check(key, docs, asked):
        open_ = {(r["f"], r["h"], r["n"], r["digest"]): r["d"] for r in asked.select(["f", "h", "n", "digest", "d"]).to_pylist()}
        if not open_:
            return pa.Table.from_pylist([], _BAD)
        by: dict[int, list] = {}
        for r in open_:
            by.setdefault(r[0], []).append(r)
        ids = docs["doc_id"].combine_chunks()
        use = pa.compute.is_in(ids, pa.array(list(by), pa.int64()))
        ids, texts = ids.filter(use).to_numpy(zero_copy_only=False), docs["text"].combine_chunks().filter(use)
        for i, j, data, bounds in W.chunks(texts):
            w = W.Words(data, bounds)
            g, at = w.windows(k)
            g = _narrow(g, bits).view(np.int64)
            first = np.searchsorted(at, w.first)
            for t in range(j - i):
                here = g[first[t] : first[t + 1]]
                order = np.argsort(here)
                for r in by.get(int(ids[i + t]), []):
                    s, e = np.searchsorted(here[order], [r[1], r[1]], "left")[0], np.searchsorted(here[order], r[1], "right")
                    for x in order[s:e].tolist():
                        a = int(at[first[t] + x])
                        if a + r[2] + k - 1 <= w.first[t + 1] and hashlib.sha256(w.bytes_of(a, a + r[2] + k - 1)).digest() == r[3]:
                            open_.pop(r, None)
                            break
        return pa.Table.from_pylist([dict(zip(_BAD.names, (*r, d), strict=True)) for r, d in open_.items()], _BAD)

    return check


def _fetcher(k: int, bits: int):
    """The words of stretches, from a document that has them: ``(f, run)``."""

    def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            runs = []
            for text, h, n, digest in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                w = W.Words(*next(iter(W.chunks(pa.array([text]))))[2:])
                g, at = w.windows(k)
                for a in at[_narrow(g, bits).view(np.int64) == h].tolist():
                    if hashlib.sha256(run := w.bytes_of(a, a + n + k - 1)).digest() == digest:
                        break
                runs.append(run.decode())
            yield pa.RecordBatch.from_arrays([b.column(4), pa.array(runs, pa.string())], ["f", "run"])

    return fetch


def _scattered(k: int):
    """Stretches of which some window is nowhere in the older document; a stretch may also match in pieces."""

    def windows(text: str) -> set[tuple[str, ...]]:
        x = re.findall(r"[^\x20\x09-\x0D]+", text)
        return {tuple(x[i : i + k]) for i in range(len(x) - k + 1)}

    def check(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            bad = [not windows(run) <= windows(text) for text, run in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(bad)], ["bad"])

    return check


def _unverified(docs: DataFrame, asked: DataFrame, parts: int, k: int, bits: int, scratch: Scratch, partitions: int) -> int:
    parted = _with_part(docs, parts)
    bad = scratch.keep(parted.groupBy("part").cogroup(asked.groupBy("part")).applyInArrow(_checker(k, bits), BAD), "open", partitions)
    if not bad.head(1):
        return 0
    owner = docs.withColumnRenamed("doc_id", "d").select("d", "text")
    runs = owner.join(bad, "d").select("text", "h", "n", "digest", "f").mapInArrow(_fetcher(k, bits), "f long, run string")
    older = docs.withColumnRenamed("doc_id", "f").select("f", "text")
    return older.join(runs, "f").select("text", "run").mapInArrow(_scattered(k), "bad boolean").where("bad").count()


class FingerprintIndex:
    """A log-structured index of window hashes in the shared folder."""

    def __init__(self, spark: SparkSession, expected_bytes: int, k: int = K, max_runs: int = 8, bits: int = 64, lanes: int = 1):
        self.spark, self.k, self.max_runs, self.bits, self.lanes = spark, k, max_runs, bits, lanes
        self.buckets = max(8, round(expected_bytes / 6.5 / BUCKET))
        self.parts = odd_at_least(expected_bytes / PART + 7)
        self.partitions = min(partitions_for(expected_bytes), self.buckets)
        self.scratch = Scratch(spark)
        self.name, self.at = f"runs_{uuid.uuid4().hex}", self.scratch.path("runs")
        self.runs: list[int] = []
        self.made = 0

    def hits(self, batch: DataFrame, keep: bool = True) -> DataFrame:
        """Match a batch with the index and itself, and add it to the index: rows of packed hits.

        ``keep=False``: only match. Runs are partitions of one table bucketed by hash
        range, so that the merge reads them in place, without a shuffle.
        """
        ids = batch.where(F.col("doc_id").isNotNull() & F.col("text").isNotNull()).select(F.col("doc_id").cast("long"), "text")
        sent = ids.mapInArrow(_sender(self.k, self.lanes, self.bits, self.parts, self.buckets), SENT)
        compact = keep and len(self.runs) >= self.max_runs
        merge = _merger(self.lanes, self.parts, self.buckets, compact)
        if self.runs:
            old = self.spark.table(self.name).where((F.col("kind") == "key") & F.col("run").isin(self.runs)).select(*_SENT.names)
            both = old.groupBy("bucket").cogroup(sent.groupBy("bucket")).applyInArrow(merge, SENT)
        else:
            both = sent.groupBy("bucket").applyInArrow(_first_run(merge), SENT)
        if not keep:
            return both.where("kind = 'hit'").select("part", "h", "h2", "d", "f")
        self.made += 1
        out = both.withColumn("run", F.lit(self.made)).write.option("compression", "zstd").bucketBy(min(self.buckets, 4096), "bucket").partitionBy("run", "kind")
        with writing(self.spark, self.partitions):
            out.mode("append").option("path", self.at).saveAsTable(self.name)
        self.spark.catalog.refreshTable(self.name)
        if compact:
            for r in self.runs:
                self.scratch.drop(f"{self.at}/run={r}/kind=key")
                self.spark.sql(f"ALTER TABLE {self.name} DROP IF EXISTS PARTITION (run = {r}, kind = 'key')")
            self.runs = []
        self.runs.append(self.made)
        self.scratch.free()
        return self.spark.table(self.name).where((F.col("kind") == "hit") & (F.col("run") == self.made)).select("part", "h", "h2", "d", "f")

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        self.scratch.drop(self.scratch.base)


def _with_part(docs: DataFrame, parts: int) -> DataFrame:
    return docs.select(F.coalesce(F.pmod(F.col("doc_id"), F.lit(parts)), F.lit(0)).cast("long").alias("part"), F.col("doc_id").cast("long").alias("doc_id"), "text")


def _once(docs: DataFrame, batches: list[DataFrame], index: FingerprintIndex, want_text: bool) -> tuple[DataFrame, int]:
    found = None
    scratch = Scratch(index.spark)
    for i, b in enumerate(batches):
        hits = index.hits(b, keep=i + 1 < len(batches))
        found = hits if found is None else found.unionByName(hits)
    found = scratch.keep(found, "hits", index.partitions)
    index.drop()
    parted = _with_part(docs, index.parts)
    marked = parted.groupBy("part").cogroup(found.groupBy("part")).applyInArrow(_marker(index.k, index.lanes, index.bits, want_text), OUT)
    marked = scratch.keep(marked, "marked", index.partitions)
    scratch.drop(found)
    asked = marked.where("kind = 'ask'").groupBy("f", "h", "n", "digest").agg(F.min("doc_id").alias("d")).withColumn("part", F.pmod("f", F.lit(index.parts)).cast("long"))
    bad = _unverified(docs, asked, index.parts, index.k, index.bits, scratch, index.partitions)
    scratch.free()
    return marked.where("kind = 'doc'").select("doc_id", "n_words", "n_removed", "text", "kept_sha256"), bad


def dedup(docs: DataFrame, k: int = K, batches: int = 2, bits: int = 64, lanes: int = 1, max_runs: int = 8, want_text: bool = True) -> DataFrame:
    """``(doc_id, n_words, n_removed, text, kept_sha256)`` of every document.

    The documents are ingested in ``batches`` ranges of ``doc_id``, oldest first.
    """
    spark = docs.sparkSession
    size, low, high = docs.agg(F.sum(F.octet_length("text")), F.min("doc_id"), F.max("doc_id")).first()
    low, high = low or 0, high or 0
    edges = [low + (high + 1 - low) * i // batches for i in range(batches + 1)]
    parts = [docs.where((F.col("doc_id") >= a) & (F.col("doc_id") < b)) for a, b in zip(edges, edges[1:], strict=False) if b > a or (low == high and a == edges[0])]
    for n, b in [(lanes, bits), (2, 64)]:
        out, bad = _once(docs, parts or [docs], FingerprintIndex(spark, size or 0, k, max_runs, b, n), want_text)
        if not bad:
            return out
    raise RuntimeError(f"{bad} matches could not be verified")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return dedup(docs, want_text=False).select("doc_id", "n_words", "n_removed", "kept_sha256")
