"""Exact top-k inner-product search with block-at-a-time pruning.

Components become integers ``floor(scale * x)``; the score of a query and a row is the
integer inner product. Rows are cut into blocks as they are stored ("document ranges").
A block has the greatest and least value of each component ("term maxima"), whose products
with a query sum to a bound no row of the block exceeds. Per query the blocks are taken by
falling bound and scored through the block's matrix ("forward index"), until the bound
falls below the query's kth score so far; bounds equal to it still count, for ties.

Queries are stated rows. Up to ``QUERIES`` of them (and ``SENT`` bytes) are sent to all
tasks, and rows stay where they are. More are dealt into blocks by hash, rows into parts of
about ``HELD``, and each block meets each part in a task of its own by shuffle, so neither
the driver nor a task holds more than one block of queries and one part of rows at any
size. Each task returns at most k rows a query; ranks come from those. Equal query rows are
searched for once.

Defined results: vectors that are null or hold null or non-finite components take no
part; only vectors of one length are compared; ties go to the smaller ``vec_id`` (null
last); every row but those with the query's own id is a candidate, equal rows each; a
query with fewer candidates gets all; sums beyond 64 bits stop at the 64-bit limits;
other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

SCALE, K = 256.0, 5
#: Queries sent at once, rows of a block, rows held at once.
QUERIES, BLOCK, HELD = 4096, 512, 65536
SENT = 64 << 20
FOUND = "slot long, query_id long, copies long, vec_id long, score long"
NAMES = ["slot", "query_id", "copies", "vec_id", "score"]
_SCHEMA = pa.schema([(c, pa.int64()) for c in NAMES])
LAST = np.iinfo(np.int64).max


def usable(df: DataFrame, vector: str = "embedding") -> DataFrame:
    v = F.col(vector)
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x.cast("double")) == float("inf")))
    return df.where(v.isNotNull() & ~bad)


class _Best:
    """The k best rows of each query so far: greater score first, then smaller id."""

    def __init__(self, n: int, k: int):
        self.k, self.score, self.ids = k, np.full((n, k), -np.inf), np.full((n, k), LAST)

    def kth(self) -> np.ndarray:
        return self.score[:, -1]

    def add(self, q: np.ndarray, scores: np.ndarray, ids: np.ndarray) -> None:
        """``scores``: a row for each query number in ``q``, a column for each of ``ids``."""
        least = self.score[q, -1]
        if scores.shape[1] > self.k:
            least = np.maximum(least, np.partition(scores, -self.k, axis=1)[:, -self.k])
        at, col = np.nonzero((scores >= least[:, None]) & (scores > -np.inf))
        if not len(at):
            return
        hit = np.unique(at)
        who = np.r_[at, np.repeat(hit, self.k)]
        score = np.r_[scores[at, col], self.score[q[hit]].ravel()]
        row = np.r_[ids[col], self.ids[q[hit]].ravel()]
        order = np.lexsort((row, -score, who))
        who, score, row = who[order], score[order], row[order]
        place = np.arange(len(who)) - np.searchsorted(who, who)
        top = place < self.k
        self.score[q[who[top]], place[top]] = score[top]
        self.ids[q[who[top]], place[top]] = row[top]


def _packed(queries: pa.Table, scale: float) -> dict[int, tuple[np.ndarray, ...]]:
    """``(slot, query_id, copies, v)`` as arrays, by length of the vector: slots, ids, copies and integer vectors."""
    out = {}
    v = queries["v"].combine_chunks() if queries.num_rows else pa.array([], pa.list_(pa.float64()))
    size = pa.compute.list_value_length(v).to_numpy(zero_copy_only=False)
    for d in np.unique(size).tolist():
        at = pa.array(np.flatnonzero(size == d))
        some = queries.take(at)
        flat = v.take(at).flatten().to_numpy(zero_copy_only=False)
        out[d] = (*(some[c].to_numpy() for c in NAMES[:3]), np.floor(scale * flat).reshape(len(at), d))
    return out


def _search(queries: dict[int, tuple[np.ndarray, ...]], k: int, scale: float):
    """``queries`` as ``_packed`` gives them."""

    def scan(best: _Best, qid: np.ndarray, q: np.ndarray, ids: np.ndarray, rows: np.ndarray) -> None:
        cuts = range(0, len(ids), BLOCK)
        top = np.array([rows[i : i + BLOCK].max(0) for i in cuts])
        low = np.array([rows[i : i + BLOCK].min(0) for i in cuts])
        bound = np.where(q > 0, q, 0) @ top.T + np.where(q < 0, q, 0) @ low.T
        order = np.argsort(-bound, axis=1, kind="stable")
        for rank in range(bound.shape[1]):
            block = order[:, rank]
            open_ = np.flatnonzero(bound[np.arange(len(q)), block] >= best.kth())
            if not len(open_):
                break
            by = open_[np.argsort(block[open_], kind="stable")]
            for some in np.split(by, np.flatnonzero(np.diff(block[by])) + 1):
                s = slice(int(block[some[0]]) * BLOCK, (int(block[some[0]]) + 1) * BLOCK)
                scores = (q[some] @ rows[s].T).astype(np.float64)
                scores[ids[s][None, :] == qid[some][:, None]] = -np.inf
                best.add(some, scores, ids[s])

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = {d: _Best(len(q[0]), k) for d, q in queries.items()}
        held: dict[int, list] = {d: [] for d in queries}

        def flush(d: int) -> None:
            if held[d]:
                ids, rows = (np.concatenate(x) for x in zip(*held[d], strict=True))
                scan(best[d], queries[d][1], queries[d][3], ids, rows)
                held[d] = []

        for b in batches:
            ids = b.column(0).fill_null(LAST).to_numpy(zero_copy_only=False)
            size = pa.compute.list_value_length(b.column(1)).to_numpy(zero_copy_only=False)
            for d in np.unique(size).tolist():
                if d not in queries:
                    continue
                at = np.flatnonzero(size == d)
                flat = b.column(1).take(pa.array(at)).flatten().to_numpy(zero_copy_only=False).astype(np.float64)
                held[d].append((ids[at], np.floor(scale * flat).reshape(len(at), d)))
                if sum(len(x[0]) for x in held[d]) >= HELD:
                    flush(d)
        for d, (slots, qid, copies, _) in queries.items():
            flush(d)
            at, place = np.nonzero(best[d].score > -np.inf)
            ids = best[d].ids[at, place]
            yield pa.RecordBatch.from_arrays([*(pa.array(c[at], pa.int64()) for c in (slots, qid, copies)), pa.array(ids, mask=ids == LAST), pa.array(best[d].score[at, place].astype(np.int64))], NAMES)

    return search


def _exact(queries: list[tuple], k: int, scale: float):
    """The same for vectors so large that float64 sums may round: Python integers, row by row."""

    def whole(v) -> list[int]:
        return [int(x) for x in np.floor(scale * np.asarray(v, np.float64)).tolist()]

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qs = [(i, qid, whole(v)) for i, (_, qid, _, v) in enumerate(queries)]
        best: dict[int, list] = {i: [] for i, *_ in qs}
        for b in batches:
            for r, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                x = whole(v)
                for i, qid, q in qs:
                    if len(q) == len(x) and r != qid:
                        score = min(max(sum(a * c for a, c in zip(q, x, strict=True)), -LAST - 1), LAST)
                        best[i] = sorted([*best[i], (-score, LAST if r is None else r)])[:k]
        rows = [(*queries[i][:3], None if r == LAST else r, -s) for i, *_ in qs for s, r in best[i]]
        yield pa.RecordBatch.from_pylist([dict(zip(NAMES, r, strict=True)) for r in rows], _SCHEMA)

    return search


def _scanner(queries: pa.Table, k: int, scale: float, fits: bool):
    if fits:
        return _search(_packed(queries, scale), k, scale)
    return _exact(list(zip(*(queries[c].to_pylist() for c in (*NAMES[:3], "v")), strict=True)), k, scale)


def topk(rows: DataFrame, is_query: Column, k: int = K, scale: float = SCALE, vector: str = "embedding", at_once: int = QUERIES, held: int = HELD) -> DataFrame:
    """``(query_id, rank, vec_id, score)`` of the k best rows of each query row."""
    rows = usable(rows, vector).select(F.col("vec_id").cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("v"))
    most = F.array_max(F.transform("v", F.abs))
    total, n, largest_query, largest, longest = rows.agg(F.count(F.lit(1)), F.count(F.when(is_query, 1)), F.max(F.when(is_query, most)), F.max(most), F.max(F.size("v"))).first()
    longest = max(1, longest or 1)
    fits = (scale * (largest_query or 0.0) + 1) * (scale * (largest or 0.0) + 1) * longest < 2.0**53  # all sums are exact in float64
    slot = F.xxhash64("vec_id", "v")
    stated = rows.where(is_query).groupBy("vec_id", "v").agg(F.count(F.lit(1)).alias("copies")).select(slot.alias("slot"), F.col("vec_id").alias("query_id"), "copies", "v")
    blocks = max(1, -(-n // at_once), -(-n * longest * 8 // SENT))
    if blocks == 1:
        found = rows.mapInArrow(_scanner(stated.toArrow(), k, scale, fits), FOUND)
    else:
        parts = max(1, -(-total // held))
        every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
        dealt = lambda c, n: F.pmod(c, F.lit(n)).cast("int")
        q = stated.withColumn("block", dealt(F.col("slot"), blocks)).withColumn("part", every(parts))
        r = rows.withColumn("part", dealt(slot, parts)).withColumn("block", every(blocks))

        def meet(queries: pa.Table, some: pa.Table) -> pa.Table:
            scan = _scanner(queries, k, scale, fits)
            return pa.Table.from_batches(list(scan(iter(some.select(["vec_id", "v"]).to_batches()))), _SCHEMA)

        found = q.groupBy("block", "part").cogroup(r.groupBy("block", "part")).applyInArrow(meet, FOUND)
    w = Window.partitionBy("query_id", "slot").orderBy(F.desc("score"), F.asc_nulls_last("vec_id"))
    top = found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
    return top.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), "copies"))).select("query_id", "rank", "vec_id", "score")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256e0 * CAST(x AS DOUBLE)) AS BIGINT)) AS x
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id,
    CAST(list_sum(list_transform(generate_series(1, len(q.x)), lambda i: q.x[i] * c.x[i])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.x) = len(c.x) WHERE q.vec_id % 50 = 0
), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
