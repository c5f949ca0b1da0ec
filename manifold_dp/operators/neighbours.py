"""Exact nearest neighbours, and sums of small matrices over rows: shared by the operators."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources import width
from .arrays import LAST, nearest

#: Bytes of queries, and else of searched rows, that may be sent to every task; rows of a block of either beyond that.
SENT, HELD, ROWS = 16 << 20, 64 << 20, 65536
FOUND = "query_id long, match_id long, dist double"
_FOUND = ["query_id", "match_id", "dist"]


def matrix(lists: pa.Array | pa.ChunkedArray, rows: int) -> np.ndarray:
    if isinstance(lists, pa.ChunkedArray):
        lists = lists.combine_chunks()
    flat = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(rows, -1) if rows else np.empty((0, 0))


def lists(m: np.ndarray) -> pa.ListArray:
    n, d = m.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * d, pa.int32()), pa.array(np.ascontiguousarray(m).ravel()))


def vector_sum(col: str, size: int) -> list[Column]:
    return [F.sum(F.element_at(col, i + 1)).alias(f"_s{i}") for i in range(size)]


def as_vector(size: int, name: str) -> Column:
    return F.array(*(F.col(f"_s{i}") for i in range(size))).alias(name)


def summed(df: DataFrame, f: Callable[[pa.RecordBatch], np.ndarray], rows: int, cols: int) -> np.ndarray:
    """The sum of ``f`` (a matrix of ``rows`` x ``cols``) over all batches: one partial matrix a task, added up by row."""

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((rows, cols))
        for b in batches:
            if b.num_rows:
                total += f(b)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(rows, dtype=np.int32)), lists(total)], ["r", "s"])

    if not rows or not cols:
        return np.zeros((rows, cols))
    got = df.mapInArrow(sums, "r int, s array<double>").groupBy("r").agg(*vector_sum("s", cols)).collect()  # ``rows`` rows
    out = np.zeros((rows, cols))
    for row in got:
        out[row.r] = [row[f"_s{k}"] for k in range(cols)]
    return out


#: Pairs of rows that one task compares, about; rows that may be dealt anew for that.
SHARE, FEW = 20_000_000, 200_000


def dealt(rows: DataFrame, pairs: int) -> DataFrame:
    """Rows of a table of bounded size over as many tasks as their pairs make worthwhile: a small file would be one."""
    tasks = min(-(-pairs // SHARE), 4 * rows.sparkSession.sparkContext.defaultParallelism)
    return rows.repartition(tasks, "id") if tasks > 1 else rows


def every(n: int) -> Column:
    return F.explode(F.sequence(F.lit(0), F.lit(n - 1)))


def block(key: Column, n: int) -> Column:
    return F.pmod(F.xxhash64(key), F.lit(n)).cast("int")


def cells(left: int, right: int, cores: int) -> tuple[int, int]:
    """Blocks of two tables whose blocks all meet: of ``ROWS`` rows at most, and two cells a core, or fewer if they would compare little."""
    a, b = (max(1, -(-n // ROWS)) for n in (left, right))
    goal = min(2 * cores, -(-left * right // SHARE))
    while a * b < goal:
        a, b = (a + 1, b) if left / a >= right / b else (a, b + 1)
    return a, b


def _rows_of(qid: np.ndarray, ids: np.ndarray, dist: np.ndarray) -> list[pa.Array]:
    there = np.isfinite(dist)
    return [pa.array(np.broadcast_to(qid[:, None], ids.shape)[there]), pa.array(ids[there]), pa.array(dist[there])]


def near_of(qid: np.ndarray, x: np.ndarray, rid: np.ndarray, y: np.ndarray, k: int, metric: str = "l2", skip_self: bool = True) -> pa.Table:
    """What ``nearest`` finds, as rows of ``FOUND``."""
    if not len(qid) or not len(rid):
        return pa.table([pa.array([], pa.int64()), pa.array([], pa.int64()), pa.array([], pa.float64())], names=_FOUND)
    return pa.table(_rows_of(qid, *nearest(qid, x, rid, y, k, metric, skip_self)), names=_FOUND)


def knn(queries: DataFrame, rows: DataFrame, k: int, metric: str = "l2", skip_self: bool = True, sent: int = SENT) -> DataFrame:
    """``(query_id, match_id, dist, rank)``: the k nearest of ``rows (id, v)`` to each of ``queries (id, v)``.

    Exact. Queries of ``sent`` bytes at most are sent to all tasks and rows stay where they
    are; else rows of ``HELD`` bytes at most are sent (unless ``sent`` is 0) and queries dealt
    out; more are dealt into blocks, both of them, as few as tasks can hold and are busy with,
    and each block meets each other one in a task of its own by shuffle, so nothing but a
    count reaches the driver. A task returns k rows a query at most. Distances count to 12 decimals, ties go to the smaller id. ``metric``:
    ``l2`` (squared) or ``cosine`` (1 - cosine).
    """
    queries, rows = queries.select("id", "v"), rows.select("id", "v")
    n, d = queries.agg(F.count(F.lit(1)), F.max(F.size("v"))).first()
    names = _FOUND
    if n * ((d or 0) + 1) * 8 <= sent:
        q = queries.orderBy("id").toArrow()
        data = queries.sparkSession.sparkContext.broadcast((q["id"].to_numpy(), matrix(q["v"], len(q))))

        def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            qid, x = data.value
            held = [b for b in batches if b.num_rows] if len(qid) else []
            best: tuple[np.ndarray, np.ndarray] | None = None
            for b in held:
                ids, dist = nearest(qid, x, b.column(0).to_numpy(), matrix(b.column(1), b.num_rows), k, metric, skip_self)
                if best is not None:  # the k best of both
                    ids, dist = np.c_[best[0], ids], np.c_[best[1], dist]
                    order = np.lexsort((ids, dist), axis=1)[:, :k]
                    ids, dist = np.take_along_axis(ids, order, 1), np.take_along_axis(dist, order, 1)
                best = ids, dist
            if best is not None:
                yield pa.RecordBatch.from_arrays(_rows_of(qid, *best), names)

        few = rows.limit(FEW + 1).count()
        found = (dealt(rows, n * few) if few <= FEW else rows).mapInArrow(search, FOUND)
    else:
        of = rows.count()
        if sent and of * ((d or 0) + 1) * 8 <= HELD:
            r = rows.orderBy("id").toArrow()
            data = queries.sparkSession.sparkContext.broadcast((r["id"].to_numpy(), matrix(r["v"], len(r))))

            def answer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                ids, y = data.value
                for b in batches:
                    if b.num_rows:
                        qid = b.column(0).to_numpy()
                        yield from near_of(qid, matrix(b.column(1), b.num_rows), ids, y, k, metric, skip_self).to_batches()

            found = dealt(queries, n * of).mapInArrow(answer, FOUND)
        else:
            blocks, parts = cells(n, of, rows.sparkSession.sparkContext.defaultParallelism)
            q = queries.select(F.col("id").alias("qid"), F.col("v").alias("qv"), block(F.col("id"), blocks).alias("qb"), every(parts).alias("rb"))
            r = rows.select(F.col("id").alias("rid"), F.col("v").alias("rv"), block(F.col("id"), parts).alias("rb"), every(blocks).alias("qb"))

            def meet(a: pa.Table, b: pa.Table) -> pa.Table:
                return near_of(a["qid"].to_numpy(), matrix(a["qv"], len(a)), b["rid"].to_numpy(), matrix(b["rv"], len(b)), k, metric, skip_self)

            found = q.groupBy("qb", "rb").cogroup(r.groupBy("qb", "rb")).applyInArrow(meet, FOUND)
    w = Window.partitionBy("query_id").orderBy("dist", "match_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


__all__ = ["LAST", "as_vector", "block", "cells", "dealt", "every", "knn", "lists", "matrix", "summed", "vector_sum", "width"]
