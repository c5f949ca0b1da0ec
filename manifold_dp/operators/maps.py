"""The spectral map and its kin, and small matrices applied to rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources import cut, drop, known_width, width
from .kernel import DenseOp, Op
from .neighbours import lists, matrix, summed
from .noise import start_matrix


def gram(v: DataFrame, left: str = "v", right: str = "v", weight: Column | None = None) -> np.ndarray:
    """left' diag(weight) right: one partial matrix a task, added up."""
    m, k = width(v, left), width(v, right)
    rows = v.select(F.col(left).alias("a"), F.col(right).alias("b"), (F.lit(1.0) if weight is None else weight).alias("w"))
    return summed(rows, lambda b: (matrix(b.column(0), b.num_rows) * b.column(2).to_numpy()[:, None]).T @ matrix(b.column(1), b.num_rows), m, k)


def times(v: DataFrame, by: np.ndarray, col: str = "v", shift: np.ndarray | None = None) -> DataFrame:
    """Each row times a small matrix, plus ``shift``; other columns stay."""
    at, names = v.columns.index(col), v.columns

    def multiply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                new = matrix(b.column(at), b.num_rows) @ by
                yield pa.RecordBatch.from_arrays([*b.columns[:at], lists(new if shift is None else new + shift), *b.columns[at + 1 :]], names)

    schema = T.StructType([T.StructField(f.name, T.ArrayType(T.DoubleType())) if f.name == col else f for f in v.schema])
    return known_width(v.mapInArrow(multiply, schema), by.shape[1], col)


def _less(rows: DataFrame, c: np.ndarray) -> DataFrame:
    """``(id, deg, b, v)`` with b c taken off v."""

    def take(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in batches:
            if n := t.num_rows:
                yield pa.RecordBatch.from_arrays([t.column(0), t.column(1), t.column(2), lists(matrix(t.column(3), n) - matrix(t.column(2), n) @ c)], ["id", "deg", "b", "v"])

    out = rows.select("id", "deg", "b", "v").mapInArrow(take, "id long, deg double, b array<double>, v array<double>")
    return known_width(known_width(out, c.shape[0], "b"), c.shape[1])


def _root(g: np.ndarray, least: float = 1e-18) -> tuple[np.ndarray, np.ndarray]:
    """S and its right inverse R: vectors with Gram matrix g, times R, are orthonormal, and times S they are back; directions of next to no length are left out."""
    values, vectors = np.linalg.eigh((g + g.T) / 2)
    keep = values > least
    size, turn = np.sqrt(values[keep]), vectors[:, keep]
    return size[:, None] * turn.T, turn / size


def spectral(points: DataFrame, sigma: float, m: int, op: Op | None = None, iterations: int = 30, seed: int = 1, power: float | None = None, tol: float = 1e-8, block: int = 16) -> tuple[DataFrame, list[float]]:
    """The m smallest non-trivial solutions of L u = lambda D u, with u' D u = 1, and their lambdas.

    The greatest eigenvalues of D^-1 W on the space that ``block`` start columns (m + 1 at least) and their
    products span, orthonormal with the degrees as weights: each round is one product and sums
    of small matrices. It ends when all residuals are below ``tol``, after ``iterations``
    rounds, or when there is nothing new. ``power`` weighs each by (1 - lambda)^power: the diffusion map.
    """
    spark = points.sparkSession
    op = (op or DenseOp(sigma)).over(points)
    k, wide = m + 1, max(m + 1, block)
    v, held, last, h = start_matrix(points, wide, 1.0, seed), None, [], np.zeros((0, 0))
    for t in range(1, iterations + 1):
        new = cut(op.apply(v).select("id", "deg", "v", F.transform("wv", lambda z: z / F.nullif(F.col("deg"), F.lit(0.0))).alias("p")), "product")
        rows = new.select("id", "deg", *(F.when(F.col("deg") > 0, F.col(c)).otherwise(F.array_repeat(F.lit(0.0), width(v))).alias(c) for c in ("v", "p")))
        rows = known_width(known_width(rows, width(v)), width(v), "p")
        if held is None:
            _, r = _root(gram(rows, weight=F.col("deg")))
            rows = times(times(rows, r), r, "p").select("id", "deg", F.col("v").alias("b"), F.col("p").alias("v"))
        else:
            rows = rows.select("id", "deg", F.col("p").alias("v")).join(held.select("id", "b"), "id").select("id", "deg", "b", "v")
        size = len(h) + (r.shape[1] if held is None else width(v))
        rows = known_width(known_width(rows, size, "b"), size - len(h))
        c = gram(rows, "b", "v", F.col("deg"))
        grown = np.zeros((size, size))
        grown[: len(h), : len(h)] = h
        grown[:, len(h) :] = c
        grown[len(h) :, :] = c.T
        h = (grown + grown.T) / 2
        rest = cut(_less(rows, c), "rest")
        rest = known_width(known_width(rest, size, "b"), c.shape[1])
        again = gram(rest, "b", "v", F.col("deg"))  # what rounding left
        clean = _less(rest, again)
        s, r = _root(gram(clean, weight=F.col("deg")))
        values, vectors = np.linalg.eigh(h)
        far = np.linalg.norm(s @ vectors[-c.shape[1] :, -k:], axis=0).max() if len(s) else 0.0
        drop(spark, *last, new)
        if far <= tol or t == iterations:
            break
        joined = times(clean, r).select("id", F.col("v"), F.concat("b", "v").alias("b"))
        held = cut(joined, "basis")
        drop(spark, rest)
        last = [held]
        v = known_width(held.select("id", "v"), r.shape[1])
    order = np.argsort(-values)[1:k]
    values = 1 - values[order]
    rotate = vectors[:, order]
    if power is not None:
        rotate = rotate * (1 - values) ** power
    return times(known_width(rest.select("id", F.col("b").alias("v")), size), rotate).select("id", "v"), values.tolist()
