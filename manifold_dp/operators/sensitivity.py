"""How much one added row can move the first contrast step: observed, and bounded.

The constants were derived anew (SURVEY 2.4): with unit rows every weight is at least b,
so degrees are at least (n - 1) b, and each row of the difference matrix is bounded by its
parts: the other columns, the diagonal and the new column.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import known_width, width
from . import arrays
from .kernel import DenseOp, laplacian
from .labels import LabelOp
from .neighbours import ROWS, vector_sum
from .step import contrast_step


def least_weight(sigma: float, domain: str = "sphere") -> float:
    """The least kernel weight between unit rows; ``orthant``: rows without negative entries."""
    return math.exp(-(2.0 if domain == "orthant" else 4.0) / sigma)


def row_bounds(n: int, alpha: float, sigma: float, domain: str = "sphere") -> dict[str, float]:
    """Bounds of the difference matrix's rows for n rows and one more: ``old``, ``new`` and their greatest, ``m``."""
    if n < 2:
        raise ValueError("two rows at least are needed")
    b = least_weight(sigma, domain)
    g = 1 / (1 + (n - 1) * b)
    others = g * (1 / math.sqrt((n - 1) * b) + alpha / (b * math.sqrt(n - 1)))
    diagonal = alpha * g / b
    column = max(g, alpha / (n * b))
    old = math.sqrt(others**2 + diagonal**2 + column**2)
    new = math.sqrt(max(1.0, alpha / b - 1) ** 2 + (1 / math.sqrt(n * b) + alpha / (b * math.sqrt(n))) ** 2)
    return {"old": old, "new": new, "m": max(old, new)}


def bound_for(n: int, alpha: float, sigma: float, q_norm: float, form: str = "uniform", domain: str = "sphere", q_spectral: float | None = None) -> float:
    """A bound of the change of the step from n rows to n + 1, given the norm of the start matrix of n + 1 rows. ``uniform``: M sqrt(n + 1) |Q|_F / 2; ``row_split``: old and new rows by their own bounds; ``spectral``: the latter with |Q|_2."""
    r = row_bounds(n, alpha, sigma, domain)
    if form == "uniform":
        return r["m"] / 2 * math.sqrt(n + 1) * q_norm
    split = math.sqrt(n * r["old"] ** 2 + r["new"] ** 2) / 2
    if form == "row_split":
        return split * q_norm
    if form == "spectral":
        return split * (q_spectral if q_spectral is not None else q_norm)
    raise ValueError(f"unknown form {form}")


def _squares(q: DataFrame) -> float:
    return q.agg(F.sum(F.aggregate("v", F.lit(0.0), lambda s, z: s + z * z))).first()[0] or 0.0


def q_norm(q: DataFrame) -> float:
    return math.sqrt(_squares(q))


@dataclass
class StartNorms:
    """Norms of the start matrix: over the rows that are there, and padded by the row of one newcomer.

    A neighbouring data set has one row more, so its start matrix does too. ``reserve``: the
    newcomer gets the next free id, whose row of the (public) start matrix is known. ``tail``:
    a bound of the norm of so many normal entries that fails with probability ``beta``, which
    the caller takes off delta; it needs no look at the matrix.
    """

    own: float
    padded: float
    spectral: float | None = None
    spectral_padded: float | None = None
    beta: float = 0.0


def start_norms(q: DataFrame, seed: int | str, sigma_q: float, spectral: bool = False) -> StartNorms:
    """The norms of ``q``, padded by the row of the id after the greatest."""
    m = width(q)
    squares, top = q.agg(F.sum(F.aggregate("v", F.lit(0.0), lambda s, z: s + z * z)), F.max("id")).first()
    extra = sigma_q * arrays.normals(seed, np.array([(top if top is not None else -1) + 1]), m)[0]
    out = StartNorms(math.sqrt(squares or 0.0), math.sqrt((squares or 0.0) + float(extra @ extra)))
    if spectral:
        from .maps import gram

        g = gram(q)
        out.spectral, out.spectral_padded = (math.sqrt(max(0.0, float(np.linalg.eigvalsh(x)[-1]))) for x in (g, g + np.outer(extra, extra)))
    return out


def tail_norms(n: int, m: int, sigma_q: float, beta: float) -> StartNorms:
    """Bounds of the norms over n and n + 1 rows of m normal entries, either failing with probability ``beta`` at most."""
    log = math.log(1 / beta)
    own, padded = (sigma_q * math.sqrt(k + 2 * math.sqrt(k * log) + 2 * log) for k in (n * m, (n + 1) * m))
    return StartNorms(own, padded, beta=beta)


def bound(n: int, alpha: float, sigma: float, norms: StartNorms, form: str = "uniform", domain: str = "sphere") -> float:
    """The bound for either neighbour: one row more, whose start matrix is the padded one, or one less (n itself is disclosed by the row count)."""
    cases = [(n, norms.padded, norms.spectral_padded), (n - 1, norms.own, norms.spectral)]
    return max(bound_for(k, alpha, sigma, size, form, domain, top) for k, size, top in cases if k >= 2)


def observed(points: DataFrame, extra: DataFrame, q: DataFrame, sigma: float, alpha: float, sigma_y: float | None = None) -> float:
    """Frobenius gap of the first step with and without the rows of ``extra``; ``q`` has rows for both. Absent rows count as Q, as a Laplacian padded by zeros leaves them."""
    outs = []
    for rows in (points, points.unionByName(extra)):
        own = known_width(q.join(rows.select("id"), "id", "left_semi"), width(q))
        outs.append(contrast_step(own, DenseOp(sigma).over(rows), LabelOp(rows, sigma_y or sigma) if alpha else None, alpha))
    a, b = outs
    j = a.withColumnRenamed("v", "va").join(b.withColumnRenamed("v", "vb"), "id", "full").join(q, "id")
    gap = F.aggregate(F.zip_with(F.coalesce("va", "v"), F.coalesce("vb", "v"), lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, z: s + z)
    return math.sqrt(j.agg(F.sum(gap)).first()[0] or 0.0)


def difference(points: DataFrame, extra: DataFrame, sigma: float, alpha: float, sigma_y: float | None = None) -> DataFrame:
    """``(i, j, value)``: the difference matrix itself, for inputs of test size."""
    sides = []
    for rows in (points, points.unionByName(extra)):
        lx = laplacian(rows, sigma).withColumnRenamed("value", "lx")
        y = rows.where("label IS NOT NULL").select("id", F.array(F.col("label").cast("double")).alias("x"))
        ly = laplacian(y, sigma_y or sigma).withColumnRenamed("value", "ly")
        deg = lx.where("i = j").select("i", F.col("lx").alias("deg"))
        cell = lx.join(ly, ["i", "j"], "left").join(deg, "i").select("i", "j", F.when(F.col("deg") != 0, (F.lit(float(alpha)) * F.coalesce("ly", F.lit(0.0)) - F.col("lx")) / F.col("deg")).otherwise(0.0).alias("c"))
        sides.append(cell)
    a, b = sides
    return a.withColumnRenamed("c", "ca").join(b.withColumnRenamed("c", "cb"), ["i", "j"], "full").select("i", "j", (F.coalesce("ca", F.lit(0.0)) - F.coalesce("cb", F.lit(0.0))).alias("value"))


def difference_norms(points: DataFrame, extra: DataFrame, sigma: float, alpha: float, sigma_y: float | None = None) -> DataFrame:
    """``(i, norm)``: the norms of the difference matrix's rows, without the matrix.

    A row's norm takes six sums over its pairs: weights, label weights and squared entries of
    the step's matrix before its division by the degree, over old and over extra rows. They
    are added up block by block, so nothing of the size of the pairs is kept.
    """
    from .kernel import Arrays, by_blocks

    wide = sigma_y or sigma

    def sums(a: Arrays, b: Arrays) -> tuple[np.ndarray, np.ndarray]:
        out, back = np.zeros((len(a["id"]), 6)), np.zeros((len(b["id"]), 6))
        of_a, of_b = (np.c_[t["old"], ~t["old"]].astype(float) for t in (a, b))
        for j in range(0, len(back), arrays.TILE[1]):
            cols = slice(j, j + arrays.TILE[1])
            codes, place = np.unique(b["label"][cols], return_inverse=True)
            for i in range(0, len(out), arrays.TILE[0]):
                rows = slice(i, i + arrays.TILE[0])
                w = arrays.weights(a["id"][rows], a["x"][rows], b["id"][cols], b["x"][cols], sigma)
                gap = a["label"][rows][:, None] - codes[None]
                y = np.take(np.where(np.isnan(gap), 0.0, np.exp(-gap * gap / wide)), place, axis=1)
                y[arrays.same(a["id"][rows], b["id"][cols])] = 0.0
                c = w - alpha * y
                c *= c
                for k, z in enumerate((w, y, c)):
                    out[rows, 2 * k : 2 * k + 2] += z @ of_b[cols]
                    back[cols, 2 * k : 2 * k + 2] += z.T @ of_a[rows]
        return out, back

    def of(a: Arrays, b: Arrays | None) -> Iterator[Arrays]:
        for t, s in zip((a, b) if b is not None else (a,), sums(a, a if b is None else b), strict=False):
            yield {"id": t["id"], "old": t["old"], "s": s}

    both = points.withColumn("old", F.lit(True)).unionByName(extra.withColumn("old", F.lit(False))).withColumn("label", F.col("label").cast("double"))
    parts = by_blocks(both, of, "id long, old boolean, s array<double>", "label", "old", side=ROWS)
    added = parts.groupBy("id", "old").agg(*vector_sum("s", 6))
    deg, more, e, e_more, square, square_more = (F.col(f"_s{k}") for k in range(6))
    whole = deg + more
    fresh = (square + square_more) / (whole * whole) + F.pow((alpha * (e + e_more) - whole) / whole, 2)  # no such row before
    moved = square * F.pow(more / (deg * whole), 2) + square_more / (whole * whole) + F.pow(alpha * (e * more - e_more * deg) / (deg * whole), 2)
    return added.select(F.col("id").alias("i"), F.when(whole == 0, 0.0).otherwise(F.sqrt(F.when(F.col("old") & (deg != 0), moved).otherwise(fresh))).alias("norm"))
