"""The contrast step, its iteration and the bound that proves its descent."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..sources import cut, drop, known_width, width
from .kernel import DenseOp, Op, laplacian_product
from .labels import LabelOp
from .noise import start_matrix, start_row


def _moved(v: DataFrame, op: Op, labels: LabelOp | None, alpha: float) -> DataFrame:
    """``(id, v, change, new)``: the rows, alpha L_Y V - L_X V, and the rows after the step."""
    rows = op.apply(v)
    half = F.when(F.col("deg") != 0, F.lit(0.5) / F.col("deg")).otherwise(F.lit(0.0))
    change = F.zip_with("v", "wv", lambda a, b: b - a * F.col("deg"))
    if alpha and labels is not None:
        rows = labels.apply(v, rows)
        change = F.zip_with(change, "lv", lambda lx, ly: lx + F.lit(float(alpha)) * ly)
    return rows.select("id", "v", change.alias("change"), half.alias("half")).select("id", "v", "change", F.zip_with("v", "change", lambda a, c: a + F.col("half") * c).alias("new"))


def contrast_step(v: DataFrame, op: Op, labels: LabelOp | None, alpha: float) -> DataFrame:
    """``(id, v)``: V + (1/2) pinv(Diag L_X) (alpha L_Y V - L_X V). A row of degree 0 stays as it is."""
    return known_width(_moved(v, op, labels, alpha).select("id", F.col("new").alias("v")), width(v))


def _dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, z: s + z)


def objective(v: DataFrame, op: Op, labels: LabelOp | None, alpha: float) -> float:
    """tr(V' L_X V) - alpha tr(V' L_Y V)."""
    x = laplacian_product(op, v).agg(F.sum(_dot("v", "lv"))).first()[0] or 0.0
    return x - (alpha * (labels.apply(v).agg(F.sum(_dot("v", "lv"))).first()[0] or 0.0) if alpha and labels is not None else 0.0)


def majorant(v: DataFrame, v0: DataFrame, op: Op, labels: LabelOp | None, alpha: float) -> float:
    """The quadratic bound of the objective that touches it at ``v0``: F(v0) + 2 <F v0, v - v0> + 2 |v - v0|^2 in the degrees' norm."""
    base = objective(v0, op, labels, alpha)
    g = laplacian_product(op, v0).withColumnRenamed("lv", "lx")
    if alpha and labels is not None:
        g = labels.apply(v0, g).withColumn("lx", F.zip_with("lx", "lv", lambda a, b: a - F.lit(float(alpha)) * b))
    j = g.select("id", F.col("v").alias("v0"), "deg", "lx").join(v.select("id", "v"), "id").withColumn("gap", F.zip_with("v", "v0", lambda a, b: a - b))
    return base + j.agg(F.sum(2 * _dot("lx", "gap") + 2 * F.col("deg") * _dot("gap", "gap"))).first()[0]


@dataclass
class Run:
    """An iterated map: the last embedding, and what each step recorded."""

    v: DataFrame
    log: list[dict] = field(default_factory=list)
    steps: list[DataFrame] = field(default_factory=list)


def run(
    points: DataFrame,
    m: int,
    sigma: float,
    alpha: float,
    steps: int = 7,
    seed: int | str = 1,
    op: Op | None = None,
    sigma_y: float | None = None,
    label_kernel: str = "gaussian_code",
    tol: float | None = None,
    rescale: bool = False,
    start: DataFrame | None = None,
    sigma_q: float = 1.0,
    monitor: bool = False,
    keep: bool = False,
    write: Callable[[DataFrame, str], DataFrame] = cut,
) -> Run:
    """``steps`` contrast steps from a start matrix (or ``start``), each written before the next.

    ``rescale`` divides by the root mean square each step and records its logarithm: ranks
    do not change and nothing overflows. ``tol`` stops when the objective's relative
    change falls below it. With ``monitor`` alone, the objective of a step is counted by the product
    of the next one. ``keep`` returns every step's embedding; else a step's table is
    deleted once the next one is written. ``write`` writes them.
    """
    op = (op or DenseOp(sigma)).over(points)
    labels = LabelOp(points, sigma_y if sigma_y is not None else sigma, label_kernel) if alpha else None
    v = start if start is not None else start_matrix(points, m, sigma_q, seed)
    spark = v.sparkSession
    v = written = known_width(write(v.select("id", "v"), "v"), m)
    out = Run(v, [], [v] if keep else [])
    last = objective(v, op, labels, alpha) if tol is not None else None
    scale = 0.0
    if monitor or tol is not None:
        out.log.append({"t": 0, "objective": last, "log_scale": 0.0})
    for t in range(1, steps + 1):
        seen = Observation()
        moved = _moved(v, op, labels, alpha)
        counts = [F.sum(_dot("new", "new")).alias("squares"), F.count(F.lit(1)).alias("rows")] if rescale else []
        if monitor and tol is None:
            counts.append((-F.sum(_dot("v", "change"))).alias("objective"))
        if counts:  # counted while it is written
            moved = moved.observe(seen, *counts)
        new = known_width(write(moved.select("id", F.col("new").alias("v")), "v"), m)
        if not keep:
            drop(spark, written)
        v = written = new
        got = seen.get if counts else {}
        if monitor and tol is None:
            out.log[-1]["objective"] = got["objective"] or 0.0
        if rescale:
            rms = math.sqrt((got["squares"] or 0.0) / max(1, got["rows"] * m)) or 1.0
            v = known_width(v.select("id", F.transform("v", lambda z: z / F.lit(rms)).alias("v")), m)  # narrow: read with the next step
            scale += math.log(rms)
        out.v = v
        if keep:
            out.steps.append(v)
        if out.log:
            out.log.append({"t": t, "objective": None, "log_scale": scale})
        if tol is not None:
            now = out.log[-1]["objective"] = objective(v, op, labels, alpha)
            if abs(now * math.exp(2 * min(scale, 300)) - last) <= tol * abs(last):
                break
            last = now * math.exp(2 * min(scale, 300))
    if out.log and out.log[-1]["objective"] is None:
        out.log[-1]["objective"] = objective(v, op, labels, alpha)
    return out


def run_many(points: DataFrame, m: int, sigma: float, arms: list[tuple[float, int | str]], steps: int, sigma_q: float = 1.0) -> list[DataFrame]:
    """What ``run`` with ``rescale`` gives for each (alpha, seed) of ``arms``, on one graph.

    Their columns lie side by side, so a step computes every weight once for all of them;
    each run has its own alpha and its own scale.
    """
    op = DenseOp(sigma).over(points)
    labels = LabelOp(points, sigma) if any(alpha for alpha, _ in arms) else None
    wide, spark = m * len(arms), points.sparkSession
    alphas = F.array(*(F.lit(float(alpha)) for alpha, _ in arms for _ in range(m)))
    v = written = known_width(cut(points.select("id", F.concat(*(start_row(m, sigma_q, seed) for _, seed in arms)).alias("v")), "v"), wide)
    own = [F.slice("new", i * m + 1, m) for i in range(len(arms))]
    for _ in range(steps):
        rows = op.apply(v)
        half = F.when(F.col("deg") != 0, F.lit(0.5) / F.col("deg")).otherwise(F.lit(0.0))
        change = F.zip_with("v", "wv", lambda a, b: b - a * F.col("deg"))
        if labels is not None:
            rows = labels.apply(v, rows)
            change = F.zip_with(change, F.zip_with("lv", alphas, lambda ly, a: a * ly), lambda lx, ly: lx + ly)
        seen = Observation()
        moved = rows.select("id", "v", change.alias("change"), half.alias("half")).select("id", F.zip_with("v", "change", lambda a, c: a + F.col("half") * c).alias("new"))
        squares = (F.sum(F.aggregate(x, F.lit(0.0), lambda s, z: s + z * z)).alias(f"s{i}") for i, x in enumerate(own))
        new = cut(moved.observe(seen, F.count(F.lit(1)).alias("rows"), *squares).select("id", F.col("new").alias("v")), "v")
        drop(spark, written)
        got, written = seen.get, new
        rms = [math.sqrt((got[f"s{i}"] or 0.0) / max(1, got["rows"] * m)) or 1.0 for i in range(len(arms))]
        scales = F.array(*(F.lit(r) for r in rms for _ in range(m)))
        v = known_width(new.select("id", F.zip_with("v", scales, lambda z, r: z / r).alias("v")), wide)
    return [known_width(v.select("id", F.slice("v", i * m + 1, m).alias("v")), m) for i in range(len(arms))]
