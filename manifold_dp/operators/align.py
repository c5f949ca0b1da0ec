"""Rigid alignment of two embeddings over shared anchors."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import dist2
from ..sources import width
from . import arrays
from .maps import times
from .neighbours import matrix, summed


@dataclass
class Motion:
    """y = scale * x R + t."""

    rotation: np.ndarray
    shift: np.ndarray
    scale: float = 1.0


def _common(src: DataFrame, dst: DataFrame) -> DataFrame:
    return src.select("id", F.col("v").alias("a")).join(dst.select("id", F.col("v").alias("b")), "id")


def moments(src: DataFrame, dst: DataFrame) -> dict:
    """Count, means, cross-covariance and spread over common ids: one partial matrix a task, added up."""
    m = width(src)

    def sums(b) -> np.ndarray:
        x, y = (np.c_[matrix(b.column(i), b.num_rows), np.ones(b.num_rows)] for i in (0, 1))
        out = np.zeros((m + 2, m + 1))
        out[: m + 1], out[m + 1, 0] = x.T @ y, (x[:, :m] ** 2).sum()
        return out

    s = summed(_common(src, dst).select("a", "b"), sums, m + 2, m + 1)
    n = s[m, m]
    if not n:
        raise ValueError("no common anchors")
    ma, mb = s[:m, m] / n, s[m, :m] / n
    return {"n": int(n), "mean_src": ma, "mean_dst": mb, "cross": s[:m, :m] / n - np.outer(ma, mb), "spread": s[m + 1, 0] / n - float(ma @ ma)}


def fit(src: DataFrame, dst: DataFrame, scale: bool = False, reflect: bool = False) -> Motion:
    """The motion of ``src`` onto ``dst`` of least squared error; a reflection only if asked for."""
    s = moments(src, dst)
    r, k = arrays.motion(s["cross"], s["spread"], scale, reflect)
    return Motion(r, s["mean_dst"] - k * s["mean_src"] @ r, k)


def apply(v: DataFrame, motion: Motion) -> DataFrame:
    return times(v, motion.scale * motion.rotation, shift=motion.shift)


def spread(v: DataFrame) -> float:
    """Root mean square distance of rows from their mean."""
    s = moments(v, v)
    return float(np.sqrt(max(s["spread"], 0.0)))


def rmsd(src: DataFrame, dst: DataFrame) -> float:
    """Root mean squared distance of common ids."""
    return float(_common(src, dst).agg(F.sqrt(F.avg(dist2(F.col("a"), F.col("b"))))).first()[0] or 0.0)
