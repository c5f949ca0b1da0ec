"""Start matrices, Gaussian calibration and noise."""

from __future__ import annotations

import math
import warnings
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import md5_normal
from ..sources import known_width


def start_row(m: int, sigma_q: float = 1.0, seed: int | str = 1) -> Column:
    dims = F.sequence(F.lit(0), F.lit(m - 1))
    return F.transform(dims, lambda j: F.lit(float(sigma_q)) * md5_normal(seed, F.col("id"), j))


def start_matrix(ids: DataFrame, m: int, sigma_q: float = 1.0, seed: int | str = 1) -> DataFrame:
    """``(id, v)``: entries N(0, sigma_q^2), a function of (seed, id, column): nothing is stored or shuffled."""
    return known_width(ids.select("id", start_row(m, sigma_q, seed).alias("v")), m)


def _phi(z: float) -> float:
    return 0.5 * math.erfc(-z / math.sqrt(2))


def trade_off(tau: float, sensitivity: float, epsilon: float) -> float:
    """The exact delta of Gaussian noise of sd ``tau`` at ``epsilon``."""
    a, b = sensitivity / (2 * tau), epsilon * tau / sensitivity
    tail = _phi(-a - b)
    return _phi(a - b) - (math.exp(epsilon + math.log(tail)) if tail > 0 else 0.0)


def calibrate(epsilon: float, delta: float, sensitivity: float, how: str = "classic") -> float:
    """The noise's sd. ``classic``: sensitivity * sqrt(2 ln(1.25 / delta)) / epsilon, proved for epsilon < 1; ``analytic``: the least sd on the exact curve."""
    if not epsilon > 0 or not 0 < delta < 1 or sensitivity < 0:
        raise ValueError("epsilon > 0, 0 < delta < 1 and sensitivity >= 0 are needed")
    if sensitivity == 0:
        return 0.0
    if how == "classic":
        if epsilon >= 1:
            warnings.warn("the classic calibration is proved for epsilon < 1 only", stacklevel=2)
        return sensitivity * math.sqrt(2 * math.log(1.25 / delta)) / epsilon
    if how != "analytic":
        raise ValueError(f"unknown calibration {how}")
    low, high = 1e-12, 1.0
    while trade_off(high, 1.0, epsilon) > delta:
        high *= 2
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if trade_off(mid, 1.0, epsilon) > delta else (low, mid)
    return sensitivity * high


def add_test_noise(v: DataFrame, tau: float, seed: int | str, allow_test_noise: bool = False) -> DataFrame:
    """Reproducible noise, for tests only: whoever knows the seed can take it off again."""
    if not allow_test_noise:
        raise ValueError("test noise hides nothing; pass allow_test_noise=True in tests")
    return v.withColumn("v", F.transform("v", lambda z, j: z + F.lit(float(tau)) * md5_normal(seed, F.col("id"), j)))


def add(v: DataFrame, tau: float) -> DataFrame:
    """Noise from the operating system's entropy, drawn per task.

    A task that runs again draws again; write the result once (``release`` does) before anything reads it.
    """

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng = np.random.default_rng()
        for b in batches:
            lists = b.column(1)
            flat = lists.flatten().to_numpy(zero_copy_only=False)
            noisy = pa.array(flat + rng.normal(0.0, tau, len(flat)))
            size = pa.compute.list_value_length(lists).to_numpy(zero_copy_only=False)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(size)], pa.int32()), noisy)], ["id", "v"])

    return v.select("id", "v").mapInArrow(draw, "id long, v array<double>")
