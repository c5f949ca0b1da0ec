"""The label graph's Laplacian times a matrix, from class sums: no pair of rows meets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources import local, width
from .neighbours import as_vector, vector_sum


class LabelOp:
    """Kernel of integer codes. ``gaussian_code``: exp(-(y - y')^2 / sigma_y), so weights depend on the coding; ``same``: 1 within a class, else 0.

    A null label is masked: its row has no edges.
    """

    def __init__(self, labels: DataFrame, sigma_y: float = 1.0, kernel: str = "gaussian_code"):
        if kernel not in ("gaussian_code", "same"):
            raise ValueError(f"unknown kernel {kernel}")
        self.labels, self.sigma_y, self.kernel = labels.select("id", "label"), sigma_y, kernel

    def weight(self, a: Column, b: Column) -> Column:
        if self.kernel == "same":
            return F.when(a == b, 1.0).otherwise(0.0)
        gap = (a - b).cast("double")
        return F.exp(-gap * gap / F.lit(float(self.sigma_y)))

    def classes(self, v: DataFrame) -> DataFrame:
        """``(label, n, s)``: size and sum of the rows of each class."""
        m = width(v)
        rows = v.select("id", "v").join(self.labels.where("label IS NOT NULL"), "id")
        return rows.groupBy("label").agg(F.count(F.lit(1)).alias("n"), *vector_sum("v", m)).select("label", "n", as_vector(m, "s"))

    def apply(self, v: DataFrame, rows: DataFrame | None = None) -> DataFrame:
        """``(id, v, e, lv)``: degree and row of L_Y V; or ``rows``, which hold ``id`` and ``v`` too, with ``e`` and ``lv``."""
        m = width(v)
        c = self.classes(v)
        a, b = c.select(F.col("label")), c.select(F.col("label").alias("_l"), "n", "s")
        k = self.weight(F.col("label"), F.col("_l"))
        on = F.col("label") == F.col("_l") if self.kernel == "same" else None
        mixed = (a.join(b, on) if on is not None else a.crossJoin(b)).withColumn("_k", k)  # one row for each two classes
        sums = mixed.groupBy("label").agg(F.sum(F.col("_k") * F.col("n")).alias("_e"), *(F.sum(F.col("_k") * F.element_at("s", i + 1)).alias(f"_s{i}") for i in range(m))).select("label", "_e", as_vector(m, "_t"))
        rows = v.select("id", "v") if rows is None else rows
        names = rows.columns
        rows = rows.join(self.labels, "id", "left").join(local(sums), "label", "left")
        e = F.coalesce(F.col("_e") - 1.0, F.lit(0.0))
        zero = F.transform("v", lambda z: z * 0.0)
        lv = F.when(F.col("_t").isNull(), zero).otherwise(F.zip_with("v", "_t", lambda z, t: z * F.col("_e") - t))
        return rows.select(*names, e.alias("e"), lv.alias("lv"))
