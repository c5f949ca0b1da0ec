"""Accuracy, separation and privacy measures."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources import width
from . import arrays
from .neighbours import as_vector, vector_sum


def _judged(matches: DataFrame, labels: DataFrame) -> DataFrame:
    """Matches with whether they have the query's label; queries without label do not count."""
    a = labels.select(F.col("id").alias("query_id"), F.col("label").alias("_q"))
    b = labels.select(F.col("id").alias("match_id"), F.col("label").alias("_m"))
    return matches.join(a, "query_id").join(b, "match_id", "left").where("_q IS NOT NULL").withColumn("hit", (F.col("_q").eqNullSafe(F.col("_m"))).cast("double"))


def recall_at(matches: DataFrame, labels: DataFrame, k: int) -> Column | float:
    """Share of queries with a match of their label among the first k."""
    per = _judged(matches, labels).where(F.col("rank") <= k).groupBy("query_id").agg(F.max("hit").alias("hit"))
    return per.agg(F.avg("hit")).first()[0]


def precision_at(matches: DataFrame, labels: DataFrame, k: int) -> float:
    """Mean share of the first k matches that have the query's label."""
    per = _judged(matches, labels).where(F.col("rank") <= k).groupBy("query_id").agg(F.avg("hit").alias("hit"))
    return per.agg(F.avg("hit")).first()[0]


def recall_table(matches: DataFrame, labels: DataFrame, ks: tuple[int, ...] = (1, 2, 4, 8)) -> DataFrame:
    """``(k, recall, precision, queries)`` by one pass over the matches."""
    j = _judged(matches, labels)
    by = j.groupBy("query_id").agg(*(F.max(F.when(F.col("rank") <= k, F.col("hit"))).alias(f"r{k}") for k in ks), *(F.avg(F.when(F.col("rank") <= k, F.col("hit"))).alias(f"p{k}") for k in ks))
    row = by.agg(F.count(F.lit(1)).alias("queries"), *(F.avg(f"r{k}").alias(f"r{k}") for k in ks), *(F.avg(f"p{k}").alias(f"p{k}") for k in ks))
    one = F.array(*(F.struct(F.lit(k).alias("k"), F.col(f"r{k}").alias("recall"), F.col(f"p{k}").alias("precision"), "queries") for k in ks))
    return row.select(F.inline(one))


def set_recall(matches: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """Share of the true first k among those returned, by query: the recall of an index."""
    t = truth.where(F.col("rank") <= k).select("query_id", "match_id")
    found = matches.where(F.col("rank") <= k).select("query_id", "match_id").intersect(t)
    n = t.groupBy("query_id").agg(F.count(F.lit(1)).alias("of"))
    return n.join(found.groupBy("query_id").agg(F.count(F.lit(1)).alias("n")), "query_id", "left").select("query_id", (F.coalesce("n", F.lit(0)) / F.col("of")).alias("recall"))


def separation(v: DataFrame, labels: DataFrame) -> float:
    """Scatter between class means over scatter within classes: what a picture of the classes would show."""
    m = width(v)
    rows = v.select("id", "v").join(labels.where("label IS NOT NULL").select("id", "label"), "id")
    square = F.aggregate("v", F.lit(0.0), lambda s, z: s + z * z)
    c = rows.groupBy("label").agg(F.count(F.lit(1)).alias("n"), *vector_sum("v", m), F.sum(square).alias("q"))
    own = F.aggregate(as_vector(m, "s"), F.lit(0.0), lambda s, z: s + z * z)
    row = c.agg(F.sum("n").alias("n"), F.sum("q").alias("q"), F.sum(own / F.col("n")).alias("c"), *(F.sum(f"_s{i}").alias(f"t{i}") for i in range(m))).first()
    middle = sum(row[f"t{i}"] ** 2 for i in range(m)) / row["n"]
    within = row["q"] - row["c"]
    return float((row["c"] - middle) / within) if within > 0 else float("inf")


def class_posterior(asked: DataFrame) -> DataFrame:
    """The server's guess of the target's class from the classes queried: ``(label, share)``."""
    total = asked.groupBy("label").agg(F.count(F.lit(1)).alias("n"))
    return total.crossJoin(F.broadcast(total.agg(F.sum("n").alias("all")))).select("label", (F.col("n") / F.col("all")).alias("share"))


def distortion(v: DataFrame, points: DataFrame, op_sigma: float) -> DataFrame:
    """``(i, j, w, gap, ratio)`` on pairs ``i < j``: how far images of near rows part."""
    from .kernel import Arrays, by_blocks, patches

    def of(a: Arrays, b: Arrays | None) -> Iterator[Arrays]:
        for rows, cols, kept in patches(a, b):
            i, j, square = kept(rows["id"][:, None]), kept(cols["id"][None]), kept(arrays.square_gaps(rows["x"], cols["x"]))
            gap = np.sqrt(kept(sum((rows["v"][:, k, None] - cols["v"][None, :, k]) ** 2 for k in range(rows["v"].shape[1]))))
            ratio = np.divide(gap, np.sqrt(square), out=np.full(len(gap), np.nan), where=square > 0)
            yield {"i": np.minimum(i, j), "j": np.maximum(i, j), "w": np.exp(-square / op_sigma), "gap": gap, "ratio": ratio}

    both = points.select("id", "x").join(v.select("id", "v"), "id")
    return by_blocks(both, of, "i long, j long, w double, gap double, ratio double", "v").withColumn("ratio", F.nanvl("ratio", F.lit(None).cast("double")))


def curve(rows: DataFrame, by: list[str], values: tuple[str, ...] = ("recall",)) -> DataFrame:
    """Mean and spread over seeds of each value, for each setting."""
    return rows.groupBy(*by).agg(*(f(v).alias(f"{v}_{name}") for v in values for f, name in ((F.avg, "mean"), (F.stddev_samp, "sd"))), F.count(F.lit(1)).alias("seeds"))


def membership(with_row: list[float], without: list[float]) -> float:
    """The best threshold's advantage (true less false positive rate) at telling two sets of scores apart."""
    cuts = sorted({*with_row, *without})
    best = 0.0
    for c in cuts:
        t = sum(x >= c for x in with_row) / len(with_row)
        f = sum(x >= c for x in without) / len(without)
        best = max(best, abs(t - f))
    return best
