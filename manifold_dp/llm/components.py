"""Connected components of an edge table by alternating large and small stars."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, join_hot


def components(edges: DataFrame, scratch: Scratch) -> DataFrame:
    """``(node, component)`` for the nodes of ``edges (a, b)``; component: the least node.

    Each round is two partial aggregates and joins, written to the shared folder; rounds
    grow with the logarithm of the nodes. Nothing is gathered by node or component: a node
    of very many edges is joined by broadcast (``join_hot``).
    """
    now = scratch.keep(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "edges")
    mark, edges = None, now.count()
    while True:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least("u", F.min("v")).alias("m"), F.count(F.lit(1)).alias("rows"))
        large = join_hot(both.where("v > u"), least, ["u"], "rows", 2 * edges).select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        down = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(down, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        new = scratch.keep(small.unionByName(down.select("u", F.col("m").alias("v"))).distinct(), "edges")
        edges, check = new.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        scratch.drop(now)
        now = new
        if (edges, check) == mark:
            break
        mark = edges, check
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
