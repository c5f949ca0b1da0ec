"""Vector and noise expressions as Columns, and the same as SQL functions.

All are plain Catalyst expressions; the SQL functions are temporary SQL-bodied ones, so
Catalyst inlines them into the plan.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, z: s + z)


def dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x * y))


def dist2(a: Column, b: Column) -> Column:
    """Squared Euclidean distance."""
    return _sum(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)))


def norm(a: Column) -> Column:
    return F.sqrt(_sum(F.transform(a, lambda x: x * x)))


def unit(a: Column) -> Column:
    """The vector at length 1; null for the zero vector."""
    n = F.nullif(norm(a), F.lit(0.0))
    # the norm stands beside each entry: inside the lambda it would be computed for each
    return F.when(n.isNotNull(), F.zip_with(a, F.array_repeat(n, F.size(a)), lambda x, y: x / y))


def gauss_weight(a: Column, b: Column, sigma: float) -> Column:
    """exp(-distance^2 / sigma): the divisor is sigma itself."""
    return F.exp(-dist2(a, b) / F.lit(float(sigma)))


def _uniform(key: Column, start: int) -> Column:
    h = F.conv(F.substring(F.md5(key), start, 8), 16, 10).cast("double")
    return (h + 0.5) / F.lit(4294967296.0)


def md5_normal(seed: int | str, i: Column, j: Column) -> Column:
    """A portable standard normal draw for (seed, i, j), equal in every SQL engine.

    For start matrices and tests; releases draw from the system's entropy instead.
    """
    key = F.concat_ws(":", F.lit(str(seed)), i.cast("string"), j.cast("string"))
    return F.sqrt(F.lit(-2.0) * F.ln(_uniform(key, 1))) * F.cos(F.lit(2 * math.pi) * _uniform(key, 9))


SQL_FUNCTIONS = {
    "vec_dot": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0.0D, (s, z) -> s + z)",
    "vec_dist2": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, z) -> s + z)",
    "vec_unit": "(a ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN transform(a, x -> x / nullif(sqrt(aggregate(transform(a, y -> y * y), 0.0D, (s, z) -> s + z)), 0.0D))",
    "gauss_weight": "(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>, sigma DOUBLE) RETURNS DOUBLE RETURN exp(-aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, z) -> s + z) / sigma)",
    "md5_normal": "(seed STRING, i BIGINT, j BIGINT) RETURNS DOUBLE RETURN sqrt(-2.0D * ln((CAST(conv(substring(md5(concat_ws(':', seed, CAST(i AS STRING), CAST(j AS STRING))), 1, 8), 16, 10) AS DOUBLE) + 0.5D) / 4294967296.0D)) * cos(2.0D * pi() * (CAST(conv(substring(md5(concat_ws(':', seed, CAST(i AS STRING), CAST(j AS STRING))), 9, 8), 16, 10) AS DOUBLE) + 0.5D) / 4294967296.0D)",
}


def register(spark: SparkSession) -> None:
    """Make ``vec_dot``, ``vec_dist2``, ``vec_unit``, ``gauss_weight`` and ``md5_normal`` known to SQL."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
