"""Session settings this engine expects, applied only where they may still change."""

from __future__ import annotations

from pyspark.sql import SparkSession


def session(name: str = "manifold_dp", master: str | None = None, **settings: str) -> SparkSession:
    """A session in UTC with adaptive execution; an existing one is returned as it is."""
    b = SparkSession.builder.appName(name).config("spark.sql.session.timeZone", "UTC").config("spark.sql.adaptive.enabled", "true")
    if master:
        b = b.master(master)
    for k, v in settings.items():
        b = b.config(k.replace("__", "."), v)
    return b.getOrCreate()
