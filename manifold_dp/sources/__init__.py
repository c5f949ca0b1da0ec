"""Table scans, schema contracts, exchange formats and the hand-over of releases."""

from __future__ import annotations

import os
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

POINTS = T.StructType([T.StructField("id", T.LongType()), T.StructField("x", T.ArrayType(T.DoubleType())), T.StructField("label", T.IntegerType()), T.StructField("role", T.StringType())])
EMBED = T.StructType([T.StructField("id", T.LongType()), T.StructField("v", T.ArrayType(T.DoubleType()))])

_ROOT = str(Path(__file__).resolve().parents[2])


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A Parquet table; columns and filters applied later reach its scan."""
    env = spark.sparkContext.environment  # lets Python workers import this package
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if _ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([_ROOT, *paths])
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """``df`` cut to ``schema``'s columns; raises if one is missing or of another type."""
    have = {f.name: f.dataType for f in df.schema}
    for f in schema:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing")
        if have[f.name].simpleString() != f.dataType.simpleString():
            raise ValueError(f"column {f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df.select(*(f.name for f in schema))


def shared_dir(spark: SparkSession) -> str:
    """The folder driver and executors share; a local one only where all run in one JVM."""
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found.rstrip("/")
    if spark.sparkContext.master.split("[")[0] != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return f"file://{tempfile.gettempdir()}/manifold_dp"


#: Rows up to which a side of a join may be sent to every executor.
SMALL = 100_000


def sized(df: DataFrame, rows: int = SMALL) -> DataFrame:
    """``df`` marked for broadcast if it has no more than ``rows`` rows, else as it is."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def local(df: DataFrame, rows: int = SMALL) -> DataFrame:
    """A small aggregate computed once and sent along with later plans; beyond ``rows`` rows, as it is."""
    got = df.limit(rows + 1).collect()
    return F.broadcast(df.sparkSession.createDataFrame(got, df.schema)) if len(got) <= rows else df


_folders: dict[tuple[str, str], str] = {}


def folder(spark: SparkSession) -> str:
    """This session's own folder in the shared one. It goes when the session's JVM ends."""
    key = spark.sparkContext.applicationId, shared_dir(spark)
    if key not in _folders:
        at = f"{key[1]}/manifold-{uuid.uuid4().hex}"
        path, fs = _there(spark, at)
        fs.mkdirs(path)
        fs.deleteOnExit(path)
        _folders[key] = at
    return _folders[key]


def _there(spark: SparkSession, at: str):
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(at)
    return path, path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def cut(df: DataFrame, name: str = "t", fmt: str = "parquet", partition_by: list[str] | None = None) -> DataFrame:
    """Write ``df`` once to the session's folder and read it back: cuts lineage, fixes random draws.

    ``drop`` deletes it as soon as nothing reads it; what lazy results read stays until the session ends.
    """
    at = f"{folder(df.sparkSession)}/{uuid.uuid4().hex[:12]}-{name}"
    w = df.write.format(fmt)
    if partition_by:
        w = w.partitionBy(*partition_by)
    w.save(at)
    out = df.sparkSession.read.schema(df.schema).format(fmt).load(at)
    out.at = at
    return out


def drop(spark: SparkSession, *tables: DataFrame | str | None) -> None:
    """Delete written tables that nothing reads any more."""
    for t in tables:
        if at := t if isinstance(t, str) else getattr(t, "at", None):
            path, fs = _there(spark, at)
            fs.delete(path, True)


def exchange(df: DataFrame, fmt: str, **options: str) -> DataFrame:
    """``df`` after a round trip through another format (csv, json, orc, parquet)."""
    at = f"{folder(df.sparkSession)}/exchange-{uuid.uuid4().hex}"
    df.write.format(fmt).options(**options).save(at)
    return df.sparkSession.read.schema(df.schema).format(fmt).options(**options).load(at)


def bucketed(df: DataFrame, key: str, buckets: int, name: str | None = None) -> DataFrame:
    """``df`` as a table bucketed and sorted by ``key``, so that joins on it need no shuffle."""
    name = name or f"bucketed_{uuid.uuid4().hex}"
    at = f"{folder(df.sparkSession)}/{name}"
    df.write.option("path", at).bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)
    return df.sparkSession.table(name)


def width(df: DataFrame, col: str = "v") -> int:
    """Length of the vectors in ``col``, looked up once; ``known_width`` spares the lookup."""
    known = df.__dict__.setdefault("_widths", {})
    if col not in known:
        known[col] = (df.select(F.size(col)).first() or [0])[0] or 0
    return known[col]


def known_width(df: DataFrame, m: int, col: str = "v") -> DataFrame:
    df.__dict__.setdefault("_widths", {})[col] = m
    return df
