"""Shared folder, scratch tables and small helpers of the text operators."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from contextvars import ContextVar
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = str(Path(__file__).resolve().parents[2])


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package from where the driver found it.

    A cluster without a shared code folder installs the package or calls
    ``addPyFile``; neither is disturbed by this.
    """
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if ROOT not in paths:
        env["PYTHONPATH"] = os.pathsep.join([ROOT, *paths])


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Only a session that runs in one JVM gets a folder of its own when the setting
    is absent; a cluster without it is refused, since its executors could not see
    a machine-local folder.
    """
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found.rstrip("/")
    if not spark.sparkContext.master.split("[")[0] == "local":
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return "file://" + tempfile.gettempdir() + "/manifold_dp"


#: Settings under which tables are written that are read from their files afterwards: an
#: execution's shuffle files go as soon as it has ended, and rows travel to Python in
#: batches small enough for long texts.
WRITING = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxRecordsPerBatch": "2000"}


@contextmanager
def writing(spark: SparkSession, partitions: int | None = None) -> Iterator[None]:
    """``WRITING`` holds within, and shuffles have ``partitions`` at least; then all is put back as it was."""
    name = "spark.sql.shuffle.partitions"
    new = WRITING | ({name: str(max(partitions, int(spark.conf.get(name))))} if partitions else {})
    old = {k: spark.conf.get(k) for k in new}
    for k, v in new.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in old.items():
            spark.conf.set(k, v)


def partitions_for(size: int) -> int:
    """Shuffle partitions for ``size`` bytes of text: about 8 MB each, beyond 80 GB fewer and larger ones."""
    return max(1, min(size >> 23, 10_000), size >> 28)


_owner: ContextVar[list | None] = ContextVar("owner", default=None)


class Scratch:
    """Tables written to the shared folder, to cut lineage and survive lost executors.

    Its maker drops what nothing reads any more. What a lazy result still reads stays until
    the block of ``owned`` ends in which the scratch was made, or else until the session's
    JVM ends, which deletes the folder.
    """

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.base = f"{shared_dir(spark)}/scratch-{uuid.uuid4().hex}"
        self.count = 0
        self.written: list[str] = []
        at, fs = self._there(self.base)
        fs.mkdirs(at)
        fs.deleteOnExit(at)
        if (mine := _owner.get()) is not None:
            mine.append(self)

    @staticmethod
    @contextmanager
    def owned() -> Iterator[None]:
        """What is made within is deleted at the end: for work whose results are written by then."""
        mine: list[Scratch] = []
        token = _owner.set(mine)
        try:
            yield
        finally:
            _owner.reset(token)
            for s in mine:
                s.drop(s.base)

    def _there(self, at: str):
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(at)
        return path, path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def path(self, name: str) -> str:
        self.count += 1
        return f"{self.base}/{self.count:03d}-{name}"

    def keep(self, df: DataFrame, name: str = "t", partitions: int | None = None) -> DataFrame:
        """Write ``df`` once and return a DataFrame that reads what was written."""
        at = self.path(name)
        with writing(self.spark, partitions):
            df.write.option("compression", "zstd").parquet(at)
        out = self.spark.read.schema(df.schema).parquet(at)
        out.scratch_path = at
        self.written.append(at)
        return out

    def drop(self, *tables: DataFrame | str) -> None:
        """Delete written tables that nothing reads any more, and free shuffle files."""
        for t in tables:
            at, fs = self._there(t if isinstance(t, str) else t.scratch_path)
            fs.delete(at, True)
        free(self.spark)

    def drop_but(self, *kept: DataFrame) -> None:
        """Delete all tables of this scratch but those."""
        stay = {t.scratch_path for t in kept}
        self.drop(*(t for t in self.written if t not in stay))
        self.written = [t for t in self.written if t in stay]

    def free(self) -> None:
        free(self.spark)


def free(spark: SparkSession) -> None:
    """Let Spark's cleaner delete shuffle files of finished plans."""
    import gc

    gc.collect()
    spark.sparkContext._jvm.System.gc()


def others(names: list[str], *results: str) -> list[str]:
    """Column names that no result column replaces; names that differ by case only are one to Spark."""
    return [n for n in names if n.lower() not in {r.lower() for r in results}]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def total_chars(df: DataFrame, text: str = "text") -> int:
    """Sum of text lengths in bytes: what partition counts are derived from."""
    return df.agg(F.sum(F.octet_length(F.col(text)))).first()[0] or 0


def odd_at_least(n: float) -> int:
    """A prime of at least ``n``, so that ids with a common step still spread."""
    n = max(3, int(n)) | 1
    while any(n % d == 0 for d in range(3, int(n**0.5) + 1, 2)):
        n += 2
    return n


#: Rows up to which a table is sent to all tasks; keys at most that ``join_hot`` sends of a larger one.
SMALL, HOT_KEYS = 100_000, 2000


def join_hot(left: DataFrame, right: DataFrame, on: list[str], rows: str, total: int) -> DataFrame:
    """Inner join with ``right``, which has one row a key and in ``rows`` how many rows of ``left`` have it, of ``total``.

    ``right`` has no more than ``total`` rows; up to ``SMALL`` it is sent to all tasks. Else
    keys of more than one in ``HOT_KEYS`` rows, of which there are fewer than that, are, so that
    no task gets all rows of a frequent key; the others meet by shuffle.
    """
    if total <= SMALL:
        return left.join(F.broadcast(right.drop(rows)), on)
    hot = F.broadcast(right.where(F.col(rows) > total // HOT_KEYS).drop(rows))
    rest = right.where(F.col(rows) <= total // HOT_KEYS).drop(rows)
    return left.join(hot, on).unionByName(left.join(hot, on, "left_anti").join(rest, on))
