"""The privacy budget each subject has spent, in exact decimals."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

MONEY = "decimal(18,9)"
SCHEMA = f"subject string, at timestamp, mechanism string, epsilon {MONEY}, delta {MONEY}, sensitivity double"


def charge(ledger: DataFrame, subjects: DataFrame, mechanism: str, epsilon: float, delta: float, sensitivity: float, at=None) -> DataFrame:
    """``ledger`` with one more charge for each of ``subjects (subject)``. Write it before what it pays for is published."""
    when = F.lit(at).cast("timestamp") if at is not None else F.current_timestamp()
    new = subjects.select("subject", when.alias("at"), F.lit(mechanism).alias("mechanism"), F.lit(str(epsilon)).cast(MONEY).alias("epsilon"), F.lit(f"{delta:.9f}").cast(MONEY).alias("delta"), F.lit(float(sensitivity)).alias("sensitivity"))
    return ledger.unionByName(new)


def spent(ledger: DataFrame) -> DataFrame:
    """Basic composition: sums for each subject."""
    return ledger.groupBy("subject").agg(F.sum("epsilon").alias("epsilon"), F.sum("delta").alias("delta"), F.count(F.lit(1)).alias("charges"))


def running(ledger: DataFrame) -> DataFrame:
    """Each charge with what its subject has spent up to it."""
    w = Window.partitionBy("subject").orderBy("at", "mechanism").rowsBetween(Window.unboundedPreceding, 0)
    return ledger.withColumn("spent", F.sum("epsilon").over(w))


def allowed(ledger: DataFrame, limit: float) -> DataFrame:
    """Charges that keep their subject within ``limit``; a charge counts against later ones even if it was refused."""
    return running(ledger).withColumn("ok", F.col("spent") <= F.lit(str(limit)).cast(MONEY))


class BudgetExceeded(RuntimeError):
    """A charge that would take its subject over the limit; nothing may be published."""


class Book:
    """A ledger in the shared folder. ``charge`` writes before it returns, so what it pays for can be published after it.

    One writer at a time: two charges made at once could both see the same balance.
    """

    def __init__(self, spark: SparkSession, path: str, limit: float | None = None):
        self.spark, self.path, self.limit = spark, path, limit
        spark.createDataFrame([], SCHEMA).write.mode("append").parquet(path)

    def rows(self) -> DataFrame:
        return self.spark.read.schema(SCHEMA).parquet(self.path)

    def spent(self, subject: str) -> float:
        return float(self.rows().where(F.col("subject") == subject).agg(F.sum("epsilon")).first()[0] or 0)

    def charge(self, subject: str, mechanism: str, epsilon: float, delta: float, sensitivity: float) -> None:
        if self.limit is not None and self.spent(subject) + epsilon > self.limit + 1e-9:
            raise BudgetExceeded(f"{subject} would spend more than {self.limit}")
        who = self.spark.createDataFrame([(subject,)], "subject string")
        charge(self.spark.createDataFrame([], SCHEMA), who, mechanism, epsilon, delta, sensitivity).coalesce(1).write.mode("append").parquet(self.path)
