"""Targets and budget charges that arrive over time."""

from __future__ import annotations

import os
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from ..operators import features, ledger, retrieval
from ..sources import cut, folder, read

from ..plans.methods import _PLANTED, _ROLE

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int | None = None) -> DataFrame:
    """The events table as a file stream, with a zoned event time."""
    read(spark, sf_dir, "events")  # workers learn where the package is
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    local = sf_dir.replace("file://", "")
    is_folder = os.path.isdir(f"{local}/events.parquet") if os.path.exists(local) else False
    s = reader.parquet(f"{sf_dir}/events.parquet") if is_folder else reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return s.withColumn("ts", F.col("ts").cast("timestamp"))


def finish(stream: DataFrame, mode: str = "append", key: list[str] | None = None) -> DataFrame:
    """Run a stream over all that is there and return its rows: into Parquet (append), a table in memory
    (complete), or Parquet by batch, of which the last row of each ``key`` counts (update)."""
    spark = stream.sparkSession
    base = f"{folder(spark)}/stream-{uuid.uuid4().hex}"
    w = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{base}/state")
    if mode == "append":
        w.format("parquet").option("path", f"{base}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{base}/out")
    if mode == "update":
        w.foreachBatch(_by_epoch(f"{base}/out")).start().awaitTermination()
        rows = spark.read.schema(T.StructType([*stream.schema, T.StructField("epoch", T.LongType())])).parquet(f"{base}/out")
        values = [c for c in stream.columns if c not in key]
        return rows.groupBy(*key).agg(F.max_by(F.struct(*values), "epoch").alias("v")).select(*key, "v.*")
    name = f"s{uuid.uuid4().hex}"
    w.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def _by_epoch(at: str, work: Callable[[DataFrame], DataFrame | None] = lambda batch: batch) -> Callable[[DataFrame, int], None]:
    """A batch's result into a folder of its epoch; a batch that is played again replaces what it wrote."""

    def write(batch: DataFrame, epoch: int) -> None:
        if (out := work(batch)) is not None:
            out.write.mode("overwrite").parquet(f"{at}/epoch={epoch}")

    return write


@query("SELECT event_type, count(*) AS n, round(sum(value), 4) + 0e0 AS total FROM events GROUP BY 1")
def stream_counts(spark, sf_dir):
    """Running aggregate, complete mode."""
    return finish(event_stream(spark, sf_dir).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total")), "complete").select("event_type", "n", (F.round("total", 4) + F.lit(0.0)).alias("total"))


@query("SELECT user_id, count(*) AS n FROM events GROUP BY 1")
def stream_update(spark, sf_dir):
    """Counts of users, update mode: a batch writes the users it changed."""
    return finish(event_stream(spark, sf_dir).groupBy("user_id").agg(F.count(F.lit(1)).alias("n")), "update", ["user_id"])


@query("SELECT epoch_us(ts) AS ts_us, count(*) * CASE WHEN ts > (SELECT max(ts) FROM events) - INTERVAL 1 HOUR THEN 3 ELSE 2 END AS n FROM events GROUP BY ts")
def stream_late_rows(spark, sf_dir):
    """All events arrive in each of three batches. Rows are late by the watermark of the batch before: in the
    third one what is behind it is dropped, the rest counts again."""
    at = f"{folder(spark)}/late-{uuid.uuid4().hex}"
    e = read(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"))
    for _ in range(3):
        e.coalesce(1).write.mode("append").parquet(at)
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(at).withWatermark("ts", "1 hour")
    return finish(s.groupBy("ts").agg(F.count(F.lit(1)).alias("n")), "update", ["ts"]).select(F.unix_micros("ts").alias("ts_us"), "n")


@query("SELECT epoch_us(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01')) AS start_us, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events WHERE event_type = 'click' GROUP BY 1")
def stream_spent_by_window(spark, sf_dir):
    """Budget asked for in each window of six hours."""
    s = event_stream(spark, sf_dir).where("event_type = 'click'").withWatermark("ts", "1 hour")
    out = finish(s.groupBy(F.window("ts", "6 hours").alias("w")).agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents")), "complete")
    return out.select(F.unix_micros("w.start").alias("start_us"), "cents")


def _windows(spark, sf_dir, size: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    out = finish(event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")), "complete")
    return out.select(F.unix_micros("w.start").alias("start_us"), "event_type", "n")


@query("SELECT epoch_us(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01')) AS start_us, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, sf_dir):
    return _windows(spark, sf_dir, "6 hours")


@query("SELECT epoch_us(time_bucket(INTERVAL 3 HOUR, ts, TIMESTAMP '2024-01-01')) - k * 10800000000 AS start_us, event_type, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY ALL")
def stream_sliding(spark, sf_dir):
    return _windows(spark, sf_dir, "6 hours", "3 hours")


@query(
    """WITH g AS (SELECT user_id, ts, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER w < 43200000000 THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM s GROUP BY user_id, k"""
)
def stream_sessions(spark, sf_dir):
    """Sessions of a user with gaps under twelve hours."""
    out = finish(event_stream(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "12 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")), "complete")
    return out.select("user_id", F.unix_micros("w.start").alias("start_us"), "n")


@query("SELECT DISTINCT event_id, user_id FROM events")
def stream_dedup(spark, sf_dir):
    """Events delivered twice count once."""
    s = event_stream(spark, sf_dir)
    twice = s.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    return finish(twice.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


@query("SELECT event_id, label FROM events JOIN embeddings ON vec_id = user_id")
def stream_static_join(spark, sf_dir):
    """Arriving targets join their features."""
    e = read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("user_id"), "label")
    return finish(event_stream(spark, sf_dir).join(e, "user_id").select("event_id", "label"))


@query("SELECT a.event_id AS request, b.event_id AS answer FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'signup' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_stream_join(spark, sf_dir):
    """A request and its answer within an hour; both sides' state is bounded by watermarks."""
    a = event_stream(spark, sf_dir).where("event_type = 'signup'").select(F.col("event_id").alias("request"), "user_id", F.col("ts").alias("ta")).withWatermark("ta", "1 hour")
    b = event_stream(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("answer"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", "1 hour")
    return finish(a.join(b, F.expr("user_id = ub AND tb >= ta AND tb <= ta + INTERVAL 1 HOUR")).select("request", "answer"))


#: Days after which a budget begins anew, counted from the charge that opened it.
PERIOD_DAYS, LIMIT = 7, 100.0


class BudgetLedger(StatefulProcessor):
    """What each user has spent in the running period, kept as state; a charge over the limit is refused and costs nothing.

    A period opens with a user's first charge and expires ``PERIOD_DAYS`` later by event
    time. A timer at its end frees the state of users who do not come back.
    """

    def __init__(self, limit: float, days: int):
        self.limit, self.period = round(limit * 100), days * 86_400_000_000

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.state = handle.getValueState("spent", "cents long, since long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802
        spent, since = self.state.get() if self.state.exists() else (0, None)
        charges = pd.concat(list(rows)).sort_values(["at_us", "event_id"])
        out = []
        for event, at, cents in zip(charges["event_id"], charges["at_us"], charges["cents"], strict=True):
            if since is None or at >= since + self.period:
                spent, since = 0, int(at)
            ok = spent + cents <= self.limit
            spent += int(cents) if ok else 0
            out.append((int(event), int(key[0]), bool(ok), int(spent)))
        self.state.update((spent, since))
        for timer in list(self.handle.listTimers()):
            self.handle.deleteTimer(timer)
        self.handle.registerTimer((since + self.period) // 1000)
        yield pd.DataFrame(out, columns=["event_id", "user_id", "ok", "spent_cents"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N802
        self.state.clear()
        yield pd.DataFrame(columns=["event_id", "user_id", "ok", "spent_cents"])

    def close(self) -> None:
        pass


@query(
    f"""WITH RECURSIVE c AS (SELECT event_id, user_id, epoch_us(ts) AS at_us, CAST(round(value * 100) AS BIGINT) AS cents, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r FROM events WHERE event_type = 'click'),
s AS (SELECT event_id, user_id, r, at_us AS since, CASE WHEN cents <= {round(LIMIT * 100)} THEN cents ELSE 0 END AS spent, cents <= {round(LIMIT * 100)} AS ok FROM c WHERE r = 1
  UNION ALL
  SELECT c.event_id, c.user_id, c.r, CASE WHEN c.at_us >= s.since + {PERIOD_DAYS * 86_400_000_000} THEN c.at_us ELSE s.since END,
    CASE WHEN c.at_us >= s.since + {PERIOD_DAYS * 86_400_000_000} THEN 0 ELSE s.spent END + CASE WHEN CASE WHEN c.at_us >= s.since + {PERIOD_DAYS * 86_400_000_000} THEN 0 ELSE s.spent END + c.cents <= {round(LIMIT * 100)} THEN c.cents ELSE 0 END,
    CASE WHEN c.at_us >= s.since + {PERIOD_DAYS * 86_400_000_000} THEN 0 ELSE s.spent END + c.cents <= {round(LIMIT * 100)}
  FROM s JOIN c ON c.user_id = s.user_id AND c.r = s.r + 1)
SELECT event_id, user_id, ok, spent AS spent_cents FROM s"""
)
def stream_ledger(spark, sf_dir):
    """Charges by stateful user ledgers whose budget expires; equals a sequential pass over each user's events."""
    s = event_stream(spark, sf_dir).where("event_type = 'click'").withWatermark("ts", "1 hour")
    s = s.select("event_id", "user_id", "ts", F.unix_micros("ts").alias("at_us"), F.round(F.col("value") * 100).cast("long").alias("cents"))
    schema = "event_id long, user_id long, ok boolean, spent_cents long"
    conf = "spark.sql.streaming.stateStore.providerClass"
    old = spark.conf.get(conf)
    spark.conf.set(conf, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return finish(s.groupBy("user_id").transformWithStateInPandas(BudgetLedger(LIMIT, PERIOD_DAYS), schema, "append", "eventTime"))
    finally:
        spark.conf.set(conf, old)


ANSWERS = "query_id long, match_id long, dist double, rank int, epoch long"


@query(
    f"""WITH {_PLANTED}, s AS (SELECT id, x, {_ROLE} AS role FROM p), asked AS (SELECT DISTINCT user_id AS id FROM events WHERE event_type = 'signup'),
k AS (SELECT a.id AS query_id, b.id AS match_id, CAST(row_number() OVER (PARTITION BY a.id ORDER BY round(list_distance(a.x, b.x) * list_distance(a.x, b.x), 12), b.id) AS INTEGER) AS rank FROM s a JOIN asked USING (id) JOIN s b ON b.role = 'server' AND a.id <> b.id)
SELECT query_id, match_id, rank FROM k WHERE rank <= 8"""
)
def stream_targets(spark, sf_dir):
    """Each batch of arriving targets is matched against a frozen server embedding, here the raw features."""
    p = features.feature_set(spark, sf_dir, "emb_planted")
    server = cut(p.where("role = 'server'").select("id", F.col("x").alias("v")), "server")
    rows = p.select("id", F.col("x").alias("v"))
    at = f"{folder(spark)}/answers-{uuid.uuid4().hex}"

    def answer(batch: DataFrame) -> DataFrame:
        return retrieval.knn(batch.select(F.col("user_id").alias("id")).distinct().join(rows, "id"), server, 8)

    s = event_stream(spark, sf_dir).where("event_type = 'signup'").select("user_id")
    s.writeStream.foreachBatch(_by_epoch(at, answer)).trigger(availableNow=True).option("checkpointLocation", f"{at}-state").start().awaitTermination()
    return spark.read.schema(ANSWERS).parquet(at).select("query_id", "match_id", "rank")


def serve_targets(spark: SparkSession, arriving: DataFrame, points: DataFrame, cfg: retrieval.Config, k: int = 8) -> DataFrame:
    """The whole private exchange for each batch of ``arriving (id)``: the client's release, charged first, is
    matched against a server embedding that was made once; a batch that the budget refuses gets no answers."""
    public, server = cut(points.where("role = 'public'"), "public"), points.where("role = 'server'")
    served = retrieval.serve(server, public, cfg)
    known = cut(points.where("role = 'target'"), "targets")
    at = f"{folder(spark)}/answers-{uuid.uuid4().hex}"

    def answer(batch: DataFrame) -> DataFrame | None:
        target = cut(batch.select("id").distinct().join(known, "id").select("id", "x", "label", "role"), "batch")
        if not target.head(1):
            return None
        try:
            return retrieval.private_retrieve(target, public, server, k, cfg, served).answers
        except ledger.BudgetExceeded:
            return None

    arriving.writeStream.foreachBatch(_by_epoch(at, answer)).trigger(availableNow=True).option("checkpointLocation", f"{at}-state").start().awaitTermination()
    none = spark.createDataFrame([], ANSWERS.replace("epoch long", "epoch int"))
    none.limit(0).write.mode("append").parquet(f"{at}/epoch=-1")
    return spark.read.schema(ANSWERS).parquet(at)


@query()
def stream_exchange(spark, sf_dir):
    """Targets that sign up, served by private exchanges under a budget."""
    p = cut(features.feature_set(spark, sf_dir, "emb_planted"), "points")
    book = ledger.Book(spark, f"{folder(spark)}/book-{uuid.uuid4().hex}", 2.0)
    cfg = retrieval.Config(m=4, steps=2, epsilon=1.0, book=book)
    arriving = event_stream(spark, sf_dir).where("event_type = 'signup'").select(F.col("user_id").alias("id"))
    return serve_targets(spark, arriving, p, cfg).select("query_id", "match_id", "rank")


@query("SELECT count(*) AS late FROM events WHERE ts < (SELECT max(ts) FROM events) - INTERVAL 1 HOUR")
def late_rows(spark, sf_dir):
    """Rows that a watermark of one hour would call late at the stream's end; they are counted, not charged twice."""
    e = read(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"))
    top = e.agg(F.max("ts").alias("top"))
    return e.crossJoin(F.broadcast(top)).where(F.col("ts") < F.col("top") - F.expr("INTERVAL 1 HOUR")).agg(F.count(F.lit(1)).alias("late"))
