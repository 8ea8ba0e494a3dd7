"""Client messages as a stream: an extension for data that arrives while training runs.

The events table plays the messages.  Times come without a zone and are cast,
since a watermark needs an instant.  Every query drains its input and stops
(`availableNow`).  Input arrives as three files in a fixed order, one for each
micro-batch, so what a watermark drops is known and a batch twin can say it.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from hushgrad.fl import storage
from hushgrad.sources.tables import SCHEMAS, load


PARTS = 3


def part_of(spark: SparkSession, sf_dir: str):  # noqa: ANN201
    """The file of an event: thirds of the range of ids."""
    high = load(spark, sf_dir, "events").agg(F.max("event_id")).first()[0] or 0
    return F.floor(F.col("event_id") * PARTS / F.lit(high + 1))


def source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a stream with an instant t; written once, a file after the other."""
    path = f"{storage.folder(spark)}/hushgrad-fl/stream-{uuid.uuid4().hex}"
    p, fs = storage._path(spark, path)
    fs.deleteOnExit(p)
    part = part_of(spark, sf_dir)
    for k in range(PARTS):  # one after the other: a file stream goes by time of writing
        load(spark, sf_dir, "events").filter(part == k).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", 1).parquet(path).withColumn("t", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str = "append", once: bool = False) -> DataFrame:
    """Runs the stream to the end of its input into a table and returns that.

    once: in a single micro-batch.  A state that expires by the clock asks for further, empty batches as long as
    the clock runs, so `availableNow` would not end."""
    spark = stream.sparkSession
    path = f"{storage.folder(spark)}/hushgrad-fl/sink-{uuid.uuid4().hex}"
    p, fs = storage._path(spark, path)
    fs.deleteOnExit(p)

    def put(batch: DataFrame, number: int) -> None:
        # a batch that runs again replaces its own folder
        batch.write.mode("overwrite").parquet(f"{path}/rows/batch={number}")

    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").foreachBatch(put)
    query = (writer.trigger(once=True) if once else writer.trigger(availableNow=True)).start()
    query.awaitTermination()
    return spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.IntegerType())])).parquet(f"{path}/rows")


def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly counts by kind; the last state of every window counts."""
    g = source(spark, sf_dir).groupBy(F.window("t", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    rows = drained(g.select(F.unix_seconds("w.start").alias("start"), "event_type", "n"), "update")
    return rows.groupBy("start", "event_type").agg(F.max_by("n", "batch").alias("n"))


def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Messages delivered twice count once."""
    s = source(spark, sf_dir)
    twice = s.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).withWatermark("t", "3650 days").dropDuplicatesWithinWatermark(["event_id"])
    return drained(twice.select("event_id", "event_type")).groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


class ClientShift(StatefulProcessor):
    """A client's reference, moved by a quarter of each message's difference to it, in order of event time.

    Messages wait in the state until the watermark has passed them and are then
    folded in; what is put out applies the waiting ones on top, without folding.
    So the result doesn't depend on micro-batches or Arrow batches.  A message
    older than what is folded in comes too late and is only counted."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.folded = handle.getValueState("folded", "shift double, seen long, until timestamp, late long")
        self.waiting = handle.getListState("waiting", "t timestamp, event_id long, value double")

    def handleInputRows(self, key, rows, timers):  # noqa: ANN001, ANN201, N802
        shift, seen, until, late = self.folded.get() if self.folded.exists() else (0.0, 0, None, 0)
        mark = pd.Timestamp(timers.getCurrentWatermarkInMs(), unit="ms")
        plain = lambda t: pd.Timestamp(t).tz_localize(None) if pd.Timestamp(t).tzinfo else pd.Timestamp(t)
        queue = [(plain(t), i, v) for t, i, v in self.waiting.get()] if self.waiting.exists() else []
        for batch in rows:
            for t, i, v in zip(batch["t"], batch["event_id"], batch["value"], strict=True):
                if until is not None and plain(t) <= plain(until):
                    late += 1
                else:
                    queue.append((plain(t), int(i), float(v)))
        queue.sort()
        ready = [q for q in queue if q[0] <= mark]
        for t, _, v in ready:
            shift, seen, until = shift + 0.25 * (v - shift), seen + 1, t
        rest = queue[len(ready) :]
        self.folded.update((shift, seen, until.to_pydatetime() if until is not None else None, late))
        if rest:
            self.waiting.put([(t.to_pydatetime(), i, v) for t, i, v in rest])
        elif self.waiting.exists():
            self.waiting.clear()
        for _, _, v in rest:
            shift, seen = shift + 0.25 * (v - shift), seen + 1
        yield pd.DataFrame({"user_id": [key[0]], "shift": [shift], "seen": [seen], "late": [late]})

    def close(self) -> None:
        pass


class Delivered(StatefulProcessor):
    """Counts a client's messages; a client not heard of for a day starts again."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.count = handle.getValueState("count", "n long", ttlDurationMs=86_400_000)

    def handleInputRows(self, key, rows, timers):  # noqa: ANN001, ANN201, N802
        n = (self.count.get()[0] if self.count.exists() else 0) + sum(len(batch) for batch in rows)
        self.count.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n]})

    def close(self) -> None:
        pass


PROVIDER = "spark.sql.streaming.stateStore.providerClass"


def _with_rocksdb(spark: SparkSession, run):  # noqa: ANN001, ANN202
    """run() with the state store that list states and TTL need; the session's own is put back."""
    before = spark.conf.get(PROVIDER, None)
    spark.conf.set(PROVIDER, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return run()
    finally:
        if before is None:
            spark.conf.unset(PROVIDER)
        else:
            spark.conf.set(PROVIDER, before)


def _shifts(spark: SparkSession, sf_dir: str, delay: str) -> DataFrame:
    keys = source(spark, sf_dir).withWatermark("t", delay).select("user_id", "event_id", "t", "value").groupBy("user_id")
    out = keys.transformWithStateInPandas(ClientShift(), "user_id long, shift double, seen long, late long", "Update", "EventTime")
    rows = _with_rocksdb(spark, lambda: drained(out, "update"))
    last = rows.groupBy("user_id").agg(F.max_by(F.struct("shift", "seen", "late"), "batch").alias("z"))
    return last.select("user_id", F.round("z.shift", 6).alias("shift"), "z.seen", "z.late")


def stream_shift_state(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every client's reference after all its messages; the delay is longer than the data, so none is late."""
    return _shifts(spark, sf_dir, "3650 days").drop("late")


def stream_delivered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Messages of each client, in a state that expires."""
    keys = source(spark, sf_dir).select("user_id", "event_id").groupBy("user_id")
    out = keys.transformWithStateInPandas(Delivered(), "user_id long, n long", "Update", "ProcessingTime")
    return _with_rocksdb(spark, lambda: drained(out, "update", once=True)).groupBy("user_id").agg(F.max("n").alias("n"))


def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts over two hours, every hour."""
    g = source(spark, sf_dir).groupBy(F.window("t", "2 hours", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    rows = drained(g.select(F.unix_seconds("w.start").alias("start"), "n"), "update")
    return rows.groupBy("start").agg(F.max_by("n", "batch").alias("n"))


def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of a user, six hours apart: the whole result after the last micro-batch."""
    s = source(spark, sf_dir).withWatermark("t", "3650 days")
    g = s.groupBy("user_id", F.session_window("t", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", "n")
    rows = drained(g, "complete")
    last = rows.join(F.broadcast(rows.agg(F.max("batch").alias("batch"))), "batch")  # one row
    return last.groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("n").alias("longest"))


def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hourly counts behind a watermark of two days: windows that ended before it take no more messages."""
    s = source(spark, sf_dir).withWatermark("t", "2 days")
    g = s.groupBy(F.window("t", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    rows = drained(g.select(F.unix_seconds("w.start").alias("start"), "n"), "update")
    return rows.groupBy("start").agg(F.max_by("n", "batch").alias("n"))


def stream_join_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clicks within ten minutes after a purchase of the same user, as an interval join of two streams."""
    s = source(spark, sf_dir)
    p = s.filter("event_type = 'purchase'").select(F.col("event_id").alias("round_id"), F.col("user_id").alias("u"), F.col("t").alias("t0")).withWatermark("t0", "3650 days")
    c = s.filter("event_type = 'click'").select("event_id", "user_id", "t").withWatermark("t", "3650 days")
    j = c.join(p, F.expr("user_id = u and t > t0 and t <= t0 + interval 10 minutes"))
    return drained(j.select("round_id", "event_id")).drop("batch")


QUERIES = {f.__name__: f for f in (stream_tumbling, stream_dedup, stream_shift_state, stream_join_rounds, stream_delivered, stream_sliding, stream_session, stream_late)}
SQL = {
    "stream_tumbling": "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_dedup": "SELECT event_type, count(*) AS n FROM events GROUP BY 1",
}
SQL["stream_shift_state"] = """WITH r AS (SELECT user_id, value, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r, count(*) OVER (PARTITION BY user_id) AS n FROM events)
  SELECT user_id, round(sum(0.25 * pow(0.75, n - r) * value), 6) AS shift, any_value(n) AS seen FROM r GROUP BY 1"""
SQL["stream_delivered"] = "SELECT user_id, count(*) AS n FROM events GROUP BY 1"
SQL["stream_sliding"] = """WITH h AS (SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS h FROM events)
  SELECT start, count(*) AS n FROM (SELECT h AS start FROM h UNION ALL SELECT h - 3600 FROM h) GROUP BY 1"""
SQL["stream_session"] = """WITH e AS (SELECT user_id, ts, event_id, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
  s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM e), c AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2)
  SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1"""
# the watermark of a part: the latest time of all parts before it, less two days; a window is late if it ended by then
SQL["stream_late"] = """WITH e AS (SELECT ts, CAST(floor(event_id * 3 / ((SELECT max(event_id) FROM events) + 1)::DOUBLE) AS BIGINT) AS part FROM events),
  m AS (SELECT p.part, (SELECT max(ts) FROM e WHERE e.part < p.part) - INTERVAL 2 DAY AS mark FROM (SELECT DISTINCT part FROM e) p)
  SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, count(*) AS n FROM e JOIN m USING (part)
  WHERE mark IS NULL OR date_trunc('hour', ts) + INTERVAL 1 HOUR > mark GROUP BY 1"""
SQL["stream_join_rounds"] = """SELECT p.event_id AS round_id, c.event_id FROM events p JOIN events c ON c.user_id = p.user_id AND c.ts > p.ts AND c.ts <= p.ts + INTERVAL 10 MINUTE
  WHERE p.event_type = 'purchase' AND c.event_type = 'click'"""
