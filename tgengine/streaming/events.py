"""Continuous events turned into snapshots and kept aggregates."""

from __future__ import annotations

import datetime

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.aggregate import step
from ..sources.graphs import day, handoff_pairs
from ..storage import fresh, stored

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
#: Type of the row that ends a finite stream, so that its last windows close too.
END = "end of stream"


def read_events(spark: SparkSession, folder: str, files: str = "*.parquet", per_trigger: int | None = None) -> DataFrame:
    r = spark.readStream.schema(SCHEMA).option("pathGlobFilter", files)
    return (r.option("maxFilesPerTrigger", per_trigger) if per_trigger else r).parquet(folder)


def staged(spark: SparkSession, events: DataFrame, cuts: list[datetime.datetime], lateness_days: int = 1) -> str:
    """A folder with the events before, between and after the cuts, written one after another, and a last row that closes all windows."""
    path = fresh(spark, "stream-source")
    rows = events.select(*[c.split()[0] for c in SCHEMA.split(", ")])
    edges = [None, *cuts, None]
    for lo, hi in zip(edges, edges[1:]):
        part = rows if lo is None else rows.filter(F.col("ts") >= F.lit(lo).cast("timestamp_ntz"))
        part = part if hi is None else part.filter(F.col("ts") < F.lit(hi).cast("timestamp_ntz"))
        part.write.mode("append").parquet(path)
    last = rows.agg((F.max("ts") + F.expr(f"interval {lateness_days + 2} days")).alias("ts"), (F.max("event_id") + 1).alias("event_id"))
    end = last.select("event_id", "ts", F.lit(None).cast("long").alias("user_id"), F.lit(END).alias("event_type"), F.lit(0.0).alias("value"), F.lit(None).cast("string").alias("props"))
    end.write.mode("append").parquet(path)
    return path


def windows(events: DataFrame, grain: str = "1 day", slide: str | None = None, lateness: str = "1 day") -> DataFrame:
    """Events of each closed window by type, tumbling or sliding; repeats are dropped, and rows later than the watermark."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])
    w = F.window("ts", grain, slide) if slide else F.window("ts", grain)
    sums = e.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    return sums


def sessions(events: DataFrame, gap: str = "6 hours", lateness: str = "1 day") -> DataFrame:
    """Runs of one user's events without a pause of `gap`."""
    e = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)
    return e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))


def run_to_table(stream: DataFrame) -> DataFrame:
    """Runs what is available now into files in the shared folder, closed windows only, and reads them.

    Rows of the end mark are to be filtered here, not in the stream: a filter that is pushed to the source would keep the mark from moving the watermark."""
    spark = stream.sparkSession
    path, marks = fresh(spark, "stream-sink"), fresh(spark, "stream-state")
    stream.writeStream.format("parquet").option("path", path).outputMode("append").option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()
    done = spark.read.schema(stream.schema).parquet(path)
    return done.filter(F.col("event_type") != END) if "event_type" in done.columns else done


class RunningCounts:
    """In-degrees over a trailing window of days, kept from batch to batch and moved by each closed day's deltas.

    State, as tables in the shared folder: the last active day of every edge and the kept aggregate; each closed day writes new
    versions, and the old ones stay for a restart. Events of a day wait until `lateness` days have begun after it; those of a
    day already closed are counted in `late` and dropped. The driver holds day numbers and paths only."""

    def __init__(self, spark: SparkSession, trailing: int, lateness: int = 1):
        self.spark, self.trailing, self.lateness = spark, trailing, lateness
        self.waiting = None
        self.last = spark.createDataFrame([], "src long, dst long, last_t int")
        self.kept = spark.createDataFrame([], "dst long, cnt long")
        self.closed, self.late, self.versions = -1, 0, []

    def __call__(self, batch: DataFrame, number: int) -> None:
        rows = batch.select("event_id", "ts", "user_id", "event_type", day("ts").alias("t"))
        rows = stored(rows if self.waiting is None else rows.unionByName(self.waiting))
        counts = {r["t"]: r["count"] for r in rows.groupBy("t").count().collect()}  # one row a day
        if not counts:
            return
        self.late += sum(n for t, n in counts.items() if t <= self.closed)
        until = max(counts) - self.lateness
        pairs = stored(handoff_pairs(rows.filter((F.col("t") > self.closed) & (F.col("t") < until) & (F.col("event_type") != END))).distinct())
        for t in range(self.closed + 1, until):
            self._close(t, pairs.filter(F.col("t") == t).select("src", "dst"))
        self.waiting = rows.filter(F.col("t") >= max(until, self.closed + 1))
        self.closed = max(self.closed, until - 1)

    def _close(self, t: int, today: DataFrame) -> None:
        first = t - self.trailing  # active until yesterday: last day after first - 1
        known = self.last.join(today.withColumn("again", F.lit(True)), ["src", "dst"], "full")
        known = stored(known.select("src", "dst", "last_t", F.coalesce("again", F.lit(False)).alias("again")))
        was = F.coalesce(F.col("last_t") >= first, F.lit(False))
        sign = F.when(F.col("again") & ~was, 1).when(~F.col("again") & (F.col("last_t") == first), -1)
        moved = known.select("dst", sign.alias("sign"), F.lit(1).alias("w")).filter("sign is not null")
        self.kept = stored(step(self.kept, moved, ()))
        self.last = stored(known.filter(F.col("again") | (F.col("last_t") > first)).select("src", "dst", F.when(F.col("again"), t).otherwise(F.col("last_t")).cast("int").alias("last_t")))
        self.versions.append((t, self.kept))

    def result(self) -> DataFrame:
        out = None
        for t, kept in self.versions:
            here = kept.select(F.lit(t).alias("t"), "dst", "cnt")
            out = here if out is None else out.unionByName(here)
        return out if out is not None else self.kept.select(F.lit(0).alias("t"), "dst", "cnt")


def run_incremental(events: DataFrame, trailing: int, lateness: int = 1) -> RunningCounts:
    """Runs what is available now; `events` is a stream."""
    spark = events.sparkSession
    state = RunningCounts(spark, trailing, lateness)
    events.writeStream.foreachBatch(state).option("checkpointLocation", fresh(spark, "stream-state")).trigger(availableNow=True).start().awaitTermination()
    return state
