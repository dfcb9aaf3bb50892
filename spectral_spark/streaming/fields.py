"""Structured Streaming: event streams to field increments, and incremental solves.

The solver is linear, so the solution of a sum of increments is the sum of their solutions: a micro-batch is solved alone
and added to what is stored.
"""

from __future__ import annotations

import tempfile
import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def shared_dir(spark: SparkSession) -> str:
    """The cluster's shared folder. Where none is set, one of our own, on a single machine only."""
    path = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if path is None:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        path = getattr(shared_dir, "own", None) or tempfile.mkdtemp(prefix="spectral_stream_")
        shared_dir.own = path
    return f"{path.rstrip('/')}/stream-{uuid.uuid4().hex}"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/event[s].parquet")


def finish(stream: DataFrame, mode: str = "append", schema: str | None = None) -> DataFrame:
    """Run a stream over what is there (``availableNow``) and return its result table.

    Append results go to Parquet in the shared folder; complete and update results are written batch by batch, the last standing.
    """
    spark = stream.sparkSession
    base = shared_dir(spark)
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/log").outputMode("append").trigger(availableNow=True).start()
    else:
        def keep(batch: DataFrame, epoch: int) -> None:
            batch.write.mode("overwrite").parquet(f"{base}/out")

        q = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{base}/log").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/out")


def tumbling_cells(events: DataFrame) -> DataFrame:
    """Hourly increments of the value field per event type; a window is emitted once the watermark has passed it."""
    w = events.withWatermark("ts", "2 hours").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.sum("value").alias("total"), F.count("*").alias("n"))
    return w.select(F.col("window.start").alias("hour"), "event_type", "total", "n")


def sliding_cells(events: DataFrame) -> DataFrame:
    w = events.withWatermark("ts", "2 hours").groupBy(F.window("ts", "6 hours", "1 hour"), "event_type").agg(F.sum("value").alias("total"))
    return w.select(F.col("window.start").alias("start"), "event_type", "total")


def session_lines(events: DataFrame) -> DataFrame:
    """Irregular lines: a user's events with gaps below an hour."""
    w = events.withWatermark("ts", "2 hours").groupBy(F.session_window("ts", "1 hour"), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "user_id", "n", "total")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type", "value")


def late_rows(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """The stream in two runs, the later events first: what comes behind the watermark is dropped, and counted by the query's progress."""
    base = shared_dir(spark)
    events = spark.read.schema(EVENTS).parquet(f"{sf_dir}/events.parquet")
    middle = F.lit("2024-01-15").cast("timestamp")
    events.where(F.col("ts") >= middle).write.parquet(f"{base}/in/a")
    stream = spark.readStream.schema(EVENTS).option("recursiveFileLookup", "true").parquet(f"{base}/in")
    out = tumbling_cells(stream)

    def run():
        q = out.writeStream.format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
        q.awaitTermination()
        return sum(s["numRowsDroppedByWatermark"] for p in q.recentProgress for s in p["stateOperators"])

    dropped = run()
    events.where(F.col("ts") < middle).write.parquet(f"{base}/in/b")
    dropped += run()
    return spark.read.schema(out.schema).parquet(f"{base}/out"), dropped


def running_field(events: DataFrame) -> DataFrame:
    """A running total per cell (event type and hour of the day), in custom state that times out after a day of event time."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key, frames, state: GroupState):
        if state.hasTimedOut:
            state.remove()
            return
        n, total = state.get if state.exists else (0, 0.0)
        for f in frames:
            n, total = n + len(f), total + float(f["value"].sum())
        state.update((n, total))
        state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), 0) + 86_400_000)
        yield pd.DataFrame({"event_type": [key[0]], "hour_of_day": [key[1]], "n": [n], "total": [total]})

    cells = events.withWatermark("ts", "2 hours").withColumn("hour_of_day", F.hour("ts"))
    out, state = "event_type string, hour_of_day int, n long, total double", "n long, total double"
    return cells.groupBy("event_type", "hour_of_day").applyInPandasWithState(update, out, state, "append", GroupStateTimeout.EventTimeTimeout)


#: State stores that keep several states and timers for a key.
ROCKS = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


class RunningCell(StatefulProcessor):
    """A cell's count and total, forgotten after a day of event time without an event."""

    def init(self, handle) -> None:
        self.handle = handle
        self.cell = handle.getValueState("cell", "n long, total double")

    def handleInputRows(self, key, rows, timerValues):
        n, total = self.cell.get() if self.cell.exists() else (0, 0.0)
        for part in rows:
            n, total = n + len(part), total + float(part["value"].sum())
        self.cell.update((n, total))
        for timer in list(self.handle.listTimers()):
            self.handle.deleteTimer(timer)
        self.handle.registerTimer(max(timerValues.getCurrentWatermarkInMs(), 0) + 86_400_000)
        yield pd.DataFrame({"event_type": [key[0]], "hour_of_day": [key[1]], "n": [n], "total": [total]})

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo):
        self.cell.clear()
        return iter(())

    def close(self) -> None:
        pass


def running_cells(events: DataFrame) -> DataFrame:
    """:func:`running_field` as a processor with a state and a timer of its own; to be run in a session whose state provider is
    ``ROCKS``."""
    cells = events.withWatermark("ts", "2 hours").withColumn("hour_of_day", F.hour("ts")).select("event_type", "hour_of_day", "ts", "value")
    out = "event_type string, hour_of_day int, n long, total double"
    return cells.groupBy("event_type", "hour_of_day").transformWithStateInPandas(RunningCell(), out, "append", "eventTime")


def with_dictionary(events: DataFrame, dictionary: DataFrame) -> DataFrame:
    """Stream-static join with a grid dictionary (event_type, axis index)."""
    return events.join(dictionary, "event_type").select("event_id", "axis", "value")


def incremental_solve(spark: SparkSession, increments: DataFrame, solve, keys: list[str]) -> DataFrame:
    """Solve every micro-batch of cell increments by ``solve`` and add it to the stored solution; a batch that is run twice
    replaces its own part, so retries do not count twice."""
    base = shared_dir(spark)

    def step(batch: DataFrame, epoch: int) -> None:
        solve(batch).write.mode("overwrite").parquet(f"{base}/parts/batch={epoch}")

    q = increments.writeStream.foreachBatch(step).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(f"{base}/parts").groupBy(*keys).agg(F.sum("v").alias("v"))
