"""Scoring of arriving nodes in micro-batches (M28) and its streaming aggregates."""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from typing import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prunegraph.operators.layers import Network
from prunegraph.operators.support import infer_batched

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Events from Parquet files, with an event time that watermarks accept."""
    rows = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events*.parquet").parquet(folder)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def half_hours(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Arrivals and value by 30-minute window."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", "30 minutes")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))


def sliding_days(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", "24 hours", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def user_sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))


def distinct_events(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def follow_ups(events: DataFrame, first: str, then: str, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Pairs (user_id, first_id, then_id): ``then`` no later than ``within`` after ``first`` (stream-stream join).

    Both watermarks and the time range bound the state that the join keeps."""
    a = events.filter(F.col("event_type") == first).withWatermark("ts", late).select(F.col("user_id").alias("a_user"), F.col("event_id").alias("first_id"), F.col("ts").alias("a_ts"))
    b = events.filter(F.col("event_type") == then).withWatermark("ts", late).select("user_id", F.col("event_id").alias("then_id"), F.col("ts").alias("b_ts"))
    near = (F.col("a_user") == F.col("user_id")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"interval {within}"))
    return a.join(b, near).select("user_id", "first_id", "then_id")


def with_static(events: DataFrame, table: DataFrame, key: str) -> DataFrame:
    """Events with the columns of a fixed table; the table is read anew by every micro-batch."""
    return events.join(table, events["user_id"] == table[key])


USER_STATE = "user_id long, n long, last_id long, most double"


def _advance(key, parts, state):
    """One user's state: events so far, the latest event (ties: larger id), the largest value."""
    if state.hasTimedOut:
        state.remove()
        return
    n, at, last, most = state.get if state.exists else (0, None, None, None)
    for rows in parts:
        n += len(rows)
        for t, i in rows[["ts_us", "event_id"]].dropna().astype("int64").nlargest(1, ["ts_us", "event_id"]).itertuples(index=False):
            if at is None or (int(t), int(i)) > (at, last):
                at, last = int(t), int(i)
        top = rows["value"].max()
        if not pd.isna(top):
            most = float(top) if most is None else max(most, float(top))
    state.update((n, at, last, most))
    if at is not None:
        state.setTimeoutTimestamp(max(at // 1000, state.getCurrentWatermarkMs()) + KEEP_MS)
    yield pd.DataFrame({"user_id": [key[0]], "n": [n], "last_id": pd.array([last], dtype="Int64"), "most": [most]})


KEEP_MS = 90 * 24 * 3600 * 1000


def user_state(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Per user what has been seen so far, emitted whenever it changes (update mode).

    State is one small row a user and is dropped 90 days of event time after the latest event.
    Rows without a user share the null user; rows without time count but are never the latest."""
    rows = events.withWatermark("ts", late).withColumn("ts_us", F.unix_micros("ts"))
    return rows.groupBy("user_id").applyInPandasWithState(_advance, USER_STATE, "n long, at long, last_id long, most double", "update", "EventTimeTimeout")


def run_to_table(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Run over all that is there; the rows emitted, also as the view ``name``.

    Each micro-batch is written beside the checkpoint by the tasks that made it, so no rows pass
    the driver; a repeated batch overwrites its own. In complete mode the last batch holds all."""
    spark, parts = stream.sparkSession, {}

    def put(rows: DataFrame, batch: int) -> None:
        parts[batch] = f"{checkpoint}-rows/{batch:010d}"
        rows.write.mode("overwrite").parquet(parts[batch])

    query = stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    paths = [parts[k] for k in sorted(parts)][-1 if mode == "complete" else 0 :]
    found = spark.read.schema(stream.schema).parquet(*paths) if paths else spark.createDataFrame([], stream.schema)
    found.createOrReplaceTempView(name)
    return found


@dataclass
class StreamScorer:
    """Scores each micro-batch of arriving nodes and stores their middle features.

    A batch reads features written by earlier batches only, and writes under its own
    number, so a repeated batch gives the same rows. ``retrain`` is called when event
    time has moved on by ``every_days``; a new model name makes older features unused."""

    net: Network
    width: int
    edges: DataFrame
    feats: DataFrame
    store: object = None
    caps: dict | None = None
    retrain: Callable | None = None
    every_days: int = 30
    sink: str | None = None
    log: list = field(default_factory=list)
    trained_at: object = None

    def on_batch(self, arrived: DataFrame, batch: int) -> None:
        spark = arrived.sparkSession
        arrived = arrived.persist()
        when = arrived.agg(F.max("ts").alias("t")).first()["t"]
        if when is None:
            arrived.unpersist()
            return
        if self.trained_at is None:
            self.trained_at = when
        elif self.retrain and (when - self.trained_at).days >= self.every_days:
            self.net, self.store.model = self.retrain(self.net, when)
            self.trained_at = when
        began = time.time()
        targets = arrived.select(F.lit(0).alias("batch_id"), F.col("node_id"))
        known = self.store.get(before_batch=batch) if self.store else None
        scores = infer_batched(self.net, targets, self.edges, self.feats, self.width, self.caps, known)
        out = scores.select("node_id", "h", F.lit(batch).cast("long").alias("stream_batch"), F.lit(when).alias("day"))
        if self.sink:
            out.write.mode("overwrite").parquet(f"{self.sink}/stream_batch={batch}")
        else:
            out.write.format("noop").mode("overwrite").save()
        if self.store:
            own = self.net.layers[0].forward(targets.select("node_id").distinct(), self.edges.join(targets.select(F.col("node_id").alias("dst")), "dst", "left_semi"), self.feats, self.width)
            self.store.put(1, own, when, batch)
        self.log.append((int(batch), when, arrived.count(), 1000 * (time.time() - began)))
        arrived.unpersist()

    def run(self, nodes: DataFrame, checkpoint: str) -> None:
        query = nodes.writeStream.foreachBatch(self.on_batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        query.awaitTermination()

    def daily(self, spark: SparkSession) -> DataFrame:
        """Per event day: batches, nodes and the largest latency."""
        rows = spark.createDataFrame(self.log, "batch long, ts timestamp, nodes long, latency_ms double")
        return rows.groupBy(F.to_date("ts").alias("day")).agg(F.count(F.lit(1)).alias("batches"), F.sum("nodes").alias("nodes"), F.max("latency_ms").alias("most_ms"))
