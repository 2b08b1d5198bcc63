"""Structured Streaming over event files: cells, sessions, joins, statistics and training; every stream has a batch twin."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..exec import passes
from ..fit import evaluate
from ..model import ModelState
from ..sources.tables import scratch
from ..tensor import TensorFrame


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream of files; ts is a timestamp under the session's time zone."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "*").parquet(*stream_folder(spark, path))
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_folder(spark: SparkSession, path: str) -> list[str]:
    """A file source reads folders: a single file is offered through a folder of its own."""
    out = scratch(spark, "events")
    spark.read.parquet(path).repartition(4, "event_id").write.parquet(out)
    return [out]


def batch_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """The stream's result after all input, written to Parquet by the tasks: appended rows, the updates of all micro-batches, or the
    whole table that the last of them gave."""
    spark = stream.sparkSession
    out, ckpt = scratch(spark, "sink"), scratch(spark, "ckpt")
    if mode == "append":
        stream.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", ckpt).trigger(availableNow=True).start(out).awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    written: list[str] = []

    def write(df: DataFrame, batch_id: int) -> None:
        df.write.mode("overwrite").parquet(f"{out}/{batch_id}")
        if f"{out}/{batch_id}" not in written:
            written.append(f"{out}/{batch_id}")

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", ckpt).trigger(availableNow=True).start().awaitTermination()
    if not written:
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(*(written if mode == "update" else written[-1:]))


def tumbling(df: DataFrame, width: str = "1 day") -> DataFrame:
    if df.isStreaming:
        df = df.withWatermark("ts", "40 days")
    g = df.groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return g.select(F.col("w.start").alias("start"), "event_type", "n", "total")


def sliding(df: DataFrame, width: str = "1 day", step: str = "6 hours") -> DataFrame:
    if df.isStreaming:
        df = df.withWatermark("ts", "40 days")
    g = df.groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n"))
    return g.select(F.col("w.start").alias("start"), "n")


def sessions(df: DataFrame, gap: str = "30 minutes") -> DataFrame:
    if df.isStreaming:
        df = df.withWatermark("ts", "40 days")
    g = df.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return g.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def dedupe(df: DataFrame) -> DataFrame:
    if df.isStreaming:
        return df.withWatermark("ts", "40 days").dropDuplicatesWithinWatermark(["event_id"])
    return df.dropDuplicates(["event_id"])


def views_to_clicks(df: DataFrame) -> DataFrame:
    """Clicks within 30 minutes after a view of the same user."""
    views = df.where("event_type = 'view'").select("user_id", F.col("event_id").alias("view_id"), F.col("ts").alias("view_ts"))
    clicks = df.where("event_type = 'click'").select(F.col("user_id").alias("click_user"), F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts"))
    if df.isStreaming:
        views, clicks = views.withWatermark("view_ts", "40 days"), clicks.withWatermark("click_ts", "40 days")
    on = (F.col("user_id") == F.col("click_user")) & (F.col("click_ts") >= F.col("view_ts")) & (F.col("click_ts") <= F.col("view_ts") + F.expr("interval 30 minutes"))
    return views.join(clicks, on).select("user_id", "view_id", "click_id")


class StreamStats:
    """Sufficient statistics at frozen factors, merged per micro-batch; a batch id that was merged is not merged again."""

    def __init__(self, model: ModelState, dims: tuple[int, ...], decay: float = 1.0):
        self.model, self.dims, self.decay, self.last = model, dims, decay, -1
        p = len(model.inducing)
        self.packed = np.zeros(p * (p + 1) // 2 + p + 3)

    def merge(self, cells: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        p = len(self.model.inducing)
        self.packed = self.decay * self.packed + passes.map_sum(TensorFrame(cells, self.dims), len(self.packed), p, self.model, passes.block_stats)
        self.last = batch_id

    def stats(self) -> passes.Stats:
        return passes.Stats.unpack(self.packed, len(self.model.inducing))


class StreamFit:
    """Several gradient steps per micro-batch from the current state."""

    def __init__(self, model: ModelState, dims: tuple[int, ...], steps: int = 3, rate: float = 0.05):
        self.model, self.dims, self.steps, self.rate, self.last, self.trace = model, dims, steps, rate, -1, []

    def merge(self, cells: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last or cells.isEmpty():
            return
        t = TensorFrame(cells, self.dims, self.model.kind)
        for _ in range(self.steps):
            value, g, m = evaluate(t, self.model)
            self.trace.append((batch_id, value))
            self.model = m.unpack(m.pack() + self.rate * g / max(1.0, float(np.linalg.norm(g))))
        self.last = batch_id


def for_each(stream: DataFrame, merge: Callable[[DataFrame, int], None]) -> None:
    stream.writeStream.foreachBatch(merge).option("checkpointLocation", scratch(stream.sparkSession, "ckpt")).trigger(availableNow=True).start().awaitTermination()


def late_rows(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> tuple[int, int]:
    """(rows kept, rows dropped behind the watermark) of a stream that gets the later half of the events, in two batches, before the
    earlier one: a batch is held against the watermark that the batch before it began with."""
    e = batch_events(spark, sf_dir)
    cut = e.agg((F.min("ts").cast("double") + (F.max("ts").cast("double") - F.min("ts").cast("double")) / 2).alias("c")).first().c
    root = scratch(spark, "late")
    later = F.col("ts").cast("double") >= cut
    even = F.col("event_id") % 2 == 0
    for name, part in (("a", later & even), ("b", later & ~even), ("c", ~later)):  # files are read in the order of their making
        e.where(part).coalesce(1).write.parquet(f"{root}/{name}")
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(f"{root}/*")
    rows = s.withWatermark("ts", delay).dropDuplicates(["event_id", "ts"]).select("event_id")
    out = scratch(spark, "sink")
    q = rows.writeStream.format("parquet").option("checkpointLocation", scratch(spark, "ckpt")).trigger(availableNow=True).start(out)
    q.awaitTermination()
    dropped = sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
    return spark.read.schema(rows.schema).parquet(out).count(), int(dropped)


def user_counters(df: DataFrame, idle_days: int = 60) -> DataFrame:
    """Clicks and views of each user, kept as state: updates of every micro-batch. The state of a user goes when the watermark is
    ``idle_days`` past the last event."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, frames, state):
        if state.hasTimedOut:
            state.remove()
            return
        clicks, views, last = state.get if state.exists else (0, 0, 0)
        for pdf in frames:
            clicks += int((pdf["event_type"] == "click").sum())
            views += int((pdf["event_type"] == "view").sum())
            last = max(last, int(pdf["ts"].max().timestamp() * 1000))
        state.update((clicks, views, last))
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + idle_days * 86_400_000)
        yield pd.DataFrame({"user_id": [key[0]], "clicks": [clicks], "views": [views]})

    return df.withWatermark("ts", "40 days").groupBy("user_id").applyInPandasWithState(update, "user_id long, clicks long, views long", "clicks long, views long, last long", "update", GroupStateTimeout.EventTimeTimeout)


def user_counters_batch(df: DataFrame) -> DataFrame:
    return df.groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.count_if(F.col("event_type") == "view").alias("views"))
