"""Streams over folders of Parquet files. Every function returns a streaming DataFrame; ``drain`` runs one to its end."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scratch import file_system, scratch_path
from ..sources.tables import SCHEMAS


def stage_files(df: DataFrame, parts: int, order: str) -> str:
    """Writes a table as ``parts`` files in order, so that a stream sees it in as many steps.

    A file stream takes files by their times, and tasks end in any order: the times are set a second apart, by part.
    """
    path = scratch_path(df.sparkSession, "stream-in")
    df.repartitionByRange(parts, order).sortWithinPartitions(order).write.parquet(path)
    _date_in_order(df.sparkSession, path)
    return path


def _date_in_order(spark: SparkSession, path: str) -> None:
    """Sets the times of a folder's part files in the order of their names, and checks that the file system keeps them."""
    root, fs = file_system(spark, path)
    listed = lambda: sorted((f for f in fs.listStatus(root) if f.getPath().getName().startswith("part-")), key=lambda f: f.getPath().getName())
    files = listed()
    last = max((f.getModificationTime() for f in files), default=0)
    for i, f in enumerate(files):
        fs.setTimes(f.getPath(), last - 1000 * (len(files) - 1 - i), -1)
    times = [f.getModificationTime() for f in listed()]
    if any(a >= b for a, b in zip(times, times[1:], strict=False)):
        raise ValueError(f"the file system of {path} does not keep the times by which a stream orders its files")


def events_stream(spark: SparkSession, path: str, delay: str = "2 hours") -> DataFrame:
    schema = SCHEMAS["events"].replace("timestamp_ntz", "timestamp")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path).withWatermark("ts", delay)


def drain(stream: DataFrame, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Runs the stream over all that is there into a Parquet table (append) or through batches (update, complete)."""
    spark = stream.sparkSession
    out, checkpoint = scratch_path(spark, "stream-out"), checkpoint or scratch_path(spark, "stream-mark")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").option("path", out).start()
    else:
        query = writer.foreachBatch(lambda batch, i: batch.withColumn("batch", F.lit(i)).write.mode("append").parquet(out)).start()
    query.awaitTermination()
    return spark.read.schema(stream.schema if mode == "append" else stream.schema.add("batch", "long")).parquet(out)


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    w = F.window("ts", width)
    return events.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "30 minutes") -> DataFrame:
    return events.groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def enriched(events: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """Stream-static join; the static side is a small table such as a model's labels."""
    return events.join(static, key)


def clicks_to_purchases(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: both sides carry a watermark, so old state is dropped."""
    a = clicks.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("ct"), F.col("event_id").alias("click"))
    b = purchases.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("pt"), F.col("event_id").alias("purchase"))
    return a.join(b, (F.col("u") == F.col("user_id")) & (F.col("pt") > F.col("ct")) & (F.col("pt") <= F.col("ct") + F.expr(f"INTERVAL {within}"))).select("click", "purchase")


def user_profiles(events: DataFrame, silent_days: int = 30) -> DataFrame:
    """Per user, a running count of each event type: five numbers of state, dropped after a silent time by the events' clock."""

    def update(key, batches, state):
        if state.hasTimedOut:
            state.remove()
            return
        counts = dict(zip(("click", "error", "purchase", "signup", "view"), state.get if state.exists else (0,) * 5, strict=True))
        for pdf in batches:
            for t, n in pdf["event_type"].value_counts().items():
                counts[t] = counts.get(t, 0) + int(n)
        values = tuple(counts[k] for k in ("click", "error", "purchase", "signup", "view"))
        state.update(values)
        state.setTimeoutTimestamp(max(0, state.getCurrentWatermarkMs()) + silent_days * 86_400_000)
        yield pd.DataFrame({"user_id": [key[0]], "click": [values[0]], "purchase": [values[2]], "view": [values[4]]})

    fields = "click long, error long, purchase long, signup long, view long"
    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, click long, purchase long, view long", fields, "update", "EventTimeTimeout")


def document_stream(spark: SparkSession, path: str) -> DataFrame:
    """Documents on a synthetic clock, a minute an id; the watermark is set after scoring."""
    docs = spark.readStream.schema(SCHEMAS["documents"]).option("maxFilesPerTrigger", 1).parquet(path)
    clock = F.timestamp_seconds(F.lit(1_704_067_200) + F.col("doc_id") * 60)
    return docs.withColumn("ts", clock)


def late_rows(spark: SparkSession) -> tuple[DataFrame, DataFrame]:
    """An on-time, a late and a duplicate row in two files, for tests: (events stream, all rows)."""
    path = scratch_path(spark, "late")
    schema = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"
    first = [(1, "2024-01-01 10:05:00", 1, "view", 1.0, "{}"), (2, "2024-01-01 15:00:00", 1, "view", 1.0, "{}")]
    second = [(3, "2024-01-01 10:06:00", 1, "view", 1.0, "{}"), (4, "2024-01-01 20:00:00", 1, "view", 1.0, "{}")]
    rows = []
    for part in (first, second):
        df = spark.createDataFrame([(a, *r) for a, *r in part], schema.replace("timestamp", "string")).withColumn("ts", F.to_timestamp("ts"))
        df.coalesce(1).write.mode("append").parquet(path)
        rows += part
    return events_stream(spark, path), spark.createDataFrame([(r[0],) for r in rows], "event_id long")
