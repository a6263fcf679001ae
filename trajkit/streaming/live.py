"""Structured Streaming twins of the panel operators.

``run`` drives a streaming query over all available files and returns what its sink holds.  Sinks
are folders in the shared directory: appended Parquet, or for updating outputs a table that keeps
each key's newest row.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from trajkit.sources.shared import shared_dir
from trajkit.sources.tables import read_table

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, files_per_batch: int | None = None) -> DataFrame:
    """Events as a file stream with event time as ``at`` (watermarks need a zoned timestamp)."""
    reader = spark.readStream.schema(EVENTS)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    # A pattern, so that one file and a folder of files are both fine.
    return reader.parquet(f"{sf_dir}/events.parque[t]").withColumn("at", F.to_utc_timestamp(F.col("ts").cast("timestamp"), F.lit("UTC")))


def run(stream: DataFrame, mode: str = "append", key: tuple[str, ...] = ()) -> DataFrame:
    """All available input through the query; complete and update outputs keep the newest rows."""
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    schema = stream.schema
    if mode == "append":
        q = stream.writeStream.outputMode("append").format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(schema).parquet(f"{base}/out")

    def keep(batch: DataFrame, epoch: int) -> None:
        # Rows are stamped with their batch; readers take each key's newest, so a batch that is
        # run again after a failure overwrites its own rows only.
        batch.withColumn("epoch", F.lit(epoch)).write.mode("overwrite").parquet(f"{base}/out/epoch={epoch}")

    q = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start()
    q.awaitTermination()
    rows = spark.read.schema(T.StructType([*schema.fields, T.StructField("epoch", T.IntegerType())])).parquet(f"{base}/out")
    if mode == "complete":
        return rows.filter(F.col("epoch") == rows.agg(F.max("epoch")).first()[0]).drop("epoch")
    newest = F.max_by(F.struct(*[c for c in stream.columns if c not in key]), "epoch").alias("x")
    return rows.groupBy(*key).agg(newest).select(*key, "x.*")


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    """Counts by day and type: the live form of the count series."""
    return events.withWatermark("at", "1 day").groupBy(F.window("at", width), "event_type").agg(F.count("*").alias("n")).select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", "n")


def sliding(events: DataFrame, width: str = "7 days", step: str = "1 day") -> DataFrame:
    return events.withWatermark("at", "7 days").groupBy(F.window("at", width, step)).agg(F.count("*").alias("n")).select(F.date_format("window.start", "yyyy-MM-dd").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "12 hours") -> DataFrame:
    s = events.withWatermark("at", "1 day").groupBy("user_id", F.session_window("at", gap)).agg(F.count("*").alias("n"))
    return s.select("user_id", F.date_format("session_window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    """Each event once, though the log delivers it twice."""
    return events.unionByName(events).withWatermark("at", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


_STATE = "days string"


def user_series(events: DataFrame) -> DataFrame:
    """Per-user series kept as state (days seen and the total), emitted on every change.  A user's
    state is one flag a day, so it does not grow with the events."""

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        days, total = state.get if state.exists else ("", 0)
        seen = set(days.split(",")) - {""}
        for f in frames:
            seen |= set(f["day"].astype(str))
            total += len(f)
        state.update((",".join(sorted(seen)), total))
        yield pd.DataFrame({"user_id": [key[0]], "total": [total], "active_days": [len(seen)]})

    day = events.select("user_id", F.date_format("at", "yyyy-MM-dd").alias("day"))
    return day.groupBy("user_id").applyInPandasWithState(step, "user_id long, total long, active_days long", "days string, total long", "update", GroupStateTimeout.NoTimeout)


def scored(events: DataFrame, classes: DataFrame) -> DataFrame:
    """Stream-static join: events by the class of their user."""
    return events.join(classes, "user_id").withWatermark("at", "1 day").groupBy("class").agg(F.count("*").alias("n"))


def purchases_after(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: other events of the user within the hour before a purchase."""
    a = events.filter("event_type = 'purchase'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("at").alias("ta")).withWatermark("ta", "1 hour")
    b = events.filter("event_type <> 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("at").alias("tb")).withWatermark("tb", "1 hour")
    return a.join(b, F.expr(f"ua = ub AND tb < ta AND tb >= ta - INTERVAL {within}")).select("a", "b")


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of rows kept and dropped when old events come after newer ones: the log is written
    in two halves, the newer first, and each half is read as one batch."""
    base = f"{shared_dir(spark)}/late-{uuid.uuid4().hex}"
    events = read_table(spark, sf_dir, "events", "event_id", "ts")
    middle = F.lit("2024-01-16").cast("timestamp_ntz")
    events.filter(F.col("ts") >= middle).write.parquet(f"{base}/in/a")
    stream = spark.readStream.schema("event_id bigint, ts timestamp_ntz").option("recursiveFileLookup", "true").parquet(f"{base}/in")
    counts = stream.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", "1 day").groupBy(F.window("at", "1 day")).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n")
    run_ = lambda: counts.writeStream.outputMode("append").format("parquet").option("path", f"{base}/out").option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    run_()
    events.filter(F.col("ts") < middle).write.parquet(f"{base}/in/b")
    run_()
    kept = spark.read.schema("start timestamp, n long").parquet(f"{base}/out").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept"))
    return kept.crossJoin(events.agg(F.count("*").alias("events"), F.sum((F.col("ts") < middle).cast("long")).alias("late")))  # one row each


Runner = Callable[[SparkSession, str], DataFrame]
