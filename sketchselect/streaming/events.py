"""Streaming twins of the event-time operators, and training over a stream.

A stream reads event files as they come; ``run_once`` drains what is there and stops.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from sketchselect.functions.hashing import SketchSpec
from sketchselect.operators import sketch
from sketchselect.schema import TABLES
from sketchselect.tables import new_path


def source(spark: SparkSession, sf_dir: str, table: str = "events", per_trigger: int = 1) -> DataFrame:
    """A file stream over one given table."""
    reader = spark.readStream.schema(TABLES[table]).option("maxFilesPerTrigger", per_trigger)
    return reader.option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir) if not _is_dir(spark, sf_dir, table) else reader.parquet(f"{sf_dir}/{table}.parquet")


def _is_dir(spark: SparkSession, sf_dir: str, table: str) -> bool:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{table}.parquet")
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).isDirectory()


def run_once(stream: DataFrame, tag: str, mode: str = "append") -> DataFrame:
    """Drain the stream into the shared folder and return what it wrote."""
    spark = stream.sparkSession
    out, state = new_path(spark, tag), new_path(spark, f"{tag}-state")
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", out)
    else:
        # complete and update results replace earlier ones; the last epoch's table is the answer
        writer = stream.writeStream.foreachBatch(lambda df, epoch: df.write.mode("overwrite").parquet(out))
    writer.outputMode(mode).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", "1 day").groupBy(F.window("ts", width)).agg(F.count("*").alias("n"))
    return w.select(F.unix_micros("window.start").alias("start"), "n")


def sliding(events: DataFrame, width: str = "2 hours", slide: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", "1 day").groupBy(F.window("ts", width, slide)).agg(F.count("*").alias("n"))
    return w.select(F.unix_micros("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    w = events.withWatermark("ts", "1 day").groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return w.select("user_id", F.unix_micros("w.start").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "1 day").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type")


def purchases_after_views(events: DataFrame) -> DataFrame:
    """Views and the purchases of the same user within the next hour."""
    views = events.filter("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("event_id").alias("view_id"), F.col("ts").alias("seen")).withWatermark("seen", "2 hours")
    bought = events.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("bought")).withWatermark("bought", "2 hours")
    near = F.expr("u = user_id AND bought >= seen AND bought <= seen + INTERVAL 1 HOUR")
    return views.join(bought, near).select("view_id", "purchase_id")


def scored(events: DataFrame, weights: DataFrame) -> DataFrame:
    """Stream-static join: events with the weight of their type."""
    return events.join(F.broadcast(weights), "event_type", "left").select("event_id", F.coalesce("weight", F.lit(0.0)).alias("score"))


def sketch_by_hour(events: DataFrame, spec: SketchSpec) -> DataFrame:
    """Cells of user activity per hour; sketches of hours add up to that of the day."""
    rows = events.withWatermark("ts", "1 day").select(F.window("ts", "1 hour").alias("w"), F.col("user_id").alias("feature_id"), F.lit(1.0).alias("value"))
    return sketch.build(rows, spec, by=["w"]).select(F.unix_micros("w.start").alias("start"), "row", "bucket", "value")


def user_totals(events: DataFrame) -> DataFrame:
    """Custom state: per user the running count and value, emitted as rows arrive."""

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for rows in batches:
            n, total = n + len(rows), total + float(rows["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "total": [total]})

    return events.groupBy("user_id").applyInPandasWithState(
        step, "user_id long, n long, total double", "n long, total double", "update", GroupStateTimeout.NoTimeout
    )
