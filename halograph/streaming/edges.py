"""Edges that arrive as events: windows, sessions, late data, duplicates, running degrees, and joins with the partition."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import fresh_path
from ..sources.tables import table


def with_time(events: DataFrame) -> DataFrame:
    """Adds key (from the JSON properties) and at, the event's instant: its local time read as UTC, whatever the session's zone."""
    seconds = F.expr("timestampdiff(SECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', CAST(ts AS TIMESTAMP_NTZ))")
    return events.withColumns({"at": F.timestamp_seconds(seconds), "key": F.get_json_object("props", "$.k").cast("long")})


def event_stream(spark: SparkSession, sf_dir: str, files: int = 4, order: Column | None = None) -> DataFrame:
    """The events as a stream of several micro-batches, one file each, in the order of order (event_id unless said otherwise)."""
    path = fresh_path(spark, "events")
    events = table(spark, sf_dir, "events")
    keyed = events.withColumn("_o", order if order is not None else F.col("event_id"))
    low, high = keyed.agg(F.min("_o"), F.max("_o")).first()
    low, step = low or 0, max(1, -(-((high or 0) - (low or 0) + 1) // files))
    for k in range(files):  # one after another, so that they are read in this order
        keyed.where((F.col("_o") >= low + k * step) & (F.col("_o") < low + (k + 1) * step)).drop("_o").coalesce(1).write.mode("append").parquet(path)
    return with_time(spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path))


def drained(stream: DataFrame, mode: str, name: str = "stream") -> DataFrame:
    """Run a stream over all that is there, and give what it wrote: all appended rows, or the last complete result."""
    spark = stream.sparkSession
    path, check = fresh_path(spark, name), fresh_path(spark, f"{name}-checkpoint")

    def write(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={batch if mode == 'append' else 0}")

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path).select(*stream.columns)


def clocked(stream: DataFrame, tick: str, name: str = "ticks") -> DataFrame:
    """(tick, it): the micro-batches of a stream as the clock of iterations, over all that is there."""
    spark = stream.sparkSession
    path, check = fresh_path(spark, name), fresh_path(spark, f"{name}-checkpoint")
    rows = stream.select(F.col(tick).alias("tick"))

    def write(df: DataFrame, batch: int) -> None:
        df.withColumn("it", F.lit(batch).cast("long")).write.mode("overwrite").parquet(f"{path}/batch={batch}")

    rows.writeStream.foreachBatch(write).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
    kind = rows.schema["tick"].dataType.simpleString()
    return spark.read.schema(f"tick {kind}, it bigint").parquet(path).select("tick", "it")


def tumbling(stream: DataFrame, length: str = "1 hour") -> DataFrame:
    return stream.groupBy(F.window("at", length).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, length: str = "2 hours", step: str = "1 hour") -> DataFrame:
    return stream.groupBy(F.window("at", length, step).alias("w")).agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    got = stream.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))
    return got.select("user_id", F.unix_seconds("w.start").alias("start"), F.unix_seconds("w.end").alias("end"), "n")


def late_edges(stream: DataFrame, delay: str = "1 hour", length: str = "1 hour") -> DataFrame:
    """Windowed counts that leave out what comes more than delay behind the newest event."""
    return stream.withWatermark("at", delay).groupBy(F.window("at", length).alias("w")).agg(F.count("*").alias("n")).select(F.unix_seconds("w.start").alias("start"), "n")


def distinct_edges(stream: DataFrame, within: str = "400 days") -> DataFrame:
    """Edges that did not come in the time `within` before. State of older ones is dropped as the watermark passes."""
    edges = stream.where("key IS NOT NULL").select("at", F.col("user_id").alias("src"), F.col("key").alias("dst"))
    return edges.withWatermark("at", within).dropDuplicatesWithinWatermark(["src", "dst"]).select("src", "dst")


def edge_parts(stream: DataFrame, parts: DataFrame) -> DataFrame:
    """New edges with the part of their source, by a join with the static partition."""
    return stream.where("key IS NOT NULL").select("event_id", F.col("user_id").alias("vid"), "key").join(parts, "vid")


def running_degree(stream: DataFrame) -> DataFrame:
    return stream.where("key IS NOT NULL").groupBy(F.col("user_id").alias("vid")).agg(F.count("*").alias("deg"))
