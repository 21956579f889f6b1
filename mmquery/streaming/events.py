"""Structured Streaming over the events table: windows, joins of streams, and triangles kept up to date."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import shared_dir


def _shared(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/mmquery/{name}-{uuid.uuid4().hex}"


def source(spark: SparkSession, sf_dir: str, files: int | None = None) -> DataFrame:
    """The events as a stream, `files` files a batch where given."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(schema)
    rows = (reader.option("maxFilesPerTrigger", files) if files else reader).parquet(f"{sf_dir}/events.parquet*")
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))  # event times need a zone


def _drain(stream: DataFrame, handle, mode: str) -> None:
    spark = stream.sparkSession
    stream.writeStream.outputMode(mode).foreachBatch(handle).option("checkpointLocation", _shared(spark, "stream")).trigger(availableNow=True).start().awaitTermination()


def hourly_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events and value of each hour and type, kept as a table that each batch replaces."""
    out = _shared(spark, "hourly")
    agg = source(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count("*").alias("n"))
    rows = agg.select(F.col("window.start").cast("timestamp_ntz").alias("hour"), "event_type", "n")
    _drain(rows, lambda df, _: df.write.mode("overwrite").parquet(out), "complete")
    return spark.read.parquet(out)


def batch_triangles(spark: SparkSession, sf_dir: str, files: int | None = None) -> DataFrame:
    """The (user, hour) pairs that close a triangle user - type - hour among all edges so far, however the stream falls into batches.

    Each batch writes its new edges beside those of the batches before, and joins them with all edges: a triangle appears
    with the last of its edges. A batch that is tried again writes the same folders again.
    """
    edges, out = _shared(spark, "edges"), _shared(spark, "triangles")
    shape = {"r": ["u", "t"], "s": ["t", "h"], "t": ["u", "h"]}
    kinds = {"u": "long", "t": "string", "h": "timestamp"}

    def handle(df: DataFrame, number: int) -> None:
        own = df.sparkSession
        rows = df.select(F.col("user_id").cast("long").alias("u"), F.col("event_type").alias("t"), F.date_trunc("hour", "ts").alias("h"), "value").dropna(subset=["u", "t", "h"])
        fresh, every = {}, {}
        for k, where in (("r", "value < 20"), ("s", "value >= 20"), ("t", "true")):
            rows.where(where).select(*shape[k]).distinct().write.mode("overwrite").parquet(f"{edges}/{k}/batch={number}")
            seen = own.read.schema(", ".join(f"{c} {kinds[c]}" for c in shape[k]) + ", batch int").option("basePath", f"{edges}/{k}").parquet(f"{edges}/{k}").where(F.col("batch") <= number)
            fresh[k], every[k] = seen.where(F.col("batch") == number).select(*shape[k]), seen.select(*shape[k]).distinct()
        found = None
        for k in shape:
            e = {j: fresh[j] if j == k else every[j] for j in shape}
            part = e["t"].join(e["r"].join(e["s"], "t").select("u", "h").distinct(), ["u", "h"], "left_semi")
            found = part if found is None else found.union(part)
        found.distinct().write.mode("overwrite").parquet(f"{out}/batch={number}")

    _drain(source(spark, sf_dir, files), handle, "append")
    return spark.read.parquet(out).select("u", F.col("h").cast("timestamp_ntz").alias("h")).distinct()


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of each user's sessions, which end after half an hour without one."""
    out = _shared(spark, "sessions")
    agg = source(spark, sf_dir).withWatermark("ts", "1 hour").groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n"))
    rows = agg.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("begin"), "n")
    _drain(rows, lambda df, _: df.write.mode("overwrite").parquet(out), "complete")
    return spark.read.parquet(out)


def clicks_after_views(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two streams joined: the clicks of a user within ten minutes after each of the user's views."""
    out = _shared(spark, "joined")
    views = source(spark, sf_dir).where("event_type = 'view'").select(F.col("user_id").alias("vu"), F.col("event_id").alias("view"), F.col("ts").alias("vt")).withWatermark("vt", "1 hour")
    clicks = source(spark, sf_dir).where("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("event_id").alias("click"), F.col("ts").alias("ct")).withWatermark("ct", "1 hour")
    rows = views.join(clicks, F.expr("vu = cu AND ct >= vt AND ct <= vt + INTERVAL 10 MINUTES")).select("view", "click")
    _drain(rows, lambda df, _: df.write.mode("append").parquet(out), "append")
    return spark.read.parquet(out)


def first_seen(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stream without repeated (user, type) pairs within the watermark."""
    out = _shared(spark, "first")
    rows = source(spark, sf_dir).withWatermark("ts", "30 days").dropDuplicatesWithinWatermark(["user_id", "event_type"]).select("user_id", "event_type")
    _drain(rows, lambda df, _: df.write.mode("append").parquet(out), "append")
    return spark.read.parquet(out)
