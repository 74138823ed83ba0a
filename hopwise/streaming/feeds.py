"""Streams around a static index: event windows, edges from events, and query pairs that meet the index as they come."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.landmarks import LandmarkIndex
from ..plans.store import shared_folder


def events(spark: SparkSession, sf_dir: str, late: str = "10 minutes") -> DataFrame:
    """The events table as a stream with event time ``at`` and a watermark; ids that repeat inside it are dropped."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    # a stream reads folders: the file is picked by its name
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    timed = raw.withColumn("at", F.col("ts").cast("timestamp")).withWatermark("at", late)
    return timed.dropDuplicatesWithinWatermark(["event_id"])


def windowed_counts(stream: DataFrame, size: str = "1 hour", slide: str | None = None) -> DataFrame:
    by = F.window("at", size, slide) if slide else F.window("at", size)
    return stream.groupBy(by.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def clicks_before_purchases(spark: SparkSession, sf_dir: str, within: str = "1 hour") -> DataFrame:
    """Interval join of two streams: each purchase with the same user's clicks in the time before it.

    Watermarks on both sides and the bound on the times let state be dropped.
    """
    stream = events(spark, sf_dir)
    p = stream.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("buyer"), F.col("at").alias("bought"))
    c = events(spark, sf_dir).where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("at").alias("clicked"))
    near = F.expr(f"buyer = user_id AND clicked <= bought AND clicked >= bought - INTERVAL {within}")
    return p.join(c, near).select("purchase", "click")


def answered(pairs: DataFrame, index: LandmarkIndex) -> DataFrame:
    """A stream of pairs (pid, u, v) joined with the index, stateless: pid, cid, and both records."""
    a = index.table.select(F.col("v").alias("u"), F.col("recs").alias("ru"))
    b = index.table.select("v", F.col("recs").alias("rv"))
    return pairs.join(a, "u").join(b, "v").select("pid", "ru", "rv")


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream until its source is read, and returns what it wrote."""
    spark = stream.sparkSession
    name = f"drained_{uuid.uuid4().hex}"
    if mode == "append":
        out = f"{shared_folder(spark)}/{name}"
        run = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{out}-state").trigger(availableNow=True).start(out, format="parquet")
        run.awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)
    kept: list[DataFrame] = []

    def keep(batch: DataFrame, _: int) -> None:
        path = f"{shared_folder(spark)}/{name}-{len(kept)}"
        batch.write.parquet(path)
        kept.append(spark.read.schema(stream.schema).parquet(path))

    run = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{shared_folder(spark)}/{name}-state").trigger(availableNow=True).foreachBatch(keep).start()
    run.awaitTermination()
    return kept[-1]  # complete mode: the last batch holds all
