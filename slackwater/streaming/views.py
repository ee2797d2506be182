"""Structured Streaming forms: file sources, watermarks, windows, joins, dedup, arbitrary state, intermittent runs."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import new_folder

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string, slot int"


def event_stream(spark: SparkSession, path: str, files_each: int = 2) -> DataFrame:
    """A folder of JSON files as a stream; ts is a timestamp, as watermarks need."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_each).json(path)


def run_once(df: DataFrame, mode: str = "append", folder: str | None = None) -> DataFrame:
    """Runs a stream until all that is there has been read, and gives back what it wrote; for complete and update modes
    the last value of each batch's rows is kept by foreachBatch, whose writes replace themselves when a batch is retried."""
    spark = df.sparkSession
    folder = folder or new_folder(spark)
    out = f"{folder}/out"

    def put(batch: DataFrame, number: int) -> None:
        target = out if mode == "complete" else f"{out}/batch={number}"
        batch.write.mode("overwrite").parquet(target)

    query = df.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    return spark.read.parquet(out)


def views_by_day(spark: SparkSession, path: str, ads: DataFrame) -> DataFrame:
    events = event_stream(spark, path).filter("event_type = 'view'").withColumn("ad_id", F.get_json_object("props", "$.k").cast("long"))
    counts = events.withWatermark("ts", "2 days").join(ads, "ad_id").groupBy("campaign", F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
    return run_once(counts.select("campaign", F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n"), "complete")


def sliding_rate(spark: SparkSession, path: str, seconds: int = 180) -> DataFrame:
    """The trailing rate over windows of some seconds, for the rate monitor."""
    events = event_stream(spark, path).withWatermark("ts", f"{seconds} seconds")
    return run_once(events.groupBy(F.window("ts", f"{seconds} seconds", "60 seconds").alias("w")).agg(F.count("*").alias("n")).select(F.unix_timestamp("w.start").alias("window_start"), (F.col("n") / seconds).alias("rate")), "complete")


def running_totals(spark: SparkSession, path: str) -> DataFrame:
    """Counts and exact sums (in cents) of each event type in state of our own; every update is written, the last counts."""

    def add(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, cents = state.get if state.exists else (0, 0)
        for frame in frames:
            n += len(frame)
            cents += int((frame["value"] * 100).round().sum())
        state.update((n, cents))
        yield pd.DataFrame({"event_type": [key[0]], "n": [n], "cents": [cents]})

    updates = event_stream(spark, path).select("event_type", "value").groupBy("event_type").applyInPandasWithState(add, "event_type string, n long, cents long", "n long, cents long", "update", "NoTimeout")
    last = run_once(updates, "update").groupBy("event_type").agg(F.max_by(F.struct("n", "cents"), "n").alias("x"))
    return last.select("event_type", "x.n", (F.col("x.cents") / 100).alias("total"))


def as_stream(df: DataFrame, files: int, order: str) -> DataFrame:
    """A table replayed as a stream of files in the order of a key."""
    spark, path = df.sparkSession, new_folder(df.sparkSession)
    df.repartitionByRange(files, order).write.parquet(path)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)


def join_streams(spark: SparkSession, orders: DataFrame, lines: DataFrame) -> DataFrame:
    """Aligned streams: each row gets the time of its key. Files are read in any order, so the watermark stays behind by
    the whole range of keys, and no row is late."""
    ends = orders.select(F.col("o_orderkey").alias("k")).union(lines.select("l_orderkey")).agg(F.min("k"), F.max("k")).first()
    delay = f"{(ends[1] or 0) - (ends[0] or 0) + 3600} seconds"
    at = lambda k: F.timestamp_seconds(F.col(k) + 86400).alias("at")
    left = as_stream(orders.select("o_orderkey", at("o_orderkey")), 3, "o_orderkey").withWatermark("at", delay)
    right = as_stream(lines.select("l_orderkey", at("l_orderkey")), 3, "l_orderkey").withWatermark("at", delay).withColumnRenamed("at", "l_at")
    near = (F.col("o_orderkey") == F.col("l_orderkey")) & F.col("l_at").between(F.col("at") - F.expr("interval 1 hour"), F.col("at") + F.expr("interval 1 hour"))
    return run_once(left.join(right, near).select("o_orderkey")).agg(F.count("*").alias("n"))


def distinct_events(spark: SparkSession, path: str) -> DataFrame:
    events = event_stream(spark, path)
    twice = events.unionByName(event_stream(spark, path)).withWatermark("ts", "40 days")
    return run_once(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id")).agg(F.count("*").alias("n"))


def intermittent_counts(spark: SparkSession, orders: DataFrame, batches: int) -> DataFrame:
    """One availableNow run for each planned batch over one checkpoint: files that came since the last run are read."""
    source, folder = new_folder(spark) + "/in", new_folder(spark)

    def put(batch: DataFrame, number: int) -> None:
        batch.groupBy("o_orderpriority").agg(F.count("*").alias("n")).write.mode("overwrite").parquet(f"{folder}/state/batch={number}")

    for b in range(batches):
        orders.select("o_orderpriority", "o_orderkey").filter(F.pmod("o_orderkey", F.lit(batches)) == b).write.mode("append").parquet(source)
        stream = spark.readStream.schema("o_orderpriority string, o_orderkey long").parquet(source)
        stream.writeStream.option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return spark.read.parquet(f"{folder}/state").groupBy("o_orderpriority").agg(F.sum("n").alias("n"))
