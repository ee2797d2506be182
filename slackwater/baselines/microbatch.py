"""The streaming baseline for real: every trigger processes what has come, whatever the deadline."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession

from ..run.repository import IncrementalQuery, StateStore
from ..sources.tables import STREAM_KEYS, new_folder, table


def micro_batch(spark: SparkSession, sf_dir: str, query: IncrementalQuery, triggers: int = 6) -> tuple[DataFrame, list[float]]:
    """The answer of a query on one stream and the seconds of each trigger. The stream is a folder with one file for each
    trigger; a trigger's state is written under its number, so one that is retried replaces itself."""
    stream, source, folder = query.streams[0], new_folder(spark), new_folder(spark)
    df = table(spark, sf_dir, stream)
    df.repartitionByRange(triggers, STREAM_KEYS[stream]).write.parquet(source)
    statics, store, took = query.static_tables(spark, sf_dir), StateStore(spark), []

    def put(batch: DataFrame, number: int) -> None:
        began = time.perf_counter()
        store.write(query.name, number, 0, query.combine(query.prepare({stream: batch}, statics)))
        took.append(time.perf_counter() - began)

    rows = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(source)
    rows.writeStream.option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).foreachBatch(put).start().awaitTermination()
    return query.finish(query.combine(store.read(query.name, 0))), took
