"""Streams replayed in any order of their files."""

import os
import time
from pathlib import Path

from slackwater.sources.tables import new_folder
from slackwater.streaming import views


def test_stream_join_counts_rows_far_behind(spark, monkeypatch):
    def latest_first(df, files, order):
        path = new_folder(spark)
        keys = [r[0] for r in df.select(order).distinct().orderBy(order).collect()]
        for k, at in enumerate(keys[::-1]):
            df.filter(f"{order} = {at}").coalesce(1).write.mode("append").parquet(path)
            for f in Path(path.removeprefix("file:")).glob("*.parquet"):
                if f not in seen:
                    seen.add(f)
                    os.utime(f, (time.time() - 1000 + 10 * k,) * 2)
        return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(path)

    seen = set()
    monkeypatch.setattr(views, "as_stream", latest_first)
    orders = spark.createDataFrame([(k * 3_000_000,) for k in range(5)], "o_orderkey long")
    lines = spark.createDataFrame([(k * 3_000_000,) for k in range(5) for _ in range(2)], "l_orderkey long")
    assert views.join_streams(spark, orders, lines).first().n == 10
