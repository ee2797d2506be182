"""Where results go."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write_states(df: DataFrame, path: str, *partitions: str) -> None:
    """Parquet by partition; only the partitions in df are replaced, so a batch can be written again."""
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*partitions).parquet(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, *keys: str) -> None:
    """A table in buckets of its keys: joins and aggregates on them need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)


def run_only(df: DataFrame) -> None:
    """Runs a frame without keeping anything."""
    df.write.format("noop").mode("overwrite").save()
