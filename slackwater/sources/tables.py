"""Scans with fixed schemas, and the slots that stand for the work units of a stream."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

SCHEMAS = {
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "region": "r_regionkey int, r_name string",
}
STREAM_KEYS = {"orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id"}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; its schema is the files' own where none is fixed here."""
    reader = spark.read.schema(SCHEMAS[name]) if name in SCHEMAS else spark.read
    return reader.parquet(f"{sf_dir}/{name}.parquet")


def read_table(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | T.StructType | None = None, **options) -> DataFrame:
    """A scan of parquet, orc, csv, json or text; the last three need a schema, as nothing is inferred."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} is read with a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def with_file(df: DataFrame) -> DataFrame:
    """The file of each row, for unit manifests."""
    return df.withColumns({"path": F.col("_metadata.file_path"), "file_size": F.col("_metadata.file_size")})


def slotted(df: DataFrame, key: str, n_slots: int, last_key: int) -> DataFrame:
    """Adds slot, 0 to n_slots - 1, a function of the key alone: equal keys of two streams share a slot, so streams are
    aligned; ranges of slots are ranges of keys, so a scan of a sorted table is pruned by them."""
    return df.withColumn("slot", F.floor(F.col(key) * F.lit(n_slots) / F.lit(last_key + 1)).cast("int"))


def slot_range(df: DataFrame, key: str, lo: int, hi: int, n_slots: int, last_key: int) -> DataFrame:
    """The rows of slots lo to hi - 1, as a range of keys that reaches the scan as a pushed filter."""
    first = lambda s: -(-s * (last_key + 1) // n_slots)
    return df.filter((F.col(key) >= first(lo)) & (F.col(key) < first(hi)))


def last_key(spark: SparkSession, sf_dir: str, stream: str) -> int:
    """The greatest key of a stream; orders decide for lineitem. One row comes to the driver."""
    stream = "orders" if stream == "lineitem" else stream
    return table(spark, sf_dir, stream).agg(F.max(STREAM_KEYS[stream])).first()[0] or 0


def late_lines(lines: DataFrame, n_slots: int, last: int) -> DataFrame:
    """lineitem with the slot of its order (event_slot) and the slot of its arrival; one line in twenty is late."""
    df = slotted(lines, "l_orderkey", n_slots, last).withColumnRenamed("slot", "event_slot")
    late = (F.col("l_orderkey") * 7 + F.col("l_linenumber")) % 20 == 0
    return df.withColumn("slot", F.when(late, F.least(F.col("event_slot") + 1 + F.col("l_linenumber") % 3, F.lit(n_slots - 1))).otherwise(F.col("event_slot")).cast("int"))


def day_slices(spark: SparkSession, sf_dir: str, hours: int, *keys: str) -> DataFrame:
    """How many events (n) came in each slice of so many hours, numbered from 1, of each day (and keys)."""
    each = (F.floor(F.hour("ts") / hours) + 1).cast("int")
    return table(spark, sf_dir, "events").groupBy(F.to_date("ts").cast("string").alias("day"), *keys, each.alias("slice")).agg(F.count("*").alias("n"))


def ad_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which campaign an ad belongs to."""
    return table(spark, sf_dir, "part").filter("p_partkey < 100").select(F.col("p_partkey").alias("ad_id"), F.col("p_brand").alias("campaign"))


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share; one of our own where the session names none and is local."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        named = "file://" + tempfile.mkdtemp(prefix="slackwater-")
        spark.sparkContext.setCheckpointDir(named)
    return named.rstrip("/")


def new_folder(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/slackwater/{uuid.uuid4().hex}"
