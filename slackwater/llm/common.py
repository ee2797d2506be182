"""What the operators share: reading tables, scratch tables in the shared folder, tokenizers, bit tricks."""

from __future__ import annotations

import base64
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WHITE = " \t\n\x0b\x0c\r"
"""Fixed values: the white space that separates words, space and the characters 9 to 13."""
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return df.select(*columns) if columns else df


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share; one of our own only where the session names none and is local."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="slackwater-")
        spark.sparkContext.setCheckpointDir(named)
    return named


def scratch(df: DataFrame) -> DataFrame:
    """Writes df to the shared folder and reads it back: lineage is cut, and a lost executor costs one read."""
    spark = df.sparkSession
    path = f"{shared_folder(spark).rstrip('/')}/slackwater/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def split_count(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


@lru_cache(maxsize=4)
def ranks_of(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}


@lru_cache(maxsize=4)
def rank_encoding(path: str, pattern: str):
    """A tiktoken encoding over a rank file, one for each Python worker."""
    import tiktoken

    return tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks_of(path), special_tokens={})


def token_ids(encoding, text: str | None, end_id: int | None) -> np.ndarray:
    """The ids of a text as unsigned 32-bit integers; a null text is empty; end_id closes it."""
    ids = np.asarray(encoding.encode_ordinary(text or ""), dtype="<u4")
    return ids if end_id is None else np.append(ids, np.uint32(end_id)).astype("<u4", copy=False)


def packed_bytes(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column end to end, and the n + 1 offsets of its values; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64, count=len(column) + 1 + column.offset)[column.offset :]
    data = column.buffers()[2]
    data = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def spread(*columns: str) -> F.Column:
    """A hash that deals rows out evenly whatever the columns hold."""
    return F.xxhash64(*columns)


def give_back() -> None:
    """Gives memory that this process no longer needs back to the system."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of glibc alone
    if trim:
        trim(0)


def lean(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]):
    """run, and afterwards the worker, which serves other tasks later, gives the memory that it no longer needs back."""

    def done(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            give_back()

    return done
