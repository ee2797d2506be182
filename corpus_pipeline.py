"""The corpus pipeline: toxicity, line dedup, near-dedup, suffix-array dedup, packing.

Each stage takes what the one before kept, (spark, docs, sf_dir), and all but the last give back the columns of
documents. run() applies them to documents, with every stage's result written to the shared folder and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from slackwater.llm import jaccard, line_dedup, packing, suffix_dedup, toxicity
from slackwater.llm.common import documents, scratch
from slackwater.llm.queries import PATTERN, RANKS


def apart(docs: DataFrame) -> DataFrame:
    """docs with all columns but doc_id and text renamed, so that none clashes with what an operator adds."""
    return docs.select(*(F.col(f"`{c}`").alias(c if c in ("doc_id", "text") else f"other_{i}") for i, c in enumerate(docs.columns)))


def back(docs: DataFrame, made: DataFrame, text: str = "text") -> DataFrame:
    """The columns of docs from what an operator made of apart(docs); the text is what is in the column `text`, and its
    length goes with it."""

    def column(i: int, name: str):
        if name == "text":
            return F.col(text)
        if name == "n_chars" and text != "text":
            return F.length(text).cast(docs.schema[name].dataType)
        return F.col(name if name == "doc_id" else f"other_{i}")

    return made.select(*(column(i, c).alias(c) for i, c in enumerate(docs.columns)))


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that are more likely toxic than not go."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return back(docs, toxicity.scored(apart(docs), toxicity.fit(docs, labels)).filter("score < 0.5"))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return back(docs, line_dedup.dedup_lines(apart(docs), min_words=1, lengths=False), "kept_text")


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return back(docs, jaccard.keep_first(apart(docs), words=5, budget=4, least=80))


def drop_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return back(docs, suffix_dedup.dedup(apart(docs), length=100), "kept_text")


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, RANKS, PATTERN, room=1024, end_id=0)


STAGES = [("toxicity", drop_toxic), ("line dedup", drop_lines), ("near-dedup", drop_near_copies), ("suffix-array dedup", drop_repeats), ("packing", pack)]
ORACLE_SQL = None  # the machine, fingerprints and packing are beyond SQL; tests hold each stage against brute force


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    for _, stage in STAGES[:-1]:
        docs = scratch(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
