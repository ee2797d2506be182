"""Quality rules by distribution divergence, in DataFrame functions alone.

Every text has two histograms: over character classes, and over the common words of its language, which are learned: the
words that are most frequent in all texts of that language. References are the means of those histograms over all
documents that pass the base rules. Languages of `least_docs` documents or more have lists and references of their own
(the 256 of most documents), all others share one. A text is rejected if the Jensen-Shannon distance (base 2, 0 to 1) of
either histogram to the reference is too large. Both limits come from the references: for classes, `class_spread` standard
deviations beyond the mean distance of the documents that made it; for words, `word_share` of the distance that a text
without any common word has. Guards: texts with fewer words than `guard_words` are judged by the base rules alone.

Rows: a null text has no words and fails the base rules; null languages belong to the shared list; with no reference (an
empty table, or no passing text) nothing is rejected by divergence; repeated rows are judged each; other columns are
ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import GAP, WHITE, scratch

OTHER = "*"
SYMBOLS = "#*$%&|<>"
"""Fixed values: the characters counted as symbols."""
PUNCTUATION = ".,;:!?'\"()-"


def let(value: Column, use) -> Column:
    """Evaluates value once and hands it to use."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0).cast("long"), lambda a, x: a + x)


def words_of(text: Column) -> Column:
    trimmed = F.btrim(text, F.lit(WHITE))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, GAP))


def repeated_words(words: Column, span: int = 3) -> Column:
    """How many words stand in windows of `span` words found twice or more in the text."""

    def covered(places: Column) -> Column:
        return total(F.transform(places, lambda p, k: F.coalesce(F.least(F.get(places, k + 1) - p, F.lit(span)), F.lit(span)).cast("long")))

    def twice(keyed: Column) -> Column:
        same = lambda x, k: F.coalesce(F.get(keyed, k)["w"] == x["w"], F.lit(False))
        return let(F.array_sort(F.transform(F.filter(keyed, lambda x, k: same(x, k + 1) | ((k > 0) & same(x, F.greatest(k - 1, F.lit(0))))), lambda x: x["i"])), covered)

    def windows(w: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(w) - span), lambda i: F.xxhash64(*(F.get(w, i + j) for j in range(span))))

    def count(t: Column) -> Column:
        keyed = F.transform(t, lambda x, i: F.struct(x.alias("w"), i.alias("i")))
        return F.when(F.size(F.array_distinct(t)) == F.size(t), F.lit(0).cast("long")).otherwise(let(F.array_sort(keyed), twice))

    return let(words, lambda w: F.when(F.size(w) < span, F.lit(0).cast("long")).otherwise(let(windows(w), count)))


def distance(p: Column, q: Column) -> Column:
    """Jensen-Shannon distance of two histograms that each sum to 1."""

    def part(a: Column, m: Column) -> Column:
        return F.when(a > 0, a * F.log2(a / m)).otherwise(F.lit(0.0))

    both = F.zip_with(p, q, lambda a, b: part(a, (a + b) / 2) + part(b, (a + b) / 2))
    return F.sqrt(F.greatest(F.aggregate(both, F.lit(0.0), lambda s, x: s + x) / 2, F.lit(0.0)))


def by_language(docs: DataFrame, least_docs: int, most_languages: int = 256) -> DataFrame:
    """doc_id, text (never null) and language, which is OTHER for all that have no list of their own."""
    own = docs.filter("lang is not null").groupBy("lang").agg(F.count("*").alias("n")).filter(F.col("n") >= least_docs)
    own = own.orderBy(F.desc("n"), "lang").limit(most_languages).select("lang", F.col("lang").alias("language"))
    df = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), "lang").join(F.broadcast(own), "lang", "left")
    return df.select("doc_id", "text", F.coalesce("language", F.lit(OTHER)).alias("language"))


def common_words(df: DataFrame, count: int) -> DataFrame:
    """language and listed: its `count` most frequent words in lower case, ties in the order of words."""
    words = df.select("language", F.explode(words_of(F.lower("text"))).alias("word")).groupBy("language", "word").agg(F.count("*").alias("n"))
    order = Window.partitionBy("language").orderBy(F.desc("n"), "word")
    best = words.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= count)
    return best.groupBy("language").agg(F.sort_array(F.collect_list(F.struct("rank", "word"))).alias("a")).select("language", F.transform("a", lambda s: s["word"]).alias("listed"))


def features(docs: DataFrame, least_docs: int = 20, n_common: int = 12) -> DataFrame:
    """Base counts and both histograms of every text."""
    df = by_language(docs, least_docs)
    lists = scratch(common_words(df, n_common))
    df = df.join(F.broadcast(lists), "language", "left").withColumns({"words": words_of(F.col("text")), "listed": F.coalesce("listed", F.array().cast("array<string>"))})

    def split_counts(words: Column) -> Column:
        found = F.filter(F.transform(words, F.lower), lambda w: F.array_contains(F.col("listed"), w))
        return let(found, lambda f: F.transform(F.col("listed"), lambda c: F.size(F.filter(f, lambda w: w == c))))

    number = lambda chars: F.regexp_count("text", F.lit("[" + re.escape(chars) + "]")).cast("long")
    n_chars = F.length("text").cast("long")
    df = df.select(
        "doc_id",
        "language",
        F.size("words").cast("long").alias("n_words"),
        (n_chars - number(WHITE)).alias("word_chars"),
        n_chars.alias("n_chars"),
        number(SYMBOLS).alias("n_symbols"),
        number("0123456789").alias("digits"),
        number(PUNCTUATION).alias("marks"),
        let(F.filter(F.split("text", "\n"), lambda x: F.btrim(x, F.lit(WHITE)) != ""), lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
        repeated_words(F.col("words")).alias("n_repeat_words"),
        split_counts(F.col("words")).alias("common"),
    )
    share = lambda c, of: F.when(F.col(of) > 0, c / F.col(of)).otherwise(F.lit(0.0)).cast("double")
    counted = F.aggregate("common", F.lit(0), lambda s, x: s + x)
    letters = F.col("word_chars") - F.col("n_symbols") - F.col("digits") - F.col("marks")
    return df.select(
        "doc_id", "language", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        F.array(*(share(c, "n_chars") for c in (letters, F.col("digits"), F.col("marks"), F.col("n_symbols"), F.col("n_chars") - F.col("word_chars")))).alias("classes"),
        F.concat(F.transform("common", lambda c: share(c, "n_words")), F.array(share(F.col("n_words") - counted, "n_words"))).alias("common"),
        ((F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))).alias("base_failed"),
    )


def references(df: DataFrame) -> DataFrame:
    """The mean histograms by language, at most one row for each list."""
    base = df.filter(~F.col("base_failed"))
    means = lambda name: base.select("language", F.posexplode(name).alias("k", "x")).groupBy("language", "k").agg(F.avg("x").alias("x")).groupBy("language").agg(F.array_sort(F.collect_list(F.struct("k", "x"))).alias("a")).select("language", F.transform("a", lambda s: s["x"]).alias(f"{name}_reference"))
    return means("classes").join(means("common"), "language")


def judge(docs: DataFrame, guard_words: int = 50, class_spread: float = 4.0, word_share: float = 0.9, least_docs: int = 20) -> DataFrame:
    """Base counts, both distances with their limits, and the verdict for every row of docs (doc_id, text, lang)."""
    df = scratch(features(docs, least_docs))
    known = scratch(references(df))
    df = df.join(F.broadcast(known), "language", "left")
    df = df.withColumns({f"{short}_distance": distance(F.col(name), F.col(f"{name}_reference")) for short, name in (("class", "classes"), ("word", "common"))})
    limits = df.filter(~F.col("base_failed")).groupBy("language").agg((F.avg("class_distance") + class_spread * F.coalesce(F.stddev_pop("class_distance"), F.lit(0.0))).alias("class_limit"))
    none = F.transform("common_reference", lambda x, i: F.when(i == F.size("common_reference") - 1, 1.0).otherwise(0.0))
    words = known.select("language", (word_share * distance(none, F.col("common_reference"))).alias("word_limit"))
    df = df.join(F.broadcast(limits.join(words, "language")), "language", "left")
    far = (F.col("class_distance") > F.col("class_limit")) | (F.col("word_distance") > F.col("word_limit"))
    kept = ~F.col("base_failed") & ~F.coalesce(far & (F.col("n_words") >= guard_words), F.lit(False))
    return df.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", kept.alias("kept"), "class_distance", "word_distance", "class_limit", "word_limit")
