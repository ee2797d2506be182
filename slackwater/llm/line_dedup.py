"""Line dedup by a suffix array over line ids, in DataFrame functions alone.

Every document is a sequence of line ids (128-bit fingerprints of its lines without outer white space; blank lines are no
part of it). Prefix doubling ranks the suffixes by their first 1, 2, 4, ... lines: the order by 2h lines is that of the
pairs of ranks by h lines, at a suffix and h lines on. Ranks are dense and distributed: intervals of equal suffixes are
dealt out by range, numbered within each range and shifted. Suffixes that are alone in their interval are settled and
leave; rounds go on until none is left.

The intervals give longest common prefixes: a suffix has the first h lines in common with the first place of its
interval. From its longest such h, a suffix looks for the same interval with h/2, h/4, ... 1 lines more that an earlier
place shares, which gives the true length of the longest run that starts there and earlier (smaller doc_id, or the same
document and an earlier line). Lines of such runs are deleted if the runs have at least `min_lines` lines, a power of two,
or if the line has at least `min_words` words.

Rows: a null text has no lines and stays null; rows equal in doc_id and text count as one document and get the same
result; null doc_ids come first; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import GAP, WHITE, scratch

KEY = ("doc_id", "text_hash")
TAKEN = ("text_hash", "gone", "gone_doc_id", "gone_text_hash", "kept_text", "n_lines", "n_removed", "longest_run")


def line_places(docs: DataFrame) -> DataFrame:
    """One row for each line that isn't blank: its document, its place among those, its place in the text, its id."""
    bare = lambda x: F.btrim(x, F.lit(WHITE))
    numbered = F.filter(F.transform(F.split("text", "\n"), lambda x, i: F.struct(i.alias("at"), bare(x).alias("line"))), lambda s: s["line"] != "")
    df = docs.filter("text is not null").select("doc_id", F.xxhash64("text").alias("text_hash"), F.posexplode(numbered).alias("pos", "s"))
    return df.select(*KEY, "pos", F.col("s.at").alias("at"), F.xxhash64("s.line").alias("id"), F.xxhash64(F.lit(1), "s.line").alias("more"), F.size(F.split("s.line", GAP)).alias("n_words"))


def place() -> Column:
    return F.struct(*KEY, "pos")


def ranked(intervals: DataFrame, *order: str) -> DataFrame:
    """intervals with rank, from 0 without gaps in the given order, which tells them all apart."""
    dealt = scratch(intervals.repartitionByRange(*order).withColumn("part", F.spark_partition_id()))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    shift = dealt.groupBy("part").agg(F.count("*").alias("n_part")).select("part", F.coalesce(F.sum("n_part").over(before), F.lit(0)).alias("shift"))
    at = F.row_number().over(Window.partitionBy("part").orderBy(*order)) - 1
    return dealt.withColumn("at_part", at).join(F.broadcast(shift), "part").withColumn("rank", F.col("at_part") + F.col("shift")).drop("part", "at_part", "shift")


def suffix_levels(lines: DataFrame) -> list[DataFrame]:
    """For h = 1, 2, 4, ..., the suffixes whose first h lines are there more than once: KEY, pos, at, n_words, the rank
    of their interval in the order of suffixes by h lines, and its first place."""
    active, order, levels = lines, ("id", "more"), []
    while True:
        intervals = active.groupBy(*order).agg(F.count("*").alias("n"), F.min(place()).alias("first")).filter("n > 1").drop("n")
        level = scratch(active.join(ranked(intervals, *order), list(order)).select(*KEY, "pos", "at", "n_words", "rank", "first"))
        if level.isEmpty():
            return levels
        levels.append(level)
        reach = Window.partitionBy(*KEY).orderBy("pos").rangeBetween(1 << (len(levels) - 1), 1 << (len(levels) - 1))
        active = level.select(*KEY, "pos", "at", "n_words", F.col("rank").alias("head"), F.first("rank").over(reach).alias("tail")).filter("tail is not null")
        order = ("head", "tail")


def same_place(a: DataFrame, b: DataFrame, shift: Column | int = 0) -> Column:
    return (a["doc_id"].eqNullSafe(b["doc_id"])) & (a["text_hash"] == b["text_hash"]) & (a["pos"] + shift == b["pos"])


def longest_runs(levels: list[DataFrame], tops: DataFrame | None = None) -> DataFrame:
    """KEY, pos and run of every suffix that starts as an earlier one does, run being the most lines that it shares with
    any earlier one. tops: KEY and top; only suffixes that share `top` lines and not twice as many are then looked at."""
    group, kept, open_ = ["length", "name"], [*KEY, "pos"], None
    for k in range(len(levels) - 1, -1, -1):
        if open_ is not None:  # does anyone who looks on share 2 ** k lines more with an earlier place?
            more = levels[k].select(*KEY, "pos", F.col("rank").alias("ext"))
            wide = open_.join(more, same_place(open_, more, F.col("length")), "left").select(open_["*"], "ext")
            longer = wide.filter("ext is not null").groupBy(*group, "ext").agg(F.min(place()).alias("new"), F.max(F.when(F.col("looks"), place())).alias("last")).filter("last > new").drop("last")
            wide = scratch(wide.join(longer, [*group, "ext"], "left").withColumn("found", F.coalesce(F.col("looks") & (place() > F.col("new")), F.lit(False))))
            on = wide.filter("new is not null").select(*kept, (F.col("length") + (1 << k)).alias("length"), F.col("new").alias("name"), F.col("found").alias("looks"))
            stay = wide.select(*kept, *group, (F.col("looks") & ~F.col("found")).alias("looks"))
            open_ = on.unionByName(stay)
        # who is later here and not on the level above begins to look, in the company of its interval
        here = levels[k].select(*kept, F.lit(1 << k).alias("length"), F.col("first").alias("name"), (place() > F.col("first")).alias("looks"))
        if tops is not None:
            near = tops.filter(F.col("top") == 1 << k)
            on = here["doc_id"].eqNullSafe(near["doc_id"]) & (here["text_hash"] == near["text_hash"])
            here = here.join(near, on, "left").select(*(here[c] for c in here.columns if c != "looks"), (here["looks"] & F.col("top").isNotNull()).alias("looks"))
        elif k + 1 < len(levels):
            above = levels[k + 1].filter(place() > F.col("first")).select(*KEY, "pos").distinct().withColumn("above", F.lit(True))
            here = here.join(above, same_place(here, above), "left").select(*(here[c] for c in here.columns if c != "looks"), (here["looks"] & F.col("above").isNull()).alias("looks"))
        if k == 0:  # nothing is shorter: no company needed
            here = here.filter("looks")
            return (here if open_ is None else open_.filter("looks").unionByName(here)).select(*kept, F.col("length").alias("run"))
        open_ = here if open_ is None else open_.unionByName(here)
        # groups without anyone who looks are done
        open_ = scratch(open_.join(open_.filter("looks").select(*group).distinct(), group, "left_semi"))


def dedup_lines(docs: DataFrame, min_lines: int = 2, min_words: int = 1, lengths: bool = True) -> DataFrame:
    """docs (doc_id, text and any others; those named as in TAKEN are replaced) with kept_text, n_lines, n_removed and,
    if lengths are asked for, longest_run (lines of the longest deleted run that starts in the document). What is deleted
    does not depend on lengths, which need as many jobs again."""
    docs = docs.drop(*TAKEN)
    lines = scratch(line_places(docs))
    levels = suffix_levels(lines)
    docs = docs.withColumn("text_hash", F.xxhash64("text"))
    if levels:
        # the floors of runs cover what the runs cover: a run of 2h - 1 lines is two of h that overlap
        later = [x.filter(place() > F.col("first")).select(*KEY, "pos", "n_words", F.lit(1 << k).alias("run")) for k, x in enumerate(levels)]
        runs = later[0]
        for more in later[1:]:
            runs = runs.unionByName(more)
        runs = scratch(runs.filter((F.col("run") >= min_lines) | (F.col("n_words") >= min_words)).groupBy(*KEY, "pos").agg(F.max("run").alias("run")))
        ahead = Window.partitionBy(*KEY).orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
        marked = lines.select(*KEY, "pos", "at").join(runs, [lines[k].eqNullSafe(runs[k]) for k in (*KEY, "pos")], "left").select(*(lines[k] for k in (*KEY, "pos", "at")), "run")
        marked = marked.withColumn("covered", F.max(F.col("pos") + F.col("run")).over(ahead) > F.col("pos"))
        gone = marked.groupBy(*KEY).agg(F.collect_set(F.when(F.col("covered"), F.col("at"))).alias("gone"), F.max("run").alias("top")).filter(F.size("gone") > 0)
        if lengths:
            tops = runs.groupBy(*KEY).agg(F.max("run").alias("top"))
            longest = longest_runs(levels, scratch(tops.filter("top > 1"))).groupBy(*KEY).agg(F.max("run").alias("longest"))
            gone = gone.join(longest, [gone[k].eqNullSafe(longest[k]) for k in KEY], "left").select(*(gone[k] for k in KEY), "gone", F.coalesce("longest", "top").alias("longest_run"))
        else:
            gone = gone.drop("top")
    else:
        gone = docs.limit(0).select(*KEY, F.array().cast("array<int>").alias("gone"), F.lit(0).alias("longest_run"))
    run = ["longest_run"] if lengths else []
    gone = gone.select(*(F.col(k).alias(f"gone_{k}") for k in KEY), "gone", *run)
    df = docs.join(gone, docs["doc_id"].eqNullSafe(gone["gone_doc_id"]) & (docs["text_hash"] == gone["gone_text_hash"]), "left").drop("gone_doc_id", "gone_text_hash", "text_hash")
    kept = F.transform(F.array(F.split("text", "\n")), lambda a: F.array_join(F.transform(F.array_except(F.sequence(F.lit(0), F.size(a) - 1), F.col("gone")), lambda i: F.get(a, i)), "\n"))
    return df.select(
        *(c for c in df.columns if c not in ("gone", "longest_run")),
        F.when(F.col("gone").isNull(), F.col("text")).otherwise(F.get(kept, F.lit(0))).alias("kept_text"),
        F.size(F.filter(F.split(F.coalesce("text", F.lit("")), "\n"), lambda x: F.btrim(x, F.lit(WHITE)) != "")).cast("long").alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_removed"),
        *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in run),
    )
