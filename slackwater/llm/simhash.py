"""SimHash near-dedup by a self-join of the binary trie of fingerprints.

Distinct fingerprints are cut into ranges of about equal size, each a run of subtrees. Pairs of ranges whose common
prefixes differ in too many bits are never formed; every other pair is one task, which walks both tries together, bit by
bit: a pair of nodes keeps the bits that already differ, is dropped when they exceed the budget, and is compared in full
when both nodes are small. A task gives out a spanning forest of its links, never all pairs of a group; links are
joined into components by alternating stars, with every round written to the shared folder.

Rows: a null text, or one without words, has fingerprint zero and is linked like any other; equal rows share all
results; a component whose doc_ids are all null has a null id; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import lean, scratch, split_count

LEAF = 64


def shingle_hashes(text: str | None, words: int, seed: int) -> np.ndarray:
    """The hashes of a text's word shingles, repeats included, as unsigned integers."""
    tokens = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z alone change, 9 to 13 and 32 split
    if not tokens:
        return np.zeros(0, np.uint64)
    joined = b" ".join(tokens)
    ends = np.cumsum([len(t) + 1 for t in tokens]) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    span = min(words, len(tokens))
    digest = xxhash.xxh64_digest
    hashes = b"".join([digest(joined[s:e], seed) for s, e in zip(starts[: len(tokens) - span + 1].tolist(), ends[span - 1 :].tolist(), strict=True)])
    return np.frombuffer(hashes, ">u8").astype(np.uint64)


def majority(hashes: np.ndarray) -> int:
    """The bits that more than half of the hashes have, as a signed integer; zero without hashes."""
    bits = np.unpackbits(hashes.astype(">u8").view(np.uint8)).reshape(-1, 64)
    return int(np.packbits(bits.sum(axis=0, dtype=np.uint32) * 2 > len(bits)).view(">i8")[0])


def fingerprint(text: str | None, words: int, seed: int) -> int:
    """The fingerprint of a text as a signed integer; its bits are the majority over the hashes of word shingles."""
    return majority(shingle_hashes(text, words, seed))


def fingerprints(docs: DataFrame, words: int = 4, seed: int = 42, also: list[Column] | None = None) -> DataFrame:
    """doc_id, the columns `also`, and the fingerprint as a long, bits."""
    df = docs.select("doc_id", "text", *(also or []))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.drop_columns("text").append_column("bits", pa.array([fingerprint(t.as_py(), words, seed) for t in batch.column(1)], pa.int64()))

    return df.mapInArrow(lean(run), T.StructType([*df.drop("text").schema.fields, T.StructField("bits", T.LongType())]))


def labels_of(u: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
    """The smallest node of the component of each of n nodes that the links (u, v) join."""
    label = np.arange(n)
    while True:
        a, b = label[u], label[v]
        if (a == b).all():
            return label
        low = np.minimum(a, b)
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        while (label[label] != label).any():
            label = label[label]


def ranges(lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """The numbers of all half-open ranges, one after another."""
    n = hi - lo
    return np.arange(n.sum()) + np.repeat(lo - np.concatenate([[0], np.cumsum(n)[:-1]]), n)


def node_pairs(a: np.ndarray, b: np.ndarray, budget: int, leaf: int = LEAF, most: int = 1 << 18) -> Iterator[np.ndarray]:
    """Pairs of small nodes (from, to in a; from, to in b) of two sorted tries whose bits so far differ within budget.

    Pairs go down together, `most` at a time, deepest first, so that few are held at once.
    """

    def middle(x: np.ndarray, lo: np.ndarray, hi: np.ndarray, bit: np.uint64) -> np.ndarray:
        top = (x[lo] >> bit | np.uint64(1)) << bit  # the first value of the right child
        return np.clip(np.searchsorted(x, top), lo, hi)

    stack = [(0, np.array([[0, len(a), 0, len(b), 0]]))]
    while stack:
        depth, front = stack.pop()
        if len(front) > most:
            stack += [(depth, front[: len(front) // 2]), (depth, front[len(front) // 2 :])]
            continue
        small = (front[:, 1] - front[:, 0] <= leaf) & (front[:, 3] - front[:, 2] <= leaf) if depth < 64 else np.ones(len(front), bool)
        if small.any():
            yield front[small, :4]
        alo, ahi, blo, bhi, off = front[~small].T
        if not len(alo):
            continue
        bit = np.uint64(63 - depth)
        am, bm = middle(a, alo, ahi, bit), middle(b, blo, bhi, bit)
        front = np.concatenate([np.stack(x, axis=1) for x in ((alo, am, blo, bm, off), (am, ahi, bm, bhi, off), (alo, am, bm, bhi, off + 1), (am, ahi, blo, bm, off + 1))])
        front = front[(front[:, 0] < front[:, 1]) & (front[:, 2] < front[:, 3]) & (front[:, 4] <= budget)]
        if len(front):
            stack.append((depth + 1, front))


def close_links(a: np.ndarray, b: np.ndarray | None, budget: int, most: int = 1 << 21) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links within budget between two sorted arrays, or inside a if b is None. Whenever more
    than `most` links are held, they shrink to a forest."""
    other = a if b is None else b
    every = a if b is None else np.concatenate([a, b])
    shift = 0 if b is None else len(a)
    u, v, held = [], [], 0

    def forest() -> tuple[np.ndarray, np.ndarray]:
        label = labels_of(np.concatenate(u), np.concatenate(v), len(every))
        at = np.flatnonzero(label != np.arange(len(every)))
        return label[at], at

    for pairs in node_pairs(a, other, budget):
        if b is None:
            pairs = pairs[pairs[:, 0] <= pairs[:, 2]]
        pairs = pairs[np.lexsort((pairs[:, 1], pairs[:, 0]))]
        cuts = np.flatnonzero(np.any(np.diff(pairs[:, :2], axis=0) != 0, axis=1)) + 1
        for group in np.split(pairs, cuts) if len(pairs) else []:
            lo, hi = group[0, :2]
            for part in range(0, len(group), 1024):
                at = ranges(group[part : part + 1024, 2], group[part : part + 1024, 3])
                i, j = np.nonzero(np.bitwise_count(a[lo:hi, None] ^ other[at][None, :]) <= budget)
                i, j = i + lo, at[j] + shift
                keep = i != j
                i, j = i[keep], j[keep]
                if len(i) > 4 * (hi - lo):  # many links: a forest of them is enough
                    nodes, k = np.unique(np.concatenate([i, j]), return_inverse=True)
                    label = labels_of(k[: len(i)], k[len(i) :], len(nodes))
                    i, j = nodes[label], nodes
                    i, j = i[i != j], j[i != j]
                u.append(i)
                v.append(j)
                held += len(i)
        if held > most:
            x, y = forest()
            u, v, held = [x], [y], len(x)
    if not u:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    x, y = forest()
    return every[x], every[y]


def links(nodes: DataFrame, budget: int = 4, least: int = 8192, aim: int = 1 << 17, most_ranges: int = 4096) -> DataFrame:
    """Links (u, v) that join all fingerprints (the column bits, distinct) within budget of one another.

    Every range meets most others, so what is dealt out grows with the number of ranges: there are up to 32 of `least`
    fingerprints for the sake of small inputs, more only of `aim`, and most_ranges in all.
    """
    spark = nodes.sparkSession
    n = nodes.count()
    count = max(1, min(32, n // least), min(most_ranges, n // aim))
    cuts = np.array(sorted(set(nodes.agg(F.percentile_approx("bits", [k / count for k in range(1, count)], 10 * count)).first()[0] or [])) if count > 1 else [], dtype=np.int64)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bits = batch.column(0).to_numpy(zero_copy_only=False)
            to = np.searchsorted(cuts, bits, side="right")
            for k in np.unique(to):
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([bits[to == k].tobytes()], pa.binary())], names=["k", "held"])

    def gather(table: pa.Table) -> pa.Table:
        bits = np.sort(np.frombuffer(b"".join(table.column("held").to_pylist()), np.int64))
        return pa.table({"k": pa.array([table.column("k")[0].as_py()], pa.int32()), "lo": pa.array([bits[0]], pa.int64()), "hi": pa.array([bits[-1]], pa.int64()), "held": pa.array([bits.tobytes()], pa.binary())})

    dealt = scratch(nodes.select("bits").mapInArrow(lean(deal), "k int, held binary").groupBy("k").applyInArrow(gather, "k int, lo long, hi long, held binary"))
    bounds = dealt.select("k", "lo", "hi").orderBy("k").toPandas()  # most_ranges rows at most
    lo, hi = (bounds[c].to_numpy().view(np.uint64) ^ np.uint64(1 << 63) for c in ("lo", "hi"))
    common = 64 - np.array([int(x).bit_length() for x in lo ^ hi])
    i, j = np.triu_indices(len(bounds))
    left = np.minimum(common[i], common[j])
    differ = np.where(left > 0, np.bitwise_count((lo[i] ^ lo[j]) >> np.minimum(64 - left, 63).astype(np.uint64)), 0)
    near = differ <= budget
    k = bounds["k"].to_numpy()
    pairs = spark.createDataFrame(pa.table({"k": pa.array(k[i[near]], pa.int32()), "l": pa.array(k[j[near]], pa.int32())}))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, l, x, y in zip(*(batch.column(c).to_pylist() for c in range(4)), strict=True):
                a, b = (np.frombuffer(z, np.uint64) ^ np.uint64(1 << 63) for z in (x, y))
                u, v = close_links(a, None if k == l else b, budget)
                yield pa.RecordBatch.from_arrays([pa.array((z ^ np.uint64(1 << 63)).view(np.int64), pa.int64()) for z in (u, v)], names=["u", "v"])

    both = pairs.join(dealt.select("k", "held"), "k").join(dealt.select(F.col("k").alias("l"), F.col("held").alias("other")), "l")
    parts = int(min(near.sum(), max(split_count(spark), 48)))
    return scratch(both.select("k", "l", "held", "other").repartition(max(1, parts), "k", "l").mapInArrow(lean(compare), "u long, v long"))


def contract(batches: Iterator[pa.RecordBatch], most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Links (node, smaller node) that join what a partition's links join, in blocks of about `most` links."""
    u, v, held = [], [], 0

    def give() -> pa.RecordBatch:
        nodes, k = np.unique(np.concatenate([*u, *v]), return_inverse=True)
        root = nodes[labels_of(k[: len(k) // 2], k[len(k) // 2 :], len(nodes))]
        return pa.RecordBatch.from_arrays([pa.array(x[root != nodes], pa.int64()) for x in (nodes, root)], names=["u", "v"])

    for batch in batches:
        u.append(batch.column(0).to_numpy(zero_copy_only=False))
        v.append(batch.column(1).to_numpy(zero_copy_only=False))
        held += batch.num_rows
        if held >= most:
            yield give()
            u, v, held = [], [], 0
    if held:
        yield give()


def components(edges: DataFrame) -> DataFrame:
    """node and root (the smallest node that it is linked to, over any number of links) of every node of edges (u, v).

    Partitions join what they can; then alternating stars, until every node hangs on one that hangs on none."""
    edges = scratch(edges.select("u", "v").mapInArrow(lean(contract), "u long, v long"))
    while True:
        ends = edges.select(F.explode(F.array(F.struct(F.col("u").alias("node"), F.lit(1).alias("below"), F.lit(0).alias("above")), F.struct(F.col("v").alias("node"), F.lit(0).alias("below"), F.lit(1).alias("above")))).alias("e"))
        if ends.groupBy("e.node").agg(F.sum("e.below").alias("below"), F.max("e.above").alias("above")).filter("below + above > 1").isEmpty():
            return edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
        # large star: everything above a node hangs on the smallest neighbour
        both = edges.union(edges.select("v", "u"))
        least = scratch(both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m")))
        edges = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        # small star: a node and what lies below it hang on the smallest of them
        edges = scratch(edges)
        least = scratch(edges.groupBy("u").agg(F.min("v").alias("m")))
        edges = edges.join(least, "u").select(F.explode(F.array(F.struct(F.col("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").filter("u <> v")
        edges = scratch(edges.distinct().mapInArrow(lean(contract), "u long, v long"))


def groups(prints: DataFrame, budget: int = 4) -> DataFrame:
    """bits, root and component_id of every fingerprint in prints (doc_id, bits); a root is one group's own."""
    nodes = scratch(prints.groupBy("bits").agg(F.min("doc_id").alias("least")))
    return named_groups(nodes, links(nodes, budget))


def named_groups(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """bits, root and component_id of every node (bits, and its smallest doc_id, least) when edges (u, v) join them."""
    roots = components(edges)
    named = scratch(nodes.join(roots, nodes["bits"] == roots["node"], "left").select("bits", "least", F.coalesce("root", "bits").alias("root")))
    group = scratch(named.groupBy("root").agg(F.min("least").alias("component_id")))
    return scratch(named.join(group, "root").select("bits", "root", "component_id"))


def near_duplicates(docs: DataFrame, words: int = 4, budget: int = 4, seed: int = 42) -> DataFrame:
    """doc_id, fingerprint (16 hexadecimal digits) and component_id of every row of docs (doc_id, text)."""
    prints = scratch(fingerprints(docs, words, seed))
    return prints.join(groups(prints, budget), "bits").select("doc_id", F.lower(F.lpad(F.hex("bits"), 16, "0")).alias("fingerprint"), "component_id")


def keep_first(docs: DataFrame, words: int = 5, budget: int = 4, seed: int = 42) -> DataFrame:
    """The rows of docs that stay when each group of near-duplicates keeps one: that of the smallest doc_id; of several
    rows with that id, that of the smallest text hash. Columns stay as they are."""
    key = F.xxhash64(F.coalesce("text", F.lit("")))
    prints = scratch(fingerprints(docs, words, seed, [key.alias("key")]))
    return first_rows(docs, prints, groups(prints, budget))


def first_rows(docs: DataFrame, prints: DataFrame, named: DataFrame) -> DataFrame:
    """The rows of docs that keep_first keeps, by prints (doc_id, key, bits) and the groups of bits."""
    key = F.xxhash64(F.coalesce("text", F.lit("")))
    first = prints.join(named, "bits").filter(F.col("doc_id").eqNullSafe(F.col("component_id")))
    first = scratch(first.groupBy("root", "doc_id").agg(F.min("key").alias("key")).select(F.col("doc_id").alias("first_id"), F.col("key").alias("first_key")))
    tagged = docs.withColumns({"_key": key, "_salt": F.monotonically_increasing_id()})
    stays = tagged.join(first, tagged["doc_id"].eqNullSafe(first["first_id"]) & (tagged["_key"] == first["first_key"])).select(*docs.columns, "_key", "_salt")
    one = Window.partitionBy("doc_id", "_key").orderBy("_salt")
    return stays.withColumn("_n", F.row_number().over(one)).filter("_n = 1").select(*docs.columns)
