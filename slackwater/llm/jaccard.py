"""Near copies by exact Jaccard similarity of word shingles; SimHash links are the first candidates.

Rows of equal shingle sets are one node. Two sets of similarity `least` or more share one of the first shingles of both,
in any one order of all shingles: the rarest come first here, so shingles of one node alone only use up places. Nodes
that share such a shingle are a list. Pairs are checked exactly: first SimHash's links; then, in small lists, all pairs
that no link joins so far; in large lists some leaders against the others, and last, if a list is not joined yet, its
blocks against one another by matrix products that give out forests. No pair of `least` or more is left out.

Rows: texts without words are one node; equal rows share all results; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import simhash
from .common import lean, scratch


def shingles(text: str | None, words: int, seed: int) -> np.ndarray:
    """The distinct hashes of a text's word shingles, those that its fingerprint counts, in ascending order."""
    return np.unique(simhash.shingle_hashes(text, words, seed))


def nodes_of(docs: DataFrame, words: int, seed: int, key: Column) -> DataFrame:
    """doc_id, key, the node (a hash of the shingle set), its number of shingles n and the fingerprint, for every row."""
    df = docs.select("doc_id", "text", key.alias("key"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hashes = [simhash.shingle_hashes(t.as_py(), words, seed) for t in batch.column(1)]
            sets = [np.unique(h) for h in hashes]
            node = np.array([xxhash.xxh64_intdigest(s.tobytes(), seed) for s in sets], np.uint64).view(np.int64)
            out = batch.drop_columns("text").append_column("node", pa.array(node, pa.int64())).append_column("n", pa.array([len(s) for s in sets], pa.int64()))
            yield out.append_column("bits", pa.array([simhash.majority(h) for h in hashes], pa.int64()))

    doc_id = df.schema["doc_id"].dataType.simpleString()
    return df.mapInArrow(lean(run), f"doc_id {doc_id}, key long, node long, n long, bits long")


def shared_shingles(docs: DataFrame, words: int, seed: int, count: int) -> DataFrame:
    """node, shingle and the number of nodes that have it, df, for shingles of two nodes or more; `count` shares of hashes."""

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = {xxhash.xxh64_intdigest(s.tobytes(), seed): s for s in (shingles(t.as_py(), words, seed) for t in batch.column(0))}
            every = np.concatenate([np.zeros(0, np.uint64), *sets.values()])
            node = np.repeat(np.array(list(sets), np.uint64), [len(s) for s in sets.values()])
            k = (every % np.uint64(count)).astype(np.int64)
            order = np.argsort(k, kind="stable")
            for at in np.split(order, np.flatnonzero(np.diff(k[order])) + 1) if len(order) else []:
                yield pa.RecordBatch.from_arrays([pa.array([k[at[0]]], pa.int64()), pa.array([every[at].tobytes()], pa.binary()), pa.array([node[at].tobytes()], pa.binary())], names=["k", "shingle", "node"])

    def count_nodes(table: pa.Table) -> pa.Table:
        s, node = (np.frombuffer(b"".join(table.column(c).to_pylist()), np.uint64) for c in ("shingle", "node"))
        order = np.lexsort((node, s))
        s, node = s[order], node[order]
        new = np.concatenate([[True], (np.diff(s) != 0) | (np.diff(node) != 0)])
        s, node = s[new], node[new]
        _, at, df = np.unique(s, return_inverse=True, return_counts=True)
        keep = df[at] > 1
        return pa.table({"node": pa.array(node[keep].view(np.int64)), "shingle": pa.array(s[keep].view(np.int64)), "df": pa.array(df[at][keep].astype(np.int64))})

    return docs.select("text").mapInArrow(lean(deal), "k long, shingle binary, node binary").groupBy("k").applyInArrow(count_nodes, "node long, shingle long, df long")


def similar(a: Column, b: Column, n: Column, m: Column, least: int) -> Column:
    both = F.size(F.array_intersect(a, b))
    return 100 * both >= least * (n + m - both)


def overlaps(shingle: np.ndarray, member: np.ndarray, a: np.ndarray, b: np.ndarray, dense: int = 16, width: int = 4096) -> np.ndarray:
    """How many shingles each member of a shares with each of b; (shingle, member) are their sets."""
    order = np.argsort(shingle, kind="stable")
    shingle, member = shingle[order], member[order]
    first = np.flatnonzero(np.concatenate([[True], shingle[1:] != shingle[:-1]]))
    df = np.diff(np.append(first, len(shingle)))
    to_a, to_b = (np.full(max(a.max(), b.max(), member.max()) + 1, -1) for _ in range(2))
    to_a[a], to_b[b] = np.arange(len(a)), np.arange(len(b))
    both = np.zeros((len(a), len(b)), np.float32)
    often = np.flatnonzero(df >= dense)
    for at in range(0, len(often), width):  # what many have: products of incidence matrices
        some = often[at : at + width]
        m, column = member[simhash.ranges(first[some], first[some] + df[some])], np.repeat(np.arange(len(some)), df[some])
        x, y = np.zeros((len(a), len(some)), np.float32), np.zeros((len(b), len(some)), np.float32)
        x[to_a[m[to_a[m] >= 0]], column[to_a[m] >= 0]] = 1
        y[to_b[m[to_b[m] >= 0]], column[to_b[m] >= 0]] = 1
        both += x @ y.T
    few = np.flatnonzero(df < dense)
    start, count = np.repeat(first[few], df[few]), np.repeat(df[few], df[few])
    i = np.repeat(simhash.ranges(first[few], first[few] + df[few]), count)
    i, j = to_a[member[i]], to_b[member[simhash.ranges(start, start + count)]]
    keep = (i >= 0) & (j >= 0)
    return both + np.bincount(i[keep] * len(b) + j[keep], minlength=both.size).reshape(both.shape)


def block_links(lists: DataFrame, held: DataFrame, least: int, members: int = 512, shingles_each: int = 1 << 19) -> DataFrame:
    """Links that join whatever is similar in large lists (list, node, n). Every two blocks of a list meet in a task of
    their own, which gives out a forest, not all pairs; blocks are bounded in members and in shingles."""
    sized = lists.groupBy("list").agg(F.greatest(F.ceil(F.count("*") / members), F.ceil(F.sum("n") / shingles_each)).cast("int").alias("blocks"))
    dealt = lists.select("list", "node").join(sized, "list").withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    met = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    met = met.select("list", "node", "block", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j")).join(held.select("node", "n", "x"), "node")

    def compare(table: pa.Table) -> pa.Table:
        node, n, block = (table.column(c).to_numpy() for c in ("node", "n", "block"))
        i, j = table.column("i")[0].as_py(), table.column("j")[0].as_py()
        x = table.column("x").combine_chunks()
        sizes = np.diff(np.asarray(x.offsets))
        a, b = np.flatnonzero(block == i), np.flatnonzero(block == j)
        u = v = np.zeros(0, np.int64)
        if len(a) and len(b):
            both = overlaps(x.flatten().to_numpy(), np.repeat(np.arange(len(node)), sizes), a, b)
            u, v = np.nonzero(100 * both >= least * (n[a][:, None] + n[b][None, :] - both))
            u, v = a[u], b[v]
        root = simhash.labels_of(u, v, len(node))
        at = np.flatnonzero(root != np.arange(len(node)))
        return pa.table({"u": pa.array(node[root[at]], pa.int64()), "v": pa.array(node[at], pa.int64())})

    return met.groupBy("list", "i", "j").applyInArrow(compare, "u long, v long")


def links(docs: DataFrame, nodes: DataFrame, words: int, budget: int, least: int, seed: int, rounds: int = 2, small: int = 64, share: int = 1 << 20) -> DataFrame:
    """Links (u, v) of similarity `least` (in hundredths) or more that join all nodes with such a link."""
    total = nodes.agg(F.sum("n")).first()[0] or 0
    shared = shared_shingles(docs, words, seed, max(48, total // share))
    rare = F.sort_array(F.collect_list(F.struct("df", "shingle")))
    held = shared.groupBy("node").agg(rare.alias("x")).join(nodes.select("node", "n"), "node").withColumn("x", F.transform("x", lambda s: s["shingle"]))
    # of the first n - ceil(least n) + 1 shingles, those that are the node's own are used up
    left = F.expr(f"size(x) - ({least} * n + 99) div 100 + 1")
    held = scratch(held.select("node", "n", "x", left.cast("int").alias("left")).filter("left > 0"))
    first = held.select("node", "n", F.explode(F.slice("x", F.lit(1), F.least("left", F.size("x")))).alias("shingle"))
    lists = first.groupBy("shingle").agg(F.sort_array(F.collect_list(F.struct("n", "node"))).alias("m")).filter("size(m) > 1").select("m").distinct()
    lists = scratch(lists.select(F.xxhash64("m").alias("list"), F.explode("m").alias("s")).select("list", "s.n", "s.node").distinct())

    def checked(pairs: DataFrame) -> DataFrame:
        a, b = (held.select(F.col("node").alias(c), F.col("n").alias(f"n_{c}"), F.col("x").alias(f"x_{c}")) for c in ("u", "v"))
        pairs = pairs.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).filter("u < v").distinct()
        return pairs.join(a, "u").join(b, "v").filter(similar(F.col("x_u"), F.col("x_v"), F.col("n_u"), F.col("n_v"), least)).select("u", "v")

    same = nodes.groupBy("bits").agg(F.min("node").alias("u"))
    near = simhash.links(same.select("bits"), budget)
    ends = [same.select(F.col("bits").alias(f"bits_{c}"), F.col("u").alias(c)) for c in ("u", "v")]
    near = near.select(F.col("u").alias("bits_u"), F.col("v").alias("bits_v")).join(ends[0], "bits_u").join(ends[1], "bits_v").select("u", "v")
    found = scratch(checked(near.union(nodes.join(same, "bits").select("u", F.col("node").alias("v")))))
    close = lambda n, m: 100 * F.least(n, m) >= least * F.greatest(n, m)
    for k in range(rounds + 1):
        rooted = lists.join(simhash.components(found), "node", "left").select("list", "node", "n", F.coalesce("root", "node").alias("root"))
        open_lists = rooted.groupBy("list").agg(F.min("root").alias("a"), F.max("root").alias("b"), F.count("*").alias("size"), F.min(F.struct(F.xxhash64("node", F.lit(k)), "node", "n", "root")).alias("leader")).filter("a < b")
        rooted = scratch(rooted.join(open_lists.select("list", "leader", "size"), "list"))
        if rooted.isEmpty():
            break
        large = rooted.filter(F.col("size") > small)
        a, b = (rooted.filter(F.col("size") <= small).select("list", *(F.col(c).alias(f"{c}_{e}") for c in ("node", "n", "root"))) for e in ("u", "v"))
        on = (F.col("node_u") < F.col("node_v")) & (F.col("root_u") != F.col("root_v")) & close(F.col("n_u"), F.col("n_v"))
        pairs = a.join(b, "list").filter(on).select(F.col("node_u").alias("u"), F.col("node_v").alias("v"))
        if k < rounds:
            led = large.filter((F.col("root") != F.col("leader.root")) & close(F.col("n"), F.col("leader.n"))).select(F.col("leader.node").alias("u"), F.col("node").alias("v"))
            found = scratch(found.union(checked(led.union(pairs))))
        else:
            found = scratch(found.union(checked(pairs)).union(block_links(large, held, least)))
        if large.isEmpty():
            break
        lists = scratch(large.select("list", "n", "node"))
    return found


def keep_first(docs: DataFrame, words: int = 5, budget: int = 4, least: int = 80, seed: int = 42) -> DataFrame:
    """The rows of docs that stay when each group that links of similarity `least` join keeps one: that of the smallest
    doc_id; of several rows with that id, that of the smallest text hash. Columns stay as they are."""
    prints = scratch(nodes_of(docs, words, seed, F.xxhash64(F.coalesce("text", F.lit("")))))
    nodes = scratch(prints.groupBy("node").agg(F.first("n").alias("n"), F.first("bits").alias("bits"), F.min("doc_id").alias("least")))
    named = simhash.named_groups(nodes.select(F.col("node").alias("bits"), "least"), links(docs, nodes, words, budget, least, seed))
    return simhash.first_rows(docs, prints.select("doc_id", "key", F.col("node").alias("bits")), named)
