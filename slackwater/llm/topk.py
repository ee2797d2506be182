"""Exact top-k search by inner product with MaxScore.

Every dimension is a term with a posting list of one weight for each vector. In a shard, a term's bound for a query is
the most that any of its postings can add over the least. Terms are taken in ascending order of bounds: as long as all of
them together cannot bring a vector to the k-th best score known so far, they are non-essential; the rest are essential
and are traversed for all vectors. Vectors are then probed for the others, in descending order of bounds, only while what
they have and what the rest could add may still reach the k-th best score.

Queries are the smaller side: their blocks go to every shard. A first search, of one shard, finds a k-th best score for
each query, which the searches of all shards start from and raise block by block of vectors. Shards are merged by score,
ties by vector id.

Rows: vectors that are null, empty or hold null or non-finite components take no part, as queries or candidates;
missing dimensions count as zero; a repeated vec_id gives a candidate for each row, but no row of the query's own id;
an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import lean, scratch, split_count, spread


def whole_vectors(vectors: DataFrame, scale: int) -> DataFrame:
    """vec_id and the components as integers, of the vectors that take part."""
    sound = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return vectors.filter(F.col("embedding").isNotNull() & (F.size("embedding") > 0) & sound & F.col("vec_id").isNotNull()).select("vec_id", F.transform("embedding", lambda x: F.floor(F.lit(float(scale)) * x.cast("double")).cast("long")).alias("x"))


def blocks(vectors: DataFrame, rows: int, name: str) -> DataFrame:
    """Rows of `rows` vectors or so: a number, the ids and a matrix of integers."""
    count = max(1, -(-vectors.count() // rows))

    def gather(table: pa.Table) -> pa.Table:
        width = max(len(x) for x in table.column("x"))
        x = np.zeros((table.num_rows, width), np.int64)
        for i, row in enumerate(table.column("x").to_pylist()):
            x[i, : len(row)] = row
        ids = table.column("vec_id").to_numpy()
        order = np.argsort(ids, kind="stable")
        return pa.table({name: pa.array([table.column(name)[0].as_py()], pa.int32()), f"{name}_ids": pa.array([ids[order].astype(np.int64).tobytes()], pa.binary()), f"{name}_x": pa.array([x[order].tobytes()], pa.binary())})

    return scratch(vectors.withColumn(name, F.pmod(spread("vec_id"), F.lit(count)).cast("int")).groupBy(name).applyInArrow(gather, f"{name} int, {name}_ids binary, {name}_x binary"))


class Shard:
    """Vectors with the least and the greatest weight of each posting list."""

    def __init__(self, ids: np.ndarray, x: np.ndarray):
        self.ids, self.low, self.high = ids, x.min(axis=0), x.max(axis=0)
        self.postings = np.ascontiguousarray(x.T)
        self.products = 0  # multiplications so far

    def split(self, bound: np.ndarray, missing) -> int:
        """How many terms, in the descending order of bound, are essential if the others' sum must stay below `missing`,
        what a vector needs beyond the least scores; all, if nothing is known."""
        if missing is None:
            return len(bound)
        return int(np.count_nonzero(bound[::-1].cumsum() >= missing))

    def top(self, query_id: int, q: np.ndarray, k: int, known=None, step: int = 8) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of all vectors that may be among the k best of this shard and reach `known`, a score that k
        vectors have; best first, k at most."""
        n = min(len(q), len(self.postings))
        q, postings = q[:n], self.postings[:n]
        most, least = np.maximum(q * self.high[:n], q * self.low[:n]), np.minimum(q * self.high[:n], q * self.low[:n])
        order = np.argsort(-(most - least), kind="stable")
        rest, floor = (np.append(x[order][::-1].cumsum()[::-1], 0) for x in (most, least))
        at = np.flatnonzero(self.ids != query_id)
        score = np.zeros(len(at), q.dtype)
        done, width = 0, self.split((most - least)[order], None if known is None else known - floor[0])
        if known is not None and rest[0] < known:
            at = at[:0]
        while done < n and len(at):
            terms = order[done : done + max(width, 1)]
            score = score + q[terms] @ (postings[terms] if len(at) == postings.shape[1] else postings[np.ix_(terms, at)])
            self.products += len(terms) * len(at)
            done += len(terms)
            sure = known
            if len(at) > k:  # scores that k vectors surely have
                here = np.sort(score)[len(score) - k] if score.dtype == object else np.partition(score, len(score) - k)[len(score) - k]
                sure = here + floor[done] if sure is None else max(sure, here + floor[done])
            if sure is not None:
                keep = score + rest[done] >= sure
                at, score = at[keep], score[keep]
            width = step
        best = np.lexsort((self.ids[at], -score))[:k]
        return self.ids[at][best], score[best]


def exact_type(a: np.ndarray, b: np.ndarray):
    """A type in which all inner products of the two are exact."""
    most = [int(max(abs(int(x.min())), abs(int(x.max())), 1)) for x in (a, b)]
    return np.float64 if most[0] * most[1] * a.shape[1] < 1 << 53 else object


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, scale: int = 256, shard_rows: int = 8192, query_rows: int = 256) -> DataFrame:
    """query_id, rank, vec_id and score of the k best vectors for each query (both: vec_id, embedding)."""
    shards, asked = blocks(whole_vectors(vectors, scale), shard_rows, "shard"), blocks(whole_vectors(queries, scale), query_rows, "block")
    kept = "query_id long, vec_id long, score long, block int"
    found_names = ["query_id", "vec_id", "score", "block"]

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows: a shard and a block of queries, with the scores known for them or null."""
        held, shard = None, None
        for batch in batches:
            for number, ids, x, block, query_ids, y, known in zip(*(batch.column(c).to_pylist() for c in range(7)), strict=True):
                ids, query_ids = np.frombuffer(ids, np.int64), np.frombuffer(query_ids, np.int64)
                x, y = np.frombuffer(x, np.int64).reshape(len(ids), -1), np.frombuffer(y, np.int64).reshape(len(query_ids), -1)
                kind = exact_type(x, y)
                if (number, kind) != held:
                    held, shard = (number, kind), Shard(ids, x.astype(kind))
                known = {r["query_id"]: r["score"] for r in known or []}
                found = [shard.top(query_id, q, k, known.get(query_id)) for query_id, q in zip(query_ids.tolist(), y.astype(kind), strict=True)]
                count = [len(f[0]) for f in found]
                columns = [np.repeat(query_ids, count), np.concatenate([f[0] for f in found]), [int(s) for f in found for s in f[1]], np.full(sum(count), block)]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, [pa.int64()] * 3 + [pa.int32()], strict=True)], names=found_names)

    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    count, last = shards.agg(F.count("*"), F.max("shard")).first()
    n_blocks = asked.count()
    pair = ["shard", "shard_ids", "shard_x", "block", "block_ids", "block_x", "known"]
    # the first search: each block meets one shard, the blocks shards in turn
    first = asked.join(shards, F.pmod("block", F.lit((last or 0) + 1)) == F.col("shard")).withColumn("known", F.lit(None).cast("array<struct<query_id: bigint, score: bigint>>"))
    known = first.select(*pair).repartition(max(1, n_blocks)).mapInArrow(lean(search), kept).withColumn("rank", F.row_number().over(best)).filter(F.col("rank") == k)
    asked = scratch(asked.join(known.groupBy("block").agg(F.collect_list(F.struct("query_id", "score")).alias("known")), "block", "left"))
    # every shard meets every block of the stated queries once; few shards are dealt out several times, each with a part of the blocks
    parts = max(1, min(n_blocks, -(-split_count(vectors.sparkSession) // max(1, count))))
    dealt = asked.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(last or 0)))).withColumn("part", F.pmod("block", F.lit(parts)).cast("int"))
    held = shards.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    found = held.hint("merge").join(dealt, ["shard", "part"]).select(*pair).mapInArrow(lean(search), kept)
    return found.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
