"""Exact nearest neighbours: the ground truth, radius search, and the contract of approximate answers."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import Nearest, by_query, matrix, slices, squared_distances
from ..functions.vector import l2

#: Bytes that one block of queries may take, in a broadcast and in a task; more queries are answered in several passes.
QUERY_BYTES = 64 << 20
NEIGHBOURS = "qid long, vec_id long, dist double"


def query_blocks(queries: DataFrame, per_query: int = 0, vector: str = "embedding") -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(qids, matrix) in id order, block by block. A query counts with its vector or with the ``per_query`` bytes that its flags or counters take, whichever is more."""
    counted = queries.agg(F.count(F.lit(1)).alias("n"), F.max(F.size(vector)).alias("d")).first()
    if not counted.n:
        return
    blocks = min(counted.n, max(1, -(-counted.n * max(8 * counted.d, per_query) // QUERY_BYTES)))
    for b in range(blocks):
        some = queries.select("qid", vector) if blocks == 1 else queries.where(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == b).select("qid", vector)
        got = some.toArrow().sort_by("qid")
        if got.num_rows:
            yield got.column("qid").to_numpy().astype(np.int64), matrix(got.column(vector))


def beside(queries: DataFrame) -> DataFrame:
    """The queries marked for broadcast if they fit one; else as they are, for a shuffled join."""
    counted = queries.agg(F.count(F.lit(1)).alias("n"), F.max(F.size(queries.columns[-1])).alias("d")).first()
    return F.broadcast(queries) if counted.n * (counted.d or 0) * 8 <= QUERY_BYTES else queries


def ranked(found: DataFrame, k: int, order: str = "dist") -> DataFrame:
    """The k best of every query over partial answers; the window's group limit prunes before the shuffle."""
    w = Window.partitionBy("qid").orderBy(order, "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "rank", "vec_id", "dist")


def knn(base: DataFrame, queries: DataFrame, k: int, impl: str = "arrow") -> DataFrame:
    """(qid, rank, vec_id, dist): the k nearest of every query, ties to the smaller id.

    ``arrow``: one scan of the base for a block of queries; every task keeps k rows a query. ``sql``: the same as a
    declared join of the base with the queries, for query sets that fit a broadcast.
    """
    if impl == "sql":
        pairs = base.crossJoin(beside(queries.select("qid", F.col("embedding").alias("q")))).select("qid", "vec_id", l2(F.col("embedding"), F.col("q")).alias("dist"))
        return ranked(pairs, k)
    out = base.sparkSession.createDataFrame([], NEIGHBOURS)
    for qids, q in query_blocks(queries):
        shared = base.sparkSession.sparkContext.broadcast((qids, q))

        def nearest(batches, shared=shared):
            qids, q = shared.value
            best = Nearest(q, k)
            for batch in batches:
                best.offer_all(batch.column("vec_id").to_numpy().astype(np.int64), matrix(batch.column("embedding")))
            yield best.batch(qids)

        out = out.unionByName(base.select("vec_id", "embedding").mapInArrow(nearest, NEIGHBOURS))
    return ranked(out, k)


def within(base: DataFrame, queries: DataFrame, radius: float) -> DataFrame:
    """(qid, vec_id, dist) of all pairs at most ``radius`` apart: a range join of the base with blocks of queries."""
    out = base.sparkSession.createDataFrame([], NEIGHBOURS)
    for qids, q in query_blocks(queries):
        shared = base.sparkSession.sparkContext.broadcast((qids, q))

        def near(batches, shared=shared):
            qids, q = shared.value
            for part in (part for batch in batches for part in slices(batch, len(q))):
                x, ids = matrix(part.column("embedding")), part.column("vec_id").to_numpy()
                rough = squared_distances(x, q)
                held = [(i, some, np.sqrt(((x[some] - q[i]) ** 2).sum(axis=1))) for i, some in by_query(rough <= radius**2 + 1e-9 * (1 + rough.max(initial=0)))]
                held = [(np.full((d <= radius).sum(), qids[i]), ids[some[d <= radius]], d[d <= radius]) for i, some, d in held]
                if held:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held)], names=["qid", "vec_id", "dist"])

        out = out.unionByName(base.select("vec_id", "embedding").mapInArrow(nearest, NEIGHBOURS))
    return ranked(out, k)


def within(base: DataFrame, queries: DataFrame, radius: float) -> DataFrame:
    """(qid, vec_id, dist) of all pairs at most ``radius`` apart: a range join of the base with blocks of queries."""
    out = base.sparkSession.createDataFrame([], NEIGHBOURS)
    for qids, q in query_blocks(queries):
        shared = base.sparkSession.sparkContext.broadcast((qids, q))

        def near(batches, shared=shared):
            qids, q = shared.value
            for batch in batches:
                x, ids = matrix(batch.column("embedding")), batch.column("vec_id").to_numpy()
                for i in range(len(q)):
                    gap = x - q[i] if len(x) else np.zeros((0, q.shape[1]))
                    dist = np.sqrt((gap * gap).sum(axis=1))
                    some = np.flatnonzero(dist <= radius)
                    if len(some):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), qids[i])), pa.array(ids[some]), pa.array(dist[some])], names=["qid", "vec_id", "dist"])

        out = out.unionByName(base.select("vec_id", "embedding").mapInArrow(near, NEIGHBOURS))
    return out
