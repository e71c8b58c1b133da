"""Which cells a query activates: the cheapest by the sum of its halves' centroid distances until enough points are in.

Three ways with one result. Cells come in order of (sum, position in list 1, position in list 2); a cell is in if the points of all
cells before it are fewer than wanted, so the last cell is kept whole.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import matrix
from .kmeans import half_parts

COUNTERS = ("popped", "empty", "comparisons", "pushes", "pops", "max_open")


@dataclass
class Work:
    """What an activation did, in steps that do not depend on the machine."""

    popped: int = 0
    empty: int = 0
    comparisons: int = 0
    pushes: int = 0
    pops: int = 0
    max_open: int = 0


@dataclass
class Activated:
    pos1: list[int] = field(default_factory=list)
    pos2: list[int] = field(default_factory=list)
    work: Work = field(default_factory=Work)


def centroid_lists(book: np.ndarray, point: np.ndarray, metric: str) -> tuple[np.ndarray, np.ndarray]:
    """Centroid numbers, nearest first (ties to the smaller), and their distances."""
    gap = book - point
    dist = (gap * gap).sum(axis=1)
    if metric == "l2":
        dist = np.sqrt(dist)
    order = np.argsort(dist, kind="stable")
    return order, dist[order]


def by_heap(d1: np.ndarray, d2: np.ndarray, counts: np.ndarray, want: float) -> Activated:
    """Rows are opened one after another; a heap holds the next cell of every open row. counts by position."""
    out, got = Activated(), 0
    frontier = [(d1[0] + d2[0], 0, 0)]
    out.work.pushes = out.work.max_open = 1
    while frontier and got < want:
        out.work.comparisons += 1  # the top is the smallest
        _, r, c = heapq.heappop(frontier)
        out.work.pops += 1
        out.pos1.append(r)
        out.pos2.append(c)
        size = int(counts[r, c])
        got += size
        out.work.popped += 1
        out.work.empty += not size
        if c == 0 and r + 1 < len(d1):
            heapq.heappush(frontier, (d1[r + 1] + d2[0], r + 1, 0))
            out.work.pushes += 1
        if c + 1 < len(d2):
            heapq.heappush(frontier, (d1[r] + d2[c + 1], r, c + 1))
            out.work.pushes += 1
        out.work.max_open = max(out.work.max_open, len(frontier))
    return out


def by_scan(d1: np.ndarray, d2: np.ndarray, counts: np.ndarray, want: float) -> Activated:
    """The same with the open rows' next sums in an array that is searched from end to end for every cell."""
    out, got, opened = Activated(), 0, 1
    column = np.zeros(len(d1), np.int64)
    cost = np.full(len(d1), np.inf)
    cost[0] = d1[0] + d2[0]
    while got < want:
        r = int(cost[:opened].argmin())
        if not np.isfinite(cost[r]):
            break
        out.work.comparisons += opened
        c = int(column[r])
        out.pos1.append(r)
        out.pos2.append(c)
        size = int(counts[r, c])
        got += size
        out.work.popped += 1
        out.work.empty += not size
        if c == 0 and opened < len(d1):
            cost[opened] = d1[opened] + d2[0]
            opened += 1
        column[r] += 1
        cost[r] = d1[r] + d2[c + 1] if c + 1 < len(d2) else np.inf
        out.work.max_open = max(out.work.max_open, opened)
    return out


def by_order(d1: np.ndarray, d2: np.ndarray, counts: np.ndarray, want: float) -> Activated:
    """All sums sorted and cumulated at once."""
    sums = (d1[:, None] + d2).ravel()
    order = np.argsort(sums, kind="stable")
    sizes = counts.ravel()[order]
    stop = int(np.searchsorted(np.cumsum(sizes) - sizes, want, "left"))
    r, c = np.divmod(order[:stop], len(d2))
    return Activated(r.tolist(), c.tolist(), Work(popped=stop, empty=int((sizes[:stop] == 0).sum()), comparisons=len(order)))


WAYS = {"heap": by_heap, "linear": by_scan, "windowed": by_order}


def ranked_lists(queries: DataFrame, space, books: list[np.ndarray], metric: str = "l2") -> DataFrame:
    """(qid, subspace, half, pos, cid, dist) for every query: a narrow map over the queries."""

    def rank(batches):
        for batch in batches:
            frames = []
            halves = half_parts(space, matrix(batch.column("embedding"))) if batch.num_rows else []
            for i, qid in enumerate(batch.column("qid").to_pylist()):
                for b, (book, points) in enumerate(zip(books, halves)):
                    cid, dist = centroid_lists(book, points[i], metric)
                    frames.append(pd.DataFrame({"qid": qid, "subspace": b // 2, "half": b % 2, "pos": np.arange(len(cid)), "cid": cid, "dist": dist}))
            if frames:
                yield pa.RecordBatch.from_pandas(pd.concat(frames), schema=pa.schema([("qid", pa.int64()), *((c, pa.int32()) for c in ("subspace", "half", "pos", "cid")), ("dist", pa.float64())]), preserve_index=False)

    return queries.select("qid", "embedding").mapInArrow(rank, "qid long, subspace int, half int, pos int, cid int, dist double")


def activate(queries: DataFrame, space, books: list[np.ndarray], counts: np.ndarray, alpha: float, way: str = "heap", metric: str = "l2") -> DataFrame:
    """(qid, subspace, c1, c2, pos1, pos2, dsum, cnt, cum_cnt, and counters) of every activated cell.

    Each query is worked on alone: its state is 2 * l distances and at most l open rows for each subspace. Counters are on the first cell's row.
    """
    shared = queries.sparkSession.sparkContext.broadcast((space, books, counts))
    names = ["qid", "subspace", "c1", "c2", "pos1", "pos2", "dsum", "cnt", "cum_cnt", *COUNTERS]
    kinds = [pa.int64(), *[pa.int32()] * 5, pa.float64(), *[pa.int64()] * (2 + len(COUNTERS))]
    schema = pa.schema(list(zip(names, kinds)))

    def run(batches):
        space, books, counts = shared.value
        for batch in batches:
            halves = half_parts(space, matrix(batch.column("embedding"))) if batch.num_rows else []
            for i, qid in enumerate(batch.column("qid").to_pylist()):
                for j in range(len(books) // 2):
                    cid1, d1 = centroid_lists(books[2 * j], halves[2 * j][i], metric)
                    cid2, d2 = centroid_lists(books[2 * j + 1], halves[2 * j + 1][i], metric)
                    own = counts[j][np.ix_(cid1, cid2)]
                    got = WAYS[way](d1, d2, own, alpha * counts[j].sum())
                    p1, p2 = np.array(got.pos1, np.int64), np.array(got.pos2, np.int64)
                    sizes = own[p1, p2]
                    first = [np.where(np.arange(len(p1)) == 0, getattr(got.work, c), 0) for c in COUNTERS]
                    columns = [np.full(len(p1), qid), np.full(len(p1), j), cid1[p1], cid2[p2], p1, p2, d1[p1] + d2[p2], sizes, np.cumsum(sizes), *first]
                    yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in zip(columns, kinds)], schema=schema)

    return queries.select(F.col("qid").cast("long").alias("qid"), "embedding").mapInArrow(run, "qid long, subspace int, c1 int, c2 int, pos1 int, pos2 int, dsum double, cnt long, cum_cnt long, " + ", ".join(f"{c} long" for c in COUNTERS))


def activated_bits(queries: DataFrame, space, books: list[np.ndarray], counts: np.ndarray, alpha: float, way: str = "heap", metric: str = "l2") -> DataFrame:
    """(qid, bits): the same cells as packed flags, subspace after subspace: ns * K bits a query."""
    shared = queries.sparkSession.sparkContext.broadcast((space, books, counts))

    def run(batches):
        space, books, counts = shared.value
        wanted = [alpha * c.sum() for c in counts]
        for batch in batches:
            halves, packed = half_parts(space, matrix(batch.column("embedding"))) if batch.num_rows else [], []
            for i in range(batch.num_rows):
                flags = np.zeros(counts.shape, bool)
                for j in range(len(counts)):
                    cid1, d1 = centroid_lists(books[2 * j], halves[2 * j][i], metric)
                    cid2, d2 = centroid_lists(books[2 * j + 1], halves[2 * j + 1][i], metric)
                    got = WAYS[way](d1, d2, counts[j][np.ix_(cid1, cid2)], wanted[j])
                    flags[j, cid1[got.pos1], cid2[got.pos2]] = True
                packed.append(np.packbits(flags).tobytes())
            yield pa.RecordBatch.from_arrays([batch.column("qid"), pa.array(packed, pa.binary())], names=["qid", "bits"])

    return queries.select(F.col("qid").cast("long").alias("qid"), "embedding").mapInArrow(run, "qid long, bits binary")


def activate_sql(ranked: DataFrame, counts: DataFrame, n: int, alpha: float) -> DataFrame:
    """The same cells as a join of the two ranked lists and a running sum of counts."""
    one = ranked.where("half = 0").select("qid", "subspace", F.col("pos").alias("pos1"), F.col("cid").alias("c1"), F.col("dist").alias("e1"))
    two = ranked.where("half = 1").select("qid", "subspace", F.col("pos").alias("pos2"), F.col("cid").alias("c2"), F.col("dist").alias("e2"))
    # counts has at most ns * K rows
    grid = one.join(two, ["qid", "subspace"]).join(F.broadcast(counts), ["subspace", "c1", "c2"], "left").withColumns({"dsum": F.col("e1") + F.col("e2"), "cnt": F.coalesce("cnt", F.lit(0))})
    running = Window.partitionBy("qid", "subspace").orderBy("dsum", "pos1", "pos2").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return grid.withColumn("cum_cnt", F.sum("cnt").over(running)).where(F.col("cum_cnt") - F.col("cnt") < alpha * n).select("qid", "subspace", "c1", "c2", "pos1", "pos2", "dsum", "cnt", "cum_cnt")
