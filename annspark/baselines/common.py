"""What the baselines share: bounded training samples, clustering of a sample, and the re-ranking scan."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import NEAR_CELLS, Nearest, matrix, places
from ..operators.exact import NEIGHBOURS, query_blocks, ranked
from ..operators.kmeans import assign, first_by_hash

#: Rows that codebooks, rotations and breakpoints are learned from.
SAMPLE = 20_000


def sample_of(base: DataFrame, size: int = SAMPLE, seed: int = 23) -> np.ndarray:
    """At most ``size`` vectors, those of the smallest seeded hashes of their ids."""
    return matrix(first_by_hash(base, size, seed).toArrow().column("embedding"))


def lloyd(x: np.ndarray, l: int, t: int, rng: np.random.Generator) -> np.ndarray:
    centres = x[rng.permutation(len(x))[np.arange(l) % len(x)]].copy()
    for _ in range(t):
        label = assign(x, centres)
        n = np.bincount(label, minlength=l)
        sums = np.stack([np.bincount(label, x[:, c], l) for c in range(x.shape[1])], axis=1)
        centres = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], centres)
    return centres


#: Rows x queries flags of the rows that a method looks at, in a task.
FLAGS = 1 << 26
_MOST = np.finfo(np.float64).max

#: (queries, queries x rows values, how far rounding may have moved them, the same for pairs (row, query) one by one)
Tile = tuple[slice, np.ndarray, float, Callable[[np.ndarray, np.ndarray], np.ndarray]]


def tiles_of(queries: int, rows: int) -> Iterator[slice]:
    """A few queries after another, so that their values for the rows stay in the core's cache."""
    step = max(1, NEAR_CELLS // max(1, rows))
    for lo in range(0, queries, step):
        yield slice(lo, min(queries, lo + step))


class Tiled:
    """What a method holds for a block of queries."""

    def tiles(self, batch: pa.RecordBatch) -> Iterator[Tile]:
        """Values of all rows for a few queries after another, infinite for rows that the method does not look at."""
        raise NotImplementedError

    def flags(self, batch: pa.RecordBatch) -> Iterator[tuple[slice, np.ndarray]]:
        """(queries, rows x queries): which rows the method looks at."""
        for some, value, _, _ in self.tiles(batch):
            yield some, np.isfinite(value).T


class EachQuery(Tiled):
    """Tiles of a function that gives the values of a batch for one query, infinite for rows that the method does not look at."""

    def __init__(self, rough: Callable, q: np.ndarray):
        self.rough, self.q = rough, q

    def tiles(self, batch: pa.RecordBatch) -> Iterator[Tile]:
        for i in range(len(self.q)):
            value = self.rough(batch, self.q, i)
            yield slice(i, i + 1), value[None], 0.0, lambda row, who, value=value: value[row]


class Candidates:
    """For each query the ``keep`` rows of the least (value, id) seen so far, with their true distances. Pairs are gathered, and cut when there are many."""

    def __init__(self, q: np.ndarray, keep: int):
        self.q, self.keep = q, keep
        self.kept = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0), np.zeros(0)  # query, id, distance, value
        self.new, self.held = [], 0
        self.bound = np.full(len(q), _MOST)  # value beyond which a row has no chance

    def offer(self, tile: Tile, ids: np.ndarray, x: np.ndarray) -> None:
        some, value, slack, values = tile
        bound = self.bound[some]
        if value.shape[1] > self.keep and (fresh := bound == _MOST).any():
            # the keep-th of these rows is a bound
            bound[fresh] = np.minimum(_MOST, np.partition(value[fresh], self.keep - 1, axis=1)[:, self.keep - 1].astype(np.float64) + slack)
        who, row = np.divmod(places(value <= np.minimum(np.finfo(value.dtype).max, bound + slack).astype(value.dtype)[:, None]), max(1, value.shape[1]))
        step = max(1, Nearest.NUMBERS // max(1, x.shape[1]))
        for lo in range(0, len(who), step):
            i, r = who[lo : lo + step] + some.start, row[lo : lo + step]
            own = values(r, i)
            near = np.flatnonzero(own <= self.bound[i])
            i, r = i[near], r[near]
            gap = x[r]
            gap -= self.q[i]
            self.new.append((i, ids[r], np.sqrt(np.multiply(gap, gap, out=gap).sum(axis=1)), own[near]))
            self.held += len(near)
            if self.held > max(Nearest.GATHERED, len(self.kept[0])):
                self.cut()

    def cut(self) -> None:
        """Keep the ``keep`` first of every query."""
        who, ids, dist, value = (np.concatenate(c) for c in zip(self.kept, *self.new))
        order = np.lexsort((ids, value, who))
        who = who[order]
        place = np.arange(len(who)) - np.searchsorted(who, who)
        order, who, place = order[place < self.keep], who[place < self.keep], place[place < self.keep]
        self.kept, self.new, self.held = (who, ids[order], dist[order], value[order]), [], 0
        last = np.flatnonzero(place == self.keep - 1)
        self.bound[who[last]] = self.kept[3][last]


def rerank_scan(points: DataFrame, columns: list[str], queries: DataFrame, k: int, keep: int, rough: Callable | None, look: Callable | None = None, per_query: int = 0) -> DataFrame:
    """(qid, rank, vec_id, dist): of all points the ``keep`` that a method's values find best (ties to the smaller id) are measured exactly.

    Values come from ``rough(batch, q, i)`` query by query, or from the tiles of ``look(q)``, many queries at a time; ``per_query`` bytes a query are what the latter holds. They are infinite for rows that the
    method does not look at. Every task keeps and measures ``keep`` rows a query; those that are among the ``keep`` best of all
    tasks count, so the answer does not depend on how the points lie in partitions and batches. If ``keep`` is no limit, every row that the method looks at is measured and tasks send k rows a query.
    """
    limited = keep < points.count()
    out = points.sparkSession.createDataFrame([], f"{NEIGHBOURS}, value double" if limited else NEIGHBOURS)
    for qids, q in query_blocks(queries, max(per_query, 32 * min(keep, SAMPLE) if limited else 0)):
        if not limited:
            out = out.unionByName(measure_all(points, columns, qids, q, k, look and look(q), rough))
            continue
        shared = points.sparkSession.sparkContext.broadcast((qids, q, look and look(q)))

        def run(batches, shared=shared):
            qids, q, held = shared.value
            held, best = held or EachQuery(rough, q), Candidates(q, keep)
            for batch in batches:
                if batch.num_rows:
                    ids, x = batch.column("vec_id").to_numpy(), matrix(batch.column("embedding"))
                    for tile in held.tiles(batch):
                        best.offer(tile, ids, x)
            best.cut()
            who, ids, dist, value = best.kept
            yield pa.RecordBatch.from_arrays([pa.array(qids[who]), pa.array(ids), pa.array(dist), pa.array(value)], names=["qid", "vec_id", "dist", "value"])

        out = out.unionByName(points.select("vec_id", "embedding", *columns).mapInArrow(run, out.schema))
    if not limited:
        return ranked(out, k)
    first = Window.partitionBy("qid").orderBy("value", "vec_id")
    return ranked(out.withColumn("r", F.row_number().over(first)).where(F.col("r") <= keep), k)


def measure_all(points: DataFrame, columns: list[str], qids: np.ndarray, q: np.ndarray, k: int, held: Tiled | None, rough: Callable | None = None) -> DataFrame:
    """(qid, vec_id, dist): for a block of queries each task's k nearest of all rows that the method looks at."""
    shared = points.sparkSession.sparkContext.broadcast((qids, q, held))

    def run(batches):
        qids, q, held = shared.value
        held, best, step = held or EachQuery(rough, q), Nearest(q, k), max(1, FLAGS // max(1, len(q)))
        for batch in (batch.slice(lo, step) for batch in batches for lo in range(0, batch.num_rows, step)):
            ids, x = batch.column("vec_id").to_numpy(), matrix(batch.column("embedding"))
            mask = np.zeros((len(ids), len(q)), bool)
            for some, own in held.flags(batch):
                mask[:, some] = own
            best.offer_mask(mask, ids, x)
        yield best.batch(qids)

    return points.select("vec_id", "embedding", *columns).mapInArrow(run, NEIGHBOURS)
