"""Collision scores: in how many subspaces a point collides with a query.

A scorer gives, for a batch of points, a matrix points x queries of integer scores. Points never move:
what crosses the network is what the callers make of the scores.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import NEAR_CELLS, ROWS, Rough, lists, low_slices, matrix, places, slices
from .exact import query_blocks
from .kmeans import first_by_hash
from .tally import GROUP, packed, packed_schema, tally, unpacked
from .transform import Space

#: Parts that an interval is split into in a round, how many points the last interval may hold, and rows whose distances tell where to begin.
WAYS_A_ROUND, BAND, ROUNDS, FIRST = 64, 2_048, 7, 16_384


def part_distances(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Squared distances points x queries in one subspace, summed component by component: alike for equal points."""
    out = np.zeros((len(p), len(q)))
    for c in range(p.shape[1]):
        gap = p[:, c : c + 1] - q[:, c]
        out += gap * gap
    return out


def pair_distances(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """``part_distances`` of row i of p and row i of q."""
    out = np.zeros(len(p))
    for c in range(p.shape[1]):
        gap = p[:, c] - q[:, c]
        out += gap * gap
    return out


@dataclass
class CellScorer:
    """Scores from codes: bitmap[subspace, cell, q] tells the activated cells; a point's scores are the sum of ns rows."""

    qids: np.ndarray
    q: np.ndarray
    bitmap: np.ndarray
    column = "cells"

    def scores(self, batch: pa.RecordBatch) -> np.ndarray:
        cells = matrix(batch.column("cells")).astype(np.int64)
        out = np.zeros((len(cells), len(self.qids)), np.int8)
        for j in range(cells.shape[1]):
            out += self.bitmap[j][cells[:, j]]
        return out

    def of(self, some: np.ndarray) -> CellScorer:
        """The same for some of the queries (their places)."""
        return CellScorer(self.qids[some], self.q[some], self.bitmap[:, :, some])


@dataclass
class ExactScorer:
    """Scores from true distances: limit[q, subspace] and last_id[q, subspace] bound the alpha * n nearest."""

    qids: np.ndarray
    q: np.ndarray
    space: Space
    limit: np.ndarray
    last_id: np.ndarray
    column = "embedding"

    def scores(self, batch: pa.RecordBatch) -> np.ndarray:
        out = np.zeros((batch.num_rows, len(self.qids)), np.int8)
        for hit in self.collides(batch):
            out += hit.view(np.int8)
        return out

    def of(self, some: np.ndarray) -> ExactScorer:
        """The same for some of the queries (their places)."""
        return ExactScorer(self.qids[some], self.q[some], self.space, self.limit[some], self.last_id[some])

    def collides(self, batch: pa.RecordBatch) -> Iterator[np.ndarray]:
        """points x queries, subspace after subspace: by rough distances, and by true ones where rounding could decide."""
        ids = batch.column("vec_id").to_numpy()
        if not hasattr(self, "_rough"):
            self._q = self.space.parts(self.q)
            self._rough = [Rough(q) for q in self._q]
        for j, p in enumerate(self.space.parts(matrix(batch.column("embedding")))):
            limit, last = self.limit[:, j], self.last_id[:, j]
            hit = np.empty((len(p), len(self.q)), bool)
            for lo in range(0, len(p), ROWS):
                some = p[lo : lo + ROWS]
                for own, rough, slack in self._rough[j].tiles(some):
                    near = rough <= (limit[own] + 2 * slack).astype(rough.dtype)
                    sure = rough <= (limit[own] - 2 * slack).astype(rough.dtype)
                    at = places(near != sure)
                    row, i = np.divmod(at, rough.shape[1])
                    i += own.start
                    d = pair_distances(some[row], self._q[j][i])
                    sure.ravel()[at] = (d < limit[i]) | ((d == limit[i]) & (ids[lo + row] <= last[i]))
                    hit[lo : lo + ROWS, own] = sure
            yield hit

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if not k.startswith("_")}


def _extent(rows: DataFrame, space: Space) -> tuple[int, np.ndarray]:
    """How many rows there are, and the largest squared length in each subspace: one row a task."""

    def run(batches):
        n, most = 0, np.zeros(len(space.directions))
        for batch in batches:
            n += batch.num_rows
            most = np.maximum(most, [(p * p).sum(axis=1).max(initial=0) for p in space.parts(matrix(batch.column("embedding")))])
        yield pa.RecordBatch.from_arrays([pa.array([n]), lists(most[None])], names=["n", "most"])

    got = rows.mapInArrow(run, "n long, most array<double>").toArrow()
    return sum(got.column("n").to_pylist()), np.nanmax(matrix(got.column("most")), axis=0, initial=0)


def _first_interval(x: np.ndarray, q: np.ndarray, space: Space, take: int, n: int, top: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where some rows ``x`` let the bounds be expected: a guess, which the counts over all rows confirm or correct."""
    share, m = take / n, len(x)
    off = 0 if m == n else 5 * np.sqrt(m * share * (1 - share)) + 2
    first, last = int(np.floor(share * m - off)) - 1, int(np.ceil(share * m + off)) - 1
    low, high = np.full(top.shape, -1.0), top.copy()
    for j, (p, qpart) in enumerate(zip(space.parts(x), space.parts(q))):
        rough, step = Rough(p), max(1, 16 * NEAR_CELLS // max(1, m))
        for lo in range(0, len(q), step):
            # queries as rows
            d, slack = rough(qpart[lo : lo + step])
            d.partition([max(first, 0), min(last, m - 1)], axis=1)
            low[lo : lo + step, j] = d[:, first] - 2 * slack if first >= 0 else -1.0
            high[lo : lo + step, j] = d[:, last] + 2 * slack if last < m else top[lo : lo + step, j]
    return low, np.maximum(high, low)


def _first_intervals(base: DataFrame, q: np.ndarray, space: Space, take: int, n: int, top: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """``_first_interval`` for parts of the queries in tasks of their own, from the rows of the smallest hashes."""
    spark, ns = base.sparkSession, top.shape[1]
    shared = spark.sparkContext.broadcast((matrix(first_by_hash(base, FIRST, 23).toArrow().column("embedding")), q, space, top))
    step = max(1, -(-len(q) // (4 * spark.sparkContext.defaultParallelism)))

    def run(batches):
        x, q, space, top = shared.value
        for lo in (lo for batch in batches for lo in batch.column("id").to_pylist()):
            some = np.concatenate(_first_interval(x, q[lo : lo + step], space, take, n, top[lo : lo + step]), axis=1)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(lo, lo + len(some))), lists(some)], names=["i", "edges"])

    got = spark.range(0, len(q), step, -(-len(q) // step)).mapInArrow(run, "i long, edges array<double>").toArrow()
    edges = matrix(got.column("edges"))[np.argsort(got.column("i").to_numpy())]
    return edges[:, :ns], edges[:, ns:]


def _interval_counts(batches, space: Space, q: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """queries x (ns counts of the rows below, in the parts of, and above an interval), by rough distances."""
    ways, ns, nq = WAYS_A_ROUND, len(space.directions), len(q)
    rough, total, n = [Rough(p) for p in space.parts(q)], np.zeros((ns, nq, ways + 2), np.int32), 0
    scale, held = ways / (high - low), [[] for _ in range(ns)]

    def add(j, least):
        if sum(map(len, held[j])) > least:
            total[j, :, 1:-1] += np.bincount(np.concatenate(held[j]), minlength=nq * ways).reshape(nq, ways)
            held[j].clear()

    for part in (batch.slice(lo, ROWS) for batch in batches for lo in range(0, batch.num_rows, ROWS)):
        n += part.num_rows
        for j, p in enumerate(space.parts(matrix(part.column("embedding")))):
            for own, d, _ in rough[j].tiles(p):
                lo = low[own, j].astype(d.dtype)
                below = d <= lo
                total[j, own, 0] += np.add.reduce(below.view(np.uint8), axis=0, dtype=np.uint8)
                at = places((d <= high[own, j].astype(d.dtype)) != below)
                i = at % d.shape[1]
                held[j].append((i + own.start) * ways + np.clip(((d.ravel()[at] - lo[i]) * scale[own.start + i, j]).astype(np.int64), 0, ways - 1))
            add(j, max(1 << 20, nq * ways))
    for j in range(ns):
        add(j, 0)
    total[..., -1] = n - total[..., :-1].sum(axis=2)
    return total.transpose(1, 0, 2).reshape(nq, -1)


def _band(batches, space: Space, q: np.ndarray, low: np.ndarray, high: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Packed (query, subspace, vec_id, distance, 0) of the rows in an interval, by true distances, and (query, subspace, count, 0, 1) of those below it."""
    qparts, nq, ns = space.parts(q), len(q), len(space.directions)
    rough, below = [Rough(p) for p in qparts], np.zeros((ns, nq), np.int64)
    for part in (part for batch in batches for part in low_slices(batch, nq, 16 * NEAR_CELLS)):
        ids, held = part.column("vec_id").to_numpy(), []
        for j, p in enumerate(space.parts(matrix(part.column("embedding")))):
            for own, d, slack in rough[j].tiles(p):
                under = d < (low[own, j] - 2 * slack).astype(d.dtype)
                below[j, own] += np.add.reduce(under.view(np.uint8), axis=0, dtype=np.uint8)
                # what is not under but not above
                row, i = np.divmod(places((d <= (high[own, j] + 2 * slack).astype(d.dtype)) != under), d.shape[1])
                i += own.start
                held.append((i, np.full(len(i), j), ids[row], pair_distances(p[row], qparts[j][i])))
        i, j, ids, d = (np.concatenate(c) for c in zip(*held))
        if len(i):
            yield packed(i.astype(np.int32), j.astype(np.int16), ids.astype(np.int64), d, np.zeros(len(i), np.int8))
    j, i = (c.ravel() for c in np.indices(below.shape))
    yield packed(i.astype(np.int32), j.astype(np.int16), below.ravel(), np.zeros(len(i)), np.ones(len(i), np.int8))


def exact_scorer(base: DataFrame, qids: np.ndarray, q: np.ndarray, space: Space, take: int) -> ExactScorer:
    """Bounds of the ``take`` nearest points per query and subspace, exactly (ties by id), without sorting the points.

    Each round splits the interval that must hold the bound into equal parts and counts all points below it and in each part. A few rows say where the first interval may lie; the counts say whether it does, and
    it is widened if not. Distances of the rounds are rough, so intervals are kept wider by what rounding may add. Rounds end when no interval holds more than ``BAND`` points; only these are ranked, by true distances.
    """
    spark, ns = base.sparkSession, len(space.directions)
    rows = base.select("vec_id", "embedding")
    n, norms = _extent(rows, space)
    if take >= n or not len(q):
        return ExactScorer(qids, q, space, np.full((len(q), ns), np.inf), np.full((len(q), ns), np.iinfo(np.int64).max))
    parts = space.parts(q)
    # what rounding may add to a rough distance, and what no distance exceeds
    slack = np.array([4 * Rough(p).slack(most, p.shape[1]) for p, most in zip(parts, norms)])
    top = np.stack([2.001 * ((p * p).sum(axis=1) + most) for p, most in zip(parts, norms)], axis=1) + slack
    low, high = _first_intervals(base, q, space, take, n, top)
    open_ = np.arange(len(q))
    for _ in range(ROUNDS):
        lo, hi = low[open_] - slack, high[open_] + slack
        shared = spark.sparkContext.broadcast((space, q[open_], lo, hi))
        total = tally(rows, lambda batches, shared=shared: _interval_counts(batches, *shared.value), ns * (WAYS_A_ROUND + 2), len(open_)).reshape(len(open_), ns, -1)
        # below the interval, in one of its parts, or above it
        bin_ = np.argmax(np.cumsum(total, axis=2) >= take, axis=2)
        width, held = (hi - lo) / WAYS_A_ROUND, np.take_along_axis(total, bin_[..., None], 2)[..., 0]
        low[open_], high[open_] = np.where(bin_ == 0, -1.0, lo + (bin_ - 1) * width), np.where(bin_ == 0, lo, np.where(bin_ > WAYS_A_ROUND, top[open_], lo + bin_ * width))
        # only queries whose bounds may still lie anywhere among many points go on
        open_ = open_[((held > BAND) & (high[open_] - low[open_] > 4 * slack)).any(axis=1)]
        if not len(open_):
            break
    low, high = low - slack, high + slack
    shared = spark.sparkContext.broadcast((space, q, low, high))
    found = rows.mapInArrow(lambda batches: _band(batches, *shared.value), packed_schema(4))

    def bound(held):
        query, j, ids, d, kind = unpacked(held, np.int32, np.int16, np.int64, np.float64, np.int8)
        at = query.astype(np.int64) * ns + j
        below = np.zeros(GROUP * ns, np.int64)
        first = int(held.column("at")[0].as_py()) * ns
        np.add.at(below, at[kind == 1] - first, ids[kind == 1])
        at, ids, d = at[kind == 0], ids[kind == 0], d[kind == 0]
        order = np.lexsort((ids, d, at))
        at, ids, d = at[order], ids[order], d[order]
        begin = np.searchsorted(at, np.arange(first, first + GROUP * ns))
        end = np.searchsorted(at, np.arange(first, first + GROUP * ns), "right")
        place = begin + take - below - 1
        good = np.flatnonzero((end > begin) & (place >= begin) & (place < end))
        return pa.table({"at": pa.array(first + good), "d": pa.array(d[place[good]]), "vec_id": pa.array(ids[place[good]])})

    last = found.groupBy("at").applyInArrow(bound, "at long, d double, vec_id long").toArrow()
    limit, last_id = np.full(len(q) * ns, np.inf), np.full(len(q) * ns, np.iinfo(np.int64).max)
    limit[last.column("at").to_numpy()], last_id[last.column("at").to_numpy()] = last.column("d").to_numpy(), last.column("vec_id").to_numpy()
    return ExactScorer(qids, q, space, limit.reshape(len(q), ns), last_id.reshape(len(q), ns))


def counter_bytes(ns: int) -> int:
    """What a query takes in a round of ``exact_scorer``: its counts and edges."""
    return 2 * 4 * ns * WAYS_A_ROUND


def exact_scorers(base: DataFrame, queries: DataFrame, space: Space, take: int, blocks: list | None = None) -> list[ExactScorer]:
    """An exact scorer for each block of queries (or for the blocks given)."""
    return [exact_scorer(base, qids, q, space, take) for qids, q in blocks or query_blocks(queries, counter_bytes(len(space.directions)))]


def bit_scorer(qids: np.ndarray, q: np.ndarray, bits: DataFrame, ns: int, l: int) -> CellScorer:
    """A scorer from (qid, bits), the packed flags of a block's activated cells: ns * K bits a query reach the driver, ns * K bytes are broadcast."""
    got = bits.toArrow().sort_by("qid")
    flags = np.zeros((len(qids), ns * l * l), np.int8)
    at = np.searchsorted(qids, got.column("qid").to_numpy())
    for i, packed in zip(at, got.column("bits").to_pylist()):
        flags[i] = np.unpackbits(np.frombuffer(packed, np.uint8), count=ns * l * l)
    return CellScorer(qids, q, np.ascontiguousarray(flags.T).reshape(ns, l * l, len(qids)))


def over_blocks(part, scorers: list) -> DataFrame:
    """The union of ``part(scorer)`` over the scorers of all blocks of queries."""
    return reduce(DataFrame.unionByName, map(part, scorers))


def score_table(points: DataFrame, scorer, keep_zero: bool = False) -> DataFrame:
    """(qid, vec_id, score) of the points that collide at all (or of all)."""
    shared = points.sparkSession.sparkContext.broadcast(scorer)

    def run(batches):
        scorer = shared.value
        for part in (part for batch in batches for part in slices(batch, len(scorer.qids))):
            s = scorer.scores(part)
            row, i = np.nonzero(s >= (0 if keep_zero else 1))
            yield pa.RecordBatch.from_arrays([pa.array(scorer.qids[i]), part.column("vec_id").take(pa.array(row)), pa.array(s[row, i].astype(np.int32))], names=["qid", "vec_id", "score"])

    return points.select("vec_id", scorer.column).mapInArrow(run, "qid long, vec_id long, score int")


def pair_scores(pairs: DataFrame, scorer: ExactScorer) -> DataFrame:
    """(qid, vec_id, score) of the (qid, vec_id, embedding) whose query is the scorer's."""
    shared = pairs.sparkSession.sparkContext.broadcast(scorer)

    def run(batches):
        scorer = shared.value
        asked = scorer.space.parts(scorer.q)
        for batch in batches:
            qid, ids = batch.column("qid").to_numpy(), batch.column("vec_id").to_numpy()
            i = np.searchsorted(scorer.qids, qid)
            own = np.flatnonzero(scorer.qids[np.minimum(i, len(scorer.qids) - 1)] == qid)
            i, score = i[own], np.zeros(len(own), np.int32)
            for j, p in enumerate(scorer.space.parts(matrix(batch.column("embedding"))[own])):
                d = pair_distances(p, asked[j][i])
                score += (d < scorer.limit[i, j]) | ((d == scorer.limit[i, j]) & (ids[own] <= scorer.last_id[i, j]))
            yield pa.RecordBatch.from_arrays([pa.array(qid[own]), pa.array(ids[own]), pa.array(score)], names=["qid", "vec_id", "score"])

    return pairs.select("qid", "vec_id", "embedding").mapInArrow(run, "qid long, vec_id long, score int")


def collision_table(points: DataFrame, scorer: ExactScorer) -> DataFrame:
    """(qid, subspace, vec_id) of all exact collisions."""
    shared = points.sparkSession.sparkContext.broadcast(scorer)

    def run(batches):
        scorer = shared.value
        for part in (part for batch in batches for part in slices(batch, len(scorer.qids))):
            for j, hit in enumerate(scorer.collides(part)):
                row, i = np.nonzero(hit)
                yield pa.RecordBatch.from_arrays([pa.array(scorer.qids[i]), pa.array(np.full(len(i), j, np.int32)), part.column("vec_id").take(pa.array(row))], names=["qid", "subspace", "vec_id"])

    return points.select("vec_id", "embedding").mapInArrow(run, "qid long, subspace int, vec_id long")


def exact_collisions_sql(parts: DataFrame, qparts: DataFrame, take: int) -> DataFrame:
    """(qid, subspace, vec_id) by a join and a rank: the definition, for small tables. (vec_id, parts) and (qid, parts)."""
    from ..functions.vector import l2sq

    long = parts.select("vec_id", F.posexplode("parts").alias("subspace", "p"))
    asked = qparts.select("qid", F.posexplode("parts").alias("subspace", "q"))
    w = Window.partitionBy("qid", "subspace").orderBy("d", "vec_id")
    pairs = long.join(F.broadcast(asked), "subspace").select("qid", "subspace", "vec_id", l2sq(F.col("p"), F.col("q")).alias("d"))
    return pairs.withColumn("r", F.row_number().over(w)).where(F.col("r") <= take).select("qid", "subspace", "vec_id")


def score(collisions: DataFrame) -> DataFrame:
    """(qid, vec_id, score) from collisions; points without any are absent."""
    return collisions.groupBy("qid", "vec_id").agg(F.count(F.lit(1)).cast("int").alias("score"))


def from_postings(posted: DataFrame, cells: DataFrame) -> DataFrame:
    """(qid, vec_id, score) by joining postings with activated cells: about alpha * n * ns ids a query are shuffled."""
    return score(posted.join(cells.select("qid", "subspace", "c1", "c2"), ["subspace", "c1", "c2"]))


def weighted(collisions: DataFrame, weights: np.ndarray) -> DataFrame:
    """(qid, vec_id, score): the sum of the weights of the subspaces in which a point collides."""
    listed = F.array(*[F.lit(float(w)) for w in weights])
    return collisions.groupBy("qid", "vec_id").agg(F.sum(F.element_at(listed, F.col("subspace") + 1)).alias("score"))


def weighted_table(points: DataFrame, scorer: ExactScorer, weights: np.ndarray) -> DataFrame:
    """The same from a scan of the points: no collision leaves its task."""
    shared = points.sparkSession.sparkContext.broadcast((scorer, np.asarray(weights, float)))

    def run(batches):
        scorer, weights = shared.value
        for part in (part for batch in batches for part in low_slices(batch, len(scorer.qids))):
            total, any_ = np.zeros((part.num_rows, len(scorer.qids))), np.zeros((part.num_rows, len(scorer.qids)), bool)
            for w, hit in zip(weights, scorer.collides(part)):
                total += w * hit
                any_ |= hit
            row, i = np.nonzero(any_)
            yield pa.RecordBatch.from_arrays([pa.array(scorer.qids[i]), part.column("vec_id").take(pa.array(row)), pa.array(total[row, i])], names=["qid", "vec_id", "score"])

    return points.select("vec_id", "embedding").mapInArrow(run, "qid long, vec_id long, score double")


@dataclass
class LevelScorer:
    """Scores are places (from 1) among the sums that the weights can give, rounded so that sums of the same weights in another order are equal; 0 without a collision."""

    plain: ExactScorer
    weights: np.ndarray
    column = "embedding"

    def __post_init__(self):
        self.qids, self.q, ns = self.plain.qids, self.plain.q, len(self.weights)
        sums = np.round(((np.arange(1 << ns)[:, None] >> np.arange(ns)) & 1) @ self.weights, 9)
        self.place = np.searchsorted(np.unique(sums[1:]), sums).astype(np.int16) + 1
        self.place[0], self.levels = 0, len(np.unique(sums[1:]))

    def of(self, some: np.ndarray) -> LevelScorer:
        """The same for some of the queries (their places)."""
        return LevelScorer(self.plain.of(some), self.weights)

    def scores(self, batch: pa.RecordBatch) -> np.ndarray:
        code = np.zeros((batch.num_rows, len(self.qids)), np.int16)
        for j, hit in enumerate(self.plain.collides(batch)):
            code |= hit.astype(np.int16) << j
        return self.place[code]
