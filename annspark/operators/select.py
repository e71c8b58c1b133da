"""Choosing candidates by score: a fixed number, or a cutoff for each query from its score histogram."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import ROWS, places, slices
from .tally import packed, packed_schema, tally, unpacked


#: Up to so many scores are counted by comparing with each of them.
LEVELS = 20
#: Bins of ids in which the rows of a level are counted.
ID_BINS = 64


def _rows_where(mask: np.ndarray) -> np.ndarray:
    """How many rows of each query (column) a mask of at most ``ROWS`` rows holds."""
    return np.add.reduce(mask.view(np.uint8), axis=0, dtype=np.uint8)


def _count(scores: np.ndarray, total: np.ndarray) -> None:
    """Add queries x scores counts of a rows x queries matrix."""
    for some in (scores[lo : lo + ROWS] for lo in range(0, len(scores), ROWS)):
        left = np.full(scores.shape[1], len(some))
        for level in range(total.shape[1] - 1, 0, -1):
            own = _rows_where(some == scores.dtype.type(level))
            total[:, level] += own
            left -= own
        total[:, 0] += left


def histogram(points: DataFrame, scorer, ns: int) -> DataFrame:
    """(qid, score, cnt) for every score from 0 to ns: tasks send ns + 1 counts a query."""
    shared = points.sparkSession.sparkContext.broadcast(scorer)

    def count(batches):
        scorer = shared.value
        total = np.zeros((len(scorer.qids), ns + 1), np.int64)
        for part in (part for batch in batches for part in slices(batch, len(scorer.qids))):
            scores = scorer.scores(part)
            if ns < LEVELS:
                _count(scores, total)
            else:
                at = scores + np.arange(len(total)) * (ns + 1)
                total += np.bincount(at.ravel(), minlength=total.size).reshape(total.shape)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(scorer.qids, ns + 1)), pa.array(np.tile(np.arange(ns + 1, dtype=np.int32), len(total))), pa.array(total.ravel())], names=["qid", "score", "cnt"])

    return points.select("vec_id", scorer.column).mapInArrow(count, "qid long, score int, cnt long").groupBy("qid", "score").agg(F.sum("cnt").alias("cnt"))


def counts_of(hist: DataFrame, qids: np.ndarray, ns: int) -> np.ndarray:
    """A histogram as queries x (ns + 1) counts: ns + 1 rows for each query of the block reach the driver."""
    got = hist.toArrow()
    counts = np.zeros((len(qids), ns + 1), np.int64)
    counts[np.searchsorted(qids, got.column("qid").to_numpy()), got.column("score").to_numpy()] = got.column("cnt").to_numpy()
    return counts


def histogram_of(scores: DataFrame, n: int, ns: int, qids: DataFrame) -> DataFrame:
    """The same from a table of positive scores; what is not there scored 0."""
    counted = scores.groupBy("qid", "score").agg(F.count(F.lit(1)).alias("cnt"))
    bins = qids.select("qid", F.explode(F.sequence(F.lit(0), F.lit(ns))).alias("score"))
    full = bins.join(counted, ["qid", "score"], "left").withColumn("cnt", F.coalesce("cnt", F.lit(0)))
    some = F.sum(F.when(F.col("score") > 0, F.col("cnt")).otherwise(0)).over(Window.partitionBy("qid"))
    return full.withColumn("cnt", F.when(F.col("score") == 0, n - some).otherwise(F.col("cnt")))


def cutoffs(hist: DataFrame, beta: float, n: int, rule: str = "lookahead", at_least: int = 0) -> DataFrame:
    """(qid, cutoff, candidate_num). Levels are taken from the top.

    ``accumulate``: until the points taken exceed beta * n. ``lookahead``: until one more level of the size
    of the last would make them exceed it. ``at_least`` lowers the cutoff until so many points are in.
    """
    down = Window.partitionBy("qid").orderBy(F.desc("score")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    held = hist.withColumn("upto", F.sum("cnt").over(down))
    limit = F.lit(beta * n)
    stop = (F.col("upto") + F.col("cnt") > limit) if rule == "lookahead" else (F.col("upto") > limit)
    stops = held.where((stop & (F.col("upto") >= at_least)) | (F.col("score") == 0))
    return stops.groupBy("qid").agg(F.max("score").alias("cutoff"), F.max_by("upto", "score").alias("candidate_num"))


#: As a last id: all points of the level are in.
EVERY = np.iinfo(np.int64).max


@dataclass
class Choice:
    """For each query (in the scorer's order): all points above ``level``, and of those at it the ids up to ``last_id``."""

    level: np.ndarray
    last_id: np.ndarray
    number: np.ndarray

    def mask(self, scores: np.ndarray, ids: np.ndarray) -> np.ndarray:
        level = self.level.astype(scores.dtype)
        if (self.last_id == EVERY).all():
            return scores >= level
        return (scores > level) | ((scores == level) & (ids[:, None] <= self.last_id))

    def pairs(self, scores: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, query) of the chosen: ids are looked at only where a score is at the level."""
        row, i = np.divmod(places(scores >= self.level.astype(scores.dtype)), scores.shape[1])
        if (self.last_id == EVERY).all():
            return row, i
        own = (ids[row] <= self.last_id[i]) | (scores[row, i] > self.level[i])
        return row[own], i[own]


def by_cutoff(counts: np.ndarray, beta: float, n: int, rule: str, at_least: int = 0) -> Choice:
    """``cutoffs`` of a block's counts (``counts_of``)."""
    upto = np.cumsum(counts[:, ::-1], axis=1)[:, ::-1]
    stop = ((upto + counts if rule == "lookahead" else upto) > beta * n) & (upto >= at_least)
    stop[:, 0] = True
    level = stop.shape[1] - 1 - np.argmax(stop[:, ::-1], axis=1)
    return Choice(level, np.full(len(level), EVERY), upto[np.arange(len(level)), level])


def by_number(counts: np.ndarray, points: DataFrame, scorer, budget: int | np.ndarray) -> Choice:
    """The ``budget`` (one, or one a query) best by (score, smaller id): the level from the counts, then the ids that complete it."""
    ns = counts.shape[1] - 1
    upto = np.cumsum(counts[:, ::-1], axis=1)[:, ::-1]
    full = upto >= np.broadcast_to(budget, len(counts))[:, None]
    level = np.where(full.any(axis=1), ns - np.argmax(full[:, ::-1], axis=1), 0)
    above = upto[np.arange(len(level)), level] - counts[np.arange(len(level)), level]
    need = np.maximum(0, budget - above)
    return Choice(level, _ids_at_level(points, scorer, level, need), np.minimum(budget, upto[:, 0]))


def _ids_at_level(points: DataFrame, scorer, level: np.ndarray, need: np.ndarray) -> np.ndarray:
    """For each query the ``need``-th smallest id among the rows whose score is ``level`` (-1 if none is needed).

    Counts by bins of ids tell the bin that holds it; only rows of that bin are scored again, and only their ids are sent.
    """
    rows, spark, ids = points.select("vec_id", scorer.column), points.sparkSession, np.full(len(level), -1)
    asked = np.flatnonzero(need > 0)
    if not len(asked):
        return ids
    # last ids of the bins but the last
    edges = np.unique(np.array(points.agg(F.percentile_approx("vec_id", [(b + 1) / ID_BINS for b in range(ID_BINS - 1)], 10_000)).first()[0], np.int64))
    scorer, level, need, bins = scorer.of(asked), level[asked], need[asked], len(edges) + 1
    shared = spark.sparkContext.broadcast((scorer, level, edges))

    def by_bin(batches):
        scorer, level, edges = shared.value
        total = np.zeros((len(level), bins), np.int32)
        for part in (part for batch in batches for part in slices(batch, len(level))):
            at_level = scorer.scores(part)
            at_level = at_level == level.astype(at_level.dtype)
            bin_ = np.searchsorted(edges, part.column("vec_id").to_numpy())
            for b in np.unique(bin_):
                own = at_level[bin_ == b] if bin_[0] != b or (bin_ != b).any() else at_level
                for lo in range(0, len(own), ROWS):
                    total[:, b] += _rows_where(own[lo : lo + ROWS])
        return total

    upto = np.cumsum(tally(rows, by_bin, bins, len(level)), axis=1)
    own = np.argmax(upto >= need[:, None], axis=1)
    left = need - np.where(own > 0, upto[np.arange(len(own)), own - 1], 0)
    found = np.flatnonzero(upto[:, -1] >= need)  # else all are in, and the last id is the largest
    own[upto[:, -1] < need] = bins
    of_bin = [np.flatnonzero(own == b) for b in range(bins)]
    held = spark.sparkContext.broadcast(([scorer.of(some) if len(some) else None for some in of_bin], level, edges, of_bin))

    def within(batches):
        scorers, level, edges, of_bin = held.value
        for batch in batches:
            bin_ = np.searchsorted(edges, batch.column("vec_id").to_numpy())
            for b in (b for b in np.unique(bin_) if scorers[b]):
                for part in slices(batch.take(pa.array(np.flatnonzero(bin_ == b))), len(of_bin[b])):
                    got = scorers[b].scores(part)
                    row, i = np.nonzero(got == level[of_bin[b]].astype(got.dtype))
                    yield packed(of_bin[b][i], part.column("vec_id").to_numpy()[row].astype(np.int64))

    def pick(part):
        i, vec_id = unpacked(part, np.int64, np.int64)
        order = np.lexsort((vec_id, i))
        i, vec_id = i[order], vec_id[order]
        who, first = np.unique(i, return_index=True)
        return pa.table({"i": pa.array(who), "vec_id": pa.array(vec_id[first + left[who] - 1])})

    if len(found):
        got = rows.mapInArrow(within, packed_schema(1)).groupBy("at").applyInArrow(pick, "i long, vec_id long").toArrow()
        ids[asked[got.column("i").to_numpy()]] = got.column("vec_id").to_numpy()
    ids[asked[own == bins]] = EVERY
    return ids


def fixed(scores: DataFrame, budget: int) -> DataFrame:
    """(qid, vec_id, score) of the ``budget`` best by (score, smaller id), from a table of scores."""
    w = Window.partitionBy("qid").orderBy(F.desc("score"), "vec_id")
    return scores.withColumn("r", F.row_number().over(w)).where(F.col("r") <= budget).drop("r")


def candidates(points: DataFrame, scorer, choice: Choice) -> DataFrame:
    """(qid, vec_id, score) of the chosen points."""
    shared = points.sparkSession.sparkContext.broadcast((scorer, choice))

    def run(batches):
        scorer, choice = shared.value
        for part in (part for batch in batches for part in slices(batch, len(scorer.qids))):
            if part.num_rows:
                s, ids = scorer.scores(part), part.column("vec_id").to_numpy()
                row, i = np.nonzero(choice.mask(s, ids))
                yield pa.RecordBatch.from_arrays([pa.array(scorer.qids[i]), pa.array(ids[row]), pa.array(s[row, i].astype(np.int32))], names=["qid", "vec_id", "score"])

    return points.select("vec_id", scorer.column).mapInArrow(run, "qid long, vec_id long, score int")
