"""Accuracy and cost measures."""

from __future__ import annotations

import time
from collections.abc import Callable
from statistics import median

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import Rough, lists, low_slices, matrix, squared_distances
from .kmeans import first_by_hash
from .tally import packed, packed_schema, tally, unpacked


def recall(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(qid, recall): share of the k true neighbours that were returned; unanswered queries have 0."""
    asked = truth.where(F.col("rank") <= k)
    hits = asked.join(result.where(F.col("rank") <= k).select("qid", "vec_id"), ["qid", "vec_id"], "left_semi").groupBy("qid").agg(F.count(F.lit(1)).alias("hits"))
    return asked.select("qid").distinct().join(hits, "qid", "left").select("qid", (F.coalesce("hits", F.lit(0)) / k).alias("recall"))


def mre(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """One row (mre, mre_terms, short_results): mean of (distance - true distance) / true distance over ranks.

    Ranks whose true distance is 0 are left out; ranks that were not returned are counted as short and left out.
    """
    t = truth.where(F.col("rank") <= k).select("qid", "rank", F.col("dist").alias("true_dist"))
    both = t.join(result.select("qid", "rank", "dist"), ["qid", "rank"], "left")
    term = F.when(F.col("true_dist") > 0, (F.col("dist") - F.col("true_dist")) / F.col("true_dist"))
    return both.agg(F.avg(term).alias("mre"), F.count(term).alias("mre_terms"), F.sum(F.col("dist").isNull().cast("long")).alias("short_results"))


def ratio_ok(result: DataFrame, truth: DataFrame, c: float) -> DataFrame:
    """(qid, rank, ok): whether each rank is within factor c of the true distance."""
    return result.select("qid", "rank", "dist").join(truth.select("qid", "rank", F.col("dist").alias("true_dist")), ["qid", "rank"]).select("qid", "rank", (F.col("dist") <= c * F.col("true_dist") + 1e-12).alias("ok"))


def accuracy(result: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """One row (recall, mre, mre_terms, short_results)."""
    return recall(result, truth, k).agg(F.avg("recall").alias("recall")).join(mre(result, truth, k))


def candidate_spread(stats: DataFrame, budget: int) -> DataFrame:
    """One row: mean, least, median, 90 % and most candidates a query, against the budget."""
    q = F.percentile("candidate_num", [0.5, 0.9])
    return stats.agg(F.avg("candidate_num").alias("mean"), F.min("candidate_num").alias("least"), q[0].alias("median"), q[1].alias("p90"), F.max("candidate_num").alias("most"), F.lit(budget).alias("budget"))


def activation_work(cells: DataFrame) -> DataFrame:
    """One row: work per query and subspace, and the overshoot of the points retrieved."""
    return cells.groupBy("qid", "subspace").agg(*[F.sum(c).alias(c) for c in ("popped", "empty", "comparisons", "pushes", "pops")], F.max("max_open").alias("max_open"), F.sum("cnt").alias("retrieved")).agg(
        *[F.avg(c).alias(c) for c in ("popped", "empty", "comparisons", "pushes", "pops", "max_open", "retrieved")]
    )


def fidelity(approximate: DataFrame, true: DataFrame) -> DataFrame:
    """(qid, overlap): share of the true (qid, subspace, vec_id) collisions among the approximate ones."""
    hits = true.join(approximate, ["qid", "subspace", "vec_id"], "left_semi").groupBy("qid").agg(F.count(F.lit(1)).alias("hits"))
    return true.groupBy("qid").agg(F.count(F.lit(1)).alias("n")).join(hits, "qid", "left").select("qid", (F.coalesce("hits", F.lit(0)) / F.col("n")).alias("overlap"))


#: Bins of distance for each query, parts of a bin that holds a percentile's edge, and rows whose distances set the range.
COARSE, FINE, FIRST = 1024, 16, 1024


class Grid:
    """Places rows in the bins of each query's squared distances: by rough distances, and by true ones where rounding could decide."""

    def __init__(self, q: np.ndarray, low: np.ndarray, step: np.ndarray):
        self.q, self.low, self.step, self.rough = q, low, step, Rough(q, single=False)

    def exact(self, dist: np.ndarray, i: np.ndarray) -> np.ndarray:
        """Bins of true distances from the queries i: a distance at an edge lies below it."""
        edge = np.rint((dist * dist - self.low[i]) / self.step[i])
        return np.where(dist <= np.sqrt(np.maximum(self.low[i] + edge * self.step[i], 0)), edge - 1, edge)

    def place(self, x: np.ndarray) -> np.ndarray:
        d, slack = self.rough(x)
        at = (d - self.low) / self.step
        near = np.abs(at - np.rint(at)) * self.step <= 2 * slack
        row, i = np.nonzero(near & (at > -1) & (at < COARSE * FINE + 1))
        at = np.floor(at)
        if len(row):
            at[row, i] = self.exact(distances(x, self.q, row, i), i)
        return np.clip(at, 0, COARSE * FINE - 1).astype(np.int32)


def distances(x: np.ndarray, q: np.ndarray, row: np.ndarray, i: np.ndarray) -> np.ndarray:
    """True distances of pairs of rows and queries."""
    out = np.empty(len(row))
    for lo in range(0, len(row), 1 << 16):
        some = slice(lo, lo + (1 << 16))
        out[some] = np.sqrt(((x[row[some]] - q[i[some]]) ** 2).sum(axis=1))
    return out


def profile(base: DataFrame, scorers: list, buckets: int = 100) -> DataFrame:
    """(percentile, mean_score): mean score of the rows of ``base`` by percentile of exact distance, over the queries of the scorers."""
    return profiles(base, [scorers], buckets)[0]


def profiles(base: DataFrame, several: list[list], buckets: int = 100) -> list[DataFrame]:
    """A profile for each list of scorers of the same blocks of queries.

    Two scans count rows by bins of distance, then by parts of the bins over a percentile's edge. The third adds up scores by percentile; only the rows of parts over an edge are ranked.
    No pairs of queries and rows are kept.
    """
    spark, n = base.sparkSession, base.count()
    big, rest, small = n // buckets + 1, n % buckets, max(1, n // buckets)
    percentile = lambda r: np.where(r < rest * big, r // big, rest + (r - rest * big) // small) + 1
    sums, seen = np.zeros((len(several), 2, buckets + 1), np.int64), matrix(first_by_hash(base, FIRST, 29).toArrow().column("embedding"))
    for block in zip(*several, strict=True):
        scorer = block[0]
        nq, rough = len(scorer.qids), squared_distances(seen, scorer.q)
        low, high = rough.min(axis=0), rough.max(axis=0)
        grid = Grid(scorer.q, low, np.maximum((high - low) / (COARSE * FINE), np.maximum(1e-9 * high, 1e-300)))
        shared = spark.sparkContext.broadcast(grid)

        def coarse(batches, shared=shared, nq=nq):
            total, own = np.zeros((nq, COARSE), np.int64), np.arange(nq) * COARSE
            for part in (part for batch in batches for part in low_slices(batch, nq)):
                at = shared.value.place(matrix(part.column("embedding"))) // FINE + own
                np.add.at(total.ravel(), at.ravel(), 1)
            return total

        upto = np.cumsum(tally(base.select("embedding"), coarse, COARSE, nq), axis=1)
        before = np.concatenate([np.zeros((nq, 1), np.int64), upto[:, :-1]], axis=1)
        whole = percentile(before)
        edge = (upto > before) & (whole != percentile(upto - 1))
        slot = np.where(edge, np.cumsum(edge, axis=1) - 1, -1).astype(np.int16)
        slots = max(1, int(edge.sum(axis=1).max(initial=0)))
        shared = spark.sparkContext.broadcast((grid, slot))

        def fine(batches, shared=shared, nq=nq, slots=slots):
            grid, slot = shared.value
            total, own = np.zeros((nq, slots * FINE), np.int64), np.arange(nq) * COARSE
            for part in (part for batch in batches for part in low_slices(batch, nq)):
                f = grid.place(matrix(part.column("embedding")))
                to = slot.ravel()[f // FINE + own].astype(np.int32)
                row, i = np.nonzero(to >= 0)
                np.add.at(total.ravel(), i * (slots * FINE) + to[row, i] * FINE + f[row, i] % FINE, 1)
            return total

        counts = tally(base.select("embedding"), fine, slots * FINE, nq).reshape(nq, slots, FINE)
        start = np.zeros((nq, slots), np.int64)
        who, bin_ = np.nonzero(edge)
        start[who, slot[who, bin_]] = before[who, bin_]
        upto = np.cumsum(counts, axis=2) + start[..., None]
        before = upto - counts
        # 0: its rows are of several percentiles
        parts = np.where((counts > 0) & (percentile(before) != percentile(upto - 1)), 0, percentile(before)).astype(np.int16).reshape(nq, -1)
        shared = spark.sparkContext.broadcast((grid, slot, whole.astype(np.int16), parts, block))
        ahead = spark.sparkContext.broadcast(before.reshape(nq, -1))
        kinds = (np.int32, np.int32, np.int64, np.float64, np.int64)
        rows = base.select(*dict.fromkeys(["vec_id", "embedding", scorer.column])).mapInArrow(lambda batches, shared=shared, slots=slots: _by_percentile(batches, *shared.value, slots, buckets), packed_schema(4 + len(block)))

        def add(held):  # evaluated before the next block
            query, key, ids, dist, cnt, *scores = unpacked(held, *kinds, *[np.int64] * len(several))
            out, done = np.zeros((len(several), 2, buckets + 1), np.int64), cnt >= 0
            np.add.at(out[0, 0], key[done], cnt[done])
            for own, score in zip(out, scores):
                np.add.at(own[1], key[done], score[done])
            query, key, ids, dist, *scores = (c[~done] for c in (query, key, ids, dist, *scores))
            order = np.lexsort((ids, dist, key, query))
            query, key = query[order], key[order]
            new = np.flatnonzero(np.concatenate([[True], (np.diff(query) != 0) | (np.diff(key) != 0)])) if len(query) else np.zeros(0, int)
            p = percentile(np.arange(len(query)) - np.repeat(new, np.diff(np.append(new, len(query)))) + ahead.value[query, key])
            np.add.at(out[0, 0], p, 1)
            for own, score in zip(out, scores):
                own[0] = out[0, 0]
                np.add.at(own[1], p, score[order])
            return pa.table({"sums": lists(out.reshape(1, -1))})

        got = rows.groupBy("at").applyInArrow(add, "sums array<long>").toArrow()
        sums += np.array(got.column("sums").to_pylist(), np.int64).reshape(-1, *sums.shape).sum(axis=0)
    return [spark.createDataFrame([(p, float(total[p] / cnt[p])) for p in range(1, buckets + 1) if cnt[p]], "percentile long, mean_score double") for cnt, total in sums]


def _by_percentile(batches, grid: Grid, slot: np.ndarray, whole: np.ndarray, parts: np.ndarray, scorers: list, slots: int, buckets: int):
    """Packed rows (query, part, vec_id, distance, -1, scores) of parts over an edge, and (0, percentile, 0, 0, count, sums of scores) of all other rows."""
    nq, sums = len(slot), np.zeros((1 + len(scorers), buckets + 1), np.int64)
    own = np.arange(nq) * COARSE
    for part in (part for batch in batches for part in low_slices(batch, nq)):
        x, ids, scores = matrix(part.column("embedding")), part.column("vec_id").to_numpy(), [scorer.scores(part) for scorer in scorers]
        f = grid.place(x)
        at = f // FINE + own
        to, of = slot.ravel()[at], whole.ravel()[at]
        row, i = np.nonzero(to >= 0)
        key = to[row, i].astype(np.int32) * FINE + f[row, i] % FINE
        of[row, i] = parts[i, key]
        sums[0] += np.bincount(of.ravel(), minlength=buckets + 1)
        for total, score in zip(sums[1:], scores):
            total += np.bincount(of.ravel(), score.ravel(), buckets + 1).astype(np.int64)
        cut = of[row, i] == 0
        row, i, key = row[cut], i[cut], key[cut]
        if len(row):
            yield packed(i.astype(np.int32), key, ids[row].astype(np.int64), distances(x, grid.q, row, i), np.full(len(row), -1), *[score[row, i].astype(np.int64) for score in scores])
    sums[:, 0] = 0
    p = np.arange(buckets + 1)
    yield packed(np.zeros(len(p), np.int32), p.astype(np.int32), np.zeros(len(p), np.int64), np.zeros(len(p)), *sums)


def timed(run: Callable[[], DataFrame], repeats: int = 3) -> float:
    """Median seconds of a warm query to a sink that keeps nothing."""
    seconds = []
    for _ in range(repeats + 1):
        begun = time.time()
        run().write.format("noop").mode("overwrite").save()
        seconds.append(time.time() - begun)
    return median(seconds[1:])


def cumulative(index_s: float, query_s: float, queries: list[int]) -> list[float]:
    """Seconds until the i-th query is answered, the building included."""
    return [index_s + i * query_s for i in queries]


def crossover(a: tuple[float, float], b: tuple[float, float]) -> float:
    """After how many queries b (index_s, query_s) has caught up with a; infinite if never, 0 if it leads from the start."""
    if b[0] <= a[0]:
        return 0.0
    return float("inf") if b[1] >= a[1] else float(np.ceil((b[0] - a[0]) / (a[1] - b[1])))


def spark_cost(spark, run: Callable[[], object]) -> dict[str, int]:
    """What an action cost the executors: tasks, and bytes read, shuffled in and shuffled out."""

    def totals() -> dict[str, int]:
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
        all_ = [executors.apply(i) for i in range(executors.size())]
        return {"tasks": sum(e.totalTasks() for e in all_), "input_bytes": sum(e.totalInputBytes() for e in all_), "shuffle_read_bytes": sum(e.totalShuffleRead() for e in all_), "shuffle_write_bytes": sum(e.totalShuffleWrite() for e in all_)}

    before = totals()
    run()
    after = totals()
    return {k: after[k] - before[k] for k in after}
