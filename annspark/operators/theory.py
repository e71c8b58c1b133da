"""Checks of the theory on data: discriminability, error bounds, preservation of distance and order."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import Rough, low_slices, matrix, slices
from ..functions.vector import l2sq
from ..sources.work import materialise
from .exact import query_blocks
from .scoring import pair_distances, pair_scores, part_distances
from .select import counts_of, histogram
from .transform import Space, apply


def gap(scores: DataFrame, truth: DataFrame, n: int, ns: int) -> DataFrame:
    """(qid, p_star, p, gap): mean collision share of the true neighbours, of all others, and the difference. Scores may lack zeros."""
    near = truth.join(scores, ["qid", "vec_id"], "left").groupBy("qid").agg(F.count(F.lit(1)).alias("k"), F.sum(F.coalesce("score", F.lit(0))).alias("s_star"))
    every = scores.groupBy("qid").agg(F.sum("score").alias("s"))
    both = near.join(every, "qid", "left").withColumn("s", F.coalesce("s", F.lit(0)))
    rates = both.select("qid", (F.col("s_star") / (F.col("k") * ns)).alias("p_star"), ((F.col("s") - F.col("s_star")) / ((n - F.col("k")) * ns)).alias("p"))
    return rates.withColumn("gap", F.col("p_star") - F.col("p"))


def error_bound(gaps: DataFrame, ns: int) -> DataFrame:
    """(qid, bound): exp(-ns gap^2 / (8 p (1 - p)))."""
    return gaps.select("qid", F.exp(-ns * F.col("gap") * F.col("gap") / (8 * F.col("p") * (1 - F.col("p")))).alias("bound"))


def separation(scores: DataFrame, truth: DataFrame, n: int, ns: int) -> DataFrame:
    """(qid, threshold, type1, type2) at the threshold of the smallest sum of errors.

    type1: share of the others that score at least it; type2: share of the neighbours that score below it.
    """
    flagged = scores.join(truth.select("qid", "vec_id", F.lit(1).alias("near")), ["qid", "vec_id"], "full").select("qid", F.coalesce("score", F.lit(0)).alias("score"), F.coalesce("near", F.lit(0)).alias("near"))
    counts = flagged.groupBy("qid", "score").agg(F.sum("near").alias("near"), F.sum(1 - F.col("near")).alias("other"))
    steps = truth.groupBy("qid").agg(F.count(F.lit(1)).alias("k")).withColumn("threshold", F.explode(F.sequence(F.lit(0), F.lit(ns + 1))))
    joined = steps.join(counts, "qid", "left").groupBy("qid", "threshold", "k").agg(
        F.sum(F.when(F.col("score") >= F.col("threshold"), F.col("other")).otherwise(0)).alias("over"), F.sum(F.when(F.col("score") < F.col("threshold"), F.col("near")).otherwise(0)).alias("under")
    )
    # points that never collided count as others at threshold 0
    errors = joined.select("qid", "threshold", F.when(F.col("threshold") == 0, 1.0).otherwise(F.col("over") / (n - F.col("k"))).alias("type1"), (F.col("under") / F.col("k")).alias("type2"))
    best = F.min_by(F.struct("threshold", "type1", "type2"), F.struct((F.col("type1") + F.col("type2")).alias("e"), "threshold"))
    return errors.groupBy("qid").agg(best.alias("b")).select("qid", "b.*")


def distance_bounds(vectors: DataFrame, pairs: DataFrame, space: Space) -> DataFrame:
    """(i, j, full, kept, eps): squared distances before and after projection, and the share lost. pairs (i, j) of ids."""
    parts = apply(vectors, space).select("vec_id", F.flatten("parts").alias("p"))
    full = vectors.select("vec_id", "embedding").join(parts, "vec_id")
    a, b = full.select(F.col("vec_id").alias("i"), F.col("embedding").alias("xi"), F.col("p").alias("pi")), full.select(F.col("vec_id").alias("j"), F.col("embedding").alias("xj"), F.col("p").alias("pj"))
    both = pairs.join(a, "i").join(b, "j").select("i", "j", l2sq(F.col("xi"), F.col("xj")).alias("full"), l2sq(F.col("pi"), F.col("pj")).alias("kept"))
    return both.withColumn("eps", F.when(F.col("full") > 0, 1 - F.col("kept") / F.col("full")).otherwise(0.0))


def order_violations(bounds: DataFrame) -> DataFrame:
    """(i, j, z) whose order by original distance is kept by enough margin, (1 - eps) of it, and yet changes after projection: there should be none."""
    eps = F.broadcast(bounds.agg(F.max("eps").alias("worst")))
    a, b = bounds.alias("a"), bounds.alias("b")
    triples = a.join(b, F.col("a.i") == F.col("b.i")).join(eps)
    kept = triples.where((F.col("a.full") < (1 - F.col("worst")) * F.col("b.full")) & (F.col("a.kept") > F.col("b.kept") * (1 + 1e-9)))
    return kept.select(F.col("a.i").alias("i"), F.col("a.j").alias("j"), F.col("b.j").alias("z"))


BOUNDS = "qid long, vec_id long, full double, kept double, eps double"
#: Intervals of distance that ``order_violations_of`` compares before it looks at rows.
INTERVALS = 128


def _pairs(batches, q: np.ndarray, space: Space):
    """(ids, full, kept, eps) of rows x queries, a slice of the rows at a time."""
    own = np.hstack(space.parts(q))
    for part in (part for batch in batches for part in slices(batch, 8 * len(q))):
        x = matrix(part.column("embedding"))
        full, kept = part_distances(x, q), part_distances(np.hstack(space.parts(x)), own)
        yield part.column("vec_id").to_numpy(), full, kept, np.where(full > 0, 1 - kept / np.where(full > 0, full, 1), 0.0)


def query_bounds(base: DataFrame, queries: DataFrame, space: Space) -> DataFrame:
    """(qid, vec_id, full, kept, eps) of every query with every row: one scan of the base for a block of queries, and no shuffle."""
    spark = base.sparkSession
    out = spark.createDataFrame([], BOUNDS)
    for qids, q in query_blocks(queries):
        shared = spark.sparkContext.broadcast((qids, q, space))

        def run(batches, shared=shared):
            qids, q, space = shared.value
            for ids, *measured in _pairs(batches, q, space):
                columns = [np.tile(qids, len(ids)), np.repeat(ids, len(qids)), *[m.ravel() for m in measured]]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["qid", "vec_id", "full", "kept", "eps"])

        out = out.unionByName(base.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding").mapInArrow(run, BOUNDS))
    return out


#: A distance that grew by more than this in projection could take part in a violation.
GROWN = 1 + 9e-10


def losses(base: DataFrame, queries: DataFrame, space: Space) -> tuple[float, bool]:
    """The largest share of a squared distance that projection loses, over every query and row, and whether any distance grew: one scan for a block of queries, by rough distances, and by true ones where rounding could decide."""
    spark, worst, grown = base.sparkSession, 0.0, False
    for _, q in query_blocks(queries):
        shared = spark.sparkContext.broadcast((q, space))

        def run(batches, shared=shared):
            q, space = shared.value
            own = np.hstack(space.parts(q))
            rough, rough_kept, lost, grew = Rough(q, single=False), Rough(own, single=False), 0.0, False
            for part in (part for batch in batches for part in low_slices(batch, len(q))):
                x = matrix(part.column("embedding"))
                kept_x = np.hstack(space.parts(x))
                (full, slack), (kept, more) = rough(x), rough_kept(kept_x)
                slack = 2 * (slack + more)
                known = full > slack
                # 1 - kept / full may be off by this, as kept is not above full but for rounding
                share = (full - kept + 3 * slack) / np.where(known, full - slack, 1)
                row, i = np.nonzero(~known | (share >= lost) | (kept - full + 2 * slack > (GROWN - 1) * (full - slack)))
                if len(row) > 4 * len(q):
                    # the rows of the largest shares first: they leave few others to look at
                    first = np.argpartition(-np.where(known, share, -1), min(len(q), share.size - 1), axis=None)[: len(q)]
                    lost = max(lost, _true(x, q, kept_x, own, *np.unravel_index(first, share.shape))[0])
                    row, i = np.nonzero(~known | (share >= lost) | (kept - full + 2 * slack > (GROWN - 1) * (full - slack)))
                for lo in range(0, len(row), 1 << 16):
                    found = _true(x, q, kept_x, own, row[lo : lo + (1 << 16)], i[lo : lo + (1 << 16)])
                    lost, grew = max(lost, found[0]), grew or found[1]
            yield pa.RecordBatch.from_arrays([pa.array([lost]), pa.array([grew])], names=["lost", "grew"])

        got = base.select("embedding").mapInArrow(run, "lost double, grew boolean").agg(F.max("lost"), F.max("grew")).first()
        worst, grown = max(worst, got[0] or 0.0), grown or bool(got[1])
    return worst, grown


def _true(x: np.ndarray, q: np.ndarray, kept_x: np.ndarray, kept_q: np.ndarray, row: np.ndarray, i: np.ndarray) -> tuple[float, bool]:
    """The largest share lost by some pairs, and whether one grew."""
    full, kept = pair_distances(x[row], q[i]), pair_distances(kept_x[row], kept_q[i])
    return float(np.where(full > 0, 1 - kept / np.where(full > 0, full, 1), 0.0).max(initial=0)), bool((kept > full * GROWN).any())


def discrimination(base: DataFrame, queries: DataFrame, truth: DataFrame, scorers: list, n: int, ns: int) -> dict[str, np.ndarray]:
    """What ``gap``, ``error_bound`` and ``separation`` say for every query, from its counts of scores and the scores of its neighbours: no table of scores is kept."""
    held = []
    pairs = materialise(truth.select("qid", "vec_id").join(base, "vec_id"), "neighbours")
    for scorer in scorers:
        every = counts_of(histogram(base, scorer, ns), scorer.qids, ns)
        found = pair_scores(pairs, scorer).groupBy("qid", "score").agg(F.count(F.lit(1)).alias("cnt"))
        held.append((every, counts_of(found, scorer.qids, ns)))
    every, near = (np.concatenate(c) for c in zip(*held))
    level, k = np.arange(ns + 1), near.sum(axis=1)
    s_star = near @ level
    p_star, p = s_star / (k * ns), (every @ level - s_star) / ((n - k) * ns)
    gaps = p_star - p
    other = every - near
    over = np.cumsum(other[:, ::-1], axis=1)[:, ::-1] / (n - k)[:, None]
    type1 = np.hstack([np.ones((len(k), 1)), over[:, 1:], np.zeros((len(k), 1))])
    type2 = np.hstack([np.zeros((len(k), 1)), np.cumsum(near, axis=1) / k[:, None]])
    best = np.argmin(type1 + type2, axis=1)[:, None]
    return {"gap": gaps, "bound": np.exp(-ns * gaps * gaps / (8 * p * (1 - p))), "type1": np.take_along_axis(type1, best, 1)[:, 0], "type2": np.take_along_axis(type2, best, 1)[:, 0]}


def order_violations_of(base: DataFrame, queries: DataFrame, space: Space, worst: float | None = None) -> DataFrame:
    """``query_order_violations`` of the bounds of every query with every row, without keeping or sorting them. worst: the largest share lost, found first if not given.

    If it is the largest of these rows, every row keeps (1 - worst) of its distance, so only rows whose distance grew, beyond the margin of the comparison, can be kept farther than a row that was farther off by enough.
    Intervals of distance tell, by the least and largest kept distance in each, which rows can take part in a violation at all; only these leave their task, to be joined.
    """
    own = worst is None
    if own:
        worst, grown = losses(base, queries, space)
        if not grown:
            return base.sparkSession.createDataFrame([], "qid long, j long, z long")
    spark, blocks = base.sparkSession, list(query_blocks(queries, 2 * 8 * INTERVALS))
    rows = base.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    tops = []
    for _, q in blocks:

        def largest(batches, q=q):
            top = np.zeros(len(q))
            for _, full, _, _ in _pairs(batches, q, space):
                top = np.maximum(top, full.max(axis=0, initial=0))
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(top))), pa.array(top)], names=["at", "v"])

        found = rows.mapInArrow(largest, "at long, v double").groupBy("at").agg(F.max("v")).collect()
        tops.append(np.array([v for _, v in sorted(tuple(r) for r in found)]))
    schema = "qid long, kind int, vec_id long, key double, kept double"
    out = spark.createDataFrame([], schema)
    for (qids, q), top in zip(blocks, tops):
        scale = INTERVALS / np.where(top > 0, top, 1)
        place = lambda v, scale=scale: np.minimum((v * scale).astype(np.int64), INTERVALS - 1)

        def extremes(batches, q=q, place=place):
            low, high, column = np.full((len(q), INTERVALS), np.inf), np.full((len(q), INTERVALS), -np.inf), np.arange(len(q))
            for _, full, kept, _ in _pairs(batches, q, space):
                np.minimum.at(low, (column, place((1 - worst) * full)), kept)
                np.maximum.at(high, (column, place(full)), np.where(kept > full * GROWN, kept, -np.inf) if own else kept)
            at = np.flatnonzero(np.isfinite(low) | np.isfinite(high))
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(low.ravel()[at]), pa.array(high.ravel()[at])], names=["at", "low", "high"])

        got = rows.mapInArrow(extremes, "at long, low double, high double").groupBy("at").agg(F.min("low").alias("low"), F.max("high").alias("high")).toArrow()
        low, high = np.full(len(q) * INTERVALS, np.inf), np.full(len(q) * INTERVALS, -np.inf)
        low[got.column("at").to_numpy()], high[got.column("at").to_numpy()] = got.column("low").to_numpy(), got.column("high").to_numpy()
        beyond = np.minimum.accumulate(low.reshape(len(q), -1)[:, ::-1], axis=1)[:, ::-1]
        before = np.maximum.accumulate(high.reshape(len(q), -1), axis=1)
        shared = spark.sparkContext.broadcast((qids, q, beyond, before))

        def suspects(batches, shared=shared, place=place):
            qids, q, beyond, before = shared.value
            column = np.arange(len(q))
            for ids, full, kept, _ in _pairs(batches, q, space):
                key = (1 - worst) * full
                for kind, value, mask in ((0, full, (kept > beyond[column, place(full)] * (1 + 1e-9)) & (kept > full * GROWN if own else True)), (1, key, kept * (1 + 1e-9) < before[column, place(key)])):
                    row, i = np.nonzero(mask)
                    columns = (qids[i], np.full(len(i), kind, np.int32), ids[row], value[row, i], kept[row, i])
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["qid", "kind", "vec_id", "key", "kept"])

        out = out.unionByName(rows.mapInArrow(suspects, schema))
    a = out.where("kind = 0").select("qid", F.col("vec_id").alias("j"), F.col("key").alias("full"), "kept")
    b = out.where("kind = 1").select("qid", F.col("vec_id").alias("z"), "key", F.col("kept").alias("kept_z"))
    return a.join(b, "qid").where((F.col("full") < F.col("key")) & (F.col("kept") > F.col("kept_z") * (1 + 1e-9))).select("qid", "j", "z")


def query_order_violations(bounds: DataFrame) -> DataFrame:
    """(qid, j, z) as ``order_violations`` has it, over all rows of every query: by one sort a query, and a join of the violating rows alone."""
    worst = F.lit(bounds.agg(F.max("eps")).first()[0])
    low = bounds.select("qid", ((1 - worst) * F.col("full")).alias("key"), F.lit(1).alias("kind"), F.col("vec_id").alias("z"), F.col("kept").alias("kept_z"))
    rows = bounds.select("qid", F.col("full").alias("key"), F.lit(0).alias("kind"), F.col("vec_id").alias("z"), F.col("kept").alias("kept_z"))
    beyond = Window.partitionBy("qid").orderBy(F.desc("key"), "kind").rowsBetween(Window.unboundedPreceding, -1)
    least = F.min(F.when(F.col("kind") == 1, F.col("kept_z"))).over(beyond)
    bad = low.unionByName(rows).withColumn("least", least).where((F.col("kind") == 0) & (F.col("kept_z") > F.col("least") * (1 + 1e-9)))
    bad = bad.select("qid", F.col("key").alias("full"), F.col("z").alias("j"), F.col("kept_z").alias("kept"))
    return bad.join(low, "qid").where((F.col("full") < F.col("key")) & (F.col("kept") > F.col("kept_z") * (1 + 1e-9))).select("qid", "j", "z")


def cov_trace(cov: np.ndarray) -> float:
    return float(np.trace(cov))
