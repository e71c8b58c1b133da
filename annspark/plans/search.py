"""Answering a batch of queries: activate cells, score, choose candidates, re-rank in the original space.

Two scans of the points and no shuffle of them: the first sends score counts, the second, which scores again, the k best
of each task. Query blocks bound every broadcast.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.arrays import Nearest, lists, matrix, slices
from ..operators import activation, scoring, select, transform
from ..operators.exact import NEIGHBOURS, beside, knn, query_blocks, ranked
from ..params import Params
from ..sources.work import materialise
from .index import Index, create

#: Beyond one in so many pairs, candidates are looked through by rough distances.
MANY = 64
STATS = "qid long, cutoff int, candidate_num long"


@dataclass
class Answer:
    neighbours: DataFrame  # qid, rank, vec_id, dist
    stats: DataFrame  # qid, cutoff, candidate_num
    cells: DataFrame | None = None


def refine_all(points: DataFrame, scorer, choices: list[select.Choice], k: int) -> DataFrame:
    """(choice, qid, vec_id, dist): for each of several choices the k nearest candidates of every task, by exact distance, in one scan."""
    shared = points.sparkSession.sparkContext.broadcast((scorer, choices))
    columns = list(dict.fromkeys(["vec_id", scorer.column, "embedding"]))

    def run(batches):
        scorer, choices = shared.value
        best = [Nearest(scorer.q, k) for _ in choices]
        for part in (part for batch in batches for part in slices(batch, len(scorer.qids))):
            ids, scores = part.column("vec_id").to_numpy(), scorer.scores(part)
            chosen = [choice.pairs(scores, ids) for choice in choices]
            some = np.unique(np.concatenate([row for row, _ in chosen]))
            if len(some):
                x = matrix(part.column("embedding").take(pa.array(some)))
                for near, (row, i) in zip(best, chosen):
                    row = np.searchsorted(some, row)
                    if MANY * len(row) < len(some) * len(scorer.qids):
                        near.offer_pairs(i, row, ids[some], x)
                    else:
                        mask = np.zeros((len(some), len(scorer.qids)), bool)
                        mask[row, i] = True
                        near.offer_mask(mask, ids[some], x)
        for c, near in enumerate(best):
            found = near.batch(scorer.qids)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(found.num_rows, c, np.int32)), *found.columns], names=["choice", *found.schema.names])

    return points.select(*columns).mapInArrow(run, f"choice int, {NEIGHBOURS}")


def refine(points: DataFrame, scorer, choice: select.Choice, k: int) -> DataFrame:
    """(qid, vec_id, dist): the k nearest candidates of every task, by exact distance."""
    return refine_all(points, scorer, [choice], k).drop("choice")


def refine_join(candidates: DataFrame, base: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """The same as joins, from (qid, vec_id): for candidate tables that stand apart from the vectors."""
    from ..functions.vector import l2

    both = candidates.select("qid", "vec_id").join(base.select("vec_id", "embedding"), "vec_id").join(beside(queries.select("qid", F.col("embedding").alias("q"))), "qid")
    return ranked(both.select("qid", "vec_id", l2(F.col("embedding"), F.col("q")).alias("dist")), k)


def _choose(points: DataFrame, scorer, params: Params, n: int, counts: np.ndarray) -> select.Choice:
    if params.selector == "cutoff":
        return select.by_cutoff(counts, params.beta, n, params.rule, params.min_candidates)
    return select.by_number(counts, points, scorer, params.budget(n))


def _block(spark, qids: np.ndarray, q: np.ndarray) -> DataFrame:
    return spark.createDataFrame(pa.table({"qid": qids, "embedding": lists(q)})).repartition(min(len(qids), spark.sparkContext.defaultParallelism))


def _stats(spark, chosen: list[tuple[int, np.ndarray, select.Choice]]) -> DataFrame:
    """(setting, qid, cutoff, candidate_num) of (setting, qids, choice): one small table, however many blocks and settings there were."""
    columns = [np.concatenate([np.zeros(0, np.int64), *part]) for part in zip(*[(np.full(len(q), i), q, c.level, c.number) for i, q, c in chosen])] or [np.zeros(0, np.int64)] * 4
    kinds = (pa.int32(), pa.int64(), pa.int32(), pa.int64())
    return spark.createDataFrame(pa.table([pa.array(c.astype(np.int64), pa.int64()).cast(k) for c, k in zip(columns, kinds)], names=["setting", "qid", "cutoff", "candidate_num"])).repartition(1)


def probe_of(index: Index, queries: DataFrame, params: Params) -> str:
    """Postings read about alpha * ns of the index and shuffle it; codes read all of it for all queries at once and shuffle nothing."""
    if params.probe != "auto":
        return params.probe
    return "postings" if queries.count() * params.alpha < 0.05 else "codes"


def _scorers(index: Index, queries: DataFrame, alpha: float, way: str, metric: str):
    """(scorer, its counts) of each block of queries; a block's flags take ns * K bytes a query."""
    ns = len(index.space.directions)
    for qids, q in query_blocks(queries, ns * index.params.cells):
        bits = activation.activated_bits(_block(index.points.sparkSession, qids, q), index.space, index.books, index.counts, alpha, way, metric)
        scorer = scoring.bit_scorer(qids, q, bits, ns, index.params.side)
        yield scorer, select.counts_of(select.histogram(index.points, scorer, ns), qids, ns)


def query(index: Index, queries: DataFrame, params: Params | None = None) -> Answer:
    """Answer (qid, embedding) queries from an index."""
    params = params or index.params
    spark, chosen = index.points.sparkSession, []
    found, stats = spark.createDataFrame([], NEIGHBOURS), spark.createDataFrame([], STATS)
    cells = activation.activate(queries, index.space, index.books, index.counts, params.alpha, params.activation, params.cell_distance)
    if probe_of(index, queries, params) == "postings":
        for qids, q in query_blocks(queries):
            block = _block(spark, qids, q)
            own = activation.activate(block, index.space, index.books, index.counts, params.alpha, params.activation, params.cell_distance)
            part, counted = _from_scores(index, materialise(scoring.from_postings(index.postings(), own), "scores"), block, params)
            found, stats = found.unionByName(part), stats.unionByName(counted)
    else:
        for scorer, counts in _scorers(index, queries, params.alpha, params.activation, params.cell_distance):
            choice = _choose(index.points, scorer, params, index.n, counts)
            found = found.unionByName(refine(index.points, scorer, choice, params.k))
            chosen.append((0, scorer.qids, choice))
        stats = _stats(spark, chosen).drop("setting")
    return Answer(ranked(found, params.k), stats, cells)


def sweep(index: Index, queries: DataFrame, settings: list[Params]) -> Answer:
    """The answers of many settings of one index, with a column ``setting`` (their number) first: settings of one alpha share activation, scores and one re-ranking scan."""
    spark, chosen = index.points.sparkSession, []
    found = spark.createDataFrame([], f"setting int, {NEIGHBOURS}")
    shared: dict[tuple, list[int]] = {}
    for number, p in enumerate(settings):
        # the ways of activation give the same cells
        shared.setdefault((p.alpha, p.cell_distance), []).append(number)
    for (alpha, metric), numbers in shared.items():
        for scorer, counts in _scorers(index, queries, alpha, "heap", metric):
            choices = [_choose(index.points, scorer, settings[i], index.n, counts) for i in numbers]
            part = refine_all(index.points, scorer, choices, max(settings[i].k for i in numbers))
            named = F.element_at(F.array(*map(F.lit, numbers)), F.col("choice") + 1)
            found = found.unionByName(part.withColumn("setting", named).drop("choice"))
            chosen += [(i, scorer.qids, choice) for i, choice in zip(numbers, choices)]
    w = Window.partitionBy("setting", "qid").orderBy("dist", "vec_id")
    most = F.element_at(F.array(*[F.lit(p.k) for p in settings]), F.col("setting") + 1)
    top = found.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= max(p.k for p in settings)).where(F.col("rank") <= most)
    return Answer(top.select("setting", "qid", "rank", "vec_id", "dist"), _stats(spark, chosen))


def _from_scores(index: Index, scores: DataFrame, block: DataFrame, params: Params) -> tuple[DataFrame, DataFrame]:
    hist = materialise(select.histogram_of(scores, index.n, len(index.space.directions), block), "histogram")
    none = index.points.sparkSession.createDataFrame([], NEIGHBOURS)
    if params.selector == "cutoff":
        # a row for each query of the block
        levels = materialise(select.cutoffs(hist, params.beta, index.n, params.rule, params.min_candidates), "levels")
        chosen = scores.join(F.broadcast(levels), "qid").where("cutoff > 0 AND score >= cutoff").select("qid", "vec_id")
        # where the cutoff is 0 every point is a candidate: the exact search
        zero = block.join(levels.where("cutoff = 0"), "qid", "left_semi")
        none = knn(index.points, zero, params.k).drop("rank")
    else:
        chosen = select.fixed(scores, params.budget(index.n)).select("qid", "vec_id")
        levels = chosen.groupBy("qid").agg(F.lit(0).alias("cutoff"), F.count(F.lit(1)).alias("candidate_num"))
    return refine_join(chosen, index.points, block, params.k).select("qid", "vec_id", "dist").unionByName(none.select("qid", "vec_id", "dist")), levels.select("qid", "cutoff", "candidate_num")


def collision_scan(base: DataFrame, queries: DataFrame, params: Params) -> Answer:
    """The method without an index: true collisions, fixed choice (or the one asked for), re-ranking."""
    spark = base.sparkSession
    space = transform.fit(base, params)
    n, ns = base.count(), params.ns
    found, chosen = spark.createDataFrame([], NEIGHBOURS), []
    for qids, q in query_blocks(queries, scoring.counter_bytes(ns)):
        scorer = scoring.exact_scorer(base, qids, q, space, params.collisions(n))
        choice = _choose(base, scorer, params, n, select.counts_of(select.histogram(base, scorer, ns), qids, ns))
        found = found.unionByName(refine(base, scorer, choice, params.k))
        chosen.append((0, qids, choice))
    return Answer(ranked(found, params.k), _stats(spark, chosen).drop("setting"))


def run(base: DataFrame, queries: DataFrame, params: Params) -> Answer:
    """Any preset end to end."""
    if params.activation == "exact":
        return collision_scan(base, queries, params)
    return query(create(base, params), queries)


def knn_join(left: DataFrame, index: Index, key: str = "vec_id") -> DataFrame:
    """(left_id, rank, vec_id, dist): the approximate neighbours of every row of ``left``."""
    return query(index, left.select(F.col(key).alias("qid"), "embedding")).neighbours.withColumnRenamed("qid", "left_id")


def filtered(index: Index, queries: DataFrame, attributes: DataFrame, predicate: str, mode: str = "pre") -> DataFrame:
    """Search among the points whose attributes (vec_id, ...) satisfy a SQL predicate.

    ``pre``: only they are counted, scored and re-ranked. ``post``: the plain answer, filtered.
    """
    allowed = attributes.where(predicate).select("vec_id")
    if mode == "post":
        return query(index, queries).neighbours.join(allowed, "vec_id", "left_semi").select("qid", "rank", "vec_id", "dist")
    from ..operators import imi

    points = materialise(index.points.join(allowed, "vec_id", "left_semi"), "filtered")
    counts = imi.occupancy(imi.cell_counts(points, index.params.side), len(index.space.directions), index.params.side)
    return query(Index(index.params, index.space, index.books, points, counts, int(counts[0].sum())), queries).neighbours
