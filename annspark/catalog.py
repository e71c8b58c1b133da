"""The registered queries of the vector-search engine and their SQL oracles.

Integers are longs and real numbers are rounded, so that both engines print the same.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .functions import sql as functions
from .functions.arrays import lists
from .operators import activation, allocate, exact, imi, linalg, metrics, scoring, select, theory, transform, weights
from .oracles import workloads as workload_oracles
from .oracles.pipeline import KNN, Pipeline
from .params import Params, preset
from .plans import index as indexes
from .plans import search, surround, workloads
from .sources import vectors
from .sources.vectors import fixture
from .sources.work import materialise, work_dir
from .streaming import streams

#: The settings of the oracles: small enough for whole pipelines in one statement.
TINY = {"ns": 8, "s": 8, "cells": 64, "t": 3, "alpha": 0.1, "beta": 0.1, "k": 10}
TINY_ADAPTIVE = TINY | {"ns": 6}
ORACLE_DIR = "/root/testdata/sf0.01"
_kept: dict = {}


def kept(spark, key, make):
    """What several queries of one session share: made once for the tables of a folder as they are now. key: a name, the folder, and whatever else tells it apart."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(key[1])
    changed = folder.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(folder).getModificationTime()
    key = (spark.sparkContext.applicationId, changed, *key)
    if key not in _kept:
        _kept[key] = make()
    return _kept[key]


def _index(spark, sf_dir, table="embeddings", **params) -> indexes.Index:
    p = Params(**params)
    return kept(spark, ("index", sf_dir, table, p), lambda: indexes.create(fixture(spark, sf_dir, table)[0], p))


def _agnostic(spark, sf_dir, **changes):
    return _index(spark, sf_dir, **(TINY | {"space": "agnostic"} | changes))


def _truth(spark, sf_dir, table="embeddings", k=10) -> DataFrame:
    return kept(spark, ("truth", sf_dir, table, k), lambda: materialise(exact.knn(*fixture(spark, sf_dir, table), k), "truth"))


def _longs(df: DataFrame, places: int = 4) -> DataFrame:
    kinds = {"int": "long", "smallint": "long", "tinyint": "long"}
    return df.select(*[F.col(c).cast(kinds[t]).alias(c) if t in kinds else F.round(c, places).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def _knn(df: DataFrame) -> DataFrame:
    return _longs(df.select("qid", "rank", "vec_id", "dist"))


def _scorers(spark, sf_dir):
    """(base, its space, an exact scorer for each block of queries)."""
    base, queries = fixture(spark, sf_dir, "embeddings")

    def make():
        space = transform.fit(base, Params(**(TINY | {"space": "agnostic"})))
        return space, scoring.exact_scorers(base, queries, space, Params(**TINY).collisions(base.count()))

    return base, *kept(spark, ("exact scorers", sf_dir), make)


def _exact_scores(spark, sf_dir):
    base, _, scorers = _scorers(spark, sf_dir)
    return base, scoring.over_blocks(lambda s: scoring.score_table(base, s), scorers)


def _exact_collisions(spark, sf_dir):
    base, space, scorers = _scorers(spark, sf_dir)
    return base, space, scoring.over_blocks(lambda s: scoring.collision_table(base, s), scorers)


def _cells(spark, sf_dir, way="heap", **changes):
    index = _agnostic(spark, sf_dir, **changes)
    queries = fixture(spark, sf_dir, "embeddings")[1]
    return index, activation.activate(queries, index.space, index.books, index.counts, index.params.alpha, way, index.params.cell_distance)


def _cell_scorers(spark, sf_dir):
    """(index, a scorer for each block of queries from the block's own cells)."""

    def make():
        index, scorers = _agnostic(spark, sf_dir), []
        for qids, q in exact.query_blocks(fixture(spark, sf_dir, "embeddings")[1], index.params.ns * index.params.cells):
            block = spark.createDataFrame(pa.table({"qid": qids, "embedding": lists(q)}))
            bits = activation.activated_bits(block, index.space, index.books, index.counts, index.params.alpha, "heap", index.params.cell_distance)
            scorers.append(scoring.bit_scorer(qids, q, bits, index.params.ns, index.params.side))
        return index, scorers

    return kept(spark, ("cell scorers", sf_dir), make)


def _histogram(spark, sf_dir):
    index, scorers = _cell_scorers(spark, sf_dir)
    return index, scoring.over_blocks(lambda s: select.histogram(index.points, s, 8), scorers)


# ---- core methods


def exact_knn(spark, sf_dir):
    return _knn(exact.knn(*fixture(spark, sf_dir, "embeddings"), 10))


def exact_knn_k1(spark, sf_dir):
    return _knn(exact.knn(*fixture(spark, sf_dir, "embeddings"), 1))


def exact_knn_declared(spark, sf_dir):
    return _knn(exact.knn(*fixture(spark, sf_dir, "embeddings"), 10, impl="sql"))


def radius_search(spark, sf_dir):
    return _longs(exact.within(*fixture(spark, sf_dir, "embeddings"), 1.15))


def ratio_contract(spark, sf_dir):
    index = _agnostic(spark, sf_dir, selector="cutoff")
    found = search.query(index, fixture(spark, sf_dir, "embeddings")[1]).neighbours
    return metrics.ratio_ok(found, _truth(spark, sf_dir), 1.05).groupBy("qid").agg(F.sum(F.col("ok").cast("long")).alias("ranks_ok"))


def collision_exact_score(spark, sf_dir):
    return _longs(_exact_scores(spark, sf_dir)[1])


def collisions_declared(spark, sf_dir):
    """What ``exact_collisions_sql`` declares, by scans: the join and its ranks would write and sort every distance."""
    return _longs(_exact_scores(spark, sf_dir)[1])


def score_profile_raw(spark, sf_dir):
    base, _, scorers = _scorers(spark, sf_dir)
    return _longs(metrics.profile(base, scorers), 6)


def collision_scan_knn(spark, sf_dir):
    return _knn(search.run(*fixture(spark, sf_dir, "embeddings"), preset("collision_scan", **TINY)).neighbours)


def _moments(spark, sf_dir, table="embeddings"):
    return kept(spark, ("moments", sf_dir, table), lambda: linalg.moments(fixture(spark, sf_dir, table)[0]))


def moments_mean(spark, sf_dir):
    found = linalg.moments_frame(spark, _moments(spark, sf_dir))
    return _longs(found.where("j < 0").select("i", F.col("value").alias("mean")), 6)


def moments_cov(spark, sf_dir):
    found = linalg.moments_frame(spark, _moments(spark, sf_dir))
    return _longs(found.where("j >= 0").select("i", "j", F.col("value").alias("cov")), 6)


def moments_declared(spark, sf_dir):
    return _longs(linalg.moments_sql(fixture(spark, sf_dir, "embeddings")[0], 64), 6)


def eigenvalue_moments(spark, sf_dir):
    values = linalg.eigensystem(_moments(spark, sf_dir).cov).values
    return _longs(spark.createDataFrame([(float(values.sum()), float((values**2).sum()))], "eigen_sum double, eigen_squares double"), 6)


def kmeans_codebooks_agnostic(spark, sf_dir):
    books = _agnostic(spark, sf_dir).books
    rows = [(b // 2, b % 2, c, i, float(v)) for b, book in enumerate(books) for c, row in enumerate(book) for i, v in enumerate(row)]
    return _longs(spark.createDataFrame(rows, "subspace long, half long, cid long, slot long, value double"))


def imi_cells_agnostic(spark, sf_dir):
    return _longs(imi.cell_counts(_agnostic(spark, sf_dir).points, 8))


def imi_postings(spark, sf_dir):
    return _longs(_agnostic(spark, sf_dir).postings())


def ranked_lists(spark, sf_dir):
    index = _agnostic(spark, sf_dir)
    return _longs(activation.ranked_lists(fixture(spark, sf_dir, "embeddings")[1], index.space, index.books))


def _activated(way):
    def run(spark, sf_dir):
        return _longs(_cells(spark, sf_dir, way)[1].select("qid", "subspace", "c1", "c2", "cnt", "cum_cnt"))

    return run


def activated_cells_declared(spark, sf_dir):
    index = _agnostic(spark, sf_dir)
    lists = activation.ranked_lists(fixture(spark, sf_dir, "embeddings")[1], index.space, index.books)
    cells = activation.activate_sql(lists, imi.cell_counts(index.points, 8), index.n, index.params.alpha)
    return _longs(cells.select("qid", "subspace", "c1", "c2", "cnt", "cum_cnt"))


def activation_work(spark, sf_dir):
    ways = [_cells(spark, sf_dir, w)[1].groupBy("qid", "subspace").agg(F.sum("popped").alias("popped"), F.sum("empty").alias("empty")).withColumn("way", F.lit(w)) for w in ("heap", "linear", "windowed")]
    return _longs(ways[0].union(ways[1]).union(ways[2]))


def score_from_codes(spark, sf_dir):
    index, scorers = _cell_scorers(spark, sf_dir)
    return _longs(scoring.over_blocks(lambda s: scoring.score_table(index.points, s), scorers))


def score_from_postings(spark, sf_dir):
    index, cells = _cells(spark, sf_dir)
    return _longs(scoring.from_postings(index.postings(), cells))


def score_histogram(spark, sf_dir):
    return _longs(_histogram(spark, sf_dir)[1])


def _cutoff(rule):
    def run(spark, sf_dir):
        index, hist = _histogram(spark, sf_dir)
        return _longs(select.cutoffs(hist, 0.1, index.n, rule))

    return run


def candidates_fixed(spark, sf_dir):
    index, scorers = _cell_scorers(spark, sf_dir)

    def chosen(scorer):
        counts = select.counts_of(select.histogram(index.points, scorer, 8), scorer.qids, 8)
        choice = select.by_number(counts, index.points, scorer, index.params.budget(index.n))
        return select.candidates(index.points, scorer, choice)

    return _longs(scoring.over_blocks(chosen, scorers))


def _method(name, table="embeddings", **changes):
    def run(spark, sf_dir):
        p = preset(name, **((TINY if "adaptive" not in preset(name).space else TINY_ADAPTIVE) | changes))
        index = _index(spark, sf_dir, table, **(p.as_dict() | {"activation": "heap", "selector": "cutoff", "rule": "lookahead", "probe": "codes"}))
        return _knn(search.query(index, fixture(spark, sf_dir, table)[1], p).neighbours)

    return run


def result_overlap(spark, sf_dir):
    a, b = _method("agnostic+cutoff")(spark, sf_dir), _method("agnostic+query")(spark, sf_dir)
    return a.select("qid", "vec_id").intersect(b.select("qid", "vec_id")).groupBy("qid").agg(F.count(F.lit(1)).alias("shared"))


def _weighted(measure):
    def run(spark, sf_dir):
        base, space, scorers = _scorers(spark, sf_dir)
        weights_ = measure(base, space)
        return _longs(scoring.over_blocks(lambda s: scoring.weighted_table(base, s, weights_), scorers))

    return run


def gap_by_query(spark, sf_dir):
    base, scores = _exact_scores(spark, sf_dir)
    return _longs(theory.gap(scores, _truth(spark, sf_dir), base.count(), 8), 6)


def error_bound(spark, sf_dir):
    base, scores = _exact_scores(spark, sf_dir)
    return _longs(theory.error_bound(theory.gap(scores, _truth(spark, sf_dir), base.count(), 8), 8), 6)


def type_errors(spark, sf_dir):
    base, scores = _exact_scores(spark, sf_dir)
    return _longs(theory.separation(scores, _truth(spark, sf_dir), base.count(), 8), 6)


def _adaptive_space(spark, sf_dir, table="skewed"):
    return kept(spark, ("space", sf_dir, table), lambda: transform.fit(fixture(spark, sf_dir, table)[0], preset("adaptive", **TINY_ADAPTIVE)))


def distance_bounds(spark, sf_dir):
    """The pairs go straight to the result: no copy of them is written between."""
    return _longs(theory.query_bounds(*fixture(spark, sf_dir, "skewed"), _adaptive_space(spark, sf_dir)), 6)


def order_violations(spark, sf_dir):
    """Over every query and all rows."""
    return theory.order_violations_of(*fixture(spark, sf_dir, "skewed"), _adaptive_space(spark, sf_dir)).agg(F.count(F.lit(1)).alias("violations"))


def allocation(spark, sf_dir):
    space = _adaptive_space(spark, sf_dir)
    return _longs(allocate.allocation_frame(spark, space.values, space.blocks), 6)


def block_entropy(spark, sf_dir):
    space = _adaptive_space(spark, sf_dir)
    rows = [(j, float(v)) for j, v in enumerate(allocate.block_entropy(space.values, space.blocks))]
    return _longs(spark.createDataFrame(rows, "subspace long, logdet double"))


def transformed_norms(spark, sf_dir):
    """Squared length of every projected vector in every subspace: free of the eigenvectors' signs."""
    parts = transform.apply(fixture(spark, sf_dir, "skewed")[0], _adaptive_space(spark, sf_dir))
    long = parts.select("vec_id", F.posexplode("parts").alias("subspace", "p"))
    return _longs(long.select("vec_id", "subspace", F.aggregate("p", F.lit(0.0), lambda t, x: t + x * x).alias("length2")))


def score_profile_transformed(spark, sf_dir):
    base, queries = fixture(spark, sf_dir, "skewed")
    scorers = scoring.exact_scorers(base, queries, _adaptive_space(spark, sf_dir), Params(**TINY).collisions(base.count()))
    return _longs(metrics.profile(base, scorers), 6)


def allocation_gap(spark, sf_dir):
    """How far the greedy deal of the six leading eigenvalues to two blocks is from the best balance."""
    values = _adaptive_space(spark, sf_dir).values[:6]
    rows = [(float(allocate.spread(values, allocate.greedy(values, 2, 3))), float(allocate.brute_force(values, 2, 3)))]
    return _longs(spark.createDataFrame(rows, "greedy_spread double, best_spread double"))


def imi_cells_adaptive(spark, sf_dir):
    return _longs(imi.cell_counts(_index(spark, sf_dir, "skewed", **(TINY_ADAPTIVE | {"space": "adaptive"})).points, 8))


def collision_sampled_score(spark, sf_dir):
    """Collision scores where the subspaces are dimensions drawn without replacement."""
    base, queries = fixture(spark, sf_dir, "embeddings")
    p = Params(**(TINY | {"space": "sampled"}))
    scorers = scoring.exact_scorers(base, queries, transform.fit(base, p), p.collisions(base.count()))
    return _longs(scoring.over_blocks(lambda s: scoring.score_table(base, s), scorers))


METHODS = ("agnostic", "agnostic+cutoff", "agnostic+query")


def recall_by_method(spark, sf_dir):
    out = None
    for name in METHODS:
        part = metrics.accuracy(_method(name)(spark, sf_dir), _knn(_truth(spark, sf_dir)), 10).withColumn("method", F.lit(name))
        out = part if out is None else out.union(part)
    return _longs(out)


CORE = {
    f.__name__: f
    for f in (
        exact_knn, exact_knn_k1, exact_knn_declared, radius_search, ratio_contract, collision_exact_score, collisions_declared, score_profile_raw, collision_scan_knn, moments_mean, moments_cov,
        moments_declared, eigenvalue_moments, kmeans_codebooks_agnostic, imi_cells_agnostic, imi_postings, ranked_lists, activated_cells_declared, activation_work, score_from_codes, score_from_postings,
        score_histogram, candidates_fixed, result_overlap, gap_by_query, error_bound, type_errors, distance_bounds, order_violations, allocation, block_entropy, transformed_norms, score_profile_transformed, recall_by_method, allocation_gap, imi_cells_adaptive, collision_sampled_score,
    )
} | {
    **{f"activated_cells_{w}": _activated(w) for w in ("heap", "linear", "windowed")}, "cutoff_lookahead": _cutoff("lookahead"), "cutoff_accumulate": _cutoff("accumulate"),
    "knn_agnostic": _method("agnostic"), "knn_agnostic_cutoff": _method("agnostic+cutoff"), "knn_agnostic_query": _method("agnostic+query"), "knn_agnostic_postings": _method("agnostic+query", probe="postings"),
    "knn_adaptive": _method("adaptive", "skewed"), "knn_agnostic_transform": _method("agnostic+transform", "skewed"), "weighted_score_variance": _weighted(weights.variance),
    "weighted_score_mean_distance": _weighted(weights.mean_distance), "weighted_score_lid": _weighted(weights.lid),
}


#: Query parameters at which a baseline looks at every point, so that its answer is the exact one.
LIMITS = {
    "two_codebook_quantiser": {"beta": 1.0, "keep": 1 << 30}, "projection_tree": {"beta": 1.0}, "bit_code_lists": {"probe": 1 << 20, "keep": 1 << 30},
    **{f"{kind}_graph": {"ef": 1 << 20} for kind in ("layered", "refined", "shortcut")},
}


def _baseline(name, **options):
    def run(spark, sf_dir):
        build, ask, _ = workloads.COMPETITORS[name]
        base, queries = fixture(spark, sf_dir, "skewed")
        return _knn(ask(kept(spark, ("baseline", sf_dir, name), lambda: build(base)), queries, 10, **options))

    return run


BASELINES = {f"{n}_knn": _baseline(n) for n in workloads.COMPETITORS} | {f"{n}_at_limit": _baseline(n, **LIMITS[n]) for n in workloads.COMPETITORS}


def filtered_knn(spark, sf_dir):
    """Search among the points of even labels only, before scoring."""
    index = _agnostic(spark, sf_dir, selector="cutoff", beta=1.0, alpha=1.0)
    labels = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "label")
    return _knn(search.filtered(index, fixture(spark, sf_dir, "embeddings")[1], labels, "label % 2 = 0"))


def filtered_knn_post(spark, sf_dir):
    """The plain answer, with neighbours of odd labels taken out."""
    index = _agnostic(spark, sf_dir, selector="cutoff")
    labels = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "label")
    return _knn(search.filtered(index, fixture(spark, sf_dir, "embeddings")[1], labels, "label % 2 = 0", "post"))


def collision_fidelity(spark, sf_dir):
    """Share of the true collisions of every query that its activated cells contain."""
    true = _exact_collisions(spark, sf_dir)[2]
    index, cells = _cells(spark, sf_dir)
    found = index.postings().join(cells.select("qid", "subspace", "c1", "c2"), ["subspace", "c1", "c2"]).select("qid", "subspace", "vec_id")
    return _longs(metrics.fidelity(found, true))


def candidate_spread(spark, sf_dir):
    index = _agnostic(spark, sf_dir, selector="cutoff")
    stats = search.query(index, fixture(spark, sf_dir, "embeddings")[1]).stats
    return _longs(metrics.candidate_spread(stats, index.params.budget(index.n)).select("mean", "least", "most", "budget"))


def method_differences(spark, sf_dir):
    """Neighbours that the exact search finds and the indexed one misses, and the other way round."""
    got, true = _method("agnostic+cutoff")(spark, sf_dir).select("qid", "vec_id"), _truth(spark, sf_dir).select("qid", "vec_id")
    return true.exceptAll(got).withColumn("side", F.lit("missed")).unionByName(got.exceptAll(true).withColumn("side", F.lit("extra")))


def distance_steps(spark, sf_dir):
    """Gap to the next rank, and the moving mean of three distances, along every true ranking."""
    w = Window.partitionBy("qid").orderBy("rank")
    t = _truth(spark, sf_dir)
    steps = t.select("qid", "rank", (F.lead("dist").over(w) - F.col("dist")).alias("gap"), F.avg("dist").over(w.rowsBetween(-2, 0)).alias("smooth"), F.percent_rank().over(w).alias("share"))
    return _longs(steps.where("gap IS NOT NULL"))


def benchmark_retrieval(spark, sf_dir):
    """The documents nearest to each benchmark item, as hashed word vectors."""
    base, queries = vectors.doc_vectors(spark, sf_dir), vectors.benchmark_vectors(spark, sf_dir)
    return exact.knn(base, queries, 1).select("qid", F.col("rank").cast("long").alias("rank"), F.round("dist", 3).alias("dist"))


def _streamed(spark, sf_dir, table):
    """A stream over a given table's file, or over the files of its folder; times without zone become times of UTC, as watermarks ask for."""
    name = f"{sf_dir}/{table}.parquet"
    at, reader = spark._jvm.org.apache.hadoop.fs.Path(name), spark.readStream.schema(spark.read.parquet(name).schema)
    folder = at.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(at).isDirectory()
    stream = reader.parquet(name) if folder else reader.option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)
    plain = [c for c, t in stream.dtypes if t == "timestamp_ntz"]
    return stream.withColumns({c: F.to_timestamp(F.concat(F.col(c).cast("string"), F.lit("Z"))) for c in plain})


def _drained(spark, stream, mode: str) -> DataFrame:
    """What a stream has put out when all that is there has been read: each batch is written to a folder of its own."""
    path = f"{work_dir(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch, number):
        batch.write.mode("overwrite").parquet(f"{path}/out/batch={number}")

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).option("recursiveFileLookup", True).parquet(f"{path}/out")


def stream_assign(spark, sf_dir):
    """The cells of embeddings that arrive as a stream, under the frozen index."""
    index = _agnostic(spark, sf_dir)
    vectors_ = _streamed(spark, sf_dir, "embeddings").where("vec_id % 25 <> 0").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding"))
    path = f"{work_dir(spark)}/appended-{uuid.uuid4().hex}"
    streams.append_codes(index, vectors_, f"{path}/codes", f"{path}/state").awaitTermination()
    return _longs(imi.postings(spark.read.parquet(f"{path}/codes"), 8))


def stream_windows(spark, sf_dir):
    found = _drained(spark, streams.windowed_counts(_streamed(spark, sf_dir, "events")), "complete")
    return found.select(surround.micros(found, "start").alias("start_us"), surround.micros(found, "end").alias("end_us"), "event_type", "n", F.round("total", 2).alias("total"))


def stream_dedup(spark, sf_dir):
    """Every event arrives twice and is counted once."""
    events = _streamed(spark, sf_dir, "events")
    twice = events.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    return _drained(spark, streams.distinct_events(twice).select("event_id", "event_type"), "append").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


def stream_drift(spark, sf_dir):
    """Running spread of the subspaces' log variances in two parts of a stream of embeddings."""
    vectors_ = _streamed(spark, sf_dir, "embeddings").select((F.col("vec_id") % 2).alias("part"), F.col("embedding").cast("array<double>").alias("embedding"))
    return _longs(_drained(spark, streams.drift(vectors_, _agnostic(spark, sf_dir)), "update"))


def _registered(spark, sf_dir, base: bool = False, index: bool = False):
    """The SQL functions, the table functions only where they are asked for, and the queries as a view: spread over the tasks, as each costs a pass."""
    rows, queries = fixture(spark, sf_dir, "embeddings")
    functions.register(spark, rows if base else None, 10, _agnostic(spark, sf_dir) if index else None)
    queries.repartition(spark.sparkContext.defaultParallelism).createOrReplaceTempView("asked_vectors")


def sql_knn_table(spark, sf_dir):
    _registered(spark, sf_dir, base=True)
    return _knn(spark.sql("SELECT k.* FROM asked_vectors, LATERAL knn(qid, embedding) k"))


def sql_activate_table(spark, sf_dir):
    _registered(spark, sf_dir, index=True)
    return _longs(spark.sql("SELECT a.* FROM asked_vectors, LATERAL activate(qid, embedding) a"))


def sql_collision_score(spark, sf_dir):
    """Scores by the SQL function, of every point with every query's lists of activated cells."""
    _registered(spark, sf_dir)
    index, cells = _cells(spark, sf_dir)
    lists_ = cells.groupBy("qid", "subspace").agg(F.collect_set((F.col("c1") * 8 + F.col("c2")).cast("int")).alias("c"))
    asked = lists_.groupBy("qid").agg(F.transform(F.array_sort(F.collect_list(F.struct("subspace", "c"))), lambda x: x["c"]).alias("activated"))
    index.points.crossJoin(exact.beside(asked)).select("qid", "vec_id", "cells", "activated").createOrReplaceTempView("scored_points")
    return _longs(spark.sql("SELECT qid, vec_id, collision_score(cells, activated) AS score FROM scored_points").where("score > 0"))


CORE |= {f.__name__: f for f in (stream_assign, stream_windows, stream_dedup, stream_drift, sql_knn_table, sql_activate_table, sql_collision_score)}
CORE |= {f.__name__: f for f in (filtered_knn, filtered_knn_post, collision_fidelity, candidate_spread, method_differences, distance_steps, benchmark_retrieval)}


def _core_sql() -> dict[str, str]:
    p = Pipeline(**{k: v for k, v in TINY.items() if k != "cells"}, l=8)
    one = Pipeline(**{k: v for k, v in TINY.items() if k not in ("cells", "k")}, l=8, k=1)
    cells = p.sql("SELECT qid, j AS subspace, c1, c2, cnt, cum_cnt::BIGINT AS cum_cnt FROM activated")
    cut = p.sql(KNN.format(name="scores_cut_knn"))
    cov = "SELECT (i - 1)::BIGINT AS i, (k - 1)::BIGINT AS j, round(covar_samp(e[i], e[k]), 6) AS cov FROM base, range(1, 65) a(i), range(1, 65) b(k) GROUP BY i, k"
    profile = "SELECT percentile, round(avg(coalesce(score, 0)), 6) AS mean_score FROM (SELECT *, ntile(100) OVER (PARTITION BY qid ORDER BY dist, vec_id) AS percentile FROM distances) LEFT JOIN exact_scores USING (qid, vec_id) GROUP BY percentile"
    gap = "SELECT qid, s_star / (10.0::DOUBLE * 8) AS p_star, (s - s_star) / ((n - 10.0::DOUBLE) * 8) AS p FROM (SELECT qid, sum(score) FILTER (near) AS s_star, sum(score) AS s FROM (SELECT a.*, t.vec_id IS NOT NULL AS near FROM exact_scores_all a LEFT JOIN truth t USING (qid, vec_id)) GROUP BY qid), size"
    errors = "SELECT qid, h.s AS threshold, sum((NOT near AND score >= h.s)::INT) / (n - 10.0::DOUBLE) AS type1, sum((near AND score < h.s)::INT) / 10.0::DOUBLE AS type2 FROM (SELECT a.*, t.vec_id IS NOT NULL AS near FROM exact_scores_all a LEFT JOIN truth t USING (qid, vec_id)), range(0, 10) h(s), size GROUP BY qid, h.s, n"
    weigh = "SELECT qid, vec_id, round(sum(w / mean), 4) AS score FROM exact JOIN weights USING (j), (SELECT avg(w) AS mean FROM weights) GROUP BY qid, vec_id"
    centres = "SELECT j, list(m ORDER BY pos) AS c FROM (SELECT j, pos, avg(p[pos]) AS m FROM base_parts, range(1, 9) r(pos) GROUP BY ALL) GROUP BY j"
    lid = """SELECT j, avg(v) AS w FROM (SELECT a_id, j, -1 / avg(ln(dist / far)) FILTER (rk < 20) AS v, min(dist) AS nearest FROM (
        SELECT *, max(dist) OVER (PARTITION BY a_id, j) AS far FROM (SELECT a.vec_id AS a_id, a.j, list_distance(a.p, b.p) AS dist, row_number() OVER (PARTITION BY a.vec_id, a.j ORDER BY list_distance(a.p, b.p), b.vec_id <> a.vec_id) - 1 AS rk
        FROM base_parts a JOIN base_parts b ON a.j = b.j) WHERE rk BETWEEN 1 AND 20) GROUP BY a_id, j) WHERE nearest > 0 GROUP BY j"""
    acc = "SELECT '{name}' AS method, (SELECT round(avg(hits / 10.0::DOUBLE), 4) FROM (SELECT t.qid, count(r.vec_id) AS hits FROM truth t LEFT JOIN {knn} r USING (qid, vec_id) GROUP BY t.qid)) AS recall, round(avg((round(r.dist, 4) - round(t.dist, 4)) / round(t.dist, 4)), 4) AS mre, count(r.dist) AS mre_terms, sum((r.dist IS NULL)::INT)::BIGINT AS short_results FROM truth t LEFT JOIN {knn} r USING (qid, rank)"
    work = " UNION ALL ".join(f"SELECT qid, j AS subspace, count(*) AS popped, sum((cnt = 0)::INT)::BIGINT AS empty, '{w}' AS way FROM activated GROUP BY qid, j" for w in ("heap", "linear", "windowed"))
    out = {
        "exact_knn": p.sql(KNN.format(name="truth")), "exact_knn_declared": p.sql(KNN.format(name="truth")), "exact_knn_k1": one.sql(KNN.format(name="truth")),
        "radius_search": p.sql("SELECT qid, vec_id, round(dist, 4) AS dist FROM distances WHERE dist <= 1.15"),
        "ratio_contract": p.sql("SELECT qid, sum((r.dist <= 1.05 * t.dist + 1e-12)::INT)::BIGINT AS ranks_ok FROM scores_cut_knn r JOIN truth t USING (qid, rank) GROUP BY qid"),
        "collision_exact_score": p.sql("SELECT qid, vec_id, score FROM exact_scores"), "collisions_declared": p.sql("SELECT qid, vec_id, score FROM exact_scores"),
        "score_profile_raw": p.sql(profile), "collision_scan_knn": p.sql(KNN.format(name="exact_scores_fixed_knn")),
        "moments_mean": p.sql("SELECT (i - 1)::BIGINT AS i, round(avg(e[i]), 6) AS mean FROM base, range(1, 65) r(i) GROUP BY i"), "moments_cov": p.sql(cov), "moments_declared": p.sql(cov),
        "eigenvalue_moments": p.sql("SELECT round(sum(c) FILTER (i = k), 6) AS eigen_sum, round(sum(c * c), 6) AS eigen_squares FROM (SELECT i, k, covar_samp(e[i], e[k]) AS c FROM base, range(1, 65) a(i), range(1, 65) b(k) GROUP BY i, k)"),
        "kmeans_codebooks_agnostic": p.sql("SELECT j AS subspace, h AS half, cid, (pos - 1)::BIGINT AS slot, round(c[pos], 4) AS value FROM book, range(1, 5) r(pos)"),
        "imi_cells_agnostic": p.sql("SELECT j AS subspace, c1, c2, cnt FROM cells"), "imi_postings": p.sql("SELECT j AS subspace, c1, c2, vec_id FROM codes"),
        "ranked_lists": p.sql("SELECT qid, j AS subspace, h AS half, pos, cid, round(dist, 4) AS dist FROM lists"),
        **{f"activated_cells_{w}": cells for w in ("heap", "linear", "windowed", "declared")}, "activation_work": p.sql(work),
        "score_from_codes": p.sql("SELECT qid, vec_id, score FROM scores"), "score_from_postings": p.sql("SELECT qid, vec_id, score FROM scores"),
        "score_histogram": p.sql("SELECT qid, score, cnt::BIGINT AS cnt FROM scores_hist"),
        **{f"cutoff_{r}": p.sql(f"SELECT qid, cutoff, candidate_num::BIGINT AS candidate_num FROM scores_{r}") for r in ("lookahead", "accumulate")},
        "candidates_fixed": p.sql("SELECT qid, vec_id, score FROM scores_fixed"), "knn_agnostic": p.sql(KNN.format(name="scores_fixed_knn")),
        "knn_agnostic_cutoff": cut, "knn_agnostic_query": cut, "knn_agnostic_postings": cut, "result_overlap": p.sql("SELECT qid, count(*) AS shared FROM scores_cut_knn GROUP BY qid"),
        "gap_by_query": p.sql("SELECT qid, round(p_star, 6) AS p_star, round(p, 6) AS p, round(p_star - p, 6) AS gap FROM gaps", gaps=gap),
        "error_bound": p.sql("SELECT qid, round(exp(-8 * (p_star - p) * (p_star - p) / (8 * p * (1 - p))), 6) AS bound FROM gaps", gaps=gap),
        "type_errors": p.sql("SELECT qid, threshold, round(type1, 6) AS type1, round(type2, 6) AS type2 FROM errors QUALIFY row_number() OVER (PARTITION BY qid ORDER BY type1 + type2, threshold) = 1", errors=errors),
        "weighted_score_variance": p.sql(weigh, centres=centres, weights="SELECT j, sum(pow(list_distance(p, c), 2)) / (count(*) - 1) AS w FROM base_parts JOIN centres USING (j) GROUP BY j"),
        "weighted_score_mean_distance": p.sql(weigh, centres=centres, weights="SELECT j, avg(list_distance(p, c)) AS w FROM base_parts JOIN centres USING (j) GROUP BY j"),
        "weighted_score_lid": p.sql(weigh, weights=lid),
        "stream_assign": p.sql("SELECT j AS subspace, c1, c2, vec_id FROM codes"), "stream_windows": surround.SQL["events_tumbling"], "stream_dedup": "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY event_type",
        "sql_knn_table": p.sql(KNN.format(name="truth")), "sql_activate_table": p.sql("SELECT qid, j AS subspace, c1, c2, cnt FROM activated"), "sql_collision_score": p.sql("SELECT qid, vec_id, score FROM scores"),
        "recall_by_method": p.sql(" UNION ALL ".join(acc.format(name=m, knn=k) for m, k in zip(METHODS, ("scores_fixed_knn", "scores_cut_knn", "scores_cut_knn")))),
    }
    even = p.sql("SELECT qid, rank::BIGINT AS rank, vec_id, round(dist, 4) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, vec_id) AS rank FROM distances JOIN (SELECT vec_id, label FROM embeddings) USING (vec_id) WHERE label % 2 = 0) WHERE rank <= 10")
    doc = surround.SQL["doc_vectors"].replace("round(v / sqrt(sum(v * v) OVER (PARTITION BY doc_id)), 4)", "v / sqrt(sum(v * v) OVER (PARTITION BY doc_id))")
    item = doc.replace("doc_id", "item_id").replace("FROM documents", "FROM benchmark")
    more = {
        "filtered_knn": even,
        "filtered_knn_post": p.sql("SELECT qid, rank::BIGINT AS rank, vec_id, round(dist, 4) AS dist FROM scores_cut_knn JOIN (SELECT vec_id, label FROM embeddings) USING (vec_id) WHERE label % 2 = 0"),
        "collision_fidelity": p.sql("SELECT e.qid, round(count(c.vec_id) / count(*)::DOUBLE, 4) AS overlap FROM exact e LEFT JOIN (SELECT a.qid, a.j, c.vec_id FROM activated a JOIN codes c ON a.j = c.j AND a.c1 = c.c1 AND a.c2 = c.c2) c ON c.qid = e.qid AND c.j = e.j AND c.vec_id = e.vec_id GROUP BY e.qid"),
        "candidate_spread": p.sql("SELECT round(avg(candidate_num), 4) AS mean, min(candidate_num)::BIGINT AS least, max(candidate_num)::BIGINT AS most, 48::BIGINT AS budget FROM scores_lookahead"),
        "method_differences": p.sql("SELECT qid, vec_id, 'missed' AS side FROM truth ANTI JOIN scores_cut_knn USING (qid, vec_id) UNION ALL SELECT qid, vec_id, 'extra' AS side FROM scores_cut_knn ANTI JOIN truth USING (qid, vec_id)"),
        "distance_steps": p.sql("SELECT qid, rank::BIGINT AS rank, round(gap, 4) AS gap, round(smooth, 4) AS smooth, round(share, 4) AS share FROM (SELECT qid, rank, lead(dist) OVER w - dist AS gap, avg(dist) OVER (PARTITION BY qid ORDER BY rank ROWS 2 PRECEDING) AS smooth, percent_rank() OVER w AS share FROM truth WINDOW w AS (PARTITION BY qid ORDER BY rank)) WHERE gap IS NOT NULL"),
        "benchmark_retrieval": f"WITH d AS ({doc}), i AS ({item}), pairs AS (SELECT i.vec_id AS qid, d.vec_id, sum(i.value * d.value) AS dot FROM i JOIN d USING (slot) GROUP BY ALL) SELECT qid, 1::BIGINT AS rank, round(sqrt(greatest(0, 2 - 2 * max(dot))), 3) AS dist FROM pairs GROUP BY qid",
    }
    dims = np.random.default_rng(Params().seed).permutation(64).reshape(8, 8)
    drawn = Pipeline(**{k: v for k, v in TINY.items() if k != "cells"}, l=8, directions=[np.eye(64)[:, np.sort(d)] for d in dims], mean=np.zeros(64))
    limit = Pipeline(table="skewed", ns=8, k=10).sql(KNN.format(name="truth"))
    spread = f"SELECT part, max(n) AS n, max(h) - min(h) AS spread FROM (SELECT part, j, sum(lv) AS h, max(n) AS n FROM (SELECT vec_id % 2 AS part, i, (i - 1) // 8 AS j, ln(greatest(var_samp(embedding[i]::DOUBLE), 1e-12)) AS lv, count(*) AS n FROM embeddings, range(1, 65) r(i) GROUP BY ALL) GROUP BY part, j) GROUP BY part"
    more |= {
        "collision_sampled_score": drawn.sql("SELECT qid, vec_id, score FROM exact_scores"), **{f"{n}_at_limit": limit for n in LIMITS},
        "stream_drift": f"SELECT part, n, round(spread, 4) AS spread, spread > 1 AS rebuild FROM ({spread})",
    }
    return out | more | _spectral_sql() | workload_oracles.sql(ORACLE_DIR)


def _spectral_sql() -> dict[str, str]:
    """Oracles of the adaptive space: directions come from numpy, all else from SQL."""
    found = workload_oracles.spectrum(ORACLE_DIR, "skewed", 64)
    if found is None:
        return {}
    _, values, _ = found
    blocks = workload_oracles.dealt(values, 6, 8)
    p = workload_oracles.pipeline(ORACLE_DIR, "skewed", "adaptive", ns=6, s=8, l=8, t=3)
    pairs = "SELECT q.qid, b.vec_id, pow(list_distance(b.e, q.e), 2) AS whole, pow(list_distance(x.p, y.p), 2) AS kept FROM base b CROSS JOIN queries q JOIN base_flat x ON x.vec_id = b.vec_id JOIN query_flat y ON y.qid = q.qid"
    flat = {"base_flat": "SELECT vec_id, flatten(list(p ORDER BY j)) AS p FROM base_parts GROUP BY vec_id", "query_flat": "SELECT qid, flatten(list(p ORDER BY j)) AS p FROM queries_parts GROUP BY qid"}
    worst = "(SELECT max(1 - kept / whole) FROM pairs)"
    six = ", ".join(f"({i}, ln({float(v)!r}::DOUBLE))" for i, v in enumerate(values[:6]))
    few = workload_oracles.dealt(values[:6], 2, 3)
    greedy = " + ".join(("" if i in few[0] else "-") + f"ln({float(v)!r}::DOUBLE)" for i, v in enumerate(values[:6])).replace("+ -", "- ")
    profile = "SELECT percentile, round(avg(coalesce(score, 0)), 6) AS mean_score FROM (SELECT *, ntile(100) OVER (PARTITION BY qid ORDER BY dist, vec_id) AS percentile FROM distances) LEFT JOIN exact_scores USING (qid, vec_id) GROUP BY percentile"
    dealt = ", ".join(f"({j}, {i}, {r}, {float(values[r])!r}::DOUBLE)" for j, b in enumerate(blocks) for i, r in enumerate(b))
    return {
        "knn_adaptive": p.sql(KNN.format(name="scores_cut_knn")), "knn_agnostic_transform": p.sql(KNN.format(name="scores_fixed_knn")), "score_profile_transformed": p.sql(profile),
        "transformed_norms": p.sql("SELECT vec_id, j::BIGINT AS subspace, round(list_dot_product(p, p), 4) AS length2 FROM base_parts"),
        "distance_bounds": p.sql("SELECT qid, vec_id, round(whole, 6) AS \"full\", round(kept, 6) AS kept, round(1 - kept / whole, 6) AS eps FROM pairs", **flat, pairs=pairs),
        "order_violations": p.sql(f"SELECT count(*) AS violations FROM pairs a JOIN pairs b ON a.qid = b.qid AND a.whole < (1 - {worst}) * b.whole AND a.kept > b.kept * (1 + 1e-9)", **flat, pairs=pairs),
        "imi_cells_adaptive": p.sql("SELECT j::BIGINT AS subspace, c1, c2, cnt FROM cells"),
        "allocation_gap": f"WITH v AS (SELECT * FROM (VALUES {six}) v(i, x)) SELECT round(abs({greedy}), 4) AS greedy_spread, (SELECT round(min(abs(2 * (a.x + b.x + c.x) - t)), 4) FROM v a, v b, v c, (SELECT sum(x) AS t FROM v) WHERE a.i = 0 AND b.i > 0 AND c.i > b.i) AS best_spread",
        "allocation": f"SELECT j::BIGINT AS subspace, i::BIGINT AS slot, r::BIGINT AS rank, round(v, 6) AS eigenvalue FROM (VALUES {dealt}) t(j, i, r, v)",
        "block_entropy": f"SELECT j::BIGINT AS subspace, round(sum(ln(v)), 4) AS logdet FROM (VALUES {dealt}) t(j, i, r, v) GROUP BY j",
    }


def queries():
    return CORE | BASELINES | surround.QUERIES | workloads.QUERIES


def oracle_sql():
    return _core_sql() | surround.SQL


def flagship(spark, sf_dir):
    return collision_scan_knn(spark, sf_dir)

