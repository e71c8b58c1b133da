"""The experiments, re-expressed on the given tables.

``workload_*`` report what does not depend on the machine (recall, error, candidates, steps, bytes), with an oracle for each where SQL can say it. ``timing_*`` report
seconds and queries a second of the same settings, which differ from run to run.
"""

from __future__ import annotations

import time
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import graph, ivf, lsh, two_codebooks
from ..operators import activation, allocate, exact, metrics, scoring, select, theory, transform, weights
from ..params import PRESETS, Params, preset
from ..sources.tables import hold_out
from ..sources.vectors import FIXTURES, doc_vectors_of, fixture, of_width
from ..sources.work import materialise, stored_bytes
from . import index as indexes
from . import search

BASE = {"ns": 6, "s": 8, "cells": 256, "t": 5, "alpha": 0.1, "beta": 0.1, "k": 10}
#: Fixed values: (d, N_s, s) published as best for the five datasets.
BEST = ((256, 6, 8), (960, 4, 10), (128, 6, 6), (96, 6, 8), (100, 6, 10))
INDEXED = tuple(name for name in PRESETS if name != "collision_scan")
#: The published ranges of alpha and beta, beta extended for tables of few rows.
ALPHAS, BETAS = (0.01, 0.02, 0.05, 0.1), (0.001, 0.005, 0.01, 0.05, 0.1)


def _held(spark: SparkSession, sf_dir: str, table: str, **options) -> tuple[DataFrame, DataFrame]:
    """(base, queries) of a vector table that is made and written once."""
    make, modulus = FIXTURES[table]
    base, queries = hold_out(materialise(make(spark, sf_dir, **options), "vectors"), modulus)
    return base, materialise(queries, "queries")


def _case(spark: SparkSession, sf_dir: str, table: str, k: int = 10, **options) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(base, queries, truth), written once."""
    base, queries = _held(spark, sf_dir, table, **options)
    return base, queries, materialise(exact.knn(base, queries, k), "truth")


def _report(spark: SparkSession, rows: list[dict]) -> DataFrame:
    kinds = {bool: "boolean", int: "long", float: "double", str: "string"}
    schema = ", ".join(f"{k} {kinds[type(v)]}" for k, v in rows[0].items())
    return spark.createDataFrame([tuple(r.values()) for r in rows], schema)


def measures(answer: search.Answer, truth: DataFrame, queries: int, settings: list[Params]) -> list[dict]:
    """For each setting of a sweep its recall, mean relative error, missing ranks, and mean and most candidates a query."""
    ks = F.array(*[F.lit(p.k) for p in settings])
    asked = truth.select("qid", "rank", "vec_id", F.col("dist").alias("true_dist"))
    found = answer.neighbours
    hits = found.join(asked.select("qid", "vec_id", F.col("rank").alias("place")), ["qid", "vec_id"]).where(F.col("place") <= F.element_at(ks, F.col("setting") + 1)).groupBy("setting").count()
    hit = {r[0]: r[1] for r in hits.collect()}
    term = F.when(F.col("true_dist") > 0, (F.col("dist") - F.col("true_dist")) / F.col("true_dist"))
    off = {r.setting: r for r in found.join(asked.select("qid", "rank", "true_dist"), ["qid", "rank"]).groupBy("setting").agg(F.avg(term).alias("mre"), F.count(F.lit(1)).alias("n")).collect()}
    spread = {r.setting: r for r in answer.stats.groupBy("setting").agg(F.avg("candidate_num").alias("mean"), F.max("candidate_num").alias("most")).collect()}
    held = truth.groupBy("rank").count().collect()
    out = []
    for i, p in enumerate(settings):
        wanted = sum(r[1] for r in held if r[0] <= p.k)
        out.append({
            "recall": round(hit.get(i, 0) / (p.k * queries), 4), "mre": round(off[i].mre or 0.0, 4) if i in off else 0.0, "short_results": wanted - (off[i].n if i in off else 0),
            "candidates": round(spread[i].mean, 4), "most_candidates": int(spread[i].most),
        })
    return out


def _facts(spark, sf_dir, named: list[tuple[dict, Params]], table: str = "skewed", **options) -> DataFrame:
    """A row for each (columns, setting): what the setting's answers are worth. Settings of one space share an index, and its sweeps share scans."""
    base, queries, truth = _case(spark, sf_dir, table, max(p.k for _, p in named), **options)
    asked, rows = queries.count(), [None] * len(named)
    groups: dict[tuple, list[int]] = {}
    for i, (_, p) in enumerate(named):
        groups.setdefault((p.space, p.ns, p.s if p.space == "adaptive" else 0, p.cells, p.t), []).append(i)
    for numbers in groups.values():
        settings = [named[i][1] for i in numbers]
        answer = search.sweep(indexes.create(base, settings[0]), queries, settings)
        answer = search.Answer(materialise(answer.neighbours, "sweep"), answer.stats)
        for i, measured in zip(numbers, measures(answer, truth, asked, settings)):
            rows[i] = {**named[i][0], **measured}
    return _report(spark, rows)


def _timed(index: indexes.Index, queries: DataFrame, truth: DataFrame, params: Params) -> dict:
    n = queries.count()
    begun = time.time()
    found = materialise(search.query(index, queries, params).neighbours, "answer")
    seconds = time.time() - begun
    return {"recall": float(metrics.accuracy(found, truth, params.k).first().recall), "ms_per_query": 1000 * seconds / n, "qps": n / seconds}


def _profiles(spark, sf_dir, table, settings: list[Params]) -> list[DataFrame]:
    """A profile for each setting; vectors, blocks of queries and places by distance are made once."""
    base, queries = _held(spark, sf_dir, table)
    n, blocks = base.count(), list(exact.query_blocks(queries, scoring.counter_bytes(max(p.ns for p in settings))))
    scorers = [scoring.exact_scorers(base, queries, transform.fit(base, p), p.collisions(n), blocks) for p in settings]
    named = [F.lit(table).alias("table"), F.col("percentile").cast("long").alias("percentile"), F.round("mean_score", 6).alias("mean_score")]
    return [shown.select(named[0], F.lit(p.ns).cast("long").alias("ns"), F.lit(p.alpha).alias("alpha"), *named[1:]) for p, shown in zip(settings, metrics.profiles(base, scorers))]


PROFILED = ("embeddings", "skewed")
#: (N_s, alpha) of the raw profiles.
RAW = ((8, 0.05), (8, 0.1), (10, 0.1))


def profile_raw(spark: SparkSession, sf_dir: str, tables=PROFILED) -> DataFrame:
    """Mean collision score by percentile of distance, data-agnostic subspaces."""
    settings = [Params(space="agnostic", ns=ns, s=2, alpha=alpha) for ns, alpha in RAW]
    return reduce(DataFrame.unionByName, [part for table in tables for part in _profiles(spark, sf_dir, table, settings)])


def profile_transformed(spark: SparkSession, sf_dir: str, tables=PROFILED) -> DataFrame:
    """The same after the transformation."""
    return reduce(DataFrame.unionByName, [part for table in tables for part in _profiles(spark, sf_dir, table, [Params(space="adaptive", ns=6, s=8, alpha=0.05)])])


def profile_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both profiles on text vectors, where many distances tie but for rounding."""
    raw = profile_raw(spark, sf_dir, ("doc_vectors",)).withColumn("space", F.lit("agnostic"))
    return raw.unionByName(profile_transformed(spark, sf_dir, ("doc_vectors",)).withColumn("space", F.lit("adaptive")))


#: The published setting of the comparison with the scan.
SCAN = BASE | {"alpha": 0.05, "beta": 0.005}


def against_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The indexed method and the scan at the published alpha and beta, on text vectors: what either finds."""
    base, queries, truth = _case(spark, sf_dir, "doc_vectors")
    p, rows = preset("adaptive", **SCAN), []
    answers = {"adaptive": search.query(indexes.create(base, p), queries, p), "collision_scan": search.collision_scan(base, queries, preset("collision_scan", **SCAN))}
    for name, answer in answers.items():
        one = search.Answer(materialise(answer.neighbours.withColumn("setting", F.lit(0)), "answer"), answer.stats.withColumn("setting", F.lit(0)))
        rows.append({"method": name, **measures(one, truth, queries.count(), [p])[0]})
    return _report(spark, rows)


def timing_against_scan(spark: SparkSession, sf_dir: str, d: int = 64) -> DataFrame:
    """The same with time and speedup; every fifth row asks, so that the jobs' overhead is shared."""
    base = materialise(fixture(spark, sf_dir, "doc_vectors", d=d)[0], "base")
    queries = materialise(base.where("vec_id % 5 = 1").withColumnRenamed("vec_id", "qid"), "queries")
    truth = materialise(exact.knn(base, queries, 10), "truth")
    p, n, rows = preset("adaptive", **SCAN), queries.count(), []
    index = indexes.create(base, p)
    for name in ("collision_scan", "adaptive"):
        begun = time.time()
        run = search.collision_scan(base, queries, preset("collision_scan", **SCAN)) if name == "collision_scan" else search.query(index, queries, p)
        found = materialise(run.neighbours, "answer")
        rows.append({"method": name, "recall": float(metrics.accuracy(found, truth, p.k).first().recall), "ms_per_query": 1000 * (time.time() - begun) / n})
    return _report(spark, [r | {"speedup": rows[0]["ms_per_query"] / r["ms_per_query"]} for r in rows])


GRID, STUDY_ALPHAS = (16, 64, 256, 1024, 4096), (0.01, 0.05, 0.1)


def activation_study(spark: SparkSession, sf_dir: str, table: str = "order_vectors", grid=GRID, alphas=STUDY_ALPHAS) -> DataFrame:
    """Heap against linear search of the open rows: steps, and whether the cells agree."""
    base, queries = _held(spark, sf_dir, table)
    p = Params(space="agnostic", ns=2, s=4, t=3)
    space, rows = transform.fit(base, p), []
    for cells in grid:
        index = indexes.create(base, p.to(cells=cells), space)
        for alpha in alphas:
            got = {w: materialise(activation.activate(queries, space, index.books, index.counts, alpha, w), w) for w in ("heap", "linear")}
            keys = ["qid", "subspace", "c1", "c2", "cum_cnt"]
            same = got["heap"].select(keys).exceptAll(got["linear"].select(keys)).isEmpty()
            for way, found in got.items():
                work = metrics.activation_work(found).first().asDict()
                rows.append({"cells": cells, "alpha": alpha, "way": way, **{k: float(v) for k, v in work.items()}, "same_cells": same})
    return _report(spark, rows)


def activation_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The study on the embeddings: what was popped, how much of it was empty, and how many points came with it."""
    found = activation_study(spark, sf_dir, "embeddings")
    return found.select(F.col("cells").cast("long").alias("cells"), "alpha", "way", *[F.round(c, 4).alias(c) for c in ("popped", "empty", "retrieved")], "same_cells")


def subspace_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _facts(spark, sf_dir, [({"ns": n}, preset("adaptive", **(BASE | {"ns": n}))) for n in (2, 4, 6, 8)])


def subspace_width(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _facts(spark, sf_dir, [({"s": s}, preset("adaptive", **(BASE | {"s": s}))) for s in (4, 6, 8, 10)])


def neighbours_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall as k grows, for all methods with an index."""
    return _facts(spark, sf_dir, [({"method": m, "k": k}, preset(m, **(BASE | {"k": k}))) for m in INDEXED for k in (1, 10, 20, 50, 100)])


def curves(spark: SparkSession, sf_dir: str, alphas=ALPHAS, betas=BETAS) -> DataFrame:
    """Recall and error over alpha and beta, for all methods with an index."""
    return _facts(spark, sf_dir, [({"method": m, "alpha": a, "beta": b}, preset(m, **(BASE | {"alpha": a, "beta": b}))) for m in INDEXED for a in alphas for b in betas])


def timing_curves(spark: SparkSession, sf_dir: str, alphas=(0.02, 0.1), betas=(0.01, 0.05, 0.1), table: str = "skewed") -> DataFrame:
    """Recall against queries a second: every setting is run alone; a part of the grid, as each run costs a second or two."""
    base, queries, truth = _case(spark, sf_dir, table)
    built = {space: indexes.create(base, Params(**BASE, space=space)) for space in ("adaptive", "agnostic")}
    rows = []
    for m in INDEXED:
        for a in alphas:
            for b in betas:
                p = preset(m, **(BASE | {"alpha": a, "beta": b}))
                rows.append({"method": m, "alpha": a, "beta": b, **_timed(built[p.space], queries, truth, p)})
    return _report(spark, rows)


def best_settings(spark: SparkSession, sf_dir: str, settings=BEST) -> DataFrame:
    """The published (N_s, s) on text vectors of the published widths, which are made in one scan: share of dimensions dropped, and recall."""
    rows, several = [], materialise(doc_vectors_of(spark, sf_dir, [d for d, _, _ in settings]), "vectors")
    for d, ns, s in settings:
        base, queries = hold_out(of_width(several, d), FIXTURES["doc_vectors"][1])
        queries = materialise(queries, "queries")
        truth = materialise(exact.knn(base, queries, 10), "truth")
        p = preset("adaptive", **(BASE | {"ns": ns, "s": s, "alpha": 0.05, "beta": 0.05}))
        index = indexes.create(base, p)
        answer = search.sweep(index, queries, [p])
        rows.append({"d": d, "ns": ns, "s": s, "reduction": round(float(index.space.reduction), 4), **measures(search.Answer(materialise(answer.neighbours, "sweep"), answer.stats), truth, queries.count(), [p])[0]})
    return _report(spark, rows)


#: N_s that the methods choose their best from; the widths of the adaptive one are as in BASE.
CHOICES = (4, 6, 8, 10)


def _best(spark, sf_dir, table: str = "skewed") -> dict[str, Params]:
    """Each method with the N_s at which it recalls most (ties: the fewest subspaces)."""
    named = [({"method": m, "ns": n}, preset(m, **(BASE | {"ns": n}))) for m in INDEXED for n in CHOICES if not (preset(m).space == "adaptive" and n * BASE["s"] > 64)]
    found: dict[str, tuple] = {}
    for r, (_, p) in zip(_facts(spark, sf_dir, named, table).collect(), named):
        found.setdefault(r.method, (-1, None))
        if r.recall > found[r.method][0]:
            found[r.method] = (r.recall, p)
    return {m: p for m, (_, p) in found.items()}


def indexing(spark: SparkSession, sf_dir: str, table: str = "skewed") -> DataFrame:
    """Every framework method with its own best number of subspaces: dimensions and bytes of its index."""
    base, rows = materialise(fixture(spark, sf_dir, table)[0], "base"), []
    for name, p in _best(spark, sf_dir, table).items():
        index = indexes.create(base, p)
        rows.append({"method": name, "ns": p.ns, "dimensions": int(sum(index.space.widths)), "logical_bytes": int(index.logical_bytes())})
    return _report(spark, rows)


def timing_indexing(spark: SparkSession, sf_dir: str, table: str = "skewed") -> DataFrame:
    """The same with seconds, preprocessing apart, and the bytes of the stored codes."""
    base, rows = materialise(fixture(spark, sf_dir, table)[0], "base"), []
    for name, p in _best(spark, sf_dir, table).items():
        index = indexes.create(base, p)
        codes = materialise(index.points.select("vec_id", "cells"), "codes-only")
        rows.append({"method": name, "ns": p.ns, "preprocess_s": index.seconds["preprocess_s"], "index_s": index.seconds["index_s"], "logical_bytes": int(index.logical_bytes()), "stored_bytes": int(stored_bytes(codes))})
    return _report(spark, rows)


#: name -> (build, query, the values that its query parameter is swept over)
COMPETITORS = {
    "two_codebook_quantiser": (two_codebooks.build, two_codebooks.query, [{"beta": b} for b in (0.02, 0.1, 0.4)]), "projection_tree": (lsh.build, lsh.query, [{"beta": b} for b in (0.02, 0.1, 0.4)]),
    "bit_code_lists": (ivf.build, ivf.query, [{"probe": n} for n in (4, 16, 64)]), "layered_graph": (graph.build, graph.query, [{"ef": n} for n in (10, 40, 160)]),
    "refined_graph": (graph.build_refined, graph.query, [{"ef": n} for n in (10, 40, 160)]), "shortcut_graph": (graph.build_shortcut, graph.query, [{"ef": n} for n in (10, 40, 160)]),
}


def competitors(spark: SparkSession, sf_dir: str, table: str = "skewed", names=tuple(COMPETITORS), k: int = 10) -> DataFrame:
    """Index seconds and bytes, and a curve of recall and queries a second, of the method and of the other paradigms. Index seconds leave preprocessing out for none of them but the method, where it is apart."""
    base, queries, truth = _case(spark, sf_dir, table, k)
    p, n = preset("adaptive", **(BASE | {"k": k})), queries.count()
    index = indexes.create(base, p)
    rows = []
    for beta in (0.02, 0.1, 0.4):
        got = _timed(index, queries, truth, p.to(beta=beta, alpha=max(p.alpha, beta / 2)))
        rows.append({"method": "adaptive", "setting": f"beta={beta}", "preprocess_s": float(index.seconds["preprocess_s"]), "index_s": float(index.seconds["index_s"]), "bytes": int(index.logical_bytes()), **got})
    for name in names:
        build, ask, sweep = COMPETITORS[name]
        begun = time.time()
        built = build(base)
        ready = time.time() - begun
        for options in sweep:
            begun = time.time()
            found = materialise(ask(built, queries, k, **options), "answer")
            seconds = time.time() - begun
            rows.append({"method": name, "setting": ",".join(f"{o}={v}" for o, v in options.items()), "preprocess_s": 0.0, "index_s": ready, "bytes": int(built.bytes()), "recall": float(metrics.accuracy(found, truth, k).first().recall), "ms_per_query": 1000 * seconds / n, "qps": n / seconds})
    return _report(spark, rows)


def cumulative_cost(spark: SparkSession, sf_dir: str, least: float = 0.9) -> DataFrame:
    """At equal recall, each method's fastest setting that reaches ``least`` (else its best): seconds until the i-th answer, and after how many queries it has caught up with the method."""
    best: dict = {}
    for r in competitors(spark, sf_dir).collect():
        rank = (r.recall >= least, r.qps if r.recall >= least else r.recall)
        if r.method not in best or rank > best[r.method][0]:
            best[r.method] = (rank, r)
    own, rows = best["adaptive"][1], []
    for name, (_, r) in best.items():
        start = r.preprocess_s + r.index_s
        caught = metrics.crossover((own.preprocess_s + own.index_s, own.ms_per_query / 1000), (start, r.ms_per_query / 1000))
        for i, s in zip((0, 100, 10_000, 100_000), metrics.cumulative(start, r.ms_per_query / 1000, [0, 100, 10_000, 100_000])):
            rows.append({"method": name, "setting": r.setting, "recall": r.recall, "queries": i, "seconds": float(s), "catches_up_after": float(caught)})
    return _report(spark, rows)


def cumulative_work(spark: SparkSession, sf_dir: str, table: str = "skewed") -> DataFrame:
    """Cumulative cost in numbers multiplied, which no machine changes: building (rounds of clustering and the last assignment), then activation lists and re-ranking; against exact search."""
    base, queries, _ = _case(spark, sf_dir, table, BASE["k"])
    p = preset("agnostic+cutoff", **BASE)
    index = indexes.create(base, p)
    d = sum(index.space.widths)
    candidates = search.query(index, queries, p).stats.agg(F.avg("candidate_num")).first()[0]
    build, each = float(index.n * d * p.side * (p.t + 1)), float(d * p.side + candidates * d)
    caught = metrics.crossover((0.0, float(index.n * d)), (build, each))
    rows = [{"queries": i, "method": m, "numbers": round(v, 4), "catches_up_after": caught} for m, (b, e) in (("agnostic+cutoff", (build, each)), ("exact", (0.0, float(index.n * d)))) for i, v in zip((0, 100, 10_000), metrics.cumulative(b, e, [0, 100, 10_000]))]
    return _report(spark, rows)


WEIGHTS = {"variance": weights.variance, "mean_distance": weights.mean_distance, "lid": weights.lid}


def weighting(spark: SparkSession, sf_dir: str, table: str = "skewed") -> DataFrame:
    """Recall of the scan with weighted collisions, against plain ones."""
    base, queries, truth = _case(spark, sf_dir, table)
    p = Params(**(BASE | {"space": "agnostic"}))
    space = transform.fit(base, p)
    scorers = scoring.exact_scorers(base, queries, space, p.collisions(base.count()))
    n = base.count()
    given = {"none": np.ones(p.ns)}
    for name, measure in WEIGHTS.items():
        plain = measure(base, space)
        given |= {name: plain, f"{name}_inverse": (1 / plain) / (1 / plain).mean()}
    rows = []
    for name, w in given.items():
        # as places among the possible sums: levels of a search with integer scores
        found = []
        for scorer in (scoring.LevelScorer(s, w) for s in scorers):
            counts = select.counts_of(select.histogram(base, scorer, scorer.levels), scorer.qids, scorer.levels)
            # rows without a collision are no candidates
            budget = np.minimum(p.budget(n), counts[:, 1:].sum(axis=1))
            found.append(search.refine(base, scorer, select.by_number(counts, base, scorer, budget), p.k))
        found = materialise(exact.ranked(reduce(DataFrame.unionByName, found), p.k), "answer")
        rows.append({"weights": name, "recall": round(float(metrics.accuracy(found, truth, p.k).first().recall), 4)})
    return _report(spark, rows)


def theory_checks(spark: SparkSession, sf_dir: str, tables=("embeddings", "skewed")) -> DataFrame:
    """Balance of entropy, gap between neighbours and others, error shares and bound, share of distance lost at worst, and preserved order."""
    rows = []
    for table in tables:
        base, queries, truth = _case(spark, sf_dir, table)
        n = base.count()
        for kind in ("agnostic", "adaptive"):
            p = Params(**(BASE | {"space": kind}))
            space = transform.fit(base, p)
            scorers = scoring.exact_scorers(base, queries, space, p.collisions(n))
            found = {name: float(np.mean(values)) for name, values in theory.discrimination(base, queries, truth, scorers, n, p.ns).items()}
            worst, grown = theory.losses(base, queries, space)
            # none can be where no distance grew
            violations = theory.order_violations_of(base, queries, space).count() if grown else 0
            entropy = allocate.spread(space.values, space.blocks) if kind == "adaptive" else 0.0
            rows.append({
                "table": table, "space": kind, "entropy_spread": round(entropy, 4), **{name: round(found[name], 4) for name in ("gap", "bound", "type1", "type2")},
                "worst_loss": round(worst, 4), "violations": violations,
            })
    return _report(spark, rows)


QUERIES = {
    f"workload_{f.__name__}": f
    for f in (profile_raw, profile_transformed, profile_text, against_scan, activation_study, activation_embeddings, subspace_count, subspace_width, best_settings, indexing, curves, neighbours_count, competitors, cumulative_cost, cumulative_work, weighting, theory_checks)
} | {f.__name__: f for f in (timing_against_scan, timing_curves, timing_indexing)}
