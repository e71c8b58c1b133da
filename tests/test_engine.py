"""The engine on small tables: exactness, identities between methods, limits and odd inputs."""

from types import SimpleNamespace

import numpy as np
import pytest
from pyspark.sql import functions as F

from annspark.baselines import common, graph, ivf, lsh, two_codebooks
from annspark.functions import sql as names
from annspark.operators import activation, exact, imi, kmeans, linalg, metrics, scoring, select, theory, transform
from annspark.params import Params, preset
from annspark.plans import index as indexes
from annspark.plans import search
from annspark.sources import tables, work
from annspark.streaming import streams

SMALL = {"ns": 3, "s": 4, "cells": 16, "t": 2, "alpha": 0.2, "beta": 0.2, "k": 5}


def frame(spark, x, key="vec_id", first=0):
    return spark.createDataFrame([(first + i, [float(v) for v in row]) for i, row in enumerate(x)], f"{key} long, embedding array<double>")


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(5)
    x = rng.standard_normal((300, 12)) * np.arange(1, 13) ** -0.5
    x[10:14] = x[9]
    q = x[:6] + 0.1 * rng.standard_normal((6, 12))
    return x, q, frame(spark, x).cache(), frame(spark, q, "qid", 1000).cache()


@pytest.fixture(scope="module")
def built(data):
    return {space: indexes.create(data[2], Params(**SMALL, space=space)) for space in ("adaptive", "agnostic")}


def brute(x, q, k):
    d = np.sqrt(((x[None] - q[:, None]) ** 2).sum(axis=2))
    return [np.lexsort((np.arange(len(x)), row))[:k].tolist() for row in d]


def answers(df):
    out = {}
    for r in df.orderBy("qid", "rank").collect():
        out.setdefault(r.qid, []).append(r.vec_id)
    return [out.get(q, []) for q in sorted(out)]


def test_exact(spark, data):
    x, q, base, queries = data
    assert answers(exact.knn(base, queries, 7)) == brute(x, q, 7) == answers(exact.knn(base.repartition(7), queries, 7, impl="sql"))
    near = exact.within(base, queries, 1.5).count()
    assert near == (((x[None] - q[:, None]) ** 2).sum(axis=2) <= 2.25).sum()
    assert exact.knn(base, queries, 500).count() == 6 * 300


def test_query_blocks(monkeypatch, data):
    x, q, base, queries = data
    monkeypatch.setattr(exact, "QUERY_BYTES", 200)
    assert answers(exact.knn(base, queries, 3)) == brute(x, q, 3)


def test_moments(data):
    x, _, base, _ = data
    found = linalg.moments(base.repartition(5))
    assert np.allclose(found.mean, x.mean(axis=0)) and np.allclose(found.cov, np.cov(x, rowvar=False)) and found.n == 300


def test_space_invariants(data, built):
    x, _, base, _ = data
    space = built["adaptive"].space
    b = np.hstack(space.directions)
    assert np.allclose(b.T @ b, np.eye(12), atol=1e-9) and [len(v) for v in space.blocks] == [4, 4, 4]
    # all dimensions are kept, so distances are too
    parts = np.hstack(space.parts(x))
    assert np.allclose(((parts[0] - parts[1]) ** 2).sum(), ((x[0] - x[1]) ** 2).sum())
    a = {r.vec_id: r.parts for r in transform.apply(base, space).collect()}
    c = {r.vec_id: r.parts for r in transform.apply_sql(base, space).collect()}
    assert all(np.allclose(a[i], c[i]) for i in a)


def test_theory(spark, data):
    x, _, base, _ = data
    space = transform.fit(base, Params(ns=2, s=3, space="adaptive"))
    pairs = spark.createDataFrame([(i, j) for i in range(8) for j in range(8, 30)], "i long, j long")
    bounds = theory.distance_bounds(base, pairs, space).cache()
    assert bounds.where("kept > full * (1 + 1e-9)").isEmpty() and theory.order_violations(bounds).isEmpty()


def test_exact_collisions(spark, data):
    x, _, base, queries = data
    space = transform.fit(base, Params(**SMALL, space="agnostic"))
    qids, q = next(exact.query_blocks(queries))
    scorer = scoring.exact_scorer(base.repartition(4), qids, q, space, 60)
    fast = {(r.qid, r.subspace, r.vec_id) for r in scoring.collision_table(base, scorer).collect()}
    plain = {(r.qid, r.subspace, r.vec_id) for r in scoring.exact_collisions_sql(transform.apply(base, space), transform.apply(queries, space, "qid"), 60).collect()}
    assert fast == plain and len(fast) == 6 * 3 * 60


def test_index_invariants(data, built):
    for index in built.values():
        assert (index.counts.sum(axis=(1, 2)) == 300).all() and index.n == 300
        assert index.postings().count() == 900
        again = indexes.create(data[2].repartition(9), index.params, index.space)
        assert (again.counts == index.counts).all()


def test_probes_and_ways_agree(data, built):
    _, _, _, queries = data
    index = built["agnostic"]
    results = [answers(search.query(index, queries, index.params.to(activation=a, probe=p)).neighbours) for a in ("heap", "linear", "windowed") for p in ("codes", "postings")]
    assert all(r == results[0] for r in results)
    lists = activation.ranked_lists(queries, index.space, index.books)
    declared = activation.activate_sql(lists, imi.cell_counts(index.points, 4), 300, 0.2).select("qid", "subspace", "c1", "c2", "cum_cnt")
    direct = activation.activate(queries, index.space, index.books, index.counts, 0.2).select("qid", "subspace", "c1", "c2", "cum_cnt")
    assert declared.exceptAll(direct).isEmpty() and direct.exceptAll(declared).isEmpty()


def test_everything_is_exact_at_the_limit(data, built):
    x, q, base, queries = data
    for index in built.values():
        assert answers(search.query(index, queries, index.params.to(alpha=1.0, beta=1.0)).neighbours) == brute(x, q, 5)
    scan = search.collision_scan(base, queries, preset("collision_scan", **(SMALL | {"alpha": 1.0, "beta": 1.0})))
    assert answers(scan.neighbours) == brute(x, q, 5)


def test_presets_share_indexes(data):
    base = data[2]
    one, two = (indexes.create(base, preset(n, **SMALL)) for n in ("adaptive", "agnostic+transform"))
    assert (one.counts == two.counts).all()


@pytest.mark.parametrize("name", ["adaptive", "agnostic", "agnostic+transform", "agnostic+cutoff", "agnostic+query", "collision_scan"])
def test_presets(data, name):
    x, q, base, queries = data
    got = search.run(base, queries, preset(name, **SMALL))
    rows = got.neighbours.collect()
    assert len({(r.qid, r.vec_id) for r in rows}) == len(rows) and all(abs(r.dist - np.linalg.norm(x[r.vec_id] - q[r.qid - 1000])) < 1e-9 for r in rows)
    truth = exact.knn(base, queries, 5)
    found = metrics.accuracy(got.neighbours, truth, 5).first()
    assert 0.3 <= found.recall <= 1 and found.mre >= 0


def test_cutoffs_by_hand(spark):
    def hist(*counts):
        top = len(counts) - 1
        return spark.createDataFrame([(1, top - i, c) for i, c in enumerate(counts)], "qid long, score int, cnt long")

    def cut(h, rule):
        return tuple(select.cutoffs(h, 0.1, 100, rule).first())[1:]

    assert cut(hist(4, 5, 20, 71), "lookahead") == (2, 9) and cut(hist(4, 5, 20, 71), "accumulate") == (1, 29)
    assert cut(hist(6, 3, 20, 71), "lookahead") == (3, 6) and cut(hist(2, 9, 20, 69), "lookahead") == (2, 11)
    assert select.cutoffs(hist(4, 5, 20, 71), 0.1, 100, "lookahead", at_least=10).first().candidate_num == 29


def test_fixed_choice_matches_the_declared_one(data, built):
    _, _, _, queries = data
    index = built["agnostic"]
    qids, q = next(exact.query_blocks(queries))
    scorer = scoring.bit_scorer(qids, q, activation.activated_bits(queries, index.space, index.books, index.counts, 0.2), 3, 4)
    hist = select.histogram(index.points, scorer, 3)
    assert hist.groupBy("qid").agg(F.sum("cnt").alias("n")).where("n <> 300").isEmpty()
    a = select.candidates(index.points, scorer, select.by_number(select.counts_of(hist, qids, 3), index.points, scorer, 37))
    b = select.fixed(scoring.score_table(index.points, scorer, keep_zero=True), 37)
    assert a.exceptAll(b).isEmpty() and a.count() == 6 * 37


def test_odd_data(spark):
    same = frame(spark, np.ones((30, 6)))
    asked = frame(spark, np.ones((1, 6)), "qid")
    for space in ("adaptive", "agnostic", "sampled"):
        p = Params(ns=2, s=3, cells=4, t=2, alpha=0.5, beta=0.5, k=3, space=space)
        assert answers(search.run(same, asked, p).neighbours) == [[0, 1, 2]]
    few = frame(spark, np.eye(5, 6))
    assert len(search.run(few, asked, Params(ns=2, s=2, cells=1, t=1, alpha=0.5, beta=1.0, k=9)).neighbours.collect()) == 5
    none = asked.where("qid < 0")
    assert search.run(same, none, Params(ns=2, s=3, cells=4, t=1)).neighbours.isEmpty() and exact.knn(same, none, 3).isEmpty()


def test_packed_flags_are_the_activated_cells(data, built):
    _, _, _, queries = data
    index = built["adaptive"]
    qids, q = next(exact.query_blocks(queries))
    cells = activation.activate(queries, index.space, index.books, index.counts, 0.2).collect()
    want = np.zeros((3, 16, len(qids)), np.int8)
    for r in cells:
        want[r.subspace, r.c1 * 4 + r.c2, r.qid - 1000] = 1
    for way in activation.WAYS:
        bits = activation.activated_bits(queries.repartition(3), index.space, index.books, index.counts, 0.2, way)
        assert (scoring.bit_scorer(qids, q, bits, 3, 4).bitmap == want).all()


def test_cutoffs_of_counts_match_the_declared_ones(spark):
    rng = np.random.default_rng(8)
    counts = rng.integers(0, 40, (30, 7))
    hist = spark.createDataFrame([(i, s, int(c)) for i, row in enumerate(counts) for s, c in enumerate(row)], "qid long, score int, cnt long")
    assert (select.counts_of(hist, np.arange(30), 6) == counts).all()
    for rule in ("lookahead", "accumulate"):
        for least in (0, 60):
            # every query has the points of its own counts; n is what the rule compares with
            got = select.by_cutoff(counts, 0.1, 300, rule, least)
            want = {r.qid: (r.cutoff, r.candidate_num) for r in select.cutoffs(hist, 0.1, 300, rule, least).collect()}
            assert [(int(a), int(b)) for a, b in zip(got.level, got.number)] == [want[i] for i in range(30)]


def test_a_sweep_answers_like_single_queries(data, built):
    _, _, base, queries = data
    for space, index in built.items():
        settings = [preset(m, **(SMALL | {"alpha": a, "beta": b, "k": k})) for m in ("adaptive", "agnostic+transform", "agnostic", "agnostic+cutoff") if preset(m).space == space for a, b, k in ((0.1, 0.05, 5), (0.2, 0.3, 2), (0.2, 0.05, 9))]
        swept = search.sweep(index, queries, settings)
        for i, p in enumerate(settings):
            single = search.query(index, queries, p)
            assert answers(swept.neighbours.where(F.col("setting") == i)) == answers(single.neighbours)
            stats = ["qid", "cutoff", "candidate_num"]
            assert sorted(swept.stats.where(F.col("setting") == i).select(stats).collect()) == sorted(single.stats.select(stats).collect())


def test_where_every_point_is_a_candidate(data, built):
    x, q, _, queries = data
    index = built["agnostic"]
    # so few cells that most points never collide, and a beta that takes them all in
    p = index.params.to(alpha=0.01, beta=0.99, probe="postings", selector="cutoff")
    got = search.query(index, queries, p)
    assert {r.cutoff for r in got.stats.collect()} == {0} and answers(got.neighbours) == brute(x, q, 5)


@pytest.mark.parametrize("n", [40, 100, 233, 300])
def test_profile_against_all_pairs(spark, data, n):
    x, q, _, queries = data
    base = frame(spark, x[:n]).repartition(3)
    space = transform.fit(base, Params(**SMALL, space="agnostic"))
    scorers = scoring.exact_scorers(base, queries, space, max(1, n // 5))
    scores = np.zeros((len(q), n))
    for s in scorers:
        for r in scoring.score_table(base, s).collect():
            scores[r.qid - 1000, r.vec_id] = r.score
    total, count = np.zeros(100), np.zeros(100)
    for i in range(len(q)):
        order = np.lexsort((np.arange(n), np.sqrt(((x[:n] - q[i]) ** 2).sum(axis=1))))
        for b, part in enumerate(np.array_split(order, 100)):
            total[b] += scores[i, part].sum()
            count[b] += len(part)
    got = {r.percentile - 1: r.mean_score for r in metrics.profile(base, scorers).collect()}
    assert set(got) == set(np.flatnonzero(count)) and all(abs(got[b] - total[b] / count[b]) < 1e-9 for b in got)


def test_candidates_do_not_depend_on_partitions(spark, data):
    _, _, base, queries = data
    for module, options in ((two_codebooks, {"beta": 0.5, "keep": 12}), (ivf, {"probe": 16, "keep": 12})):
        built_ = module.build(base)
        once = answers(module.query(built_, queries, 5, **options))
        built_.points = built_.points.repartition(7)
        assert answers(module.query(built_, queries, 5, **options)) == once


def test_projection_tree_passes_over_far_leaves(data):
    x, q, base, queries = data
    made = lsh.build(base, sets=2, projections=4, symbols=32)
    rows = made.points.orderBy("vec_id").toArrow().combine_chunks().to_batches()[0]
    symbols = np.array(rows.column("symbols").to_pylist())
    for v in q:
        whole = made.lower_bounds(symbols, v)
        for radius in np.quantile(whole, [0.05, 0.3, 0.8]):
            near = made.bounds_within(rows, v, radius)
            # nothing within the radius is lost, and leaves beyond it are not looked at
            assert ((near == whole) | (whole > radius)).all() and (radius > np.median(whole) or np.isinf(near).any())
    assert answers(lsh.query(made, queries, 5, beta=1.0)) == brute(x, q, 5)


def test_graphs_are_exact_when_they_walk_everywhere(data):
    x, q, base, queries = data
    for build in (graph.build, graph.build_shortcut, graph.build_refined):
        made = build(base)
        assert answers(graph.query(made, queries, 5, ef=10_000)) == brute(x, q, 5)
    levels = {r.level for r in made.nodes.collect()}
    assert max(levels) >= 1  # the refined lists have layers over them
    jumps = [r for r in graph.build_shortcut(base, m=3).nodes.collect() if r.shortcuts]
    assert jumps and all(r.level >= 2 for r in jumps)


def test_rows_without_a_limit_are_measured_in_their_tasks(data):
    x, q, base, queries = data
    made = lsh.build(base)
    found = lsh.query(made, queries, 5, beta=1.0)
    assert answers(found) == brute(x, q, 5) and "value" not in found._jdf.queryExecution().executedPlan().toString()

    def rough(batch, q, i):
        ids = batch.column("vec_id").to_numpy()
        return np.where(ids % 2 == 0, (ids // 2 % 7).astype(float), np.inf)

    # with a limit: the rows of the least (value, id), of many ties, in batches that are cut one after another
    for keep in (3, 20, 100):
        first = sorted((i // 2 % 7, i) for i in range(0, len(x), 2))[:keep]
        chosen = [i for _, i in first]
        assert answers(common.rerank_scan(base, [], queries, 3, keep, rough)) == [[chosen[j] for j in np.lexsort((chosen, d))[:3]] for d in np.sqrt(((x[chosen][None] - q[:, None]) ** 2).sum(axis=2))]


def test_walks_that_keep_every_point_are_taken_together(data, monkeypatch):
    x, q, base, _ = data
    rows, kept, walk = graph.build(base).nodes.toArrow(), [], graph._walk
    monkeypatch.setattr(graph, "_walk", lambda x, links, q, entries, ef: kept.append(ef) or walk(x, links, q, entries, ef))
    for kind in ("layered", "refined"):
        found = graph._answer(SimpleNamespace(value=(np.arange(len(q)), q)), kind, 5, len(x))(rows).to_pandas()
        assert [found[found.qid == i].sort_values(["dist", "vec_id"]).vec_id.tolist() for i in range(len(q))] == brute(x, q, 5)
    # query by query only the layers are walked
    assert kept and set(kept) == {1}
    # links lead one way from {0, 1, 2} to {3, 4}; 5 stands alone
    reach = graph.Reach({0: [1], 1: [2], 2: [0, 3], 3: [4], 4: [3], 5: []})
    assert [np.flatnonzero(reach.masks[reach.of(i)]).tolist() for i in range(6)] == [[0, 1, 2, 3, 4]] * 3 + [[3, 4]] * 2 + [[5]] and len(reach.masks) == 3


def test_work_tables_can_be_cleared(spark, monkeypatch):
    monkeypatch.setattr(work, "_written", [])
    made = work.materialise(spark.range(5).toDF("vec_id"), "gone")
    assert work.stored_bytes(made) > 0 and work.clear(spark) >= 1 and work.clear(spark) == 0


def test_rejected_rows(spark):
    rows = [(1, [1.0, 2.0]), (2, None), (3, [1.0, None]), (4, [float("nan"), 1.0]), (None, [1.0, 2.0]), (6, [1.0]), (7, [3.0, 4.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    assert sorted(r.vec_id for r in tables.sound(df).collect()) == [1, 7]
    assert {r.reason for r in tables.rejected(df, 2).collect()} == {"no vector", "null component", "not finite", "no id", "wrong length"}


def test_formats(spark, tmp_path, data):
    _, _, base, _ = data
    for fmt in ("orc", "json", "parquet"):
        base.limit(5).write.format(fmt).save(str(tmp_path / fmt))
        assert tables.read_vectors(spark, str(tmp_path / fmt), fmt).count() == 5
    base.limit(5).select("vec_id", F.array_join("embedding", " ").alias("embedding")).write.option("header", True).csv(str(tmp_path / "csv"))
    assert tables.sound(tables.read_vectors(spark, str(tmp_path / "csv"), "csv")).count() == 5


def test_stored_index(spark, tmp_path, data):
    _, _, base, queries = data
    made = indexes.create(base, Params(**SMALL), path=str(tmp_path / "index"))
    read = indexes.load(spark, str(tmp_path / "index"))
    assert answers(search.query(read, queries).neighbours) == answers(search.query(made, queries).neighbours)


def test_filtered(data, built):
    x, q, base, queries = data
    index = built["agnostic"]
    index = indexes.Index(index.params.to(alpha=1.0, beta=1.0), index.space, index.books, index.points, index.counts, index.n)
    attributes = base.select("vec_id", (F.col("vec_id") % 3).alias("third"))
    got = answers(search.filtered(index, queries, attributes, "third = 1"))
    assert got == [[i for i in row if i % 3 == 1][:5] for row in brute(x, q, 300)]
    assert all(i % 3 == 1 for row in answers(search.filtered(index, queries, attributes, "third = 1", "post")) for i in row)
    assert search.knn_join(base.limit(3), index).count() == 15


@pytest.mark.parametrize("build,ask,least", [(two_codebooks.build, two_codebooks.query, 0.4), (lsh.build, lsh.query, 0.6), (ivf.build, ivf.query, 0.6), (graph.build, graph.query, 0.9), (graph.build_shortcut, graph.query, 0.9), (graph.build_refined, graph.query, 0.7)])
def test_baselines(data, build, ask, least):
    _, _, base, queries = data
    found = ask(build(base), queries, 5)
    assert metrics.accuracy(found, exact.knn(base, queries, 5), 5).first().recall >= least


def test_graph_shards(data):
    _, _, base, queries = data
    found = graph.query(graph.build(base, shard=80), queries, 5)
    assert metrics.accuracy(found, exact.knn(base, queries, 5), 5).first().recall >= 0.9


def test_kmeans_starts(data):
    x, _, base, _ = data
    space = transform.fit(base, Params(**SMALL, space="agnostic"))

    def loss(books):
        return sum(((p[:, None] - b) ** 2).sum(axis=2).min(axis=1).sum() for p, b in zip(kmeans.half_parts(space, x), books))

    start = kmeans.initial(base, space, 4, "spread", 1)
    for init in ("spread", "random", "kmeans++"):
        assert loss(kmeans.fit_all(base, space, 4, 4, init)) < loss(start)
    assert np.allclose(start[0][0], x[0][:2]) and np.allclose(start[0][3], x[299][:2])


def test_measures(spark):
    truth = spark.createDataFrame([(1, 1, 5, 0.0), (1, 2, 6, 2.0)], "qid long, rank int, vec_id long, dist double")
    got = spark.createDataFrame([(1, 1, 6, 2.0)], "qid long, rank int, vec_id long, dist double")
    row = metrics.accuracy(got, truth, 2).first()
    assert row.recall == 0.5 and row.short_results == 1 and row.mre_terms == 0 and row.mre is None
    assert metrics.crossover((10, 1.0), (20, 0.5)) == 20 and metrics.crossover((10, 1.0), (5, 9)) == 0 and metrics.crossover((1, 1), (2, 2)) == float("inf")
    assert metrics.cumulative(2.0, 0.5, [0, 4]) == [2.0, 4.0]


def test_sql_functions(spark, data, built):
    _, _, base, queries = data
    names.register(spark, base.limit(50), 3, built["agnostic"])
    queries.createOrReplaceTempView("asked")
    assert spark.sql("SELECT k.* FROM asked, LATERAL knn(qid, embedding) k").count() == 18
    assert spark.sql("SELECT a.* FROM asked, LATERAL activate(qid, embedding) a").groupBy("qid", "subspace").agg(F.sum("cnt").alias("n")).where("n < 60").isEmpty()
    assert spark.sql("SELECT l2_distance(array(0D, 3D), array(4D, 0D)) d").first().d == 5.0
    call = "collision_score(array(1, 2, 3), array(array(1, 5), array(7), array(3, 3)))"
    assert spark.sql(f"SELECT {call} s").first().s == 2
    assert spark.range(1).select(names.collision_score(F.expr("array(1, 2, 3)"), F.expr("array(array(1, 5), array(7), array(3, 3))")).alias("s")).first().s == 2


def test_streams(spark, tmp_path, data, built):
    x, _, base, _ = data
    index = built["agnostic"]
    base.limit(40).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("vec_id long, embedding array<double>").parquet(str(tmp_path / "in"))
    streams.append_codes(index, stream, str(tmp_path / "codes"), str(tmp_path / "state")).awaitTermination()
    got = spark.read.parquet(str(tmp_path / "codes")).select("vec_id", "cells")
    assert got.count() == 40 and got.exceptAll(index.points.select("vec_id", "cells")).isEmpty()
    parts = spark.readStream.schema("vec_id long, embedding array<double>").parquet(str(tmp_path / "in")).withColumn("part", F.lit(1).cast("long"))
    run = streams.drift(parts, index).writeStream.outputMode("update").format("memory").queryName("drift").trigger(availableNow=True).start()
    run.awaitTermination()
    assert spark.table("drift").first().n == 40


def test_late_events(spark, tmp_path):
    def put(name, rows):
        spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.to_timestamp("ts")).write.parquet(str(tmp_path / "in" / name))

    put("a", [(1, "2024-01-01 00:01:00", 1, "x", 1.0, ""), (2, "2024-01-01 00:03:00", 1, "x", 2.0, "")])
    stream = spark.readStream.schema(streams.EVENT).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))

    def run():
        streams.windowed_counts(stream).writeStream.outputMode("append").format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start().awaitTermination()

    run()
    put("b", [(3, "2024-01-01 01:00:00", 1, "x", 4.0, "")])
    run()
    put("c", [(4, "2024-01-01 00:02:00", 1, "x", 8.0, "")])  # later than the watermark
    put("d", [(5, "2024-01-01 03:00:00", 1, "x", 16.0, "")])
    run()
    rows = {str(r.start): (r.n, r.total) for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert rows["2024-01-01 00:00:00"] == (2, 3.0) and rows["2024-01-01 01:00:00"] == (1, 4.0)
