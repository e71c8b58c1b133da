"""Registered queries look at all queries and all rows, whatever the limits of one pass."""

import hashlib
import re

import duckdb
import numpy as np
import pytest

from annspark import catalog
from annspark.functions import arrays
from annspark.functions import sql as functions
from annspark.operators import exact, kmeans, metrics, scoring, select, theory, transform, weights
from annspark.params import Params
from annspark.plans import search, surround, workloads
from annspark.sources import vectors, work

SF = "/root/testdata/sf0.001"
BY_BLOCKS = ["collision_exact_score", "score_from_codes", "score_histogram", "cutoff_lookahead", "candidates_fixed", "collision_fidelity", "gap_by_query", "score_profile_transformed", "knn_agnostic_query", "collision_scan_knn"]


@pytest.fixture
def fresh():
    kept = dict(catalog._kept)
    catalog._kept.clear()
    yield
    catalog._kept.clear()
    catalog._kept.update(kept)


def test_every_block_of_queries_is_answered(spark, fresh, monkeypatch):
    whole = {name: sorted(catalog.CORE[name](spark, SF).collect()) for name in BY_BLOCKS}
    assert len({r.qid for r in whole["score_histogram"]}) == catalog.fixture(spark, SF, "embeddings")[1].count()
    for key in [k for k in catalog._kept if "scorer" in k[2]]:
        del catalog._kept[key]
    monkeypatch.setattr(exact, "QUERY_BYTES", 64 * 8 * 8)
    assert len(list(exact.query_blocks(catalog.fixture(spark, SF, "embeddings")[1]))) > 1
    assert {name: sorted(catalog.CORE[name](spark, SF).collect()) for name in BY_BLOCKS} == whole


def test_dimensionality_weights_look_at_all_rows(spark):
    rng = np.random.default_rng(3)
    # the later ids are of lower dimension in the first subspace
    x = rng.standard_normal((700, 4))
    x[512:, 1] = x[512:, 0]
    x[20] = x[19]
    base = spark.createDataFrame([(i, [float(v) for v in row]) for i, row in enumerate(x)], "vec_id long, embedding array<double>").cache()
    space = transform.fit(base, Params(space="agnostic", ns=2, s=2))
    expected = []
    for p in space.parts(x):
        near = np.sort(np.sqrt(((p[:, None] - p[None]) ** 2).sum(axis=2)), axis=1)[:, 1:21]
        near = near[near[:, 0] > 0]
        expected.append(np.mean(-1 / np.mean(np.log(near[:, :-1] / near[:, -1:]), axis=1)))
    assert np.allclose(weights.lid(base, space), np.array(expected) / np.mean(expected), rtol=1e-6)


def test_order_is_checked_over_all_rows(spark, fresh):
    base, queries = catalog.fixture(spark, SF, "skewed")
    assert theory.query_bounds(base, queries, catalog._adaptive_space(spark, SF)).count() == base.count() * queries.count()
    assert catalog.order_violations(spark, SF).first().violations == 0
    rng = np.random.default_rng(4)
    rows = [(q, i, float(f), float(k), 0.1) for q in range(2) for i, (f, k) in enumerate(rng.random((80, 2)))]
    expected = sorted((a[0], a[1], b[1]) for a in rows for b in rows if a[0] == b[0] and a[2] < (1 - 0.1) * b[2] and a[3] > b[3] * (1 + 1e-9))
    got = theory.query_order_violations(spark.createDataFrame(rows, "qid long, vec_id long, full double, kept double, eps double"))
    assert expected and sorted(tuple(r) for r in got.collect()) == expected


@pytest.mark.parametrize("ids", ["id * 3 - 400000", "id * id", "id"])
def test_first_centroids_stand_at_exact_ranks_of_large_tables(spark, ids):
    """More rows than approximate percentiles tell apart."""
    n, l = 300_000, 8
    base = spark.range(0, n, 1, 3).selectExpr(f"{ids} AS vec_id").selectExpr("vec_id", "array(CAST(vec_id AS double), 0D) AS embedding")
    at = lambda i: eval(ids, {"id": i})
    found = kmeans.initial(base, transform.of_dimensions(2, [np.arange(2)]), l, "spread", 17)[0]
    assert found[:, 0].tolist() == [at(c * (n - 1) // (l - 1)) for c in range(l)]
    assert kmeans.ids_at(base.where("false").unionByName(base.limit(1)), [0, 0]) == [base.first().vec_id] * 2


def test_document_vectors_agree_with_sql_at_halves(spark, tmp_path):
    """A vector of length 800 has components whose fifth decimal is a 5; some letters have more than one small form."""
    buckets = {}
    for i in range(5_000):
        h = int(hashlib.md5(f"w{i}".encode()).hexdigest()[:7], 16)
        if h // 64 % 2 == 0:
            buckets.setdefault(h % 64, f"w{i}")
    words = [buckets[b] for b in range(6)]
    long = " ".join(w for w, n in zip(words, (57, 797, 39, 4, 2, 1)) for _ in range(n))
    spark.createDataFrame([(1, long), (2, "ΟΔΟΣ İ ΣΑΣ Éa"), (3, None), (4, "a b a")], "doc_id long, text string").coalesce(1).write.parquet(str(tmp_path / "documents.parquet"))
    got = surround.QUERIES["doc_vectors"](spark, str(tmp_path)).select("vec_id", "slot", "value").collect()
    with duckdb.connect() as db:
        db.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{tmp_path}/documents.parquet/*.parquet')")
        expected = db.sql(f"SELECT vec_id, slot, value FROM ({surround.SQL['doc_vectors']})").fetchall()
    assert sorted(tuple(r) for r in got) == sorted(expected) and {r[0] for r in expected} == {1, 2, 4}


def test_streams_read_tables_of_several_files(spark, fresh, tmp_path):
    spark.read.parquet(f"{SF}/embeddings.parquet").repartition(3).write.parquet(str(tmp_path / "embeddings.parquet"))
    for name in ("stream_assign", "stream_drift"):
        assert sorted(catalog.CORE[name](spark, str(tmp_path)).collect()) == sorted(catalog.CORE[name](spark, SF).collect())


def test_table_function_carries_large_bases(spark):
    """More than 100,000 rows, with equal ones among the nearest."""
    base = spark.range(100_020).selectExpr("id AS vec_id", "array(CAST(id DIV 3 AS double), 1D) AS embedding")
    found = list(functions.knn_table(base, 5).func().eval(7, [20_000.0, 1.0]))
    assert [f[:3] for f in found] == [(7, r, v) for r, v in enumerate((60_000, 60_001, 60_002, 59_997, 59_998), 1)] and [f[3] for f in found] == [0, 0, 0, 1, 1]
    assert list(functions.knn_table(base.limit(0), 5).func().eval(7, [1.0, 1.0])) == []
    with pytest.raises(ValueError, match="too large"):
        functions.knn_table(spark.range(1 << 21).selectExpr("id AS vec_id", "array_repeat(0D, 64) AS embedding"), 5)


def test_bounds_and_violations_keep_no_pairs(spark, fresh, monkeypatch):
    base, queries = catalog.fixture(spark, SF, "skewed")
    space = catalog._adaptive_space(spark, SF)
    written = len(work._written)
    bounds = theory.query_bounds(base, queries, space).collect()
    expected = []
    for qid in {b.qid for b in bounds}:
        ids, full, kept = (np.array(c) for c in zip(*[(b.vec_id, b.full, b.kept) for b in bounds if b.qid == qid]))
        j, z = np.nonzero((full[:, None] < (1 - 0.03) * full) & (kept[:, None] > kept * (1 + 1e-9)))
        expected += [(qid, int(a), int(b)) for a, b in zip(ids[j], ids[z])]
    expected.sort()
    for limit in (exact.QUERY_BYTES, 16_000):
        monkeypatch.setattr(exact, "QUERY_BYTES", limit)
        assert expected and sorted(tuple(r) for r in theory.order_violations_of(base, queries, space, 0.03).collect()) == expected
    assert catalog.order_violations(spark, SF).first().violations == 0 and catalog.distance_bounds(spark, SF).count() == len(bounds) == 480 * 20
    assert len(work._written) == written
    assert "Exchange" not in catalog.distance_bounds(spark, SF)._jdf.queryExecution().executedPlan().toString()


def test_bounds_and_profiles_with_ties_and_wide_values(spark):
    """Rows that tie at a bound, rounding that could decide, values beyond single precision, and no pair of query and row written between."""
    rng = np.random.default_rng(11)
    plain = rng.integers(0, 3, (400, 6)).astype(float)
    for x in (plain, plain * 1e-3 + 1e4, plain * 1e25, np.vstack([rng.standard_normal((200, 6)), np.zeros((200, 6))])):
        rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(5).cache()
        asked = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x[::9])], "qid long, embedding array<double>")
        space = transform.fit(rows, Params(space="agnostic", ns=2, s=3))
        one, two = (scoring.exact_scorers(rows, asked, space, take) for take in (40, 130))
        score = np.zeros((len(x[::9]), len(x)))
        for p in space.parts(x):
            for i, q in enumerate(p[::9]):
                score[i, np.lexsort((np.arange(len(x)), scoring.pair_distances(p, np.tile(q, (len(p), 1)))))[:40]] += 1
        got = {(r.qid, r.vec_id): r.score for r in scoring.score_table(rows, one[0], keep_zero=True).collect()}
        assert all(got[i, k] == score[i, k] for i in range(len(score)) for k in range(len(x)))
        total = np.zeros(100)
        for i, q in enumerate(x[::9]):
            order = np.lexsort((np.arange(len(x)), np.sqrt(((x - q) ** 2).sum(axis=1))))
            total += score[i, order].reshape(100, -1).mean(axis=1) / len(score)
        several = metrics.profiles(rows, [one, two])
        assert np.allclose([r.mean_score for r in several[0].orderBy("percentile").collect()], total)
        assert several[1].collect() == metrics.profile(rows, two).collect()


def test_theory_from_counts_is_the_theory_of_all_pairs(spark):
    rng = np.random.default_rng(12)
    x = rng.standard_normal((300, 8))
    x[40] = x[41] = x[0]
    base = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(3).cache()
    queries = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x[:30])], "qid long, embedding array<double>").cache()
    truth = exact.knn(base, queries, 5).cache()
    for kind in ("agnostic", "adaptive"):
        space = transform.fit(base, Params(space=kind, ns=2, s=3))
        scorers = scoring.exact_scorers(base, queries, space, 60)
        scores = scoring.over_blocks(lambda s: scoring.score_table(base, s), scorers).cache()
        got = theory.discrimination(base, queries, truth, scorers, 300, 2)
        gaps = theory.gap(scores, truth, 300, 2)
        plain = {"gap": gaps.select("qid", "gap"), "bound": theory.error_bound(gaps, 2), **{c: theory.separation(scores, truth, 300, 2).select("qid", c) for c in ("type1", "type2")}}
        for name, frame in plain.items():
            assert np.allclose(got[name], [r[1] for r in frame.orderBy("qid").collect()], atol=1e-12), name
        bounds = theory.query_bounds(base, queries, space).toPandas()
        worst, grown = theory.losses(base, queries, space)
        assert abs(worst - bounds.eps.max()) < 1e-12 and grown == bool((bounds.kept > bounds.full * theory.GROWN).any())
    # a projection that stretches
    space.directions[0] = space.directions[0] * 1.5
    worst, grown = theory.losses(base, queries, space)
    expected = theory.query_order_violations(theory.query_bounds(base, queries, space)).count()
    assert grown and expected and theory.order_violations_of(base, queries, space).count() == expected


def test_weights_in_blocks_and_in_a_scan(spark, monkeypatch):
    rng = np.random.default_rng(13)
    x = rng.standard_normal((200, 6))
    base = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(3).cache()
    queries = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x[:12])], "qid long, embedding array<double>").cache()
    space = transform.fit(base, Params(space="agnostic", ns=3, s=2))
    once = weights.lid(base, space)
    monkeypatch.setattr(weights, "ROW_BYTES", 1000)
    assert np.allclose(weights.lid(base, space), once, rtol=1e-12)
    (scorer,) = scoring.exact_scorers(base, queries, space, 40)
    plain = {(r.qid, r.vec_id): r.score for r in scoring.weighted(scoring.collision_table(base, scorer), once).collect()}
    got = {(r.qid, r.vec_id): r.score for r in scoring.weighted_table(base, scorer, once).collect()}
    assert set(got) == set(plain) and all(abs(got[k] - plain[k]) < 1e-12 for k in got)
    levels = scoring.LevelScorer(scorer, once)
    ranked = {(r.qid, r.vec_id): r.score for r in scoring.score_table(base, levels).collect()}
    assert set(ranked) == set(plain)
    assert len({(ranked[k], round(plain[k], 9)) for k in plain}) == len(set(ranked.values())) and all(ranked[a] <= ranked[b] for a in plain for b in [max(plain, key=plain.get)])


def test_declared_scores_shuffle_no_pairs(spark, fresh):
    made = catalog.collisions_declared(spark, SF)
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in plan and "Exchange hashpartitioning" not in plan
    base, queries = catalog.fixture(spark, SF, "embeddings")
    space = transform.fit(base, Params(**(catalog.TINY | {"space": "agnostic"})))
    plain = scoring.score(scoring.exact_collisions_sql(transform.apply(base, space), transform.apply(queries, space, "qid"), Params(**catalog.TINY).collisions(base.count())))
    assert sorted(tuple(r) for r in made.collect()) == sorted(tuple(r) for r in plain.collect())


def test_text_vectors_take_one_scan(spark):
    texts = [(1, "b a\ta\nb\x0bc"), (2, None), (3, ""), (4, " \f\r "), (5, "İI\u00a0x Σ Éa"), (6, "one"), (6, "two one"), (7, None), (7, "z"), (8, "w" * 300)]
    rows = spark.createDataFrame(texts, "id long, text string")
    for d in (3, 64):
        expected = {}
        for key in {k for k, _ in texts}:
            total = np.zeros(d)
            for word in re.split(r"[ \t\n\x0b\f\r]+", " ".join(t for k, t in texts if k == key and t).replace("İ", "i").replace("Σ", "σ").lower()):
                if word:
                    h = int(hashlib.md5(word.encode()).hexdigest()[:7], 16)
                    total[h % d] += 1 if h // d % 2 == 0 else -1
            if total.any():
                expected[key] = (total / np.sqrt((total * total).sum())).tolist()
        assert {r.vec_id: r.embedding for r in vectors.text_vectors(rows, "id", d).collect()} == expected
    alone = vectors.text_vectors(rows.where("id < 6"), "id")._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in alone and "Exchange" not in alone and "Generate" not in alone


def test_rounds_of_the_bounds_go_on_with_open_queries_only(spark, monkeypatch):
    """a query whose bound is known is not counted again, and the bounds are those of a sort."""
    rng = np.random.default_rng(3)
    x = np.round(rng.normal(size=(3_000, 6)), 2)
    x[:400, :3] = x[0, :3]
    q = np.concatenate([x[:1], rng.normal(size=(30, 6))])
    base = spark.createDataFrame([(i, row.tolist()) for i, row in enumerate(x)], "vec_id long, embedding array<double>")
    space, asked, take, tally = transform.of_dimensions(6, [np.arange(3), np.arange(3, 6)]), [], 150, scoring.tally
    monkeypatch.setattr(scoring, "tally", lambda rows, count, width, queries: asked.append(queries) or tally(rows, count, width, queries))
    for name, value in (("FIRST", 200), ("BAND", 30)):
        monkeypatch.setattr(scoring, name, value)
    scorer = scoring.exact_scorer(base, np.arange(len(q)), q, space, take)
    assert asked[0] == len(q) and len(asked) > 1 and max(asked[1:]) < len(q)
    for j, (p, part) in enumerate(zip(space.parts(x), space.parts(q))):
        d = scoring.part_distances(p, part)
        last = [np.lexsort((np.arange(len(x)), d[:, i]))[take - 1] for i in range(len(q))]
        assert (scorer.last_id[:, j] == last).all() and (scorer.limit[:, j] == d[last, np.arange(len(q))]).all()


@pytest.mark.parametrize("many", [1, 10**9])
def test_candidates_and_their_nearest_without_a_step_for_each_query(spark, monkeypatch, many):
    """chosen ids and the nearest of them, where levels tie and rows are copies, are those of a sort; nothing is offered query by query."""
    rng = np.random.default_rng(4)
    x = rng.integers(0, 3, (900, 6)).astype(float)
    ids = rng.permutation(5_000)[:900]
    base = spark.createDataFrame([(int(i), row.tolist()) for i, row in zip(ids, x)], "vec_id long, embedding array<double>").repartition(3)
    q, space, budget, k = x[::60] + 0.1, transform.of_dimensions(6, [np.arange(3), np.arange(3, 6)]), 70, 5
    monkeypatch.setattr(search, "MANY", many)
    monkeypatch.setattr(arrays.Nearest, "offer", None)
    scorer = scoring.exact_scorer(base, np.arange(len(q)), q, space, 200)
    counts = select.counts_of(select.histogram(base, scorer, 2), scorer.qids, 2)
    got = exact.ranked(search.refine(base, scorer, select.by_number(counts, base, scorer, budget), k), k).collect()
    exact_scores = np.zeros((len(x), len(q)), int)
    for p, part in zip(space.parts(x), space.parts(q)):
        d = scoring.part_distances(p, part)
        for i in range(len(q)):
            exact_scores[np.lexsort((ids, d[:, i]))[:200], i] += 1
    wanted = []
    for i in range(len(q)):
        own = np.lexsort((ids, -exact_scores[:, i]))[:budget]
        dist = np.sqrt(((x[own] - q[i]) ** 2).sum(axis=1))
        wanted += [(i, r + 1, int(ids[own[o]])) for r, o in enumerate(np.lexsort((ids[own], dist))[:k])]
    assert sorted((r.qid, r.rank, r.vec_id) for r in got) == wanted


def test_text_vectors_of_several_widths_come_from_one_scan(spark, monkeypatch):
    """as they are one by one, also where a text is zero in one width only; the table is made once."""
    def place(word, d):
        h = int(hashlib.md5(word.encode()).hexdigest()[:7], 16)
        return h % d, h // d % 2

    words = [f"w{i}" for i in range(400)]
    pair = next((a, b) for a in words for b in words if place(a, 8)[0] == place(b, 8)[0] and place(a, 8)[1] != place(b, 8)[1] and place(a, 20)[0] != place(b, 20)[0])
    texts = spark.createDataFrame([(0, " ".join(pair)), (1, "one two three"), (2, ""), (3, None), (4, "w1 W1 w2")], "doc_id long, text string")
    several = vectors.text_vectors_of(texts, "doc_id", (8, 20))
    for d, held in ((8, {1, 4}), (20, {0, 1, 4})):
        got = {r.vec_id: r.embedding for r in vectors.of_width(several, d).collect()}
        assert set(got) == held and got == {r.vec_id: r.embedding for r in vectors.text_vectors(texts, "doc_id", d).collect()} and all(len(v) == d for v in got.values())
    made, materialise = [], workloads.materialise
    monkeypatch.setattr(workloads, "materialise", lambda df, name: made.append(name) or materialise(df, name))
    rows = workloads.best_settings(spark, "/root/testdata/sf0.001", ((32, 2, 4), (48, 2, 4))).collect()
    assert [r.d for r in rows] == [32, 48] and made.count("vectors") == 1
