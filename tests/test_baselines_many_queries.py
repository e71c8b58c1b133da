"""the baselines take many queries at a step, and answer as they do query by query."""

import numpy as np
import pyarrow as pa
import pytest

from annspark.baselines import common, graph, ivf, lsh, two_codebooks
from annspark.functions import arrays


@pytest.fixture(scope="module")
def data(spark):
    rng = np.random.default_rng(8)
    x = rng.standard_normal((400, 12)) * np.arange(1, 13) ** -0.5
    x[20:140] = x[19]  # copies, whose order is decided by their ids
    q = np.concatenate([x[:12] + 0.1 * rng.standard_normal((12, 12)), x[19:20]])
    tables = [spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(part)], f"{key} long, embedding array<double>").repartition(3).cache() for key, part in (("vec_id", x), ("qid", q))]
    return x, q, *tables


def rows_of(made):
    return made.points.orderBy("vec_id").toArrow().combine_chunks().to_batches()[0]


def answer_of(x, q, values, k, keep):
    """The k nearest of the ``keep`` rows of the least (value, id); rows of no finite value are not looked at."""
    out = []
    for i, value in enumerate(values):
        some = [j for j in np.lexsort((np.arange(len(x)), value)) if np.isfinite(value[j])][:keep]
        dist = np.sqrt(((x[some] - q[i]) ** 2).sum(axis=1))
        out += [(i, r + 1, some[o]) for r, o in enumerate(np.lexsort((some, dist))[:k])]
    return out


def got_of(df):
    return sorted((r.qid, r.rank, r.vec_id) for r in df.collect())


def test_two_codebooks(data):
    x, q, base, queries = data
    made = two_codebooks.build(base, cells=16)
    rows = rows_of(made)
    cell, code = rows.column("cell").to_numpy(), arrays.matrix(rows.column("code")).astype(int)
    for beta in (0.1, 0.6):
        values = np.full((len(q), len(x)), np.inf)
        for i, y in enumerate(q @ made.rotation):
            order = [two_codebooks.centroid_lists(c, h[0], "l2sq") for c, h in zip(made.coarse, two_codebooks._halves(y[None]))]
            got = two_codebooks.by_heap(order[0][1], order[1][1], made.counts[np.ix_(order[0][0], order[1][0])], beta * made.n)
            taken = order[0][0][got.pos1] * made.counts.shape[1] + order[1][0][got.pos2]
            for j in np.flatnonzero(np.isin(cell, taken)):
                rest = y - np.hstack([made.coarse[0][cell[j] // made.counts.shape[1]], made.coarse[1][cell[j] % made.counts.shape[1]]])
                values[i, j] = round(sum(((p - f[c]) ** 2).sum() for p, f, c in zip(two_codebooks._pieces(rest[None], len(made.fine)), made.fine, code[j])), 12)
        for keep in (7, 30, 10**6):
            assert got_of(two_codebooks.query(made, queries, 5, beta=beta, keep=keep)) == answer_of(x, q, values, 5, keep)


def test_bit_codes(data):
    x, q, base, queries = data
    made = ivf.build(base, lists_=12)
    rows = rows_of(made)
    label, length, own = (rows.column(c).to_numpy() for c in ("list", "length", "own"))
    shown = arrays.matrix(rows.column("code")) - 3.5
    values = np.full((len(q), len(x)), np.inf)
    for i, v in enumerate(q):
        far = ((made.centres - v) ** 2).sum(axis=1)
        for j in np.flatnonzero(np.isin(label, np.argsort(far, kind="stable")[:5])):
            product = shown[j] @ ((v - made.centres[label[j]]) @ made.rotation) / max(own[j], 1e-12)
            cosine2 = min(1, own[j] ** 2 / (shown[j] @ shown[j]))
            error = 1.9 * np.sqrt(far[label[j]] * max(0, (1 - cosine2) / max(cosine2, 1e-12)) / 11)
            values[i, j] = round(far[label[j]] + length[j] ** 2 - 2 * length[j] * (product + error), 12)
    for keep in (7, 30, 10**6):
        assert got_of(ivf.query(made, queries, 5, probe=5, keep=keep)) == answer_of(x, q, values, 5, keep)


@pytest.mark.parametrize("scale", [1.0, 1e-12, 1e18])
def test_projection_tree(spark, data, scale):
    x, q = data[0] * scale, data[1] * scale
    base, queries = (spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(part)], f"{key} long, embedding array<double>").repartition(2) for key, part in (("vec_id", x), ("qid", q)))
    made = lsh.build(base, sets=2, projections=4, symbols=32)
    rows = rows_of(made)
    symbols = arrays.matrix(rows.column("symbols")).astype(int)
    bounds = np.stack([made.lower_bounds(symbols, v) for v in q])
    # the last edge is a bound itself
    edges = np.array([0.0, *np.quantile(bounds, [0.2, 0.6]), bounds.max()])
    counted = lsh.Looked(made, q).counts(rows, edges)
    assert (np.cumsum(counted, axis=1)[:, :-1] == (bounds[:, :, None] <= edges).sum(axis=1)).all()
    radius = np.sort(bounds, axis=1)[:, 150]
    for some, mask in lsh.Looked(made, q, radius).flags(rows):
        assert (mask == (bounds[some] <= radius[some, None]).T).all()
    # the least range of the grid that holds enough
    beta = 0.2
    widest = float(np.abs(made.breaks).max()) * 4 * np.sqrt(4) + 1e-9
    radii = np.concatenate([[0.0], widest / 1.5 ** np.arange(lsh.LEVELS - 1, -1, -1)])
    values = np.stack([np.where(own <= next(r for r in radii if (own <= r).sum() >= beta * len(x) + 5), 0.0, np.inf) for own in bounds])
    assert got_of(lsh.query(made, queries, 5, beta=beta)) == answer_of(x, q, values, 5, len(x))


def test_ranges_are_counted_in_one_scan(data, monkeypatch):
    """All ranges of all queries come from one pass over the points, another measures: no function is called query by query."""
    _, _, base, queries = data
    made, scans = lsh.build(base, sets=2, projections=4, symbols=32), []
    made.points = made.points.cache()
    kind = type(made.points)
    plain = kind.mapInArrow
    monkeypatch.setattr(kind, "mapInArrow", lambda self, *a, **o: scans.append(self.columns) or plain(self, *a, **o))
    lsh.query(made, queries, 5, beta=0.9)
    assert scans == [["symbols"], ["vec_id", "embedding", "symbols", "leaves"]]


@pytest.mark.parametrize("ef", [1, 4, 25])
def test_walks_in_step(monkeypatch, ef):
    rng = np.random.default_rng(2)
    x, q = rng.standard_normal((260, 6)), rng.standard_normal((90, 6))
    _, links = graph.layered(x, 4, 12, np.random.default_rng(1))
    near = [list(dict.fromkeys(links[0][i])) for i in range(len(x))]
    entries = rng.integers(0, len(x), (len(q), 3))
    entries[:, 2] = np.where(entries[:, 2] % 3 == 0, entries[:, 1], -1)
    monkeypatch.setattr(graph, "WALKED", 30 * len(x))  # three blocks of queries
    far, met = graph._walk(x, graph.Links(near), q, entries, ef)
    for i, v in enumerate(q):
        one = graph._walk(x, near, v, [int(e) for e in entries[i] if e >= 0], ef)
        assert [p for _, p in one] == met[i][met[i] >= 0].tolist() and [d for d, _ in one] == far[i][met[i] >= 0].tolist()
    # a part that is smaller than what a walk may hold
    far, met = graph._walk(x, graph.Links([[1], [0]] + [[]] * (len(x) - 2)), q, np.zeros((len(q), 1), int), 5)
    assert all(sorted(row) == [-1, -1, -1, 0, 1] for row in met.tolist()) and np.isinf(far[:, 2:]).all()


def test_layers_from_known_distances(monkeypatch):
    """The same graph, copies among the points included; no walk of the building takes its distances step by step."""
    x = np.round(np.random.default_rng(4).standard_normal((300, 5)), 1)
    x[80:110] = x[79]
    walk, walked = graph._walk, []
    monkeypatch.setattr(graph, "_walk", lambda *given: walked.append(1) or walk(*given))
    made = graph.layered(x, 4, 12, np.random.default_rng(1))
    assert not walked
    monkeypatch.setattr(graph, "KNOWN", 0)
    assert graph.layered(x, 4, 12, np.random.default_rng(1)) == made and walked
    monkeypatch.setattr(graph, "KNOWN", 150)
    assert graph.layered(x, 4, 12, np.random.default_rng(1)) == made


@pytest.mark.parametrize("n", [1, 2, 9, 70])
def test_refined_lists_against_sets(n):
    rng = np.random.default_rng(n)
    x, s, r, rounds = rng.standard_normal((n, 5)), 6, 2, 3
    hashes = rng.permutation(7 * n).reshape(7, n)

    def d(u, v):
        return (((x[u] - x[v]) ** 2).sum(), v)

    order = sorted(range(n), key=lambda v: hashes[0][v])
    lists = {u: {order[(p + step) % n] for step in range(1, s + 1)} - {u} for p, u in enumerate(order)}
    for step in range(rounds):
        ways = {(u, v) for u in lists for v in sorted(lists[u], key=lambda v: hashes[1 + 2 * step][v])[:r]}
        ways |= {(v, u) for u, v in ways}
        held = {u: sorted((v for w, v in ways if w == u), key=lambda v: hashes[2 + 2 * step][v])[: 2 * r] for u in range(n)}
        for own in held.values():
            for a in own:
                lists[a] |= set(own) - {a}
        lists = {u: set(sorted(own, key=lambda v: d(u, v))[:s]) for u, own in lists.items()}
    both = {(u, v) for u in lists for v in lists[u]} | {(v, u) for u in lists for v in lists[u]}
    assert graph._refine(x, hashes, s, r, rounds) == [sorted(v for w, v in both if w == u) for u in range(n)]


def test_values_are_settled_where_rounding_could_decide():
    """Rough values that are off by up to the slack give the same candidates."""
    rng = np.random.default_rng(6)
    x, q, true = rng.standard_normal((500, 3)), rng.standard_normal((40, 3)), rng.integers(0, 60, (40, 500)) / 10
    best = common.Candidates(q, 9)
    for lo in range(0, 500, 70):
        own = slice(lo, min(500, lo + 70))
        for some in common.tiles_of(40, 1 << 15):
            moved = true[some, own] + rng.uniform(-0.3, 0.3, true[some, own].shape)
            best.offer((some, moved, 0.3, lambda row, who, own=own: true[who, own.start + row]), np.arange(500)[own], x[own])
    best.cut()
    who, ids, dist, value = best.kept
    wanted = [sorted(np.lexsort((np.arange(500), true[i]))[:9].tolist()) for i in range(40)]
    assert [sorted(ids[who == i].tolist()) for i in range(40)] == wanted and (value == true[who, ids]).all()
    assert np.allclose(dist, np.sqrt(((x[ids] - q[who]) ** 2).sum(axis=1))) and pa.array(ids).null_count == 0
