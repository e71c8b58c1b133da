"""Proximity graphs, one for each shard of the points: layered, refined, and with shortcuts.

From public literature, in the simplest form. Shards are hash buckets of at most about ``shard`` points, so a graph fits one task; a query walks every
shard's graph and the k best of all shards are the answer. ``layered`` descends from its summit layer by layer. ``refined`` builds its neighbour lists by exchange
among neighbours' neighbours, a shard's pairs in arrays, and then puts layers over them; S and R are read as the length of the lists and the neighbours that
each point offers a round. ``shortcut`` is the layered graph whose points of the upper layers record the points of the first layer nearest to them when it is built: a query walks the
top layer, jumps along the recorded shortcuts past the layers between, and goes on in the base. Both readings are
assumptions of ours, as published descriptions beyond the parameters were not at hand.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import CELLS, Nearest, matrix, squared_distances
from ..operators.exact import NEIGHBOURS, query_blocks, ranked
from ..sources.work import materialise

#: Up to so many points a new one's distances to all before it are taken at once: looking them up is cheaper than taking a few for each step.
KNOWN = 10_000
#: Flags of points that walks have met, for all walks that go in step.
WALKED = 1 << 22
ROWS = "shard int, vec_id long, level int, neighbours array<array<long>>, shortcuts array<long>, embedding array<double>"


@dataclass
class Graph:
    nodes: DataFrame
    kind: str
    n: int
    degree: int
    shards: int

    def bytes(self) -> int:
        return 8 * self.n * self.degree


def _walk(x: np.ndarray, links, q: np.ndarray, entries, ef: int):
    """Best-first search: the ef nearest that were met, nearest first. For one query a list of (squared distance, point); for a matrix of queries, with a row of entries each, see ``_walks``."""
    if q.ndim == 2:
        return _walks(x, links, q, entries, ef)
    seen = set(entries)
    start = [(float(((x[e] - q) ** 2).sum()), e) for e in seen]
    todo = list(start)
    heapq.heapify(todo)
    best = [(-d, e) for d, e in start]
    heapq.heapify(best)
    while len(best) > ef:
        heapq.heappop(best)
    while todo:
        d, at = heapq.heappop(todo)
        if len(best) >= ef and d > -best[0][0]:
            break
        new = [v for v in links[at] if v not in seen]
        if not new:
            continue
        seen.update(new)
        gap = x[new]
        gap -= q
        gap *= gap
        for dist, v in zip(np.add.reduce(gap, axis=1).tolist(), new):
            if len(best) < ef:
                heapq.heappush(todo, (dist, v))
                heapq.heappush(best, (-dist, v))
            elif dist < -best[0][0]:
                heapq.heappush(todo, (dist, v))
                heapq.heapreplace(best, (-dist, v))
    return sorted((-d, e) for d, e in best)


def _walk_known(known: list[float], links: dict[int, list[int]], entries: list[int], ef: int) -> list[tuple[float, int]]:
    """``_walk`` where the squared distances are known."""
    seen = set(entries)
    todo = [(known[e], e) for e in seen]
    best = [(-d, e) for d, e in todo]
    heapq.heapify(todo)
    heapq.heapify(best)
    while len(best) > ef:
        heapq.heappop(best)
    push, replace, pop = heapq.heappush, heapq.heapreplace, heapq.heappop
    last = -best[0][0] if len(best) >= ef else np.inf
    while todo:
        d, at = pop(todo)
        if d > last:
            break
        for v in links[at]:
            if v not in seen:
                seen.add(v)
                dist = known[v]
                if dist < last:
                    push(todo, (dist, v))
                    if len(best) < ef:
                        push(best, (-dist, v))
                        if len(best) == ef:
                            last = -best[0][0]
                    else:
                        replace(best, (-dist, v))
                        last = -best[0][0]
    return sorted((-d, e) for d, e in best)


class Links:
    """The links of all points of a layer, one list after another."""

    def __init__(self, near: list[list[int]]):
        self.start = np.concatenate([[0], np.cumsum([len(v) for v in near])])
        self.to = np.fromiter((v for own in near for v in own), np.int64, self.start[-1])

    def of(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place in ``at``, neighbour) of all neighbours of several points."""
        degree = self.start[at + 1] - self.start[at]
        who = np.repeat(np.arange(len(at)), degree)
        return who, self.to[np.arange(len(who)) + np.repeat(self.start[at] - np.cumsum(degree) + degree, degree)]


def _walks(x: np.ndarray, links: Links, q: np.ndarray, entries: np.ndarray, ef: int) -> tuple[np.ndarray, np.ndarray]:
    """(queries x ef squared distances, points): the walk of every query, a step of all of them at a time; entries below 0 are none, and what was not met is infinitely far.

    What a walk holds is the ef nearest it met; it steps to the nearest of these that it has not left, until it has left them all.
    """
    far, near = np.full((len(q), ef), np.inf), np.full((len(q), ef), -1)
    step = max(1, WALKED // max(1, len(x)))
    for lo in range(0, len(q), step):
        _in_step(x, links, q[lo : lo + step], entries[lo : lo + step], far[lo : lo + step], near[lo : lo + step])
    order = np.lexsort((near, far), axis=1)
    return np.take_along_axis(far, order, axis=1), np.take_along_axis(near, order, axis=1)


def _in_step(x: np.ndarray, links: Links, q: np.ndarray, entries: np.ndarray, far_out: np.ndarray, near_out: np.ndarray) -> None:
    ef, who = far_out.shape[1], np.arange(len(q))
    # of the walks under way: what they hold, and the distances of what they have not left
    far, near, open_ = far_out.copy(), near_out.copy(), far_out.copy()
    seen, worst = np.zeros((len(q), len(x)), bool), np.full(len(q), np.inf)
    row, column = np.nonzero(entries >= 0)
    # by query and point, each once
    row, new = np.divmod(np.unique(row * len(x) + entries[row, column]), len(x))
    while True:
        seen[row, new] = True
        gap = x[new]
        gap -= q[who[row]]
        gap *= gap
        dist = np.add.reduce(gap, axis=1)
        # fewer than ef: infinitely far ones fill up
        some = np.flatnonzero(dist < worst[row])
        row, new, dist = row[some], new[some], dist[some]
        if len(row):
            got = np.unique(row)
            place, own = np.arange(len(row)) - np.searchsorted(row, row), np.searchsorted(got, row)
            width = int(place.max()) + 1
            more, names = np.full((len(got), width), np.inf), np.full((len(got), width), -1)
            more[own, place], names[own, place] = dist, new
            if width > 1:
                order = np.argsort(more, axis=1)[:, :ef]
                more, names = np.take_along_axis(more, order, axis=1), np.take_along_axis(names, order, axis=1)
                width = more.shape[1]
            # the nearest new one takes the place of the farthest held, the next that of the next, while it is nearer
            held = far[got]
            last = held.argmax(axis=1)[:, None] if width == 1 else np.argpartition(held, ef - width, axis=1)[:, ef - width :]
            value = np.take_along_axis(held, last, axis=1)
            if width > 1:
                order = np.argsort(-value, axis=1)
                value, last = np.take_along_axis(value, order, axis=1), np.take_along_axis(last, order, axis=1)
            i, j = np.nonzero(more < value)
            to = got[i], last[i, j]
            far[to] = open_[to] = more[i, j]
            near[to] = names[i, j]
            worst[got] = far[got].max(axis=1)
        at = open_.argmin(axis=1)
        every = np.arange(len(who))
        going = np.isfinite(open_[every, at])
        if not going.all():
            if not going.any():
                far_out[who], near_out[who] = far, near
                return
            if 4 * going.sum() <= 3 * len(who):
                far_out[who[~going]], near_out[who[~going]] = far[~going], near[~going]
                who, far, near, open_, seen, worst, at = who[going], far[going], near[going], open_[going], seen[going], worst[going], at[going]
                every, going = np.arange(len(who)), np.ones(len(who), bool)
        active = every[going]
        open_[active, at[going]] = np.inf
        row, new = links.of(near[active, at[going]])
        row = active[row]
        unmet = ~seen[row, new]
        row, new = row[unmet], new[unmet]


def _met(links: dict[int, list[int]], at: int) -> np.ndarray:
    """Which points can be reached from one."""
    seen, todo = np.zeros(len(links), bool), [at]
    seen[at] = True
    while todo:
        near = np.unique([v for u in todo for v in links[u]]).astype(int)
        todo = near[~seen[near]].tolist()
        seen[todo] = True
    return seen


class Reach:
    """What a walk meets that keeps every point: all that its entries reach. Points that reach each other share a mask."""

    def __init__(self, links: dict[int, list[int]]):
        self.links, self.back = links, {i: [] for i in links}
        for i, near in links.items():
            for v in near:
                self.back[v].append(i)
        self.own, self.masks = np.full(len(links), -1), []

    def of(self, at: int) -> int:
        """The number of the entry's mask."""
        if self.own[at] < 0:
            to = _met(self.links, at)
            self.own[to & _met(self.back, at)] = len(self.masks)
            self.masks.append(to)
        return int(self.own[at])


def _pruned(x: np.ndarray, at: int, near: list[tuple[float, int]], m: int) -> list[int]:
    """The relative-neighbour rule: a candidate stays if it is nearer to the point than to any that stayed."""
    kept: list[int] = []
    own = x[[v for _, v in near]]
    least = np.full(len(near), np.inf)  # of each candidate to those that stayed
    for i, (d, v) in enumerate(near):
        if v != at and d < least[i]:
            kept.append(v)
            if len(kept) >= m:
                break
            gap = own[i + 1 :] - own[i]
            gap *= gap
            np.minimum(least[i + 1 :], np.add.reduce(gap, axis=1), out=least[i + 1 :])
    for _, v in near:
        if len(kept) >= m:
            break
        if v != at and v not in kept:
            kept.append(v)
    return kept


def layered(x: np.ndarray, m: int, ef: int, rng: np.random.Generator) -> tuple[list[int], list[dict[int, list[int]]]]:
    """Level of every point, and for each level its links."""
    levels = np.minimum((-np.log(rng.uniform(1e-12, 1, len(x))) / np.log(m)).astype(int), 8).tolist()
    links: list[dict[int, list[int]]] = [{} for _ in range(max(levels, default=0) + 1)]
    top = entry = -1
    room = np.empty(x[:KNOWN].shape)
    for i in range(len(x)):
        at = [entry] if entry >= 0 else []
        if i < KNOWN:
            gap = np.subtract(x[:i], x[i], out=room[:i])
            gap *= gap
            known = np.add.reduce(gap, axis=1).tolist()
        for level in range(top, levels[i], -1):
            at = [(_walk_known(known, links[level], at, 1) if i < KNOWN else _walk(x, links[level], x[i], at, 1))[0][1]]
        for level in range(min(top, levels[i]), -1, -1):
            near = _walk_known(known, links[level], at, ef) if i < KNOWN else _walk(x, links[level], x[i], at, ef)
            own = links[level][i] = _pruned(x, i, near, m)
            for v in own:
                back = links[level][v]
                back.append(i)
                if len(back) > 2 * m:
                    far = ((x[back] - x[v]) ** 2).sum(axis=1)
                    links[level][v] = _pruned(x, v, sorted(zip(far.tolist(), back)), m)
            at = [v for _, v in near]
        for level in range(top + 1, levels[i] + 1):
            links[level][i] = []
        if levels[i] > top:
            top, entry = levels[i], i
    return levels, links


def _sharded(base: DataFrame, shard: int) -> tuple[DataFrame, int]:
    """The points with their shard, and the number of shards."""
    shards = max(1, -(-base.count() // shard))
    return base.select(F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int").alias("shard"), F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding")), shards


def _by_shard(rows: DataFrame, shards: int):
    """Grouped so that each shard has a task of its own."""
    return rows.repartitionById(shards, "shard").groupBy("shard")


def _rows(rows: pa.Table, ids: np.ndarray, levels: list[int], links: list[dict[int, list[int]]], jumps: dict[int, list[int]]) -> pa.Table:
    named = [[[int(ids[v]) for v in links[level].get(i, ())] for level in range(levels[i] + 1)] for i in range(len(ids))]
    jumped = [[int(ids[v]) for v in jumps.get(i, ())] for i in range(len(ids))]
    return pa.table({"shard": rows.column("shard"), "vec_id": rows.column("vec_id"), "level": pa.array(levels, pa.int32()), "neighbours": pa.array(named, pa.list_(pa.list_(pa.int64()))), "shortcuts": pa.array(jumped, pa.list_(pa.int64())), "embedding": rows.column("embedding")})


def build(base: DataFrame, m: int = 12, ef_build: int = 60, shard: int = 5_000, kind: str = "layered", seed: int = 23) -> Graph:
    def one(rows):
        rows = rows.sort_by("vec_id")
        x, ids = matrix(rows.column("embedding")), rows.column("vec_id").to_numpy()
        levels, links = layered(x, m, ef_build, np.random.default_rng(seed))
        upper = [i for i, level in enumerate(levels) if level == len(links) - 1] if kind == "shortcut" and len(links) > 2 else []
        jumps = {i: [v for _, v in _walk(x, links[1], x[i], [i], m)] for i in upper}
        return _rows(rows, ids, levels, links, jumps)

    points, shards = _sharded(base, shard)
    nodes = materialise(_by_shard(points, shards).applyInArrow(one, ROWS), "graph")
    return Graph(nodes, kind, nodes.count(), 2 * m, shards)


def build_shortcut(base: DataFrame, m: int = 16, ef_build: int = 40, shard: int = 5_000) -> Graph:
    return build(base, m, ef_build, shard, "shortcut")


def build_refined(base: DataFrame, s: int = 12, r: int = 4, rounds: int = 4, shard: int = 5_000, seed: int = 23) -> Graph:
    """Neighbour lists of length s from random ones, improved over rounds, each shard in its task; r neighbours are offered on each side."""
    points, shards = _sharded(base, shard)
    # seeded orders of the points: of the first lists, and of each round's offers and of those that meet
    seeds = [seed, *[step + more for step in range(rounds) for more in (0, 100)]]
    hashed = points.select("*", F.array(*[F.xxhash64(F.lit(v), "vec_id") for v in seeds]).alias("hashes"))
    nodes = materialise(_by_shard(hashed, shards).applyInArrow(_refined(s, r, rounds, seed), ROWS), "refined")
    return Graph(nodes, "refined", nodes.count(), 2 * s, shards)


def _first(u: np.ndarray, order: tuple[np.ndarray, ...], most: int) -> np.ndarray:
    """Which pairs are among the ``most`` first of their u, in the order of the keys (the last counts most)."""
    at = np.lexsort((*order, u))
    own = u[at]
    return np.sort(at[np.arange(len(at)) - np.searchsorted(own, own) < most])


def _refine(x: np.ndarray, hashes: np.ndarray, s: int, r: int, rounds: int) -> list[list[int]]:
    """One shard's lists, both ways. ``hashes`` has a row for the first lists, then two for each round."""
    n, across = len(x), np.ascontiguousarray(x.T)

    def distinct(u, v):
        return np.divmod(np.unique(np.concatenate(u) * n + np.concatenate(v)), n)

    def squared(u, v):
        total = np.zeros(len(u))
        for line in across:
            gap = line[u] - line[v]
            total += gap * gap
        return total

    # the first lists: the next s points in a seeded order
    order = np.argsort(hashes[0], kind="stable")
    u, v = distinct([np.repeat(order, s)], [order[(np.arange(n)[:, None] + np.arange(1, s + 1)) % n].ravel()])
    u, v = u[u != v], v[u != v]
    d = squared(u, v)
    for step in range(rounds):
        offer, cap = hashes[1 + 2 * step], hashes[2 + 2 * step]
        some = _first(u, (offer[v],), r)
        a, b = distinct([u[some], v[some]], [v[some], u[some]])
        some = _first(a, (cap[b],), 2 * r)
        # points with a neighbour in common meet; each offers a bounded number
        a, b = a[some], b[some]
        start, degree = np.searchsorted(a, a), np.bincount(a, minlength=n)[a]
        left = np.repeat(b, degree)
        right = b[np.arange(len(left)) + np.repeat(start - np.cumsum(degree) + degree, degree)]
        fresh = np.setdiff1d((left * n + right)[left != right], u * n + v)
        u, v, d = np.concatenate([u, fresh // n]), np.concatenate([v, fresh % n]), np.concatenate([d, squared(fresh // n, fresh % n)])
        some = _first(u, (v, d), s)
        u, v, d = u[some], v[some], d[some]
    u, v = distinct([u, v], [v, u])
    return [own.tolist() for own in np.split(v, np.searchsorted(u, np.arange(1, n)))]


def _refined(s: int, r: int, rounds: int, seed: int):
    """Refines one shard's lists and puts layers over them: each has about one point in s of the one below, linked to its s nearest there, pruned, and back."""

    def one(rows):
        rows = rows.sort_by("vec_id")
        x, ids = matrix(rows.column("embedding")), rows.column("vec_id").to_numpy()
        levels = np.minimum((-np.log(np.random.default_rng(seed).uniform(1e-12, 1, len(x))) / np.log(max(2, s))).astype(int), 8)
        hashes = rows.column("hashes").combine_chunks().flatten().to_numpy().reshape(len(x), -1).T
        links = [dict(enumerate(_refine(x, hashes, s, r, rounds)))]
        for level in range(1, int(levels.max(initial=0)) + 1):
            own = np.flatnonzero(levels >= level)
            far = squared_distances(x[own], x[own])
            held: dict[int, list[int]] = {int(i): [] for i in own}
            for k, i in enumerate(own.tolist()):
                near = [(float(far[k, j]), int(own[j])) for j in np.argsort(far[k], kind="stable")[: 2 * s + 1]]
                for v in _pruned(x, i, near, s):
                    held[i].append(v)
                    held[v].append(i)
            links.append({i: sorted(set(v)) for i, v in held.items()})
        return _rows(rows, ids, levels.tolist(), links, {})

    return one


def query(graph: Graph, queries: DataFrame, k: int = 10, ef: int = 100) -> DataFrame:
    """(qid, rank, vec_id, dist)."""
    out = graph.nodes.sparkSession.createDataFrame([], NEIGHBOURS)
    for qids, q in query_blocks(queries):
        shared = graph.nodes.sparkSession.sparkContext.broadcast((qids, q))
        out = out.unionByName(_by_shard(graph.nodes, graph.shards).applyInArrow(_answer(shared, graph.kind, k, ef), NEIGHBOURS))
    return ranked(out, k)


def _three_nearest(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """For each query the places of the three nearest rows, or of all if they are fewer."""
    far = np.stack([((q - row) ** 2).sum(axis=1) for row in x], axis=1)
    return np.argsort(far, axis=1, kind="stable")[:, :3]


def _answer(shared, kind: str, k: int, ef: int):
    """Walks one shard's graph for every query."""

    def one(rows):
        qids, q = shared.value
        rows = rows.sort_by("vec_id")
        x, ids = matrix(rows.column("embedding")), rows.column("vec_id").to_numpy()
        level = rows.column("level").to_numpy()
        named = rows.column("neighbours").to_pylist()
        top = int(level.max())
        links = [{i: np.searchsorted(ids, near[l]).tolist() for i, near in enumerate(named) if l < len(near)} for l in range(top + 1)]
        summit = int(np.flatnonzero(level == top)[0])
        jumps = {i: np.searchsorted(ids, near).tolist() for i, near in enumerate(rows.column("shortcuts").to_pylist()) if near}
        # lists that were refined apart from the layers may fall into parts: some points of the base help in
        spread = np.linspace(0, len(x) - 1, min(len(x), 16)).astype(int)
        layers = [Links([near.get(i, []) for i in range(len(x))]) for near in links]
        at = np.full((len(q), 1), summit)
        if kind == "shortcut" and jumps:
            at = _walk(x, layers[top], q, at, 1)[1]
            helped = np.full((len(q), 3), -1)
            for point in np.unique(at):
                near, own = np.array(jumps[int(point)]), np.flatnonzero(at[:, 0] == point)
                helped[own, : len(near)] = near[_three_nearest(x[near], q[own])]
            at = np.hstack([at, helped])
        else:
            for l in range(top, 0, -1):
                at = _walk(x, layers[l], q, at, 1)[1]
        if kind == "refined":
            helped = spread[_three_nearest(x[spread], q)]
            at = np.hstack([at, helped])
        parts = [pa.record_batch({"qid": pa.array([], pa.int64()), "vec_id": pa.array([], pa.int64()), "dist": pa.array([], pa.float64())})]
        # such a walk leaves out no point that it can reach, so these are measured for all queries together
        reach, alike = Reach(links[0]) if max(ef, k) >= len(x) else None, {}
        if reach:
            for number, own in enumerate(at.tolist()):
                alike.setdefault(frozenset(reach.of(v) for v in own if v >= 0), []).append(number)
        else:
            step = max(1, WALKED // len(x))
            for lo in range(0, len(q), step):
                far, near = (met[:, :k] for met in _walk(x, layers[0], q[lo : lo + step], at[lo : lo + step], max(ef, k)))
                row, column = np.nonzero(near >= 0)
                parts.append(pa.record_batch({"qid": qids[lo + row], "vec_id": ids[near[row, column]], "dist": np.sqrt(far[row, column])}))
        for masks, own in alike.items():
            near, met = Nearest(q[own], k), np.flatnonzero(np.any([reach.masks[m] for m in masks], axis=0))
            step = max(1, CELLS // len(own))
            for lo in range(0, len(met), step):
                some = met[lo : lo + step]
                near.offer_all(ids[some], x[some])
            parts.append(near.batch(qids[own]))
        return pa.Table.from_batches(parts)

    return one
