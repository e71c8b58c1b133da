"""Projection hashing with breakpoint-encoded symbols, a tree over the symbols, and a widening range.

From public literature: L sets of K Gaussian projections; each projection is cut at quantiles of a sample into at most 256 symbols. For each set a tree splits the symbols
in two, at the median of the dimension that spreads most, until a leaf has its share of the sample; a leaf is a box of symbols. A query descends the trees: only points in leaves
whose box comes within the range are looked at, and their symbols bound the projected distance from below. Ranges widen by the factor c until beta * n + k points lie within
in some set, and those are measured exactly. The trees have at most ``LEAVES`` leaves each, whatever n, so they are broadcast; points carry the numbers of their leaves.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import lists, matrix, places
from ..operators.exact import NEIGHBOURS, query_blocks, ranked
from ..sources.work import materialise
from .common import Tiled, measure_all, sample_of

LEVELS = 24
LEAVES = 256


@dataclass
class Tree:
    """Inner nodes (dimension, first symbol of the right side, children; a child below 0 is leaf -1 - child) and the leaves' boxes of symbols."""

    dim: list[int] = field(default_factory=list)
    cut: list[int] = field(default_factory=list)
    child: list[list[int]] = field(default_factory=list)
    low: list[np.ndarray] = field(default_factory=list)
    high: list[np.ndarray] = field(default_factory=list)

    @classmethod
    def grow(cls, symbols: np.ndarray, top: int, leaves: int = LEAVES) -> Tree:
        tree, share = cls(), max(1, -(-len(symbols) // leaves))

        def split(rows: np.ndarray, low: np.ndarray, high: np.ndarray) -> int:
            own = symbols[rows]
            spread = own.max(axis=0) - own.min(axis=0) if len(rows) else np.zeros(symbols.shape[1])
            if len(rows) <= share or not spread.max():
                tree.low.append(low), tree.high.append(high)
                return -len(tree.low)
            dim = int(spread.argmax())
            cut = int(np.clip(np.median(own[:, dim]), own[:, dim].min() + 1, own[:, dim].max()))
            node = len(tree.dim)
            tree.dim.append(dim), tree.cut.append(cut), tree.child.append([0, 0])
            right = own[:, dim] >= cut
            low_right, high_left = low.copy(), high.copy()
            low_right[dim], high_left[dim] = cut, cut - 1
            tree.child[node] = [split(rows[~right], low, high_left), split(rows[right], low_right, high)]
            return node

        split(np.arange(len(symbols)), np.zeros(symbols.shape[1], int), np.full(symbols.shape[1], top))
        return tree

    def leaf_of(self, symbols: np.ndarray) -> np.ndarray:
        """The leaf of each row, all rows in step."""
        at = np.full(len(symbols), 0 if self.dim else -1)
        dim, cut, child = np.array(self.dim, int), np.array(self.cut, int), np.array(self.child, int).reshape(-1, 2)
        while (inner := np.flatnonzero(at >= 0)).size:
            node = at[inner]
            at[inner] = child[node, (symbols[inner, dim[node]] >= cut[node]).astype(int)]
        return -1 - at


@dataclass
class ProjectionHash:
    directions: np.ndarray  # L x d x K
    breaks: np.ndarray  # L x K x symbols - 1
    trees: list[Tree]
    points: DataFrame | None
    n: int

    def bytes(self) -> int:
        trees = sum(3 * len(t.dim) + 2 * len(t.low) * self.directions.shape[2] for t in self.trees)
        return self.n * (8 + self.directions.shape[0] * (2 + self.directions.shape[2])) + 8 * (self.directions.size + self.breaks.size + trees)

    def places_of(self, q: np.ndarray) -> np.ndarray:
        """Where the queries lie: queries x sets x projections; the same, to the last bit, whichever queries come together."""
        return np.stack([[v @ d for d in self.directions] for v in q])

    def _gaps(self, place: np.ndarray, t: int, c: int | np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """How far symbols of a projection lie from places on it."""
        below, above = self._ends[0][t, c, symbol], self._ends[1][t, c, symbol]
        return np.maximum(0, np.maximum(below - place, place - above))

    @cached_property
    def _ends(self) -> tuple[np.ndarray, np.ndarray]:
        """Least and greatest place of every symbol: sets x projections x symbols."""
        open_ = np.full((*self.breaks.shape[:2], 1), np.inf)
        return np.concatenate([-open_, self.breaks], axis=2), np.concatenate([self.breaks, open_], axis=2)

    def leaves_near(self, at: np.ndarray, radius: np.ndarray) -> list[np.ndarray]:
        """For each set leaves x queries: which leaves' boxes come within the queries' radii."""
        out = []
        for t, tree in enumerate(self.trees):
            low, high, total = np.array(tree.low), np.array(tree.high), 0.0
            for c in range(at.shape[2]):
                # a box's range of symbols is one long symbol
                gap = np.maximum(0, np.maximum(self._ends[0][t, c, low[:, c], None] - at[:, t, c], at[:, t, c] - self._ends[1][t, c, high[:, c], None]))
                total = total + gap * gap
            # a box is never farther than a point in it, however the sums are rounded
            out.append(total * (1 - 1e-12) <= radius * radius)
        return out

    def pair_bounds(self, symbols: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Least possible projected distance of each point (row) to the query of the same row, the smallest over the sets."""
        best, width = np.full(len(symbols), np.inf), self.directions.shape[2]
        for t in range(len(self.directions)):
            gap = self._gaps(at[:, t], t, np.arange(width), symbols[:, t * width : (t + 1) * width])
            np.minimum(best, (gap * gap).sum(axis=1), out=best)
        return np.sqrt(best)

    def lower_bounds(self, symbols: np.ndarray, q: np.ndarray) -> np.ndarray:
        """Least possible projected distance of every point to q."""
        return self.pair_bounds(symbols, np.broadcast_to(self.places_of(q[None]), (len(symbols), *self.directions.shape[::2])))

    def bounds_within(self, batch: pa.RecordBatch, q: np.ndarray, radius: float) -> np.ndarray:
        """Lower bounds of the points in leaves that come within the radius; infinite for all others, whose symbols are not looked at."""
        leaf = matrix(batch.column("leaves")).astype(np.int64)
        some = np.flatnonzero(np.any([near[leaf[:, t], 0] for t, near in enumerate(self.leaves_near(self.places_of(q[None]), np.array([radius])))], axis=0))
        out = np.full(batch.num_rows, np.inf)
        if len(some):
            out[some] = self.lower_bounds(matrix(batch.column("symbols").take(pa.array(some))).astype(np.int64), q)
        return out

    def rough_bounds(self, symbols: np.ndarray, at: np.ndarray, kind: type) -> np.ndarray:
        """Points x queries: squares of the lower bounds, summed in the given precision from tables of the projections' gaps. ``symbols`` has a row for each projection."""
        best, width, rows = None, at.shape[2], symbols.shape[1]
        buffer = np.empty((STRIPE, len(at)), kind)
        for t in range(at.shape[1]):
            total = np.zeros((rows, len(at)), kind)
            for c in range(width):
                gap = np.maximum(self._ends[0][t, c, :, None] - at[:, t, c], at[:, t, c] - self._ends[1][t, c, :, None])
                np.maximum(0, gap, out=gap)
                table = np.multiply(gap, gap, out=gap).astype(kind)
                for lo in range(0, rows, STRIPE):
                    own = symbols[t * width + c, lo : lo + STRIPE]
                    total[lo : lo + STRIPE] += np.take(table, own, axis=0, out=buffer[: len(own)], mode="clip")
            best = total if best is None else np.minimum(best, total, out=best)
        return best


#: Queries whose tables of one projection stay in a core's cache, and rows that are looked up in them at a time.
TILE, STRIPE = 128, 1024
#: By what share sums in single precision may be off, or more.
SLACK = 1e-5


class Looked(Tiled):
    """Bounds of a batch's points to a block of queries, tile by tile; pairs where rounding could decide are settled one by one."""

    def __init__(self, index: ProjectionHash, q: np.ndarray, radius: np.ndarray | None = None):
        self.index, self.places, self.radius = index, index.places_of(q), radius
        most = float(np.abs(self.places).max(initial=0) + np.abs(index.breaks).max(initial=0))
        self.kind = np.float32 if 1e-10 < most < 1e15 else np.float64

    def _edges(self, edges: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Below and above what rounding may do to squares."""
        return (edges * edges * (1 - SLACK) - 1e-30).astype(self.kind), (edges * edges * (1 + SLACK) + 1e-30).astype(self.kind)

    def counts(self, batch: pa.RecordBatch, edges: np.ndarray) -> np.ndarray:
        """Queries x (edges + 1): how many points have a bound up to the first of the ascending edges, up to the next, and so on."""
        symbols = _by_projection(batch)
        total, (low, high) = np.zeros((len(self.places), len(edges) + 1), np.int64), self._edges(edges)
        for lo in range(0, len(total), TILE):
            own = self.places[lo : lo + TILE]
            square = self.index.rough_bounds(symbols, own, self.kind)
            place = np.searchsorted(high, square.ravel(), "left").reshape(square.shape)
            row, i = np.divmod(places(place != np.searchsorted(low, square.ravel(), "left").reshape(square.shape)), len(own))
            place[row, i] = np.searchsorted(edges, self.index.pair_bounds(symbols.T[row], own[i]), "left")
            place += np.arange(len(own)) * total.shape[1]
            total[lo : lo + TILE] = np.bincount(place.ravel(), minlength=len(own) * total.shape[1]).reshape(len(own), -1)
        return total

    def flags(self, batch: pa.RecordBatch) -> Iterator[tuple[slice, np.ndarray]]:
        """Points within the queries' ranges. Those in leaves that no range of a tile's queries touches are passed over."""
        symbols, leaf = _by_projection(batch), matrix(batch.column("leaves")).astype(np.int64)
        for lo in range(0, len(self.places), TILE):
            some = slice(lo, min(len(self.places), lo + TILE))
            own, radius = self.places[some], self.radius[some]
            touched = np.any([near.any(axis=1)[leaf[:, t]] for t, near in enumerate(self.index.leaves_near(own, radius))], axis=0)
            rows, mask = np.flatnonzero(touched), np.zeros((batch.num_rows, len(own)), bool)
            if len(rows):
                looked = symbols if len(rows) == batch.num_rows else np.ascontiguousarray(symbols[:, rows])
                square, (low, high) = self.index.rough_bounds(looked, own, self.kind), self._edges(radius)
                inside = square <= low
                row, i = np.divmod(places(inside != (square <= high)), len(own))
                inside[row, i] = self.index.pair_bounds(looked.T[row], own[i]) <= radius[i]
                mask[rows] = inside
            yield some, mask


def _by_projection(batch: pa.RecordBatch) -> np.ndarray:
    """The points' symbols, a row for each projection."""
    return np.ascontiguousarray(matrix(batch.column("symbols")).T.astype(np.intp))


def build(base: DataFrame, sets: int = 4, projections: int = 16, symbols: int = 256, seed: int = 23) -> ProjectionHash:
    x = sample_of(base)
    directions = np.random.default_rng(seed).standard_normal((sets, x.shape[1], projections))
    quantiles = np.arange(1, symbols) / symbols
    breaks = np.stack([np.quantile(x @ d, quantiles, axis=0).T for d in directions])

    def symbols_of(x, directions, breaks, t):
        return np.stack([np.searchsorted(breaks[t, c], x @ directions[t][:, c], "left") for c in range(directions.shape[2])], axis=1)

    trees = [Tree.grow(symbols_of(x, directions, breaks, t), symbols - 1) for t in range(sets)]
    shared = base.sparkSession.sparkContext.broadcast((directions, breaks, trees))

    def encode(batches):
        directions, breaks, trees = shared.value
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column("embedding"))
                own = [symbols_of(x, directions, breaks, t) for t in range(len(directions))]
                leaves = np.stack([tree.leaf_of(s) for tree, s in zip(trees, own)], axis=1)
                yield pa.RecordBatch.from_arrays([batch.column("vec_id"), lists(np.hstack(own).astype(np.int16)), lists(leaves.astype(np.int16)), batch.column("embedding")], names=["vec_id", "symbols", "leaves", "embedding"])

    schema = "vec_id long, symbols array<smallint>, leaves array<smallint>, embedding array<double>"
    points = materialise(base.select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).mapInArrow(encode, schema), "projection-hash")
    return ProjectionHash(directions, breaks, trees, points, points.count())


def query(index: ProjectionHash, queries: DataFrame, k: int = 10, beta: float = 0.1, c: float = 1.5) -> DataFrame:
    """(qid, rank, vec_id, dist)."""
    n = index.n
    bare = ProjectionHash(index.directions, index.breaks, index.trees, None, n)
    # the widest range holds everything; each narrower one is c times less
    widest = float(np.abs(index.breaks).max()) * 4 * np.sqrt(index.directions.shape[2]) + 1e-9
    radii = np.concatenate([[0.0], widest / c ** np.arange(LEVELS - 1, -1, -1)])
    want, out = min(n, beta * n + k), index.points.sparkSession.createDataFrame([], NEIGHBOURS)
    for qids, q in query_blocks(queries, max(8 * (LEVELS + 2), 8 * index.directions.shape[0] * index.directions.shape[2])):
        shared = index.points.sparkSession.sparkContext.broadcast(Looked(bare, q))

        def count(batches, shared=shared):
            held = shared.value
            total = np.zeros((len(held.places), len(radii) + 1), np.int64)
            for batch in batches:
                if batch.num_rows:
                    total += held.counts(batch, radii)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(total.size)), pa.array(total.ravel())], names=["at", "n"])

        # points within every range, from one scan
        got = index.points.select("symbols").mapInArrow(count, "at long, n long").groupBy("at").agg(F.sum("n").alias("n")).toArrow()
        total = np.zeros(len(q) * (len(radii) + 1), np.int64)
        total[got.column("at").to_numpy()] = got.column("n").to_numpy()
        enough = np.cumsum(total.reshape(len(q), -1), axis=1)[:, : len(radii)] >= want
        radius = np.where(enough.any(axis=1), radii[enough.argmax(axis=1)], radii[-1])
        out = out.unionByName(measure_all(index.points, ["symbols", "leaves"], qids, q, k, Looked(bare, q, radius)))
    return ranked(out, k)
