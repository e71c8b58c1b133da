"""Two-codebook inverted index with an optimised rotation and product-quantised residuals.

From public literature: the rotation and the codebooks are learned in turn (orthogonal Procrustes), points are filed by the nearest centroid of
each half and keep a byte per residual piece; a query takes cells in order of distance until beta * n points are in,
ranks them by lookup tables and re-ranks the best exactly.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.arrays import Rough, lists, matrix
from ..operators.activation import by_heap, centroid_lists
from ..operators.kmeans import assign
from ..sources.work import materialise
from .common import Tile, Tiled, lloyd, rerank_scan, sample_of, tiles_of


@dataclass
class TwoCodebooks:
    rotation: np.ndarray
    coarse: list[np.ndarray]
    fine: list[np.ndarray]
    counts: np.ndarray
    points: DataFrame
    n: int

    def bytes(self) -> int:
        return self.n * (8 + len(self.fine)) + 8 * (self.rotation.size + sum(b.size for b in self.coarse + self.fine) + self.counts.size)


def _halves(x: np.ndarray) -> list[np.ndarray]:
    return [x[:, : x.shape[1] // 2], x[:, x.shape[1] // 2 :]]


def _pieces(x: np.ndarray, m: int) -> list[np.ndarray]:
    return np.array_split(x, m, axis=1)


def build(base: DataFrame, cells: int = 256, pieces: int = 8, codes: int = 16, rounds: int = 4, seed: int = 23) -> TwoCodebooks:
    rng = np.random.default_rng(seed)
    x = sample_of(base)
    side = int(np.sqrt(cells))
    rotation = np.linalg.qr(rng.standard_normal((x.shape[1],) * 2))[0]
    for _ in range(rounds):
        y = x @ rotation
        coarse = [lloyd(h, side, 4, rng) for h in _halves(y)]
        near = np.hstack([c[assign(h, c)] for h, c in zip(_halves(y), coarse)])
        u, _, vt = np.linalg.svd(x.T @ near)
        rotation = u @ vt
    y = x @ rotation
    coarse = [lloyd(h, side, 8, rng) for h in _halves(y)]
    residual = y - np.hstack([c[assign(h, c)] for h, c in zip(_halves(y), coarse)])
    fine = [lloyd(p, codes, 8, rng) for p in _pieces(residual, pieces)]
    shared = base.sparkSession.sparkContext.broadcast((rotation, coarse, fine))

    def encode(batches):
        rotation, coarse, fine = shared.value
        for batch in batches:
            if batch.num_rows:
                y = matrix(batch.column("embedding")) @ rotation
                label = [assign(h, c) for h, c in zip(_halves(y), coarse)]
                residual = y - np.hstack([c[v] for c, v in zip(coarse, label)])
                bytes_ = np.stack([assign(p, f) for p, f in zip(_pieces(residual, len(fine)), fine)], axis=1)
                yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array((label[0] * len(coarse[1]) + label[1]).astype(np.int32)), lists(bytes_.astype(np.int8)), batch.column("embedding")], names=["vec_id", "cell", "code", "embedding"])

    points = materialise(base.select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).mapInArrow(encode, "vec_id long, cell int, code array<tinyint>, embedding array<double>"), "two-codebooks")
    counts = np.zeros((side, side), np.int64)
    for cell, n in points.groupBy("cell").count().collect():  # at most ``cells`` rows
        counts[cell // side, cell % side] = n
    return TwoCodebooks(rotation, coarse, fine, counts, points, int(counts.sum()))


class Looked(Tiled):
    """Tiles of a block of queries: their squared distances to what the codes say of the points in the cells that they take."""

    def __init__(self, index: TwoCodebooks, y: np.ndarray, taken: np.ndarray):
        self.coarse, self.fine, self.side, self.y, self.taken = index.coarse, index.fine, index.counts.shape[1], y, taken

    def tiles(self, batch: pa.RecordBatch) -> Iterator[Tile]:
        cell, code = batch.column("cell").to_numpy(), matrix(batch.column("code")).astype(np.int64)
        shown = np.hstack([self.coarse[0][cell // self.side], self.coarse[1][cell % self.side]])
        shown += np.hstack([book[own] for book, own in zip(self.fine, code.T)])
        rough = Rough(shown)

        def values(row, who):
            gap = shown[row]
            gap -= self.y[who]
            return np.multiply(gap, gap, out=gap).sum(axis=1)

        for some in tiles_of(len(self.y), len(cell)):
            value, slack = rough(self.y[some])
            value[~self.taken[some][:, cell]] = np.inf
            yield some, value, slack, values


def _taken(spark: SparkSession, index: TwoCodebooks, y: np.ndarray, beta: float) -> np.ndarray:
    """Queries x cells: which cells each rotated query takes. Every query walks its cells once, in tasks."""
    coarse, counts, want = index.coarse, index.counts, beta * index.n

    def walk(batches):
        for batch in batches:
            flags = np.zeros((batch.num_rows, counts.size), bool)
            halves = _halves(matrix(batch.column("y"))) if batch.num_rows else []
            for i in range(batch.num_rows):
                (order1, d1), (order2, d2) = [centroid_lists(c, h[i], "l2sq") for c, h in zip(coarse, halves)]
                got = by_heap(d1, d2, counts[np.ix_(order1, order2)], want)
                flags[i, order1[got.pos1] * counts.shape[1] + order2[got.pos2]] = True
            yield pa.RecordBatch.from_arrays([batch.column("i"), pa.array([np.packbits(f).tobytes() for f in flags], pa.binary())], names=["i", "bits"])

    asked = spark.createDataFrame(pa.table({"i": np.arange(len(y)), "y": lists(y)})).repartition(min(len(y), spark.sparkContext.defaultParallelism))
    got = asked.mapInArrow(walk, "i long, bits binary").toArrow().sort_by("i")
    return np.unpackbits(np.frombuffer(b"".join(got.column("bits").to_pylist()), np.uint8).reshape(len(y), -1), axis=1)[:, : counts.size].astype(bool)


def query(index: TwoCodebooks, queries: DataFrame, k: int = 10, beta: float = 0.1, keep: int | None = None) -> DataFrame:
    """(qid, rank, vec_id, dist)."""

    def look(q):
        y = q @ index.rotation
        return Looked(index, y, _taken(index.points.sparkSession, index, y, beta))

    return rerank_scan(index.points, ["cell", "code"], queries, k, keep or 8 * k, None, look, 8 * index.rotation.size // len(index.rotation) + index.counts.size)
