"""Inverted lists with few-bit codes and an unbiased estimate of the inner product.

From public literature: points are filed under the nearest of K centroids; the residual is scaled to length 1, rotated at random and rounded to B bits a dimension.
Kept beside the code are the residual's length and the code's product with it; the estimated product with a query is the code's product with the
query over that. Points of the nearest ``probe`` lists whose estimate less its error bound is best are measured exactly.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import lists, matrix
from ..operators.kmeans import assign
from ..sources.work import materialise
from .common import Tile, Tiled, lloyd, rerank_scan, sample_of, tiles_of


@dataclass
class BitLists:
    centres: np.ndarray
    rotation: np.ndarray
    bits: int
    points: DataFrame
    n: int

    def bytes(self) -> int:
        return self.n * (8 + 16 + self.centres.shape[1] * self.bits // 8) + 8 * (self.centres.size + self.rotation.size)


def build(base: DataFrame, lists_: int = 64, bits: int = 3, seed: int = 23) -> BitLists:
    rng = np.random.default_rng(seed)
    x = sample_of(base)
    centres = lloyd(x, min(lists_, len(x)), 10, rng)
    rotation = np.linalg.qr(rng.standard_normal((x.shape[1],) * 2))[0]
    top = (1 << bits) - 1
    shared = base.sparkSession.sparkContext.broadcast((centres, rotation))

    def encode(batches):
        centres, rotation = shared.value
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column("embedding"))
                label = assign(x, centres)
                residual = (x - centres[label]) @ rotation
                length = np.sqrt((residual**2).sum(axis=1))
                unit = residual / np.maximum(length, 1e-12)[:, None]
                step = np.maximum(np.abs(unit).max(axis=1, keepdims=True), 1e-12) * 2 / (top + 1)
                code = np.clip(np.floor(unit / step) + (top + 1) / 2, 0, top)
                shown = code - top / 2
                own = (shown * unit).sum(axis=1)
                yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(label.astype(np.int32)), lists(code.astype(np.int8)), pa.array(length), pa.array(own), batch.column("embedding")], names=["vec_id", "list", "code", "length", "own", "embedding"])

    schema = "vec_id long, list int, code array<tinyint>, length double, own double, embedding array<double>"
    points = materialise(base.select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).mapInArrow(encode, schema), "bit-lists")
    return BitLists(centres, rotation, bits, points, points.count())


class Looked(Tiled):
    """Tiles of a block of queries: for the points of the lists that they probe the estimated squared distance, less its error bound."""

    def __init__(self, index: BitLists, q: np.ndarray, probe: int, confidence: float):
        self.top, self.confidence, self.q, self.centres = (1 << index.bits) - 1, confidence, q, index.centres
        self.turned, self.turned_centres = q @ index.rotation, index.centres @ index.rotation
        self.far = np.stack([((index.centres - v) ** 2).sum(axis=1) for v in q])
        self.probed = np.zeros(self.far.shape, bool)
        np.put_along_axis(self.probed, np.argsort(self.far, axis=1, kind="stable")[:, :probe], True, axis=1)

    def tiles(self, batch: pa.RecordBatch) -> Iterator[Tile]:
        label, length, own = (batch.column(c).to_numpy() for c in ("list", "length", "own"))
        shown = matrix(batch.column("code")) - self.top / 2
        own_ = np.maximum(own, 1e-12)
        cosine2 = np.minimum(1, own**2 / np.maximum((shown**2).sum(axis=1), 1e-12))
        loose = np.maximum(0, (1 - cosine2) / np.maximum(cosine2, 1e-12))
        width = max(1, shown.shape[1] - 1)

        def values(row, who):
            of = label[row]
            product = ((self.turned[who] - self.turned_centres[of]) * shown[row]).sum(axis=1) / own_[row]
            far = self.far[who, of]
            return far + length[row] ** 2 - 2 * length[row] * (product + self.confidence * np.sqrt(far * loose[row] / width))

        # the same in parts that depend on the point alone, times parts that depend on the query
        scaled = shown * (2 * length / own_)[:, None]
        fixed = length**2 + (scaled * self.turned_centres[label]).sum(axis=1)
        error = 2 * self.confidence * length * np.sqrt(loose / width)
        root = np.sqrt(self.far)
        reach = np.sqrt((scaled**2).sum(axis=1).max(initial=0) * (self.turned**2).sum(axis=1).max(initial=0))
        slack = 1e-13 * (shown.shape[1] + 6) * float(self.far.max(initial=0) + np.abs(fixed).max(initial=0) + reach + error.max(initial=0) * root.max(initial=0)) + 1e-300
        for some in tiles_of(len(self.q), len(label)):
            value = self.turned[some] @ -scaled.T
            value += fixed
            value += self.far[some][:, label]
            value -= root[some][:, label] * error
            value[~self.probed[some][:, label]] = np.inf
            yield some, value, slack, values


def query(index: BitLists, queries: DataFrame, k: int = 10, probe: int = 8, keep: int | None = None, confidence: float = 1.9) -> DataFrame:
    """(qid, rank, vec_id, dist)."""
    held = 16 * index.centres.shape[1] + 9 * len(index.centres)
    return rerank_scan(index.points, ["list", "code", "length", "own"], queries, k, keep or 8 * k, None, lambda q: Looked(index, q, probe, confidence), held)
