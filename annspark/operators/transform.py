"""A space: how a vector is laid out in subspaces. Fitting one, and applying it to tables."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import lists, matrix
from ..functions.vector import dot
from ..params import Params
from . import allocate, linalg, partition


@dataclass
class Space:
    """Subspace j of x is (x - mean) @ directions[j]."""

    mean: np.ndarray
    directions: list[np.ndarray]
    values: np.ndarray | None = None
    blocks: list[list[int]] | None = None

    def parts(self, x: np.ndarray) -> list[np.ndarray]:
        if not len(x):
            return [np.zeros((0, b.shape[1])) for b in self.directions]
        x = x - self.mean
        return [x @ b for b in self.directions]

    @property
    def widths(self) -> list[int]:
        return [b.shape[1] for b in self.directions]

    @property
    def reduction(self) -> float:
        """Share of the dimensions that are dropped."""
        return 1 - sum(self.widths) / len(self.mean)


def of_dimensions(d: int, dims: list[np.ndarray]) -> Space:
    eye = np.eye(d)
    return Space(np.zeros(d), [eye[:, part] for part in dims])


def fit(base: DataFrame, params: Params) -> Space:
    """The space that ``params`` asks for; the adaptive one needs the moments of the base."""
    if params.space == "adaptive":
        found = linalg.moments(base)
        system = linalg.eigensystem(found.cov)
        blocks = allocate.greedy(system.values, params.ns, params.s)
        return Space(found.mean, [system.vectors[:, b] for b in blocks], system.values, blocks)
    first = base.select(F.size("embedding")).first()
    if first is None:
        raise ValueError("no vectors")
    dims = partition.contiguous(first[0], params.ns) if params.space == "agnostic" else partition.sampled(first[0], params.ns, params.seed)
    return of_dimensions(first[0], dims)


def apply(vectors: DataFrame, space: Space, key: str = "vec_id") -> DataFrame:
    """(key, parts): an array for each subspace. A narrow map over Arrow batches."""

    def project(batches):
        for batch in batches:
            if batch.num_rows:
                parts = [lists(p) for p in space.parts(matrix(batch.column("embedding")))]
                ends = np.arange(batch.num_rows + 1) * len(parts)
                order = np.arange(len(parts) * batch.num_rows).reshape(len(parts), batch.num_rows).T.ravel()
                nested = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.concat_arrays(parts).take(pa.array(order)))
                yield pa.RecordBatch.from_arrays([batch.column(key), nested], names=[key, "parts"])

    return vectors.select(F.col(key).cast("long").alias(key), "embedding").mapInArrow(project, f"{key} long, parts array<array<double>>")


def apply_sql(vectors: DataFrame, space: Space, key: str = "vec_id") -> DataFrame:
    """The same as column expressions, for parity with SQL."""
    centred = F.zip_with("embedding", F.array(*[F.lit(float(m)) for m in space.mean]), lambda x, m: x - m)
    parts = [F.array(*[dot(F.col("c"), F.array(*[F.lit(float(v)) for v in column])) for column in b.T]) for b in space.directions]
    return vectors.select(key, centred.alias("c")).select(key, F.array(*parts).alias("parts"))
