"""SQL names for vector functions, and table functions for LATERAL joins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from .arrays import matrix


@pandas_udf(T.DoubleType())
def l2_distance(a: pd.Series, b: pd.Series) -> pd.Series:
    """Euclidean distance of two vectors of equal length; null for a null."""
    return pd.Series([None if x is None or y is None else float(np.sqrt(((np.asarray(x, float) - np.asarray(y, float)) ** 2).sum())) for x, y in zip(a, b)])


@pandas_udf(T.DoubleType())
def cosine_similarity(a: pd.Series, b: pd.Series) -> pd.Series:
    out = []
    for x, y in zip(a, b):
        x, y = np.asarray(x, float), np.asarray(y, float)
        size = np.sqrt((x * x).sum() * (y * y).sum())
        out.append(float((x * y).sum() / size) if size else None)
    return pd.Series(out)


def collision_score(cells, activated) -> Column:
    """How many of a point's cells (one for each subspace) are in the lists of activated cells: an expression of built-in functions."""
    hits = F.zip_with(cells, activated, lambda cell, listed: F.array_contains(listed, cell))
    return F.size(F.filter(hits, lambda hit: hit))


COLLISION_SCORE = """CREATE OR REPLACE TEMPORARY FUNCTION collision_score(cells ARRAY<INT>, activated ARRAY<ARRAY<INT>>) RETURNS INT
  RETURN size(filter(zip_with(cells, activated, (cell, listed) -> array_contains(listed, cell)), hit -> hit))"""


@pandas_udf(T.ArrayType(T.DoubleType()))
def vector_mean(v: pd.Series) -> list:
    """Mean of a group's vectors."""
    return np.mean(np.stack([np.asarray(x, float) for x in v]), axis=0).tolist()


#: Bytes of a base that a table function carries to every worker.
CARRIED_BYTES = 256 << 20


def knn_table(base: DataFrame, k: int):
    """A table function knn(qid, vector) over a base that the function carries with it (at most ``CARRIED_BYTES``)."""
    counted = base.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("embedding")).alias("d")).first()
    if counted.n * ((counted.d or 0) + 2) * 8 > CARRIED_BYTES:
        raise ValueError("the base is too large to be carried by a function; use plans.search")
    rows = base.orderBy("vec_id").select("vec_id", "embedding").toArrow()
    ids, x = rows.column("vec_id").to_numpy(), matrix(rows.column("embedding"))
    size = (x * x).sum(axis=1)

    @udtf(returnType="qid long, rank int, vec_id long, dist double")
    class Knn:
        def eval(self, qid: int, vector: list) -> Iterator[tuple]:
            if not len(ids):
                return
            q = np.asarray(vector, float)
            # one product tells which rows rounding leaves a chance; their distances are taken one by one
            rough = size - 2 * (x @ q) + (q * q).sum()
            at = min(k, len(ids)) - 1
            near = np.flatnonzero(rough <= np.partition(rough, at)[at] + 1e-9 * (1 + np.abs(rough).max()))
            dist = np.sqrt(((x[near] - q) ** 2).sum(axis=1))
            for r, i in enumerate(np.lexsort((ids[near], dist))[:k], 1):
                yield qid, r, int(ids[near[i]]), float(dist[i])

    return Knn


def activate_table(index):
    """A table function activate(qid, vector): the cells that a query activates, subspace by subspace."""
    from ..operators.activation import WAYS, centroid_lists
    from ..operators.kmeans import half_parts

    space, books, counts, params = index.space, index.books, index.counts, index.params

    @udtf(returnType="qid long, subspace int, c1 int, c2 int, cnt long")
    class Activate:
        def eval(self, qid: int, vector: list) -> Iterator[tuple]:
            halves = half_parts(space, np.asarray(vector, float)[None])
            for j in range(len(books) // 2):
                one, two = (centroid_lists(books[2 * j + h], halves[2 * j + h][0], params.cell_distance) for h in (0, 1))
                own = counts[j][np.ix_(one[0], two[0])]
                got = WAYS["heap"](one[1], two[1], own, params.alpha * counts[j].sum())
                for a, b in zip(got.pos1, got.pos2):
                    yield qid, j, int(one[0][a]), int(two[0][b]), int(own[a, b])

    return Activate


def register(spark: SparkSession, base: DataFrame | None = None, k: int = 10, index=None) -> None:
    """Make the functions known to SQL; the table functions only with what they need."""
    for name, f in (("l2_distance", l2_distance), ("cosine_similarity", cosine_similarity), ("vector_mean", vector_mean)):
        spark.udf.register(name, f)
    spark.sql(COLLISION_SCORE)
    if base is not None:
        spark.udtf.register("knn", knn_table(base, k))
    if index is not None:
        spark.udtf.register("activate", activate_table(index))


__all__ = ["activate_table", "collision_score", "cosine_similarity", "knn_table", "l2_distance", "register", "vector_mean"]
