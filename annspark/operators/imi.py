"""The inverted multi-index, kept by point (codes), by cell (postings), and as cell counts."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import lists, matrix
from .kmeans import assign, half_parts
from .transform import Space


def cells_of(space: Space, books: list[np.ndarray], x: np.ndarray) -> np.ndarray:
    """Cell c1 * l + c2 of every row in every subspace (columns)."""
    labels = [assign(points, book) for points, book in zip(half_parts(space, x), books)]
    return np.stack([labels[2 * j] * len(books[2 * j + 1]) + labels[2 * j + 1] for j in range(len(books) // 2)], axis=1)


def codes(base: DataFrame, space: Space, books: list[np.ndarray]) -> DataFrame:
    """(vec_id, cells, embedding): a narrow map; vectors stay beside their codes, so that re-ranking needs no join."""
    shared = base.sparkSession.sparkContext.broadcast((space, books))

    def label(batches):
        for batch in batches:
            if batch.num_rows:
                space, books = shared.value
                cells = cells_of(space, books, matrix(batch.column("embedding")))
                yield pa.RecordBatch.from_arrays([batch.column("vec_id"), lists(cells.astype(np.int32)), batch.column("embedding")], names=["vec_id", "cells", "embedding"])

    return base.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding")).mapInArrow(label, "vec_id long, cells array<int>, embedding array<double>")


def _long(coded: DataFrame) -> DataFrame:
    return coded.select("vec_id", F.posexplode("cells").alias("subspace", "cell"))


def postings(coded: DataFrame, l: int) -> DataFrame:
    """(subspace, c1, c2, vec_id): one row for each point and subspace."""
    return _long(coded).select("subspace", F.expr(f"CAST(cell DIV {l} AS int)").alias("c1"), (F.col("cell") % l).alias("c2"), "vec_id")


def cell_counts(coded: DataFrame, l: int) -> DataFrame:
    """(subspace, c1, c2, cnt) of the occupied cells; added map-side."""
    counted = _long(coded.select("vec_id", "cells")).groupBy("subspace", "cell").agg(F.count(F.lit(1)).alias("cnt"))
    return counted.select("subspace", F.expr(f"CAST(cell DIV {l} AS int)").alias("c1"), (F.col("cell") % l).alias("c2"), "cnt")


def posting_map(posted: DataFrame) -> DataFrame:
    """(subspace, cell_ids): cells as a map from "c1,c2" to sorted ids, as small indexes are shown."""
    lists_ = posted.groupBy("subspace", "c1", "c2").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))
    return lists_.groupBy("subspace").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct(F.concat_ws(",", "c1", "c2"), "ids")))).alias("cell_ids"))


def occupancy(counts: DataFrame, ns: int, l: int) -> np.ndarray:
    """Counts as an array ns x l x l: at most ns * K rows, whatever the data."""
    out = np.zeros((ns, l, l), np.int64)
    got = counts.toArrow()
    out[tuple(got.column(c).to_numpy() for c in ("subspace", "c1", "c2"))] = got.column("cnt").to_numpy()
    return out
