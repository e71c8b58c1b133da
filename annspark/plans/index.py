"""Building, storing and reading an index."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import imi, kmeans, transform
from ..operators.transform import Space
from ..params import Params
from ..sources.work import materialise, work_dir

VERSION = 1


@dataclass
class Index:
    params: Params
    space: Space
    books: list[np.ndarray]
    points: DataFrame  # vec_id, cells, embedding
    counts: np.ndarray  # ns x l x l
    n: int
    seconds: dict[str, float] = field(default_factory=dict)
    posted: DataFrame | None = None

    def postings(self) -> DataFrame:
        """(subspace, c1, c2, vec_id); made once, on demand, clustered by cell for pruning."""
        if self.posted is None:
            posted = imi.postings(self.points, self.params.side)
            self.posted = materialise(posted.repartition("subspace", "c1").sortWithinPartitions("subspace", "c1", "c2"), "postings")
        return self.posted

    def logical_bytes(self) -> int:
        """Ids in postings, codebooks and model, in eight-byte numbers; without the dataset."""
        model = self.space.mean.size + sum(b.size for b in self.space.directions) if self.space.values is not None else 0
        return 8 * (self.n * len(self.space.directions) + sum(b.size for b in self.books) + model + self.counts.size)


def _narrow(base: DataFrame, space: Space) -> tuple[DataFrame, Space]:
    """What the rounds of clustering scan: the vectors, or, if a space keeps no more than half of their dimensions, its parts, written once, and the space that has them as they are."""
    kept = sum(space.widths)
    if 2 * kept > len(space.mean):
        return base, space
    ends = np.cumsum(space.widths)
    parts = transform.apply(base, space).select("vec_id", F.flatten("parts").alias("embedding"))
    return materialise(parts, "parts"), transform.of_dimensions(kept, [np.arange(end - width, end) for end, width in zip(ends, space.widths)])


def create(base: DataFrame, params: Params, space: Space | None = None, path: str | None = None, train_fraction: float | None = None) -> Index:
    """An index of (vec_id, embedding). Seconds of the space (preprocessing) are kept apart from those of the index."""
    begun = time.time()
    space = space or transform.fit(base, params)
    fitted = time.time()
    books = kmeans.fit_all(*_narrow(base, space), params.side, params.t, params.init, params.seed, train_fraction)
    points = materialise(imi.codes(base, space, books), "codes", path and f"{path}/codes")
    counts = imi.occupancy(imi.cell_counts(points, params.side), len(space.directions), params.side)
    index = Index(params, space, books, points, counts, int(counts[0].sum()), {"preprocess_s": fitted - begun, "index_s": time.time() - fitted})
    if path:
        save(index, path)
    return index


def save(index: Index, path: str) -> None:
    """The manifest and the small tables beside the codes: JSON rows, written by Spark so that any store will do."""
    spark = index.points.sparkSession
    body = {
        "version": VERSION, "params": index.params.as_dict(), "n": index.n, "mean": index.space.mean.tolist(), "directions": [b.tolist() for b in index.space.directions],
        "values": None if index.space.values is None else index.space.values.tolist(), "blocks": index.space.blocks, "books": [b.tolist() for b in index.books], "counts": index.counts.tolist(),
    }
    spark.createDataFrame([(json.dumps(body, sort_keys=True),)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def load(spark: SparkSession, path: str) -> Index:
    body = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    if body["version"] != VERSION:
        raise ValueError(f"index version {body['version']}, not {VERSION}")
    values = None if body["values"] is None else np.array(body["values"])
    space = Space(np.array(body["mean"]), [np.array(b) for b in body["directions"]], values, body["blocks"])
    return Index(Params(**body["params"]), space, [np.array(b) for b in body["books"]], spark.read.parquet(f"{path}/codes"), np.array(body["counts"]), body["n"])


def default_path(spark: SparkSession, name: str) -> str:
    return f"{work_dir(spark)}/index-{name}"
