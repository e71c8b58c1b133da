"""All codebooks at once: Lloyd's rounds for both halves of every subspace in one pass a round."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.arrays import matrix, squared_distances
from .partition import halves
from .transform import Space

#: Rows that k-means++ looks at.
SAMPLE = 4_096
#: Bits of the ids that a round of ``ids_at`` tells apart.
BITS = 10


def half_parts(space: Space, x: np.ndarray) -> list[np.ndarray]:
    """Half 0 and half 1 of subspace 0, then of subspace 1, and so on: 2 * ns matrices."""
    return [p[:, h] for p in space.parts(x) for h in halves(p.shape[1])]


def assign(points: np.ndarray, centroids: np.ndarray) -> np.ndarray:
    """Nearest centroid of every point, ties to the smaller number; near ties are settled by direct distances."""
    if centroids.shape[1] == 0:
        return np.zeros(len(points), np.int64)
    rough = squared_distances(points, centroids)
    best = rough.argmin(axis=1)
    bound = rough[np.arange(len(points)), best] + 1e-9 * (1 + rough.max(initial=0))
    for i in np.flatnonzero((rough <= bound[:, None]).sum(axis=1) > 1):
        best[i] = ((centroids - points[i]) ** 2).sum(axis=1).argmin()
    return best


def first_by_hash(base: DataFrame, size: int, seed: int) -> DataFrame:
    """(embedding): the ``size`` rows of the smallest seeded hashes of their ids. A filter lets about four times as many through, so that tasks send next to nothing."""
    unit = 1 << 30
    place = F.pmod(F.xxhash64(F.lit(seed), "vec_id"), F.lit(unit))
    return base.where(place < max(1, 4 * size * unit // max(1, base.count()))).orderBy(place, "vec_id").limit(size).select("embedding")


def ids_at(base: DataFrame, ranks: list[int]) -> list[int]:
    """The ids at the given ranks (from 0) of the id order, exactly and without a sort: counts by leading bits, then by more bits within the bins that hold a rank."""
    vec_id = F.col("vec_id").cast("long")
    low, high = base.agg(F.min(vec_id), F.max(vec_id)).first()
    rows, last, bits, places = base, None, max(0, (high - low).bit_length() - BITS), [(None, 0)] * len(ranks)
    while last != 0:
        # at most 2 ** BITS + 1 rows, or 2 ** BITS for each rank
        counted = sorted(tuple(r) for r in rows.groupBy(F.shiftright(vec_id, bits).alias("bin")).count().collect())
        for i, (rank, (outer, below)) in enumerate(zip(ranks, places)):
            for inner, count in counted:
                if last is None or inner >> (last - bits) == outer:
                    if rank < below + count:
                        places[i] = inner, below
                        break
                    below += count
        rows, last, bits = base.where(F.shiftright(vec_id, bits).isin(sorted({p[0] for p in places}))), bits, max(0, bits - BITS)
    return [p[0] for p in places]


def initial(base: DataFrame, space: Space, l: int, init: str, seed: int) -> list[np.ndarray]:
    """First centroids. ``spread``: rows evenly spaced in id order; ``random``: rows of the smallest seeded hashes; ``kmeans++`` on a sample."""
    if init == "spread":
        n = base.count()
        ranks = [(c * (n - 1)) // (l - 1) if l > 1 else 0 for c in range(l)]
        picked = ids_at(base, ranks)
        rows = {r[0]: r[1] for r in base.where(F.col("vec_id").isin(sorted(set(picked)))).select("vec_id", "embedding").collect()}  # l rows
        x = np.array([rows[i] for i in picked], float)
    else:
        size = l if init == "random" else max(l, SAMPLE)
        rows = first_by_hash(base, size, seed).collect()
        x = np.array([r[0] for r in rows], float)
        if init == "random":
            x = x[np.arange(l) % len(x)]
    found = half_parts(space, x)
    return found if init != "kmeans++" else [_plus_plus(p, l, np.random.default_rng(seed)) for p in found]


def _plus_plus(points: np.ndarray, l: int, rng: np.random.Generator) -> np.ndarray:
    chosen = [points[rng.integers(len(points))]]
    far = ((points - chosen[0]) ** 2).sum(axis=1)
    while len(chosen) < l:
        chosen.append(points[rng.choice(len(points), p=far / far.sum())] if far.sum() > 0 else points[rng.integers(len(points))])
        far = np.minimum(far, ((points - chosen[-1]) ** 2).sum(axis=1))
    return np.array(chosen)


def fit_all(base: DataFrame, space: Space, l: int, t: int, init: str = "spread", seed: int = 17, train_fraction: float | None = None) -> list[np.ndarray]:
    """2 * ns codebooks of l centroids after exactly t rounds; an empty cluster keeps its centroid.

    A round is one scan; tasks send sums and counts per centroid, 2 * ns * l * width rows at most,
    which are added map-side and then by a hash aggregate.
    """
    books = initial(base, space, l, init, seed)
    rows = base.select("embedding")
    if train_fraction is not None:
        rows = base.where(F.pmod(F.xxhash64(F.lit(seed), "vec_id"), F.lit(1_000_000)) < int(train_fraction * 1_000_000)).select("embedding")
    for _ in range(t):
        shared = base.sparkSession.sparkContext.broadcast(books)

        def partial(batches, shared=shared):
            books = shared.value
            sums = [np.zeros((len(b), b.shape[1] + 1)) for b in books]
            for batch in batches:
                for total, book, points in zip(sums, books, half_parts(space, matrix(batch.column("embedding"))) if batch.num_rows else ()):
                    label = assign(points, book)
                    total[:, -1] += np.bincount(label, minlength=len(book))
                    for c in range(points.shape[1]):
                        total[:, c] += np.bincount(label, points[:, c], len(book))
            for b, total in enumerate(sums):
                cid, slot = np.nonzero(np.broadcast_to(total[:, -1:] > 0, total.shape))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(cid), b), pa.int32()), pa.array(cid, pa.int32()), pa.array(slot, pa.int32()), pa.array(total[cid, slot])], names=["book", "cid", "slot", "v"])

        added = rows.mapInArrow(partial, "book int, cid int, slot int, v double").groupBy("book", "cid", "slot").agg(F.sum("v").alias("v")).toArrow()
        totals = [np.zeros((len(b), b.shape[1] + 1)) for b in books]
        book, cid, slot, v = (added.column(c).to_numpy() for c in ("book", "cid", "slot", "v"))
        for b, total in enumerate(totals):
            some = book == b
            total[cid[some], slot[some]] = v[some]
        books = [np.where(total[:, -1:] > 0, total[:, :-1] / np.maximum(total[:, -1:], 1), b) for b, total in zip(books, totals)]
        shared.destroy()
    return books


def fit_mllib(base: DataFrame, space: Space, l: int, t: int, seed: int = 17) -> list[np.ndarray]:
    """The same codebooks by pyspark.ml, one job after another for each half: a cross-check, not the way to build an index."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    from .transform import apply

    parts, books = apply(base, space).cache(), []
    for j, width in enumerate(space.widths):
        for half in halves(width):
            start, count = half.start or 0, (half.stop or width) - (half.start or 0)
            points = parts.select(array_to_vector(F.slice(F.element_at("parts", j + 1), start + 1, count)).alias("features"))
            books.append(np.array(KMeans(k=l, maxIter=t, seed=seed).fit(points).clusterCenters()))
    parts.unpersist()
    return books
