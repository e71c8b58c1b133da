"""Approximate nearest neighbours by cosine: multiprobe hashing with p-stable (Gaussian) projections.

Vectors are scaled to length 1, where the largest cosine is the smallest Euclidean distance. A table projects them on Gaussian
directions (made orthogonal) and cuts each projection into two open cells at a randomly shifted edge. The number of projections follows the
number of rows, so that a bucket holds about ``BUCKET_ROWS``, up to ``MAX_PROJECTIONS``; the number of tables follows it too (``layout``).
A query visits perturbed buckets of all tables in the order of their estimated success: the probability that a neighbour
falls in the bucket, a product of normal probabilities over the projections. It stops when the
estimated success of all tables together reaches ``TARGET`` and more than k rows were met in some table, or all.

Neighbours are modelled by what is measured: ``SAMPLE`` rows (by hash of the id, a bounded sample) are searched exactly, in one scan of all rows, and how
their k nearest project, given how they project themselves, gives slope and noise of every projection. Every row is indexed.

Execution: vectors are written once. Buckets are packed in order into chunks of at most ``CHUNK`` rows; a bucket that holds more
(copies of one vector, say) is dealt to as many chunks as it needs, and queries are dealt to parts of about ``QUERY_PART``, so
neither rows nor queries of a task grow with the table. Base rows and probing queries meet
by chunk and part; for each query the rows of its visited buckets alone are compared, the k best scored anew
one by one from the original vectors in double precision. The k best over chunks and tables, equal
vectors met twice counted once, are the answer; ``met`` counts the rows that a query was compared with, over all tables.

Edge cases: vectors that are null, all zero, of another length than most, or hold null or non-finite components take
no part; fewer candidates than k give all of them; ties go to the smaller id; of rows that repeat an id one counts (that of the smallest vector); an
empty table gives no rows. Tables are read by the names given, further columns are not looked at and cannot clash.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import erf, log2, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, table

BUCKET_ROWS = 4
MAX_PROJECTIONS = 16
MAX_TABLES = 8
TARGET = 0.96
SAMPLE = 128
CHUNK = 4_096
#: Queries that meet a chunk in one task, about.
QUERY_PART = 4_096
#: Success is ordered in STEPS (a power of two) steps for each halving, down to 2 ** -DEPTH.
STEPS, DEPTH = 16, 60


def layout(n: int, d: int) -> tuple[int, int]:
    """(tables, projections) for n rows of d components: one table where buckets are few, more as they get small."""
    projections = int(min(MAX_PROJECTIONS, d, max(1, round(log2(max(n, 1) / BUCKET_ROWS)) if n > BUCKET_ROWS else 1)))
    return min(MAX_TABLES, max(1, projections - 8)), projections


def valid_vectors(rows: DataFrame, key: str, vector: str) -> DataFrame:
    """(id, v): one row for each id whose vector can take part, in the number type that it came in (integers as doubles)."""
    kind = rows.select(vector).schema[0].dataType.elementType.simpleString()
    sound = rows.select(F.col(key).cast("long").alias("id"), F.col(vector).cast("array<float>" if kind == "float" else "array<double>").alias("v")).where(
        F.col("id").isNotNull() & F.col("v").isNotNull() & F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    )
    return sound.groupBy("id").agg(F.min("v").alias("v"))


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False)
    return flat.reshape(len(column), -1)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


_phi = np.vectorize(lambda x: 0.5 * (1 + erf(x / sqrt(2))), otypes=[float])


@dataclass
class Hashes:
    """The tables: directions, edges, and how the projections of near neighbours follow those of a query."""

    directions: np.ndarray  # tables x dimension x projections
    edges: np.ndarray  # tables x projections
    middle: np.ndarray  # tables x projections
    slope: np.ndarray
    noise: np.ndarray

    @classmethod
    def fit(cls, sample: np.ndarray, owner: np.ndarray, near: np.ndarray, tables: int, projections: int, seed: int = 4) -> Hashes:
        """``near``: neighbours of the rows ``owner`` of the sample."""
        rng = np.random.default_rng(seed)
        d = sample.shape[1]
        directions = np.stack([np.linalg.qr(rng.standard_normal((d, projections)))[0] for _ in range(tables)])
        y = _unit(sample) @ directions
        middle, spread = y.mean(axis=1), y.std(axis=1) + 1e-9
        edges = middle + spread * rng.uniform(-0.25, 0.25, middle.shape)
        slope, noise = np.ones_like(middle), spread.copy()
        if len(near):
            own = y[:, owner] - middle[:, None]
            there = _unit(near) @ directions - middle[:, None]
            slope = (own * there).sum(axis=1) / np.maximum((own * own).sum(axis=1), 1e-12)
            noise = np.sqrt(((there - slope[:, None] * own) ** 2).mean(axis=1)) + 1e-3 * spread
        return cls(directions, edges, middle, slope, noise)

    @property
    def shape(self) -> tuple[int, int]:
        """Tables, and buckets of each."""
        return len(self.edges), 1 << self.edges.shape[1]

    def buckets(self, unit: np.ndarray) -> np.ndarray:
        """The bucket of every vector in every table (columns), numbered over all tables."""
        powers = 1 << np.arange(self.edges.shape[1])
        return np.stack([((unit @ a) > e).astype(np.int64) @ powers + t * self.shape[1] for t, (a, e) in enumerate(zip(self.directions, self.edges))], axis=1)

    def below(self, unit: np.ndarray) -> np.ndarray:
        """Probability that a neighbour of a query (row) lies below the edge of each projection of each table."""
        own = np.moveaxis(unit @ self.directions, 0, 1) - self.middle
        return np.clip(_phi((self.edges - self.middle - self.slope * own) / self.noise), 1e-9, 1 - 1e-9)

    @staticmethod
    def success(below: np.ndarray) -> np.ndarray:
        """Of one query: the probability that a neighbour falls in each bucket (columns) of each table (rows)."""

        def product(side):
            each = np.ones((len(side), 1))
            for j in range(side.shape[1]):
                # bit j of a bucket's number tells the side of edge j
                each = np.concatenate([each * side[:, j : j + 1], each * (1 - side[:, j : j + 1])], axis=1)
            return each

        half = below.shape[1] // 2
        return (product(below[:, half:])[:, :, None] * product(below[:, :half])[:, None, :]).reshape(len(below), -1)

    def probes(self, unit: np.ndarray, target: float, held: np.ndarray | None = None, least: int = 0):
        """For each query the buckets that it visits: the likeliest of all tables until all together reach the target.

        ``held``: rows in every bucket; empty ones are passed over, and the visit goes on until ``least`` rows were met in some table, or all.
        """
        tables, size = self.shape
        for below in self.below(unit):
            p = self.success(below)
            # the exponent and the leading bits of a number order it as its logarithm does
            step = np.minimum(STEPS * DEPTH - 1, (1023 * STEPS - 1) - (p.view(np.int64) >> (52 - STEPS.bit_length() + 1)))
            at = (step + STEPS * DEPTH * np.arange(tables)[:, None]).ravel()

            def upto(weights, at=at):
                return np.cumsum(np.bincount(at, weights.ravel(), tables * STEPS * DEPTH).reshape(tables, -1), axis=1)

            miss = np.prod(1 - np.minimum(upto(p), 1), axis=0)
            last = int(np.argmax(miss <= 1 - target)) if (miss <= 1 - target).any() else STEPS * DEPTH - 1
            visited = step <= last
            if held is not None:
                rows = upto(held.reshape(tables, size)).max(axis=0)
                if rows[last] < least:
                    visited = step <= (int(np.argmax(rows >= least)) if (rows >= least).any() else STEPS * DEPTH - 1)
                visited &= held.reshape(tables, size) > 0
            yield np.flatnonzero(visited)


def _chunks(held: np.ndarray, size: int, per_table: int) -> tuple[np.ndarray, np.ndarray]:
    """First chunk and number of chunks of each bucket: small ones of a table share, large ones get several."""
    first, parts = np.zeros(len(held), np.int64), np.zeros(len(held), np.int64)
    at, room, table_no = 0, size, 0
    for bucket in np.flatnonzero(held).tolist():
        n = int(held[bucket])
        if bucket // per_table != table_no:
            # a chunk holds an id once, so it holds one table
            at, room, table_no = at + (room < size), size, bucket // per_table
        if n > size:
            at += room < size
            first[bucket], parts[bucket] = at, -(-n // size)
            at, room = at + parts[bucket], size
            continue
        if n > room:
            at, room = at + 1, size
        first[bucket], parts[bucket] = at, 1
        room -= n
    return first, parts


def _best(score: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    return np.lexsort((ids, -score))[:k]


def _exact(x: np.ndarray, norms: np.ndarray, q: np.ndarray) -> np.ndarray:
    """The cosine of each row with q, summed alike for equal rows."""
    return (x * q).sum(axis=1) / (norms * np.sqrt((q * q).sum()))


def _score_chunk(k: int):
    kinds = {"query_id": pa.int64(), "vec_id": pa.int64(), "score": pa.float64(), "met": pa.int64()}

    def run(_, base: pa.Table, queries: pa.Table) -> pa.Table:
        out: dict[str, list] = {name: [] for name in kinds}
        if base.num_rows and queries.num_rows:
            base = base.sort_by("bucket")
            ids, buckets = base.column("id").to_numpy(), base.column("bucket").to_numpy()
            x = _matrix(base.column("v").combine_chunks())
            norms = np.sqrt((x * x).sum(axis=1))
            unit = x / norms[:, None]
            known, starts = np.unique(buckets, return_index=True)
            stops = np.append(starts[1:], len(ids))
            qids = queries.column("qid").to_numpy()
            q = _matrix(queries.column("qv").combine_chunks())
            visits = queries.column("buckets").combine_chunks()
            flat, ends = visits.flatten().to_numpy(), np.concatenate([[0], np.cumsum(visits.value_lengths().to_numpy())])
            for i, v in enumerate(q):
                at = np.searchsorted(known, flat[ends[i] : ends[i + 1]])
                sizes = stops[at] - starts[at]
                rows = np.repeat(starts[at] - np.cumsum(sizes) + sizes, sizes) + np.arange(sizes.sum())
                rows = rows[ids[rows] != qids[i]]
                if not len(rows):
                    continue
                near = unit[rows] @ (v / np.sqrt((v * v).sum()))
                if len(rows) > k:
                    # all that may be among the k best but for rounding, scored alike one by one
                    rows, met = rows[near >= np.partition(near, len(rows) - k)[len(rows) - k] - 1e-9], len(rows)
                else:
                    met = len(rows)
                exact = _exact(x[rows], norms[rows], v)
                top = _best(exact, ids[rows], k)
                out["query_id"] += [int(qids[i])] * len(top)
                out["vec_id"] += ids[rows[top]].tolist()
                out["score"] += exact[top].tolist()
                out["met"] += [met] + [0] * (len(top) - 1)
        return pa.table({name: pa.array(out[name], kind) for name, kind in kinds.items()})

    return run


def _neighbours_of_sample(base: DataFrame, sample: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(row of the sample, vector) of the k nearest of every sampled row: one scan that keeps k rows a sampled row and task, then one for the vectors."""
    spark = base.sparkSession
    shared = spark.sparkContext.broadcast((_unit(sample), ids))

    def nearest(batches):
        unit, own = shared.value
        best_id, best = np.full((len(own), 0), 0), np.zeros((len(own), 0))
        for batch in batches:
            if not batch.num_rows:
                continue
            others = batch.column("id").to_numpy()
            near = unit @ _unit(_matrix(batch.column("v"))).T
            # copies fall in the query's own bucket: the model is of its other neighbours
            near[(own[:, None] == others) | (near > 1 - 1e-9)] = -9
            best, best_id = np.hstack([best, near]), np.hstack([best_id, np.broadcast_to(others, near.shape)])
            keep = np.argsort(-best, axis=1, kind="stable")[:, :k]
            best, best_id = np.take_along_axis(best, keep, 1), np.take_along_axis(best_id, keep, 1)
        row, at = np.nonzero(best > -2)
        yield pa.RecordBatch.from_arrays([pa.array(row), pa.array(best_id[row, at]), pa.array(best[row, at])], names=["owner", "id", "near"])

    w = Window.partitionBy("owner").orderBy(F.desc("near"), "id")
    ranked = base.mapInArrow(nearest, "owner long, id long, near double").withColumn("r", F.row_number().over(w)).where(F.col("r") <= k)
    pairs = cut(ranked.select("owner", "id"), "ann-pairs")  # k rows a sampled row
    got = base.join(F.broadcast(pairs), "id").select("owner", "v").toArrow()
    if not got.num_rows:
        return np.zeros(0, np.int64), np.zeros((0, sample.shape[1]))
    return got.column("owner").to_numpy(), _matrix(got.column("v").combine_chunks())


def search(base: DataFrame, queries: DataFrame, k: int = 5, target: float = TARGET, tables: int | None = None, projections: int | None = None, chunk: int = CHUNK, sample: int = SAMPLE, query_part: int = QUERY_PART) -> DataFrame:
    """(query_id, rank, vec_id, score, met) for (id, v) tables of valid vectors; a row with the query's own id is no candidate."""
    spark = base.sparkSession
    sizes = base.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    if sizes is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double, met long")
    base, queries = (df.where(F.size("v") == sizes.d) for df in (base, queries))
    own = layout(sizes["count"], sizes.d)
    tables, projections = tables or own[0], min(projections or own[1], sizes.d)
    # the bounded sample: about four rows for each that is wanted pass the filter, so tasks send next to nothing
    place, unit = F.pmod(F.xxhash64("id"), F.lit(1 << 30)), 1 << 30
    rows = base.where(place < max(1, 4 * sample * unit // sizes["count"])).orderBy(place, "id").limit(sample).collect()
    some, ids = np.array([r.v for r in rows], float), np.array([r.id for r in rows], np.int64)
    hashes = Hashes.fit(some, *_neighbours_of_sample(base, some, ids, k), tables, projections)
    shared = spark.sparkContext.broadcast(hashes)
    size = hashes.shape[1]
    kind = base.schema["v"].dataType.simpleString()

    def hashed(batches):
        for batch in batches:
            if batch.num_rows:
                b = shared.value.buckets(_unit(_matrix(batch.column("v"))))
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(b) + 1) * b.shape[1], pa.int32()), pa.array(b.ravel()))
                yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("v"), lists], names=["id", "v", "buckets"])

    indexed = base.select("id", "v").mapInArrow(hashed, f"id long, v {kind}, buckets array<long>").withColumn("bucket", F.explode("buckets")).drop("buckets")
    held = np.zeros(tables * size, np.int64)
    for r in indexed.groupBy("bucket").count().collect():  # at most tables * 2 ** projections rows
        held[r[0]] = r[1]
    placed = spark.sparkContext.broadcast((*_chunks(held, chunk, size), held))
    query_parts = max(1, -(-queries.count() // query_part))

    def dealt(batches):
        first, parts, _ = placed.value
        for batch in batches:
            bucket, ids = batch.column("bucket").to_numpy(), batch.column("id").to_numpy()
            spread = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)
            where = first[bucket] + (spread % np.maximum(parts[bucket], 1).astype(np.uint64)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(where), *(batch.column(c) for c in ("bucket", "id", "v"))], names=["chunk", "bucket", "id", "v"])

    chunks = indexed.select("id", "v", "bucket").mapInArrow(dealt, f"chunk long, bucket long, id long, v {kind}")
    chunks = chunks.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(query_parts - 1))))

    def probing(batches):
        first, parts, held = placed.value
        for batch in batches:
            for lo in range(0, batch.num_rows, 64):
                part = batch.slice(lo, 64)
                row, where, bucket = [], [], []
                for i, visited in enumerate(shared.value.probes(_unit(_matrix(part.column("v"))), target, held, k + 1)):
                    n = parts[visited]
                    row.append(np.full(n.sum(), i))
                    bucket.append(np.repeat(visited, n))
                    where.append(np.repeat(first[visited] - np.cumsum(n) + n, n) + np.arange(n.sum()))
                if not sum(map(len, row)):
                    continue
                row, where, bucket = map(np.concatenate, (row, where, bucket))
                order = np.lexsort((bucket, where, row))
                row, where, bucket = row[order], where[order], bucket[order]
                new = np.flatnonzero(np.r_[True, (row[1:] != row[:-1]) | (where[1:] != where[:-1])])
                lists = pa.ListArray.from_arrays(pa.array(np.r_[new, len(row)], pa.int32()), pa.array(bucket))
                yield pa.RecordBatch.from_arrays([pa.array(where[new]), part.column("id").take(pa.array(row[new])), part.column("v").take(pa.array(row[new])), lists], names=["chunk", "qid", "qv", "buckets"])

    visits = queries.select("id", "v").mapInArrow(probing, f"chunk long, qid long, qv {kind}, buckets array<long>").withColumn("part", F.pmod(F.xxhash64("qid"), F.lit(query_parts)).cast("int"))
    both = chunks.groupBy("chunk", "part").cogroup(visits.groupBy("chunk", "part"))
    found = cut(both.applyInArrow(_score_chunk(k), "query_id long, vec_id long, score double, met long"), "ann-found")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    once = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    top = once.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
    met = found.groupBy("query_id").agg(F.sum("met").alias("met"))
    return top.join(met, "query_id").select("query_id", "rank", "vec_id", "score", "met")


def query(spark, sf_dir):
    """Contract digest, and in ``met`` how many rows each query was compared with."""
    vectors = cut(valid_vectors(table(spark, sf_dir, "embeddings"), "vec_id", "embedding"), "ann-vectors")
    return search(vectors, vectors.where(F.col("id") % 50 == 0), k=5)
