"""Parts that the trained operators share: bounded deterministic samples and fitting in one task."""

from __future__ import annotations

import pickle
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fold(doc_id: str, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``; null for a null id."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % parts


def bounded_ids(rows: DataFrame, key: str, klass: str, each: int) -> DataFrame:
    """(key, klass): about ``each`` rows of every class and never more than twice that in all, chosen by a hash of the key.

    The classes are counted first; a row stays if its hash lies under its class's share, so no class is gathered anywhere.
    """
    shares = rows.groupBy(klass).agg(F.count(F.lit(1)).alias("_n"))
    sizes = {r[0]: r[1] for r in shares.collect()}  # one row for each class
    if not sizes:
        return rows.select(key, klass)
    unit = F.pmod(F.xxhash64(F.lit(11), key), F.lit(1 << 30)) / float(1 << 30)
    share = F.coalesce(*[F.when(F.col(klass) == k, F.lit(each / n)) for k, n in sizes.items()])
    return rows.where(unit < share).select(key, klass).orderBy(F.xxhash64(F.lit(11), key), key).limit(2 * each * len(sizes))


#: Characters of the longest text that is learned from; longer ones are left to scoring.
LONGEST = 200_000


def bounded_texts(docs: DataFrame, ids: DataFrame, klass: str, longest: int = LONGEST) -> DataFrame:
    """(text, class): one row for each of the bounded ``ids`` (doc_id, class), of the texts of at most ``longest`` characters.

    Of rows that repeat an id the text of the smallest hash counts, so the rows are no more than the ids, and their bytes no more than the rows by ``longest``.
    """
    short = docs.where(F.col("text").isNotNull() & (F.length("text") <= longest)).select("doc_id", "text").join(F.broadcast(ids.select("doc_id", F.col(klass).alias("label"))), "doc_id")
    return short.groupBy("doc_id").agg(F.min_by(F.struct("text", "label"), F.struct(F.xxhash64("text"), "label")).alias("row")).select("row.text", "row.label")


def fit_in_one_task(sample: DataFrame, fit: Callable[[pa.Table], object]) -> object | None:
    """``fit`` of the whole sample (bounded by its maker), run in an executor; only the model comes to the driver."""
    schema = pa.schema([("model", pa.binary())])

    def run(batches):
        got = list(batches)
        if got:
            yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(fit(pa.Table.from_batches(got)))], pa.binary())], schema=schema)

    rows = sample.repartition(1).mapInArrow(run, "model binary").collect()
    return pickle.loads(rows[0][0]) if rows else None
