"""Vector tables built from the given tables. All return (vec_id, embedding) with doubles."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from hashlib import md5

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.arrays import CELLS, lists
from .tables import hold_out, load

EVENT_TYPES = ("click", "view", "purchase", "signup", "error")


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding"))


def skewed(spark: SparkSession, sf_dir: str, power: float = 0.7) -> DataFrame:
    """The embeddings with coordinate i (from 1) times i ** -power: an unequal spectrum."""
    return embeddings(spark, sf_dir).withColumn("embedding", F.transform("embedding", lambda x, i: x * F.pow((i + 1).cast("double"), F.lit(-power))))


def _word_counts(texts: pa.Array, widths: Sequence[int]) -> Iterator[np.ndarray]:
    """For each width d texts x d signed counts of hashed words; a word is hashed once however often it stands there."""
    # at space, \t, \n, \v, \f and \r
    split = pc.ascii_split_whitespace(texts)
    row, words = pc.list_parent_indices(split).to_numpy(), pc.list_flatten(split).dictionary_encode()
    known = words.dictionary.cast(pa.binary()).to_pylist()
    # the first seven of its hexadecimal digits
    h = np.frombuffer(b"".join([md5(word).digest()[:4] for word in known]), ">u4").astype(np.int64) >> 4
    some, at = pc.binary_length(words.dictionary).to_numpy() > 0, words.indices.to_numpy()
    for d in widths:
        sign = np.where(h // d % 2 == 0, 1.0, -1.0) * some
        yield np.bincount(row * d + (h % d)[at], sign[at], len(texts) * d).reshape(len(texts), d)


def text_vectors(texts: DataFrame, key: str, d: int = 64) -> DataFrame:
    """Words hashed into d signed buckets, counted and scaled to length 1. Bucket and sign come from an md5 prefix.

    A scan in which a word is hashed once a batch; nothing is shuffled, unless an id has several texts, which are put together first. Texts without words are zero vectors and are left out.
    """
    return of_width(text_vectors_of(texts, key, (d,)), d)


def text_vectors_of(texts: DataFrame, key: str, widths: Sequence[int]) -> DataFrame:
    """(vec_id, and for each width d a column ``embedding_d``): the vectors of several widths from one scan; null where they are zero."""
    widths = tuple(dict.fromkeys(widths))
    if not texts.groupBy(key).count().where("count > 1").isEmpty():
        texts = texts.groupBy(key).agg(F.array_join(F.collect_list("text"), " ").alias("text"))
    # letter by letter: Spark's lower makes two letters of one of these, and looks at what follows the other
    plain = F.when(F.contains("text", F.lit("İ")) | F.contains("text", F.lit("Σ")), F.translate("text", "İΣ", "iσ")).otherwise(F.col("text"))
    names = [f"embedding_{d}" for d in widths]

    def count(batches):
        step = max(1, CELLS // sum(widths))
        for part in (batch.slice(lo, step) for batch in batches for lo in range(0, batch.num_rows, step)):
            columns = []
            for total in _word_counts(part.column("text"), widths):
                length = np.sqrt((total * total).sum(axis=1))
                columns.append(lists(total / np.where(length > 0, length, 1.0)[:, None], missing=length == 0))
            yield pa.RecordBatch.from_arrays([part.column("vec_id"), *columns], names=["vec_id", *names])

    held = texts.select(F.col(key).alias("vec_id"), F.lower(plain).alias("text"))
    return held.mapInArrow(count, f"vec_id {held.schema['vec_id'].dataType.simpleString()}, " + ", ".join(f"{name} array<double>" for name in names))


def of_width(several: DataFrame, d: int) -> DataFrame:
    """(vec_id, embedding) of one width of ``text_vectors_of``, without the zero vectors."""
    return several.select("vec_id", F.col(f"embedding_{d}").alias("embedding")).where("embedding IS NOT NULL")


def doc_vectors(spark: SparkSession, sf_dir: str, d: int = 64) -> DataFrame:
    return text_vectors(load(spark, sf_dir, "documents"), "doc_id", d)


def doc_vectors_of(spark: SparkSession, sf_dir: str, widths: Sequence[int]) -> DataFrame:
    """Several widths of the same, for ``of_width``."""
    return text_vectors_of(load(spark, sf_dir, "documents"), "doc_id", widths)


def benchmark_vectors(spark: SparkSession, sf_dir: str, d: int = 64) -> DataFrame:
    return text_vectors(load(spark, sf_dir, "benchmark"), "item_id", d).withColumnRenamed("vec_id", "qid")


def _standardised(rows: DataFrame, key: str, columns: list[str]) -> DataFrame:
    stats = rows.agg(*[f(c).alias(f"{c}_{n}") for c in columns for n, f in (("m", F.avg), ("s", F.stddev_samp))])
    # one row
    scaled = [(F.col(c) - F.col(f"{c}_m")) / F.when(F.col(f"{c}_s") > 0, F.col(f"{c}_s")).otherwise(1.0) for c in columns]
    return rows.join(F.broadcast(stats)).select(F.col(key).alias("vec_id"), F.array(*scaled).alias("embedding"))


def order_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight standardised measures of every order."""
    lines, orders = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice", "o_orderdate")
    joined = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    rows = joined.groupBy("l_orderkey").agg(
        F.count(F.lit(1)).cast("double").alias("lines"), F.sum("l_quantity").alias("quantity"), F.avg("l_extendedprice").alias("price"), F.sum("l_extendedprice").alias("paid"),
        F.avg("l_discount").alias("discount"), F.avg("l_tax").alias("tax"), F.max("o_totalprice").alias("total"), F.avg(F.datediff("l_shipdate", "o_orderdate").cast("double")).alias("days"),
    )
    return _standardised(rows, "l_orderkey", ["lines", "quantity", "price", "paid", "discount", "tax", "total", "days"])


def event_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Count and mean value of every event type for each user, standardised."""
    events = load(spark, sf_dir, "events")
    kinds = sorted(r[0] for r in events.select("event_type").distinct().collect())
    measures = [F.sum(F.when(F.col("event_type") == k, 1.0).otherwise(0.0)).alias(f"n{i}") for i, k in enumerate(kinds)]
    measures += [F.coalesce(F.avg(F.when(F.col("event_type") == k, F.col("value"))), F.lit(0.0)).alias(f"v{i}") for i, k in enumerate(kinds)]
    names = [f"{p}{i}" for p in "nv" for i in range(len(kinds))]
    return _standardised(events.groupBy("user_id").agg(*measures), "user_id", names)


#: name -> (maker, modulus of the held-out queries)
FIXTURES = {"embeddings": (embeddings, 25), "skewed": (skewed, 25), "doc_vectors": (doc_vectors, 100), "order_vectors": (order_vectors, 1500), "event_vectors": (event_vectors, 15)}


def fixture(spark: SparkSession, sf_dir: str, name: str, **options) -> tuple[DataFrame, DataFrame]:
    """(base, queries) of a vector table."""
    make, modulus = FIXTURES[name]
    return hold_out(make(spark, sf_dir, **options), modulus)
