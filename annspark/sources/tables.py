"""Reading and writing: the given tables, user vectors in several formats, results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_vectors(spark: SparkSession, path: str, fmt: str = "parquet", key: str = "vec_id", vector: str = "embedding", separator: str = " ") -> DataFrame:
    """(vec_id, embedding) from Parquet, ORC or JSON with an array column, or CSV with one separated text column."""
    if fmt == "csv":
        raw = spark.read.schema(f"{key} long, {vector} string").option("header", True).csv(path)
        return raw.select(F.col(key).alias("vec_id"), F.transform(F.split(vector, separator), lambda x: x.cast("double")).alias("embedding"))
    reader = spark.read.schema(f"{key} long, {vector} array<double>") if fmt == "json" else spark.read
    return reader.format(fmt).load(path).select(F.col(key).cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("embedding"))


def sound(vectors: DataFrame, d: int | None = None) -> DataFrame:
    """Rows that can be indexed: an id, no null or non-finite component, the length ``d`` (by default the commonest)."""
    fit = vectors.where(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))))
    if d is None:
        first = fit.groupBy(F.size("embedding").alias("d")).count().orderBy(F.desc("count"), "d").first()
        d = first.d if first else 0
    return fit.where(F.size("embedding") == d)


def rejected(vectors: DataFrame, d: int) -> DataFrame:
    """(vec_id, reason) of the rows that ``sound`` leaves out."""
    reason = (
        F.when(F.col("vec_id").isNull(), "no id").when(F.col("embedding").isNull(), "no vector").when(F.exists("embedding", lambda x: x.isNull()), "null component")
        .when(F.exists("embedding", lambda x: F.isnan(x) | (F.abs(x) == float("inf"))), "not finite").when(F.size("embedding") != d, "wrong length")
    )
    return vectors.select("vec_id", reason.alias("reason")).where("reason IS NOT NULL")


def hold_out(vectors: DataFrame, modulus: int) -> tuple[DataFrame, DataFrame]:
    """The dataset without the queries, and the queries (qid, embedding): ids divisible by ``modulus``."""
    queries = vectors.where(F.col("vec_id") % modulus == 0)
    return vectors.where(F.col("vec_id") % modulus != 0), queries.withColumnRenamed("vec_id", "qid")


def write_result(result: DataFrame, path: str | None = None, view: str | None = None) -> None:
    """A result as Parquet, as a temporary view, or to nowhere (for timing)."""
    if path:
        result.write.mode("overwrite").parquet(path)
    if view:
        result.createOrReplaceTempView(view)
    if not path and not view:
        result.write.format("noop").mode("overwrite").save()
