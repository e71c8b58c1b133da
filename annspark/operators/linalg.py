"""Mean, covariance and eigensystem of a vector table."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.arrays import lists, matrix


@dataclass
class Moments:
    n: int
    mean: np.ndarray
    cov: np.ndarray  # divisor n - 1


def moments(base: DataFrame) -> Moments:
    """One pass: every task sums its rows and their products about a common pilot; a hash aggregate adds the tasks' numbers one by one.

    What is shuffled is (d + 1) d numbers a task, and no worker holds more than its share of one set of them; one set reaches the driver.
    """
    pilot_row = base.select("embedding").orderBy("vec_id").limit(1).collect()
    if not pilot_row:
        raise ValueError("no vectors")
    pilot = np.array(pilot_row[0][0], float)
    d = len(pilot)

    def partial(batches):
        n, total, products = 0, np.zeros(d), np.zeros((d, d))
        for batch in batches:
            if batch.num_rows:
                x = matrix(batch.column("embedding")) - pilot
                n += len(x)
                total += x.sum(axis=0)
                products += x.T @ x
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(-1, d), pa.int32()), pa.array(np.full(d + 1, n)), lists(np.vstack([total, products]))], names=["i", "n", "v"])

    parts = base.select("embedding").mapInArrow(partial, "i int, n long, v array<double>")
    added = parts.select("i", "n", F.posexplode("v").alias("j", "v")).groupBy("i", "j").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).toArrow()
    i, j, counts, v = (added.column(c).to_numpy() for c in ("i", "j", "n", "v"))
    n, sums = int(counts[0]), np.zeros((d + 1, d))
    sums[i + 1, j] = v
    total, products = sums[0], sums[1:]
    cov = (products - np.outer(total, total) / n) / max(1, n - 1)
    return Moments(n, pilot + total / n, (cov + cov.T) / 2)


def moments_frame(spark: SparkSession, found: Moments) -> DataFrame:
    """(i, j, cov) and, as j = -1, the mean."""
    rows = [(i, -1, float(m)) for i, m in enumerate(found.mean)] + [(i, j, float(found.cov[i, j])) for i in range(len(found.mean)) for j in range(len(found.mean))]
    return spark.createDataFrame(rows, "i int, j int, value double")


def moments_sql(base: DataFrame, d: int) -> DataFrame:
    """(i, j, cov) by covar_samp over pairs of components: for small d, and as a check."""
    x = base.select("vec_id", F.posexplode("embedding").alias("i", "x"))
    y = base.select("vec_id", F.posexplode("embedding").alias("j", "y"))
    return x.join(y, "vec_id").groupBy("i", "j").agg(F.covar_samp("x", "y").alias("cov"))


@dataclass
class Eigensystem:
    values: np.ndarray  # falling
    vectors: np.ndarray  # columns, the entry of largest magnitude positive


def eigensystem(cov: np.ndarray) -> Eigensystem:
    values, vectors = np.linalg.eigh(cov)
    order = np.argsort(-values, kind="stable")
    values, vectors = values[order], vectors[:, order]
    lead = np.argmax(np.abs(vectors), axis=0)
    return Eigensystem(values, vectors * np.where(vectors[lead, np.arange(len(values))] < 0, -1, 1))
