"""Tables between steps: written to the folder that driver and executors share, so that a lost executor costs a reread."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def work_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only a local session may do without; it gets a folder of its own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not found:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="annspark-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


#: What was written between steps, for ``clear``.
_written: list[tuple[str, str]] = []


def materialise(df: DataFrame, name: str, path: str | None = None) -> DataFrame:
    """A table written and read back. Without a ``path`` it lies in the shared folder until ``clear``."""
    spark = df.sparkSession
    if path is None:
        path = f"{work_dir(spark)}/{name}-{uuid.uuid4().hex}"
        _written.append((spark.sparkContext.applicationId, path))
    df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def clear(spark: SparkSession) -> int:
    """Delete the tables that this session wrote between steps, and say how many: when no result that reads them is needed any more."""
    own = [path for app, path in _written if app == spark.sparkContext.applicationId]
    for path in own:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    _written[:] = [w for w in _written if w[1] not in own]
    return len(own)


def stored_bytes(df: DataFrame) -> int:
    """Bytes of the Parquet files that a table is read from."""
    spark, total = df.sparkSession, 0
    for name in df.inputFiles():
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        total += path.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(path).getLen()
    return total
