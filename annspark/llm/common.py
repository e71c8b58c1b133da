"""Shared parts: the shared folder, lineage cuts, table reading and byte-level text batches."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..sources.work import work_dir as shared_dir

#: Bytes of text that a Python worker handles at once; a longer text is a batch of its own.
SLICE_BYTES = 1 << 19
#: The word separators of every contract: space and \t\n\v\f\r.
SPACES = np.zeros(256, bool)
SPACES[[9, 10, 11, 12, 13, 32]] = True
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def without(docs: DataFrame, *names: str) -> DataFrame:
    """``docs`` less the columns that an operator gives anew: where a name clashes, the operator's column takes its place."""
    gone = {n.lower() for n in names}
    return docs.drop(*[c for c in docs.columns if c.lower() in gone])


def free(docs: DataFrame, name: str) -> str:
    """``name``, lengthened until no column of ``docs`` has it: for columns that an operator needs inside."""
    held = {c.lower() for c in docs.columns}
    while name.lower() in held:
        name += "_"
    return name


def cut(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: a short lineage that outlives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._cut_path = path
    return out


def forget(df: DataFrame) -> None:
    """Delete the files of a table that ``cut`` made and that nothing reads any more."""
    spark, path = df.sparkSession, getattr(df, "_cut_path", None)
    if path:
        jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
        jpath.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jpath, True)


def text_slices(column: pa.Array, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Runs of rows ``lo:hi`` with their UTF-8 bytes and the n+1 offsets into them; null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.fill_null("").cast(pa.large_string())
    n = len(column)
    if not n:
        return
    _, raw_offsets, raw = column.buffers()
    offsets = np.frombuffer(raw_offsets, np.int64, n + 1, column.offset * 8)
    data = np.frombuffer(raw, np.uint8) if raw is not None and raw.size else np.zeros(0, np.uint8)
    lo = 0
    while lo < n:
        hi = int(np.searchsorted(offsets, offsets[lo] + limit, "right")) - 1
        hi = min(n, max(hi, lo + 1))
        yield lo, hi, data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        lo = hi


def word_spans(buf: np.ndarray, offsets: np.ndarray, breaks: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte start and end of every word, and for each text the index of its first word (n+1 of them)."""
    ink = ~breaks[buf]
    edge = np.zeros(len(buf) + 1, bool)
    edge[offsets] = True
    before = np.empty(len(buf), bool)
    after = np.empty(len(buf), bool)
    if len(buf):
        before[0], before[1:] = True, ~ink[:-1]
        after[-1], after[:-1] = True, ~ink[1:]
    starts = np.flatnonzero(ink & (before | edge[:-1]))
    ends = np.flatnonzero(ink & (after | edge[1:])) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def word_runs(starts: np.ndarray, ends: np.ndarray, limit: int = SLICE_BYTES) -> Iterator[tuple[int, int, int, int]]:
    """Runs ``i:j`` of words, and the bytes ``lo:hi`` that they lie in: about ``limit`` bytes, or one longer word.

    A long text is worked through run by run, so that what is held for each byte is held for one run only.
    """
    i = 0
    while i < len(starts):
        j = max(i + 1, int(np.searchsorted(ends, starts[i] + limit, "right")))
        yield i, j, int(starts[i]), int(ends[j - 1])
        i = j


_BASE = np.uint64(0x9E3779B97F4A7C15)
_powers: list[np.ndarray] = []


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers[0]) < n:
        size = max(n, 1 << 16)
        inverse = np.uint64(pow(int(_BASE), -1, 1 << 64))
        _powers[:] = [np.cumprod(np.concatenate([[np.uint64(1)], np.full(size - 1, x, np.uint64)]), dtype=np.uint64) for x in (_BASE, inverse)]
    return _powers[0], _powers[1]


def mix(x: np.ndarray) -> np.ndarray:
    """A finalising permutation of 64-bit values."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def span_hashes(codes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each span of ``codes`` (any unsigned integers) by differences of one running sum."""
    up, down = _power_tables(len(codes) + 1)
    total = np.zeros(len(codes) + 1, np.uint64)
    np.cumsum((codes.astype(np.uint64) + np.uint64(1)) * up[: len(codes)], out=total[1:])
    return mix((total[ends] - total[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def word_hashes(buf: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """``span_hashes`` of words in order, run by run."""
    runs = [span_hashes(buf[lo:hi], starts[i:j] - lo, ends[i:j] - lo) for i, j, lo, hi in word_runs(starts, ends)]
    return np.concatenate(runs) if runs else np.zeros(0, np.uint64)


def lower_ascii(buf: np.ndarray) -> np.ndarray:
    return np.where((buf >= 65) & (buf <= 90), buf + np.uint8(32), buf)
