"""Counts and rows that tasks send by groups of queries, as bytes: added and ranked where they arrive, so that the driver gets what is asked for and nothing else."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: Queries of a group.
GROUP = 16


def tally(rows: DataFrame, count: Callable, width: int, queries: int) -> np.ndarray:
    """queries x width numbers: the sum of what ``count(batches)`` gives in every task."""

    def run(batches):
        total = np.ascontiguousarray(count(batches), np.int32)
        for at in range(0, queries, GROUP):
            yield pa.RecordBatch.from_arrays([pa.array([at]), pa.array([total[at : at + GROUP].tobytes()])], names=["at", "counts"])

    def add(held):
        total = sum(np.frombuffer(one, np.int32).astype(np.int64) for one in held.column("counts").to_pylist())
        return pa.table({"at": held.column("at").slice(0, 1), "counts": pa.array([total.tobytes()])})

    out = np.zeros((queries, width), np.int64)
    got = rows.mapInArrow(run, "at long, counts binary").groupBy("at").applyInArrow(add, "at long, counts binary").toArrow()
    for at, counts in zip(got.column("at").to_pylist(), got.column("counts").to_pylist()):
        out[at : at + GROUP] = np.frombuffer(counts, np.int64).reshape(-1, width)
    return out


def packed(query: np.ndarray, *columns: np.ndarray):
    """Rows of (query, ...) as a record batch with one row for each group of queries."""
    order = np.argsort(query // GROUP, kind="stable")
    groups = query[order] // GROUP
    cuts = np.flatnonzero(np.diff(groups, prepend=-1, append=-1)) if len(groups) else np.zeros(1, int)
    sorted_ = [np.ascontiguousarray(c[order]) for c in (query, *columns)]
    pieces = [pa.array([c[a:b].tobytes() for a, b in zip(cuts, cuts[1:])], pa.binary()) for c in sorted_]
    return pa.RecordBatch.from_arrays([pa.array(groups[cuts[:-1]].astype(np.int64) * GROUP), *pieces], names=["at", *[f"c{i}" for i in range(len(sorted_))]])


def packed_schema(columns: int) -> str:
    return "at long, " + ", ".join(f"c{i} binary" for i in range(columns + 1))


def unpacked(held: pa.Table, *kinds) -> list[np.ndarray]:
    """The columns of a group's rows from all tasks."""
    return [np.frombuffer(b"".join(held.column(f"c{i}").to_pylist()), kind) for i, kind in enumerate(kinds)]
