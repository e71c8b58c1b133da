"""Streams around an index: adding points to a frozen index, statistics of a query log, and watching for drift."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import imi
from ..plans.index import Index

EVENT = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def assign(index: Index, vectors: DataFrame) -> DataFrame:
    """(vec_id, cells, embedding) of new points under the frozen codebooks; works on streams and tables alike."""
    return imi.codes(vectors, index.space, index.books)


def append_codes(index: Index, vectors: DataFrame, path: str, checkpoint: str):
    """Stream new points into a codes table: each batch overwrites the folder of its own number, so a replayed batch adds nothing twice."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return assign(index, vectors).writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def windowed_counts(events: DataFrame, kind: str = "tumbling", late: str = "10 minutes") -> DataFrame:
    """(start, end, event_type, n, total) over tumbling (5 min), sliding (10 min by 5) or session (10 min gap) windows.

    On a stream, rows later than ``late`` are dropped; on a table the watermark does nothing, so this is its own batch twin.
    """
    span = {"tumbling": lambda: F.window("ts", "5 minutes"), "sliding": lambda: F.window("ts", "10 minutes", "5 minutes"), "session": lambda: F.session_window("ts", "10 minutes")}[kind]()
    grouped = events.withWatermark("ts", late).groupBy(span.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return grouped.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "total")


def distinct_events(events: DataFrame, late: str = "10 minutes") -> DataFrame:
    """Each event_id once, as far as the watermark remembers."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def drift(vectors: DataFrame, index: Index, limit: float = 1.0) -> DataFrame:
    """(part, n, spread, rebuild): running entropy spread of the index's subspaces for each of a stream's parts (a column ``part``).

    The state of a part is a count, sums and sums of squares of the projected components; the spread is that of the sums of logarithms of their variances.
    """
    space = index.space
    widths = np.cumsum([0, *space.widths])

    def update(key, frames: Iterator[pd.DataFrame], state):
        n, total, squares = state.get if state.exists else (0, [0.0] * int(widths[-1]), [0.0] * int(widths[-1]))
        total, squares = np.array(total), np.array(squares)
        for frame in frames:
            x = np.hstack(space.parts(np.stack([np.asarray(v, float) for v in frame["embedding"]])))
            n, total, squares = n + len(x), total + x.sum(axis=0), squares + (x * x).sum(axis=0)
        state.update((n, total.tolist(), squares.tolist()))
        var = np.maximum((squares - total**2 / n) / max(1, n - 1), 1e-12)
        blocks = [np.log(var[a:b]).sum() for a, b in zip(widths[:-1], widths[1:])]
        spread = float(max(blocks) - min(blocks))
        yield pd.DataFrame({"part": [key[0]], "n": [n], "spread": [spread], "rebuild": [spread > limit]})

    return vectors.groupBy("part").applyInPandasWithState(update, "part long, n long, spread double, rebuild boolean", "n long, total array<double>, squares array<double>", "update", "NoTimeout")
