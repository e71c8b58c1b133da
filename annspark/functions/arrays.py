"""Between Arrow list columns and numpy matrices, and the k best of each row."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """A list column of equal lengths as a matrix of doubles."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64, copy=False)
    return flat.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def lists(rows: np.ndarray, kind: pa.DataType | None = None, missing: np.ndarray | None = None) -> pa.Array:
    """A matrix as a list column, null where ``missing``."""
    n, width = rows.shape
    return pa.ListArray.from_arrays(pa.array(np.arange(n + 1) * width, pa.int32()), pa.array(np.ascontiguousarray(rows).ravel(), kind), mask=None if missing is None else pa.array(missing))


#: Numbers of a rows x queries matrix that a task works on at once.
CELLS = 1 << 22


def slices(batch: pa.RecordBatch, queries: int) -> Iterator[pa.RecordBatch]:
    """Parts of a batch whose rows x queries matrices stay below ``CELLS`` numbers."""
    step = max(1, CELLS // max(1, queries))
    for lo in range(0, batch.num_rows, step):
        yield batch.slice(lo, step)


def squared_distances(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Rows of x against rows of q by one matrix product; may be off by rounding."""
    return np.maximum(0, (x * x).sum(1)[:, None] - 2 * (x @ q.T) + (q * q).sum(1))


#: Numbers of a rows x queries matrix of ``Rough`` values: few enough to stay in a core's cache.
NEAR_CELLS = 1 << 18
#: Queries of a tile, and rows (so few that counts of them fit a byte).
TILE, ROWS = 1 << 11, 255


class Rough:
    """Squared distances of rows to fixed queries by one matrix product, and how far rounding may have moved them from the sums of squares."""

    def __init__(self, q: np.ndarray, single: bool = True):
        norms = (q * q).sum(axis=1)
        self.most = float(norms.max(initial=0))
        # beyond what single precision holds
        self.kind = np.float32 if single and self.most < 1e30 else np.float64
        self.right = np.concatenate([-2 * q.T, np.ones((1, len(q))), norms[None]]).astype(self.kind)

    def __call__(self, x: np.ndarray) -> tuple[np.ndarray, float]:
        """(rows x queries, slack)."""
        left, slack = self._left(x)
        return left @ self.right.astype(left.dtype, copy=False), slack

    def _left(self, x: np.ndarray) -> tuple[np.ndarray, float]:
        norms = (x * x).sum(axis=1)
        most = float(norms.max(initial=0))
        kind = self.kind if most < 1e30 else np.float64
        return np.column_stack([x, norms, np.ones(len(x))]).astype(kind), self.slack(most, x.shape[1])

    def tiles(self, x: np.ndarray) -> Iterator[tuple[slice, np.ndarray, float]]:
        """(queries, rows x these queries, slack) for a few queries after another, so that a product is still in the core's cache when it is read. The next tile overwrites it."""
        left, slack = self._left(x)
        right = self.right.astype(left.dtype, copy=False)
        out = np.empty(len(x) * min(TILE, right.shape[1]), left.dtype)
        for lo in range(0, right.shape[1], TILE):
            some = right[:, lo : lo + TILE]
            yield slice(lo, lo + some.shape[1]), np.matmul(left, some, out=out[: len(x) * some.shape[1]].reshape(len(x), -1)), slack

    def slack(self, most: float, width: int) -> float:
        """The same for rows of at most the squared length ``most``."""
        unit = 1.2e-7 if self.kind == np.float32 and most < 1e30 else 2.3e-16
        return 1.1 * unit * (width + 6) * (most + self.most) + 1e-36


def low_slices(batch: pa.RecordBatch, queries: int, cells: int = NEAR_CELLS) -> Iterator[pa.RecordBatch]:
    """Parts of a batch for ``Rough``: of at most 255 rows, so that counts of rows fit a byte."""
    step = min(ROWS, max(1, cells // max(1, queries)))
    for lo in range(0, batch.num_rows, step):
        yield batch.slice(lo, step)


def places(mask: np.ndarray) -> np.ndarray:
    """``np.flatnonzero`` of a mask that holds few, eight at a look."""
    flat = mask.ravel()
    whole = len(flat) // 8 * 8
    at = (np.flatnonzero(flat[:whole].view(np.uint64))[:, None] * 8 + np.arange(8)).ravel()
    return np.concatenate([at[flat[at]], whole + np.flatnonzero(flat[whole:])])


def by_query(mask: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(query, its rows) of every query (column of the mask) that has any."""
    who, row = np.nonzero(mask.T)
    cuts = np.searchsorted(who, np.arange(mask.shape[1] + 1))
    for i in np.flatnonzero(np.diff(cuts)):
        yield int(i), row[cuts[i] : cuts[i + 1]]


class Nearest:
    """The k nearest rows seen so far, for each of several queries; ties go to the smaller id.

    Pairs that may be among them are gathered, and cut to k a query when there are many: no step works query by query.
    """

    #: Numbers of the rows whose distances are taken at once, and pairs gathered before they are cut (or as many as are kept, if more).
    NUMBERS, GATHERED = 1 << 21, 1 << 18

    def __init__(self, queries: np.ndarray, k: int):
        self.q, self.k = queries, k
        self.kept = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)  # query, id, distance
        self.new, self.held = [], 0
        self.bound = np.full(len(queries), np.inf)  # distance beyond which a row has no chance

    def offer(self, i: int, ids: np.ndarray, x: np.ndarray) -> None:
        """Rows for query i."""
        self.offer_pairs(np.full(len(ids), i), np.arange(len(ids)), ids, x)

    def offer_pairs(self, who: np.ndarray, row: np.ndarray, ids: np.ndarray, x: np.ndarray) -> None:
        """Row ``row[p]`` of (ids, x) for query ``who[p]``: distances are taken one by one, so that equal rows are equally far."""
        step = max(1, self.NUMBERS // max(1, x.shape[1]))
        for lo in range(0, len(who), step):
            i, r = who[lo : lo + step], row[lo : lo + step]
            gap = x[r]
            gap -= self.q[i]
            dist = np.sqrt(np.multiply(gap, gap, out=gap).sum(axis=1))
            near = np.flatnonzero(dist <= self.bound[i])
            self.new.append((i[near], ids[r[near]], dist[near]))
            self.held += len(near)
            if self.held > max(self.GATHERED, len(self.kept[0])):
                self.cut()

    def cut(self) -> None:
        """Keep the k nearest of every query."""
        who, ids, dist = (np.concatenate(c) for c in zip(self.kept, *self.new))
        order = np.lexsort((ids, dist, who))
        who = who[order]
        place = np.arange(len(who)) - np.searchsorted(who, who)
        order, who = order[place < self.k], who[place < self.k]
        self.kept, self.new, self.held = (who, ids[order], dist[order]), [], 0
        last = np.flatnonzero(place[place < self.k] == self.k - 1)
        self.bound[who[last]] = self.kept[2][last]

    def offer_all(self, ids: np.ndarray, x: np.ndarray) -> None:
        """Rows for every query: all rows that rounding leaves a chance are offered."""
        if not len(ids) or not len(self.q):
            return
        if not hasattr(self, "_rough"):
            self._rough = Rough(self.q)
        new = ~np.isfinite(self.bound)
        for lo in range(0, len(ids), ROWS):
            part, own = x[lo : lo + ROWS], ids[lo : lo + ROWS]
            for some, rough, slack in self._rough.tiles(part):
                if not lo and len(part) > self.k and new[some].any():
                    # the k-th of these rows is a bound
                    kth = np.maximum(0, np.partition(rough, self.k - 1, axis=0)[self.k - 1].astype(np.float64))
                    self.bound[some] = np.minimum(self.bound[some], np.sqrt(kth + 2 * slack))
                at = places(rough <= (self.bound[some] ** 2 + 2 * slack).astype(rough.dtype))
                if len(at):
                    row, i = np.divmod(at, rough.shape[1])
                    self.offer_pairs(i + some.start, row, own, part)

    def offer_mask(self, mask: np.ndarray, ids: np.ndarray, x: np.ndarray) -> None:
        """Rows for the queries that a rows x queries mask tells: for many pairs, as rough distances leave few of them."""
        if not hasattr(self, "_rough"):
            self._rough = Rough(self.q)
        new = ~np.isfinite(self.bound)
        for lo in range(0, len(ids), ROWS):
            part = x[lo : lo + ROWS]
            for some, rough, slack in self._rough.tiles(part):
                if not lo and len(part) > self.k and new[some].any():
                    # the k-th of these rows is a bound, where so many are meant
                    kth = np.maximum(0, np.partition(np.where(mask[:ROWS, some], rough, np.inf), self.k - 1, axis=0)[self.k - 1].astype(np.float64))
                    self.bound[some] = np.minimum(self.bound[some], np.sqrt(kth + 2 * slack))
                at = places((rough <= (self.bound[some] ** 2 + 2 * slack).astype(rough.dtype)) & mask[lo : lo + ROWS, some])
                if len(at):
                    row, i = np.divmod(at, rough.shape[1])
                    self.offer_pairs(i + some.start, row, ids[lo : lo + ROWS], part)

    def batch(self, qids: np.ndarray) -> pa.RecordBatch:
        self.cut()
        who, ids, dist = self.kept
        return pa.RecordBatch.from_arrays([pa.array(qids[who]), pa.array(ids), pa.array(dist)], names=["qid", "vec_id", "dist"])
