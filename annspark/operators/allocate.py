"""Dealing eigenvectors to subspaces so that the subspaces' entropies balance."""

from __future__ import annotations

import heapq
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

#: Eigenvalues are floored at this share of the largest, so that logarithms exist for singular data.
FLOOR = 1e-12


def scale(values: np.ndarray, eps: float = FLOOR) -> np.ndarray:
    """Falling eigenvalues divided by the smallest (floored): all are at least 1."""
    values = np.maximum(values, eps * values[0] if values[0] > 0 else 1.0)
    return values / values[-1]


def greedy(values: np.ndarray, ns: int, s: int, eps: float = FLOOR) -> list[list[int]]:
    """Ranks of the eigenvalues of each block, in the order they came.

    The leading ns * s go one by one to the open block of the smallest product so far (kept as a sum
    of logarithms; ties to the lower block); a block closes when it holds s.
    """
    if ns * s > len(values):
        raise ValueError(f"{ns} blocks of {s} need {ns * s} directions; there are {len(values)}")
    gains = np.log(scale(np.asarray(values, float), eps))
    blocks: list[list[int]] = [[] for _ in range(ns)]
    open_ = [(0.0, j) for j in range(ns)]
    for rank in range(ns * s):
        held, j = heapq.heappop(open_)
        blocks[j].append(rank)
        if len(blocks[j]) < s:
            heapq.heappush(open_, (held + gains[rank], j))
    return blocks


def block_entropy(values: np.ndarray, blocks: list[list[int]]) -> np.ndarray:
    """Log determinant of the covariance within each block: the sum of its eigenvalues' logarithms."""
    safe = np.maximum(values, FLOOR * max(values[0], 1e-300))
    return np.array([np.log(safe[b]).sum() for b in blocks])


def spread(values: np.ndarray, blocks: list[list[int]]) -> float:
    """Largest less smallest block entropy."""
    h = block_entropy(values, blocks)
    return float(h.max() - h.min())


def brute_force(values: np.ndarray, ns: int, s: int) -> float:
    """The smallest spread of any deal of the leading ns * s values into ns blocks of s; for small tests."""

    def deals(rest: tuple[int, ...]):
        if not rest:
            yield []
            return
        for others in combinations(rest[1:], s - 1):
            block = [rest[0], *others]
            for more in deals(tuple(r for r in rest if r not in block)):
                yield [block, *more]

    return min(spread(values, d) for d in deals(tuple(range(ns * s))))


def allocation_frame(spark: SparkSession, values: np.ndarray, blocks: list[list[int]]) -> DataFrame:
    """(subspace, slot, rank, eigenvalue)."""
    return spark.createDataFrame([(j, i, r, float(values[r])) for j, b in enumerate(blocks) for i, r in enumerate(b)], "subspace int, slot int, rank int, eigenvalue double")
