"""Subspaces of given dimensions: by seeded sampling, or contiguous; and the two halves of each."""

from __future__ import annotations

import numpy as np


def contiguous(d: int, ns: int) -> list[np.ndarray]:
    """``ns`` runs of floor(d / ns) dimensions; the last takes what remains."""
    s = d // ns
    if not s:
        raise ValueError(f"{ns} subspaces need at least as many dimensions, not {d}")
    return [np.arange(j * s, d if j == ns - 1 else (j + 1) * s) for j in range(ns)]


def sampled(d: int, ns: int, seed: int = 17) -> list[np.ndarray]:
    """The same sizes, dimensions drawn without replacement."""
    order = np.random.default_rng(seed).permutation(d)
    return [np.sort(order[dims]) for dims in contiguous(d, ns)]


def halves(width: int) -> tuple[slice, slice]:
    """The first floor(width / 2) slots, and the others."""
    return slice(0, width // 2), slice(width // 2, width)
