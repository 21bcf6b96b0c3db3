"""Comparing many boxes or points with one query, k dimensions at a time."""

from __future__ import annotations

import numpy as np


def bounded(lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """The dimensions that a query bounds; an absent bound is NaN."""
    return np.flatnonzero(~(np.isnan(lo) & np.isnan(hi)))


def groups(dims: np.ndarray, k: int | None) -> list[np.ndarray]:
    """Chunks of k dimensions, and the tail one by one; fewer than k dimensions go one by one as well."""
    full = len(dims) // k * k if k else 0
    return [dims[a : a + k] for a in range(0, full, k or 1)] + [dims[a : a + 1] for a in range(full, len(dims))]


def passes(low: np.ndarray, high: np.ndarray, lo: np.ndarray, hi: np.ndarray, k: int | None = None) -> tuple[np.ndarray, int]:
    """(which of the boxes low .. high meet the query lo .. hi, dimensions compared). A point has low = high.

    A box leaves at its first chunk that fails; NaN coordinates meet no bound.
    """
    a, b = np.where(np.isnan(lo), -np.inf, lo), np.where(np.isnan(hi), np.inf, hi)
    live, compared = np.arange(len(low)), 0
    for g in groups(bounded(lo, hi), k):
        compared += len(live) * len(g)
        if len(live) == len(low):
            x, y = low[:, g], high[:, g]
        else:
            at = np.ix_(live, g)
            x, y = low[at], (low if high is low else high)[at]
        good = ((y >= a[g]) & (x <= b[g])).all(axis=1)
        live = live[good]
        if not len(live):
            break
    return live, compared
