"""A VA-file over the rows of one partition: a bucket of rows per occupied cell, looked up by cell codes."""

from __future__ import annotations

import numpy as np

from .lanes import passes

#: The code of a value that no cell holds (NaN). Fixed value.
NONE = 255


def build(x: np.ndarray, bits: int = 2) -> dict[str, np.ndarray]:
    """cuts (m x 2^bits - 1, equal widths), cells (occupied codes), at (offsets of their buckets), rows, x (by bucket).

    The outermost cells are open-ended, so later values beyond them still have a cell.
    """
    n, m = x.shape
    parts = 2**bits
    finite = np.where(np.isfinite(x), x, np.nan)
    with np.errstate(invalid="ignore"):
        some = np.isfinite(x).any(axis=0) if n else np.zeros(m, bool)
        lo, hi = (np.array([f(finite[:, j]) if some[j] else 0.0 for j in range(m)]) for f in (np.nanmin, np.nanmax))
    cuts = lo[:, None] + (hi - lo)[:, None] / parts * np.arange(1, parts)[None]
    codes = np.zeros((n, m), np.uint8)
    for j in range(m):
        codes[:, j] = np.where(np.isnan(x[:, j]), NONE, np.searchsorted(cuts[j], x[:, j], side="right"))
    if not n:
        return {"cuts": cuts, "cells": codes, "at": np.zeros(1, np.int64), "rows": np.zeros(0, np.int64), "x": x}
    order = np.lexsort(codes.T[::-1])
    ordered = codes[order]
    starts = np.flatnonzero(np.concatenate(([True], (ordered[1:] != ordered[:-1]).any(axis=1))))
    return {"cuts": cuts, "cells": ordered[starts], "at": np.append(starts, n), "rows": order, "x": np.ascontiguousarray(x[order])}


def code_range(cuts: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each bounded dimension the first and the last code; NaN where it is free."""
    top = cuts.shape[1]
    free = np.isnan(lo) & np.isnan(hi)
    first = np.array([0 if np.isnan(v) else np.searchsorted(c, v, side="right") for c, v in zip(cuts, lo, strict=True)], float)
    last = np.array([top if np.isnan(v) else np.searchsorted(c, v, side="right") for c, v in zip(cuts, hi, strict=True)], float)
    return np.where(free, np.nan, first), np.where(free, np.nan, last)


def search(held: dict[str, np.ndarray], lo: np.ndarray, hi: np.ndarray, k: int | None = None) -> tuple[np.ndarray, dict[str, int]]:
    cells, at = held["cells"], held["at"]
    met, compared = passes(cells, cells, *code_range(held["cuts"], lo, hi), k)
    sizes = at[met + 1] - at[met]
    tested = np.repeat(at[met] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
    x = held["x"][tested]
    found, more = passes(x, x, lo, hi, k)
    return held["rows"][tested[found]], {"nodes_visited": len(met), "nodes": len(cells), "compared": compared + more, "objects_tested": len(tested)}
