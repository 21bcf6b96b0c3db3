"""What a scan keeps of one partition: its objects by rows or by columns. Searched like an index, so all compare alike."""

from __future__ import annotations

import numpy as np

from .lanes import bounded, passes


def build_rows(x: np.ndarray) -> dict[str, np.ndarray]:
    return {"x": np.ascontiguousarray(x)}


def build_columns(x: np.ndarray) -> dict[str, np.ndarray]:
    return {"columns": np.ascontiguousarray(x.T)}


def search_rows(held: dict[str, np.ndarray], lo: np.ndarray, hi: np.ndarray, k: int | None = None) -> tuple[np.ndarray, dict[str, int]]:
    x = held["x"]
    rows, compared = passes(x, x, lo, hi, k)
    return rows, {"nodes_visited": 0, "nodes": 0, "compared": compared, "objects_tested": len(x)}


def search_columns(held: dict[str, np.ndarray], lo: np.ndarray, hi: np.ndarray, k: int | None = None) -> tuple[np.ndarray, dict[str, int]]:
    """Every queried column is compared whole and the bitmaps are combined; k does not apply to one dimension."""
    columns = held["columns"]
    bits = np.ones(columns.shape[1], bool)
    dims = bounded(lo, hi)
    for j in dims:
        c = columns[j]
        bits &= (c >= (-np.inf if np.isnan(lo[j]) else lo[j])) & (c <= (np.inf if np.isnan(hi[j]) else hi[j]))
    return np.flatnonzero(bits), {"nodes_visited": 0, "nodes": 0, "compared": len(dims) * len(bits), "objects_tested": len(bits)}
