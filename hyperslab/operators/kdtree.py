"""kd-trees over the rows of one partition: every node holds an object, the delimiter dimension cycles with depth."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from .lanes import passes


@dataclass
class KdTree:
    """Nodes in breadth-first order. bucket: rows below the depth limit, tested one by one with their node."""

    x: np.ndarray  # objects, n x m
    row: np.ndarray
    left: np.ndarray
    right: np.ndarray
    depth: np.ndarray
    bucket: dict[int, np.ndarray]


def build(x: np.ndarray, variant: str = "insertion", max_depth: int | None = None) -> KdTree:
    """variant 'insertion': the tree that inserting the rows in order makes; 'median': each node splits at a median.

    Built level by level, all nodes of a level at once: the first row of a subset in insertion order becomes its node, the others go left if
    they are smaller or equal in the node's dimension. Many equal values would make a chain; below max_depth a
    subset stays a bucket.
    """
    n, m = x.shape
    limit = max_depth if max_depth is not None else max(16, int(4 * np.log2(n + 1)))
    row, left, right, depth = (np.full(n, -1, np.int32) for _ in range(4))
    bucket: dict[int, np.ndarray] = {}
    rows, starts, parent, side = np.arange(n, dtype=np.int32), np.zeros(min(1, n), np.int64), np.full(1, -1), np.zeros(1, np.int64)
    first = d = 0  # number of the level's first node
    while len(rows):
        count, dim = len(starts), d % m
        sizes = np.diff(np.append(starts, len(rows)))
        nodes = first + np.arange(count)
        if d:
            left[parent[side == 0]], right[parent[side == 1]] = nodes[side == 0], nodes[side == 1]
        depth[nodes] = d
        if d >= limit:
            row[nodes] = rows[starts]
            bucket = {int(nodes[g]): rows[starts[g] + 1 : starts[g] + sizes[g]] for g in np.flatnonzero(sizes > 1)}
            first += count
            break
        group = np.repeat(np.arange(count), sizes)
        head = starts
        if variant == "median":
            head = np.where(sizes > 2, np.lexsort((x[rows, dim], group))[starts + sizes // 2], starts)
        row[nodes] = rows[head]
        cut = x[row[nodes], dim]
        others = np.ones(len(rows), bool)
        others[head] = False
        rest, group = rows[others], group[others]
        goes_left = x[rest, dim] <= cut[group]
        loads = np.bincount(2 * group + ~goes_left, minlength=2 * count)  # left and right of every node
        at = np.cumsum(loads) - loads
        place = np.empty(len(rest), np.int64)
        for s, chosen in ((0, goes_left), (1, ~goes_left)):
            own = group[chosen]
            before = np.cumsum(loads[s::2]) - loads[s::2]
            place[chosen] = at[s::2][own] + np.arange(len(own)) - before[own]
        rows = np.empty(len(rest), np.int32)
        rows[place] = rest
        full = np.flatnonzero(loads)
        starts, parent, side = at[full], first + full // 2, full % 2
        first, d = first + count, d + 1
    return KdTree(x, row[:first], left[:first], right[:first], depth[:first], bucket)


def search(tree: KdTree, lo: np.ndarray, hi: np.ndarray, k: int | None = None) -> tuple[np.ndarray, dict[str, int]]:
    """(rows in the box, counters). A frontier of nodes per step; an unspecified delimiter opens both sides."""
    m = tree.x.shape[1] if tree.x.ndim == 2 else 1
    hits, visited, compared, objects = [], 0, 0, 0
    frontier = np.zeros(min(1, len(tree.row)), np.int64)
    while len(frontier):
        visited += len(frontier)
        rows = tree.row[frontier]
        tested = np.concatenate([rows, *(tree.bucket[f] for f in frontier.tolist() if f in tree.bucket)]) if tree.bucket else rows
        x = tree.x[tested]
        ok, c = passes(x, x, lo, hi, k)
        compared, objects = compared + c, objects + len(tested)
        hits.append(tested[ok])
        dim = tree.depth[frontier] % m
        value = tree.x[rows, dim]
        opens_left = ~(lo[dim] > value)
        opens_right = ~(hi[dim] <= value)
        nan = np.isnan(value)  # objects without a value there went right
        nxt = np.concatenate((tree.left[frontier][opens_left | nan], tree.right[frontier][opens_right | nan]))
        frontier = nxt[nxt >= 0]
    return np.concatenate(hits) if hits else np.zeros(0, np.int64), {"nodes_visited": visited, "nodes": len(tree.row), "compared": compared, "objects_tested": objects}


def arrays(tree: KdTree) -> dict[str, np.ndarray]:
    """The tree as plain arrays; buckets as one list with offsets."""
    nodes = np.array(sorted(tree.bucket), np.int64)
    held = [tree.bucket[k] for k in nodes.tolist()]
    ends = np.cumsum([0, *map(len, held)])
    return {"x": tree.x, "row": tree.row, "left": tree.left, "right": tree.right, "depth": tree.depth, "bucket_of": nodes, "bucket_at": ends, "bucket": np.concatenate(held) if held else np.zeros(0, np.int64)}


def of_arrays(a: dict[str, np.ndarray]) -> KdTree:
    bucket = {int(k): a["bucket"][a["bucket_at"][i] : a["bucket_at"][i + 1]] for i, k in enumerate(a["bucket_of"])}
    return KdTree(a["x"], a["row"], a["left"], a["right"], a["depth"], bucket)
