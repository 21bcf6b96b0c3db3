"""R-trees over the rows of one partition: R* insertion, the quadratic split before it, and packed bulk loading."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from .lanes import bounded, passes

#: Entries per node, least filling and share of entries that are put in again.
CAPACITY, LEAST, AGAIN = 96, 0.4, 0.3


@dataclass
class Node:
    level: int  # 0: a leaf of objects
    lo: np.ndarray  # entries x m
    hi: np.ndarray
    items: list  # row numbers in a leaf, nodes above


@dataclass
class RTree:
    root: Node
    lo: np.ndarray
    hi: np.ndarray
    stats: dict[str, int] = field(default_factory=dict)


def _cover(node: Node) -> tuple[np.ndarray, np.ndarray]:
    return node.lo.min(axis=0), node.hi.max(axis=0)


def _volume(lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """In the unit cube; sides of zero count as very thin, so that ties are told apart in many dimensions."""
    return np.exp(np.log(np.maximum(hi - lo, 1e-9)).sum(axis=-1) / lo.shape[-1])


def _overlap(lo: np.ndarray, hi: np.ndarray, los: np.ndarray, his: np.ndarray) -> np.ndarray:
    side = np.minimum(hi, his) - np.maximum(lo, los)
    return np.where((side >= 0).all(axis=-1), np.exp(np.log(np.maximum(side, 1e-9)).sum(axis=-1) / lo.shape[-1]), 0.0)


def build(x: np.ndarray, variant: str = "rstar", *, upper: np.ndarray | None = None, capacity: int = CAPACITY) -> RTree:
    """A tree over points x, or over rectangles x .. upper. variant: 'rstar', 'quadratic' or 'packed'.

    Decisions are taken on dimensions scaled to [0, 1]; searches compare the values as they are.
    """
    lo, hi = x, x if upper is None else upper
    n, m = lo.shape
    if not n:
        return RTree(Node(0, lo, hi, []), lo, hi)
    least, span = np.nanmin(lo, axis=0), np.nanmax(hi, axis=0) - np.nanmin(lo, axis=0)
    scale = np.where(span > 0, span, 1.0)
    a, b = np.nan_to_num((lo - least) / scale), np.nan_to_num((hi - least) / scale)
    tree = _Packer(a, b, capacity).build() if variant == "packed" else _Inserter(a, b, capacity, variant == "rstar").build()
    _restore(tree, lo, hi)
    return RTree(tree, lo, hi)


def _restore(node: Node, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Boxes of the unscaled values, from the leaves up."""
    if node.level == 0:
        rows = np.array(node.items, np.int64)
        node.lo, node.hi = lo[rows], hi[rows]
    else:
        each = [_restore(child, lo, hi) for child in node.items]
        node.lo, node.hi = np.stack([e[0] for e in each]), np.stack([e[1] for e in each])
    return np.fmin.reduce(node.lo, axis=0), np.fmax.reduce(node.hi, axis=0)


class _Packer:
    """Sort-tile bulk loading, level by level."""

    def __init__(self, lo: np.ndarray, hi: np.ndarray, capacity: int):
        self.lo, self.hi, self.capacity = lo, hi, capacity

    def _tiles(self, centre: np.ndarray) -> list[np.ndarray]:
        m = min(centre.shape[1], 3)
        groups = [np.arange(len(centre))]
        for d in range(m):
            after = []
            for g in groups:
                slabs = max(1, int(np.ceil((len(g) / self.capacity) ** (1 / (m - d)))))
                order = g[np.argsort(centre[g, d], kind="stable")]
                after += [part for part in np.array_split(order, slabs) if len(part)]
            groups = after
        return [g[a : a + self.capacity] for g in groups for a in range(0, len(g), self.capacity)]

    def build(self) -> Node:
        nodes = [Node(0, self.lo[g], self.hi[g], g.tolist()) for g in self._tiles((self.lo + self.hi) / 2)]
        level = 0
        while len(nodes) > 1:
            level += 1
            boxes = [_cover(n) for n in nodes]
            lo, hi = np.stack([b[0] for b in boxes]), np.stack([b[1] for b in boxes])
            nodes = [Node(level, lo[g], hi[g], [nodes[k] for k in g]) for g in self._tiles((lo + hi) / 2)]
        return nodes[0]


class _Open:
    """A node that takes entries. Their boxes stand in columns, lower bounds over negated upper ones, so that a box holds
    another if it is nowhere greater, and covers by the minimum."""

    __slots__ = ("level", "box", "volume", "items")

    def __init__(self, level: int, box: np.ndarray, items: list, room: int):
        self.level, self.items = level, items
        self.box, self.volume = np.empty((len(box), room)), np.empty(room)
        self.box[:, : len(items)] = box
        if level:
            self.volume[: len(items)] = _volumes(box)

    def used(self) -> np.ndarray:
        return self.box[:, : len(self.items)]

    def cover(self) -> np.ndarray:
        return self.used().min(axis=1)

    def put(self, k: int, box: np.ndarray) -> None:
        self.box[:, k] = box
        if self.level:
            self.volume[k] = _volumes(box)

    def add(self, box: np.ndarray, item) -> None:
        self.put(len(self.items), box)
        self.items.append(item)

    def closed(self) -> Node:
        m = len(self.box) // 2
        box = self.used()
        return Node(self.level, box[:m].T.copy(), -box[m:].T, [child.closed() for child in self.items] if self.level else self.items)


def _volumes(box: np.ndarray) -> np.ndarray:
    """`_volume` of boxes in columns."""
    m = len(box) // 2
    return np.exp(np.log(np.maximum(-(box[:m] + box[m:]), 1e-9)).sum(axis=0) / m)


def _added(used: np.ndarray, wide: np.ndarray, some: np.ndarray) -> np.ndarray:
    """By how much the overlap of the entries some with all others grows if they widen; only pairs that then meet have
    volumes taken."""
    m = len(used) // 2
    side = np.maximum(wide[:, some, None], used[:, None, :])
    side = -(side[:m] + side[m:])
    meet = np.logical_and.reduce(side >= 0, axis=0)
    meet[np.arange(len(some)), some] = False
    i, j = meet.nonzero()
    out = np.zeros(meet.shape)
    both = np.concatenate((np.maximum(wide[:, some[i]], used[:, j]), np.maximum(used[:, some[i]], used[:, j])), axis=1)
    volume = _volumes(both)
    volume[(both[:m] + both[m:] > 0).any(axis=0)] = 0
    out[i, j] = volume[: len(i)] - volume[len(i) :]
    return out.sum(axis=1)


class _Inserter:
    def __init__(self, lo: np.ndarray, hi: np.ndarray, capacity: int, star: bool):
        self.capacity, self.star = capacity, star
        self.boxes = np.concatenate((lo, -hi), axis=1)
        self.root = self._open(0, self.boxes[:0].T, [])

    def _open(self, level: int, box: np.ndarray, items: list) -> _Open:
        return _Open(level, box, items, max(self.capacity, 2) + 1)

    def build(self) -> Node:
        for k, box in enumerate(self.boxes):
            self.reinserted: set[int] = set()
            self._insert(box, k, 0)
        return self.root.closed()

    def _insert(self, box: np.ndarray, item, level: int) -> None:
        path, node = [], self.root
        while node.level > level:
            k = self._choose(node, box)
            path.append((node, k))
            node = node.items[k]
        node.add(box, item)
        if len(node.items) > self.capacity:
            self._overflow(path, node)

    def _choose(self, node: _Open, box: np.ndarray) -> int:
        """The entry that takes the box, widened to hold it."""
        used, before = node.used(), node.volume[: len(node.items)]
        holds = np.logical_and.reduce(used <= box[:, None], axis=0).nonzero()[0]
        if len(holds):  # nothing grows, so no overlap does
            return int(holds[0] if len(holds) == 1 else holds[before[holds].argmin()])
        wide = np.minimum(used, box[:, None])
        after = _volumes(wide)
        order = np.lexsort((before, after - before))
        k = int(self._least_overlap(used, wide, order) if self.star and node.level == 1 else order[0])
        node.box[:, k], node.volume[k] = wide[:, k], after[k]
        return k

    def _least_overlap(self, used: np.ndarray, wide: np.ndarray, order: np.ndarray) -> int:
        """Of all entries the one whose widening adds least overlap with the others; equals keep the given order. None
        adds less than nothing, so the first that adds nothing ends the search."""
        sums = []
        for some in (order[:4], order[4:16], order[16:]):
            sums.append(np.round(_added(used, wide, some), 12))
            free = np.flatnonzero(sums[-1] <= 0)
            if len(free):
                return some[free[0]]
        return order[np.concatenate(sums).argmin()]

    def _overflow(self, path: list[tuple[_Open, int]], node: _Open) -> None:
        while len(node.items) > self.capacity:
            if self.star and node is not self.root and node.level not in self.reinserted:
                self.reinserted.add(node.level)
                self._again(path, node)
                return
            one, two = self._split(node)
            if node is self.root:
                self.root = self._open(node.level + 1, np.stack([one.cover(), two.cover()], axis=1), [one, two])
                return
            parent, k = path.pop()
            parent.put(k, one.cover())
            parent.items[k] = one
            parent.add(two.cover(), two)
            node = parent

    def _again(self, path: list[tuple[_Open, int]], node: _Open) -> None:
        """Takes the entries farthest from the node's centre out and inserts them from the top, nearest first."""
        box, cover, m = node.used().copy(), node.cover(), len(node.box) // 2
        far = np.argsort(-((((box[:m] - box[m:]) - (cover[:m] - cover[m:])[:, None]) ** 2).sum(axis=0)), kind="stable")[: int(AGAIN * len(node.items))]
        keep = np.setdiff1d(np.arange(len(node.items)), far)
        out = [(box[:, k], node.items[k]) for k in far[::-1]]
        node.items = [node.items[k] for k in keep]
        node.box[:, : len(keep)], node.volume[: len(keep)] = box[:, keep], node.volume[keep]
        for parent, k in reversed(path):
            parent.put(k, parent.items[k].cover())
        for entry in out:
            self._insert(*entry, node.level)

    def _split(self, node: _Open) -> tuple[_Open, _Open]:
        box, m = node.used(), len(node.box) // 2
        plain = Node(node.level, box[:m].T.copy(), -box[m:].T, node.items)
        groups = self._axis_split(plain) if self.star else self._quadratic(plain)
        return tuple(self._open(node.level, box[:, g], [node.items[k] for k in g]) for g in groups)

    def _axis_split(self, node: Node) -> tuple[np.ndarray, np.ndarray]:
        """The axis of the least sum of margins over all legal cuts, and on it the cut of the least overlap."""
        n, m = node.lo.shape
        fewest = max(1, int(LEAST * self.capacity))
        cuts = np.arange(fewest, n - fewest + 1)
        orders = np.argsort(np.stack((node.lo.T, node.hi.T), axis=1).reshape(2 * m, n), axis=1, kind="stable")  # per axis by lower, then by upper bound
        lo, hi = node.lo[orders], node.hi[orders]
        a_lo, a_hi = (f.accumulate(x, axis=1)[:, cuts - 1] for f, x in ((np.minimum, lo), (np.maximum, hi)))
        b_lo, b_hi = (f.accumulate(x[:, ::-1], axis=1)[:, ::-1][:, cuts] for f, x in ((np.minimum, lo), (np.maximum, hi)))
        margins = (a_hi - a_lo).reshape(2 * m, -1).sum(axis=1) + (b_hi - b_lo).reshape(2 * m, -1).sum(axis=1)
        axis = int((margins[::2] + margins[1::2]).argmin())
        scored = []
        for k in (2 * axis, 2 * axis + 1):
            over, area = _overlap(a_lo[k], a_hi[k], b_lo[k], b_hi[k]), _volume(a_lo[k], a_hi[k]) + _volume(b_lo[k], b_hi[k])
            c = int(np.lexsort((area, over))[0])
            scored.append(((float(over[c]), float(area[c])), orders[k], int(cuts[c])))
        _, order, cut = min(scored, key=lambda s: s[0])
        return order[:cut], order[cut:]

    def _quadratic(self, node: Node) -> tuple[np.ndarray, np.ndarray]:
        """Seeds that would waste most together; then the entry with the strongest preference, one after another."""
        n = len(node.items)
        fewest = max(1, int(LEAST * self.capacity))
        volume = _volume(node.lo, node.hi)
        waste = _volume(np.minimum(node.lo[:, None], node.lo[None]), np.maximum(node.hi[:, None], node.hi[None])) - volume[:, None] - volume[None]
        np.fill_diagonal(waste, -np.inf)
        groups = [[k] for k in divmod(int(waste.argmax()), n)]
        cover = [[node.lo[g[0]].copy(), node.hi[g[0]].copy()] for g in groups]
        rest = np.setdiff1d(np.arange(n), [g[0] for g in groups])
        while len(rest):
            short = [k for k in (0, 1) if len(groups[k]) + len(rest) <= fewest]
            if short:
                groups[short[0]] += rest.tolist()
                break
            growth = np.stack([_volume(np.minimum(node.lo[rest], lo), np.maximum(node.hi[rest], hi)) - _volume(lo, hi) for lo, hi in cover])
            pick = int(np.abs(growth[0] - growth[1]).argmax())
            k = int(rest[pick])
            side = int(growth[0][pick] > growth[1][pick]) if growth[0][pick] != growth[1][pick] else int(len(groups[0]) > len(groups[1]))
            groups[side].append(k)
            cover[side] = [np.minimum(cover[side][0], node.lo[k]), np.maximum(cover[side][1], node.hi[k])]
            rest = np.delete(rest, pick)
        return np.array(groups[0]), np.array(groups[1])


def arrays(tree: RTree) -> dict[str, np.ndarray]:
    """The tree as plain arrays, nodes breadth first: level and first entry of each, the entries' boxes and what they hold
    (a row in a leaf, a node above)."""
    level, first, lows, highs, held = [], [0], [], [], []
    queue, at = [tree.root], 1
    for node in queue:  # grows while it is read
        level.append(node.level)
        first.append(first[-1] + len(node.items))
        lows.append(node.lo)
        highs.append(node.hi)
        if node.level:
            held += range(at, at + len(node.items))
            at += len(node.items)
            queue += node.items
        else:
            held += node.items
    return {"level": np.array(level), "first": np.array(first), "lo": np.concatenate(lows), "hi": np.concatenate(highs), "held": np.array(held, np.int64)}


def search(tree: RTree | dict[str, np.ndarray], lo: np.ndarray, hi: np.ndarray, *, accept_contained: bool = False, k: int | None = None) -> tuple[np.ndarray, dict[str, int]]:
    """(rows that meet the box, counters). NaN bounds are absent; rows with NaN in a bounded dimension never meet.

    k: dimensions of a box compared at once, in inner nodes and leaves. accept_contained: a leaf that lies wholly in
    the box is taken untested.
    """
    a = tree if isinstance(tree, dict) else arrays(tree)
    dims = bounded(lo, hi)
    low, high = np.where(np.isnan(lo), -np.inf, lo)[dims], np.where(np.isnan(hi), np.inf, hi)[dims]
    hits: list[np.ndarray] = []
    nodes = leaves = tested = compared = 0
    frontier = np.zeros(1, np.int64)
    while len(frontier):
        nodes += len(frontier)
        sizes = a["first"][frontier + 1] - a["first"][frontier]
        entry = np.repeat(a["first"][frontier] - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
        leaf = a["level"][frontier[0]] == 0  # all nodes of a level are leaves or none is
        if leaf:
            leaves += len(frontier)
            if accept_contained and len(entry):
                starts = (np.cumsum(sizes) - sizes)[sizes > 0]
                within = ((a["lo"][entry][:, dims] >= low) & (a["hi"][entry][:, dims] <= high)).all(axis=1)
                whole = np.repeat(np.logical_and.reduceat(within, starts), sizes[sizes > 0])
                hits.append(a["held"][entry[whole]])
                entry = entry[~whole]
            tested += len(entry)
        ok, c = passes(a["lo"][entry], a["hi"][entry], lo, hi, k)
        compared += c
        if leaf:
            hits.append(a["held"][entry[ok]])
            break
        frontier = a["held"][entry[ok]]
    return np.concatenate(hits) if hits else np.zeros(0, np.int64), {"nodes_visited": nodes, "leaves_visited": leaves, "compared": compared, "objects_tested": tested, "nodes": len(a["level"])}


def leaves_of(node: Node) -> list[Node]:
    return [node] if node.level == 0 else [leaf for child in node.items for leaf in leaves_of(child)]


def leaf_overlap(tree: RTree) -> float:
    """Sum of the overlap of all pairs of leaves, as the geometric mean of the shared sides."""
    covers = [_cover(leaf) for leaf in leaves_of(tree.root) if leaf.items]
    lo, hi = np.stack([c[0] for c in covers]), np.stack([c[1] for c in covers])
    return float(sum(_overlap(lo[k], hi[k], lo[k + 1 :], hi[k + 1 :]).sum() for k in range(len(lo) - 1)))
