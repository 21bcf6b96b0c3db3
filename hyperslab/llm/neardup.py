"""Near-duplicate documents by an LSH forest over MinHash signatures.

A document is its set of word shingles. Documents with equal sets are one class, and only the class's first
document goes on. Each of several trees sorts the signatures in an order of hashes of its own, dealt to tasks by ranges
of that order. Documents that agree in the first hashes are a region. Where a region is dense it is deepened, hash by
hash, until the documents that share the longer prefix are few or the order's hashes are used up: each document has the
depth of its own neighbourhood. The neighbours with whom it shares the prefix of that depth are its candidates; a compact
sketch weighs them, and each document takes one partner per tree. Links are confirmed on the full sets.

Deepening leaves pairs open that share the short prefix only. What was deepened, or cut by the bounds of a task, is
settled afterwards if the confirmed links leave several components in it: regions of up to `block` documents are read
whole, every pair across components; the documents of larger ones go to a second forest of more trees and twice the
depth, in which regions are far smaller; what is large there still is read by pairs of blocks. Pairs across components
go through whole signatures, a finer one-permutation sketch and full sets.

Chance alone limits recall: a pair of similarity s shares no region of any tree with probability
(1 - s^depth)^trees, 5e-6 at 0.75 in the first forest; 2.5e-5 in the second, whose trees draw on the same hashes; the
sketch's bound is five standard deviations wide.

Cases: a null or empty text has no shingles and links to nothing; fewer words than a shingle make one shingle;
rows that share an id count as one document; a null id stays a row and takes the component of its class in `linked`,
and is kept by `deduplicated` if its component has no other row that goes before it; an empty table gives an empty
result; further columns are ignored by `linked` and kept by `deduplicated`.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .graph import components
from .words import mixed, shingles, words_of


@dataclass(frozen=True)
class Forest:
    trees: int = 32
    depth: int = 4  # hashes that a region shares
    more: int = 4  # hashes, at most 4, that the order goes on to, by which dense regions are deepened
    window: int = 64  # neighbours that a document is weighed with; a region of more is deepened
    block: int = 4096  # rows of a region, or of a block of it, that are read again at once
    second: tuple[int, int] = (8, 256)  # depth and trees of the forest for large regions
    shingle: int = 5
    bins: int = 1024  # of the finer sketch that pairs across components go through; a power of two
    percent: int = 75  # 100 * intersection >= percent * union
    seed: int = 1

    @property
    def hashes(self) -> int:
        return self.trees * self.depth

    def multipliers(self) -> np.ndarray:
        return mixed(np.arange(1, self.hashes + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(self.seed)) | np.uint64(1)

    def orders(self, level: int = 0) -> tuple[np.ndarray, int]:
        """(the hashes of every tree's order, how many of them make a region). Level 1 is the second forest."""
        if level == 0:
            return (np.arange(self.trees)[:, None] * self.depth + np.arange(self.depth + self.more)) % self.hashes, self.depth
        depth, trees = min(self.second[0], self.hashes), self.second[1]
        rng = np.random.default_rng(self.seed)
        drawn = np.stack([rng.permutation(self.hashes) for _ in range(trees)])
        return drawn[:, np.arange(depth + self.more) % self.hashes], depth

    def most_differing(self) -> int:
        """Bits in which sketches may differ: as expected at the similarity bound, and five standard deviations."""
        size, p = min(self.hashes, 128), (1 - self.percent / 100) / 2
        return int(size * p + 5 * (size * p * (1 - p)) ** 0.5)

    def least_equal(self) -> int:
        """Hashes in which signatures agree at the similarity bound, less five standard deviations."""
        p = self.percent / 100
        return int(self.hashes * p - 5 * (self.hashes * p * (1 - p)) ** 0.5)


def sets_of(texts: pa.Array, size: int) -> Iterator[np.ndarray]:
    """Of each text its distinct shingle hashes, ascending."""
    hashes, at = shingles(words_of(texts, lower=True), size)
    for k in range(len(at) - 1):
        yield np.unique(hashes[at[k] : at[k + 1]])


def signature(found: np.ndarray, multipliers: np.ndarray) -> np.ndarray:
    least = np.full(len(multipliers), np.iinfo(np.uint64).max, np.uint64)
    with np.errstate(over="ignore"):
        for at in range(0, len(found), 2048):
            np.minimum(least, (multipliers[:, None] * found[None, at : at + 2048]).min(axis=1), out=least)
    return (least >> np.uint64(32)).astype("<u4")


def binned(found: np.ndarray, bins: int) -> np.ndarray:
    """One-permutation MinHash: a byte of the least hash in each bin, 0 in an empty bin."""
    x = mixed(found)
    top = np.uint64(64 - int(bins).bit_length() + 1)
    least = np.full(bins, np.iinfo(np.uint64).max, np.uint64)
    np.minimum.at(least, (x >> top).astype(np.int64), x)
    return np.where(least == np.iinfo(np.uint64).max, 0, 1 + (least >> np.uint64(8)) % np.uint64(255)).astype(np.uint8)


def _close(x: np.ndarray, y: np.ndarray, n: np.ndarray, forest: Forest) -> np.ndarray:
    """Whether rows x and y of bins, of sets of n elements together, allow the similarity.

    Of a union of f elements m bins are filled; the share of equal ones has the variance
    s (1 - s) (f - m) / (m (f - 1)), so small sets are judged nearly exactly. The bound leaves five deviations.
    """
    filled = ((x | y) != 0).sum(axis=1)
    equal = ((x == y) & (x != 0)).sum(axis=1)
    p = forest.percent / 100
    union = np.maximum(n / (1 + p), filled)
    deviation = np.sqrt(p * (1 - p) * (union - filled) / np.maximum(filled * (union - 1), 1))
    return equal >= filled * (p - 5 * deviation) - 1  # one bin more for the discreteness of small sets


def profiles(docs: DataFrame, forest: Forest) -> DataFrame:
    """doc_id, n_shingles, set_digest (null for no shingles), signature of every row of docs(doc_id, text)."""
    multipliers = forest.multipliers()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.parts(batch, "text", 4 << 20):
                counts, digests, signatures = [], [], []
                for found in sets_of(part.column("text"), forest.shingle):
                    counts.append(len(found))
                    digests.append(hashlib.blake2b(found.tobytes(), digest_size=16).digest() if len(found) else None)
                    signatures.append(signature(found, multipliers).tobytes() if len(found) else None)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(counts, pa.int64()), pa.array(digests, pa.binary()), pa.array(signatures, pa.binary())], names=["doc_id", "n_shingles", "set_digest", "signature"])

    return docs.mapInArrow(run, "doc_id long, n_shingles long, set_digest binary, signature binary")


def regions_of(hashes: np.ndarray, forest: Forest, level: int = 0) -> np.ndarray:
    """Of each signature (documents x hashes) its region in every tree."""
    order, depth = forest.orders(level)
    region = np.broadcast_to(np.arange(1, len(order) + 1, dtype=np.uint64), (len(hashes), len(order)))
    with np.errstate(over="ignore"):
        for d in range(depth):
            region = mixed(region * np.uint64(0x9E3779B97F4A7C15) + hashes[:, order[:, d]].astype(np.uint64))
    return region.view(np.int64)


def onward_of(hashes: np.ndarray, forest: Forest, level: int = 0) -> np.ndarray:
    """Of each signature, in every tree, 16 bits of each hash after those of the region, the next one highest."""
    order, depth = forest.orders(level)
    out = np.zeros((len(hashes), len(order)), np.uint64)
    for d in range(4):
        out <<= np.uint64(16)
        if d < forest.more:
            out |= hashes[:, order[:, depth + d]].astype(np.uint64) & np.uint64(0xFFFF)
    return out.view(np.int64)


_LEAF = [("region", pa.int64()), ("onward", pa.int64()), ("id", pa.int64()), ("n", pa.int64()), ("sketch_a", pa.int64()), ("sketch_b", pa.int64())]
LEAVES = "region long, onward long, id long, n long, sketch_a long, sketch_b long"


def leaves(firsts: DataFrame, forest: Forest, level: int = 0) -> DataFrame:
    """A row per document and tree: its region, its place within, and one bit of each hash."""
    trees = len(forest.orders(level)[0])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 64_000 // trees):
                part = batch.slice(at, 64_000 // trees)
                k = part.num_rows
                hashes = np.frombuffer(b"".join(part.column("signature").to_pylist()), "<u4").reshape(k, forest.hashes)
                bits = np.packbits((hashes[:, :128] & np.uint32(1)).astype(np.uint8), axis=1)
                sketch = np.zeros((k, 16), np.uint8)
                sketch[:, : bits.shape[1]] = bits
                two = sketch.view(np.int64)
                each = [np.repeat(part.column(c).to_numpy(), trees) for c in ("doc_id", "n_shingles")]
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in (regions_of(hashes, forest, level).ravel(), onward_of(hashes, forest, level).ravel(), *each, *(np.repeat(two[:, j], trees) for j in (0, 1)))], names=[c for c, _ in _LEAF])

    return firsts.mapInArrow(run, LEAVES)


def _likely(n_a, n_b, xa, xb, ya, yb, forest: Forest) -> np.ndarray:
    """Whether two sizes allow the similarity and the sketches agree enough for it."""
    fits = 100 * np.minimum(n_a, n_b) >= forest.percent * np.maximum(n_a, n_b)
    return fits & (np.bitwise_count((xa ^ xb).view(np.uint64)).astype(np.int16) + np.bitwise_count((ya ^ yb).view(np.uint64)) <= forest.most_differing())


_FOUND = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("region", pa.int64())])
FOUND = "a long, b long, region long"


def _pairs(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.maximum(a, b)), pa.array(np.minimum(a, b)), pa.nulls(len(a), pa.int64())], schema=_FOUND)


def _neighbourhoods(region: np.ndarray, onward: np.ndarray, forest: Forest) -> tuple[np.ndarray, np.ndarray]:
    """Of rows in order, (a number that rows of one neighbourhood share, hashes by which it is deeper than its region).

    A row takes the shortest prefix that at most window + 1 rows share, or the longest there is. Prefixes nest, so all
    rows that share the prefix take the same one.
    """
    n = len(region)
    number, deeper, open_ = np.zeros(n, np.int64), np.zeros(n, np.int64), np.ones(n, bool)
    bits = onward.view(np.uint64)
    for d in range(forest.more + 1):
        edge = np.concatenate(([True], region[1:] != region[:-1]))
        if d:
            prefix = bits >> np.uint64(64 - 16 * d)
            edge[1:] |= prefix[1:] != prefix[:-1]
        run = np.cumsum(edge) - 1
        few = np.bincount(run)[run] <= forest.window + 1
        take = open_ & (few | (d == forest.more))
        number[take], deeper[take] = run[take] * (forest.more + 1) + d, d
        open_ &= ~take
        if not open_.any():
            break
    return number, deeper


def _look(x: dict[str, np.ndarray], forest: Forest, cut: bool) -> Iterator[pa.RecordBatch]:
    """Pairs of whole regions x in order, or of a part of one that is cut, and the members to read again."""
    r = x["region"]
    sizes = np.diff(np.append(np.flatnonzero(np.concatenate(([True], r[1:] != r[:-1]))), len(r)))
    some = np.repeat((sizes > 1) | cut, sizes)
    x = {c: v[some] for c, v in x.items()}
    r, ids, sizes = x["region"], x["id"], sizes[(sizes > 1) | cut]
    n = len(r)
    if not n:
        return
    starts = np.cumsum(sizes) - sizes
    number, deeper = _neighbourhoods(r, x["onward"], forest)
    partner, counted = np.full(n, np.iinfo(np.int64).max), np.zeros(n, np.int64)
    for d in range(1, forest.window + 1):
        lo = np.flatnonzero(number[:-d] == number[d:])
        if not len(lo):
            break  # a neighbourhood is a run: none has two rows so far apart
        lo = lo[_likely(*(x[c][k] for c in ("n", "sketch_a", "sketch_b") for k in (lo, lo + d)), forest)]
        counted[lo + d] += 1
        np.minimum.at(partner, lo + d, ids[lo])
    took = np.flatnonzero((counted > 0) & (partner != ids))
    yield _pairs(ids[took], partner[took])
    again = np.add.reduceat(counted, starts) > np.add.reduceat((counted > 0).astype(np.int64), starts)
    rest = np.repeat(again | (np.maximum.reduceat(deeper, starts) > 0) | (sizes > forest.window + 1) | cut, sizes)
    if rest.any():
        yield pa.RecordBatch.from_arrays([pa.array(ids[rest]), pa.nulls(int(rest.sum()), pa.int64()), pa.array(r[rest])], schema=_FOUND)


def neighbours(leaf: DataFrame, forest: Forest) -> DataFrame:
    """Candidate pairs (a > b, region null), and members (a, region; b null) of regions to be read again.

    The orders are dealt by ranges, so a dense region is spread over tasks like any other stretch; the first and the
    last region of a task may go on elsewhere and count as cut. A task holds a block of a long region at a time.
    """
    dealt = leaf.repartitionByRange("region", "onward", "id").sortWithinPartitions("region", "onward", "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = {c: np.zeros(0, np.int64) for c, _ in _LEAF}
        cut_off = None  # the region of which a part lies elsewhere
        for batch in batches:
            if not batch.num_rows:
                continue
            held = {c: np.concatenate((v, batch.column(c).to_numpy())) for c, v in held.items()}
            r = held["region"]
            cut_off = int(r[0]) if cut_off is None else cut_off
            last = int(np.flatnonzero(np.concatenate(([True], r[1:] != r[:-1])))[-1])
            if r[-1] != cut_off:
                head = int((r[:last] == cut_off).sum())
                if head:
                    yield from _look({c: v[:head] for c, v in held.items()}, forest, True)
                if head < last:
                    yield from _look({c: v[head:last] for c, v in held.items()}, forest, False)
                cut_off = 0 if r[-1] else 1  # any other region than the one held
            held = {c: v[last:] for c, v in held.items()} if r[-1] != cut_off else held
            if len(held["region"]) > forest.block:
                cut_off = int(r[-1])
                yield from _look(held, forest, True)
                held = {c: v[:0] for c, v in held.items()}
        if len(held["region"]):
            yield from _look(held, forest, True)

    return dealt.mapInArrow(run, FOUND)


def left_open(members: DataFrame, labels: DataFrame) -> DataFrame:
    """(a, region, component, size) of the members of regions that hold several components. A written table."""
    known = common.written(common.looked_up(members.select("a", "region"), labels.withColumnRenamed("node", "a"), "a", "left").withColumn("component", F.coalesce("component", "a")), "members")
    several = common.written(known.groupBy("region").agg(F.count("*").alias("size"), F.min("component").alias("least"), F.max("component").alias("most")).where("least < most").select("region", "size"), "regions")
    return common.written(common.looked_up(known, several, "region"), "members")


def across(open_members: DataFrame, signatures: DataFrame, docs: DataFrame, forest: Forest, level: int) -> DataFrame:
    """Likely pairs (a > b) of different components in regions that hold several, by pairs of blocks.

    Here whole signatures are compared and then the finer bins, which leaves few pairs below the similarity: they
    would grow with the square of a large group. A pair comes out of the first tree only in which it shares a region.
    """
    blocks = F.ceil(F.col("size") / forest.block).cast("int")

    def bins(found: np.ndarray) -> bytes:
        return binned(found, forest.bins).tobytes()

    fine = texts_as(open_members.select(F.col("a").alias("doc_id")).distinct(), docs, bins, forest)
    dealt = (
        open_members.join(fine.select(F.col("doc_id").alias("a"), F.col("found").alias("bins")), "a")
        .join(signatures.select(F.col("doc_id").alias("a"), F.col("n_shingles").alias("n"), "signature"), "a")
        .withColumn("mine", F.pmod(F.xxhash64("a"), blocks).cast("int"))
        .withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
        .select("region", F.least("mine", "other").alias("one"), F.greatest("mine", "other").alias("two"), "mine", "a", "component", "n", "signature", "bins")
        .repartition("region", "one", "two")
        .sortWithinPartitions("region", "one", "two", "mine")
    )

    def compare(x: dict[str, np.ndarray]) -> Iterator[pa.RecordBatch]:
        """x: the rows of one pair of blocks."""
        if x["component"].min() == x["component"].max():
            return
        hashes = np.frombuffer(b"".join(x["signature"]), "<u4").reshape(len(x["a"]), forest.hashes)
        region = regions_of(hashes, forest, level)
        fine = np.frombuffer(b"".join(x["bins"]), np.uint8).reshape(len(x["a"]), forest.bins)
        own = x["one"][0] == x["two"][0]
        cut = len(x["a"]) if own else int((x["mine"] == x["one"][0]).sum())
        for at in range(0, cut, 64):
            right = np.arange(at if own else cut, len(x["a"]))
            left = np.arange(at, min(cut, at + 64))[:, None]
            small, large = np.minimum(x["n"][left], x["n"][right]), np.maximum(x["n"][left], x["n"][right])
            i, j = np.nonzero((100 * small >= forest.percent * large) & (x["component"][left] != x["component"][right]) & ((right > left) | (not own)))
            for a in range(0, len(i), 1 << 14):
                one, two = i[a : a + (1 << 14)] + at, right[j[a : a + (1 << 14)]]
                likely = (hashes[one] == hashes[two]).sum(axis=1) >= forest.least_equal()
                one, two = one[likely], two[likely]
                likely = _close(fine[one], fine[two], x["n"][one] + x["n"][two], forest)
                one, two = one[likely], two[likely]
                shared = region[one] == region[two]
                first = region[one, shared.argmax(axis=1)] == x["region"][0]
                if first.any():
                    yield _pairs(x["a"][one[first]], x["a"][two[first]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, np.ndarray] = {}
        for batch in batches:
            if not batch.num_rows:
                continue
            new = {c: np.array(batch.column(c).to_pylist(), object) if c in ("signature", "bins") else batch.column(c).to_numpy() for c in batch.schema.names}
            held = {c: np.concatenate((held[c], v)) for c, v in new.items()} if held else new
            edge = np.zeros(len(held["a"]), bool)
            edge[0] = True
            for c in ("region", "one", "two"):
                edge[1:] |= held[c][1:] != held[c][:-1]
            starts = np.flatnonzero(edge)
            for a, b in zip(starts, starts[1:], strict=False):
                yield from compare({c: v[a:b] for c, v in held.items()})
            held = {c: v[starts[-1] :] for c, v in held.items()}
        if held:
            yield from compare(held)

    return dealt.mapInArrow(run, FOUND).select("a", "b")


def settled(pairs: DataFrame, labels: DataFrame | None, docs: DataFrame, forest: Forest) -> DataFrame:
    """labels (node, component) with what pairs add: of each document one pair first, then those that still lie apart.

    Links found later join components, not documents, so each call of `components` has a smaller graph.
    """
    pairs = common.written(pairs, "pairs")
    wanted = pairs.select(F.col("a").alias("doc_id")).union(pairs.select(F.col("b").alias("doc_id"))).distinct()
    sets = texts_as(wanted, docs, np.ndarray.tobytes, forest)
    first = pairs.groupBy("a").agg(F.min("b").alias("b"))
    rest = pairs.join(first, ["a", "b"], "left_anti")
    for some in (first, rest):
        if labels is not None:
            some = _between(some, labels).where("a_in != b_in").select("a", "b")
        new = common.written(confirmed(some, sets, forest), "links")
        if labels is None:
            labels = components(new)
        elif not new.isEmpty():
            joined = components(_between(new, labels).select(F.col("a_in").alias("a"), F.col("b_in").alias("b")).distinct())
            onward = common.written(joined.where("node != component").select(F.col("node").alias("component"), F.col("component").alias("onward")), "onward")
            moved = common.looked_up(labels, onward, "component", "left").select("node", F.coalesce("onward", "component").alias("component"))
            labels = common.written(moved.union(joined.join(labels, "node", "left_anti").select("node", "component")), "labels")
    return labels


def _between(pairs: DataFrame, labels: DataFrame) -> DataFrame:
    """pairs (a, b) with the components a_in and b_in; a document without one is its own."""
    for c in ("a", "b"):
        pairs = common.looked_up(pairs, labels.select(F.col("node").alias(c), F.col("component").alias(f"{c}_in")), c, "left")
    return pairs.select("a", "b", *(F.coalesce(f"{c}_in", c).alias(f"{c}_in") for c in ("a", "b")))


def texts_as(wanted: DataFrame, docs: DataFrame, form: Callable[[np.ndarray], bytes], forest: Forest) -> DataFrame:
    """(doc_id, found): a form of the shingle set of every document in wanted (doc_id), from a written table.

    docs (doc_id, text) has one row per wanted id, and others that are passed over. A Bloom filter of 2^25 bits,
    8 MB at every size, keeps most of those from the shuffle; the join is exact.
    """
    wanted = common.written(wanted, "wanted")
    word = F.shiftright(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 25)), 6).cast("int").alias("word")
    bit = F.expr("shiftleft(1L, cast(pmod(xxhash64(doc_id), 64) as int))")
    words = wanted.groupBy(word).agg(F.bit_or(bit).alias("bits"))
    some = docs.withColumn("word", word).join(F.broadcast(words), "word").where(F.col("bits").bitwiseAND(bit) != 0).select("doc_id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.parts(batch, "text", 4 << 20):
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([form(x) for x in sets_of(part.column("text"), forest.shingle)], pa.binary())], names=["doc_id", "found"])

    return common.written(some.join(wanted, "doc_id", "left_semi").mapInArrow(run, "doc_id long, found binary"), "sets")


def confirmed(pairs: DataFrame, sets: DataFrame, forest: Forest, *, share: int = 256) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough. Each pair moves the set of a; b's comes once to `share` pairs."""
    pairs = common.written(pairs, "pairs")
    shares = pairs.groupBy("b").agg(F.ceil(F.count("*") / share).cast("int").alias("shares"))
    tests = pairs.join(shares, "b").select("a", "b", F.pmod(F.xxhash64("a"), "shares").cast("int").alias("salt")).join(sets.withColumnRenamed("doc_id", "a"), "a").select("b", "a", "found", "salt")
    heads = shares.join(sets.withColumnRenamed("doc_id", "b"), "b").select("b", F.lit(None).cast("long").alias("a"), "found", F.explode(F.sequence(F.lit(0), F.col("shares") - 1)).alias("salt"))
    dealt = tests.union(heads).repartition("b", "salt").sortWithinPartitions("b", "salt", F.col("a").asc_nulls_first())
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head = np.zeros(0, np.uint64)
        for batch in batches:
            out_a, out_b = [], []
            for b, a, found in zip(batch.column("b").to_pylist(), batch.column("a").to_pylist(), batch.column("found").to_pylist(), strict=True):
                these = np.frombuffer(found, np.uint64)
                if a is None:
                    head = these
                    continue
                shared = len(np.intersect1d(head, these, assume_unique=True))
                if 100 * shared >= forest.percent * (len(head) + len(these) - shared):
                    out_a.append(a)
                    out_b.append(b)
            yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], schema=schema)

    return dealt.mapInArrow(test, "a long, b long")


def linked(docs: DataFrame, forest: Forest = Forest(), *, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """doc_id, n_shingles, set_digest, component_id of every row of docs."""
    rows = docs.select(F.col(id_column).cast("long").alias("doc_id"), F.col(text_column).alias("text"))
    profile = common.written(profiles(rows, forest), "profiles")
    sets = profile.where("set_digest is not null")
    classes = common.written(sets.groupBy("set_digest").agg(F.min("doc_id").alias("first")), "classes")
    firsts = sets.join(classes.where("first is not null").select(F.col("first").alias("doc_id"), "set_digest"), ["doc_id", "set_digest"], "left_semi")
    texts = rows.where("doc_id is not null")
    some, labels = firsts.select("doc_id", "n_shingles", "signature"), None
    for level in (0, 1):
        found = common.written(neighbours(leaves(some, forest, level), forest), "forest")
        labels = settled(found.where("region is null").select("a", "b").distinct(), labels, texts, forest)
        held = left_open(found.where("region is not null"), labels)
        if held.isEmpty():
            break
        small = held if level else held.where(F.col("size") <= forest.block)
        labels = settled(across(small, firsts, texts, forest, level), labels, texts, forest)
        large = held.where(F.col("size") > forest.block).select(F.col("a").alias("doc_id")).distinct()
        if level or large.isEmpty():
            break
        some = common.written(firsts.join(large, "doc_id", "left_semi").select("doc_id", "n_shingles", "signature"), "dense")
    of_class = classes.join(labels.withColumnRenamed("node", "first"), "first", "left").select("set_digest", F.coalesce("component", "first").alias("class_component"))
    return profile.drop("signature").join(of_class, "set_digest", "left").select(
        "doc_id", "n_shingles", "set_digest", F.when(F.col("set_digest").isNull(), F.col("doc_id")).otherwise(F.coalesce("class_component", "doc_id")).alias("component_id")
    )


def deduplicated(docs: DataFrame, forest: Forest = Forest(), *, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row of docs per component, with all its columns: that of the least id, nulls last.

    Rows are linked by a number from a written table, so rows without an id are near-duplicates like any others, and
    rows that share an id are in one component. Of those the row of most shingles stays, then that of the least number.
    """
    row = "_row"
    while row in {c.lower() for c in docs.columns}:
        row += "_"
    numbered = common.written(docs.withColumn(row, F.monotonically_increasing_id()), "rows")
    found = linked(numbered, forest, id_column=row, text_column=text_column).select(F.col("doc_id").alias("row"), "n_shingles", F.col("component_id").alias("component"))
    ids = numbered.select(F.col(row).alias("row"), F.col(f"`{id_column}`").cast("long").alias("id"))
    labelled = common.written(found.join(ids, "row"), "labelled")
    places = labelled.where("id is not null").select("id", "component").distinct()
    several = places.groupBy("id").agg(F.min("component").alias("least"), F.max("component").alias("most")).where("least < most")
    links = common.written(places.join(several, "id").where("component != least").select(F.col("component").alias("a"), F.col("least").alias("b")).distinct(), "links")
    if not links.isEmpty():
        onward = common.written(components(links).select(F.col("node").alias("component"), F.col("component").alias("onward")), "onward")
        labelled = common.looked_up(labelled, onward, "component", "left").withColumn("component", F.coalesce("onward", "component"))
    best = labelled.groupBy("component").agg(F.min(F.struct(F.col("id").isNull().alias("no_id"), "id", (-F.col("n_shingles")).alias("n"), "row")).alias("best")).select(F.col("best.row").alias("row"))
    dropped = common.written(labelled.select("row").join(best, "row", "left_anti").select(F.col("row").alias(row)), "dropped")
    return common.looked_up(numbered, dropped, row, "left_anti").select(*(F.col(f"`{c}`") for c in docs.columns))
