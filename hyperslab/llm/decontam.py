"""Benchmark decontamination: SimHash over item-sized windows, a multi-index over Hamming blocks, exact similarity.

For every benchmark item each document is read through windows of the item's size. A window that holds too few of
the benchmark's shingles to reach the similarity is passed over, which loses nothing. The others get a fingerprint
that votes over their shingles by (shingle, how often so far in the window), so that a repeated shingle is as many
independent votes, and the share of differing bits follows the weighted similarity, repeats or not. The fingerprint
slides with the window: one vote in, one out.

Fingerprints are looked up by blocks: if two differ in at most radius bits, they differ in at most radius / blocks bits
in one block, so the blocks together find all. Blocks are long (32 bits) because the radius is a quarter of the bits: of
unrelated pairs 2.8 in 100 share a block that near, where blocks of 8 bits pass 71 in 100. Candidates are verified by
the weighted similarity of their shingles, weights being the counts.

At a similarity of 75 % a bit differs with probability 0.177 on average and 0.1875 at most (sets of 4 or 5 shingles):
45 or 48 of 256 bits, deviation 6.2. The radius of 71 leaves a pair beyond it with probability 8e-5 at most there,
and less above. exact=True compares every window that passes the first test with every item of its size instead.

The benchmark is the stated query set: it lies in the shared folder in blocks of about most_items items, and a task
holds one block at a time; each block is a pass over the documents.

Cases: a null or empty text matches nothing, in either table; a text of fewer words than a shingle is one shingle;
a document shorter than an item is one window; a null id is kept; repeated rows are matched one by one; an empty
table gives an empty result; texts of any length are read in slices of windows; further columns, whatever they are
called, are ignored by `matches` and kept by `clean_rows`.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .words import mixed, shingles, words_of

#: Multipliers that tell the words of a fingerprint, and the repeats of a shingle, apart. Fixed values.
_WORD, _REPEAT = np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F)


@dataclass(frozen=True)
class Match:
    shingle: int = 5
    percent: int = 75
    words: int = 4  # of 64 bits each
    radius: int = 71
    blocks: int = 8  # of 64 * words / blocks bits: 32, or 64 or 16
    most_items: int = 20_000
    windows: int = 4096  # that are held at once
    exact: bool = False


def votes(hashes: np.ndarray, repeat: np.ndarray, words: int) -> np.ndarray:
    """+1 or -1 for each of 64 * words bits of each shingle, the repeat-th of its kind."""
    with np.errstate(over="ignore"):
        base = mixed(hashes + repeat.astype(np.uint64) * _REPEAT)
        each = np.stack([mixed(base + np.uint64(k + 1) * _WORD) for k in range(words)], axis=1)
    bits = np.unpackbits(each.astype("<u8").view(np.uint8).reshape(len(hashes), 8 * words), axis=1, bitorder="little")
    return bits.astype(np.int8) * 2 - 1


def fingerprint(sums: np.ndarray) -> np.ndarray:
    """Bits from the signs of the rows of sums, 8 bytes a word."""
    return np.packbits(sums > 0, axis=1, bitorder="little").view("<u8")


def repeats(hashes: np.ndarray) -> np.ndarray:
    """Of each shingle, how often it came up to there."""
    return Places(hashes).before(np.zeros(len(hashes), np.int64)) if len(hashes) else np.zeros(0, np.int64)


class Places:
    """Where each shingle of a text occurs."""

    def __init__(self, hashes: np.ndarray):
        self.n = len(hashes)
        self.kinds, code = np.unique(hashes, return_inverse=True)
        code = code.astype(np.int64)
        self.key = code * (self.n + 1)
        self.sorted = np.sort(self.key + np.arange(self.n))
        self.rank = np.searchsorted(self.sorted, self.key + np.arange(self.n))

    def before(self, start: np.ndarray, at: np.ndarray | None = None) -> np.ndarray:
        """How often the shingle at each place (all places by default) occurs from start to that place."""
        at = np.arange(self.n) if at is None else at
        return self.rank[at] - np.searchsorted(self.sorted, self.key[at] + start) + 1

    def after(self, end: np.ndarray, at: np.ndarray) -> np.ndarray:
        """How often the shingle at each place occurs from there to end (exclusive)."""
        return np.searchsorted(self.sorted, self.key[at] + end) - self.rank[at]

    def shared(self, kinds: np.ndarray, counts: np.ndarray, starts: np.ndarray, size: int) -> np.ndarray:
        """Of the windows at starts, the sums of the lesser of their counts and counts, over kinds of shingles."""
        code = np.minimum(np.searchsorted(self.kinds, kinds), len(self.kinds) - 1)
        here = self.kinds[code] == kinds
        key, most = code[here].astype(np.int64) * (self.n + 1), counts[here]
        out = np.zeros(len(starts), np.int64)
        step = max(1, (1 << 20) // max(1, len(key)))
        for a in range(0, len(starts), step):
            some = starts[a : a + step, None]
            held = np.searchsorted(self.sorted, key[None] + some + size) - np.searchsorted(self.sorted, key[None] + some)
            out[a : a + step] = np.minimum(held, most[None]).sum(axis=1)
        return out


class Index:
    """The items of one block of the benchmark: their shingles by number of shingles, and the blocks of their fingerprints."""

    def __init__(self, ids: list[int], texts: list[str | None], match: Match):
        self.match = match
        hashes, at = shingles(words_of(pa.array(texts, pa.large_string()), lower=True), match.shingle)
        self.sizes: dict[int, list[int]] = {}
        self.items = [(i, hashes[at[k] : at[k + 1]]) for k, i in enumerate(ids)]
        for k, (_, x) in enumerate(self.items):
            if len(x):
                self.sizes.setdefault(len(x), []).append(k)
        self.every = np.unique(hashes)
        self.bags = [np.unique(x, return_counts=True) for _, x in self.items]
        self.prints = {m: np.concatenate([self.print_of(self.items[k][1]) for k in own]) for m, own in self.sizes.items()}

    def print_of(self, hashes: np.ndarray) -> np.ndarray:
        return fingerprint(votes(hashes, repeats(hashes), self.match.words).sum(axis=0, dtype=np.int64)[None])

    def least(self, m: int) -> int:
        """Of m shingles, those that must be shared."""
        return max(1, math.ceil(m * self.match.percent / 100))

    def parts(self, prints: np.ndarray) -> np.ndarray:
        """The blocks of fingerprints as numbers."""
        return prints.view(f"<u{8 * self.match.words // self.match.blocks}")

    def candidates(self, m: int, prints: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(window, item) places of all fingerprints within the radius, for some items at a time. A block that is near
        makes a candidate, the whole distance decides."""
        own, near = self.prints[m], self.match.radius // self.match.blocks
        mine = self.parts(prints)
        step = max(1, (4 << 20) // max(1, len(prints)))
        for at in range(0, len(own), step):
            some = own[at : at + step]
            if self.match.exact:
                w, k = (x.ravel() for x in np.indices((len(prints), len(some))))
            else:
                found = np.zeros((len(prints), len(some)), bool)
                for b, of_block in enumerate(self.parts(some).T):
                    found |= np.bitwise_count(mine[:, b, None] ^ of_block[None]) <= near
                w, k = np.nonzero(found)
                close = np.bitwise_count(prints[w] ^ some[k]).sum(axis=1, dtype=np.int64) <= self.match.radius
                w, k = w[close], k[close]
            yield w, k + at

    def window_prints(self, hashes: np.ndarray, places: Places, windows: np.ndarray, size: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(windows, fingerprints) in slices: runs of near windows slide, one vote in and one out; others begin anew."""
        far = np.flatnonzero(np.diff(windows) > size) + 1
        of = lambda at, repeat: votes(hashes[at], repeat, self.match.words)
        for run in np.split(windows, far):
            first = int(run[0])
            held = np.arange(first, first + size)
            sums = np.zeros((1, 64 * self.match.words), np.int64)
            for a in range(0, size, self.match.windows):
                some = held[a : a + self.match.windows]
                sums = sums + of(some, places.before(np.full(len(some), first), some)).sum(axis=0, dtype=np.int64)
            done = 0
            while done < len(run):
                last = min(int(run[-1]), first + self.match.windows - 1)
                out = np.arange(first, last)
                moved = of(out + size, places.before(out + 1, out + size)).astype(np.int64) - of(out, places.after(out + size, out))
                slid = np.concatenate((sums, sums + np.cumsum(moved, axis=0)))
                end = int(np.searchsorted(run, last, side="right"))
                if end > done:
                    yield run[done:end], fingerprint(slid[run[done:end] - first])
                sums, done = slid[-1:], end
                if done < len(run):  # on to the window after the slice
                    step = of(np.array([last + size]), places.before(np.array([last + 1]), np.array([last + size]))).astype(np.int64) - of(np.array([last]), places.after(np.array([last + size]), np.array([last])))
                    sums, first = sums + step, last + 1

    def of_document(self, hashes: np.ndarray, hits: np.ndarray) -> Iterator[tuple[int, int, int, int, int]]:
        """(item, shared, all, first shingle, shingles) of the best window of each item found."""
        n, counts = len(hashes), np.concatenate(([0], np.cumsum(hits)))
        places = None
        for m, own in self.sizes.items():
            size = min(m, n)
            windows = np.flatnonzero(counts[size:] - counts[: n - size + 1] >= self.least(m))
            if not len(windows):
                continue
            places = places or Places(hashes)
            best: dict[int, tuple[float, int, int, int]] = {}
            for some, prints in self.window_prints(hashes, places, windows, size):
                for w, k in self.candidates(m, prints):
                    for item in np.unique(k).tolist():
                        starts = some[w[k == item]]
                        shared = places.shared(*self.bags[own[item]], starts, size)
                        top = int(shared.argmax())  # all windows have one size: most shared is most similar
                        alike, total = int(shared[top]), size + m - int(shared[top])
                        if 100 * alike >= self.match.percent * total and alike / total > best.get(item, (0.0,))[0]:
                            best[item] = alike / total, alike, total, int(starts[top])
            for item, (_, shared, total, at) in best.items():
                yield own[item], shared, total, at, size

    def of_texts(self, texts: pa.Array) -> Iterator[tuple[int, int, int, int, int, int]]:
        """(text, item, shared, all, first shingle, shingles)."""
        if not self.sizes:
            return
        hashes, at = shingles(words_of(texts, lower=True), self.match.shingle)
        place = np.minimum(np.searchsorted(self.every, hashes), len(self.every) - 1)
        hits = self.every[place] == hashes
        total = np.concatenate(([0], np.cumsum(hits)))[at]
        fewest = min(map(self.least, self.sizes))
        for k in np.flatnonzero(np.diff(total) >= fewest).tolist():
            for found in self.of_document(hashes[at[k] : at[k + 1]], hits[at[k] : at[k + 1]]):
                yield (k, *found)


def _stored(benchmark: DataFrame, match: Match, id_column: str, text_column: str) -> list[str]:
    """The benchmark in blocks, each a folder of Parquet files; what there is on the driver are their names."""
    spark = benchmark.sparkSession
    items = benchmark.select(F.col(f"`{id_column}`").cast("long").alias("id"), F.col(f"`{text_column}`").alias("text"))
    blocks = -(-items.count() // match.most_items)
    if not blocks:
        return []
    folder = common.new_folder(spark, "benchmark")
    items.withColumn("block", F.pmod(F.monotonically_increasing_id(), F.lit(blocks))).repartition(blocks, "block").write.partitionBy("block").parquet(folder)
    return [f"{folder}/block={k}" for k in range(blocks)]


_held: dict[tuple[str, Match], Index] = {}


def _index(folder: str, match: Match) -> Index:
    """The index of one block, made once per Python worker, which holds one."""
    if (folder, match) not in _held:
        _held.clear()
        where, path = common.open_store(folder)
        files = sorted(x.path for x in where.get_file_info(common.fs.FileSelector(path, allow_not_found=True)) if x.path.endswith(".parquet"))
        ids, texts = [], []
        for file in files:
            with where.open_input_file(file) as data:
                rows = pq.ParquetFile(data).read(columns=["id", "text"])
                ids += rows.column("id").to_pylist()
                texts += rows.column("text").to_pylist()
        _held[folder, match] = Index(ids, texts, match)
    return _held[folder, match]


MATCHES = "doc_id long, item_id long, shared_shingles long, all_shingles long, similarity double, first_word long, n_words long"
_MATCHES = pa.schema([("doc_id", pa.int64()), ("item_id", pa.int64()), ("shared_shingles", pa.int64()), ("all_shingles", pa.int64()), ("similarity", pa.float64()), ("first_word", pa.int64()), ("n_words", pa.int64())])


def matches(docs: DataFrame, benchmark: DataFrame, match: Match = Match(), *, id_column: str = "doc_id", text_column: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """A row per document and item that a window of it repeats, with the best window. One pass per block of items."""
    rows = docs.select(F.col(f"`{id_column}`").cast("long").alias("id"), F.col(f"`{text_column}`").alias("text"))

    def found(block: str):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = _index(block, match)
            for batch in batches:
                for part in common.parts(batch, "text", 4 << 20):
                    ids = part.column("id").to_pylist()
                    out = [
                        {"doc_id": ids[k], "item_id": index.items[item][0], "shared_shingles": shared, "all_shingles": total, "similarity": shared / total, "first_word": at, "n_words": size + match.shingle - 1}
                        for k, item, shared, total, at, size in index.of_texts(part.column("text"))
                    ]
                    if out:
                        yield pa.RecordBatch.from_pylist(out, schema=_MATCHES)

        return rows.mapInArrow(run, MATCHES)

    each = [found(block) for block in _stored(benchmark, match, item_id, item_text)]
    if not each:
        return rows.sparkSession.createDataFrame([], MATCHES)
    out = each[0]
    for more in each[1:]:
        out = out.unionByName(more)
    return out


def clean_rows(docs: DataFrame, benchmark: DataFrame, match: Match = Match(), *, text_column: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """The rows of docs that repeat no item, with all their columns. No shuffle."""
    place = docs.columns.index(text_column)

    def without(block: str, rows: DataFrame) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index = _index(block, match)
            for batch in batches:
                for part in common.parts(batch.rename_columns([str(k) for k in range(batch.num_columns)]), str(place), 4 << 20):
                    good = np.ones(part.num_rows, bool)
                    good[[found[0] for found in index.of_texts(part.column(place))]] = False
                    yield part.filter(pa.array(good)).rename_columns(batch.schema.names)

        return rows.mapInArrow(run, docs.schema)

    for block in _stored(benchmark, match, item_id, item_text):
        docs = without(block, docs)
    return docs
