"""Quality rules on repetition within a text, from suffix arrays of its words.

The suffixes of all texts of a batch are sorted together by prefix doubling, each text by itself. Longest
common prefixes of neighbours give the intervals whose prefixes are the maximal repeated substrings; a word
is covered if a repeated substring of enough words reaches over it.

Cases: a null text has no words and fails the base rules; a text without words likewise; a null id is kept;
repeated rows are judged one by one; an empty table gives an empty result; further columns are ignored by
`measure` and kept by `kept_rows`, whatever they are called.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .words import words_of

#: The characters that count as symbols.
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Limits:
    """The base rules (words, share of words in repeats of window words) and those on maximal repeats."""

    least_words: int = 10
    window: int = 5
    most_repeat_percent: int = 20
    repeat_words: int = 20  # a maximal repeat counts for the two limits below from so many words on
    most_covered_percent: int = 15
    longest_repeat: int = 100


def suffix_order(codes: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """(suffix array, classes, ends): suffixes sorted within each text.

    classes[k][i] numbers the words i .. i + 2^k - 1: equal numbers, equal words of one text. Only suffixes that
    are still tied are sorted again, so a level costs what is left to decide.
    """
    n = len(codes)
    doc = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    ends = offsets[1:][doc] if n else np.zeros(0, np.int64)
    key = doc * np.int64(int(codes.max(initial=0)) + 1) + codes
    order = np.argsort(key, kind="stable")
    new = np.concatenate(([True], key[order][1:] != key[order][:-1])) if n else np.zeros(0, bool)
    starts = np.flatnonzero(new)
    rank = np.empty(n, np.int32)
    rank[order] = np.repeat(starts, np.diff(np.append(starts, n)))
    classes, step = [rank], 1
    while True:
        sizes = np.diff(np.append(starts, n))
        tied = np.repeat(sizes > 1, sizes)  # by place in order
        places = np.flatnonzero(tied)
        if not len(places):
            break
        at = order[places]
        onward = at + step
        second = np.where(onward < ends[at], rank[np.minimum(onward, n - 1)], -1)
        again = np.lexsort((second, rank[at]))
        at, second = at[again], second[again]
        order[places] = at
        first = rank[at]
        new[places] = np.concatenate(([True], (first[1:] != first[:-1]) | (second[1:] != second[:-1])))
        starts = np.flatnonzero(new)
        whole = np.repeat(starts, np.diff(np.append(starts, n)))
        rank = rank.copy()
        rank[at] = whole[places]
        classes.append(rank)
        step *= 2
    return order, classes, ends


def common_prefixes(order: np.ndarray, classes: list[np.ndarray], ends: np.ndarray) -> np.ndarray:
    """Of each place in order but the first, the words that its suffix shares with the one before it."""
    n = len(order)
    lengths = np.zeros(n, np.int32)
    if n < 2:
        return lengths
    pairs = np.flatnonzero(classes[0][order[1:]] == classes[0][order[:-1]]) + 1
    a, b, left = order[pairs - 1].copy(), order[pairs].copy(), np.zeros(len(pairs), np.int32)
    end = ends[a] if len(a) else a
    for k in range(len(classes) - 1, -1, -1):
        inside = (a < end) & (b < end)
        same = np.zeros(len(a), bool)
        same[inside] = classes[k][a[inside]] == classes[k][b[inside]]
        step = same.astype(np.int64) << k
        a += step
        b += step
        left += step.astype(np.int32)
    lengths[pairs] = left
    return lengths


def repeats(codes: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Of each word, the length of the longest substring that begins there and occurs elsewhere in its text."""
    order, classes, ends = suffix_order(codes, offsets)
    lcp = common_prefixes(order, classes, ends)
    longest = np.zeros(len(codes), np.int32)
    longest[order] = np.maximum(lcp, np.append(lcp[1:], 0)) if len(codes) else 0
    return longest


def covered(longest: np.ndarray, offsets: np.ndarray, least: int) -> np.ndarray:
    """Words of each text in the union of the repeated substrings of least words or more."""
    n = len(longest)
    steps = np.zeros(n + 1, np.int64)
    begins = np.flatnonzero(longest >= least)
    np.add.at(steps, begins, 1)
    np.add.at(steps, begins + longest[begins], -1)
    inside = np.concatenate(([0], np.cumsum(np.cumsum(steps[:-1]) > 0)))
    return inside[offsets[1:]] - inside[offsets[:-1]]


MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, covered_words long, longest_repeat long"
_NAMES = [x.split()[0] for x in MEASURES.split(", ")]


def measures(texts: pa.Array, limits: Limits) -> list[np.ndarray]:
    """The columns of MEASURES."""
    words = words_of(texts)
    n = np.diff(words.offsets)
    longest = repeats(words.codes, words.offsets)
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    chars = pc.utf8_length(pc.replace_substring_regex(texts, "[\\x20\\x09-\\x0D]+", "")).to_numpy()
    symbols = sum(pc.count_substring(texts, s).to_numpy(zero_copy_only=False).astype(np.int64) for s in SYMBOLS)
    lines = np.fromiter(map(_repeated_lines, texts.to_pylist()), np.int64, len(texts))
    most = np.maximum.reduceat(np.append(longest, 0), words.offsets[:-1]) if len(n) else n
    return [n, chars, symbols, lines, covered(longest, words.offsets, limits.window), covered(longest, words.offsets, limits.repeat_words), np.where(n > 0, most, 0)]


def _repeated_lines(text: str) -> int:
    if "\n" not in text:
        return 0
    lines = [x for x in text.split("\n") if x.strip(" \t\n\v\f\r")]
    return len(lines) - len(set(lines))


def measure(docs: DataFrame, limits: Limits = Limits(), *, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """doc_id, the columns of MEASURES, base_failed and kept for every row of docs. No shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.parts(batch, "text", 4 << 20):
                yield pa.RecordBatch.from_arrays([part.column("id"), *(pa.array(x.astype(np.int64)) for x in measures(part.column("text"), limits))], names=["doc_id", *_NAMES])

    found = docs.select(F.col(id_column).cast("long").alias("id"), F.col(text_column).alias("text")).mapInArrow(run, f"doc_id long, {MEASURES}")
    return judged(found, limits)


def judged(found: DataFrame, limits: Limits) -> DataFrame:
    failed = (F.col("n_words") < limits.least_words) | (100 * F.col("n_repeat_words") > limits.most_repeat_percent * F.col("n_words"))
    bad = (100 * F.col("covered_words") > limits.most_covered_percent * F.col("n_words")) | (F.col("longest_repeat") > limits.longest_repeat)
    return found.withColumn("base_failed", failed).withColumn("kept", ~(failed | bad))


def kept_rows(docs: DataFrame, limits: Limits = Limits(), *, text_column: str = "text") -> DataFrame:
    """The rows of docs that pass, with all their columns, in one pass without a shuffle."""
    at = docs.columns.index(text_column)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in common.parts(batch.rename_columns([str(k) for k in range(batch.num_columns)]), str(at), 4 << 20):
                n, _, _, _, repeat, cover, longest = measures(part.column(at), limits)
                good = (n >= limits.least_words) & (100 * repeat <= limits.most_repeat_percent * n) & (100 * cover <= limits.most_covered_percent * n) & (longest <= limits.longest_repeat)
                yield part.filter(pa.array(good)).rename_columns(batch.schema.names)

    return docs.mapInArrow(run, docs.schema)
