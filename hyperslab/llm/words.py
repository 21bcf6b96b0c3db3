"""Words and word shingles of many texts at once.

A word is a longest run of characters other than the ASCII white space \\x20 \\x09-\\x0D.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc

#: Odd multipliers of the word hashes in a shingle, and of the finishing mix. Fixed values.
_STEP = np.uint64(0x9E3779B97F4A7C15)
_MIX = (np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))


class Words(NamedTuple):
    offsets: np.ndarray  # word offsets of the texts, one more than texts
    codes: np.ndarray  # of each word, its place in vocabulary
    vocabulary: pa.Array

    def hashes(self) -> np.ndarray:
        """Of each word, 64 bits that are the same in every process."""
        of = pd.util.hash_array(np.asarray(self.vocabulary.to_pandas(), dtype=object), categorize=False) if len(self.vocabulary) else np.zeros(0, np.uint64)
        return of[self.codes]


def words_of(texts: pa.Array, lower: bool = False) -> Words:
    """Words of texts; null has none. lower: A-Z as a-z."""
    if texts.offset:  # string kernels misread slices
        texts = texts.take(pa.array(np.arange(len(texts))))
    texts = pc.fill_null(texts.cast(pa.large_string()), "")
    split = pc.ascii_split_whitespace(pc.ascii_lower(texts) if lower else texts)
    flat, ends = split.flatten(), split.offsets.to_numpy() - split.offsets[0].as_py()
    real = pc.greater(pc.binary_length(flat), 0).to_numpy(zero_copy_only=False)
    offsets = np.concatenate(([0], np.cumsum(real)))[ends]
    coded = (flat if real.all() else flat.filter(pa.array(real))).dictionary_encode()
    return Words(offsets.astype(np.int64), coded.indices.to_numpy(zero_copy_only=False).astype(np.int64), coded.dictionary)


def mixed(x: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * _MIX[0]
        x = (x ^ (x >> np.uint64(27))) * _MIX[1]
        return x ^ (x >> np.uint64(31))


def shingles(words: Words, size: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, offsets): of each text its shingles in order, with repeats.

    A text of fewer words than size has one shingle, all its words; a text without words has none.
    """
    h, n = words.hashes(), np.diff(words.offsets)
    counts = np.where(n >= size, n - size + 1, np.minimum(n, 1))
    ends = np.concatenate(([0], np.cumsum(counts)))
    start = np.repeat(words.offsets[:-1] - ends[:-1], counts) + np.arange(ends[-1])
    length = np.repeat(np.minimum(n, size), counts)
    out = length.astype(np.uint64)
    with np.errstate(over="ignore"):
        for k in range(size):
            inside = length > k
            out = np.where(inside, mixed(out * _STEP + h[np.where(inside, start + k, 0)]) if len(h) else out, out)
    return out, ends
