"""Packing documents into training sequences by the cutting-stock problem.

Documents are cut into full sequences and one remainder. The histogram of remainders, which has at most one
entry per length, is the demand of a cutting-stock problem: a linear program over patterns (multisets of
lengths that fit a sequence), whose columns a knapsack recursion prices. The patterns with their rounded
rates then fill the sequences of every partition from its documents, ranked within their length, without a shuffle.

Cases: a null text is empty and has its end id alone; a null id is kept; repeated ids are separate documents;
an empty table gives no sequence; further columns are ignored; a text of any length is cut into as many
sequences as it needs.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, tokens

PIECES = "doc_id long, start long, length long, doc_tokens long, ids binary"


def pieces(docs: DataFrame, tokenizer: str, *, word_ends: bool = False, end_id: int = 0, size: int = 1024, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """Token pieces of at most size ids: doc_id, start, length, doc_tokens, ids (little-endian unsigned 32 bit)."""

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = tokens.encoder(tokenizer, word_ends)
        for batch in batches:
            for part in common.parts(batch, "text"):
                ids, at = encode(part.column("text"))
                n = np.diff(at)
                ids, at = np.insert(ids, at[1:], np.uint32(end_id)), at + np.arange(len(at))
                n = n + 1
                k = -(-n // size)
                doc = np.repeat(np.arange(len(n)), k)
                start = (np.arange(len(doc)) - np.repeat(np.cumsum(k) - k, k)) * size
                length = np.minimum(size, n[doc] - start)
                ends = np.concatenate(([0], np.cumsum(length))).astype(np.int32)
                data = pa.BinaryArray.from_buffers(pa.binary(), len(doc), [None, pa.py_buffer((ends * 4).astype(np.int32)), pa.py_buffer(ids.astype("<u4"))])
                yield pa.RecordBatch.from_arrays([part.column("id").take(pa.array(doc)), *map(pa.array, (start, length, n[doc])), data], names=["doc_id", "start", "length", "doc_tokens", "ids"])

    return docs.select(F.col(id_column).cast("long").alias("id"), F.col(text_column).alias("text")).mapInArrow(cut, PIECES)


def knapsack(values: np.ndarray, size: int) -> tuple[float, np.ndarray]:
    """The best multiset of the lengths 1..size that fits size; values[l] is that of length l (0 for length 0)."""
    best, took = np.zeros(size + 1), np.zeros(size + 1, np.int64)
    for c in range(1, size + 1):
        gains = values[1 : c + 1] + best[c - 1 :: -1][:c]
        k = int(gains.argmax())
        if gains[k] > best[c - 1] + 1e-12:
            best[c], took[c] = gains[k], k + 1
        else:
            best[c] = best[c - 1]
    pattern, c = np.zeros(size + 1, np.int64), size
    while c > 0:
        pattern[took[c]] += took[c] > 0
        c -= max(1, took[c])
    return float(best[size]), pattern


def first_fit(demand: np.ndarray, size: int) -> list[np.ndarray]:
    """Patterns of packing longest pieces first, each used as often as its pieces last."""
    left, made = demand.copy(), []
    left[0] = 0
    while left.any():
        pattern, room = np.zeros(size + 1, np.int64), size
        while room and len(fits := np.flatnonzero(left[: room + 1] > pattern[: room + 1])):
            length = int(fits[-1])
            n = int(min(room // length, left[length] - pattern[length]))
            pattern[length] += n
            room -= n * length
        need = pattern > 0
        left -= pattern * int((left[need] // pattern[need]).min())
        made.append(pattern)
    return made


def solve(demand: np.ndarray, size: int, *, gap: float = 0.005, most_steps: int = 600) -> tuple[np.ndarray, np.ndarray, float]:
    """(patterns, rates, bound) of the cutting-stock linear program for demand[l] pieces of length l.

    Revised simplex: columns of `first_fit` that improve it enter first, then those that `knapsack` prices. It
    stops at the optimum, or when the sum of the rates is within gap of a lower bound, or after most_steps priced
    columns (any basis covers the demand, so the patterns stay right).
    """
    lengths = np.flatnonzero(demand)
    if not len(lengths):
        return np.zeros((0, size + 1), np.int64), np.zeros(0), 0.0
    d = demand[lengths].astype(float)
    columns = np.diag((size // lengths).astype(float))
    inverse, x = np.diag(1 / np.diag(columns)), d / (size // lengths)
    bound = float(d @ lengths) / size

    def enter(column: np.ndarray) -> None:
        nonlocal x
        step = inverse @ column
        ratios = np.where(step > 1e-9, x / np.where(step > 1e-9, step, 1), np.inf)
        out = int(ratios.argmin())
        t = ratios[out]
        x = np.maximum(x - t * step, 0)
        x[out] = t
        pivot = inverse[out] / step[out]
        np.subtract(inverse, np.outer(step, pivot), out=inverse)
        inverse[out] = pivot
        columns[:, out] = column

    for pattern in first_fit(demand, size):
        column = pattern[lengths].astype(float)
        if inverse.sum(axis=0) @ column > 1 + 1e-9:
            enter(column)
    for _ in range(most_steps):
        if x.sum() <= bound * (1 + gap):
            break
        values = np.full(size + 1, -1.0)
        values[lengths] = inverse.sum(axis=0)
        worth, pattern = knapsack(values, size)
        if worth <= 1 + 1e-9:
            break
        bound = max(bound, x.sum() / worth)
        enter(pattern[lengths].astype(float))
    full = np.zeros((len(lengths), size + 1), np.int64)
    full[:, lengths] = np.rint(columns.T).astype(np.int64)
    order = np.argsort(-x, kind="stable")
    order = order[x[order] > 1e-9]
    return full[order], x[order], bound


def fill(lengths: np.ndarray, patterns: np.ndarray, rates: np.ndarray, demand: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(sequence, offset) of each piece. lengths: of the pieces of one partition, in rank order within a length.

    Each pattern is used at its rate times the partition's share of the demand, rounded up as far as the
    pieces last; what is left goes, longest first, to the fullest sequence that still has room.
    """
    have = np.bincount(lengths, minlength=size + 1)
    sequence, offset = np.full(len(lengths), -1, np.int64), np.zeros(len(lengths), np.int64)
    ranked = np.argsort(lengths, kind="stable")
    first = np.concatenate(([0], np.cumsum(have)))[:-1]
    used = np.zeros(size + 1, np.int64)
    n = int(have[size])  # full ones need no partner
    sequence[ranked[first[size] : first[size] + n]] = np.arange(n)
    used[size] = n
    share = have[1:size].sum() / max(1, demand[1:size].sum())
    room: list[tuple[int, int]] = []
    for pattern, rate in zip(patterns, rates, strict=True):
        need = np.flatnonzero(pattern)
        if not len(need) or need[-1] == size:
            continue
        times = min(int(np.ceil(rate * share - 1e-9)), int(((have - used)[need] // pattern[need]).min()))
        if times <= 0:
            continue
        at = 0
        for length in need[::-1]:
            a = pattern[length]
            rows = ranked[first[length] + used[length] : first[length] + used[length] + a * times].reshape(times, a)
            sequence[rows] = n + np.arange(times)[:, None]
            offset[rows] = at + length * np.arange(a)
            used[length] += a * times
            at += length * a
        if at < size:
            room += [(n + k, at) for k in range(times)]
        n += times
    free: list[list[tuple[int, int]]] = [[] for _ in range(size + 1)]
    for s, at in room:
        free[size - at].append((s, at))
    open_sizes = np.array([len(x) > 0 for x in free])
    for length in range(size, 0, -1):
        for row in ranked[first[length] + used[length] : first[length] + have[length]]:
            k = int(open_sizes[length:].argmax()) + length
            if open_sizes[k]:
                s, at = free[k].pop()
                open_sizes[k] = bool(free[k])
            else:
                s, at, k, n = n, 0, size, n + 1
            sequence[row], offset[row] = s, at
            free[k - length].append((s, at + length))
            open_sizes[k - length] = True
    return sequence, offset


def pack(cut: DataFrame, *, size: int = 1024, gap: float = 0.005, most_steps: int = 600) -> DataFrame:
    """Place pieces into sequences: the columns of `pieces` with sequence_id and offset.

    cut is read twice, so it should be a written table. A task holds the pieces of its partition, which
    spark.sql.files.maxPartitionBytes bounds. The demand that reaches the driver has size rows at most.
    """
    demand = np.zeros(size + 1, np.int64)
    for row in cut.groupBy("length").count().collect():
        demand[row["length"]] = row["count"]
    remainders = demand.copy()
    remainders[size] = 0
    patterns, rates, _ = solve(remainders, size, gap=gap, most_steps=most_steps)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = list(batches)
        if not held:
            return
        sequence, offset = fill(pc.cast(pa.chunked_array([b.column("length") for b in held]), pa.int64()).to_numpy(), patterns, rates, remainders, size)
        base, at = TaskContext.get().partitionId() << 40, 0
        for b in held:
            n = b.num_rows
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(sequence[at : at + n] + base), pa.array(offset[at : at + n])], names=[*b.schema.names, "sequence_id", "offset"])
            at += n

    return cut.mapInArrow(place, f"{PIECES}, sequence_id long, offset long")
