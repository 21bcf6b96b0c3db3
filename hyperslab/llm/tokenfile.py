"""Token-id files: every id in the fewest bits its vocabulary needs, with offsets for random access.

A file holds one shard: documents in ascending id order.

    blocks   ids packed low bits first; each block starts at a byte, so block b is found by its offset
    offsets  uint64 byte offset of every block, and of the end of the last
    index    int64 document id and uint64 first id (from the shard's start) of every document, and the count of ids
    trailer  place of the offsets, magic, format version, bits per id, ids per block, and as uint64 the numbers of
             documents, of those without an id (they come first) and of ids

Cases: a null text is empty and yields its end id alone; documents without an id sort first, and their number tells them
from the least int64; repeated document ids stay separate documents, in a row; an empty table makes no file; further
columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common, tokens

_MAGIC, _VERSION, _TRAILER = b"HSTK", 2, struct.Struct("<Q4sBBHQQQ")


def bits_for(vocabulary: int) -> int:
    """The bits that the largest id of a vocabulary of that size needs."""
    return max(1, int(vocabulary - 1).bit_length())


def packed(ids: np.ndarray, bits: int) -> bytes:
    """ids in bits bits each, low bits first; ends at a full byte."""
    if bits == 16:
        return ids.astype("<u2").tobytes()
    if bits == 32:
        return ids.astype("<u4").tobytes()
    lanes = (ids[:, None] >> np.arange(bits, dtype=np.uint32)) & np.uint32(1)
    return np.packbits(lanes.astype(np.uint8).ravel(), bitorder="little").tobytes()


def unpacked(data: bytes, bits: int, count: int) -> np.ndarray:
    """The first count ids of data."""
    if bits in (16, 32):
        return np.frombuffer(data, f"<u{bits // 8}", count).astype(np.uint32)
    lanes = np.unpackbits(np.frombuffer(data, np.uint8), count=count * bits, bitorder="little").reshape(count, bits)
    return (lanes.astype(np.uint32) << np.arange(bits, dtype=np.uint32)).sum(axis=1, dtype=np.uint32)


class ShardWriter:
    """Writes one shard; holds a block and the index in memory, never all ids."""

    def __init__(self, out, bits: int, block: int):
        self.out, self.bits, self.block = out, bits, block
        self.docs: list[int] = []
        self.without = 0
        self.firsts: list[int] = []
        self.offsets: list[int] = []
        self.rest, self.n, self.at = np.zeros(0, np.uint32), 0, 0

    def add(self, doc: int | None, ids: np.ndarray) -> None:
        """Documents without an id come before all others."""
        if doc is None and self.without < len(self.docs):
            raise ValueError("a document without an id after one with an id")
        self.without += doc is None
        self.docs.append(0 if doc is None else doc)
        self.firsts.append(self.n)
        self.n += len(ids)
        self.rest = np.concatenate((self.rest, ids))
        while len(self.rest) >= self.block:
            self._put(self.rest[: self.block])
            self.rest = self.rest[self.block :]

    def _put(self, ids: np.ndarray) -> None:
        data = packed(ids, self.bits)
        self.offsets.append(self.at)
        self.out.write(data)
        self.at += len(data)

    def close(self) -> None:
        if len(self.rest):
            self._put(self.rest)
        place = self.at
        self.out.write(np.array([*self.offsets, self.at], "<u8").tobytes())
        self.out.write(np.array(self.docs, "<i8").tobytes())
        self.out.write(np.array([*self.firsts, self.n], "<u8").tobytes())
        self.out.write(_TRAILER.pack(place, _MAGIC, _VERSION, self.bits, self.block & 0xFFFF, len(self.docs), self.without, self.n))


class Shard:
    """Random access to one shard."""

    def __init__(self, uri: str):
        where, path = common.open_store(uri)
        self.file = where.open_input_file(path)
        end = self.file.size()
        place, magic, version, self.bits, block, docs, self.without, self.n = _TRAILER.unpack(self.file.read_at(_TRAILER.size, end - _TRAILER.size))
        if magic != _MAGIC or version != _VERSION:
            raise ValueError(f"{uri} is not a token file of version {_VERSION}")
        self.block = block or 1 << 16
        rest = self.file.read_at(end - _TRAILER.size - place, place)
        blocks = -(-self.n // self.block)
        self.offsets = np.frombuffer(rest, "<u8", blocks + 1)
        self.docs = np.frombuffer(rest, "<i8", docs, 8 * (blocks + 1))
        self.firsts = np.frombuffer(rest, "<u8", docs + 1, 8 * (blocks + 1 + docs)).astype(np.int64)

    def ids(self, start: int, end: int) -> np.ndarray:
        """The ids from start up to end: reads the blocks that hold them only."""
        if end <= start:
            return np.zeros(0, np.uint32)
        a, b = start // self.block, -(-end // self.block)
        data = self.file.read_at(int(self.offsets[b] - self.offsets[a]), int(self.offsets[a]))
        if self.bits % 8 == 0 or self.block % 8 == 0:  # blocks end at full bytes
            all_ids = unpacked(data, self.bits, min(self.n, b * self.block) - a * self.block)
            return all_ids[start - a * self.block : end - a * self.block]
        return np.concatenate([self._one(k) for k in range(a, b)])[start - a * self.block : end - a * self.block]

    def _one(self, k: int) -> np.ndarray:
        data = self.file.read_at(int(self.offsets[k + 1] - self.offsets[k]), int(self.offsets[k]))
        return unpacked(data, self.bits, min(self.block, self.n - k * self.block))


def write(docs: DataFrame, tokenizer: str, word_ends: bool, end_id: int, vocabulary: int, folder: str, *, id_column: str = "doc_id", text_column: str = "text", block: int = 4096) -> DataFrame:
    """Write docs as shards into folder, in ascending id order; one row per shard: shard, path, n_docs, n_ids.

    Rows are dealt by ranges of (id, hash of text, place in the input), so that even one id with many equal rows is
    shared among tasks.
    The result is a written table: reading it doesn't tokenize again.
    """
    bits = bits_for(vocabulary)
    block = min(block, 1 << 15)
    rows = docs.select(F.col(id_column).cast("long").alias("id"), F.col(text_column).alias("text"))
    dealt = rows.withColumn("place", F.monotonically_increasing_id()).repartitionByRange(F.col("id"), F.xxhash64("text"), F.col("place")).drop("place").sortWithinPartitions("id", F.xxhash64("text"))

    def shard(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, number, first = tokens.encoder(tokenizer, word_ends), TaskContext.get().partitionId(), next(batches, None)
        if first is None:
            return
        uri = f"{folder}/shard-{number:06d}.tokens"
        with common.whole_file(uri) as out:
            writer = ShardWriter(out, bits, block)
            while first is not None:
                for part in common.parts(first, "text"):
                    ids, at = encode(part.column("text"))
                    for k, doc in enumerate(part.column("id").to_pylist()):
                        writer.add(doc, np.append(ids[at[k] : at[k + 1]], np.uint32(end_id)))
                first = next(batches, None)
            writer.close()
        yield pa.RecordBatch.from_pydict({"shard": [number], "path": [uri], "n_docs": [len(writer.docs)], "n_ids": [writer.n]})

    return common.written(dealt.mapInArrow(shard, "shard long, path string, n_docs long, n_ids long"), "token-shards")


def read(shards: DataFrame) -> DataFrame:
    """One row per document of those shards: doc_id, start (ids before it over all shards), ids (array of long)."""
    return _documents(shards, "ids array<long>", [pa.field("ids", pa.list_(pa.int64()))], lambda ids: {"ids": ids.tolist()})


def digests(shards: DataFrame) -> DataFrame:
    """One row per document: doc_id, start, n_tokens, ids_crc32 of its ids as little-endian unsigned 32-bit integers."""
    fields = [pa.field("n_tokens", pa.int64()), pa.field("ids_crc32", pa.int64())]
    return _documents(shards, "n_tokens long, ids_crc32 long", fields, lambda ids: {"n_tokens": len(ids), "ids_crc32": zlib.crc32(ids.astype("<u4").tobytes())})


def _documents(shards: DataFrame, columns: str, fields: list[pa.Field], of) -> DataFrame:
    """Reads each shard in steps of about a million ids. The running sum over shards has a row per file."""
    before = F.coalesce(F.sum("n_ids").over(Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    schema = pa.schema([pa.field("doc_id", pa.int64()), pa.field("start", pa.int64()), *fields])

    def documents(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in (row for batch in batches for row in batch.to_pylist()):
            shard, k = Shard(row["path"]), 0
            firsts = shard.firsts
            while k < len(shard.docs):
                end = max(k + 1, int(np.searchsorted(firsts, firsts[k] + (1 << 20), side="right")) - 1)
                ids = shard.ids(int(firsts[k]), int(firsts[end]))
                rows = []
                for j in range(k, end):
                    doc = int(shard.docs[j])
                    rows.append({"doc_id": None if j < shard.without else doc, "start": row["base"] + int(firsts[j])} | of(ids[firsts[j] - firsts[k] : firsts[j + 1] - firsts[k]]))
                yield pa.RecordBatch.from_pylist(rows, schema=schema)
                k = end

    many = max(1, 2 * shards.sparkSession.sparkContext.defaultParallelism)
    return shards.withColumn("base", before).repartition(many, "shard").mapInArrow(documents, f"doc_id long, start long, {columns}")
