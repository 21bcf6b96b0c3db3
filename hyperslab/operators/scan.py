"""Scans over row partitions and over column partitions."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.encode import with_row_id
from ..model import BoxQuery, FeatureSpace
from ..shared import written
from .predicate import box_predicate, chunked_predicate, conjuncts


class RowScan:
    """Tests every row where it lies. p partitions dealt at build; None keeps the file splits.

    chunk: dimensions compared at once (None: one by one). full_width: compare unspecified dimensions too. Rows are
    compared with the bounds of an empty box (lo > hi) too.
    A search has no exchange: the result's partitions are the concatenated partial results.
    """

    def __init__(self, df: DataFrame, space: FeatureSpace, *, p: int | None = None, chunk: int | None = None, full_width: bool = False, order: list[str] | None = None):
        rows = space.features(df)
        self.space, self.chunk, self.full_width, self.order = space, chunk, full_width, order
        self.rows = rows if p is None else rows.coalesce(1) if p == 1 else rows.repartition(p)

    def predicate(self, query: BoxQuery):
        if self.chunk:
            return chunked_predicate(query, self.space, self.chunk)
        return box_predicate(query, self.space, full_width=self.full_width, order=self.order, foreseen=False)

    def search(self, query: BoxQuery) -> DataFrame:
        return self.rows.where(self.predicate(query)).select(*self.space.ids)

    def count(self, query: BoxQuery) -> DataFrame:
        return self.rows.where(self.predicate(query)).agg(F.count("*").alias("n_hits"))


#: Rows that one bitmap covers, as Spark's bitmap functions have it.
BITS = 32_768


class ColumnScan:
    """One partition per dimension, scanned by itself; the row ids or bitmaps of the dimensions are then combined.

    combine: 'bitmap' (bitwise and per bucket of rows), 'intersect' (semi joins of row ids), 'count' (dimensions
    matched per row), 'fused' (one filter on the columnar reader). A partial match reads only its dimensions.
    chunks: row ranges that each dimension is chopped into besides (two-level partitioning).
    codec: how the columns are stored: 'zstd' over dictionary and run-length pages (the default), 'snappy' or 'none'.
    Except for 'fused', the columns are stored with their row ids at build; a search reads them from there.
    """

    def __init__(self, df: DataFrame, space: FeatureSpace, *, combine: str = "bitmap", chunks: int | None = None, vector: bool = False, codec: str = "zstd"):
        if combine not in ("bitmap", "intersect", "count", "fused"):
            raise ValueError(combine)
        self.space, self.combine, self.chunks, self.vector = space, combine, chunks, vector
        self.row_id = space.free("row_id")[0]
        self.rows = space.features(df) if combine == "fused" else written(with_row_id(space.features(df), space.ids, name=self.row_id), "columns", compression=codec)

    def _column(self, dim: str) -> DataFrame:
        column = self.rows.select(F.col(self.row_id).alias("row_id"), F.col(f"`{dim}`").alias("value"))
        return column.repartitionByRange(self.chunks, "row_id") if self.chunks else column

    def _hits(self, dim: str, interval) -> DataFrame:
        column = self._column(dim)
        if not self.vector:
            return column.where(reduce(lambda a, b: a & b, conjuncts("value", interval))).select("row_id")
        lo, hi = (-np.inf if interval.lo is None else interval.lo), (np.inf if interval.hi is None else interval.hi)

        def compare(batches):
            for b in batches:
                x = b.column(1).to_numpy(zero_copy_only=False).astype(float)
                yield pa.RecordBatch.from_arrays([b.column(0).filter(pa.array((x >= lo) & (x <= hi)))], names=["row_id"])

        return column.mapInArrow(compare, "row_id long")

    def bitmaps(self, query: BoxQuery) -> DataFrame:
        """(dim, bucket, bits): a bitmap per dimension and bucket with a hit."""
        each = [
            self._hits(d, i).groupBy(F.bitmap_bucket_number("row_id").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("row_id")).alias("bits")).select(F.lit(d).alias("dim"), "bucket", "bits")
            for d, i in query.specified(self.space)
        ]
        return reduce(DataFrame.unionByName, each)

    def combined(self, query: BoxQuery) -> DataFrame:
        """(bucket, bits) after the bitwise and; a bucket that some dimension doesn't hit is gone."""
        maps = self.bitmaps(query)
        q = query.n_dims(self.space)
        if q == 1:
            return maps.select("bucket", "bits")
        return maps.groupBy("bucket").agg(F.count("*").alias("n"), F.bitmap_and_agg("bits").alias("bits")).where(F.col("n") == q).select("bucket", "bits")

    @staticmethod
    def decoded(maps: DataFrame) -> DataFrame:
        """The row ids of the set bits."""

        def run(batches):
            for b in batches:
                for bucket, bits in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    set_bits = np.flatnonzero(np.unpackbits(np.frombuffer(bits, np.uint8), bitorder="little"))
                    yield pa.RecordBatch.from_arrays([pa.array((bucket - 1) * BITS + set_bits + 1)], names=["row_id"])

        return maps.mapInArrow(run, "row_id long")

    def row_ids(self, query: BoxQuery) -> DataFrame:
        if self.combine == "bitmap":
            return self.decoded(self.combined(query))
        each = [self._hits(d, i) for d, i in query.specified(self.space)]
        if self.combine == "intersect":
            return reduce(lambda a, b: a.join(b, "row_id", "left_semi"), each)
        return reduce(DataFrame.unionAll, each).groupBy("row_id").agg(F.count("*").alias("n")).where(F.col("n") == len(each)).select("row_id")

    def search(self, query: BoxQuery) -> DataFrame:
        if query.is_empty:
            return self.rows.where(F.lit(False)).select(*self.space.ids)
        if self.combine == "fused" or not query.specified(self.space):
            return self.rows.where(box_predicate(query, self.space)).select(*self.space.ids)
        return self.rows.join(self.row_ids(query).withColumnRenamed("row_id", self.row_id), self.row_id, "left_semi").select(*self.space.ids)

    def count(self, query: BoxQuery) -> DataFrame:
        """Hits without decoding."""
        return self.combined(query).agg(F.coalesce(F.sum(F.bitmap_count("bits")), F.lit(0)).alias("n_hits"))
