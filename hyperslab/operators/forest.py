"""A forest: one index per partition of rows, all searched, the answers concatenated.

Faithful to the conservative way of running index structures in parallel. Every index spans the whole space, so none
can be left out; at 100 TB use the layouts instead, which prune before tasks start. Built once and saved, a forest is
searched from its table: a search reads the stored structures and builds none.

Cases: null and NaN values lie in no bounded interval; equal rows are objects of their own; an empty table makes a
forest without trees; ids and dimensions may have any name.
"""

from __future__ import annotations

import io
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass
from functools import reduce
from operator import add

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.encode import with_row_id
from ..model import BoxQuery, FeatureSpace
from . import cells, flat, kdtree, rtree
from .predicate import box_predicate

Arrays = dict[str, np.ndarray]


@dataclass(frozen=True)
class Kind:
    """How a partition's objects become plain arrays, and how these are searched."""

    build: Callable[[np.ndarray], Arrays]
    search: Callable[..., tuple[np.ndarray, dict[str, int]]]


def _kd(variant: str) -> Kind:
    return Kind(lambda x: kdtree.arrays(kdtree.build(x, variant)), lambda a, lo, hi, k: kdtree.search(kdtree.of_arrays(a), lo, hi, k))


def _r(variant: str, accept: bool = False) -> Kind:
    return Kind(lambda x: rtree.arrays(rtree.build(x, variant)), lambda a, lo, hi, k: rtree.search(a, lo, hi, k=k, accept_contained=accept))


#: 'rows' and 'columns' keep the objects only: the scans, searched in the same way as the indexes.
KINDS = {
    "kd": _kd("insertion"), "kd_median": _kd("median"), "rstar": _r("rstar"), "rstar_contained": _r("rstar", True), "quadratic": _r("quadratic"), "packed": _r("packed"),
    "va": Kind(cells.build, cells.search), "rows": Kind(flat.build_rows, flat.search_rows), "columns": Kind(flat.build_columns, flat.search_columns),
}
TREES = "tree long, piece int, part int, n long, seconds double, ids binary, arrays binary"
_TREES = pa.schema([("tree", pa.int64()), ("piece", pa.int32()), ("part", pa.int32()), ("n", pa.int64()), ("seconds", pa.float64()), ("ids", pa.binary()), ("arrays", pa.binary())])
#: Bytes of values that a worker builds a structure over at once; it holds some ten times as much meanwhile. The tree of
#: a partition with more rows is kept in pieces, each a structure of its own; it counts as one tree.
PIECE_BYTES = 2 << 20


def piece_rows(m: int) -> int:
    """Rows of m dimensions in a piece at most."""
    return max(1, PIECE_BYTES // (8 * max(1, m)))


def pieces(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[tuple[int, int, pa.Table]]:
    """(part, number of the piece in it, rows) from batches whose first column is the part: its rows lie together."""
    held: list[pa.RecordBatch] = []
    current, number, size = None, 0, 0
    for batch in batches:
        parts = batch.column(0).to_numpy()
        edges = [0, *(np.flatnonzero(parts[1:] != parts[:-1]) + 1).tolist(), len(parts)]
        for a, b in zip(edges, edges[1:], strict=False):
            while a < b:
                if held and (parts[a] != current or size >= most):
                    yield current, number, pa.Table.from_batches(held)
                    held, size, number = [], 0, number + 1
                if parts[a] != current:
                    current, number = int(parts[a]), 0
                n = min(b - a, most - size)
                held.append(batch.slice(a, n))
                a, size = a + n, size + n
    if held:
        yield current, number, pa.Table.from_batches(held)


def _stored(arrays: Arrays) -> bytes:
    out = io.BytesIO()
    np.savez(out, **arrays)
    return out.getvalue()


def _opened(data: bytes) -> Arrays:
    with np.load(io.BytesIO(data), allow_pickle=False) as held:
        return {k: held[k] for k in held.files}


class Forest:
    """trees: a row per piece of an index, with its structure and objects as arrays and their ids as an Arrow stream.
    builds: how many builds the trees come from; pieces of one tree share its number."""

    def __init__(self, trees: DataFrame, space: FeatureSpace, kind: str, id_schema: str, gone: DataFrame | None = None, builds: int = 1):
        self.trees, self.space, self.kind, self.id_schema, self.gone, self.builds = trees, space, kind, id_schema, gone, builds

    @staticmethod
    def dealt(df: DataFrame, space: FeatureSpace, p: int, assign: str = "hash", seed: int = 1, workload: Sequence[BoxQuery] = ()) -> DataFrame:
        """Ids and dimensions of df with their partition, a column named space.free("part").

        assign: 'hash' of the ids; 'random'; 'round_robin' over the key order; 'arithmetic' on the first id; 'balanced':
        rows in the order of how many queries of workload they meet are dealt in turn, so each partition has an equal
        share of every degree of heat and the queries' answers spread evenly.
        """
        rows, part = space.features(df), space.free("part")[0]
        ids = [F.col(f"`{c}`") for c in space.ids]
        if assign == "random":
            return rows.withColumn(part, F.floor(F.rand(seed) * p).cast("int"))
        if assign == "arithmetic":
            return rows.withColumn(part, F.pmod(ids[0] * 7_919 + 31, F.lit(p)).cast("int"))
        if assign == "hash":
            return rows.withColumn(part, F.pmod(F.xxhash64(*ids), F.lit(p)).cast("int"))
        number = space.free("number")[0]
        if assign == "round_robin":
            return with_row_id(rows, space.ids, name=number).withColumn(part, F.pmod(F.col(number) - 1, F.lit(p)).cast("int")).drop(number)
        if assign == "balanced":
            heat, order = space.free("heat", "order")
            met = reduce(add, [F.coalesce(box_predicate(q, space), F.lit(False)).cast("int") for q in workload], F.lit(0))
            marked = rows.withColumn(heat, met).withColumn(order, F.xxhash64(*ids, F.lit(seed)))
            return with_row_id(marked, (heat, order, *space.ids), name=number).withColumn(part, F.pmod(F.col(number) - 1, F.lit(p)).cast("int")).drop(number, heat, order)
        raise ValueError(assign)

    @classmethod
    def build(cls, df: DataFrame, space: FeatureSpace, kind: str = "kd", *, p: int = 8, assign: str = "hash", order: str = "random", seed: int = 1, workload: Sequence[BoxQuery] = (), number: int = 0) -> Forest:
        """order: in which rows of a piece are inserted, 'random' (a hash of the ids and the seed) or 'sorted' (by the dimensions).
        Every partition is built by a task of its own. number: of the build, for trees that stand beside others."""
        if kind not in KINDS:
            raise ValueError(kind)
        part = space.free("part")[0]
        rows = cls.dealt(df, space, p, assign, seed, workload)
        ids = [F.col(f"`{c}`") for c in space.ids]
        values = [F.col(f"`{d}`").cast("double") for d in space.dims]
        inner = [f"_v{k}" for k in range(space.m)]
        named = rows.select(F.col(part).alias("_part"), *(c.alias(f"_i{k}") for k, c in enumerate(ids)), *(v.alias(c) for v, c in zip(values, inner, strict=True)))
        key = F.xxhash64(*(f"_i{k}" for k in range(len(ids))), F.lit(seed)) if order == "random" else F.lit(0).cast("long")
        dealt = named.repartitionById(p, F.col("_part")).select("*", key.alias("_key"))  # a part's rows come to one task, unsorted
        names, first, made, most = list(space.ids), 1 + len(ids), KINDS[kind].build, piece_rows(space.m)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            import time

            for part, piece, table in pieces(batches, most):
                x = np.stack([table.column(first + k).to_numpy() for k in range(len(inner))], axis=1)
                inserted = np.argsort(table.column(first + len(inner)).to_numpy(), kind="stable") if order == "random" else np.lexsort(x.T[::-1])
                x = x[inserted]
                sink = io.BytesIO()
                keys_only = table.select(list(range(1, first))).rename_columns(names).take(inserted).combine_chunks()
                with pa.ipc.new_stream(sink, keys_only.schema) as out:
                    out.write_table(keys_only)
                began = time.perf_counter()
                arrays = made(x)
                took = time.perf_counter() - began
                yield pa.RecordBatch.from_pylist([{"tree": number * 1_000_000 + part, "piece": piece, "part": part, "n": len(x), "seconds": took, "ids": sink.getvalue(), "arrays": _stored(arrays)}], schema=_TREES)

        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.select(*ids).schema)
        return cls(dealt.mapInArrow(run, TREES), space, kind, schema)

    def save(self, path: str) -> Forest:
        """The forest read from Parquet at path: built once, searched often. A row group ends once it has 1 MB, which is
        looked at after every row, and without least and greatest values, which the footer would hold until the end of the
        file: so writer and reader hold a piece or two."""
        self.trees.write.mode("overwrite").option("compression", "zstd").option("parquet.enable.dictionary", False).option("parquet.column.statistics.enabled", False).option("parquet.block.size", 1 << 20).option("parquet.page.size.row.check.min", 1).option("parquet.page.size.row.check.max", 1).parquet(path)
        return Forest(self.trees.sparkSession.read.schema(TREES).parquet(path), self.space, self.kind, self.id_schema, self.gone, self.builds)

    def append(self, df: DataFrame, **how) -> Forest:
        """A bulk insert: further trees beside the old ones."""
        more = Forest.build(df, self.space, self.kind, number=self.builds, **how)
        return Forest(self.trees.unionByName(more.trees), self.space, self.kind, self.id_schema, self.gone, self.builds + 1)

    def delete(self, ids: DataFrame) -> Forest:
        """Objects that searches leave out from now on; a rebuild makes that permanent."""
        gone = ids.select(*(F.col(f"`{c}`") for c in self.space.ids))
        return Forest(self.trees, self.space, self.kind, self.id_schema, gone if self.gone is None else self.gone.unionByName(gone), self.builds)

    def _bounds(self, queries: Sequence[tuple[int, str, BoxQuery]]) -> list[tuple[int, np.ndarray, np.ndarray]]:
        return [(i, *(np.array([np.nan if b is None else b for b in side], float) for side in q.bounds(self.space))) for i, _, q in queries if not q.is_empty]

    def search(self, query: BoxQuery, k: int | None = None) -> DataFrame:
        """The ids of the objects in the box. k: dimensions compared at once."""
        return self.search_batch([(0, "", query)], k).select(*(F.col(f"`{c}`") for c in self.space.ids))

    def search_batch(self, queries: Sequence[tuple[int, str, BoxQuery]], k: int | None = None) -> DataFrame:
        """(query_id, ids): every tree is opened once for all queries."""
        search, bounds, name = KINDS[self.kind].search, self._bounds(queries), self.space.free("query_id")[0]

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for ids, data in zip(batch.column(0), batch.column(1), strict=True):
                    keys, arrays = pa.ipc.open_stream(ids.as_buffer()).read_all(), _opened(data.as_py())
                    for i, lo, hi in bounds:
                        rows, _ = search(arrays, lo, hi, k)
                        if len(rows):
                            for hits in keys.take(pa.array(rows)).combine_chunks().to_batches():
                                yield pa.RecordBatch.from_arrays([pa.array(np.full(hits.num_rows, i)), *hits.columns], names=[name, *hits.schema.names])

        found = self.trees.select("ids", "arrays").mapInArrow(run, f"`{name}` long, {self.id_schema}")
        found = found if self.gone is None else found.join(self.gone, list(self.space.ids), "left_anti")
        return found.select(F.col(name).alias("query_id"), *(F.col(f"`{c}`") for c in self.space.ids))

    def work_batch(self, queries: Sequence[tuple[int, str, BoxQuery]], k: int | None = None) -> DataFrame:
        """(query_id, hits, trees, nodes_visited, nodes, compared, objects_tested) summed over the trees; no ids are read
        and tombstones are not looked up, so hits counts deleted objects too."""
        search, bounds = KINDS[self.kind].search, self._bounds(queries)
        names = ("hits", "nodes_visited", "nodes", "compared", "objects_tested")

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for tree, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    arrays, out = _opened(data.as_py()), []
                    for i, lo, hi in bounds:
                        rows, counters = search(arrays, lo, hi, k)
                        out.append({"query_id": i, "tree": tree, **{c: int(v) for c, v in (counters | {"hits": len(rows)}).items() if c in names}})
                    if out:
                        yield pa.RecordBatch.from_pylist(out, schema=pa.schema([(c, pa.int64()) for c in ("query_id", "tree", *names)]))

        schema = ", ".join(f"{c} long" for c in ("query_id", "tree", *names))
        each = self.trees.select("tree", "arrays").mapInArrow(run, schema).groupBy("query_id", "tree").agg(*(F.sum(c).alias(c) for c in names))
        return each.groupBy("query_id").agg(F.sum("hits").alias("hits"), F.count("*").alias("trees"), *(F.sum(c).alias(c) for c in names[1:]))

    def work(self, query: BoxQuery, k: int | None = None) -> DataFrame:
        """(metric, value) of one query: the sums of `work_batch`."""
        row = self.work_batch([(0, "", query)], k)
        return row.select(F.explode(F.array(*(F.struct(F.lit(c).alias("metric"), F.col(c).alias("value")) for c in row.columns[1:]))).alias("s")).select("s.*")

    def build_cost(self) -> DataFrame:
        """trees, objects, seconds of all builds together and of the longest one."""
        each = self.trees.groupBy("tree").agg(F.sum("n").alias("n"), F.sum("seconds").alias("seconds"))
        return each.agg(F.count("*").alias("trees"), F.sum("n").alias("n"), F.sum("seconds").alias("seconds"), F.max("seconds").alias("longest"))

    def space_bytes(self) -> DataFrame:
        """index_bytes (structure and objects) and data_bytes (32-bit values, as the reference counts) of all trees."""
        return self.trees.agg(F.sum(F.length("arrays")).alias("index_bytes"), (F.sum("n") * 4 * self.space.m).alias("data_bytes"))
