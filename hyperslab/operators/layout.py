"""Clustered layouts: one global arrangement of files with a small directory. The form for 100 TB.

An immutable directory of leaf boxes is filtered first; only the files of leaves that meet the box are read, by
partition pruning on the leaf. Within a file rows are sorted, so row groups prune by their statistics as well.

Cases: null and NaN values lie in no bounded interval and widen no leaf's box; equal rows share a leaf; an empty table
has an empty directory; ids and dimensions may have any name.
"""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import BoxQuery, FeatureSpace
from .batch import inside
from .predicate import box_predicate

#: Leaves up to which a search names them in the filter; beyond, the directory is joined and prunes at run time.
NAMED_LEAVES = 5_000
#: Rows a sample for split planes has at most.
SAMPLE_ROWS = 200_000


class Layout:
    def __init__(self, spark: SparkSession, path: str, space: FeatureSpace):
        self.space, self.path, self.leaf = space, path, space.free("leaf")[0]
        self.rows = spark.read.parquet(f"{path}/rows")
        self.directory = spark.read.option("recursiveFileLookup", "true").parquet(f"{path}/directory")

    @classmethod
    def write(cls, df: DataFrame, space: FeatureSpace, path: str, *, kind: str = "kd", leaves: int = 32, sample_seed: int = 1) -> Layout:
        """kind: 'kd' (median planes, dimensions cycling), 'str' (slabs, then tiles), 'cell' or 'zorder' (cell codes in order)."""
        rows = space.features(df)
        named = space.free("leaf")[0]
        leaf = {"kd": _kd_leaf, "str": _tile_leaf, "cell": _cell_leaf, "zorder": _cell_leaf}[kind](rows, space, leaves, sample_seed, kind)
        placed = rows.withColumn(named, leaf.cast("int"))
        placed.repartition(named).sortWithinPartitions(named, *space.dims[:2]).write.mode("overwrite").partitionBy(named).parquet(f"{path}/rows")
        spark = df.sparkSession
        stored = spark.read.schema(placed.select(*space.ids, *space.dims, named).schema).parquet(f"{path}/rows")
        boxes = stored.groupBy(F.col(named).alias("leaf")).agg(*_box_columns(space))
        boxes.coalesce(1).write.mode("overwrite").parquet(f"{path}/directory/first")
        return cls(spark, path, space)

    def append(self, df: DataFrame, *, batch: int | None = None) -> Layout:
        """Rows of df as further files, a leaf of their own per call, with their directory row: a bulk insert. The files
        come first, so a search that runs meanwhile sees all of it or nothing. batch: a number of the caller's; a batch
        that is appended again replaces itself."""
        number = self.directory.agg(F.coalesce(F.max("leaf"), F.lit(0)) + 1).first()[0] if batch is None else -1 - batch
        return self._put(df, number, f"append-{number}")

    def _put(self, df: DataFrame, number: int, name: str) -> Layout:
        spark, part = df.sparkSession, f"{self.path}/rows/{self.leaf}={number}"
        self.space.features(df).write.mode("overwrite").parquet(part)
        boxes = spark.read.parquet(part).agg(F.lit(number).alias("leaf"), *_box_columns(self.space))
        boxes.where("n > 0").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/directory/{name}")
        return Layout(spark, self.path, self.space)

    def meets(self, query: BoxQuery) -> Column:
        tests = [t for d, i in query.specified(self.space) for t in ([F.col(f"hi_{d}") >= i.lo] if i.lo is not None else []) + ([F.col(f"lo_{d}") <= i.hi] if i.hi is not None else [])]
        return reduce(and_, tests) if tests else F.lit(True)

    def search(self, query: BoxQuery) -> DataFrame:
        met = self.directory.where(self.meets(query)).select("leaf")
        named = [r["leaf"] for r in met.limit(NAMED_LEAVES + 1).collect()]
        rows = self.rows.where(F.col(self.leaf).isin(named)) if len(named) <= NAMED_LEAVES else self.rows.join(met.withColumnRenamed("leaf", self.leaf), self.leaf, "left_semi")
        return rows.where(box_predicate(query, self.space)).select(*self.space.ids)

    def search_batch(self, queries: DataFrame) -> DataFrame:
        """(query_id, ids): queries meet leaves of the directory first, then rows by the leaf."""
        q_id, lo, hi = self.space.free("query_id", "lo", "hi")
        met = queries.join(self.directory, _meeting(self.space, "lo", "hi", "hi_", "lo_"))
        sent = met.select(F.col("query_id").alias(q_id), F.col("lo").alias(lo), F.col("hi").alias(hi), F.col("leaf").alias(self.leaf))
        return self.rows.join(sent, self.leaf).where(inside(self.space, lo, hi)).select(F.col(q_id).alias("query_id"), *self.space.ids)

    def work(self, query: BoxQuery) -> DataFrame:
        met = self.meets(query)
        return self.directory.agg(F.count("*").alias("leaves"), F.count(F.when(met, 1)).alias("leaves_visited"), F.coalesce(F.sum(F.when(met, F.col("n"))), F.lit(0)).alias("rows_read"), F.sum("n").alias("rows"))


def _box_columns(space: FeatureSpace) -> list[Column]:
    """n, and lo_<dim> and hi_<dim> over the values that are numbers."""
    real = lambda d: F.when(~F.isnan(F.col(f"`{d}`").cast("double")), F.col(f"`{d}`"))
    return [F.count("*").alias("n"), *(f(real(d)).alias(f"{name}_{d}") for d in space.dims for name, f in (("lo", F.min), ("hi", F.max)))]


def _meeting(space: FeatureSpace, lo: str, hi: str, high: str, low: str) -> Column:
    """Interval of the query (arrays lo, hi) and box (columns low<dim>, high<dim>) overlap wherever the query has a bound."""
    tests = [(F.col(lo)[j].isNull() | (F.col(f"`{high}{d}`") >= F.col(lo)[j])) & (F.col(hi)[j].isNull() | (F.col(f"`{low}{d}`") <= F.col(hi)[j])) for j, d in enumerate(space.dims)]
    return reduce(and_, tests)


def _sampled(rows: DataFrame, space: FeatureSpace, seed: int):
    """Up to SAMPLE_ROWS rows by hash of the ids: split planes need no more, whatever the table's size."""
    n = rows.count()
    share = min(1.0, SAMPLE_ROWS / max(1, n))
    some = rows if share == 1 else rows.where(F.pmod(F.xxhash64(*space.ids, F.lit(seed)), F.lit(1 << 20)) < int(share * (1 << 20)))
    return some.select(*(F.col(d).cast("double").alias(d) for d in space.dims)).limit(SAMPLE_ROWS).toPandas().to_numpy()


def _kd_leaf(rows: DataFrame, space: FeatureSpace, leaves: int, seed: int, kind: str) -> Column:
    import numpy as np

    x = _sampled(rows, space, seed)

    def split(part, depth: int, number: int) -> Column:
        if 2**depth >= leaves or len(part) < 2:
            return F.lit(number)
        for step in range(space.m):  # a dimension that the median separates
            j = (depth + step) % space.m
            plane = float(np.nanmedian(part[:, j])) if len(part) else 0.0
            left = part[:, j] <= plane
            if left.any() and not left.all():
                return F.when(F.col(space.dims[j]) <= plane, split(part[left], depth + 1, 2 * number)).otherwise(split(part[~left], depth + 1, 2 * number + 1))
        return F.lit(number)

    return split(x, 0, 1)


def _tile_leaf(rows: DataFrame, space: FeatureSpace, leaves: int, seed: int, kind: str) -> Column:
    import numpy as np

    x = _sampled(rows, space, seed)
    slabs = max(1, int(round(leaves**0.5)))
    if not len(x):
        return F.lit(0)
    a = np.unique(np.nanquantile(x[:, 0], np.linspace(0, 1, slabs + 1)[1:-1]))
    slab = np.searchsorted(a, x[:, 0], side="left")
    number = reduce(lambda s, c: s + (F.col(space.dims[0]) > float(c)).cast("int"), a, F.lit(0))
    second = space.dims[min(1, space.m - 1)]
    out = F.lit(0)
    for k in range(len(a) + 1):
        own = x[slab == k, min(1, space.m - 1)]
        b = np.unique(np.nanquantile(own, np.linspace(0, 1, slabs + 1)[1:-1])) if len(own) else []
        tile = reduce(lambda s, c: s + (F.col(second) > float(c)).cast("int"), b, F.lit(0))
        out = F.when(number == k, tile + k * slabs).otherwise(out)
    return out


def _cell_leaf(rows: DataFrame, space: FeatureSpace, leaves: int, seed: int, kind: str) -> Column:
    """The leading dimensions' codes, as one number ('cell') or with their bits interleaved ('zorder')."""
    import numpy as np

    x = _sampled(rows, space, seed)
    used = min(space.m, 3)
    bits = max(1, int(np.log2(max(2, leaves)) // used))
    codes = []
    for j in range(used):
        cuts = np.unique(np.nanquantile(x[:, j], np.linspace(0, 1, 2**bits + 1)[1:-1])) if len(x) else []
        codes.append(reduce(lambda s, c: s + (F.col(space.dims[j]) > float(c)).cast("int"), cuts, F.lit(0)))
    if kind == "cell":
        return reduce(lambda a, c: a * (2**bits) + c, codes)
    return reduce(lambda a, b: a + b, [F.shiftleft(F.shiftright(c, b).bitwiseAND(F.lit(1)), b * used + j) for b in range(bits) for j, c in enumerate(codes)])
