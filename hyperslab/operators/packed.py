"""A packed tree in DataFrame functions: nested tiles of equal counts, their bounding boxes as a directory.

Stored at build, rows sorted by leaf: a search filters the directory and reads the row groups of the leaves it meets.

Cases: null and NaN values lie in no bounded interval and widen no box; equal values go to tiles by the ids; an empty
table has no leaf; ids and dimensions may have any name.
"""

from __future__ import annotations

from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.encode import with_row_id
from ..model import BoxQuery, FeatureSpace
from ..shared import written
from .predicate import box_predicate

#: Leaves up to which a search names them in the filter; beyond, the directory is joined.
NAMED_LEAVES = 5_000


class PackedTree:
    """rows with leaf; leaves: a row per leaf with its box and count. Both are written tables."""

    def __init__(self, df: DataFrame, space: FeatureSpace, *, tiles: int = 9, levels: int = 3):
        """tiles per level and dimension. The first dimension's tiles come from row numbers in its order, so no task
        holds all rows; the windows of the next levels run within tiles."""
        self.space, self.tiles = space, tiles
        self.leaf, number = space.free("leaf", "number")
        t = space.free(*(f"t{k}" for k in range(max(1, min(levels, space.m)))))
        ids = [F.col(f"`{c}`") for c in space.ids]
        ordered = with_row_id(space.features(df), (space.dims[0], *space.ids), name=number)
        n = ordered.count()
        size, more = divmod(n, tiles)  # the first tiles have one row more
        place = F.col(number) - 1
        first = F.when(place < more * (size + 1), F.floor(place / (size + 1))).otherwise(more + F.floor((place - more * (size + 1)) / max(1, size)))
        tiled = ordered.withColumn(t[0], first.cast("int")).drop(number)
        for k, name in list(enumerate(t))[1:]:
            tiled = tiled.withColumn(name, F.ntile(tiles).over(Window.partitionBy(*t[:k]).orderBy(F.col(f"`{space.dims[k]}`"), *ids)) - 1)
        leaf = reduce(lambda a, c: a * tiles + F.col(c), t, F.lit(0)).cast("int")
        placed = tiled.withColumn(self.leaf, leaf).drop(*t)
        self.rows = written(placed.sortWithinPartitions(self.leaf), "packed-rows")
        self.leaves = written(self.boxes(self.rows, self.leaf), "packed-leaves")

    def boxes(self, rows: DataFrame, key: str) -> DataFrame:
        real = lambda d: F.when(~F.isnan(F.col(f"`{d}`").cast("double")), F.col(f"`{d}`"))
        return rows.groupBy(F.col(key).alias("leaf")).agg(F.count("*").alias("n"), *(f(real(d)).alias(f"{name}_{d}") for d in self.space.dims for name, f in (("lo", F.min), ("hi", F.max))))

    def upper(self) -> DataFrame:
        """The level above the leaves: leaves that share all but their last tile."""
        return self.leaves.groupBy(F.floor(F.col("leaf") / self.tiles).cast("int").alias("node")).agg(F.sum("n").alias("n"), F.count("*").alias("n_leaves"), *(f(f"`{name}_{d}`").alias(f"{name}_{d}") for d in self.space.dims for name, f in (("lo", F.min), ("hi", F.max))))

    def meets(self, query: BoxQuery) -> Column:
        tests = [t for d, i in query.specified(self.space) for t in ([F.col(f"`hi_{d}`") >= i.lo] if i.lo is not None else []) + ([F.col(f"`lo_{d}`") <= i.hi] if i.hi is not None else [])]
        return reduce(and_, tests) if tests else F.lit(True)

    def search(self, query: BoxQuery) -> DataFrame:
        met = self.leaves.where(self.meets(query)).select("leaf")
        named = [r["leaf"] for r in met.limit(NAMED_LEAVES + 1).collect()]
        rows = self.rows.where(F.col(self.leaf).isin(named)) if len(named) <= NAMED_LEAVES else self.rows.join(met.withColumnRenamed("leaf", self.leaf), self.leaf, "left_semi")
        return rows.where(box_predicate(query, self.space)).select(*self.space.ids)

    def work(self, query: BoxQuery) -> DataFrame:
        """leaves, leaves_visited, objects_tested."""
        met = self.meets(query)
        return self.leaves.agg(F.count("*").alias("leaves"), F.count(F.when(met, 1)).alias("leaves_visited"), F.coalesce(F.sum(F.when(met, F.col("n"))), F.lit(0)).alias("objects_tested"))

    def overlap(self) -> DataFrame:
        """n_pairs of leaves that overlap, and the volume they share, summed over the pairs. The directory meets itself."""
        other = self.leaves.select(*(F.col(f"`{c}`").alias(f"b_{c}") for c in self.leaves.columns))
        meets, volume = F.col("leaf") < F.col("b_leaf"), F.lit(1.0)
        for d in self.space.dims:
            lo, hi = F.greatest(f"`lo_{d}`", f"`b_lo_{d}`"), F.least(f"`hi_{d}`", f"`b_hi_{d}`")
            meets, volume = meets & (lo <= hi), volume * (hi - lo)
        return self.leaves.join(other, meets).agg(F.count("*").alias("n_pairs"), F.coalesce(F.sum(volume), F.lit(0.0)).alias("volume"))
