"""VA-file: cells of 2^b parts per dimension, a sparse directory of the occupied ones, exact tests within them.

One VA-file over all rows, in DataFrame functions; `Forest(kind="va")` has one per partition. Stored, its rows lie by
cell, so a code range prunes row groups.

Cases: null and NaN have no cell and lie in no bounded interval; equal rows share a cell; a dimension with one value
or none has one cell; an empty table gives an empty result; an id or dimension called like a code or cell column
(c_<dim>, cell_<number>) is refused.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from operator import and_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import BoxQuery, FeatureSpace
from ..shared import written
from .predicate import box_predicate

#: Bits that one word of a packed cell code holds.
WORD = 62


@dataclass
class VaFile:
    """rows: ids, dims, codes c_<dim>, cell words; cuts: per dimension the inner cut points, ascending."""

    rows: DataFrame
    space: FeatureSpace
    bits: dict[str, int]
    cuts: dict[str, list[float]]
    mode: str = "cells"  # or 'flat': candidates by the codes alone, then fetched by their ids

    @staticmethod
    def equal_width_cuts(df: DataFrame, space: FeatureSpace, bits: dict[str, int]) -> dict[str, list[float]]:
        row = df.agg(*(f(F.when(~F.isnan(F.col(d).cast("double")), F.col(d))).cast("double").alias(f"{n}_{d}") for d in space.dims for n, f in (("lo", F.min), ("hi", F.max)))).first()
        out = {}
        for d in space.dims:
            lo, hi, parts = row[f"lo_{d}"], row[f"hi_{d}"], 2 ** bits[d]
            out[d] = [] if lo is None or hi == lo else [lo + (hi - lo) / parts * k for k in range(1, parts)]
        return out

    @staticmethod
    def equal_depth_cuts(df: DataFrame, space: FeatureSpace, bits: dict[str, int], accuracy: int = 10_000) -> dict[str, list[float]]:
        row = df.agg(*(F.percentile_approx(d, [k / 2 ** bits[d] for k in range(1, 2 ** bits[d])], accuracy).alias(d) for d in space.dims if bits[d])).first()
        return {d: sorted({float(v) for v in row[d]}) if bits[d] and row[d] else [] for d in space.dims}

    @classmethod
    def build(cls, df: DataFrame, space: FeatureSpace, *, bits: int | dict[str, int] = 2, split: str = "equi_width", mode: str = "cells") -> VaFile:
        """One pass for the cuts and a projection. Outermost cells are open-ended: later values outside still fit."""
        per = dict.fromkeys(space.dims, bits) if isinstance(bits, int) else bits
        taken = {f"c_{d}" for d in space.dims} & {*space.ids, *space.dims} | {c for c in (*space.ids, *space.dims) if c.startswith("cell_") and c[5:].isdigit()}
        if taken:
            raise ValueError(f"names of code columns: {sorted(taken)}")
        rows = space.features(df)
        cuts = (cls.equal_width_cuts if split == "equi_width" else cls.equal_depth_cuts)(rows, space, per)
        coded = rows.select("*", *(cls.code(F.col(d), cuts[d]).alias(f"c_{d}") for d in space.dims))
        return cls(coded.select("*", *cls.words(space, per)), space, per, cuts, mode)

    def stored(self) -> VaFile:
        """The same VA-file read from a written table, its rows in the order of their cells."""
        words = [c for c in self.rows.columns if c.startswith("cell_") and c[5:].isdigit()]
        placed = self.rows.repartitionByRange(*words).sortWithinPartitions(*words)
        return VaFile(written(placed, "va-rows"), self.space, self.bits, self.cuts, self.mode)

    @staticmethod
    def code(c: Column, cuts: list[float]) -> Column:
        """Number of cuts at or below the value; null and NaN have no cell (null)."""
        n = reduce(lambda a, b: a + b, [(c >= F.lit(cut)).cast("int") for cut in cuts], F.lit(0)) if cuts else F.lit(0)
        return F.when(c.isNotNull() & ~F.isnan(c.cast("double")), n)

    @staticmethod
    def words(space: FeatureSpace, bits: dict[str, int]) -> list[Column]:
        """The codes packed into as many 62-bit words as they need: cell_0, cell_1, ..."""
        out, word, at = [], [], 0
        for d in space.dims:
            if at + bits[d] > WORD:
                out.append(word)
                word, at = [], 0
            word.append(F.shiftleft(F.coalesce(F.col(f"c_{d}"), F.lit(0)).cast("long"), at))
            at += bits[d]
        out.append(word)
        return [reduce(lambda a, b: a.bitwiseOR(b), w).alias(f"cell_{k}") for k, w in enumerate(out)]

    def code_range(self, d: str, lo: float | None, hi: float | None) -> tuple[int, int]:
        top = len(self.cuts[d])
        below = lambda v: sum(cut <= v for cut in self.cuts[d])
        return (0 if lo is None else below(lo)), (top if hi is None else below(hi))

    def candidate(self, query: BoxQuery) -> Column:
        """Rows of cells that meet the box: whole numbers, so files clustered by cell prune."""
        tests = []
        for d, i in query.specified(self.space):
            a, b = self.code_range(d, i.lo, i.hi)
            tests.append(F.col(f"c_{d}").between(a, b))
        return reduce(and_, tests) if tests else F.lit(True)

    def contained(self, query: BoxQuery) -> Column:
        """Rows of cells strictly inside the box in all its dimensions: no exact test needed."""
        tests = []
        for d, i in query.specified(self.space):
            a, b = self.code_range(d, i.lo, i.hi)
            tests.append(F.col(f"c_{d}").between(a + (i.lo is not None), b - (i.hi is not None)))
        return reduce(and_, tests) if tests else F.lit(True)

    def search(self, query: BoxQuery, *, accept_contained: bool = False) -> DataFrame:
        if query.is_empty:
            return self.rows.where(F.lit(False)).select(*self.space.ids)
        exact = box_predicate(query, self.space)
        if accept_contained:
            exact = self.contained(query) | exact
        if self.mode == "flat":
            ids = list(self.space.ids)
            codes = self.rows.where(self.candidate(query)).select(*ids)
            return self.rows.select(*ids, *self.space.dims).join(codes, ids, "left_semi").where(box_predicate(query, self.space)).select(*ids)
        return self.rows.where(self.candidate(query) & exact).select(*self.space.ids)

    def directory(self, *more: str) -> DataFrame:
        """Occupied cells with their number of rows (by the columns more besides, for one VA-file per partition)."""
        return self.rows.groupBy(*more, *(f"c_{d}" for d in self.space.dims)).agg(F.count("*").alias("n"))

    def work(self, query: BoxQuery) -> DataFrame:
        """cells, cells_met, candidates, contained, hits of one query."""
        d = self.directory()
        cells = d.agg(F.count("*").alias("cells"), F.count(F.when(self.candidate(query), 1)).alias("cells_met"))
        rows = self.rows.agg(F.count(F.when(self.candidate(query), 1)).alias("candidates"), F.count(F.when(self.contained(query), 1)).alias("contained"), F.count(F.when(box_predicate(query, self.space), 1)).alias("hits"))
        return cells.crossJoin(rows)  # one row each

    def bucket_load(self) -> DataFrame:
        """occupied, possible cells, mean, greatest and deviation of the load, and the expected load over all cells."""
        possible = float(2 ** sum(self.bits.values()))
        return self.directory().agg(F.count("*").alias("occupied"), F.lit(possible).alias("possible"), F.avg("n").alias("mean_load"), F.max("n").alias("max_load"), F.stddev_pop("n").alias("sd_load"), (F.sum("n") / F.lit(possible)).alias("expected_load"))
