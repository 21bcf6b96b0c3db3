"""Box queries: a closed interval on some or all dimensions of a feature space."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class Interval:
    """lo <= value <= hi; an absent bound is None. NaN and null values lie in no interval."""

    lo: float | None = None
    hi: float | None = None

    @staticmethod
    def point(value: float) -> Interval:
        return Interval(value, value)

    @property
    def is_point(self) -> bool:
        return self.lo is not None and self.lo == self.hi

    @property
    def is_empty(self) -> bool:
        return any(b is not None and math.isnan(b) for b in (self.lo, self.hi)) or self.lo is not None and self.hi is not None and self.lo > self.hi

    @property
    def is_free(self) -> bool:
        return self.lo is None and self.hi is None

    def meets(self, lo: float, hi: float) -> bool:
        return (self.hi is None or lo <= self.hi) and (self.lo is None or hi >= self.lo)


@dataclass(frozen=True)
class FeatureSpace:
    """Which columns identify an object and which are its dimensions, in order."""

    ids: tuple[str, ...]
    dims: tuple[str, ...]

    def features(self, df: DataFrame) -> DataFrame:
        """Ids and dimensions of df; fails on missing columns before any job runs."""
        missing = [c for c in (*self.ids, *self.dims) if c not in df.columns]
        if missing:
            raise ValueError(f"columns missing from the feature table: {missing}")
        return df.select(*self.ids, *self.dims)

    def free(self, *names: str) -> tuple[str, ...]:
        """Those names, or longer ones where an id or a dimension is called so: for helper columns."""
        taken = {c.lower() for c in (*self.ids, *self.dims)}
        return tuple("_" * next(k for k in range(len(taken) + 1) if "_" * k + n not in taken) + n for n in names)

    @property
    def m(self) -> int:
        return len(self.dims)


@dataclass(frozen=True)
class BoxQuery:
    """Intervals by dimension name; a dimension that isn't named is unspecified."""

    box: dict[str, Interval] = field(default_factory=dict)

    @staticmethod
    def of(**bounds: tuple[float | None, float | None] | float) -> BoxQuery:
        return BoxQuery({d: Interval(*b) if isinstance(b, tuple) else Interval.point(b) for d, b in bounds.items()})

    def specified(self, space: FeatureSpace) -> list[tuple[str, Interval]]:
        unknown = set(self.box) - set(space.dims)
        if unknown:
            raise ValueError(f"no such dimensions: {sorted(unknown)}")
        return [(d, self.box[d]) for d in space.dims if d in self.box and not self.box[d].is_free]

    def n_dims(self, space: FeatureSpace) -> int:
        return len(self.specified(space))

    def is_complete(self, space: FeatureSpace) -> bool:
        return self.n_dims(space) == space.m

    @property
    def is_empty(self) -> bool:
        return any(i.is_empty for i in self.box.values())

    def bounds(self, space: FeatureSpace) -> tuple[list[float | None], list[float | None]]:
        each = [self.box.get(d, Interval()) for d in space.dims]
        return [i.lo for i in each], [i.hi for i in each]

    def sql(self, names: dict[str, str] | None = None) -> str:
        """The conjunction as SQL text. names: expressions that stand for dimensions."""
        tests = []
        for d, i in self.box.items():
            e = (names or {}).get(d, d)
            tests += [f"{e} >= CAST({i.lo!r} AS DOUBLE)"] * (i.lo is not None) + [f"{e} <= CAST({i.hi!r} AS DOUBLE)"] * (i.hi is not None)
        return " AND ".join(tests) or "TRUE"


BATCH = "query_id bigint, template string, lo array<double>, hi array<double>"


def query_batch(spark: SparkSession, queries: list[tuple[int, str, BoxQuery]], space: FeatureSpace) -> DataFrame:
    """Queries as rows (query_id, template, lo, hi); an absent bound is a null element."""
    return spark.createDataFrame([(k, t, *q.bounds(space)) for k, t, q in queries], BATCH)
