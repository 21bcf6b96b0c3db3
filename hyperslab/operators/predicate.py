"""Box predicates as Catalyst expressions."""

from __future__ import annotations

import math
from functools import reduce
from operator import add, and_

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..model import BoxQuery, FeatureSpace, Interval


def conjuncts(dim: str, interval: Interval, floating: bool = True, foreseen: bool = True) -> list[Column]:
    """Tests of one dimension. floating: also keep NaN out, which Spark orders above all numbers. foreseen: an interval
    with lo > hi is false without a look at the rows; otherwise both bounds are compared. NaN bounds are always foreseen."""
    c = F.col(dim)
    if interval.is_empty and (foreseen or any(b is not None and math.isnan(b) for b in (interval.lo, interval.hi))):
        return [F.lit(False)]
    if interval.is_point:
        return [c == F.lit(interval.lo)]
    tests = [c >= F.lit(interval.lo)] if interval.lo is not None else []
    if interval.hi is not None:
        tests.append(c <= F.lit(interval.hi))
    elif floating and tests:
        tests.append(~F.isnan(c.cast("double")))
    return tests


def box_predicate(query: BoxQuery, space: FeatureSpace, *, full_width: bool = False, order: list[str] | None = None, foreseen: bool = True) -> Column:
    """The conjunction, dimension by dimension; a row leaves at its first failing test.

    full_width also compares the unspecified dimensions with an always-true interval. order: dimensions to test first.
    foreseen: as `conjuncts` has it.
    """
    named = dict(query.specified(space))
    dims = [d for d in order or [] if d in named] + [d for d in space.dims if d in named and d not in (order or [])]
    tests = [t for d in dims for t in conjuncts(d, named[d], foreseen=foreseen)]
    if full_width:
        for d in (d for d in space.dims if d not in named):
            c = F.col(d)
            tests.append(c.isNull() | F.isnan(c.cast("double")) | ((c >= F.lit(float("-inf"))) & (c <= F.lit(float("inf")))))
    return reduce(and_, tests, F.lit(True)) if tests else F.lit(True)


def chunked_predicate(query: BoxQuery, space: FeatureSpace, k: int = 8, *, prefilter: bool = False) -> Column:
    """k dimensions at a time: the numbers of passed tests are summed and compared; the tail goes one by one.

    With fewer than k dimensions it is the plain predicate. The chunks lose pushdown; prefilter puts the plain
    conjuncts in front to keep it.
    """
    dims = query.specified(space)
    chunks = [dims[a : a + k] for a in range(0, len(dims) // k * k, k)]
    out = [reduce(add, [F.coalesce(reduce(and_, conjuncts(d, i)), F.lit(False)).cast("int") for d, i in chunk]) == F.lit(k) for chunk in chunks]
    out += [t for d, i in dims[len(chunks) * k :] for t in conjuncts(d, i)]
    if prefilter:
        out = [t for d, i in dims for t in conjuncts(d, i)] + out
    return reduce(and_, out) if out else F.lit(True)


def selectivity_order(selectivities: dict[str, float]) -> list[str]:
    """Dimensions from the most to the least selective."""
    return sorted(selectivities, key=lambda d: (selectivities[d], d))
