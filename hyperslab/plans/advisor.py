"""Which access path to take for a query, from estimates."""

from __future__ import annotations

import math
from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.measures import dim_selectivity
from ..model import BoxQuery, FeatureSpace
from ..operators.predicate import box_predicate

#: Break-even selectivity found on modern machines, the rule before it, the rows below which a scan wins.
BREAK_EVEN, OLD_RULE, SMALL = 0.01, 0.2, 100_000


@dataclass(frozen=True)
class Choice:
    path: str
    reason: str


def choose_path(selectivity: float, n: int, m: int, q: int, *, threshold: float = BREAK_EVEN, high_m: int | None = None) -> Choice:
    """row_scan, column_scan, kd_tree or va_file. high_m: dimensions above which the cells are taken (off by default)."""
    scan = Choice("column_scan", f"{q} of {m} dimensions are queried") if q <= m / 2 else Choice("row_scan", f"{q} of {m} dimensions are queried")
    if n <= SMALL:
        return Choice(scan.path, f"{n} rows are scanned faster than looked up; {scan.reason}")
    if selectivity > threshold:
        return Choice(scan.path, f"selectivity {selectivity:.4g} is above {threshold:g}; {scan.reason}")
    if high_m is not None and m > high_m:
        return Choice("va_file", f"{m} dimensions")
    return Choice("kd_tree", f"selectivity {selectivity:.4g} is at most {threshold:g}")


def choice_column(selectivity: Column, n: Column, m: int, q: Column, threshold: float = BREAK_EVEN, small: int = SMALL) -> Column:
    """The same rules over rows of estimates. small: rows up to which a scan wins on the machines at hand."""
    scan = F.when(q <= m / 2, "column_scan").otherwise("row_scan")
    return F.when((n <= small) | (selectivity > threshold), scan).otherwise("kd_tree")


def io_break_even(ratio: float) -> float:
    """Share of the data above which a scan wins if sequential access is ratio times faster than random access."""
    if ratio <= 0:
        raise ValueError("ratio must be positive")
    return 1 / ratio


def break_even(index: Sequence[tuple[float, float]], scan: Sequence[tuple[float, float]]) -> float | None:
    """Selectivity at which the index's throughput falls below the scan's: log-linear between the measured points."""
    scans = dict(scan)
    points = sorted((s, math.log(t / scans[s])) for s, t in index if s in scans)
    for (s, a), (t, b) in zip(points, points[1:], strict=False):
        if a >= 0 > b:
            return math.exp(math.log(s) + (math.log(t) - math.log(s)) * a / (a - b))
    return None


def estimate_selectivity(df: DataFrame, space: FeatureSpace, query: BoxQuery, method: str = "independent", *, sample_rows: int = 100_000) -> float:
    """'exact', 'independent' (product per dimension), 'histogram' (product from quantiles) or 'sample' (bounded)."""
    if method == "exact":
        return df.agg(F.avg(F.coalesce(box_predicate(query, space), F.lit(False)).cast("double"))).first()[0] or 0.0
    if method == "independent":
        return math.prod(r["selectivity"] or 0.0 for r in dim_selectivity(df, space, query).collect())
    if method == "sample":
        n = df.count()
        return df.sample(min(1.0, sample_rows / max(n, 1)), seed=1).agg(F.avg(F.coalesce(box_predicate(query, space), F.lit(False)).cast("double"))).first()[0] or 0.0
    if method == "histogram":
        steps = [k / 100 for k in range(101)]
        dims = query.specified(space)
        row = df.agg(*(F.percentile_approx(F.col(d).cast("double"), steps, 10_000).alias(d) for d, _ in dims)).first()
        share = lambda cuts, i: sum((i.lo is None or c >= i.lo) and (i.hi is None or c <= i.hi) for c in cuts) / len(cuts) if cuts else 0.0
        return math.prod(share(row[d], i) for d, i in dims)
    raise ValueError(method)
