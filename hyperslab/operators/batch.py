"""Many box queries in one job.

Answers don't depend on the number of queries: the ways below differ in cost only.

Cases: an absent bound is a null element; a null or NaN value lies in no bounded interval and in every free one; a
NaN bound or lo > hi makes the query empty; equal rows are hits of their own; a query without bounds meets every
row; an empty table or batch gives an empty result; dimensions may have any name, also those of helper columns.
"""

from __future__ import annotations

from functools import reduce
from operator import and_

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import BoxQuery, FeatureSpace, Interval
from . import flat
from .predicate import box_predicate

#: Bytes of query rows that may go to every task. A batch beyond it is joined by bins.
BROADCAST_BYTES = 16 << 20
#: Rows of one bin that one task compares with the queries of the bin; a bin of more is salted.
BIN_ROWS = 2_000_000
#: Queries counted in one pass over the rows.
CHUNK = 50


def _quoted(name: str) -> Column:
    return F.col(f"`{name}`")


def inside(space: FeatureSpace, lo: str = "lo", hi: str = "hi") -> Column:
    """Row within the query of the same row (arrays lo, hi); an absent bound is null."""
    tests = []
    for j, d in enumerate(space.dims):
        a, b, x = F.col(lo)[j], F.col(hi)[j], _quoted(d)
        above = (x >= a) & ~F.isnan(x.cast("double")) & ~F.isnan(a)
        tests.append((a.isNull() & b.isNull()) | ((a.isNull() | above) & (b.isNull() | (x <= b) & ~F.isnan(b)) & x.isNotNull()))
    return reduce(and_, tests)


def broadcast_queries(space: FeatureSpace, most: int | None = None) -> int:
    """Query rows that fit most bytes (BROADCAST_BYTES): two arrays of m values, and what a row takes besides."""
    return max(1, (BROADCAST_BYTES if most is None else most) // (2 * 9 * space.m + 96))


def search_batch(df: DataFrame, space: FeatureSpace, queries: DataFrame, *, mode: str = "auto", bins: int = 256, broadcast_bytes: int | None = None) -> DataFrame:
    """(query_id, ids) of all hits. mode: 'theta' (queries go to every task; fails if they don't fit), 'binned', or
    'auto', which counts the queries and takes theta as long as they fit."""
    if mode not in ("auto", "theta", "binned"):
        raise ValueError(mode)
    rows = space.features(df)
    boxes = queries.select("query_id", "lo", "hi")
    if mode != "binned":
        most = broadcast_queries(space, broadcast_bytes)
        few = boxes.limit(most + 1).count() <= most
        if few:
            names = space.free("query_id", "lo", "hi")
            sent = boxes.select(*(F.col(c).alias(n) for c, n in zip(("query_id", "lo", "hi"), names, strict=True)))
            return rows.join(F.broadcast(sent), inside(space, *names[1:])).select(F.col(names[0]).alias("query_id"), *map(_quoted, space.ids))
        if mode == "theta":
            raise ValueError(f"more than {most} queries don't fit a broadcast; take mode 'binned'")
    return _binned(rows, space, boxes, bins)


def _place(c: Column, cuts: list[float]) -> Column:
    """Number of cuts at or below c: among every 16th one, then among those after it. Constant arrays keep the code small."""
    below = lambda some: F.size(F.filter(some, lambda v: v <= c))
    values = lambda some: f"cast(array({', '.join(f'double({repr(v)!r})' for v in some)}) as array<double>)"
    if len(cuts) <= 32:
        return below(F.expr(values(cuts)))
    coarse = below(F.expr(values(cuts[15::16])))
    runs = [cuts[a : a + 15] for a in range(0, len(cuts), 16)]
    runs += [[]] * (len(cuts[15::16]) + 1 - len(runs))
    return coarse * 16 + below(F.get(F.expr(f"array({', '.join(map(values, runs))})"), coarse))


def _binned(rows: DataFrame, space: FeatureSpace, boxes: DataFrame, bins: int) -> DataFrame:
    """Rounds over dimensions. A round takes the queries that bound its dimension, as intervals of bins at the quantiles
    of that dimension, and joins them with the rows by bin; queries that leave it free wait for the next round. Those
    without any bound go to all bins of the last round. Bins of many rows are salted."""
    q_id, lo, hi, at, salt = space.free("query_id", "lo", "hi", "bin", "salt")
    real = lambda d: F.when(~F.isnan(_quoted(d).cast("double")), _quoted(d).cast("double"))
    steps = [k / bins for k in range(1, bins)]
    cut_row = rows.agg(*(F.percentile_approx(real(d), steps, 10 * bins).alias(f"c{j}") for j, d in enumerate(space.dims))).first()
    cuts = [sorted(set(cut_row[f"c{j}"] or [])) for j in range(space.m)]
    sent = boxes.select(F.col("query_id").alias(q_id), F.col("lo").alias(lo), F.col("hi").alias(hi))
    order = _narrowest_first(sent, lo, hi, cuts)
    bounded = [F.expr(f"`{lo}`[{j}] is not null or `{hi}`[{j}] is not null") for j in range(space.m)]
    empty = F.expr(f"exists(arrays_zip(`{lo}`, `{hi}`), b -> coalesce(b.`{lo}` > b.`{hi}` or isnan(b.`{lo}`) or isnan(b.`{hi}`), false))")
    first = F.coalesce(*(F.when(bounded[j], F.lit(k)) for k, j in enumerate(order)), F.lit(space.m))
    marked = sent.where(~empty).withColumn(salt, first)
    used = [r[salt] for r in marked.select(salt).distinct().orderBy(salt).collect()]  # m + 1 values at most
    if used == [space.m]:
        used = [0, space.m]  # no query has a bound
    out = []
    for n, k in enumerate(used):
        if k == space.m:
            break
        last = n + 1 < len(used) and used[n + 1] == space.m  # those without a bound go along
        own = marked.where(F.col(salt).isin([k, space.m] if last else [k])).drop(salt)
        j = order[k]
        out.append(_round(rows, space, own, j, cuts[j], bounded[j], (q_id, lo, hi, at, salt)))
    if not out:
        return rows.select(F.lit(None).cast("long").alias("query_id"), *map(_quoted, space.ids)).where(F.lit(False))
    return reduce(DataFrame.unionAll, out)


def _narrowest_first(queries: DataFrame, lo: str, hi: str, cuts: list[list[float]], some: int = 1000) -> list[int]:
    """Dimensions by the mean share of bins that an interval meets, over some queries: it decides the cost, not the answer."""
    import numpy as np

    picked = queries.select(lo, hi).limit(some).collect()
    width = []
    for j, c in enumerate(cuts):
        ends = [(0 if r[0][j] is None else np.searchsorted(c, r[0][j], side="right"), len(c) if r[1][j] is None else np.searchsorted(c, r[1][j], side="right")) for r in picked]
        width.append(float(np.mean([max(0, b - a + 1) / (len(c) + 1) for a, b in ends])) if ends else 1.0)
    return sorted(range(len(cuts)), key=lambda j: width[j])


def _round(rows: DataFrame, space: FeatureSpace, queries: DataFrame, j: int, cuts: list[float], bounded: Column, names: tuple[str, ...]) -> DataFrame:
    q_id, lo, hi, at, salt = names
    x = _quoted(space.dims[j]).cast("double")
    ordered = x.isNotNull() & ~F.isnan(x)
    placed = rows.withColumn(at, F.when(ordered, _place(x, cuts)).otherwise(F.lit(len(cuts) + 1)))
    loads = {r[at]: r["n"] for r in placed.groupBy(at).agg(F.count("*").alias("n")).collect()}  # a row per bin
    heavy = {b: -(-n // BIN_ROWS) for b, n in loads.items() if n > BIN_ROWS}
    salts = reduce(lambda c, b: c.when(F.col(at) == b, F.lit(heavy[b])), heavy, F.when(F.lit(False), F.lit(1))).otherwise(F.lit(1))
    first = F.when(F.col(lo)[j].isNotNull(), _place(F.col(lo)[j], cuts)).otherwise(F.lit(0))
    last = F.when(F.col(hi)[j].isNotNull(), _place(F.col(hi)[j], cuts)).otherwise(F.lit(len(cuts)))
    # the place after the bins is that of values without an order; only queries that leave the dimension free go there
    spread = queries.withColumn(at, F.explode(F.sequence(first, F.when(bounded, last).otherwise(F.lit(len(cuts) + 1)))))
    spread = spread.withColumn(salt, F.explode(F.sequence(F.lit(0), salts - 1)))
    dealt = placed.withColumn(salt, F.pmod(F.xxhash64(*map(_quoted, (*space.ids, *space.dims))), salts).cast("int"))
    return dealt.join(spread, [at, salt]).where(inside(space, lo, hi)).select(F.col(q_id).alias("query_id"), *map(_quoted, space.ids))


def shared_counts(df: DataFrame, space: FeatureSpace, queries: list[tuple[int, str, BoxQuery]], *, chunk: int = CHUNK) -> DataFrame:
    """(query_id, n_hits) of every query, 0 included: conditional sums, chunk queries in one pass over the rows.

    Bounds are literals in the compiled code and a query tests the dimensions it bounds only. The plan grows with the
    queries, so they come from the driver; df is read once per chunk: give a stored or cached table.
    """
    rows, out = space.features(df), []
    for a in range(0, len(queries), chunk):
        some = queries[a : a + chunk]
        row = rows.agg(*(F.count(F.when(box_predicate(q, space), 1)).alias(f"q{k}") for k, (_, _, q) in enumerate(some)))
        each = F.array(*(F.struct(F.lit(i).cast("long").alias("query_id"), F.col(f"q{k}").alias("n_hits")) for k, (i, _, _) in enumerate(some)))
        out.append(row.select(F.explode(each).alias("s")).select("s.query_id", "s.n_hits"))
    if not out:
        return rows.select(F.lit(0).cast("long").alias("query_id"), F.lit(0).cast("long").alias("n_hits")).where(F.lit(False))
    return reduce(DataFrame.unionAll, out)


#: Bytes of values that are compared with all queries at once: rows are gathered to blocks of columns of that size.
BLOCK_BYTES = 4 << 20


def scan_counts(df: DataFrame, space: FeatureSpace, queries: list[tuple[int, str, BoxQuery]]) -> DataFrame:
    """(query_id, n_hits) of the queries with a hit: a column scan for all queries in one pass over the rows where they lie.

    Nothing is dealt out, written or kept: a task holds one block of rows and a counter per query.
    """
    bounds = [(i, *(np.array([np.nan if b is None else b for b in side], float) for side in q.bounds(space))) for i, _, q in queries if not q.is_empty]
    most = max(1, BLOCK_BYTES // (8 * max(1, space.m)))

    def run(batches):
        found, held = np.zeros(len(bounds), np.int64), []

        def counted() -> None:
            block = {"columns": np.stack([np.concatenate([b.column(j).to_numpy(zero_copy_only=False) for b in held]) for j in range(space.m)])}
            for k, (_, lo, hi) in enumerate(bounds):
                found[k] += len(flat.search_columns(block, lo, hi)[0])
            held.clear()

        for batch in batches:
            for a in range(0, batch.num_rows, most):
                held.append(batch.slice(a, most))
                if sum(b.num_rows for b in held) >= most:
                    counted()
        if held:
            counted()
        some = np.flatnonzero(found)
        yield pa.RecordBatch.from_arrays([pa.array([bounds[k][0] for k in some], pa.int64()), pa.array(found[some])], names=["query_id", "n_hits"])

    values = space.features(df).select(*(_quoted(d).cast("double").alias(f"v{j}") for j, d in enumerate(space.dims)))
    return values.mapInArrow(run, "query_id long, n_hits long").groupBy("query_id").agg(F.sum("n_hits").alias("n_hits"))


def taken(queries: DataFrame, space: FeatureSpace) -> list[tuple[int, str, BoxQuery]]:
    """Query rows (query_id, template, lo, hi) on the driver, as many as may be broadcast; more fail."""
    most = broadcast_queries(space)
    rows = queries.select("query_id", "template", "lo", "hi").limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"more than {most} queries: take search_batch")
    return [(r["query_id"], r["template"], BoxQuery({d: Interval(a, b) for d, a, b in zip(space.dims, r["lo"], r["hi"], strict=True) if (a, b) != (None, None)})) for r in rows]


def counts(hits: DataFrame) -> DataFrame:
    """(query_id, n_hits)."""
    return hits.groupBy("query_id").agg(F.count("*").alias("n_hits"))

