"""What the experiments measure: selectivity, comparisons, balance, space, throughput and how they compare."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import BoxQuery, FeatureSpace
from ..operators.predicate import box_predicate, conjuncts


def selectivity(df: DataFrame, space: FeatureSpace, query: BoxQuery) -> DataFrame:
    """n, n_hits, selectivity."""
    return df.agg(F.count("*").alias("n"), F.count(F.when(box_predicate(query, space), 1)).alias("n_hits")).withColumn("selectivity", F.col("n_hits") / F.col("n"))


def dim_selectivity(df: DataFrame, space: FeatureSpace, query: BoxQuery) -> DataFrame:
    """(dim, selectivity) of each queried dimension, in one pass."""
    dims = query.specified(space)
    row = df.agg(*(F.avg(F.coalesce(reduce(lambda a, b: a & b, conjuncts(d, i)), F.lit(False)).cast("double")).alias(d) for d, i in dims))
    return row.select(F.explode(F.array(*(F.struct(F.lit(d).alias("dim"), F.col(d).alias("selectivity")) for d, _ in dims))).alias("s")).select("s.*")


def independence_error(df: DataFrame, space: FeatureSpace, query: BoxQuery) -> DataFrame:
    """true selectivity, the product of those per dimension, and their ratio."""
    dims = query.specified(space)
    row = df.agg(F.avg(F.coalesce(box_predicate(query, space), F.lit(False)).cast("double")).alias("true_selectivity"), *(F.avg(F.coalesce(reduce(lambda a, b: a & b, conjuncts(d, i)), F.lit(False)).cast("double")).alias(d) for d, i in dims))
    product = F.aggregate(F.array(*(F.col(d) for d, _ in dims)), F.lit(1.0), lambda acc, x: acc * x)
    return row.select("true_selectivity", product.alias("product")).withColumn("ratio", F.when(F.col("true_selectivity") > 0, F.col("product") / F.col("true_selectivity")))


def distinct_profile(df: DataFrame, space: FeatureSpace, approximate: bool = False) -> DataFrame:
    """(dim, n_distinct)."""
    f = F.approx_count_distinct if approximate else F.countDistinct
    row = df.agg(*(f(d).alias(d) for d in space.dims))
    return row.select(F.explode(F.array(*(F.struct(F.lit(d).alias("dim"), F.col(d).alias("n_distinct")) for d in space.dims))).alias("s")).select("s.*")


def raw_size_mib(n: int, m: int, value_bytes: int = 4) -> float:
    return n * m * value_bytes / 2**20


def dims_compared(df: DataFrame, space: FeatureSpace, query: BoxQuery, k: int = 1) -> DataFrame:
    """n and the dimensions compared over all rows until the first mismatch, k at a time."""
    dims = query.specified(space)
    step = k if len(dims) >= k else 1
    groups = [dims[a : a + step] for a in range(0, len(dims) // step * step, step)] + [[x] for x in dims[len(dims) // step * step :]]
    done, case = 0, None
    for g in groups:
        done += len(g)
        fails = ~F.coalesce(reduce(lambda a, b: a & b, [t for d, i in g for t in conjuncts(d, i)]), F.lit(False))
        case = F.when(fails, F.lit(done)) if case is None else case.when(fails, F.lit(done))
    each = F.lit(0) if case is None else case.otherwise(F.lit(done))
    return df.agg(F.count("*").alias("n"), F.sum(each).alias("compared"))


def balance(df: DataFrame, part: Column) -> DataFrame:
    """parts, least and greatest number of rows, and the greatest over the mean."""
    return df.groupBy(part.alias("part")).agg(F.count("*").alias("n")).agg(F.count("*").alias("parts"), F.min("n").alias("least"), F.max("n").alias("most"), (F.max("n") / F.avg("n")).alias("imbalance"))


def bitmap_bytes(n: int, q: int) -> int:
    """Bytes of the intermediate bitmaps of a column scan when every bucket has a hit."""
    return math.ceil(n / 32_768) * 4_096 * q


def assert_same(a: DataFrame, b: DataFrame) -> None:
    """Fails unless two answers are equal as multisets."""
    for one, two in ((a, b), (b, a)):
        if not one.exceptAll(two).isEmpty():
            raise AssertionError("the answers differ")


def timed(run: Callable[[], DataFrame]) -> float:
    """Seconds to compute all rows, written nowhere."""
    t = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def throughput(search: Callable[[BoxQuery], DataFrame], queries: Sequence[BoxQuery], warmup: int = 1) -> dict[str, float]:
    """Queries per second, one job each, after warm-up runs; with median, 95th percentile and deviation of the latency."""
    for q in queries[:warmup]:
        timed(lambda q=q: search(q))
    each = sorted(timed(lambda q=q: search(q)) for q in queries)
    mean = sum(each) / len(each)
    return {"queries_per_second": len(each) / sum(each), "median": each[len(each) // 2], "p95": each[min(len(each) - 1, int(0.95 * len(each)))], "sd": (sum((x - mean) ** 2 for x in each) / len(each)) ** 0.5}


def speedup(base: float, other: float) -> float:
    """How many times faster other is, from seconds."""
    return base / other


def saving(scan: float, index: float) -> float:
    """Seconds that the index saves per query."""
    return scan - index
