"""SQL functions: a box test over arrays, and query rows from pairs of row numbers."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def box_match(point: Column, lo: Column, hi: Column) -> Column:
    """Whether every coordinate lies within its bounds; a null bound is free, a null or NaN coordinate fails a bound."""
    tests = F.zip_with(F.zip_with(lo, hi, lambda a, b: F.struct(a.alias("a"), b.alias("b"))), point, lambda i, x: (i["a"].isNull() | ((x >= i["a"]) & ~F.isnan(x.cast("double")))) & (i["b"].isNull() | (x <= i["b"])))
    return F.coalesce(F.forall(tests, lambda t: F.coalesce(t, F.lit(False))), F.lit(False))


class PairPicks:
    """Rows (query_id, first, second): which row numbers make the corners of each pair."""

    def eval(self, n: int, count: int, seed: int):
        for k in range(count):
            yield k, ((k + seed) * 7_919 + 13) % n, ((k + seed) * 104_729 + 71) % n


def register(spark: SparkSession) -> None:
    """box_match(point, lo, hi) as a SQL function without Python, and pair_picks(n, count, seed) as a table function."""
    from pyspark.sql.functions import udtf

    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION box_match(point ARRAY<DOUBLE>, lo ARRAY<DOUBLE>, hi ARRAY<DOUBLE>) RETURNS BOOLEAN RETURN "
        "coalesce(forall(zip_with(arrays_zip(lo, hi), point, (i, x) -> coalesce((i.lo IS NULL OR (x >= i.lo AND NOT isnan(x))) AND (i.hi IS NULL OR x <= i.hi), false)), t -> t), false)"
    )
    spark.udtf.register("pair_picks", udtf(PairPicks, returnType="query_id: bigint, first: bigint, second: bigint"))
