"""From table columns to numbers, and dense row ids."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..shared import written


def epoch_days(c: Column | str) -> Column:
    return F.datediff(F.to_date(c), F.lit("1970-01-01").cast("date")).cast("double")


def epoch_seconds(c: Column | str) -> Column:
    return F.unix_micros(F.col(c).cast("timestamp") if isinstance(c, str) else c.cast("timestamp")) / F.lit(1e6)


#: Values of a dictionary that may be sent to every task.
SENT = 50_000


def dictionary_codes(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    """Adds <column>_code: the rank of the value among the column's distinct ones, from 1; null stays null.

    The ranks of the distinct values are made in one task: for columns of up to some million different values (names,
    codes); hash_code needs no dictionary. Up to SENT values are sent to every task, so rows stay where they lie; with
    more the join is left to Spark to choose.
    """
    for c in columns:
        ranked = df.select(F.col(c).alias("_value")).where("_value is not null").distinct().select("_value", F.dense_rank().over(Window.orderBy("_value")).cast("double").alias(f"{c}_code"))
        few = ranked.limit(SENT + 1).count() <= SENT
        df = df.join(F.broadcast(ranked) if few else ranked, F.col(c) == F.col("_value"), "left").drop("_value")
    return df


def hash_code(c: Column, values: int = 1 << 24) -> Column:
    """A number below values from a hash: the paper's way with strings; two strings may share one."""
    return F.when(c.isNotNull(), F.pmod(F.xxhash64(c), F.lit(values)).cast("double"))


def hash_collisions(df: DataFrame, column: str, values: int = 1 << 24) -> DataFrame:
    """n_values, n_codes: how many distinct values share codes."""
    d = df.select(F.col(column).alias("v")).where("v is not null").distinct()
    return d.agg(F.count("*").alias("n_values"), F.countDistinct(hash_code(F.col("v"), values)).alias("n_codes"))


def with_row_id(df: DataFrame, key: Sequence[str], *, name: str = "row_id") -> DataFrame:
    """Adds name, 1 to n in the order of key, nulls first; rows of an equal key come in any order. A written table.

    Rows are dealt by ranges of the key, sorted within and written with their partition and their place in it; the
    sums of the partitions before come by a join that has a row per partition. One shuffle, no task sees all rows.
    """
    spark, place, part = df.sparkSession, "_place", "_part"
    while {place, part} & {c.lower() for c in df.columns}:
        place, part = f"_{place}", f"_{part}"
    keys = [F.col(f"`{c}`") for c in key]
    marked = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn(place, F.monotonically_increasing_id())
    dealt = written(marked, "row-ids")
    low = F.lit((1 << 33) - 1)
    sums = dealt.groupBy(F.shiftright(place, 33).cast("int").alias("part")).agg(F.count("*").alias("n")).orderBy("part").collect()
    before, total = [], 0
    for r in sums:  # a row per partition
        before.append((r["part"], total))
        total += r["n"]
    starts = spark.createDataFrame(before, f"`{part}` int, `{name}` long")
    numbered = dealt.withColumn(part, F.shiftright(place, 33).cast("int")).join(F.broadcast(starts), part)
    return numbered.withColumn(name, F.col(f"`{name}`") + F.col(place).bitwiseAND(low) + 1).select(*(F.col(f"`{c}`") for c in df.columns), F.col(f"`{name}`"))
