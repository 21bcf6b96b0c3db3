"""Synthetic data by arithmetic that any engine can repeat: the same rows for the same arguments."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A prime, and the levels of the lattice that values lie on.
PRIME, LEVELS = 2_147_483_647, 1_000_000


def _steps(j: int, seed: int) -> tuple[int, int]:
    return (1_000_003 * (2 * j + 1) + 7_919 * seed) % 1_000_000_000 + 1, (2_000_003 * (j + 5) + 104_729 * seed) % 1_000_000_000 + 17


def lattice(i: Column, j: int, seed: int = 0) -> Column:
    """A level 0 .. LEVELS - 1 of object i in dimension j: two squarings and two linear steps modulo a prime."""
    a, c = _steps(j, seed)
    x = (i * F.lit(a).cast("long") + F.lit(c).cast("long")) % PRIME
    x = (x * x) % PRIME
    x = (x * 16_807 + 12_345) % PRIME
    return (x * x) % PRIME % LEVELS


def lattice_sql(i: str, j: int, seed: int = 0) -> str:
    a, c = _steps(j, seed)
    x = f"(({i} * {a}::BIGINT + {c}) % {PRIME})"
    y = f"((({x} * {x}) % {PRIME} * 16807 + 12345) % {PRIME})"
    return f"(({y} * {y}) % {PRIME} % {LEVELS})"


#: Rows of a partition of generated data.
SPLIT = 250_000


def _ids(spark: SparkSession, n: int) -> DataFrame:
    return spark.range(0, n, 1, max(spark.sparkContext.defaultParallelism, -(-n // SPLIT)))


def uniform(spark: SparkSession, n: int, m: int, seed: int = 0) -> DataFrame:
    """id and d0 .. d{m-1}, uniform in [0, 1)."""
    return _ids(spark, n).select("id", *((lattice(F.col("id"), j, seed) / F.lit(float(LEVELS))).alias(f"d{j}") for j in range(m)))


def _ids_sql(n: int | str) -> str:
    """Ids 0 to n - 1; n may be the name of a table, for as many as it has rows."""
    return f"SELECT range AS id FROM range({n})" if isinstance(n, int) else f"SELECT row_number() OVER () - 1 AS id FROM {n}"


def uniform_sql(n: int | str, m: int, seed: int = 0) -> str:
    return f"SELECT id, {', '.join(f'CAST({lattice_sql('id', j, seed)} AS DOUBLE) / {LEVELS}.0::DOUBLE AS d{j}' for j in range(m))} FROM ({_ids_sql(n)})"


def _box(k: int, j: int, c: int) -> tuple[float, float]:
    """Corner and side of cluster k of c in dimension j. Clusters follow one another in every dimension, so that a
    pair from two of them spans those between, as the reported selectivities require."""
    side = round((0.5 + 0.3 * ((37 * k + 11 * j) % 10) / 10) / c, 6)
    return round(k / c + (1 / c - side) * ((53 * k + 29 * j + 7) % 97) / 97, 6), side


def clustered(spark: SparkSession, n: int, m: int, c: int, seed: int = 0) -> DataFrame:
    """id, cluster (id mod c) and m dimensions uniform within the cluster's box."""
    cluster = F.col("id") % c

    def value(j: int) -> Column:
        corner, side = (F.element_at(F.array(*(F.lit(_box(k, j, c)[which]) for k in range(c))), (cluster + 1).cast("int")) for which in (0, 1))
        return corner + side * (lattice(F.col("id"), j, seed) / F.lit(float(LEVELS)))

    return _ids(spark, n).select("id", cluster.alias("cluster"), *(value(j).alias(f"d{j}") for j in range(m)))


def clustered_sql(n: int | str, m: int, c: int, seed: int = 0) -> str:
    def value(j: int) -> str:
        corner, side = (f"[{', '.join(f'{_box(k, j, c)[which]!r}::DOUBLE' for k in range(c))}][CAST(id % {c} + 1 AS INT)]" for which in (0, 1))
        return f"{corner} + {side} * (CAST({lattice_sql('id', j, seed)} AS DOUBLE) / {LEVELS}.0::DOUBLE)"

    return f"SELECT id, id % {c} AS cluster, {', '.join(f'{value(j)} AS d{j}' for j in range(m))} FROM ({_ids_sql(n)})"


def power_like(spark: SparkSession, n: int, seed: int = 0) -> DataFrame:
    """Sensor-like data: time, and two correlated measures on coarse levels, a slow wave with noise."""
    i = F.col("id").cast("double")
    wave = F.sin(i / F.lit(n / 12.0)) + 0.4 * F.sin(i / F.lit(n / 97.0))
    noise = [lattice(F.col("id"), j, seed) / F.lit(float(LEVELS)) - 0.5 for j in (0, 1)]
    return _ids(spark, n).select("id", i.alias("d0"), F.round(4000 + 1500 * wave + 900 * noise[0], 0).alias("d1"), F.round(4200 + 1400 * wave + 1000 * noise[1], 0).alias("d2"))
