"""Query workloads: random pairs as corners, boxes of a target selectivity, and the eight templates with their mix."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.encode import with_row_id
from ..model import BoxQuery, FeatureSpace, Interval, query_batch
from ..shared import written

#: Which rows make pair k, as multiplier and offset modulo the number of rows.
PAIR_A, PAIR_B = (7_919, 13), (104_729, 71)


#: Places up to which they are sent to every task.
SENT = 100_000


def rows_at(rows: DataFrame, space: FeatureSpace, picks: DataFrame, numbered: DataFrame, few: bool) -> DataFrame:
    """The rows of a feature table at the places (0-based, by the ids) that picks has in its column place, with place.

    numbered: the ids with place, as `_numbered` has them. Ids only are sorted and written; values are read of the rows
    that are picked. Of rows with equal ids each is found at one of their places. few: the picks fit every task.
    """
    sent = F.broadcast if few else (lambda d: d)
    part, rank = space.free("place", "rank")
    ids = [f"`{c}`" for c in space.ids]
    same = lambda a, b: reduce(and_, [F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in ids])
    chosen = written(numbered.join(sent(picks.select(F.col("place").alias(part)).distinct()), part), "picked")
    keys = chosen.select(*ids).distinct()
    firsts = numbered.alias("a").join(sent(keys.alias("b")), same("a", "b"), "left_semi").groupBy(*ids).agg(F.min(part).alias(rank))
    ranked = chosen.alias("a").join(sent(firsts.alias("b")), same("a", "b")).select(*(f"a.{c}" for c in ids), f"a.{part}", (F.col(f"a.{part}") - F.col(f"b.{rank}") + 1).alias(rank))
    met = rows.alias("a").join(sent(keys.alias("b")), same("a", "b"), "left_semi")
    met = met.withColumn(rank, F.row_number().over(Window.partitionBy(*ids).orderBy(*(f"`{d}`" for d in space.dims))))
    return met.alias("a").join(sent(ranked.alias("b")), same("a", "b") & (F.col(f"a.{rank}") == F.col(f"b.{rank}"))).select(F.col(f"b.{part}").alias("place"), F.array(*(F.col(f"a.`{d}`") for d in space.dims)).alias("x"))


def _numbered(rows: DataFrame, space: FeatureSpace) -> DataFrame:
    """The ids with their place in their own order, from 0."""
    part = space.free("place")[0]
    return with_row_id(rows.select(*(f"`{c}`" for c in space.ids)), space.ids, name=part).withColumn(part, F.col(part) - 1)


def pair_boxes(df: DataFrame, space: FeatureSpace, count: int, seed: int = 0) -> DataFrame:
    """Query rows whose corners are two stored objects, the least and the greatest value per dimension."""
    rows = space.features(df).where(" AND ".join(f"{d} IS NOT NULL" for d in space.dims))
    numbered = _numbered(rows, space)
    n = numbered.agg(F.count("*").alias("n"))
    picks = df.sparkSession.range(count).crossJoin(F.broadcast(n)).where("n > 0")  # count rows by one row
    each = [picks.select(F.col("id").alias("query_id"), F.lit(name).alias("corner"), F.pmod((F.col("id") + seed) * a + c, "n").alias("place")) for (a, c), name in ((PAIR_A, "one"), (PAIR_B, "two"))]
    places = written(each[0].unionAll(each[1]), "places")
    found = written(rows_at(rows, space, places, numbered, count <= SENT), "corners")
    corners = [places.where(F.col("corner") == name).join(found, "place").select("query_id", F.col("x").alias(name)) for name in ("one", "two")]
    return corners[0].join(corners[1], "query_id").select("query_id", F.lit("pair").alias("template"), F.zip_with("one", "two", lambda a, b: F.least(a, b)).alias("lo"), F.zip_with("one", "two", lambda a, b: F.greatest(a, b)).alias("hi"))


def pair_boxes_sql(table_sql: str, space: FeatureSpace, count: int, seed: int = 0) -> str:
    dims = ", ".join(f"least(a.{d}, b.{d}) AS lo_{d}, greatest(a.{d}, b.{d}) AS hi_{d}" for d in space.dims)
    return f"""WITH t AS ({table_sql}), r AS (SELECT *, row_number() OVER (ORDER BY {", ".join(space.ids)}) - 1 AS place, count(*) OVER () AS n FROM t),
q AS (SELECT k.range AS query_id, {dims} FROM range({count}) AS k JOIN r AS a ON a.place = ((k.range + {seed}) * {PAIR_A[0]} + {PAIR_A[1]}) % a.n JOIN r AS b ON b.place = ((k.range + {seed}) * {PAIR_B[0]} + {PAIR_B[1]}) % b.n)"""


def target_boxes(space: FeatureSpace, selectivity: float, count: int, *, low: float = 0.0, high: float = 1.0) -> list[BoxQuery]:
    """Boxes that a uniform object meets with that probability: side selectivity^(1/m), never sticking out."""
    side = selectivity ** (1 / space.m)
    out = []
    for k in range(count):
        corners = [((k * 2_654_435 + j * 40_503 + 12_345) % 10_007) / 10_007 * (1 - side) for j in range(space.m)]
        out.append(BoxQuery({d: Interval(low + (high - low) * c, low + (high - low) * (c + side)) for d, c in zip(space.dims, corners, strict=True)}))
    return out


_SLACK = 1e-9


def template(name: str, k: int, *, status_codes: Sequence[float] = (1.0, 2.0)) -> BoxQuery:
    """Instance k of t1 .. t7 or t3x over the wide19 space."""
    day = Interval(25.0 * ((37 * k) % 67) + _FIRST_DAY, 25.0 * ((37 * k) % 67) + _FIRST_DAY + 833)
    block, single = Interval(float(k % 18), float(k % 18 + 7)), Interval.point(float(k % 25))
    quantity = lambda width: Interval(1.0 + k % 15, 1.0 + k % 15 + width - 1)
    discount = lambda steps: Interval((k % steps) / 100 - _SLACK, (k % steps) / 100 + 0.04 + _SLACK)
    if name == "t1":
        return BoxQuery({"nation": block, "day": day})
    if name == "t2":
        return BoxQuery({"nation": block, "day": day, "quantity": quantity(35), "price": Interval(5_000.0, 67_000.0), "discount": discount(6)})
    if name == "t3":
        return BoxQuery({"nation": block, "day": day, "quantity": quantity(25)})
    if name == "t3x":
        return BoxQuery({"nation": single, "day": day, "quantity": quantity(35), "price": Interval(5_000.0, 70_000.0), "discount": Interval(0.05 - _SLACK, 0.1 + _SLACK)})
    box = {"nation": single, "day": day, "quantity": quantity(20), "discount": discount(7)}
    more = {"tax": Interval(None, 0.07 + _SLACK), "status": Interval.point(status_codes[k % 2]), "size": Interval(1.0 + k % 25, 1.0 + k % 25 + 24)}
    depth = {"t4": 0, "t5": 1, "t6": 2, "t7": 3}
    if name not in depth:
        raise ValueError(f"{name} is not a template of fixed bounds; t8 comes from narrow_boxes")
    return BoxQuery(box | dict(list(more.items())[: depth[name]]))


#: The day number on which the ship dates begin, and half-widths of the complete-match template. Fixed values.
_FIRST_DAY = 9132.0
HALF = {"day": 30, "quantity": 5, "price": 2000, "discount": 0.02, "tax": 0.02, "size": 5, "customer": 50, "supplier": 5, "part": 50, "line": 1, "supplier_nation": 2}


def narrow_boxes(df: DataFrame, space: FeatureSpace, count: int) -> DataFrame:
    """The complete-match template: a narrow box on all dimensions around each of count rows spread over the key order."""
    rows = space.features(df)
    numbered = _numbered(rows, space)
    n = numbered.agg(F.count("*").alias("n"))
    picks = df.sparkSession.range(count).crossJoin(F.broadcast(n)).where("n > 0")
    chosen = written(picks.select(F.col("id").alias("query_id"), F.floor(F.col("id") * F.col("n") / F.lit(count)).alias("place")), "places")
    bounds = [F.array(*(F.col("x")[j] + sign * (HALF.get(d, 0) + (_SLACK if d in ("discount", "tax") else 0)) for j, d in enumerate(space.dims))) for sign in (-1, 1)]
    return chosen.join(rows_at(rows, space, chosen, numbered, count <= SENT), "place").select("query_id", F.lit("t8").alias("template"), bounds[0].alias("lo"), bounds[1].alias("hi"))


def drawn(count: int, weights: dict[str, int], seed: int = 0) -> list[tuple[int, str]]:
    """Query k and its template, by an arithmetic hash over the weights."""
    pool = [t for t, w in weights.items() for _ in range(w)]
    return [(k, pool[((k + seed) * 7_919 + 31) % 104_729 % len(pool)]) for k in range(count)]


ALL = ("t1", "t2", "t3", "t4", "t5", "t6", "t7", "t8")


def mixed_boxes(df: DataFrame, space: FeatureSpace, count: int, weights: dict[str, int] | None = None, seed: int = 0) -> DataFrame:
    """Query rows of all eight templates in a random order; query k of t8 is the narrow box k of count over df."""
    names = drawn(count, weights or dict.fromkeys(ALL, 1), seed)
    fixed = query_batch(df.sparkSession, [(k, t, template(t, k)) for k, t in names if t != "t8"], space)
    narrow = [(k,) for k, t in names if t == "t8"]
    if not narrow:
        return fixed
    return fixed.unionByName(narrow_boxes(df, space, count).join(F.broadcast(df.sparkSession.createDataFrame(narrow, "query_id bigint")), "query_id", "left_semi"))


def workload_profile(hits: DataFrame, queries: DataFrame, n: DataFrame) -> DataFrame:
    """template, n_queries, mean and deviation of the selectivity (percent) and of the queried dimensions.

    hits: (query_id, n_hits); n: one row with the number of objects, n.
    """
    dims = F.size(F.filter(F.arrays_zip("lo", "hi"), lambda b: b["lo"].isNotNull() | b["hi"].isNotNull())).cast("double")
    each = queries.select("query_id", "template", dims.alias("dims")).join(hits, "query_id", "left").crossJoin(F.broadcast(n)).withColumn("s", 100 * F.coalesce("n_hits", F.lit(0)) / F.col("n"))
    return each.groupBy("template").agg(F.count("*").alias("n_queries"), F.avg("s").alias("mean_selectivity"), F.stddev_pop("s").alias("sd_selectivity"), F.avg("dims").alias("mean_dims"), F.stddev_pop("dims").alias("sd_dims"))


__all__ = ["ALL", "HALF", "drawn", "mixed_boxes", "narrow_boxes", "pair_boxes", "pair_boxes_sql", "target_boxes", "template", "workload_profile"]
