"""Feature tables in text and column formats, and files of queries."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import FeatureSpace

FORMATS = ("csv", "json", "orc", "parquet")

QUERY_LINES = "query_id bigint, template string, box map<string, struct<lo: double, hi: double>>"


def store(df: DataFrame, path: str, fmt: str) -> None:
    """Write df as csv (with a header), json, orc or parquet; columns of plain types only."""
    if fmt not in FORMATS:
        raise ValueError(fmt)
    writer = df.write.format(fmt)
    (writer.option("header", True) if fmt == "csv" else writer).save(path)


def load(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    """Read such files under a given schema: no pass over the data to infer one. A malformed row fails the job.

    Cases: empty cells of csv and absent fields of json are null; NaN and infinities come back; no files fail. csv has no
    way to tell an empty string from null.
    """
    if fmt not in FORMATS:
        raise ValueError(fmt)
    reader = spark.read.format(fmt).schema(schema)
    if fmt in ("csv", "json"):
        reader = reader.option("mode", "FAILFAST")
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def queries_from(spark: SparkSession, path: str, space: FeatureSpace) -> DataFrame:
    """Queries (query_id, template, lo, hi) from JSON lines {"query_id", "template", "box": {dimension: {"lo", "hi"}}}.

    Cases: an absent dimension or bound is free, as is a null box; a dimension that the space doesn't have fails the
    job; repeated query_ids stay; an empty file has no queries.
    """
    lines = spark.read.schema(QUERY_LINES).option("mode", "FAILFAST").json(path)
    unknown = F.array_except(F.map_keys("box"), F.array(*(F.lit(d) for d in space.dims)))

    def bounds(side: str) -> Column:
        known = F.array(*(F.try_element_at("box", F.lit(d))[side] for d in space.dims))
        return F.when(F.size(unknown) > 0, F.raise_error(F.concat(F.lit("no such dimensions: "), F.array_join(unknown, ", ")))).otherwise(known)

    return lines.select("query_id", "template", bounds("lo").alias("lo"), bounds("hi").alias("hi"))


def queries_to(queries: DataFrame, path: str, space: FeatureSpace) -> None:
    """Write queries (query_id, template, lo, hi) as such JSON lines; free dimensions are left out."""
    boxes = F.map_from_entries(F.filter(F.array(*(F.struct(F.lit(d).alias("key"), F.struct(F.col("lo")[j].alias("lo"), F.col("hi")[j].alias("hi")).alias("value")) for j, d in enumerate(space.dims))), lambda e: e["value"]["lo"].isNotNull() | e["value"]["hi"].isNotNull()))
    queries.select("query_id", "template", boxes.alias("box")).write.json(path)
