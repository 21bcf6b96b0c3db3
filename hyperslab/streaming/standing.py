"""Standing box queries over streams, windowed counts of their hits, and bulk appends to clustered files.

Cases: null and NaN values lie in no bounded interval; an event without a time lies in no window; rows later than the
delay are dropped by windows, sessions and deduplication, and counted in the query's progress
(numRowsDroppedByWatermark); a batch that runs again replaces what it wrote.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encode import epoch_seconds
from ..model import BoxQuery, FeatureSpace
from ..operators.batch import inside
from ..operators.layout import Layout
from ..operators.predicate import box_predicate


def event_stream(spark: SparkSession, path: str, schema: str, **options) -> DataFrame:
    """A file stream with event time at: zone-less times can't carry a watermark, so they become instants (UTC sessions)."""
    return spark.readStream.schema(schema).options(**options).parquet(path).withColumn("at", F.col("ts").cast("timestamp"))


def with_features(events: DataFrame) -> DataFrame:
    return events.withColumn("second", epoch_seconds("ts")).withColumn("user", F.col("user_id").cast("double"))


def standing_query(events: DataFrame, space: FeatureSpace, query: BoxQuery) -> DataFrame:
    """Stateless: the rows of each batch that lie in the box."""
    return events.where(box_predicate(query, space))


def standing_queries(events: DataFrame, space: FeatureSpace, queries: DataFrame) -> DataFrame:
    """Stream rows by the static queries they meet: (query_id, all columns)."""
    return events.join(F.broadcast(queries.select("query_id", "lo", "hi")), inside(space)).drop("lo", "hi")


def windowed_counts(hits: DataFrame, *, size: str = "1 day", slide: str | None = None, delay: str = "10 minutes") -> DataFrame:
    """Hits per tumbling or sliding window of event time; later rows than delay are dropped."""
    frame = F.window("at", size, slide) if slide else F.window("at", size)
    return hits.withWatermark("at", delay).groupBy(frame.alias("w")).agg(F.count("*").alias("n_hits"))


def session_counts(hits: DataFrame, *, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    """Hits per user and session."""
    return hits.withWatermark("at", delay).groupBy("user_id", F.session_window("at", gap).alias("w")).agg(F.count("*").alias("n_hits"))


def deduplicated(events: DataFrame, *, delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("at", delay).dropDuplicatesWithinWatermark(["event_id"])


def running_selectivity(events: DataFrame, space: FeatureSpace, query: BoxQuery) -> DataFrame:
    """Rows so far and hits so far, for update or complete mode."""
    return events.groupBy().agg(F.count("*").alias("n"), F.count(F.when(box_predicate(query, space), 1)).alias("n_hits"))


def append_batches(stream: DataFrame, path: str, checkpoint: str):
    """Writes every batch to a folder of its own, named by the batch: a batch that is run again replaces itself."""

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint)


def append_to_layout(stream: DataFrame, path: str, space: FeatureSpace, checkpoint: str):
    """Every batch becomes files of the layout at path with their directory row; one that is run again replaces itself."""

    def put(batch: DataFrame, number: int) -> None:
        Layout(batch.sparkSession, path, space).append(batch, batch=number)

    return stream.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint)
