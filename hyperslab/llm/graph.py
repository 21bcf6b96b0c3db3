"""Connected components of links between documents, as DataFrame jobs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def components(links: DataFrame) -> DataFrame:
    """(node, component) of every node of links (a, b): the smallest node that can be reached.

    Each round takes the least label of the neighbours and then the label of the label. The first step is a minimum by
    key, summed up before the shuffle; the second looks up the labels in use, each once, so a component of very many
    nodes isn't gathered by its label. A written table ends each round. Labels only fall, so the rounds end.

    Cases: a link of a node with itself is a component of one; repeated links count once; no links give no rows.
    """
    both = common.written(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "links")
    least = both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("least"))
    labels = common.written(least.select("node", F.least("node", "least").alias("component")), "labels")
    while True:
        heard = common.looked_up(both, labels.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node")).agg(F.min("component").alias("heard"))
        nearer = common.written(labels.join(heard, "node").select("node", F.col("component").alias("before"), F.least("component", "heard").alias("component")), "labels")
        used = nearer.select("component").distinct()
        onward = common.written(used.join(nearer.select(F.col("node").alias("component"), F.col("component").alias("onward")), "component").where("onward < component"), "labels")
        if onward.isEmpty() and nearer.where("component != before").isEmpty():
            return nearer.select("node", "component")
        labels = common.written(common.looked_up(nearer, onward, "component", "left").select("node", F.coalesce("onward", "component").alias("component")), "labels")
