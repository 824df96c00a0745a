"""Connected components of a table of links, by spreading the largest label."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import store


def components(links: DataFrame) -> DataFrame:
    """node, component (the largest node id of it) for every node of links(a, b).

    Each round a node takes the largest label among itself and its neighbours, then that label's own label, so chains halve.
    A node with very many links is pre-aggregated before the shuffle, and its join can be split.
    Every round is written to the shared folder: no lineage grows, a lost executor costs one round.
    """
    both = store(links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).filter("a <> b").distinct(), "links")
    labels = store(both.groupBy(F.col("a").alias("node")).agg(F.max("b").alias("m")).select("node", F.greatest("node", "m").alias("label")), "labels")
    while True:
        heard = both.join(labels, both.b == labels.node).groupBy("a").agg(F.max("label").alias("heard"))
        spread = labels.join(heard, labels.node == heard.a, "left").select("node", "label", F.greatest("label", "heard").alias("up"))
        upper = labels.select(F.col("node").alias("up"), F.col("label").alias("over"))
        new = store(spread.join(upper, "up", "left").select("node", F.greatest("up", "over").alias("label"), (F.greatest("up", "over") > F.col("label")).alias("moved")), "labels")
        labels = new.select("node", "label")
        if new.filter("moved").isEmpty():
            return labels.withColumnRenamed("label", "component")
