"""Connected components by alternating stars, without collecting links anywhere."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..store import cut


def components(edges: DataFrame) -> DataFrame:
    """(node, label) for every node of links (x, y); the label is the component's smallest node.

    Each round points larger neighbours, then smaller ones, at the smallest neighbour. A
    hub's links are never gathered: its minimum is a map-side combined aggregate that is
    joined back. Ends when the set of links no longer changes. Self links are ignored.
    """
    links = cut(edges.select(F.greatest("x", "y").alias("u"), F.least("x", "y").alias("v")).filter("u != v").distinct())
    before = None
    while True:
        both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u != v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u")
        small = small.filter("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        links = cut(small.distinct())
        now = links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == before:
            break
        before = now
    labels = links.select(F.col("u").alias("node"), F.col("v").alias("label"))
    return labels.unionByName(links.select(F.col("v").alias("node"), F.col("v").alias("label")).distinct())
