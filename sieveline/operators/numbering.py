"""Places of rows inside ordered groups, without a hot group meeting in one task."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..store import stored


def numbered(df: DataFrame, keys: list[str], order_by: list[str], name: str = "__n") -> DataFrame:
    """Add ``name``: the place of each row in its group by order, from 0.

    Two levels: ranges of (keys, order) are sorted on their own, and a running sum over the
    few ranges of a group says where each one starts. The rows are written once in between,
    with their places in their ranges, so that both levels see the same ranges and no row is
    sorted twice. Rows that tie in the order are numbered in any order.
    """
    ranges = df.repartitionByRange(*keys, *order_by).sortWithinPartitions(*keys, *order_by)
    # The number of the range in the upper bits, the place in it in the lower 33.
    rows = stored(ranges.withColumn("__at", F.monotonically_increasing_id()), "numbered").withColumn("__range", F.shiftright("__at", 33))
    before = Window.partitionBy(*keys).orderBy("__range").rowsBetween(Window.unboundedPreceding, -1)
    sums = rows.groupBy(*keys, "__range").agg(F.count(F.lit(1)).alias("__c"), F.min("__at").alias("__first"))
    starts = sums.select(*[F.col(k).alias(f"__k{i}") for i, k in enumerate(keys)], F.col("__range").alias("__r"), (F.coalesce(F.sum("__c").over(before), F.lit(0)) - F.col("__first")).alias("__start"))
    starts = stored(starts, "starts")
    same = F.col("__range") == F.col("__r")
    for i, k in enumerate(keys):
        same = same & F.col(k).eqNullSafe(F.col(f"__k{i}"))
    out = rows.join(starts, same)
    return out.withColumn(name, F.col("__at") + F.col("__start")).drop("__at", "__start", "__range", "__r", *[f"__k{i}" for i in range(len(keys))])


def largest_group(df: DataFrame, keys: list[str]) -> int:
    """Rows of the largest group: one map-side combined count."""
    return df.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
