"""Mixing sources to target weights along a time-varying curriculum (operator 5).

Targets: sources, ordered by code point with null last, weigh 3, 1, 2, repeating; together
they ask for a share of all words. A target stops at a cap in epochs of its source and the
excess goes to the others by weight (water filling, one pass over the sources sorted by
cap per weight). Positions: each source has a weight schedule over training time; its
integral, scaled to the target, is the source's cumulative demand of words. Documents
stand in a pseudo-random order inside their source; the demand is inverted at each
document's cumulative words, which gives its training position in [0, 1), and the mix is
range-sorted by position.

A hot source never meets in one task: cumulative words are found in two levels, a sum a
bucket of documents and a running sum inside each bucket; the number of buckets follows
the source's size.

Defined results: null text has size 0; a null source is a source, the last; documents of
size 0 are never taken; rows that repeat all columns are separate documents; empty tables
give empty results. Order is by MD5 of the id, then id, then size, so reruns agree.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import packed, words

#: Weights of the sources in order, repeating.
WEIGHTS = (3, 1, 2)
#: Words the mix takes, as a share of all words, and the most epochs of one source.
SHARE, MAX_EPOCHS = 1.5, 2
#: Documents in one bucket of the running sum.
BUCKET_ROWS = 4_000
#: A schedule's weight at the start of training relative to its end: by place in WEIGHTS.
TILT = (0.5, 1.0, 2.0)


def _buckets(n: Column) -> Column:
    return F.ceil(n / F.lit(BUCKET_ROWS)).cast("long")


def source_targets(sized: DataFrame, share: float = SHARE, weights: tuple[int, ...] = WEIGHTS, max_epochs: int = MAX_EPOCHS) -> DataFrame:
    """One row per source of rows (source, size): nth (its number), source_size, n_docs, weight, tilt, target."""
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    per = per.withColumn("nth", F.row_number().over(order))
    place = (F.col("nth") - 1) % len(weights)
    pick = lambda xs: F.element_at(F.array(*map(F.lit, xs)), F.col("place") + 1)
    per = per.withColumn("place", place).withColumn("weight", pick(weights)).withColumn("tilt", pick([TILT[i % len(TILT)] for i in range(len(weights))]))
    everything = Window.partitionBy(F.lit(0))
    fill = Window.orderBy((F.col("source_size") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    zero = F.lit(0).cast("long")
    left = F.lit(float(share)) * F.sum("source_size").over(everything) - F.lit(max_epochs) * F.coalesce(F.sum("source_size").over(before), zero)
    level = left / (F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), zero))
    per = per.withColumn("level", level)
    # The water level is that of the first source, by cap per weight, that stays under its cap.
    under = F.col("weight") * F.col("level") <= F.lit(max_epochs) * F.col("source_size")
    per = per.withColumn("level", F.first(F.when(under, F.col("level")), ignorenulls=True).over(fill.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    cap = (F.lit(max_epochs) * F.col("source_size")).cast("double")
    target = F.least(cap, F.coalesce(F.col("weight") * F.col("level"), cap))
    return per.select("source", "nth", "source_size", "n_docs", "weight", "tilt", target.alias("target"))


def invert_demand(share_of_target: Column, tilt: Column) -> Column:
    """Training time at which a source whose weight moves linearly from tilt to 1 has met that share of its demand."""
    # The integral of tilt + (1 - tilt) t, divided by its value at 1, equals the share.
    a, c = (F.lit(1.0) - tilt) / 2, share_of_target * (tilt + 1) / 2
    return 2 * c / (tilt + F.sqrt(F.greatest(tilt * tilt + 4 * a * c, F.lit(0.0))))


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", share: float = SHARE, weights: tuple[int, ...] = WEIGHTS, max_epochs: int = MAX_EPOCHS, carry: bool = False) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, taken and ``positions``.

    ``taken`` counts the words the mix takes of the document over all epochs; the last
    epoch may end inside a document. ``positions`` has the training time of each copy.
    With ``carry`` the original columns come along in ``row``, the text packed: it is shuffled
    for the running sums and, by those who sort the mix, once more a copy.
    """
    row = [packed(F.col(c)).alias(c) if c == text_col else F.col(c) for c in docs.columns]
    d = docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), F.size(words(F.col(text_col))).cast("long").alias("size"), *([F.struct(*row).alias("row")] if carry else []))
    targets = source_targets(d.select("source", "size"), share, weights, max_epochs)
    key = F.md5(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    number = F.conv(F.substring(key, 1, 8), 16, 10).cast("long")
    keyed = d.join(targets.withColumnRenamed("source", "of"), F.col("source").eqNullSafe(F.col("of"))).drop("of").withColumn("key", key)
    # Buckets split the range of the key, so that their order is the key's.
    keyed = keyed.withColumn("bucket", F.shiftright(number * _buckets(F.col("n_docs")), 32))
    sums = keyed.groupBy("nth", "bucket").agg(F.sum("size").alias("in_bucket"))
    before = Window.partitionBy("nth").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.select("nth", "bucket", F.coalesce(F.sum("in_bucket").over(before), F.lit(0)).alias("start"))
    inside = Window.partitionBy("nth", "bucket").orderBy("key", F.col("doc_id").asc_nulls_last(), "size").rowsBetween(Window.unboundedPreceding, -1)
    run = keyed.withColumn("c", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    # The window's keys, which are never null: its rows, whole texts with carry, stay where they are.
    run = run.join(starts, ["nth", "bucket"]).withColumn("c", F.col("c") + F.col("start"))
    goal = F.floor(F.col("target") + 0.5)
    taken, positions = F.lit(0).cast("long"), []
    for epoch in range(max_epochs):
        offset = F.col("source_size") * epoch
        part = F.greatest(F.lit(0).cast("long"), F.least(F.col("c") + F.col("size"), goal - offset) - F.col("c"))
        taken = taken + part
        share_met = (F.col("c") + offset) / F.greatest(goal, F.lit(1))
        positions.append(F.when(part > 0, F.struct(invert_demand(share_met, F.col("tilt")).alias("position"), F.lit(epoch).alias("epoch"), part.alias("n_words"))))
    out = run.select("doc_id", "source", "size", "source_size", "target", taken.alias("taken"), F.array_compact(F.array(*positions)).alias("positions"), *(["row"] if carry else []))
    return out


def curriculum(mixed: DataFrame) -> DataFrame:
    """The training order: one row per copy taken, range-sorted by position."""
    rows = mixed.select("*", F.inline("positions")).drop("positions")
    return rows.orderBy("position", "doc_id", "epoch")
