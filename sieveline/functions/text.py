"""Token counts, budgets and deterministic buckets as Catalyst expressions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

GAP = "[...]"


def tokens(text: Column) -> Column:
    """Non-empty pieces between blanks and line ends; empty for null."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), "[ \n]+"), lambda t: t != "")


def token_count(text: Column) -> Column:
    return F.size(tokens(text))


def truncate_middle(text: Column, budget: int) -> Column:
    """At most ``budget`` tokens: both ends stay, the middle gives way to a gap marker."""
    t = tokens(text)
    head, tail = (budget + 1) // 2, budget // 2
    short = F.concat_ws(" ", F.slice(t, 1, head), F.lit(GAP), F.slice(t, F.size(t) - tail + 1, tail))
    return F.when(F.size(t) <= budget, text).otherwise(short)


def bucket(*parts: Column | str) -> Column:
    """A number from 0 to 999 that any engine with MD5 can recompute."""
    joined = F.concat_ws("|", *[p if isinstance(p, Column) else F.lit(p) for p in parts])
    return F.conv(F.substring(F.md5(joined), 1, 8), 16, 10).cast("long") % 1000


def pack_prompt(df: DataFrame, outputs: list[str], referenced: list[str], budget: int, name: str = "prompt") -> DataFrame:
    """Three tiers under one budget: outputs whole, referenced attributes whole, the rest cut in the middle.

    What the first two tiers leave of the budget is shared evenly by the other columns.
    """
    rest = [c for c in df.columns if c not in outputs and c not in referenced]
    full = [F.coalesce(F.col(c).cast("string"), F.lit("")) for c in [*outputs, *referenced]]
    used = sum((token_count(c) for c in full), F.lit(0))
    share = F.greatest(F.lit(0), F.floor((F.lit(budget) - used) / F.lit(max(1, len(rest))))).cast("int")

    def cut(c):
        t = tokens(F.coalesce(F.col(c).cast("string"), F.lit("")))
        head, tail = F.ceil(share / 2).cast("int"), F.floor(share / 2).cast("int")
        return F.when(F.size(t) <= share, F.concat_ws(" ", t)).otherwise(F.concat_ws(" ", F.slice(t, 1, head), F.lit(GAP), F.slice(t, F.size(t) - tail + 1, tail)))

    return df.withColumn(name, F.concat_ws("\n", *full, *map(cut, rest)))


def jaccard(a: Column, b: Column) -> Column:
    """Token Jaccard similarity of two strings; 0 where both are empty."""
    x, y = F.array_distinct(tokens(F.lower(a))), F.array_distinct(tokens(F.lower(b)))
    both = F.size(F.array_intersect(x, y))
    return F.when(F.size(F.array_union(x, y)) == 0, F.lit(0.0)).otherwise(both / F.size(F.array_union(x, y)))


def register_sql(spark) -> None:
    """SQL names that Catalyst inlines: sem_tokens, sem_bucket and sem_jaccard."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sem_tokens(t STRING) RETURNS INT RETURN size(filter(split(coalesce(t, ''), '[ \n]+'), x -> x != ''))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sem_bucket(t STRING) RETURNS BIGINT RETURN cast(conv(substr(md5(t), 1, 8), 16, 10) AS BIGINT) % 1000")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION sem_jaccard(a STRING, b STRING) RETURNS DOUBLE RETURN size(array_intersect(split(lower(a), ' +'), split(lower(b), ' +'))) / size(array_union(split(lower(a), ' +'), split(lower(b), ' +')))")
