"""Unnest, split, gather and header lineage: no model behind them."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import tokens


def unnest(df: DataFrame, col: str, keep_empty: bool = False, recursive: int = 0) -> DataFrame:
    """One row per element; rows without one go unless ``keep_empty``. Nested arrays open ``recursive`` times more."""
    for _ in range(recursive + 1):
        df = df.withColumn(col, (F.explode_outer if keep_empty else F.explode)(col))
    return df


def unnest_fields(df: DataFrame, col: str, fields: list[str] | None = None) -> DataFrame:
    """Lift fields of a struct (all, or those named) into the row."""
    names = fields or df.schema[col].dataType.names
    return df.select("*", *[F.col(f"{col}.{n}").alias(n) for n in names]).drop(col)


def _chunked(df: DataFrame, key: str, name: str, pieces: Column, id_col: str) -> DataFrame:
    ident = F.md5(F.concat_ws("|", F.lit(name), F.col(id_col).cast("string")))
    out = df.withColumn(f"{name}_id", ident).select("*", F.posexplode(pieces).alias(f"{name}_chunk_num", f"{key}_chunk"))
    return out.withColumn(f"{name}_chunk_num", F.col(f"{name}_chunk_num") + 1)


def split_tokens(df: DataFrame, key: str, num_tokens: int, name: str = "split", id_col: str = "doc_id") -> DataFrame:
    """Chunks of ``num_tokens`` tokens, numbered from 1; the long text itself stays behind."""
    t = tokens(F.col(key))
    starts = F.filter(F.sequence(F.lit(1), F.greatest(F.size("__t"), F.lit(1)), F.lit(num_tokens)), lambda i: i <= F.size("__t"))
    pieces = F.transform(starts, lambda i: F.concat_ws(" ", F.slice("__t", i, num_tokens)))
    return _chunked(df.withColumn("__t", t).drop(key), key, name, pieces, id_col).drop("__t")


def split_delimiter(df: DataFrame, key: str, delimiter: str, group: int = 1, name: str = "split", id_col: str = "doc_id") -> DataFrame:
    """Chunks between literal delimiters, ``group`` pieces each; empty pieces go."""
    quoted = "".join(c if c.isalnum() or c.isspace() else "\\" + c for c in delimiter)
    parts = F.filter(F.split(F.coalesce(F.col(key), F.lit("")), quoted), lambda x: F.trim(x) != "")
    starts = F.filter(F.sequence(F.lit(1), F.greatest(F.size("__t"), F.lit(1)), F.lit(group)), lambda i: i <= F.size("__t"))
    pieces = F.transform(starts, lambda i: F.concat_ws(delimiter, F.slice("__t", i, group)))
    return _chunked(df.withColumn("__t", parts).drop(key), key, name, pieces, id_col).drop("__t")


@dataclass(frozen=True)
class Side:
    """Chunks of one side: counts of nearest-first sections and the columns they show.

    ``head`` and ``tail`` are counted from the document's outside for previous chunks
    (head: first ones, tail: right before) and from the chunk for next ones (head: right
    after, tail: last ones). ``fraction`` shows only a part of the nearest chunk.
    """

    head: int = 0
    tail: int = 0
    middle: bool = False
    head_key: str | None = None
    middle_key: str | None = None
    tail_key: str | None = None
    fraction: float | None = None


@dataclass(frozen=True)
class Peripheral:
    previous: Side = field(default_factory=Side)
    next: Side = field(default_factory=Side)


def _part(text: Column, fraction: float, from_end: bool) -> Column:
    t = tokens(text)
    n = F.ceil(F.size(t) * F.lit(fraction)).cast("int")
    return F.concat_ws(" ", F.slice(t, F.size(t) - n + 1, n) if from_end else F.slice(t, 1, n))


def gather(df: DataFrame, doc_id: str, order: str, content: str, peripheral: Peripheral, rendered: str | None = None, headers: str | None = None) -> DataFrame:
    """Add ``<content>_rendered``: the chunk between tags of its context; the rows stay the same.

    Sections are read through bounded frames: a row holds the chunks that it shows and no
    others, whatever the length of the document (only ``middle`` shows all of a stretch).
    Never overlapping: head before tail before middle. Skipped stretches are marked with
    their number of chunks.
    """
    w = Window.partitionBy(doc_id).orderBy(order)
    back = Window.partitionBy(doc_id).orderBy(F.col(order).desc())
    p, q = peripheral.previous, peripheral.next
    empty = F.array().cast("array<string>")
    out = df.withColumn("__i", F.row_number().over(w)).withColumn("__n", F.count(F.lit(1)).over(Window.partitionBy(doc_id)))
    n, i = F.col("__n"), F.col("__i")
    shown = lambda key: F.struct(F.col(key or content).cast("string").alias("x"))
    text = lambda xs: xs["x"]
    columns: dict[str, Column] = {}

    def keep(name: str, value: Column) -> Column:
        columns[name] = value
        return F.col(name)

    def frame(name: str, key: str | None, start: int, end: int) -> Column:
        return keep(name, F.collect_list(shown(key)).over(w.rowsBetween(start, end)))

    def outermost(name: str, key: str | None, count: int, window) -> Column:
        """The first ``count`` chunks of a document in the window's order, as far as they stand before the row."""
        found = [keep(f"{name}{k}", F.nth_value(shown(key), k).over(window.rowsBetween(Window.unboundedPreceding, -1))) for k in range(1, count + 1)]
        return F.array_compact(F.array(*found)) if found else F.array().cast("array<struct<x:string>>")

    def gap(count: Column) -> Column:
        return F.when(count > 0, F.array(F.concat(F.lit("[... "), count.cast("string"), F.lit(" chunks ...]")))).otherwise(empty)

    def part(xs: Column, start: Column, count: Column) -> Column:
        return F.when(count > 0, text(F.slice(xs, F.greatest(start, F.lit(1)), F.greatest(count, F.lit(0))))).otherwise(empty)

    before, after = (i - 1).cast("int"), (n - i).cast("int")
    head = F.least(F.lit(p.head), before)
    tail = F.least(F.lit(p.tail), before - head)
    mid = before - head - tail
    if p.fraction is not None:
        last = keep("__last", F.lag(content).over(w))
        prev = F.when(i > 1, F.array(_part(last, p.fraction, True))).otherwise(empty)
    else:
        near_end = frame("__tail", p.tail_key, -p.tail, -1) if p.tail else F.array().cast("array<struct<x:string>>")
        if p.middle and not p.head:
            # All that stands before the nearest ones: nothing to cut, and null sections are not shown anyway.
            middle = keep("__mid", F.collect_list(F.col(p.middle_key or content).cast("string")).over(w.rowsBetween(Window.unboundedPreceding, -p.tail - 1)))
        else:
            middle = part(frame("__mid", p.middle_key, Window.unboundedPreceding, -1), head + 1, mid) if p.middle else gap(mid)
        prev = F.concat(text(outermost("__head", p.head_key, p.head, w)), middle, part(near_end, F.size(near_end) - tail + 1, tail))
    near = F.least(F.lit(q.head), after)
    far = F.least(F.lit(q.tail), after - near)
    rest = after - near - far
    if q.fraction is not None:
        following = keep("__following", F.lead(content).over(w))
        nxt = F.when(i < n, F.array(_part(following, q.fraction, False))).otherwise(empty)
    else:
        right_after = text(frame("__near", q.head_key, 1, q.head)) if q.head else empty
        middle = part(frame("__rest", q.middle_key, 1, Window.unboundedFollowing), near + 1, rest) if q.middle else gap(rest)
        # The last chunks come last to first.
        ends = outermost("__far", q.tail_key, q.tail, back)
        nxt = F.concat(right_after, middle, F.reverse(part(ends, F.lit(1), far)))
    parts = []
    if headers:
        parts.append(F.when(F.coalesce(F.col(headers), F.lit("")) != "", F.concat(F.lit("<headers>"), F.col(headers), F.lit("</headers>\n"))).otherwise(""))
    # Each chunk of a side is shown or counted in a gap, so that the sections need not be made twice to see if there are any.
    wrap = lambda tag, xs, chunks: F.when(chunks > 0, F.concat(F.lit(f"<{tag}>"), F.array_join(xs, "\n"), F.lit(f"</{tag}>"))).otherwise("")
    whole = F.concat(*parts, wrap("previous", prev, before), F.lit("<chunk>"), F.col(content), F.lit("</chunk>"), wrap("next", nxt, after))
    return out.withColumns(columns).withColumn(rendered or f"{content}_rendered", whole).drop("__i", "__n", *columns)


def header_lineage(df: DataFrame, doc_id: str, order: str, headers: str, levels: int = 3, mode: str = "path", name: str = "lineage") -> DataFrame:
    """Active headers above each chunk, by level, from ``headers`` (array of level and header).

    For each level the latest header of earlier chunks; in ``path`` mode a level is reset
    by a later shallower header, in ``latest`` mode it is not. Only levels above the
    chunk's first header are shown, all of them where it has none.
    """
    before = Window.partitionBy(doc_id).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    out, found = df, []
    for level in range(1, levels + 1):
        own = F.filter(F.transform(headers, lambda h, i: F.struct(h["level"].alias("level"), h["header"].alias("header"), i.alias("pos"))), lambda h: h["level"] == level)
        last = F.when(F.size(own) > 0, F.struct(F.struct(F.col(order).alias("chunk"), F.element_at(own, -1)["pos"].alias("pos")).alias("at"), F.element_at(own, -1)["header"].alias("header")))
        out = out.withColumn(f"__h{level}", F.last(last, ignorenulls=True).over(before))
    first = F.coalesce(F.get(headers, F.lit(0))["level"], F.lit(levels + 1))
    for level in range(1, levels + 1):
        own, live = F.col(f"__h{level}"), F.col(f"__h{level}").isNotNull() & (F.lit(level) < first)
        if mode == "path":
            for up in range(1, level):
                live = live & ~F.coalesce(F.col(f"__h{up}.at") > own["at"], F.lit(False))
        found.append(F.when(live, own["header"]))
    return out.withColumn(name, F.concat_ws(" > ", *found)).drop(*[f"__h{x}" for x in range(1, levels + 1)])
