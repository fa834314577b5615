"""Map, parallel map, filter, reduce, batched fold, tree merge, validation and gleaning."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import PerfectModel, Task
from ..store import cut, stored
from .numbering import largest_group, numbered

PERFECT = PerfectModel()
#: Most rows of a group that one call of a summary gets; larger groups need ``merge``, a fold or a tree.
MAX_GROUP = 1_000_000
#: Parts over which the rows of a group are summarised before they are merged.
PARTS = 64
#: Batches of a group that a fold holds in one row; the state goes on to the next such row.
SEGMENT = 256
#: States of neighbouring segments that are merged at once, level by level.
MERGED = 32


def sem_map(df: DataFrame, task: Task, model=PERFECT, doc_id: str = "doc_id", drop_keys: tuple[str, ...] = (), turn: int = 0) -> DataFrame:
    """Add the task's answer to every row; ``drop_keys`` leave, so that scans need not read them further."""
    return df.withColumn(task.name, model.answer(task, F.col(doc_id), turn)).drop(*drop_keys)


def sem_parallel_map(df: DataFrame, tasks: list[Task], model=PERFECT, doc_id: str = "doc_id") -> DataFrame:
    """Independent tasks on the same rows in one projection.

    Tasks over one column share its token count where the model needs it, which a
    projection below them computes once.
    """
    shared = {}
    if hasattr(model, "counted"):
        for i, content in enumerate(dict.fromkeys(t.content for t in tasks)):
            shared[content] = f"__tokens{i}"
        df = df.select("*", *[model.counted(F.col(c)).alias(n) for c, n in shared.items()])
        answers = [model.answer(t, F.col(doc_id), counted=F.col(shared[t.content])).alias(t.name) for t in tasks]
    else:
        answers = [model.answer(t, F.col(doc_id)).alias(t.name) for t in tasks]
    return df.select("*", *answers).drop(*shared.values())


def sem_filter(df: DataFrame, task: Task, model=PERFECT, doc_id: str = "doc_id") -> DataFrame:
    return df.filter(model.answer(task, F.col(doc_id)))


def _guarded(rows: Column) -> Column:
    """The rows of a group, or an error where one call cannot be meant to hold them."""
    large = F.raise_error(F.concat(F.lit("a group has "), F.size(rows).cast("string"), F.lit(" rows: give merge, or use fold or tree_reduce")))
    return F.when(F.size(rows) > MAX_GROUP, large.cast("void")).otherwise(rows)


def sem_reduce(df: DataFrame, keys: list[str], payload: list[str], summarise: Callable[[Column], Column], name: str = "answer", order_by: list[str] | None = None, merge: Callable[[Column], Column] | None = None) -> DataFrame:
    """One row per key: ``summarise`` gets the group's structs, sorted by ``order_by`` if given.

    Without keys the whole frame is one group. An associative summary says with ``merge``
    how an array of its answers becomes one: groups are then summarised in :data:`PARTS`
    parts by a hash of their rows first, so that neither a hot group nor the frame meets in
    one task. Without ``merge`` a group of over :data:`MAX_GROUP` rows is an error.
    """
    fields = [*(order_by or []), *[p for p in payload if p not in (order_by or [])]]
    listed = F.collect_list(F.struct(*fields))
    if merge and not order_by:
        part = F.pmod(F.xxhash64(*fields, F.monotonically_increasing_id()), F.lit(PARTS)).cast("int")
        parts = df.withColumn("__part", part).groupBy(*keys, "__part").agg(listed.alias("__rows")).select(*keys, summarise(F.col("__rows")).alias("__a"))
        return parts.groupBy(*keys).agg(F.collect_list("__a").alias("__as")).select(*keys, merge(F.col("__as")).alias(name))
    rows = F.array_sort(listed) if order_by else listed
    return df.groupBy(*keys).agg(rows.alias("__rows")).select(*keys, summarise(_guarded(F.col("__rows"))).alias(name))


def fold(df: DataFrame, keys: list[str], payload: list[str], order_by: list[str], batch_size: int, zero: Column, step: Callable[[Column, Column], Column], finish: Callable[[Column], Column] = lambda s: s, name: str = "answer", merge: Callable[[Column, Column], Column] | None = None, segment: int = SEGMENT, places: str | None = None, merge_all: Callable[[Column], Column] | None = None) -> DataFrame:
    """Batched fold: batches of a group in order, each handed to ``step`` with the state so far.

    The state is any struct, so that a scratchpad travels beside the accumulated output.
    Also returns ``n_calls``, the length of the sequential chain. A row holds at most
    ``segment`` batches. Where a group has more, the state is written and goes on to its
    next segment, round by round; an associative step may give ``merge`` of two states
    instead: all segments are then folded at once, and their states are merged in a tree.
    ``merge_all`` makes one state of an array of them in order, where that takes less than
    going through a growing state once for each.
    ``places`` names a column that has each row's place in its group by order, from 0, so
    that folds of the same rows need not number them again.
    """
    if places:
        placed = df.select(*keys, F.struct(*payload).alias("__row"), F.col(places).alias("__n"))
    else:
        slim = df.select(*keys, F.struct(*payload).alias("__row"), *[F.col(c).alias(f"__o{i}") for i, c in enumerate(order_by)])
        placed = numbered(slim, keys, [f"__o{i}" for i in range(len(order_by))])
    listed = F.sort_array(F.collect_list(F.struct("__n", "__row")))
    calls = F.ceil(F.count(F.lit(1)) / batch_size).cast("long")
    parts = placed.groupBy(*keys, F.floor(F.col("__n") / (batch_size * segment)).alias("__s")).agg(listed.alias("__rows"), calls.alias("__calls"))
    starts = F.sequence(F.lit(1), F.size("__rows"), F.lit(batch_size))
    # A lambda's own variable: the sorted rows are made once, not for each batch.
    cut_up = F.transform(F.array(F.transform("__rows", lambda r: r["__row"])), lambda xs: F.transform(starts, lambda i: F.slice(xs, i, batch_size)))
    parts = parts.select(*keys, "__s", F.get(cut_up, F.lit(0)).alias("__batches"), "__calls")
    run = lambda start: F.aggregate("__batches", start, step)
    rounds = math.ceil((largest_group(df, keys) or 1) / batch_size / segment)
    if rounds <= 1:
        return parts.select(*keys, finish(run(zero)).alias(name), F.col("__calls").alias("n_calls"))
    if merge or merge_all:
        states = parts.select(*keys, "__s", run(zero).alias("__state"), "__calls")
        while rounds > 1:
            joined = states.groupBy(*keys, F.floor(F.col("__s") / MERGED).alias("__s")).agg(F.sort_array(F.collect_list(F.struct("__s", "__state"))).alias("__all"), F.sum("__calls").alias("__calls"))
            if merge_all:
                whole = merge_all(F.transform("__all", lambda s: s["__state"]))
            else:
                whole = F.aggregate(F.slice("__all", 2, MERGED), F.get("__all", F.lit(0))["__state"], lambda acc, s: merge(acc, s["__state"]))
            states = joined.select(*keys, "__s", whole.alias("__state"), "__calls")
            rounds = math.ceil(rounds / MERGED)
        return states.select(*keys, finish(F.col("__state")).alias(name), F.col("__calls").alias("n_calls"))
    parts, state = stored(parts, "segments"), None
    for i in range(rounds):
        now = parts.filter(F.col("__s") == i)
        if state is None:
            state = cut(now.select(*keys, run(zero).alias("__state"), "__calls"))
            continue
        same = F.lit(True)
        for j, k in enumerate(keys):
            same = same & F.col(k).eqNullSafe(F.col(f"__k{j}"))
        following = now.select(*[F.col(k).alias(f"__k{j}") for j, k in enumerate(keys)], "__batches", F.col("__calls").alias("__more"))
        both = state.join(following, same, "left")
        after = F.when(F.col("__batches").isNull(), F.col("__state")).otherwise(run(F.col("__state")))
        state = cut(both.select(*keys, after.alias("__state"), (F.col("__calls") + F.coalesce("__more", F.lit(0))).alias("__calls")))
    return state.select(*keys, finish(F.col("__state")).alias(name), F.col("__calls").alias("n_calls"))


def tree_reduce(df: DataFrame, keys: list[str], value: str, order_by: list[str], fanout: int, merge: Callable[[Column], Column], levels: int | None = None) -> DataFrame:
    """Hierarchical merge for associative tasks: ``fanout`` neighbours become one, level by level.

    As many levels as the largest group needs (or those given; then the last one merges what is left).
    """
    if levels is None:
        levels = max(0, math.ceil(math.log(max(1, largest_group(df, keys)), fanout)) - 1)
    cur = numbered(df.select(*keys, F.col(value).alias("__v"), *[F.col(c).alias(f"__o{i}") for i, c in enumerate(order_by)]), keys, [f"__o{i}" for i in range(len(order_by))])
    cur = cur.select(*keys, "__v", "__n")
    for _ in range(levels):
        cur = cur.groupBy(*keys, F.floor(F.col("__n") / fanout).alias("__n")).agg(F.array_sort(F.collect_list(F.struct("__n", "__v"))).alias("__vs"))
        cur = cur.select(*keys, "__n", merge(F.transform("__vs", lambda r: r["__v"])).alias("__v"))
    last = cur.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("__n", "__v"))).alias("__vs"))
    return last.select(*keys, merge(F.transform("__vs", lambda r: r["__v"])).alias(value))


def validate_retry(df: DataFrame, task: Task, model, checks: list[str], max_retries: int, doc_id: str = "doc_id") -> DataFrame:
    """Map, then run the task again on rows only that fail a check; ``attempts`` counts the calls.

    Checks are SQL predicates over inputs and outputs. Each retry is a conditional column,
    so that good rows are not asked again and the plan stays one stage.
    """
    ok = F.coalesce(F.expr(" AND ".join(f"({c})" for c in checks)), F.lit(False))
    out = sem_map(df, task, model, doc_id).withColumn("attempts", F.lit(1))
    for turn in range(1, max_retries + 1):
        again = ~ok
        out = out.withColumn("__again", again).withColumn(task.name, F.when(F.col("__again"), model.answer(task, F.col(doc_id), turn)).otherwise(F.col(task.name)))
        out = out.withColumn("attempts", F.col("attempts") + F.col("__again").cast("int")).drop("__again")
    return out.withColumn("valid", ok)


def glean(df: DataFrame, task: Task, model, satisfied: Callable[[Column, Column], Column], rounds: int, doc_id: str = "doc_id") -> DataFrame:
    """Gleaning: a validator judges each answer, and a refinement adds what a further pass finds.

    ``calls`` is 1 plus two for every round that a row goes through (judge and refine).
    """
    out = sem_map(df, task, model, doc_id).withColumn("calls", F.lit(1))
    for turn in range(1, rounds + 1):
        out = out.withColumn("__open", ~satisfied(F.col(task.content), F.col(task.name)))
        better = F.array_union(F.col(task.name), model.answer(task, F.col(doc_id), turn)) if task.is_list else model.answer(task, F.col(doc_id), turn)
        out = out.withColumn(task.name, F.when(F.col("__open"), better).otherwise(F.col(task.name)))
        out = out.withColumn("calls", F.col("calls") + F.when(F.col("__open"), 2).otherwise(0)).drop("__open")
    return out


def sem_rank(df: DataFrame, keys: list[str], score: Column, ties: list[str], k: int) -> DataFrame:
    """The k best rows of each group with their ``rank``."""
    w = Window.partitionBy(*keys).orderBy(score.desc(), *ties)
    return df.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def sem_sort(df: DataFrame, score: Column, ties: list[str], k: int | None = None) -> DataFrame:
    out = df.orderBy(score.desc(), *ties)
    return out if k is None else out.limit(k)
