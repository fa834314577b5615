"""Accuracy-first search: sampling, validators, recursive rewriting and two-stage selection.

Works on the plan only; data is touched through small jobs over one stored sample, drawn
with larger documents more likely and grown as operators turn out to be selective. All
outputs of sub-plans are kept by fingerprint.
"""

from __future__ import annotations

import math
import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import token_count
from ..model import grouped
from ..store import stored
from .directives import DIRECTIVES, Directive, Hints, chunk_sizes, gather_shapes, partition_asks
from .ir import Context, Op, Pipeline

#: Plans that go into pairwise comparison; rating scale; least share of the scale that needs no rewriting.
TOP_K, SCALE, GOOD = 6, 4, 0.9375
#: Least mean tokens of an attribute that is worth projecting before a reduce or a join.
LONG_ATTRIBUTE = 32


def size_biased_sample(df: DataFrame, id_col: str, size: Column, n: int, seed: str = "0") -> DataFrame:
    """n ids drawn without replacement, larger documents more likely: the n smallest of -ln(u)/size.

    u comes from MD5 of seed and id, so any engine draws the same sample. Only the id and
    the size are read, and the plan keeps n rows a task instead of sorting.
    """
    slot = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed), F.col(id_col).cast("string"))), 1, 8), 16, 10).cast("double")
    u = (slot + 1) / F.lit(float(2**32 + 1))
    return df.select(id_col, (-F.log(u) / F.greatest(size, F.lit(1))).alias("key")).orderBy("key", id_col).limit(n)


def required_sample(base: int, selectivities: list[float]) -> int:
    """The base sample grown by the inverse of every selectivity so far."""
    return math.ceil(base / math.prod(selectivities)) if selectivities else base


@dataclass(frozen=True)
class Criterion:
    """One binary test of an output; a column over input and output attributes."""

    name: str
    test: Callable[[], Column]


@dataclass(frozen=True)
class Verdict:
    """Whether outputs are good enough, and why not."""

    satisfied: bool
    mean: float
    reason: str


@dataclass(frozen=True)
class Validator:
    """Criteria over the attributes ``needs``; ratings go from 1 to ``scale`` (4 or 5)."""

    criteria: tuple[Criterion, ...]
    scale: int = SCALE
    needs: tuple[str, ...] = ()

    def passed(self) -> Column:
        return sum((F.coalesce(c.test(), F.lit(False)).cast("int") for c in self.criteria), F.lit(0))

    def rating(self) -> Column:
        """1 (no criterion holds) to ``scale`` (all hold)."""
        return 1 + F.floor(self.passed() / F.lit(len(self.criteria)) * (self.scale - 1))

    def judge(self, outputs: DataFrame) -> float:
        return self.verdict(outputs).mean

    def verdict(self, outputs: DataFrame) -> Verdict:
        """The mean rating against the bar, with the share of outputs that pass each failing criterion."""
        shares = [F.avg(F.coalesce(c.test(), F.lit(False)).cast("int")) for c in self.criteria]
        mean, *rates = outputs.agg(F.avg(self.rating()), *shares).first()
        bad = sorted((r or 0.0, c.name) for r, c in zip(rates, self.criteria) if (r or 0.0) < 1)
        reason = "; ".join(f"{n}: {r:.0%}" for r, n in bad) or "all criteria hold"
        return Verdict((mean or 0.0) >= GOOD * self.scale, mean or 0.0, reason)


def extraction_validator(answer: str, text: str, types: list[str], scale: int = SCALE) -> Validator:
    """Explicit tests for list extraction: supported by the text, of a listed type, no blanks, no repeats, coverage."""
    a, t = F.col(answer), F.col(text)
    return Validator(
        (
            Criterion("every span is in the source", lambda: F.forall(a, lambda x: F.contains(t, x["span"]))),
            Criterion("every type is listed", lambda: F.forall(a, lambda x: x["type"].isin(*types))),
            Criterion("no attribute is empty", lambda: F.forall(a, lambda x: (F.length(x["span"]) > 0) & (F.length(x["type"]) > 0))),
            Criterion("nothing is repeated", lambda: F.size(F.array_distinct(a)) == F.size(a)),
            # Hints of something to extract: an at-sign or a dotted number asks for at least one item.
            Criterion("something is found where signs of it stand", lambda: (~t.rlike("[a-z0-9]@[a-z]|[0-9][.][0-9]")) | (F.size(a) > 0)),
        ),
        scale,
        (answer, text),
    )


def rate_plans(outputs: dict[str, DataFrame], validator: Validator, doc_id: str) -> DataFrame:
    """(plan_id, doc_id, passed, rating) of every plan's output rows, in one tagged union."""
    tagged = [df.select(F.lit(p).alias("plan_id"), F.col(doc_id).alias("doc_id"), validator.passed().alias("passed"), validator.rating().alias("rating")) for p, df in outputs.items()]
    return reduce(DataFrame.unionByName, tagged)


def plan_scores(ratings: DataFrame) -> DataFrame:
    return ratings.groupBy("plan_id").agg(F.round(F.avg("rating"), 6).alias("mean_rating"), F.round(F.avg("passed"), 6).alias("mean_passed"))


def duel_plans(ratings: DataFrame, k: int = TOP_K, strategy: str = "two_stage") -> DataFrame:
    """Round robin of the k best-rated plans: (plan_id, mean_rating, wins), best first.

    In a pair the plan that passes more criteria on more documents wins. Ties of wins go to
    the higher mean rating, then to the smaller plan id. ``rate`` stops after the ratings;
    ``duel`` has all plans meet, whatever their rating.
    """
    scores = plan_scores(ratings)
    if strategy == "rate":
        return scores.select("plan_id", "mean_rating", F.lit(0).cast("long").alias("wins")).orderBy(F.col("mean_rating").desc(), "plan_id")
    top = scores
    if strategy == "two_stage":
        top = scores.orderBy(F.col("mean_rating").desc(), F.col("mean_passed").desc(), "plan_id").limit(k)
    best = ratings.join(top.select("plan_id"), "plan_id")
    a, b = best.alias("a"), best.alias("b")
    pairs = a.join(b, (F.col("a.doc_id") == F.col("b.doc_id")) & (F.col("a.plan_id") < F.col("b.plan_id")))
    sign = F.sum(F.signum(F.col("a.passed") - F.col("b.passed")))
    duels = pairs.groupBy(F.col("a.plan_id").alias("x"), F.col("b.plan_id").alias("y")).agg(sign.alias("s")).filter("s != 0")
    wins = duels.select(F.when(F.col("s") > 0, F.col("x")).otherwise(F.col("y")).alias("plan_id")).groupBy("plan_id").agg(F.count(F.lit(1)).alias("wins"))
    out = top.join(wins, "plan_id", "left").select("plan_id", "mean_rating", F.coalesce("wins", F.lit(0)).alias("wins"))
    return out.orderBy(F.col("wins").desc(), F.col("mean_rating").desc(), "plan_id")


@dataclass(frozen=True)
class Stats:
    """What the generator knows of the sample's texts and of the model."""

    mean_tokens: float
    max_tokens: int
    limit: int


class RuleGenerator:
    """Which directives apply and with which configurations, by rules over tasks and statistics.

    Where the caller's hints leave a choice open (no chunk sizes, no parts), it is filled:
    chunk sizes from the model's limit and the mean length, context shapes by the ratio of
    document to chunk, sub-tasks in groups of one to three.
    """

    def __init__(self, chunk_cap: int = 8, shapes: int | None = None):
        self.chunk_cap, self.shapes = chunk_cap, shapes

    def applicable(self, d: Directive, ops: tuple[Op, ...], hints: Hints, stats: Stats) -> bool:
        task = next((t for o in ops for t in o.tasks_of()), None)
        if d.id == "D1":
            return stats.max_tokens > min(self.sizes(hints, stats), default=stats.max_tokens)
        if d.id == "D11":
            return task is not None and (task.asks >= 2 or len(hints.parts) >= 2)
        if d.id in ("D12", "D13"):
            return stats.mean_tokens >= LONG_ATTRIBUTE
        return True

    def sizes(self, hints: Hints, stats: Stats) -> list[int]:
        return list(hints.chunk_tokens) or [n for n in chunk_sizes(stats.limit, stats.mean_tokens, self.chunk_cap) if n < stats.max_tokens]

    def propose(self, d: Directive, ops: tuple[Op, ...], hints: Hints, stats: Stats) -> list[Hints]:
        """Hints to apply the directive with, one set a configuration."""
        if d.id == "D1":
            out = []
            for n in self.sizes(hints, stats):
                shapes = hints.peripherals or tuple(gather_shapes(stats.mean_tokens, n))[: self.shapes]
                out.append(replace(hints, chunk_tokens=(n,), peripherals=shapes))
            return out
        if d.id == "D11":
            task = ops[0].tasks_of()[0]
            parts = list(hints.parts or task.parts)
            out = []
            for size in (1, 2, 3):
                if size < len(parts) or size == 1:
                    groups = partition_asks(task, parts, size)
                    tasks = tuple(g[0] if len(g) == 1 else grouped(g, f"{task.name}_{size}_{i}") for i, g in enumerate(groups))
                    out.append(replace(hints, parts=tasks))
            return out
        if d.id == "D7":
            return [replace(hints, gleaning=n) for n in dict.fromkeys((1, hints.gleaning))]
        return [hints]


@dataclass
class Search:
    """State of one optimisation: sample, model context, caches and the account of what was tried."""

    source: DataFrame
    ctx: Context
    hints: Hints
    validator: Validator
    text: str = "text"
    base: int = 40
    directives: tuple[Directive, ...] = DIRECTIVES
    generator: RuleGenerator = field(default_factory=RuleGenerator)
    strategy: str = "two_stage"
    max_depth: int = 2
    max_plans: int = 40
    seed: str = "0"
    cache: dict[str, DataFrame] = field(default_factory=dict)
    selectivity: list[float] = field(default_factory=list)
    broken: list[str] = field(default_factory=list)
    dropped: list[str] = field(default_factory=list)
    notes: list[str] = field(default_factory=list)
    tried: int = 0
    seconds: float = 0.0
    bill: list = field(default_factory=list)

    def __post_init__(self):
        self.draw()

    def draw(self) -> None:
        """A sample as large as the selectivities so far ask for; outputs over the last one go."""
        self.size = required_sample(self.base, self.selectivity)
        size = token_count(F.col(self.text))
        ids = size_biased_sample(self.source, self.ctx.doc_id, size, self.size, self.seed).select(self.ctx.doc_id)
        self.sample = stored(self.source.join(ids, self.ctx.doc_id, "left_semi"), "sample")
        n, mean, most = self.sample.agg(F.count(F.lit(1)), F.avg(size), F.max(size)).first()
        self.rows, self.stats = n, Stats(mean or 0.0, most or 0, self.ctx.model.profile.context_tokens)
        self.cache.clear()

    def output(self, plan: Pipeline) -> DataFrame:
        key = plan.fingerprint()
        if key not in self.cache:
            began = time.time()
            self.cache[key] = stored(plan.run(self.sample, self.ctx), "output")
            self.bill.append(plan.ledger(self.sample, self.ctx))
            self.tried += 1
            self.seconds += time.time() - began
        return self.cache[key]

    def complete(self, plan: Pipeline) -> bool:
        """Whether a plan's output has the attributes that the validator looks at; analyses only."""
        return set(self.validator.needs) <= set(plan.run(self.sample, self.ctx).columns)

    def note_selectivity(self, before: tuple[Op, ...], after: tuple[Op, ...]) -> None:
        """Rows out by rows in of what was just optimised; a selective part makes the sample grow."""
        if not self.complete(Pipeline(after)):
            return
        n = self.output(Pipeline(after)).count()
        m = self.output(Pipeline(before)).count() if before and self.complete(Pipeline(before)) else self.rows
        if m and 0 < n < m:
            self.selectivity.append(n / m)
            self.draw()

    def account(self) -> DataFrame:
        """Plans, calls, tokens and dollars of all sub-plans that were run over the sample."""
        spark = self.source.sparkSession
        rows = reduce(DataFrame.unionByName, self.bill, spark.createDataFrame([], "step int, op string, calls long, tokens_in long, tokens_out long, dollars double"))
        total = [F.coalesce(F.sum(c), F.lit(0)).cast("long").alias(c) for c in ("calls", "tokens_in", "tokens_out")]
        return rows.agg(*total, F.round(F.coalesce(F.sum("dollars"), F.lit(0.0)), 6).alias("dollars")).withColumn("plans", F.lit(self.tried))


def optimize_pipeline(plan: Pipeline, search: Search, before: tuple[Op, ...] = (), depth: int = 0) -> Pipeline:
    """Left to right: the longest suffix of what is done that matches a directive with the next operator, else that alone."""
    done: tuple[Op, ...] = ()
    trail: tuple[str, ...] = plan.trail
    for op in plan.ops:
        start = next((i for i in range(len(done)) if any(d.matches((*done[i:], op)) for d in search.directives)), len(done))
        better = _optimize_part((*before, *done[:start]), (*done[start:], op), search, depth)
        if depth == 0:
            search.note_selectivity((*before, *done), (*before, *done[:start], *better.ops))
        done = (*done[:start], *better.ops)
        trail = (*trail, *better.trail)
    return Pipeline(done, trail)


def _optimize_part(before: tuple[Op, ...], part: tuple[Op, ...], search: Search, depth: int) -> Pipeline:
    here, whole = Pipeline(part), Pipeline((*before, *part))
    found = [d for d in search.directives if d.matches(part) and search.generator.applicable(d, part, search.hints, search.stats)]
    if not found or depth >= search.max_depth or not search.complete(whole):
        return here
    verdict = search.validator.verdict(search.output(whole))
    search.notes.append(f"{' > '.join(type(o).__name__ for o in part)}: {verdict.mean:.3f}, {verdict.reason}")
    if verdict.satisfied:
        return here
    candidates = {"00 as written": (here, whole)}
    for d in found:
        sets = [ops for h in search.generator.propose(d, part, search.hints, search.stats) for ops in d.apply(part, h)]
        for i, ops in enumerate(sets):
            label = f"{len(candidates):02d} {d.id} {d.name} {i}"
            if search.tried >= search.max_plans:
                search.dropped.append(label)
                continue
            if not search.complete(Pipeline((*before, *ops))):
                search.broken.append(label)
                continue
            # Operators that a directive has made are optimised themselves, behind what stands before them.
            inner = optimize_pipeline(Pipeline(ops), search, before, depth + 1) if depth + 1 < search.max_depth else Pipeline(ops)
            candidates[label] = (Pipeline(inner.ops, (f"{d.id} {d.name}", *inner.trail)), Pipeline((*before, *inner.ops)))
    ratings = stored(rate_plans({k: search.output(v[1]) for k, v in candidates.items()}, search.validator, search.ctx.doc_id), "ratings")
    best = duel_plans(ratings, strategy=search.strategy).first()
    return candidates[best.plan_id][0]


def optimize(plan: Pipeline, df: DataFrame, search: Search) -> Pipeline:
    """Check the prompts, then search; the result runs on the whole data."""
    plan.analyze(df)
    return optimize_pipeline(plan, search)


def pareto(plans: DataFrame, accuracy: str, cost: str) -> DataFrame:
    """Plans that no other beats in both accuracy and cost."""
    w = Window.orderBy(F.col(cost), F.col(accuracy).desc()).rowsBetween(Window.unboundedPreceding, -1)
    return plans.withColumn("__best", F.max(accuracy).over(w)).filter(F.col("__best").isNull() | (F.col(accuracy) > F.col("__best"))).drop("__best")


def overflow(df: DataFrame, text: str, limit: int) -> DataFrame:
    """Mark rows whose text does not fit a model's context: ``fits`` decides the branch that they take."""
    return df.withColumn("fits", token_count(F.col(text)) <= limit)


def run_adaptive(plan: Pipeline, fallback: Pipeline, df: DataFrame, text: str, limit: int, ctx: Context) -> DataFrame:
    """Rows that fit go through the plan, the others through the fallback (say, a chunked one)."""
    marked = overflow(df, text, limit)
    a = plan.run(marked.filter("fits").drop("fits"), ctx)
    b = fallback.run(marked.filter("not fits").drop("fits"), ctx)
    common = [c for c in a.columns if c in b.columns]
    return a.select(*common).unionByName(b.select(*common))
