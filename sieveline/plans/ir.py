"""Operators of a pipeline as frozen records, lowered one by one onto a lazy DataFrame."""

from __future__ import annotations

import hashlib
import json
from collections.abc import Callable
from dataclasses import dataclass, field, fields, is_dataclass, replace
from functools import reduce
from types import CodeType, FunctionType
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import operators as O
from ..functions.prompts import Template, fold_prompt
from ..functions.text import token_count
from ..model import PerfectModel, Task


def identity(x: Any) -> Any:
    """What makes two parts of a plan the same: the content of records, and of functions their
    code, constants, defaults and what they close over. Other objects are only equal to themselves."""
    if x is None or isinstance(x, (str, int, float, bool, bytes)):
        return x
    if isinstance(x, (tuple, list)):
        return [identity(v) for v in x]
    if isinstance(x, (set, frozenset)):
        return sorted(map(str, x))
    if isinstance(x, dict):
        return sorted((str(k), identity(v)) for k, v in x.items())
    if isinstance(x, T.DataType):
        return x.json()
    if isinstance(x, CodeType):
        return [x.co_code.hex(), identity([c for c in x.co_consts]), list(x.co_names)]
    if isinstance(x, FunctionType):
        cells = []
        for c in x.__closure__ or ():
            try:
                v = c.cell_contents
            except ValueError:
                v = "empty"
            cells.append("itself" if v is x else identity(v))
        return [x.__module__, x.__qualname__, identity(x.__code__), cells, identity(x.__defaults__ or ()), identity(x.__kwdefaults__ or {})]
    if isinstance(x, Column):
        return str(x)
    if is_dataclass(x) and not isinstance(x, type):
        return [type(x).__qualname__, [(f.name, identity(getattr(x, f.name))) for f in fields(x)]]
    if hasattr(x, "func") and hasattr(x, "args"):  # a partial function
        return ["partial", identity(x.func), identity(x.args), identity(x.keywords)]
    return f"{type(x).__qualname__} {getattr(x, '__name__', '')} {id(x)}"


@dataclass(frozen=True)
class Context:
    """What lowering needs beside the plan: model and document key."""

    model: Any = field(default_factory=PerfectModel)
    doc_id: str = "doc_id"


@dataclass(frozen=True)
class Op:
    def lower(self, df: DataFrame, ctx: Context) -> DataFrame:
        raise NotImplementedError

    def tasks_of(self) -> tuple[Task, ...]:
        """The requests that this operator makes for each row."""
        return ()

    def describe(self) -> dict:
        out = {"op": type(self).__name__}
        for f in fields(self):
            v = getattr(self, f.name)
            out[f.name] = v.name if isinstance(v, Task) else [t.name for t in v] if isinstance(v, tuple) and v and isinstance(v[0], Task) else getattr(v, "__name__", None) or (v if isinstance(v, (str, int, float, bool, type(None))) else str(v))
        return out


@dataclass(frozen=True)
class MapOp(Op):
    task: Task
    drop: tuple[str, ...] = ()
    gleaning: int = 0
    satisfied: Callable[[Column, Column], Column] | None = None
    model: Any = None

    def tasks_of(self):
        return (self.task,)

    def lower(self, df, ctx):
        model = self.model or ctx.model
        if self.gleaning:
            return O.glean(df, self.task, model, self.satisfied, self.gleaning, ctx.doc_id).drop("calls", *self.drop)
        return O.sem_map(df, self.task, model, ctx.doc_id, self.drop)


@dataclass(frozen=True)
class ParallelMapOp(Op):
    tasks: tuple[Task, ...]

    def tasks_of(self):
        return self.tasks

    def lower(self, df, ctx):
        return O.sem_parallel_map(df, list(self.tasks), ctx.model, ctx.doc_id)


@dataclass(frozen=True)
class FilterOp(Op):
    task: Task

    def tasks_of(self):
        return (self.task,)

    def lower(self, df, ctx):
        return O.sem_filter(df, self.task, ctx.model, ctx.doc_id)


@dataclass(frozen=True)
class ProjectOp(Op):
    """Row-local code: adds ``name`` from an expression and drops columns."""

    name: str
    expr: Callable[[], Column]
    drop: tuple[str, ...] = ()

    def lower(self, df, ctx):
        return df.withColumn(self.name, self.expr()).drop(*self.drop)


@dataclass(frozen=True)
class UnnestOp(Op):
    col: str
    keep_empty: bool = False
    fields_only: bool = False

    def lower(self, df, ctx):
        return O.unnest_fields(df, self.col) if self.fields_only else O.unnest(df, self.col, self.keep_empty)


@dataclass(frozen=True)
class SplitOp(Op):
    """Chunks of ``num_tokens`` tokens; with a delimiter, of that many pieces between delimiters."""

    key: str
    num_tokens: int
    name: str = "split"
    delimiter: str | None = None

    def lower(self, df, ctx):
        if self.delimiter is not None:
            return O.split_delimiter(df, self.key, self.delimiter, self.num_tokens, self.name, ctx.doc_id)
        return O.split_tokens(df, self.key, self.num_tokens, self.name, ctx.doc_id)


@dataclass(frozen=True)
class GatherOp(Op):
    content: str
    peripheral: O.Peripheral = field(default_factory=O.Peripheral)
    name: str = "split"
    headers: str | None = None

    def lower(self, df, ctx):
        return O.gather(df, f"{self.name}_id", f"{self.name}_chunk_num", self.content, self.peripheral, headers=self.headers)


@dataclass(frozen=True)
class ReduceOp(Op):
    """Groups by keys; ``summarise`` maps the array of payload structs to ``name``; ``carry`` keeps first values."""

    keys: tuple[str, ...]
    payload: tuple[str, ...]
    summarise: Callable[[Column], Column]
    name: str
    order_by: tuple[str, ...] = ()
    carry: tuple[str, ...] = ()

    def lower(self, df, ctx):
        rows = F.collect_list(F.struct(*[c for c in self.order_by if c not in self.payload], *self.payload))
        rows = F.array_sort(rows) if self.order_by else rows
        out = df.groupBy(*self.keys).agg(rows.alias("__rows"), *[F.first(c, ignorenulls=True).alias(c) for c in self.carry if c not in self.keys])
        return out.withColumn(self.name, self.summarise(F.col("__rows"))).drop("__rows")


@dataclass(frozen=True)
class FoldOp(Op):
    """Batched fold of groups; the prompt of later batches is given or derived from the first one's."""

    keys: tuple[str, ...]
    payload: tuple[str, ...]
    order_by: tuple[str, ...]
    batch_size: int
    zero: Callable[[], Column]
    step: Callable[[Column, Column], Column]
    name: str
    finish: Callable[[Column], Column] = lambda s: s
    prompt: str = ""
    later_prompt: str = ""

    def prompts(self) -> tuple[str, str]:
        """Prompt of the first and of later batches."""
        return self.prompt, self.later_prompt or (fold_prompt(self.prompt, self.name) if self.prompt else "")

    def lower(self, df, ctx):
        return O.fold(df, list(self.keys), list(self.payload), list(self.order_by), self.batch_size, self.zero(), self.step, self.finish, self.name)


@dataclass(frozen=True)
class ResolveOp(Op):
    key: str
    compare: Callable[..., Column]
    block: Callable[[DataFrame, str], DataFrame] = O.normalized_pairs
    context: str | None = None

    def lower(self, df, ctx):
        return O.resolve(df, self.key, self.block(df, self.key), self.compare, context=self.context)


@dataclass(frozen=True)
class EquijoinOp(Op):
    right: Callable[[], DataFrame]
    left_id: str
    right_id: str
    block: Callable[[DataFrame, DataFrame], DataFrame]
    compare: Callable[[DataFrame], Column] | None = None
    how: str = "inner"

    def lower(self, df, ctx):
        right = self.right()
        return O.equijoin(df, right, self.left_id, self.right_id, self.block(df, right), self.compare, self.how)


@dataclass(frozen=True)
class Pipeline:
    ops: tuple[Op, ...]
    trail: tuple[str, ...] = ()

    def run(self, df: DataFrame, ctx: Context | None = None) -> DataFrame:
        for op in self.ops:
            df = op.lower(df, ctx or Context())
        return df

    def analyze(self, df: DataFrame) -> None:
        """Reject prompts without an input placeholder before anything runs."""
        for op in self.ops:
            for task in op.tasks_of():
                if task.prompt:
                    Template(task.prompt).check([*df.columns, task.content])
            if isinstance(op, FoldOp):
                for p in filter(None, op.prompts()):
                    Template(p).check([*df.columns, *op.payload, "inputs", op.name])

    def ledger(self, df: DataFrame, ctx: Context | None = None) -> DataFrame:
        """(step, op, calls, tokens_in, tokens_out, dollars) of each operator that asks a model, over a frame.

        A round of gleaning is a judging and a refining call; rows that need neither are
        counted as if they did, so that this is an upper bound for gleaned maps.
        """
        ctx, out = ctx or Context(), []
        for i, op in enumerate(self.ops):
            after = op.lower(df, ctx)
            if tasks := op.tasks_of():
                model = getattr(op, "model", None) or ctx.model
                p, times = model.profile, 1 + 2 * getattr(op, "gleaning", 0)
                read = sum((F.least(token_count(F.col(t.content).cast("string")), F.lit(p.context_tokens)).cast("long") for t in tasks), F.lit(0).cast("long"))
                asked = df.agg((F.count(F.lit(1)) * len(tasks) * times).alias("calls"), (F.coalesce(F.sum(read), F.lit(0)) * times).alias("tokens_in"))
                names = [t.name for t in tasks if t.name in after.columns]
                said = sum((token_count(F.to_json(F.struct(n))).cast("long") for n in names), F.lit(0).cast("long"))
                given = after.agg(F.coalesce(F.sum(said), F.lit(0)).alias("tokens_out"))
                row = asked.crossJoin(given).withColumn("dollars", F.round((F.col("tokens_in") * p.price_in + F.col("tokens_out") * p.price_out) / 1e6, 9))
                out.append(row.select(F.lit(i).alias("step"), F.lit(type(op).__name__).alias("op"), "calls", "tokens_in", "tokens_out", "dollars"))
            df = after
        if not out:
            return df.sparkSession.createDataFrame([], "step int, op string, calls long, tokens_in long, tokens_out long, dollars double")
        return reduce(DataFrame.unionByName, out)

    def fingerprint(self) -> str:
        return hashlib.md5(json.dumps(identity(self.ops), sort_keys=True).encode()).hexdigest()

    def explain(self) -> str:
        return "\n".join([*(f"{i}. {json.dumps(op.describe(), default=str)}" for i, op in enumerate(self.ops)), *(f"rewritten by {t}" for t in self.trail)])

    def with_(self, start: int, stop: int, ops: tuple[Op, ...], directive: str) -> Pipeline:
        return replace(self, ops=(*self.ops[:start], *ops, *self.ops[stop:]), trail=(*self.trail, directive))
