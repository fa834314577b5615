"""The narrow interface behind which language models sit.

A :class:`Task` has a prompt, an output schema and a reference answer: a Catalyst
expression over the content column. :class:`PerfectModel` gives the reference answer.
:class:`SimulatedModel` loses and invents items by a deterministic rule that any SQL engine
can replay; it is built so that length and the number of asks hurt, so numbers made with it
test the machinery and say nothing about real models. :class:`EndpointModel` calls a user's
function in Arrow batches.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .functions.prompts import Template, conform
from .functions.text import bucket, token_count, truncate_middle
from .store import scratch


@dataclass(frozen=True)
class Task:
    """One request per row: the answer goes to the column ``name``.

    ``parts`` are requests for single attributes that together ask for the same as this one.
    """

    name: str
    content: str
    reference: Callable[[Column], Column]
    schema: T.DataType = field(default_factory=lambda: T.ArrayType(T.StructType().add("type", "string").add("span", "string")))
    prompt: str = ""
    asks: int = 1
    parts: tuple[Task, ...] = ()

    def on(self, content: str, name: str | None = None) -> Task:
        """The same task over another column."""
        return replace(self, content=content, name=name or self.name, prompt=self.prompt.replace("{{ input." + self.content + " }}", "{{ input." + content + " }}"), parts=tuple(p.on(content) for p in self.parts))

    @property
    def is_list(self) -> bool:
        return isinstance(self.schema, T.ArrayType)


def grouped(parts: list[Task], name: str) -> Task:
    """One list request for what several related ones ask for."""
    first = parts[0]
    prompt = "\n".join(p.prompt for p in parts)

    def reference(c: Column) -> Column:
        return F.array_sort(F.array_distinct(F.concat(*[p.reference(c) for p in parts])))

    return replace(first, name=name, reference=reference, prompt=prompt, asks=sum(p.asks for p in parts), parts=tuple(parts))


@dataclass(frozen=True)
class Profile:
    """Limits, prices per million tokens and error rates (permille) of a model.

    ``disorder``: places by which an item of a list may be late, per hundred tokens of input.
    ``whole``: a text over the context is read in parts, so that nothing of it is left out.
    """

    name: str = "small"
    context_tokens: int = 4000
    price_in: float = 0.15
    price_out: float = 0.60
    keep: int = 950
    per_hundred_tokens: int = 25
    per_ask: int = 30
    floor: int = 300
    hallucination: int = 20
    gleaning_bonus: int = 150
    disorder: int = 0
    whole: bool = False


class PerfectModel:
    profile = Profile("perfect", 10**9, 0.0, 0.0)

    def answer(self, task: Task, doc_id: Column, turn: int = 0) -> Column:
        return task.reference(F.col(task.content))


@dataclass(frozen=True)
class SimulatedModel:
    """Keeps an item iff its bucket is under a bound that falls with tokens and asks."""

    profile: Profile = Profile()
    seed: str = "0"

    def counted(self, content: Column) -> Column:
        """What the model sees of a text and its number of tokens, for tasks that share them."""
        return F.struct(token_count(content).alias("n"), self.seen(content).alias("seen"))

    def seen(self, content: Column) -> Column:
        """What the model sees of a text."""
        return content if self.profile.whole else truncate_middle(content, self.profile.context_tokens)

    def bound(self, task: Task, turn: int, n: Column) -> Column:
        p = self.profile
        n = F.least(n, F.lit(p.context_tokens))
        fall = F.lit(p.keep - p.per_ask * (task.asks - 1) + p.gleaning_bonus * turn) - F.floor(n / 100).cast("int") * p.per_hundred_tokens
        return F.least(F.lit(1000), F.greatest(F.lit(p.floor), fall))

    def answer(self, task: Task, doc_id: Column, turn: int = 0, counted: Column | None = None) -> Column:
        content = F.col(task.content)
        seen = task.reference(counted["seen"] if counted is not None else self.seen(content))
        n = counted["n"] if counted is not None else token_count(content)
        who, bound = doc_id.cast("string"), self.bound(task, turn, n)
        if not task.is_list:
            if not isinstance(task.schema, T.BooleanType):
                return seen
            return F.when(bucket(self.seed, self.profile.name, task.name, who, str(turn)) < bound, seen).otherwise(~seen)
        names = task.schema.elementType.names if isinstance(task.schema.elementType, T.StructType) else []
        parts = lambda x: [x[k].cast("string") for k in names] or [x.cast("string")]
        kept = F.filter(seen, lambda x: bucket(self.seed, self.profile.name, who, *parts(x), str(turn)) < bound)
        if self.profile.disorder:
            reach = F.floor(F.least(n, F.lit(self.profile.context_tokens)) / 100) * self.profile.disorder
            late = lambda x: F.floor(bucket(self.seed, "late", who, *parts(x)) * reach / 1000)
            placed = F.array_sort(F.transform(kept, lambda x, i: F.struct((i + late(x)).alias("at"), i.alias("i"), x.alias("x"))))
            kept = F.transform(placed, lambda r: r["x"])
        if not names:
            return kept
        made = F.array(F.struct(*[F.lit("invented").alias(k) if i == 0 else F.concat(F.lit("item "), who).alias(k) for i, k in enumerate(names)]))
        return F.when(bucket(self.seed, "h", self.profile.name, who, task.name, str(turn)) < self.profile.hallucination, F.concat(kept, made)).otherwise(kept)


class EndpointError(RuntimeError):
    """An endpoint gave no usable answer."""


@dataclass(frozen=True)
class EndpointModel:
    """Calls ``complete(prompts) -> JSON texts`` per Arrow batch, at most ``per_second`` prompts a task.

    Errors of :attr:`transient` types are tried again, others end the job. An answer that is
    not JSON, or a list of another length, is asked for again as often; what then still is
    not JSON is null, or ends the job if ``strict``.
    """

    complete: Callable[[list[str]], list[str]]
    profile: Profile = Profile("endpoint", 128_000)
    attempts: int = 3
    per_second: float = 0.0
    transient: tuple[type, ...] = (ConnectionError, TimeoutError, OSError)
    strict: bool = False

    def answer(self, task: Task, doc_id: Column, turn: int = 0) -> Column:
        return conform(self.raw(Template(task.prompt).render()), task.schema)

    def raw(self, prompts: Column) -> Column:
        """The JSON text of each answer."""
        complete, attempts, rate, transient, strict = self.complete, self.attempts, self.per_second, self.transient, self.strict

        def usable(text) -> bool:
            import json

            try:
                json.loads(text)
                return True
            except (TypeError, ValueError):
                return False

        def ask(prompts):
            for batch in prompts:
                texts = batch.fillna("").tolist()
                out: list = [None] * len(texts)
                for i in range(attempts):
                    left = [k for k, x in enumerate(out) if not usable(x)]
                    if not left:
                        break
                    try:
                        found = complete([texts[k] for k in left])
                    except transient:
                        if i + 1 == attempts:
                            raise
                        time.sleep(0.1 * 2**i)
                        continue
                    if rate:
                        time.sleep(len(left) / rate)
                    if len(found) != len(left):
                        raise EndpointError(f"{len(left)} prompts got {len(found)} answers")
                    for k, x in zip(left, found):
                        out[k] = x
                bad = sum(not usable(x) for x in out)
                if bad and strict:
                    raise EndpointError(f"{bad} answers are not JSON after {attempts} attempts")
                yield type(batch)([x if usable(x) else None for x in out])

        from collections.abc import Iterator

        import pandas as pd

        ask.__annotations__ = {"prompts": Iterator[pd.Series], "return": Iterator[pd.Series]}
        return F.pandas_udf(ask, "string").asNondeterministic()(prompts)


@dataclass
class RequestCache:
    """Answers by model, schema and prompt in a table of the shared folder: each distinct request is asked once.

    The prompt holds the payload. Repeated prompts of one run are asked once too; runs that
    write at the same time may both ask, and the same answer then stands twice.
    """

    path: str = ""

    def map(self, df: DataFrame, task: Task, model: EndpointModel) -> DataFrame:
        """The same as a map with the model, with answers from the table where it has them."""
        spark = df.sparkSession
        if not self.path:
            self.path = scratch(spark, "requests")
        salt = f"{model.profile.name}|{task.schema.json()}|"
        asked = df.withColumn("__prompt", Template(task.prompt).render()).withColumn("__request", F.sha2(F.concat(F.lit(salt), F.col("__prompt")), 256))
        schema = "request string, answer string"
        folder = spark._jvm.org.apache.hadoop.fs.Path(self.path)
        if not folder.getFileSystem(spark._jsc.hadoopConfiguration()).exists(folder):
            spark.createDataFrame([], schema).write.parquet(self.path)
        known = spark.read.schema(schema).parquet(self.path)
        new = asked.select("__request", "__prompt").dropDuplicates(["__request"]).join(known, F.col("__request") == F.col("request"), "left_anti")
        new.select(F.col("__request").alias("request"), model.raw(F.col("__prompt")).alias("answer")).write.mode("append").parquet(self.path)
        answers = spark.read.schema(schema).parquet(self.path).groupBy("request").agg(F.max("answer").alias("__answer"))
        out = asked.join(answers, F.col("__request") == F.col("request"), "left").drop("request")
        return out.withColumn(task.name, conform(F.col("__answer"), task.schema)).drop("__prompt", "__request", "__answer")


def ledger(df: DataFrame, task: Task, model, calls_per_row: int = 1) -> DataFrame:
    """Calls, prompt and answer tokens and dollars of a task over a frame."""
    p = model.profile
    n_in = F.sum(F.least(token_count(F.col(task.content)), F.lit(p.context_tokens)).cast("long")) * calls_per_row
    n_out = F.sum(token_count(F.to_json(F.array(F.col(task.name)))).cast("long"))
    row = df.agg((F.count(F.lit(1)) * calls_per_row).alias("calls"), F.coalesce(n_in, F.lit(0)).alias("tokens_in"), F.coalesce(n_out, F.lit(0)).alias("tokens_out"))
    return row.withColumn("dollars", F.round((F.col("tokens_in") * p.price_in + F.col("tokens_out") * p.price_out) / 1e6, 6))
