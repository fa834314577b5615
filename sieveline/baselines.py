"""The programs that optimised plans are compared with."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .functions.prompts import conform
from .functions.text import jaccard, truncate_middle
from .model import PerfectModel, Task
from .operators import all_words_pairs, sem_map
from .plans.ir import Context, Pipeline
from .store import small, stored


def as_written(plan: Pipeline, df: DataFrame, model=None, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """The user's operators, one call each; over-long input loses its middle."""
    model = model or PerfectModel()
    if model.profile.context_tokens < 10**9:
        df = df.withColumn(text, truncate_middle(F.col(text), model.profile.context_tokens))
    return plan.run(df, Context(model, doc_id))


def string_map(df: DataFrame, task: Task, model=None, doc_id: str = "doc_id") -> DataFrame:
    """One map whose answer is a string that has to be parsed; ``parse_failed`` marks what does not."""
    raw = sem_map(df, task, model or PerfectModel(), doc_id).withColumn("__raw", F.to_json(task.name))
    out = raw.withColumn(task.name, conform(F.col("__raw"), task.schema))
    return out.withColumn("parse_failed", F.col(task.name).isNull()).drop("__raw")


def doc_query(df: DataFrame, task: Task, model=None, doc_id: str = "doc_id") -> DataFrame:
    """One query for the fields and types of the schema over each document, asked one type at a time and
    normalised like :func:`string_map`; answers of all queries are united."""
    from functools import reduce

    parts = list(task.parts) or [task]
    for i, p in enumerate(parts):
        df = string_map(df, p.on(p.content, f"__query{i}"), model, doc_id).withColumnRenamed("parse_failed", f"__failed{i}")
    found = F.concat(*[F.coalesce(F.col(f"__query{i}"), F.array().cast(task.schema)) for i in range(len(parts))])
    failed = reduce(lambda a, b: a & b, [F.col(f"__failed{i}") for i in range(len(parts))])
    out = df.withColumn(task.name, F.array_sort(F.array_distinct(found))).withColumn("parse_failed", failed)
    return out.drop(*[f"__{k}{i}" for k in ("query", "failed") for i in range(len(parts))])


#: What field descriptions compile to in the schema-driven program.
CODE = {"address of a mailbox": "[A-Za-z0-9_.+-]+@[A-Za-z0-9.-]+[A-Za-z]", "dotted number": "[0-9]+[.][0-9]+[.][0-9]+[.][0-9]+"}


def schema_convert(df: DataFrame, text: str, fields: dict[str, str]) -> DataFrame:
    """Fields with descriptions become code that takes the first match of each document; no model runs."""
    return df.select("*", *[F.nullif(F.regexp_extract(F.col(text), CODE[d], 0), F.lit("")).alias(n) for n, d in fields.items()])


def best_sentence(df: DataFrame, doc_id: str, text: str, descriptions: DataFrame, threshold: float) -> DataFrame:
    """Per document and type the sentence most similar to the type's description, if above the threshold."""
    s = df.select(doc_id, F.explode(F.array_distinct(F.filter(F.split(text, "[.\n]"), lambda x: F.trim(x) != ""))).alias("span"))
    s = s.withColumn("span", F.trim("span"))
    # A sentence meets a description by their words; the few descriptions are broadcast after a check.
    by_word = small(descriptions.withColumn("__w", F.explode(F.array_distinct(F.split(F.lower("description"), " +")))))
    pairs = s.withColumn("__w", F.explode(F.array_distinct(F.split(F.lower("span"), " +")))).join(by_word, "__w").drop("__w").distinct()
    pairs = pairs.withColumn("sim", F.round(jaccard(F.col("span"), F.col("description")), 6)).filter(F.col("sim") > threshold)
    return pairs.groupBy(doc_id, "type").agg(F.max_by("span", F.struct("sim", "span")).alias("span"), F.max("sim").alias("sim"))


def lexicon_reviews(df: DataFrame, group: str, review: str, text: str, lexicon: list[str], k: int = 10) -> DataFrame:
    """Sentiment by a word list: the first k negative and first k other reviews of each group."""
    negative = F.col(text).rlike("|".join(lexicon))
    w = Window.partitionBy(group, "negative").orderBy(review)
    return df.select(group, review, negative.alias("negative")).withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def pattern_locations(df: DataFrame, keys: list[str], text: str, gazetteer: DataFrame, place: str) -> DataFrame:
    """Places of the gazetteer that stand in the text: both meet by their words, then the text is searched."""
    g = gazetteer.select(F.col(place).alias("place")).distinct()
    rows = stored(df.select(*keys, text), "texts").withColumn("__key", F.to_json(F.struct(*keys)))
    pairs = all_words_pairs(rows, "__key", text, g, "place", "place").distinct()
    hits = rows.join(pairs, "__key").filter(F.contains(F.col(text), F.col("place")))
    return hits.select(*keys, "place").distinct()


def substring_rank(left: DataFrame, left_id: str, text: str, candidates: DataFrame, right: DataFrame, right_id: str, label: str) -> DataFrame:
    """Exact substring labels, longest first, over blocked pairs."""
    hits = candidates.join(left.select(left_id, text), left_id).join(right.select(right_id, label), right_id).filter(F.contains(F.col(text), F.col(label)))
    w = Window.partitionBy(left_id).orderBy(F.length(label).desc(), right_id)
    return hits.select(left_id, right_id, label).withColumn("rank", F.row_number().over(w))


def random_middle(text: Column, budget: int) -> Column:
    """Middle truncation, which for unordered reviews samples them at random."""
    return truncate_middle(text, budget)
