"""Corpus pipeline: language ID, near duplicates, personal data, mixing, tokens.

Every stage takes (spark, docs, sf_dir), works on all rows of docs and returns a frame
that is written as Parquet and read again as the next one's docs. All stages but the last
return the columns of ``documents``, and further columns of docs are left out. An empty
table gives an empty one in every stage. Defined results for null, empty and repeated rows:

* language ID rejects a document without text or letter; repeated rows all stay;
* near duplicates keeps one row of each id and text that leads a group; a document without
  words is linked with nothing and stays, and so does each different text of an id;
* personal data leaves null texts null, with ``n_chars`` 0;
* mixing takes no document without words, and treats repeated rows as documents of their own;
* byte BPE gives null and empty texts no ids.

Very long texts go through every stage whole.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sieveline.llm import bpe, jaccard, langid, mixing, pii
from sieveline.llm.common import small_batches, unpacked
from sieveline.llm.queries import PATTERN, VOCABULARY
from sieveline.store import scratch

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Least language score of a document that stays: half of one plus a cosine of zero.
MIN_SCORE = 0.5


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in a recognised language, ``lang`` being what was recognised."""
    small_batches(spark)
    model = langid.learn(docs.filter(~langid.split(F.col("doc_id"))))
    found = langid.identify(docs.select(*COLUMNS), model)
    good = found.filter((F.col("lang_pred") != "und") & (F.col("score") >= MIN_SCORE))
    return good.withColumn("lang", F.col("lang_pred")).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near copies."""
    small_batches(spark)
    groups = jaccard.near_duplicates(docs.select("doc_id", "text"))
    leads = groups.filter(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("lead")).distinct()
    kept = docs.join(leads, docs["doc_id"].eqNullSafe(leads["lead"]), "left_semi")
    return kept.withColumn("th", F.xxhash64("text")).dropDuplicates(["doc_id", "th"]).select(*COLUMNS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose personal data is replaced by the names of its kinds."""
    clean = pii.redact(docs.select(*COLUMNS))
    return clean.withColumn("n_chars", F.coalesce(F.length("text"), F.lit(0)).cast("long")).select(*COLUMNS)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix in training order: each document as often as at least half of its words are taken."""
    small_batches(spark)
    copies = mixing.mix(docs.select(*COLUMNS), carry=True).select("row", "size", F.inline("positions"))
    taken = copies.filter(2 * F.col("n_words") >= F.col("size")).orderBy("position", "row.doc_id", "epoch")
    return taken.select("row.*").withColumn("text", unpacked(F.col("text"))).select(*COLUMNS)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens and the digests of ids and decoded bytes."""
    small_batches(spark)
    return bpe.digests(bpe.round_trip(docs.select("doc_id", "text"), VOCABULARY, PATTERN))


STAGES = [
    ("language_id", language),
    ("near_duplicates", near_duplicates),
    ("personal_data", personal_data),
    ("mixing", mix),
    ("byte_bpe", tokens),
]
#: Language ID, wide joins and the encoder are not SQL; the tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir."""
    folder = scratch(spark, "corpus")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for i, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if i == len(STAGES) - 1:
            return out
        out.write.parquet(f"{folder}/{i}-{name}")
        docs = spark.read.parquet(f"{folder}/{i}-{name}")
    return docs
