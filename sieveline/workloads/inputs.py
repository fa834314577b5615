"""Collections derived from the given tables; all of them are lazy and deterministic."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import token_count
from ..model import Task

# Clause types and the patterns that find them (Java and RE2 agree on them).
CLAUSES = {
    "abuse": "trash|clown|idiot|scum|worthless|moron|pathetic|loser|stupid|disgusting",
    "apache": "Licensed under the Apache License, Version 2.0.",
    "cc": "CC BY-NC 4.0",
    "email": "[A-Za-z0-9_.+-]+@[A-Za-z0-9.-]+[A-Za-z]",
    "ip": "[0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}",
    "phone": "[(][0-9]{3}[)] [0-9]{3}-[0-9]{4}",
    "rights": "[Aa]ll rights reserved",
    "secret": "token = .[0-9a-f]+",
}
#: Types whose spans hold no white space, so that no chunk border cuts them.
CONTACTS = ["email", "ip"]
LEXICON = CLAUSES["abuse"].split("|")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def items(text: Column, types: list[str]) -> Column:
    """Sorted distinct (type, span) structs of a text."""

    def of(kind: str) -> Column:
        # Only a line feed ends a line, as for RE2: otherwise Java's dot stops at \r, \x85, \u2028 and \u2029 too.
        found = F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit("(?d)" + CLAUSES[kind]), F.lit(0))
        return F.transform(found, lambda m: F.struct(F.lit(kind).alias("type"), m.alias("span")))

    found = [of(t) for t in types]
    return F.array_sort(F.array_distinct(F.concat(*found)))


def extraction(types: list[str], name: str = "items", content: str = "text", asks: int | None = None) -> Task:
    prompt = "List every " + ", ".join(types) + " in this text:\n{{ input." + content + " }}"
    parts = tuple(extraction([t], f"only_{t}", content) for t in types) if len(types) > 1 else ()
    return Task(name, content, lambda c: items(c, types), prompt=prompt, asks=asks or len(types), parts=parts)


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")


def gold_spans(docs: DataFrame, types: list[str]) -> DataFrame:
    return docs.select("doc_id", F.explode(items(F.col("text"), types)).alias("x")).select("doc_id", "x.type", "x.span")


def dossiers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One long document per source: its texts in order, each after a marker."""
    d = documents(spark, sf_dir).withColumn("part", F.concat(F.lit("[[doc:"), F.col("doc_id").cast("string"), F.lit("]] "), F.col("text")))
    rows = F.array_sort(F.collect_list(F.struct("doc_id", "part")))
    return d.groupBy(F.col("source").alias("doc_id")).agg(F.array_join(F.transform(rows, lambda r: r["part"]), "\n").alias("text"))


def alias(user: Column, event: Column) -> Column:
    """One of four spellings of a user, chosen by the event."""
    n, pick = user.cast("string"), F.conv(F.substring(F.md5(event.cast("string")), 1, 4), 16, 10).cast("long") % 4
    return F.when(pick == 0, F.concat(F.lit("user "), n)).when(pick == 1, F.concat(F.lit("USER-"), n)).when(pick == 2, F.concat(F.lit("u"), n)).otherwise(F.concat(F.lit("User #"), n))


def daily_logs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One long document per day of events: a line an event, in hash order."""
    e = table(spark, sf_dir, "events")
    line = F.concat_ws(" ; ", F.col("event_id").cast("string"), F.date_format("ts", "yyyy-MM-dd HH:mm:ss"), alias(F.col("user_id"), F.col("event_id")), F.col("event_type"), F.concat(F.lit("k="), F.get_json_object("props", "$.k")))
    rows = F.array_sort(F.collect_list(F.struct(F.md5(F.col("event_id").cast("string")).alias("h"), line.alias("line"))))
    return e.groupBy(F.date_format("ts", "yyyy-MM-dd").alias("doc_id")).agg(F.array_join(F.transform(rows, lambda r: r["line"]), "\n").alias("text"))


def reviews(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(game, review_id, ts, text, toxic): labelled documents with the time of the event of their id."""
    d, l, e = (table(spark, sf_dir, n) for n in ("documents", "labels", "events"))
    return d.join(l, "doc_id").join(e.select(F.col("event_id").alias("doc_id"), "ts"), "doc_id").select(F.col("source").alias("game"), F.col("doc_id").alias("review_id"), "ts", "text", "toxic")


def sightings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(o_orderkey, raw, clean, place): an order's first part name in one of five spellings and its customer's nation."""
    o, li, p, c, n = (table(spark, sf_dir, x) for x in ("orders", "lineitem", "part", "customer", "nation"))
    first = li.groupBy("l_orderkey").agg(F.min("l_partkey").alias("p_partkey"))
    j = o.join(first, o["o_orderkey"] == first["l_orderkey"]).join(p.select("p_partkey", "p_name"), "p_partkey")
    j = j.join(c.select("c_custkey", "c_nationkey"), j["o_custkey"] == c["c_custkey"]).join(n, F.col("c_nationkey") == F.col("n_nationkey"))
    pick = F.conv(F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 4), 16, 10).cast("long") % 5
    name = F.col("p_name")
    raw = F.when(pick == 0, name).when(pick == 1, F.upper(name)).when(pick == 2, F.concat(F.lit("item: "), name)).when(pick == 3, F.concat(F.lit("The "), name)).otherwise(F.concat(name, F.lit("s")))
    return j.select("o_orderkey", raw.alias("raw"), name.alias("clean"), F.col("n_name").alias("place"))


def fold_name(x: Column) -> Column:
    """What the five spellings of a sighting have in common."""
    return F.regexp_replace(F.regexp_replace(F.lower(x), "^(item: |the )", ""), "s$", "")


def order_articles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(o_orderkey, text, names): short articles that name every part of an order."""
    o, li, p = (table(spark, sf_dir, x) for x in ("orders", "lineitem", "part"))
    lines = li.join(p.select(F.col("p_partkey").alias("l_partkey"), "p_name"), "l_partkey")
    lines = lines.join(o.select(F.col("o_orderkey").alias("l_orderkey")), "l_orderkey", "left_semi")
    names = F.array_sort(F.collect_set("p_name"))
    # One name in four has a word more after its first, so that it does not stand there as it is listed.
    odd = lambda x: F.conv(F.substring(F.md5(F.concat_ws("|", F.col("o_orderkey").cast("string"), x)), 1, 4), 16, 10).cast("long") % 4 == 0
    written = F.transform("names", lambda x: F.when(odd(x), F.regexp_replace(x, "^([^ ]+) ", "$1 spare ")).otherwise(x))
    out = lines.groupBy(F.col("l_orderkey").alias("o_orderkey")).agg(names.alias("names"))
    return out.withColumn("text", F.concat(F.lit("the parcel held "), F.array_join(written, " and then "), F.lit(" .")))


def ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(region, pos, line, level, header): lines of a report whose headers nest region, nation, customer."""
    r, n, c = (table(spark, sf_dir, x) for x in ("region", "nation", "customer"))
    j = r.join(n, r["r_regionkey"] == n["n_regionkey"]).join(c, F.col("n_nationkey") == F.col("c_nationkey"))
    top = r.select(F.col("r_name").alias("region"), F.struct(F.lit(-1).alias("n"), F.lit(-1).cast("long").alias("c")).alias("pos"), F.lit(1).alias("level"), F.concat(F.lit("# "), F.col("r_name")).alias("line"))
    mid = j.select(F.col("r_name").alias("region"), F.struct(F.col("n_nationkey").alias("n"), F.lit(-1).cast("long").alias("c")).alias("pos"), F.lit(2).alias("level"), F.concat(F.lit("## "), F.col("n_name")).alias("line")).distinct()
    low = j.select(F.col("r_name").alias("region"), F.struct(F.col("n_nationkey").alias("n"), F.col("c_custkey").alias("c")).alias("pos"), F.lit(3).alias("level"), F.concat(F.lit("### "), F.col("c_name")).alias("line"))
    return top.unionByName(mid).unionByName(low)


#: A review in a game's document: its id, time and words up to the next one.
REVIEW = r"\[\[review:([0-9]+) ([0-9-]+ [0-9:]+)\]\]([^\[]*)"


def game_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One long document per game: its reviews in hash order, each after a marker with id and time."""
    r = reviews(spark, sf_dir)
    body = F.replace(F.replace(F.coalesce("text", F.lit("")), F.lit("["), F.lit("(")), F.lit("\n"), F.lit(" "))
    one = F.concat(F.lit("[[review:"), F.col("review_id").cast("string"), F.lit(" "), F.date_format("ts", "yyyy-MM-dd HH:mm:ss"), F.lit("]] "), body)
    rows = F.array_sort(F.collect_list(F.struct(F.md5(F.col("review_id").cast("string")).alias("h"), one.alias("one"))))
    return r.groupBy("game").agg(F.array_join(F.transform(rows, lambda x: x["one"]), " ").alias("text"))


def first_reviews(items: Column, k: int = 10) -> Column:
    """The first k negative and the first k positive reviews in order of time."""

    def of(kind):
        mine = F.transform(F.filter(items, lambda x: x["type"] == kind), lambda x: F.struct(x["at"].alias("at"), x["span"].alias("span")))
        return F.transform(F.slice(F.array_sort(F.array_distinct(mine)), 1, k), lambda x: F.struct(F.lit(kind).alias("type"), x["span"].alias("span"), x["at"].alias("at")))

    return F.concat(of("negative"), of("positive"))


def reviews_in(text: Column) -> Column:
    """(type, span, at) of each review of a document: sentiment by the word list, id and time."""
    ids, times, bodies = (F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(REVIEW), F.lit(k)) for k in (1, 2, 3))
    pairs = F.zip_with(ids, times, lambda i, t: F.struct(i.alias("span"), t.alias("at")))
    kind = lambda b: F.when(b.rlike(CLAUSES["abuse"]), "negative").otherwise("positive")
    return F.zip_with(pairs, bodies, lambda p, b: F.struct(kind(b).alias("type"), p["span"].alias("span"), p["at"].alias("at")))


def with_sizes(df: DataFrame, text: str = "text") -> DataFrame:
    return df.withColumn("n_tokens", token_count(F.col(text)))
