"""Measures and baselines on inputs whose answers SQL can give."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import baselines as B
from .. import measures as M
from .. import operators as O
from ..model import Task
from ..plans.ir import MapOp, Pipeline
from ..workloads import inputs as W
from .registry import query, spans, toks
from .semantic import _PASSAGE_SQL, CONTACT_SQL, flat, passage_pairs

BASE = spans(CONTACT_SQL)


@query(
    f"WITH g AS ({BASE}), p AS (SELECT * FROM g WHERE doc_id % 3 <> 0 UNION ALL SELECT doc_id, 'ip', 'made up' FROM g WHERE type = 'ip' AND doc_id % 2 = 0 GROUP BY doc_id), "
    "u AS (SELECT doc_id, (SELECT count(*) FROM p WHERE p.doc_id = x.doc_id) AS np, (SELECT count(*) FROM g WHERE g.doc_id = x.doc_id) AS ng, (SELECT count(*) FROM p SEMI JOIN g ON p.doc_id = g.doc_id AND p.type = g.type AND lower(p.span) = lower(g.span) WHERE p.doc_id = x.doc_id) AS tp FROM (SELECT doc_id FROM p UNION SELECT doc_id FROM g) x), "
    "v AS (SELECT CASE WHEN np > 0 THEN tp / np ELSE 0 END AS p, CASE WHEN ng > 0 THEN tp / ng ELSE 0 END AS r FROM u) "
    "SELECT round(avg(p), 6) AS precision, round(avg(r), 6) AS recall, round(avg(CASE WHEN p + r > 0 THEN 2 * p * r / (p + r) ELSE 0 END), 6) AS f1 FROM v"
)
def metric_span_prf(spark, sf):
    """A third of the documents is not predicted and some have an invented span."""
    gold = W.gold_spans(W.documents(spark, sf), W.CONTACTS)
    made = gold.filter("type = 'ip' and doc_id % 2 = 0").select("doc_id").distinct().select("doc_id", F.lit("ip").alias("type"), F.lit("made up").alias("span"))
    return M.averaged(M.span_prf(gold.filter("doc_id % 3 != 0").unionByName(made), gold))


@query(f"SELECT round(avg(length(span)), 6) AS avg_chars FROM ({BASE})")
def metric_avg_chars(spark, sf):
    return M.average_chars(W.gold_spans(W.documents(spark, sf), W.CONTACTS))


@query(f"SELECT round(avg((type <> 'email')::INT), 6) AS outside FROM ({BASE})")
def metric_outside_list(spark, sf):
    return M.rate(W.gold_spans(W.documents(spark, sf), W.CONTACTS), ~F.col("type").isin("email"), "outside")


@query("SELECT round(avg((d.doc_id IS NULL)::INT), 6) AS hallucination FROM (SELECT event_id AS doc_id FROM events) e LEFT JOIN documents d USING (doc_id)")
def metric_missing_ids(spark, sf):
    return M.missing_rate(W.table(spark, sf, "events").select(F.col("event_id").alias("doc_id")), W.documents(spark, sf), ["doc_id"])


@query("SELECT d.source AS game, round((2.0 * sum((b.ts > a.ts)::INT - (b.ts < a.ts)::INT)) / (max(n) * (max(n) - 1)), 6) AS tau FROM (SELECT source, doc_id, ts, count(*) OVER (PARTITION BY source) AS n FROM documents JOIN labels USING (doc_id) JOIN events ON event_id = doc_id) a JOIN (SELECT source, doc_id, ts FROM documents JOIN labels USING (doc_id) JOIN events ON event_id = doc_id) b ON a.source = b.source AND a.doc_id < b.doc_id JOIN (SELECT DISTINCT source FROM documents) d ON d.source = a.source GROUP BY d.source HAVING max(n) > 1")
def metric_kendall(spark, sf):
    r = W.reviews(spark, sf)
    return M.kendall_tau(r, ["game"], "review_id", "ts").filter("tau is not null")


@query()
def metric_kendall_large(spark, sf):
    """Merge counting against the pairwise measure: the number of groups where they differ is 0."""
    r = W.reviews(spark, sf).withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    a, b = M.kendall_tau(r, ["game"], "review_id", "t"), M.kendall_tau_large(r, ["game"], "review_id", "t").withColumnRenamed("tau", "tau2")
    return a.join(b, "game").agg(F.sum((~F.col("tau").eqNullSafe(F.col("tau2"))).cast("int")).alias("different"))


@query(f"WITH h AS ({_PASSAGE_SQL}), g AS (SELECT doc_id, count(*) AS r FROM h GROUP BY doc_id) SELECT round(avg(least(1, r) / least(1, r)), 6) AS rp_at_1, round(avg(least(5, r) / least(5, r)), 6) AS rp_at_5 FROM g")
def metric_rank_precision(spark, sf):
    gold = passage_pairs(spark, sf)
    ranked = base_substring_rank(spark, sf)
    hits = ranked.select("doc_id", "item_id", "rank")
    return M.rank_precision(hits, gold.join(hits.select("doc_id", "item_id"), ["doc_id", "item_id"]), "doc_id", "item_id", (1, 5))


@query(f"SELECT round(avg((regexp_matches(text, '{W.CLAUSES['abuse']}')::INT = toxic)::INT), 6) AS accuracy FROM documents JOIN labels USING (doc_id)")
def metric_label_accuracy(spark, sf):
    pred = W.documents(spark, sf).select("doc_id", F.col("text").rlike(W.CLAUSES["abuse"]).cast("int").alias("answer"))
    return M.label_accuracy(pred, W.table(spark, sf, "labels"), ["doc_id"], "answer", "toxic")


@query("WITH s AS (SELECT DISTINCT n_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)) SELECT round(avg((n_nationkey < 20)::INT), 6) AS precision, count(*)::BIGINT AS distinct_found FROM s JOIN nation USING (n_name)")
def metric_verified_precision(spark, sf):
    s = W.sightings(spark, sf).withColumn("text", F.concat("raw", F.lit(" seen in "), "place"))
    g = W.table(spark, sf, "nation").filter("n_nationkey < 20")
    return M.verified_precision(s.select("o_orderkey", "place"), s, ["o_orderkey"], "place", "text", g, "n_name")


@query(f"SELECT round(avg((len({toks('text')}) > 100)::INT), 6) AS long_enough, round(avg(contains(text, '.')::INT), 6) AS has_sentence FROM documents")
def metric_criteria(spark, sf):
    from ..functions.text import token_count

    return M.criterion_pass(W.documents(spark, sf), {"long_enough": token_count(F.col("text")) > 100, "has_sentence": F.contains("text", F.lit("."))})


@query("WITH j AS (SELECT quality = 1 AS a, toxic = 0 AS b FROM labels), r AS (SELECT avg((a = b)::DOUBLE) AS po, avg(a::DOUBLE) AS pa, avg(b::DOUBLE) AS pb FROM j) SELECT round(po, 6) AS agreement, round((po - (pa * pb + (1 - pa) * (1 - pb))) / (1 - (pa * pb + (1 - pa) * (1 - pb))), 6) AS kappa FROM r")
def metric_agreement(spark, sf):
    j = W.table(spark, sf, "labels").select((F.col("quality") == 1).cast("int").alias("a"), (F.col("toxic") == 0).cast("int").alias("b"))
    return M.agreement(j, "a", "b")


@query("SELECT 1.0::DOUBLE AS pair_precision, round(sum(s * (s - 1) / 2) / max(t), 6) AS pair_recall FROM (SELECT n_regionkey, n_nationkey % 2 AS h, count(*) AS s FROM nation GROUP BY ALL), (SELECT sum(c * (c - 1) / 2) AS t FROM (SELECT count(*) AS c FROM nation GROUP BY n_regionkey))")
def metric_pair_prf(spark, sf):
    n = W.table(spark, sf, "nation")
    made = n.select("n_name", F.concat_ws("-", "n_regionkey", F.col("n_nationkey") % 2).alias("cluster"))
    return M.pair_prf(made, n.select("n_name", "n_regionkey"), "n_name", "cluster", "n_regionkey")


@query(f"WITH g AS ({_PASSAGE_SQL}), n AS (SELECT (SELECT count(*) FROM documents) * (SELECT count(*) FROM benchmark) AS c) SELECT 1.0::DOUBLE AS recall, (SELECT count(*) FROM g) > 0 AS some FROM n")
def metric_blocking(spark, sf):
    c = passage_pairs(spark, sf)
    gold = O.equijoin(W.documents(spark, sf), W.table(spark, sf, "benchmark").withColumnRenamed("text", "label"), "doc_id", "item_id", c, lambda m: F.contains("text", "label")).select("doc_id", "item_id")
    return M.blocking_stats(c, gold, ["doc_id", "item_id"], F.lit(1)).select("recall", (F.col("recall") > 0).alias("some"))


@query("SELECT round(avg((toxic > 0)::INT), 6) AS better_toxic, round(0.631 / 0.47 - 1, 6) AS gain FROM labels")
def metric_share_better(spark, sf):
    return M.share_better(W.table(spark, sf, "labels"), "toxic", 0).withColumn("gain", M.improvement(F.lit(0.631), F.lit(0.47)))


@query("SELECT (SELECT count(*) FROM documents WHERE lang = 'en') / (SELECT count(*) FROM documents) AS selectivity")
def metric_selectivity(spark, sf):
    return W.documents(spark, sf).agg((F.sum((F.col("lang") == "en").cast("int")) / F.count(F.lit(1))).alias("selectivity"))


@query(BASE)
def base_as_written(spark, sf):
    return flat(B.as_written(Pipeline((MapOp(W.extraction(W.CONTACTS)),)), W.documents(spark, sf)))


@query(BASE)
def base_string_map(spark, sf):
    return flat(B.string_map(W.documents(spark, sf), W.extraction(W.CONTACTS)).filter("not parse_failed"))


@query(BASE)
def base_doc_query(spark, sf):
    return flat(B.doc_query(W.documents(spark, sf), W.extraction(W.CONTACTS)))


@query("SELECT doc_id, nullif(regexp_extract(text, '[A-Za-z0-9_.+-]+@[A-Za-z0-9.-]+[A-Za-z]'), '') AS email, nullif(regexp_extract(text, '[0-9]+[.][0-9]+[.][0-9]+[.][0-9]+'), '') AS ip FROM documents")
def base_schema_convert(spark, sf):
    return B.schema_convert(W.documents(spark, sf), "text", {"email": "address of a mailbox", "ip": "dotted number"}).select("doc_id", "email", "ip")


@query()
def base_best_sentence(spark, sf):
    types = spark.createDataFrame([("license", "licensed under the apache license, version 2"), ("rights", "all rights reserved")], "type string, description string")
    return B.best_sentence(W.documents(spark, sf), "doc_id", "text", types, 0.5)


@query(f"SELECT source AS game, doc_id AS review_id, negative, rank::INT AS rank FROM (SELECT source, doc_id, regexp_matches(text, '{W.CLAUSES['abuse']}') AS negative, row_number() OVER (PARTITION BY source, regexp_matches(text, '{W.CLAUSES['abuse']}') ORDER BY doc_id) AS rank FROM documents JOIN labels USING (doc_id) JOIN events ON event_id = doc_id) WHERE rank <= 10")
def base_lexicon_reviews(spark, sf):
    return B.lexicon_reviews(W.reviews(spark, sf), "game", "review_id", "text", W.LEXICON)


@query("WITH s AS (SELECT o_orderkey, n_name || '; passed by ' || 'NATION_' || (o_orderkey % 31) || '; on ' || o_orderkey AS t FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)) SELECT DISTINCT o_orderkey, n_name AS place FROM s JOIN nation ON contains(t, n_name) AND list_contains(string_split_regex(lower(t), '[^a-z0-9]+'), lower(string_split(n_name, '_')[2]))")
def base_pattern_locations(spark, sf):
    """Texts with the customer's nation, a second place that the gazetteer may not know, and a number."""
    other = F.concat(F.lit("NATION_"), (F.col("o_orderkey") % 31).cast("string"))
    s = W.sightings(spark, sf).withColumn("text", F.concat("place", F.lit("; passed by "), other, F.lit("; on "), F.col("o_orderkey").cast("string")))
    return B.pattern_locations(s, ["o_orderkey"], "text", W.table(spark, sf, "nation"), "n_name")


@query(f"SELECT p.doc_id, p.item_id, row_number() OVER (PARTITION BY p.doc_id ORDER BY length(b.text) DESC, p.item_id)::INT AS rank FROM ({_PASSAGE_SQL}) p JOIN benchmark b USING (item_id)")
def base_substring_rank(spark, sf):
    b = W.table(spark, sf, "benchmark").withColumnRenamed("text", "label")
    return B.substring_rank(W.documents(spark, sf), "doc_id", "text", passage_pairs(spark, sf), b, "item_id", "label").select("doc_id", "item_id", "rank")


@query()
def base_map_search_filter(spark, sf):
    """Ranked passages by hashed vectors of the text, 49 nearest, then the containment filter."""
    d, b = W.documents(spark, sf).select("doc_id", "text"), W.table(spark, sf, "benchmark").withColumnRenamed("text", "label")
    left = d.join(O.hashed_vectors(d, "doc_id", "text"), "doc_id")
    right = b.join(O.hashed_vectors(b, "item_id", "label"), "item_id")
    return O.map_search_filter(left, "doc_id", right, "item_id", "vector", 49, F.contains("text", "label")).select("doc_id", "item_id", "rank")


@query(f"SELECT d.doc_id, len({toks('d.text')})::BIGINT AS n FROM documents d ORDER BY n DESC, doc_id LIMIT 20")
def semantic_sort_topk(spark, sf):
    from ..functions.text import token_count

    task = Task("n", "text", lambda c: token_count(c).cast("long"), T.LongType())
    return O.sem_sort(O.sem_map(W.documents(spark, sf), task, drop_keys=("text",)), F.col("n"), ["doc_id"], 20).select("doc_id", "n")
