"""Streams with state, user functions and relational shapes that users of the engine also need."""

import numpy as np
import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import operators as O
from ..functions.text import register_sql
from ..model import Task
from ..plans.directives import BY_ID, Hints
from ..plans.ir import GatherOp, Pipeline, SplitOp
from ..store import scratch
from ..streaming import drain, drain_deliveries, resolve_batches
from ..workloads import inputs as W
from .registry import SQL, query, toks
from .semantic import _LINES, _SPLIT
from .streams import _events


@query("SELECT user_id, count(*)::BIGINT AS n FROM (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s")
def stream_session(spark, sf):
    """Events of a user no more than six hours apart."""
    g = _events(spark, sf).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "6 hours"), "user_id").count()
    return drain(g.select("user_id", F.col("count").alias("n")), "complete")


@query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 6 HOUR")
def stream_interval_join(spark, sf):
    """Two streams: purchases up to six hours after a click of the same user."""
    clicks = _events(spark, sf).filter("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 day")
    bought = _events(spark, sf).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("v"), F.col("ts").alias("s")).withWatermark("s", "1 day")
    return drain(clicks.join(bought, F.expr("u = v AND s >= t AND s <= t + INTERVAL 6 HOURS")).select("click", "purchase"))


@query("WITH e AS (SELECT event_type = 'purchase' OR ts >= TIMESTAMP '2024-01-15' AS second, ts, date_trunc('day', ts)::TIMESTAMP AS d FROM events), w AS (SELECT max(ts) FILTER (NOT second) - INTERVAL 1 DAY AS before, max(ts) - INTERVAL 1 DAY AS after FROM e) SELECT strftime(d, '%Y-%m-%d') AS day, count(*)::BIGINT AS n FROM e, w WHERE (NOT second OR d + INTERVAL 1 DAY > before) AND d + INTERVAL 1 DAY <= after GROUP BY d")
def stream_late_data(spark, sf):
    """Events a day; the second delivery holds all from the fifteenth on and every purchase.

    Purchases of days that the watermark of the first delivery has closed are too late.
    """
    events = W.table(spark, sf, "events").select("event_type", F.col("ts").cast("timestamp").alias("ts"))
    second = (F.col("event_type") == "purchase") | (F.col("ts") >= F.lit("2024-01-15").cast("timestamp"))

    def per_day(stream):
        g = stream.withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).count()
        return g.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), F.col("count").alias("n"))

    return drain_deliveries([events.filter(~second), events.filter(second)], per_day)


@query("SELECT DISTINCT event_type AS value, upper(event_type) AS canonical FROM events")
def stream_resolve_batches(spark, sf):
    """Values that a mapping table does not have yet are resolved batch by batch."""
    path = scratch(spark, "mapping")
    resolve_batches(_events(spark, sf), "event_type", lambda c: F.upper(c), path)
    return spark.read.parquet(path)


@query(f"SELECT doc_id, len({toks('text')})::BIGINT AS n FROM documents")
def udf_pandas_tokens(spark, sf):
    """A scalar function of users over Arrow batches."""

    @F.pandas_udf("long")
    def count(texts: pd.Series) -> pd.Series:
        return texts.fillna("").str.count("[^ \n]+")

    return W.documents(spark, sf).select("doc_id", count("text").alias("n"))


@query(SQL["metric_kendall"])
def udaf_tau(spark, sf):
    """Kendall's tau as an aggregate function of users."""

    @F.pandas_udf("double")
    def tau(position: pd.Series, value: pd.Series) -> float:
        v = value.to_numpy()[np.argsort(position.to_numpy(), kind="stable")]
        n = len(v)
        if n < 2:
            return float("nan")
        above = np.sign(v[None, :] - v[:, None])
        return round(float(np.triu(above, 1).sum()) / (n * (n - 1) / 2), 6)

    r = W.reviews(spark, sf).withColumn("t", F.unix_micros(F.col("ts").cast("timestamp")))
    return r.groupBy("game").agg(tau("review_id", "t").alias("tau")).filter(~F.isnan("tau"))


@query(f"SELECT doc_id, split_chunk_num::INT AS n, text_chunk AS chunk FROM ({_SPLIT})")
def udtf_split(spark, sf):
    """The split operator as a table function in SQL."""

    @F.udtf(returnType="n int, chunk string")
    class SplitTokens:
        def eval(self, text: str, size: int):
            words = [w for w in (text or "").replace("\n", " ").split(" ") if w]
            for i in range(0, len(words), size):
                yield i // size + 1, " ".join(words[i : i + size])

    spark.udtf.register("sem_split", SplitTokens)
    W.documents(spark, sf).createOrReplaceTempView("__docs_to_split")
    return spark.sql("SELECT doc_id, c.n, c.chunk FROM __docs_to_split, LATERAL sem_split(text, 100) c")


_SIDES = "string_split(lower(lang || ' ' || source), ' ')"


@query(f"SELECT doc_id, round(len(list_intersect({_SIDES}, ['en', 'src1'])) / len(list_distinct(list_concat({_SIDES}, ['en', 'src1']))), 6) AS sim FROM documents")
def sql_udf_jaccard(spark, sf):
    """A SQL function that Catalyst inlines."""
    register_sql(spark)
    W.documents(spark, sf).createOrReplaceTempView("__docs_to_compare")
    return spark.sql("SELECT doc_id, round(sem_jaccard(lang || ' ' || source, 'en src1'), 6) AS sim FROM __docs_to_compare")


@query("SELECT lang, quantile_cont(n_chars, 0.5)::DOUBLE AS half, quantile_cont(n_chars, 0.9)::DOUBLE AS most FROM documents GROUP BY lang")
def rel_percentile(spark, sf):
    return W.table(spark, sf, "documents").groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("half"), F.percentile("n_chars", 0.9).alias("most"))


@query("SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS running FROM orders")
def rel_win_running(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return W.table(spark, sf, "orders").select("o_orderkey", F.round(F.sum("o_totalprice").over(w), 2).alias("running"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY d RANGE BETWEEN 1 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM (SELECT *, date_diff('day', TIMESTAMP '2024-01-01', ts) AS d FROM events)")
def rel_win_range(spark, sf):
    """Events of a user on the same day and the day before."""
    day = F.datediff(F.col("ts"), F.lit("2024-01-01").cast("date"))
    w = Window.partitionBy("user_id").orderBy("d").rangeBetween(-1, 0)
    return W.table(spark, sf, "events").withColumn("d", day).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@query("SELECT a.n_name AS x, b.n_name AS y FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_nationkey > b.n_nationkey")
def rel_join_theta(spark, sf):
    n = W.table(spark, sf, "nation")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, (F.col("a.n_regionkey") < F.col("b.n_regionkey")) & (F.col("a.n_nationkey") > F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("x"), F.col("b.n_name").alias("y"))


@query("SELECT o_custkey, o_orderkey, r::INT AS r FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def rel_topk_per_group(spark, sf):
    out = O.sem_rank(W.table(spark, sf, "orders"), ["o_custkey"], F.col("o_totalprice"), ["o_orderkey"], 2)
    return out.select("o_custkey", "o_orderkey", F.col("rank").alias("r"))


@query(f"SELECT doc_id, len(list_distinct(t))::BIGINT AS n_distinct, t[1] AS first, t[-1] AS last, list_contains(t, 'the') AS has_the, len(list_filter(t, lambda x: length(x) > 8))::BIGINT AS n_long FROM (SELECT doc_id, {toks('text')} AS t FROM documents) WHERE len(t) > 0")
def rel_array_functions(spark, sf):
    from ..functions.text import tokens

    d = W.documents(spark, sf).select("doc_id", tokens(F.col("text")).alias("t")).filter(F.size("t") > 0)
    return d.select("doc_id", F.size(F.array_distinct("t")).cast("long").alias("n_distinct"), F.get("t", F.lit(0)).alias("first"), F.element_at("t", -1).alias("last"), F.array_contains("t", "the").alias("has_the"), F.size(F.filter("t", lambda x: F.length(x) > 8)).cast("long").alias("n_long"))


@query("SELECT conv_id, count(DISTINCT turn)::BIGINT AS n, min(CASE WHEN turn = 1 THEN role END) AS second FROM conversations GROUP BY conv_id")
def rel_map_functions(spark, sf):
    c = W.table(spark, sf, "conversations").groupBy("conv_id", "turn").agg(F.min("role").alias("role"))
    m = c.groupBy("conv_id").agg(F.map_from_entries(F.collect_list(F.struct("turn", "role"))).alias("m"))
    return m.select("conv_id", F.size(F.map_keys("m")).cast("long").alias("n"), F.try_element_at("m", F.lit(1).cast("long")).alias("second"))


#: What marks a line of a document as part of its licence notes.
_NOTES = "|".join((W.CLAUSES["apache"].replace(".", "[.]"), W.CLAUSES["rights"], "CC BY-NC"))


@query(f"SELECT doc_id, (i + 1)::INT AS line, t[i + 1] AS piece FROM ({_LINES}), range(0, len(t)) r(i) WHERE NOT regexp_matches(t[i + 1], '{_NOTES}')")
def wl_reference_section(spark, sf):
    """Lines that only hold references (here: licence notes) are dropped after gather, before any further request."""
    wanted = Task("wanted", "text_chunk", lambda c: ~c.rlike(_NOTES), T.BooleanType())
    split, gather = SplitOp("text", 1, delimiter="\n"), GatherOp("text_chunk")
    kept = BY_ID["D4"].apply((gather,), Hints(relevant=wanted))[0]
    out = Pipeline((split, *kept), ("D4 chunk filtering",)).run(W.documents(spark, sf))
    return out.select("doc_id", F.col("split_chunk_num").alias("line"), F.col("text_chunk").alias("piece"))


_CALLS = "SELECT DISTINCT list_sort(list_distinct(list_slice(list_filter(string_split_regex(lower(text), '[^a-zà-ÿß0-9]+'), lambda w: length(w) >= 3), 1, 2))) AS k FROM documents WHERE doc_id % 50 = 0"


@query(f"WITH p AS (SELECT page_id, list_filter(string_split_regex(lower(regexp_replace(html, '<[^>]*>', ' ', 'g')), '[^a-zà-ÿß0-9]+'), lambda w: w <> '') AS w FROM pages), c AS ({_CALLS}) SELECT page_id, array_to_string(k, ' ') AS call FROM p JOIN c ON len(k) > 0 AND list_has_all(w, k)")
def wl_papers_funding(spark, sf):
    """Papers (pages) are projected to their words before they meet calls of two key words each.

    The calls are the stated few: key words of every 50th document, against all pages.
    """
    key = F.array_sort(F.array_distinct(F.slice(F.filter(F.split(F.lower("text"), "[^a-zà-ÿß0-9]+"), lambda w: F.length(w) >= 3), 1, 2)))
    calls = W.documents(spark, sf).filter("doc_id % 50 = 0").select(F.array_join(key, " ").alias("call")).distinct().filter("call != ''")
    bare = Task("words", "html", lambda c: F.regexp_replace(c, "<[^>]*>", " "), T.StringType())
    pages = O.sem_map(W.table(spark, sf, "pages"), bare, doc_id="page_id", drop_keys=("html",)).select("page_id", "words")
    return O.all_words_pairs(pages, "page_id", "words", calls, "call", "call")
