"""Each rewrite directive against the operator that it replaces, and the optimizer."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import operators as O
from ..functions.text import token_count, tokens
from ..model import PerfectModel, Profile, SimulatedModel, Task
from ..plans.directives import BY_ID, Hints, first_tokens, union_items
from ..plans.ir import Context, EquijoinOp, GatherOp, MapOp, Pipeline, ProjectOp, ReduceOp, SplitOp, UnnestOp
from ..plans.optimizer import RuleGenerator, Search, duel_plans, extraction_validator, optimize, pareto, plan_scores, rate_plans, run_adaptive
from ..store import stored
from ..workloads import inputs as W
from .registry import query, spans, toks
from .semantic import _LINES, _PASSAGE_SQL, _SPLIT, CONTACT_SQL, flat

BASE = spans(CONTACT_SQL)
HINTS = Hints(chunk_tokens=(100,), columns=("doc_id", "text", "lang", "source"))


def _first(directive: str, ops, hints, pick: int = 0) -> Pipeline:
    made = BY_ID[directive].apply(tuple(ops), hints)
    return Pipeline(made[pick], (directive,))


@query(BASE)
def d01_chunked_extract(spark, sf):
    """Split, gather, map, reduce instead of one map; no contact is cut, so the answer is the same."""
    plan = _first("D1", [MapOp(W.extraction(W.CONTACTS))], HINTS, 1)
    return flat(plan.run(W.documents(spark, sf)))


@query(f"SELECT s.doc_id, s.split_chunk_num::INT AS split_chunk_num, array_to_string(list_slice({toks('d.text')}, 1, 5), ' ') AS front FROM ({_SPLIT}) s JOIN documents d USING (doc_id)")
def d02_metadata(spark, sf):
    plan = _first("D2", [SplitOp("text", 100)], replace(HINTS, metadata=first_tokens("text", 5)))
    return plan.run(W.documents(spark, sf)).select("doc_id", "split_chunk_num", "front")


@query(f"SELECT doc_id, split_chunk_num::INT AS split_chunk_num, (split_chunk_num - 1)::INT AS summaries FROM ({_SPLIT})")
def d03_summaries(spark, sf):
    """Summaries of all earlier chunks are shown: their number is counted in the rendered text."""
    summary = Task("summary", "text_chunk", lambda c: F.concat(F.lit("<s>"), F.get(tokens(c), F.lit(0))), T.StringType())
    plan = _first("D3", [SplitOp("text", 100), GatherOp("text_chunk")], replace(HINTS, summary=summary))
    out = plan.run(W.documents(spark, sf))
    return out.select("doc_id", "split_chunk_num", (F.size(F.split("text_chunk_rendered", "<s>")) - 1).alias("summaries"))


@query(f"SELECT doc_id, split_chunk_num::INT AS split_chunk_num, (split_chunk_num > 1)::BOOLEAN AS has_context FROM ({_SPLIT}) WHERE contains(text_chunk, '@')")
def d04_chunk_filter(spark, sf):
    """Irrelevant chunks go after gather, so that they still serve as context."""
    relevant = Task("relevant", "text_chunk", lambda c: F.contains(c, F.lit("@")), T.BooleanType())
    chunks = Pipeline((SplitOp("text", 100),)).run(W.documents(spark, sf))
    plan = _first("D4", [GatherOp("text_chunk", O.Peripheral(O.Side(tail=1)))], replace(HINTS, relevant=relevant))
    return plan.run(chunks).select("doc_id", "split_chunk_num", F.contains("text_chunk_rendered", F.lit("<previous>")).alias("has_context"))


@query(BASE)
def d05_flatten(spark, sf):
    task = W.extraction(W.CONTACTS, content="text_chunk")
    chunks = Pipeline((SplitOp("text", 100),)).run(W.documents(spark, sf))
    plan = _first("D5", [GatherOp("text_chunk"), MapOp(task)], HINTS)
    return plan.run(chunks).select("doc_id", "items.type", "items.span").distinct()


_LEVELS = "SELECT r_name, count(*)::BIGINT AS n, max(o_totalprice) AS top FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name"


def _regional(spark, sf):
    o, c, n, r = (W.table(spark, sf, x) for x in ("orders", "customer", "nation", "region"))
    j = o.join(c, o["o_custkey"] == c["c_custkey"]).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return j.select("r_name", "n_name", F.col("o_totalprice").alias("price"))


def _whole(rows):
    return F.struct(F.size(rows).cast("long").alias("n"), F.array_max(F.transform(rows, lambda r: r["price"])).alias("top"))


@query(_LEVELS)
def d06_multilevel(spark, sf):
    """Nation first, then region."""
    final = lambda rows: F.struct(F.aggregate(rows, F.lit(0).cast("long"), lambda a, r: a + r["__partial"]["n"]).alias("n"), F.array_max(F.transform(rows, lambda r: r["__partial"]["top"])).alias("top"))
    op = ReduceOp(("r_name",), ("price",), _whole, "answer")
    plan = _first("D6", [op], replace(HINTS, finer_keys=("n_name",), partial=_whole, final=final))
    return plan.run(_regional(spark, sf)).select("r_name", "answer.*")


@query(BASE)
def d07_glean_map(spark, sf):
    """With the reference model gleaning adds nothing and loses nothing."""
    return flat(_first("D7", [MapOp(W.extraction(W.CONTACTS))], HINTS).run(W.documents(spark, sf)))


@query("SELECT r_name, least(4, count(DISTINCT n_name))::BIGINT AS n FROM nation JOIN region ON n_regionkey = r_regionkey WHERE n_nationkey IN (SELECT c_nationkey FROM customer JOIN orders ON c_custkey = o_custkey) GROUP BY r_name")
def d08_glean_reduce(spark, sf):
    """A model that names two nations a call is asked on, the group at hand, until nothing in it is unnamed."""
    names = lambda rows: F.array_sort(F.array_distinct(F.transform(rows, lambda r: r["n_name"])))
    few = lambda rows: F.slice(names(rows), 1, 2)
    more = lambda rows, answer: F.concat(answer, F.slice(F.array_except(names(rows), answer), 1, 2))
    named = lambda text, answer: F.size(F.regexp_extract_all(F.aggregate(answer, text, lambda t, n: F.replace(t, F.concat(F.lit('"'), n, F.lit('"')), F.lit(""))), F.lit("NATION"), F.lit(0))) == 0
    plan = _first("D8", [ReduceOp(("r_name",), ("n_name",), few, "names")], replace(HINTS, satisfied=named, refine=more, gleaning=1))
    return plan.run(_regional(spark, sf).select("r_name", "n_name").distinct()).select("r_name", F.size("names").cast("long").alias("n"))


@query("SELECT upper(p_name) AS name, count(*)::BIGINT AS n FROM part GROUP BY 1")
def d09_resolve_keys(spark, sf):
    p = W.table(spark, sf, "part").select(F.when(F.col("p_partkey") % 3 == 0, F.upper("p_name")).otherwise(F.col("p_name")).alias("name"), "p_partkey")
    op = ReduceOp(("name",), ("p_partkey",), lambda rows: F.size(rows).cast("long"), "n")
    plan = _first("D9", [op], replace(HINTS, compare=lambda x, y: F.lower(x) == F.lower(y)))
    return plan.run(p).select(F.upper("name").alias("name"), "n")


@query(BASE)
def d10_chain(spark, sf):
    """Irrelevant lines go first, then the original task runs on what is left."""
    drop = Task("text", "text", lambda c: F.array_join(F.filter(F.split(c, "\n"), lambda x: x.rlike("@|[0-9]")), "\n"), T.StringType())
    plan = _first("D10", [MapOp(W.extraction(W.CONTACTS))], replace(HINTS, chain=(MapOp(drop),)))
    return flat(plan.run(W.documents(spark, sf)))


@query(f"SELECT doc_id, sum(ceil(len(t) / 5.0))::BIGINT AS groups FROM ({_LINES}) GROUP BY doc_id HAVING sum(len(t)) > 0")
def d10_compress_groups(spark, sf):
    """The other chain: every five lines become one summary before the original map."""
    squeeze = Task("text", "text", lambda c: F.transform(F.sequence(F.lit(0), F.floor((F.size(F.filter(F.split(c, "\n"), lambda x: F.trim(x) != "")) - 1) / 5)), lambda i: i), T.ArrayType(T.LongType()))
    count = Task("groups", "text", lambda c: F.size(c).cast("long"), T.LongType())
    plan = _first("D10", [MapOp(count)], replace(HINTS, chain=(MapOp(squeeze),)))
    return plan.run(W.documents(spark, sf).filter("text rlike '[^ \\n]'")).select("doc_id", "groups")


def parts(types):
    return tuple(W.extraction([t], f"only_{t}") for t in types)


@query(BASE)
def d11_isolate(spark, sf):
    plan = _first("D11", [MapOp(W.extraction(W.CONTACTS))], replace(HINTS, parts=parts(W.CONTACTS)))
    return flat(plan.run(W.documents(spark, sf)))


@query("SELECT p_type, count(*)::BIGINT AS n, sum((l_returnflag = 'R')::INT)::BIGINT AS returned FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_type")
def d12_preaggregate(spark, sf):
    """Each line is cut to its return flag before the groups are formed."""
    li = W.table(spark, sf, "lineitem").join(W.table(spark, sf, "part"), F.col("l_partkey") == F.col("p_partkey"))
    flag = Task("flag", "l_returnflag", lambda c: (c == "R").cast("int"), T.IntegerType())
    raw = lambda rows: F.struct(F.size(rows).cast("long").alias("n"), F.aggregate(rows, F.lit(0).cast("long"), lambda a, r: a + (r["l_returnflag"] == "R").cast("int")).alias("returned"))
    short = lambda rows: F.struct(F.size(rows).cast("long").alias("n"), F.aggregate(rows, F.lit(0).cast("long"), lambda a, r: a + r["flag"]).alias("returned"))
    plan = _first("D12", [ReduceOp(("p_type",), ("l_returnflag", "l_shipdate"), raw, "x")], replace(HINTS, projection=flag, final=short, doc_key="l_orderkey"))
    return plan.run(li, Context(doc_id="l_orderkey")).select("p_type", "x.*")


@query(_PASSAGE_SQL)
def d13_prejoin(spark, sf):
    """The left side is projected to its normalised text before the join."""
    labels = lambda: W.table(spark, sf, "benchmark").withColumnRenamed("text", "label")
    block = lambda left, right: O.all_words_pairs(left, "doc_id", "short", right, "item_id", "label")
    short = Task("short", "text", lambda c: F.lower(c), T.StringType())
    op = EquijoinOp(labels, "doc_id", "item_id", block, lambda m: F.contains("text", "label"))
    return _first("D13", [op], replace(HINTS, projection=short)).run(W.documents(spark, sf)).select("doc_id", "item_id")


#: A case of a daily log: an event's id and time, the officer as spelled, and its type.
CASE = "[0-9]+ ; [0-9-]+ [0-9:]+ ; [^;\n]+ ; error(?= ;|[\n<]|$)"


def _cases(text):
    return F.regexp_extract_all(text, F.lit(CASE), F.lit(0))


def _numbered_cases(shown):
    """(type, span) of the chunk's cases: day and number of the case in its log, and the officer.

    The day is read from the header. The number goes on from the cases of all earlier
    chunks, which the summaries of the far ones mark and the near ones show.
    """
    own, before = F.substring_index(shown, "<chunk>", -1), F.substring_index(shown, "<chunk>", 1)
    day = F.regexp_extract(F.substring_index(before, "\n", 1), "<headers>([^<]*)</headers>", 1)
    # Summaries have a mark for each case, which nothing else has: there is one piece more than marks.
    first = F.size(F.split(before, "\\*")) + F.size(_cases(before))
    number = lambda xs: F.transform(xs, lambda x, i: F.struct(F.concat(x["day"], F.lit(" #"), (x["first"] + i).cast("string")).alias("type"), F.trim(F.element_at(F.split(x["line"], " ; "), 3)).alias("span")))
    # A lambda's own variables: what stands before the chunk is read once, not for each case.
    heads = F.array(F.struct(day.alias("day"), first.alias("first")))
    return F.flatten(F.transform(heads, lambda h: number(F.transform(_cases(own), lambda x: F.struct(h["day"].alias("day"), h["first"].alias("first"), x.alias("line"))))))


@dataclass(frozen=True)
class Hasty(PerfectModel):
    """Names few items at first, and all of them when it is asked again."""

    few: int = 5

    def answer(self, task, doc_id, turn=0):
        items = super().answer(task, doc_id, turn)
        return items if turn else F.slice(items, 1, self.few)


@query("SELECT DISTINCT user_id, count(*)::BIGINT AS n FROM events WHERE event_type = 'error' GROUP BY user_id")
def composite_case_files(spark, sf):
    """The composite plan: metadata, split, summaries, gather, map, gleaning, reduce, unnest, resolve, reduce.

    The map reads the chunk in its context: the day, found in the log's first line, is a
    header, and summaries mark the cases of the far earlier chunks. Both name a case, by
    which the last reduce counts. Gleaning asks again where cases are not named.
    """
    # What stands for tags and marks in what the map reads is nowhere else in it.
    logs = W.daily_logs(spark, sf).withColumn("text", F.replace(F.replace("text", F.lit("<"), F.lit("(")), F.lit("*"), F.lit("+")))
    cases = Task("cases", "text_chunk_rendered", _numbered_cases)
    complete = lambda shown, a: F.size(a) == F.size(_cases(F.substring_index(shown, "<chunk>", -1)))
    # Lines are the delimiter here, so that no case is cut.
    logs = O.split_delimiter(logs.withColumn("day", F.regexp_extract("text", "^[^;]* ; ([0-9-]+) ", 1)), "text", "\n", 40)
    logs = logs.withColumn("summary", F.repeat(F.lit("*"), F.size(_cases(F.col("text_chunk")))))
    logs = O.gather(logs, "split_id", "split_chunk_num", "text_chunk", O.Peripheral(O.Side(tail=2, middle=True, middle_key="summary")), headers="day")
    plan = Pipeline(
        (
            MapOp(cases, gleaning=1, satisfied=complete, model=Hasty()),
            ReduceOp(("doc_id",), ("cases",), union_items("cases"), "cases", ("split_chunk_num",)),
            UnnestOp("cases"),
            ProjectOp("officer", lambda: F.col("cases.span")),
            ProjectOp("event", lambda: F.col("cases.type")),
        )
    )
    # Read by blocking, counts and the replacement: the logs are written and cut once.
    flatted = stored(plan.run(logs).select("officer", "event"), "cases")
    number = lambda x: F.regexp_extract(x, "[0-9]+", 0)
    values = flatted.select("officer").distinct().withColumn("n", number(F.col("officer")))
    pairs = values.join(values.groupBy("n").agg(F.min("officer").alias("x")), "n").filter("x < officer").select("x", F.col("officer").alias("y"))
    same = O.resolve(flatted, "officer", pairs, lambda x, y: number(x) == number(y))
    return same.groupBy("officer").agg(F.countDistinct("event").alias("n")).select(number(F.col("officer")).cast("long").alias("user_id"), "n")


def _candidates(spark, sf):
    task = W.extraction(W.CONTACTS)
    sim = SimulatedModel(Profile("s", 4000, keep=800, per_hundred_tokens=60, per_ask=100, floor=100, hallucination=30))
    hints = replace(HINTS, parts=parts(W.CONTACTS))
    plans = {"map": Pipeline((MapOp(task),)), "chunk": _first("D1", [MapOp(task)], hints), "isolate": _first("D11", [MapOp(task)], hints), "glean": _first("D7", [MapOp(task)], hints)}
    d = W.documents(spark, sf).filter(F.size(W.items(F.col("text"), W.CONTACTS)) > 0)
    keep = d.select("doc_id", F.col("text").alias("source_text"))
    outs = {k: p.run(d, Context(sim)).select("doc_id", "items").join(keep, "doc_id") for k, p in plans.items()}
    return outs, extraction_validator("items", "source_text", W.CONTACTS)


@query()
def rate_candidate_plans(spark, sf):
    outs, v = _candidates(spark, sf)
    return plan_scores(rate_plans(outs, v, "doc_id"))


@query()
def duel_candidate_plans(spark, sf):
    outs, v = _candidates(spark, sf)
    return duel_plans(rate_plans(outs, v, "doc_id"))


#: What the search runs against: long texts and several asks hurt.
SEARCHED = SimulatedModel(Profile("s", 4000, keep=700, per_hundred_tokens=60, per_ask=100, floor=100, hallucination=30))
_SIGNS = "regexp_matches(text, '@|[0-9][.][0-9]')"


def _search(spark, sf, **more):
    d = W.documents(spark, sf).filter("text rlike '@|[0-9][.][0-9]'").withColumn("source_text", F.col("text"))
    hints = Hints(columns=("doc_id", "text", "lang", "source", "source_text"))
    validator = extraction_validator("items", "source_text", W.CONTACTS, more.pop("scale", 4))
    generator = RuleGenerator(chunk_cap=2, shapes=1)
    return d, Search(d, Context(SEARCHED), hints, validator, generator=generator, **({"max_depth": 1, "max_plans": 8} | more))


@query()
def optimize_contacts(spark, sf):
    """The full search on a simulated model: what it picked, what it cost, and the ratings over all documents."""
    plan = Pipeline((MapOp(W.extraction(W.CONTACTS)),))
    d, search = _search(spark, sf)
    best = optimize(plan, d, search)
    judge = lambda p: round(search.validator.judge(p.run(d, search.ctx)), 6)
    bill = search.account().first()
    row = (" / ".join(best.trail), bill.plans, bill.calls, bill.tokens_in, bill.dollars, judge(plan), judge(best))
    return spark.createDataFrame([row], "picked string, tried int, calls long, tokens_in long, dollars double, as_written double, optimized double")


@query()
def optimize_strategies(spark, sf):
    """Two-stage selection beside its ablations, and the other rating scale: pick and rating over all documents."""
    out = []
    for strategy, scale in (("two_stage", 4), ("rate", 4), ("duel", 4), ("two_stage", 5)):
        d, search = _search(spark, sf, strategy=strategy, scale=scale, max_plans=4)
        best = optimize(Pipeline((MapOp(W.extraction(W.CONTACTS)),)), d, search)
        out.append((strategy, scale, " / ".join(best.trail), round(search.validator.judge(best.run(d, search.ctx)), 6)))
    return spark.createDataFrame(out, "strategy string, scale int, picked string, rating double")


@query(f"WITH d AS (SELECT doc_id, len({toks('text')}) AS n FROM documents WHERE {_SIGNS}), s AS (SELECT n FROM d ORDER BY -ln((('0x' || substr(md5('0|' || doc_id), 1, 8))::BIGINT + 1.0) / 4294967297.0) / greatest(n, 1), doc_id LIMIT 40) SELECT 3::BIGINT * count(*) AS calls, 3::BIGINT * sum(least(n, 4000))::BIGINT AS tokens_in, max(n)::BIGINT AS longest FROM s")
def optimize_account(spark, sf):
    """The account of one gleaned plan over the search's own sample: three calls a document."""
    d, search = _search(spark, sf)
    plan = _first("D7", [MapOp(W.extraction(W.CONTACTS))], HINTS)
    search.output(plan)
    return search.account().select("calls", "tokens_in").withColumn("longest", F.lit(search.stats.max_tokens).cast("long"))


_PARETO = "SELECT lang || ' ' || source AS plan, count(*)::BIGINT AS accuracy, sum(n_chars)::BIGINT AS cost FROM documents GROUP BY ALL"


@query(f"WITH p AS ({_PARETO}) SELECT plan, accuracy, cost FROM p WHERE NOT EXISTS (SELECT 1 FROM p q WHERE q.plan <> p.plan AND q.cost <= p.cost AND q.accuracy >= p.accuracy AND (q.cost < p.cost OR q.accuracy > p.accuracy))")
def pareto_plans(spark, sf):
    """Groups of documents as plans, their number as accuracy and their characters as cost."""
    d = W.table(spark, sf, "documents").groupBy(F.concat_ws(" ", "lang", "source").alias("plan")).agg(F.count(F.lit(1)).alias("accuracy"), F.sum("n_chars").alias("cost"))
    return pareto(d, "accuracy", "cost")


@query(BASE)
def overflow_fallback(spark, sf):
    """Documents beyond the context limit take the chunked plan at run time."""
    task = W.extraction(W.CONTACTS)
    plain = Pipeline((MapOp(task),))
    chunked = _first("D1", [MapOp(task)], HINTS)
    return flat(run_adaptive(plain, chunked, W.documents(spark, sf), "text", 300, Context()))


@query(f"SELECT source, sum(len({toks('text')}))::BIGINT AS n FROM documents GROUP BY source")
def derived_reduce(spark, sf):
    d = W.documents(spark, sf).withColumn("k", token_count(F.col("text")).cast("long"))
    op = ReduceOp(("source",), ("k",), lambda rows: F.aggregate(rows, F.lit(0).cast("long"), lambda a, r: a + r["k"]), "n")
    return Pipeline((op,)).run(d)
