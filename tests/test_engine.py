"""Templates, schemas, operators, directives, measures and search on hand fixtures."""

import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieveline import catalogue
from sieveline import measures as M
from sieveline import operators as O
from sieveline.functions.prompts import Template, parse_schema
from sieveline.functions.text import truncate_middle
from sieveline.model import EndpointModel, Task
from sieveline.plans import directives as D
from sieveline.plans.ir import GatherOp, MapOp, Pipeline
from sieveline.plans.optimizer import duel_plans, required_sample
from sieveline.workloads import inputs as W


def test_template_needs_a_placeholder():
    with pytest.raises(ValueError):
        Template("Summarise.").check(["text"])
    with pytest.raises(ValueError):
        Template("Summarise {{ input.body }}").check(["text"])
    Template("Summarise {{ input.text }}").check(["text"])


def test_schema_language():
    kind = parse_schema("list[{a: str, b: int, c: {d: list[bool]}}]")
    assert kind.simpleString() == "array<struct<a:string,b:bigint,c:struct<d:array<boolean>>>>"
    with pytest.raises(ValueError):
        parse_schema("list[{a: what}]")


def test_split_then_join_is_the_text(spark, sf):
    d = W.documents(spark, sf).limit(30)
    chunks = O.split_tokens(d, "text", 7).groupBy("doc_id").agg(F.array_sort(F.collect_list(F.struct("split_chunk_num", "text_chunk"))).alias("c"))
    back = {r.doc_id: " ".join(x.text_chunk for x in r.c) for r in chunks.collect()}
    for r in d.collect():
        assert back.get(r.doc_id, "") == " ".join(t for t in r.text.replace("\n", " ").split(" ") if t)


def test_gather_of_seven_chunks(spark):
    d = spark.createDataFrame([(1, i, w) for i, w in enumerate("abcdefg", 1)], "id int, n int, x string")
    got = {r.n: r.x_rendered for r in O.gather(d, "id", "n", "x", O.Peripheral(O.Side(head=1, tail=1), O.Side(head=1))).collect()}
    assert got[1] == "<chunk>a</chunk><next>b\n[... 5 chunks ...]</next>"
    assert got[4] == "<previous>a\n[... 1 chunks ...]\nc</previous><chunk>d</chunk><next>e\n[... 2 chunks ...]</next>"
    assert got[7] == "<previous>a\n[... 4 chunks ...]\nf</previous><chunk>g</chunk>"


def test_header_lineage_modes(spark):
    heads = [(1, 1, "A"), (2, 2, "B"), (3, 3, "C"), (4, 2, "D"), (5, 1, "E"), (6, None, None), (7, 3, "F")]
    rows = [(1, n, [(lv, h)] if lv else []) for n, lv, h in heads]
    d = spark.createDataFrame(rows, "id int, n int, hs array<struct<level:int,header:string>>")
    path = {r.n: r.lineage for r in O.header_lineage(d, "id", "n", "hs").collect()}
    assert path == {1: "", 2: "A", 3: "A > B", 4: "A", 5: "", 6: "E", 7: "E"}
    latest = {r.n: r.lineage for r in O.header_lineage(d, "id", "n", "hs", mode="latest").collect()}
    assert latest[6] == "E > D > C" and latest[7] == "E > D"


def test_components_of_a_chain(spark):
    labels = O.components(spark.createDataFrame([("a", "b"), ("b", "c"), ("e", "d")], "x string, y string"))
    assert {r.node: r.label for r in labels.collect()} == {"a": "a", "b": "a", "c": "a", "d": "d", "e": "d"}


def test_kendall(spark):
    rows = [("same", i, v) for i, v in enumerate([1, 2, 3, 4])] + [("back", i, v) for i, v in enumerate([4, 3, 2, 1])] + [("swap", i, v) for i, v in enumerate([1, 2, 4, 3])] + [("ties", i, v) for i, v in enumerate([1, 1, 2, 3])]
    d = spark.createDataFrame(rows, "g string, p int, v int")
    a = {r.g: r.tau for r in M.kendall_tau(d, ["g"], "p", "v").collect()}
    assert a["same"] == 1 and a["back"] == -1 and a["swap"] == pytest.approx(2 / 3, abs=1e-6) and a["ties"] == pytest.approx(5 / 6, abs=1e-6)
    assert {r.g: r.tau for r in M.kendall_tau_large(d, ["g"], "p", "v").collect()} == a
    b = {r.g: r.tau for r in M.kendall_tau(d, ["g"], "p", "v", "b").collect()}
    assert b["ties"] == pytest.approx(5 / (6 * 5) ** 0.5, abs=1e-6)


def test_jaccard_edge_is_strict(spark):
    gold = spark.createDataFrame([(1, "t", " ".join(f"w{i}" for i in range(20)))], "doc_id int, type string, span string")
    three = gold.withColumn("span", F.lit("w0 w1 w2"))
    four = gold.withColumn("span", F.lit("w0 w1 w2 w3"))
    assert M.span_prf(three, gold).first().precision == 0 and M.span_prf(four, gold).first().precision == 1


def test_rank_precision(spark):
    ranked = spark.createDataFrame([(1, x, i) for i, x in enumerate("abcdef", 1)], "d int, x string, rank int")
    gold = spark.createDataFrame([(1, "a"), (1, "e"), (1, "z")], "d int, x string")
    assert M.rank_precision(ranked, gold, "d", "x", (5,)).first()[0] == pytest.approx(2 / 3, abs=1e-6)


def test_threshold_keeps_95_percent(spark):
    d = spark.createDataFrame([(i / 20, True) for i in range(1, 21)] + [(0.99, False)], "sim double, match boolean")
    assert O.tune_threshold(d, "sim", "match").first().threshold == pytest.approx(0.1)


def test_candidates():
    assert required_sample(20, [0.5, 0.3]) == 134
    assert D.chunk_sizes(1000, 400) == sorted({150, 300, 450, 600, 750, 60, 128, 196, 264, 332, 400})
    assert len(D.chunk_sizes(1000, 400, cap=8)) == 8
    assert len(D.gather_shapes(100, 95)) == 3


def test_truncation_keeps_both_ends(spark):
    row = spark.range(1).select(truncate_middle(F.lit("a b c d e f g"), 4).alias("x")).first()
    assert row.x == "a b [...] f g"


def test_filter_stays_above_the_window(spark, sf):
    """Dropped chunks still serve as context: the filter on content must not sink below gather."""
    chunks = O.split_tokens(W.documents(spark, sf), "text", 100)
    out = GatherOp("text_chunk", O.Peripheral(O.Side(tail=1))).lower(chunks, None).filter(F.contains("text_chunk", F.lit("@")))
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Contains(text_chunk") < plan.index("Window")


def test_isolation_has_no_shuffle(spark, sf):
    parts = tuple(W.extraction([t], f"only_{t}") for t in W.CONTACTS)
    plan = Pipeline(D.BY_ID["D11"].apply((MapOp(W.extraction(W.CONTACTS)),), D.Hints(parts=parts))[0])
    text = plan.run(W.documents(spark, sf))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in text and "Python" not in text


def test_endpoint_model(spark):
    def complete(prompts):
        return [f'{{"n": {len(p)}}}' for p in prompts]

    task = Task("answer", "text", lambda c: c, parse_schema("{n: int}"), prompt="Count {{ input.text }}")
    d = spark.createDataFrame([(1, "abc"), (2, None)], "doc_id int, text string")
    assert [r.answer.n for r in O.sem_map(d, task, EndpointModel(complete)).orderBy("doc_id").collect()] == [9, 6]


def test_duel_picks_the_plan_with_most_wins(spark):
    rows = [("a", i, 3 if i < 2 else 1, 3) for i in range(3)] + [("b", i, 2, 3) for i in range(3)] + [("c", i, 0, 1) for i in range(3)]
    r = duel_plans(spark.createDataFrame(rows, "plan_id string, doc_id int, passed int, rating int")).first()
    assert (r.plan_id, r.wins) == ("a", 2)


def test_gleaning_never_loses_items(spark, sf):
    from sieveline.catalogue.workloads import SIM, TYPES

    d = W.documents(spark, sf)
    task = W.extraction(TYPES)
    once = O.glean(d, task, SIM, lambda t, a: F.lit(False), 1)
    twice = O.glean(d, task, SIM, lambda t, a: F.lit(False), 2)
    j = once.select("doc_id", F.col("items").alias("x"), F.col("calls").alias("c")).join(twice.select("doc_id", "items", "calls"), "doc_id")
    assert j.filter(F.size(F.array_except("x", "items")) > 0).count() == 0
    assert j.agg(F.max("c"), F.max("calls")).first() == (3, 5)


@pytest.mark.parametrize("name", ["d01_chunked_extract", "d06_multilevel", "d09_resolve_keys", "d11_isolate", "composite_case_files", "gather_prev_next", "resolve_part_names", "metric_span_prf", "wl_contracts_opt_items", "stream_fold_state", "stream_late_data"])
def test_oracle(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
    cur = con.execute(catalogue.oracle_sql()[name])
    names = [c[0] for c in cur.description]
    df = catalogue.queries()[name](spark, sf)
    assert sorted(names) == sorted(df.columns)
    key = lambda row: [(x is None, str(x)) for x in row]
    assert sorted((tuple(r[c] for c in names) for r in df.collect()), key=key) == sorted(cur.fetchall(), key=key)


def test_schema_types():
    assert isinstance(parse_schema("float"), T.DoubleType)
