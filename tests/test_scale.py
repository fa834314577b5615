"""Skewed groups, long documents, plan identity, saved pipelines, the request cache and the search's own parts."""

from dataclasses import replace

import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from sieveline import operators as O
from sieveline import store
from sieveline.catalogue.directives import HINTS, _search
from sieveline.functions.prompts import fold_prompt, parse_schema
from sieveline.model import EndpointModel, PerfectModel, RequestCache, Task
from sieveline.operators import semantic
from sieveline.plans import directives as D
from sieveline.plans import ir
from sieveline.plans.optimizer import Criterion, RuleGenerator, Stats, Validator, duel_plans, optimize
from sieveline.sources import load_pipeline, save_pipeline
from sieveline.workloads import inputs as W


@pytest.fixture(scope="module")
def skewed(spark):
    """One group with 99 % of the rows, one null group."""
    hot = spark.range(20_000).select(F.lit("hot").alias("k"), F.col("id"), (F.col("id") * 7919 % 20_011).alias("o"))
    few = spark.createDataFrame([("b", i, -i) for i in range(150)] + [(None, i, i) for i in range(50)], "k string, id long, o long")
    return hot.unionByName(few).repartition(8)


def test_numbering_of_a_skewed_group(skewed):
    rows = O.numbered(skewed, ["k"], ["o"]).collect()
    for k in ("hot", "b", None):
        mine = sorted((r.o, r["__n"]) for r in rows if r.k == k)
        assert [n for _, n in mine] == list(range(len(mine)))
    assert O.numbered(skewed.limit(0), ["k"], ["o"]).count() == 0


def test_numbering_spreads_a_hot_group(spark, skewed):
    ranges = skewed.repartitionByRange(8, "k", "o").withColumn("p", F.spark_partition_id())
    most = ranges.groupBy("p").count().agg(F.max("count")).first()[0]
    assert most < 0.5 * skewed.count()


def _last_and_count(acc, rows):
    return F.struct((acc["n"] + F.size(rows)).alias("n"), F.element_at(F.transform(rows, lambda r: r["id"]), -1).alias("last"))


@pytest.mark.parametrize("segment", [3, 10_000])
def test_fold_passes_its_state_on(spark, skewed, segment):
    zero = F.struct(F.lit(0).alias("n"), F.lit(None).cast("long").alias("last"))
    got = {r.k: (r.answer.n, r.answer.last, r.n_calls) for r in O.fold(skewed.filter("k is null or k = 'b' or id < 2000"), ["k"], ["id"], ["o"], 41, zero, _last_and_count, segment=segment).collect()}
    top = max(range(2000), key=lambda i: i * 7919 % 20_011)
    assert got == {"hot": (2000, top, 49), "b": (150, 0, 4), None: (50, 49, 2)}


def test_fold_merges_states_of_associative_steps(skewed):
    zero = F.lit(0).cast("long")
    step = lambda acc, rows: acc + F.aggregate(rows, F.lit(0).cast("long"), lambda a, r: a + r["id"])
    got = {r.k: (r.answer, r.n_calls) for r in O.fold(skewed, ["k"], ["id"], ["o"], 41, zero, step, merge=lambda a, b: a + b, segment=5).collect()}
    assert got == {"hot": (sum(range(20_000)), 488), "b": (sum(range(150)), 4), None: (sum(range(50)), 2)}


def test_tree_and_reduce_of_a_skewed_group(skewed, monkeypatch):
    total = lambda xs: F.aggregate(xs, F.lit(0).cast("long"), lambda a, x: a + x)
    expect = {"hot": sum(range(20_000)), "b": sum(range(150)), None: sum(range(50))}
    assert {r.k: r.id for r in O.tree_reduce(skewed, ["k"], "id", ["o"], 16, total).collect()} == expect
    of_rows = lambda rows: total(F.transform(rows, lambda r: r["id"]))
    assert {r.k: r.answer for r in O.sem_reduce(skewed, ["k"], ["id"], of_rows, merge=total).collect()} == expect
    assert O.sem_reduce(skewed, [], ["id"], of_rows, merge=total).first().answer == sum(expect.values())
    monkeypatch.setattr(semantic, "MAX_GROUP", 1000)
    with pytest.raises(Exception, match="a group has 20000 rows"):
        O.sem_reduce(skewed, ["k"], ["id"], of_rows).collect()


def _plain_gather(xs, i, p, q):
    """What stands around chunk i (from 0) by slices of the whole list."""
    before, after = xs[:i], xs[i + 1 :]
    head = before[: p.head]
    tail = before[len(head) :][-p.tail :] if p.tail else []
    mid = before[len(head) : len(before) - len(tail)]
    near = after[: q.head]
    far = after[len(near) :][-q.tail :] if q.tail else []
    rest = after[len(near) : len(after) - len(far)]
    gap = lambda x: [f"[... {len(x)} chunks ...]"] if x else []
    prev, nxt = head + (mid if p.middle else gap(mid)) + tail, near + (rest if q.middle else gap(rest)) + far
    wrap = lambda t, x: f"<{t}>" + "\n".join(x) + f"</{t}>" if x else ""
    return wrap("previous", prev) + f"<chunk>{xs[i]}</chunk>" + wrap("next", nxt)


@pytest.mark.parametrize("p,q", [((2, 3, False), (1, 2, False)), ((0, 2, True), (0, 0, False)), ((1, 0, False), (2, 0, True)), ((0, 0, False), (0, 3, False)), ((3, 1, True), (1, 3, True))])
def test_gather_sections_equal_plain_slices(spark, p, q):
    p, q = (O.Side(head=h, tail=t, middle=m) for h, t, m in (p, q))
    d = spark.createDataFrame([(doc, i, f"c{doc}_{i}") for doc, n in ((1, 1), (2, 3), (3, 9)) for i in range(1, n + 1)], "id int, n int, x string")
    got = {(r.id, r.n): r.x_rendered for r in O.gather(d, "id", "n", "x", O.Peripheral(p, q)).collect()}
    for doc, n in ((1, 1), (2, 3), (3, 9)):
        xs = [f"c{doc}_{i}" for i in range(1, n + 1)]
        assert [got[doc, i] for i in range(1, n + 1)] == [_plain_gather(xs, i, p, q) for i in range(n)]


def test_gather_of_a_document_of_100000_chunks(spark):
    d = spark.range(1, 100_001).select(F.lit(1).alias("doc"), F.col("id").alias("n"), F.concat(F.lit("c"), F.col("id").cast("string")).alias("x"))
    out = O.gather(d, "doc", "n", "x", O.Peripheral(O.Side(head=1, tail=2), O.Side(head=1, tail=1)))
    r = out.filter("n = 50000").first()
    assert r.x_rendered == "<previous>c1\n[... 49996 chunks ...]\nc49998\nc49999</previous><chunk>c50000</chunk><next>c50001\n[... 49998 chunks ...]\nc100000</next>"
    assert out.agg(F.max(F.length("x_rendered"))).first()[0] < 200


def test_search_join_and_threshold_by_blocks(spark, sf, monkeypatch):
    e = W.table(spark, sf, "embeddings").select("vec_id", "embedding")
    a, b = e.filter("vec_id < 20").toDF("a", "v"), e.toDF("b", "v")
    whole = sorted(map(tuple, O.similar(a, b, "a", "b", "v", k=7).collect()))
    assert len(whole) == 140 and all((i, i) in {(x, y) for x, y, _ in whole} for i in range(20))
    monkeypatch.setattr(O.pairs, "BLOCK_ROWS", 60)
    near = O.map_search_filter(a, "a", b, "b", "v", 7, F.lit(True))
    assert sorted((r.a, r.b, r.sim) for r in near.collect()) == whole
    assert "CartesianProduct" not in near._jdf.queryExecution().executedPlan().toString()
    limits = {r.b for r in O.cosine_pairs(a, b, "a", "b", "v", 0.9).collect()}
    assert limits == set(range(20))


def test_plans_are_told_apart_by_content():
    def op(prompt, n):
        return ir.MapOp(Task("items", "text", lambda c: F.substring(c, 1, n), T.StringType(), prompt=prompt))

    prints = {ir.Pipeline((op(p, n),)).fingerprint() for p in ("one {{ input.text }}", "two {{ input.text }}") for n in (1, 2)}
    assert len(prints) == 4 and ir.Pipeline((op("x", 1),)).fingerprint() == ir.Pipeline((op("x", 1),)).fingerprint()
    reduces = {ir.Pipeline((ir.ReduceOp(("k",), ("x",), f, "a"),)).fingerprint() for f in (lambda r: F.size(r), lambda r: F.size(r) + 1)}
    assert len(reduces) == 2
    glean = {ir.Pipeline((replace(op("x", 1), gleaning=1, satisfied=lambda t, a, k=k: F.size(a) > k),)).fingerprint() for k in (1, 2)}
    assert len(glean) == 2


@pytest.mark.parametrize("ending", ["yaml", "json"])
def test_saved_pipelines_load_again(spark, sf, tmp_path, ending):
    items = W.extraction(W.CONTACTS)
    flag = Task("flag", "text", lambda c: F.contains(c, F.lit("@")), T.BooleanType(), prompt="Is there one in {{ input.text }}?")
    labels = lambda: W.table(spark, sf, "benchmark").withColumnRenamed("text", "label")
    block = lambda left, right: O.all_words_pairs(left, "doc_id", "text", right, "item_id", "label")
    plan = ir.Pipeline(
        (
            ir.FilterOp(flag),
            ir.ParallelMapOp((flag, items)),
            ir.ProjectOp("n", lambda: F.size("items"), ("flag",)),
            ir.EquijoinOp(labels, "doc_id", "item_id", block, None, "left"),
            ir.SplitOp("text", 50),
            ir.GatherOp("text_chunk", O.Peripheral(O.Side(head=1, middle=True, middle_key="text_chunk"), O.Side(fraction=0.5))),
            ir.MapOp(items.on("text_chunk"), ("source",), 1, lambda t, a: F.size(a) > 0),
            ir.UnnestOp("items", True),
            ir.ResolveOp("lang", lambda x, y: F.lower(x) == F.lower(y)),
            ir.ReduceOp(("lang",), ("doc_id",), lambda rows: F.size(rows), "n", ("doc_id",)),
            ir.FoldOp(("lang",), ("n",), ("n",), 5, lambda: F.lit(0), lambda acc, r: acc + F.size(r), "total", prompt="Sum up {{ inputs }}"),
        ),
        ("D1 document chunking",),
    )
    path = str(tmp_path / f"p.{ending}")
    registry = save_pipeline(plan, path)
    again = load_pipeline(path, registry)
    assert again.fingerprint() == plan.fingerprint() and again.trail == plan.trail
    small = ir.Pipeline(plan.ops[:3])
    registry = save_pipeline(small, path)
    d = W.documents(spark, sf)
    assert sorted(r.n for r in load_pipeline(path, registry).run(d).collect()) == sorted(r.n for r in small.run(d).collect())


def test_pipelines_written_by_users():
    task = W.extraction(W.CONTACTS)
    spec = {"operations": [{"type": "split", "split_key": "text", "method_kwargs": {"num_tokens": 9}}, {"type": "gather", "content_key": "text_chunk", "peripheral_chunks": {"previous": {"tail": 1}}}, {"type": "map", "name": "find", "drop_keys": ["lang"]}, {"type": "unnest", "unnest_key": "items"}]}
    plan = load_pipeline(spec, {"find": task})
    assert plan.ops[1].peripheral == O.Peripheral(O.Side(tail=1)) and plan.ops[2].task is task and plan.ops[2].drop == ("lang",)
    with pytest.raises(ValueError):
        load_pipeline({"operations": [{"type": "map", "name": "find", "what": 1}]}, {"find": task})


def test_later_prompts_of_a_fold_are_given_or_derived(spark):
    op = ir.FoldOp(("k",), ("x",), ("x",), 2, lambda: F.lit(0), lambda a, r: a, "total", prompt="Name all in {{ inputs }}")
    assert op.prompts()[1] == fold_prompt("Name all in {{ inputs }}", "total") and "{{ total }}" in op.prompts()[1]
    assert replace(op, later_prompt="More of {{ inputs }}").prompts()[1] == "More of {{ inputs }}"
    d = spark.createDataFrame([("a", 1)], "k string, x int")
    ir.Pipeline((op,)).analyze(d)
    with pytest.raises(ValueError):
        ir.Pipeline((replace(op, prompt="Name all"),)).analyze(d)


def test_requests_are_asked_once(spark, tmp_path):
    log = tmp_path / "asked"
    log.mkdir()

    def complete(prompts):
        import uuid

        (log / uuid.uuid4().hex).write_text("\n".join(prompts))
        return [f'{{"n": {len(p)}}}' for p in prompts]

    asked = lambda: sorted(x for f in log.iterdir() for x in f.read_text().split("\n") if x)
    task = Task("answer", "text", lambda c: c, parse_schema("{n: int}"), prompt="Count {{ input.text }}")
    cache = RequestCache(str(tmp_path / "cache"))
    d = spark.createDataFrame([(1, "abc"), (2, "abc"), (3, "de")], "doc_id int, text string")
    for _ in range(2):
        assert sorted((r.doc_id, r.answer.n) for r in cache.map(d, task, EndpointModel(complete)).collect()) == [(1, 9), (2, 9), (3, 8)]
    assert asked() == ["Count abc", "Count de"]
    more = d.unionByName(spark.createDataFrame([(4, "new")], d.schema))
    assert cache.map(more, task, EndpointModel(complete)).count() == 4 and asked() == ["Count abc", "Count de", "Count new"]


def test_answers_that_are_not_json_are_asked_for_again(spark):
    def complete(prompts):
        return ["not json" if len(prompts) > 1 else '{"n": 1}' for _ in prompts]

    task = Task("answer", "text", lambda c: c, parse_schema("{n: int}"), prompt="Count {{ input.text }}")
    d = spark.createDataFrame([(1, "a"), (2, "b")], "doc_id int, text string").coalesce(1)
    assert [r.answer for r in O.sem_map(d, task, EndpointModel(complete)).collect()] == [None, None]
    with pytest.raises(Exception, match="not JSON"):
        O.sem_map(d, task, EndpointModel(complete, strict=True)).collect()


def test_generator_fills_what_hints_leave_open():
    g, stats = RuleGenerator(chunk_cap=8), Stats(533.0, 2000, 4000)
    op = (ir.MapOp(W.extraction(sorted(W.CLAUSES))),)
    sizes = [h.chunk_tokens[0] for h in g.propose(D.BY_ID["D1"], op, D.Hints(), stats)]
    assert sizes == [n for n in D.chunk_sizes(4000, 533.0, 8) if n < 2000] and len(sizes) > 3
    groups = [len(h.parts) for h in g.propose(D.BY_ID["D11"], op, D.Hints(), stats)]
    assert groups == [8, 4, 3]
    assert not g.applicable(D.BY_ID["D11"], (ir.MapOp(W.extraction(["ip"])),), D.Hints(), stats)
    assert not g.applicable(D.BY_ID["D1"], op, D.Hints(), Stats(1.0, 1, 4000))
    assert not g.applicable(D.BY_ID["D12"], op, D.Hints(), Stats(20.0, 20, 4000))


def test_verdicts_have_a_reason(spark):
    v = Validator((Criterion("is even", lambda: F.col("x") % 2 == 0), Criterion("is small", lambda: F.col("x") < 100)), 5, ("x",))
    got = v.verdict(spark.range(10).select(F.col("id").alias("x")))
    assert (got.satisfied, got.mean, got.reason) == (False, 4.0, "is even: 50%")
    assert v.verdict(spark.createDataFrame([(2,)], "x int")).satisfied


def test_strategies_of_selection(spark):
    rows = [("a", i, 3 if i < 2 else 1, 3) for i in range(3)] + [("b", i, 2, 4) for i in range(3)] + [("c", i, 0, 1) for i in range(3)]
    ratings = spark.createDataFrame(rows, "plan_id string, doc_id int, passed int, rating int")
    assert duel_plans(ratings, strategy="rate").first().plan_id == "b"
    assert duel_plans(ratings, strategy="duel").first().plan_id == duel_plans(ratings).first().plan_id == "a"
    assert duel_plans(ratings, k=1).count() == 1


def test_search_grows_its_sample_and_counts_what_it_drops(spark, sf):
    keep = Task("kept", "text", lambda c: F.length(c) % 2 == 0, T.BooleanType())
    d, search = _search(spark, sf, max_plans=2)
    search.validator = replace(search.validator, needs=("text",), criteria=(Criterion("never", lambda: F.lit(False)),))
    first = search.size
    best = optimize(ir.Pipeline((ir.FilterOp(keep), ir.MapOp(W.extraction(W.CONTACTS)))), d, search)
    assert search.size > first and search.selectivity and len(best.ops) >= 2
    assert search.dropped and search.notes and search.account().first().plans == search.tried


def test_search_goes_into_what_it_makes(spark, sf):
    """A chunked map may be gleaned in turn, behind operators that stand before it."""
    d, search = _search(spark, sf, max_depth=2, max_plans=30)
    search.directives = (D.BY_ID["D1"], D.BY_ID["D7"])
    search.hints = replace(search.hints, chunk_tokens=(100,), peripherals=(O.Peripheral(),))
    before = ir.ProjectOp("note", lambda: F.lit(1))
    best = optimize(ir.Pipeline((before, ir.MapOp(W.extraction(W.CONTACTS)))), d, search)
    assert any("MapOp" in n and "ReduceOp" not in n for n in search.notes[1:]) and best.ops[0] is before
    with pytest.raises(Exception):
        bad = replace(search.validator, needs=("no_such",))
        bad.judge(search.sample.select(F.col("no_such")))


def test_gleaned_reduce_stops_when_satisfied(spark):
    rows = spark.createDataFrame([("g", i) for i in range(7)], "k string, x int")
    two = lambda r: F.slice(F.array_sort(F.transform(r, lambda e: e["x"])), 1, 2)
    more = lambda r, a: F.concat(a, F.slice(F.array_except(F.array_sort(F.transform(r, lambda e: e["x"])), a), 1, 2))
    for rounds, n in ((1, 4), (2, 6), (9, 7)):
        op = ir.ReduceOp(("k",), ("x",), two, "xs")
        (made,) = D.BY_ID["D8"].apply((op,), replace(HINTS, refine=more, gleaning=rounds, satisfied=lambda t, a: F.size(a) >= 7))
        assert ir.Pipeline(made).run(rows).first().xs == list(range(n))


def test_ledger_counts_calls_and_tokens(spark):
    d = spark.createDataFrame([(1, "a b c"), (2, "d")], "doc_id int, text string")
    op = ir.MapOp(Task("n", "text", lambda c: F.length(c), T.IntegerType()))
    r = ir.Pipeline((op, ir.ProjectOp("z", lambda: F.lit(0)))).ledger(d, ir.Context(PerfectModel())).collect()
    assert [(x.step, x.op, x.calls, x.tokens_in) for x in r] == [(0, "MapOp", 2, 4)]
    assert ir.Pipeline((ir.ProjectOp("z", lambda: F.lit(0)),)).ledger(d).count() == 0


def test_written_tables_can_be_swept(spark):
    df = store.stored(spark.range(3), "to_sweep")
    assert df.count() == 3 and any("to_sweep" in x for x in store._made)
    with pytest.raises(ValueError):
        store.small(spark.range(20), 10)
