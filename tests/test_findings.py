"""What a reviewer found on larger tables, each on the smallest table that shows it."""

import duckdb
import pytest

from sieveline import catalogue


def long_documents(spark, folder):
    """Documents over the context of the model, with contacts in their middle."""
    text = " ".join(f"w{i}" if i % 500 else f"u{i}@mail.example.com" for i in range(9000))
    rows = [(i, text.replace("@mail", f"@mail{i}"), "en", "src1", len(text)) for i in range(20)] + [(20, None, "en", None, 0)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    return str(folder)


def equal_to_sql(spark, folder, name, tables):
    con = duckdb.connect()
    for t in tables:
        con.execute(f"create view {t} as select * from read_parquet('{folder}/{t}.parquet/*.parquet')")
    cur = con.execute(catalogue.oracle_sql()[name])
    names = [c[0] for c in cur.description]
    got = [tuple(r[c] for c in names) for r in catalogue.queries()[name](spark, folder).collect()]
    assert got and sorted(got, key=repr) == sorted(cur.fetchall(), key=repr)


@pytest.mark.parametrize("name", ["wl_contracts_base_items", "wl_contracts_opt_items"])
def test_contracts_of_long_documents(spark, tmp_path, name):
    equal_to_sql(spark, long_documents(spark, tmp_path), name, ["documents"])


@pytest.mark.parametrize("name", ["wl_contracts_base_items", "wl_contracts_opt_items"])
def test_contracts_with_odd_line_ends(spark, tmp_path, name):
    """A dot of a pattern stands for any character but a line feed."""
    ends = ["\r", "\x85", "\u2028", "\u2029", "\n", "\x0b", "\x00", "\U0001f389"]
    texts = [f"x token = {e}0f and CC BY-NC 4{e}0 under Licensed under the Apache License, Version 2{e}0{e} a@b.c" for e in ends]
    rows = [(i, texts[i % len(ends)], "en", "src1", 0) for i in range(20 * len(ends))]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    equal_to_sql(spark, str(tmp_path), name, ["documents"])


@pytest.fixture(scope="module")
def many_events(spark, tmp_path_factory):
    """60,000 events of three types, two of them with more batches than a fold holds in one row."""
    from pyspark.sql import functions as F

    folder = str(tmp_path_factory.mktemp("many"))
    kind = F.when(F.col("id") % 100 == 0, "rare").when(F.col("id") % 2 == 0, "even").otherwise("odd")
    ts = F.timestamp_seconds(F.lit(1_704_067_200) + F.col("id") * 7919 % 60_013)
    spark.range(60_000).select(F.col("id").alias("event_id"), ts.alias("ts"), (F.col("id") * 31 % 20_000).alias("user_id"), kind.alias("event_type")).write.parquet(f"{folder}/events.parquet")
    return folder


@pytest.mark.parametrize("name", ["wl_fold_batches", "fold_batch_invariance", "fold_repeat_users"])
def test_folds_of_associative_steps_take_no_rounds(spark, many_events, monkeypatch, name):
    def passed_on(df):
        raise AssertionError("a state went on from segment to segment")

    monkeypatch.setattr("sieveline.operators.semantic.cut", passed_on)
    equal_to_sql(spark, many_events, name, ["events"])


@pytest.mark.parametrize("name", ["fold_batch_invariance", "fold_repeat_users"])
def test_repeat_users_of_odd_events(spark, tmp_path, name):
    """Null users beside each other, only null ones repeated, no user repeated, no type."""
    from datetime import datetime, timedelta

    users = {"nulls": [None, None, 1, 2], "both": [5, None, 5, None, 7], "once": [1, 2, 3], None: [4, 4, None]}
    rows = [(k, u) for k, us in users.items() for u in us] + [("long", i * 31 % 1500) for i in range(2000)]
    rows = [(i, datetime(2024, 1, 1) + timedelta(seconds=i), u, k) for i, (k, u) in enumerate(rows)]
    spark.createDataFrame(rows, "event_id long, ts timestamp, user_id long, event_type string").write.parquet(f"{tmp_path}/events.parquet")
    equal_to_sql(spark, str(tmp_path), name, ["events"])


def test_events_are_numbered_and_merged_without_a_pass_a_state(spark, many_events):
    from sieveline import operators as O

    e = spark.read.parquet(f"{many_events}/events.parquet")
    numbered = O.numbered(e, ["event_type"], ["ts", "event_id"])._jdf.queryExecution().executedPlan().toString()
    assert "Window" not in numbered and "SortMergeJoin" not in numbered
    plan = catalogue.queries()["fold_repeat_users"](spark, many_events)._jdf.queryExecution().analyzed().toString()
    assert plan.count("flatten(transform(transform(__all") >= 2 and "aggregate(slice(__all" not in plan


def test_union_of_a_large_group_compares_no_item_with_all_others(spark):
    from pyspark.sql import functions as F

    from sieveline.plans.directives import union_items

    rows = [("b", "y"), ("a", None), ("b", "x"), None, ("a", None), ("b", "y"), (None, "z")]
    d = spark.createDataFrame([(1, rows[:3]), (2, rows[3:]), (3, []), (4, None)], "n int, items array<struct<type:string,span:string>>")
    out = d.filter("n < 4").groupBy().agg(F.collect_list(F.struct("n", "items")).alias("r")).select(union_items("items")(F.col("r")).alias("x"))
    assert [x and tuple(x) for x in out.first().x] == [(None, "z"), ("a", None), ("b", "x"), ("b", "y"), None]
    assert "array_distinct" not in out._jdf.queryExecution().optimizedPlan().toString()


def test_mixing_shuffles_packed_texts(spark):
    from pyspark.sql import functions as F

    import corpus_pipeline
    from sieveline.llm import mixing

    texts = ["one two three", "  ", "", None, "naïve 🎉 words\n\tand more " * 400, "a\x00b c"]
    rows = [(i, texts[i % len(texts)], "en", f"src{i % 2}", 0) for i in range(60)]
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = {tuple(r) for r in corpus_pipeline.mix(spark, d, "").collect()}
    assert got and got <= set(rows) and {r[1] for r in got} == {texts[0], texts[4], texts[5]}
    whole, size = "row.text", F.length(F.col("row.text"))
    packed = mixing.mix(d, carry=True).filter("doc_id % 6 = 4")
    assert dict(packed.select(whole).dtypes)["text"] == "binary" and packed.agg(F.max(size)).first()[0] < len(texts[4].encode()) / 10


def test_sign_buckets_shuffle_no_candidates(spark, sf, monkeypatch):
    import numpy as np
    from pyspark.sql import functions as F

    from sieveline import operators as O
    from sieveline.workloads import inputs as W

    e = W.table(spark, sf, "embeddings").select("vec_id", "embedding")
    a, b = e.filter("vec_id < 30").toDF("a", "v"), e.toDF("b", "v").unionByName(e.limit(1).select(F.lit(-1).alias("b"), F.lit(None).cast("array<float>").alias("v")))
    planes = np.random.Generator(np.random.Philox(key=7)).standard_normal((3, 4, 64))
    rows = {r.vec_id: np.array(r.embedding, float) for r in e.collect()}
    signs = {i: [tuple(p @ v >= 0) for p in planes] for i, v in rows.items()}
    near = lambda i, j: round(float(rows[i] @ rows[j]), 6) >= 0.1 and any(x == y for x, y in zip(signs[i], signs[j]))
    expect = sorted((i, j) for i in range(30) for j in rows if near(i, j))
    monkeypatch.setattr(O.pairs, "BLOCK_ROWS", 60)
    found = O.cosine_pairs(a, b, "a", "b", "v", 0.1, rounds=3, bits=4)
    assert sorted((r.a, r.b) for r in found.collect()) == expect and len(expect) > 60
    assert "Join" not in found._jdf.queryExecution().optimizedPlan().toString()


@pytest.fixture(scope="module")
def case_events(spark, tmp_path_factory):
    """Three days of 300 events, half of them errors, some written twice or with signs of tags and marks."""
    from datetime import datetime, timedelta

    folder = str(tmp_path_factory.mktemp("cases"))
    kinds = ["error", "view", "error", "<chunk>*", "errors", "error"]
    rows = [(i, datetime(2024, 1, 1 + i // 300) + timedelta(seconds=i), i * 7 % 11, kinds[i % 6], '{"k": "* <5> ' + str(i) + '"}') for i in range(900)]
    spark.createDataFrame(rows + rows[100:160], "event_id long, ts timestamp, user_id long, event_type string, props string").write.parquet(f"{folder}/events.parquet")
    return folder


def test_case_files_equal_sql_on_odd_events(spark, case_events):
    equal_to_sql(spark, case_events, "composite_case_files", ["events"])


@pytest.mark.parametrize("stage", ["metadata", "summaries", "gather", "gleaning"])
def test_case_files_need_each_stage(spark, case_events, monkeypatch, stage):
    """Without a stage, its rows otherwise the same, cases are lost."""
    from pyspark.sql import functions as F

    from sieveline import operators as O

    whole, gather, glean = catalogue.queries()["composite_case_files"](spark, case_events).agg(F.sum("n")).first()[0], O.gather, O.glean
    less = {
        "metadata": ("gather", lambda df, *a, **k: gather(df.withColumn("day", F.lit("")), *a, **k)),
        "summaries": ("gather", lambda df, *a, **k: gather(df.withColumn("summary", F.lit("")), *a, **k)),
        "gather": ("gather", lambda df, doc, order, content, p, **k: gather(df, doc, order, content, O.Peripheral(), **k)),
        "gleaning": ("glean", lambda df, task, model, satisfied, rounds, *a: glean(df, task, model, satisfied, 0, *a)),
    }
    monkeypatch.setattr(O, *less[stage])
    assert catalogue.queries()["composite_case_files"](spark, case_events).agg(F.sum("n")).first()[0] < whole


def test_recall_of_sign_buckets_is_of_all_vectors(spark, tmp_path, monkeypatch):
    """Close vectors, most of them not at every 20th id, some the same and one null, in several blocks and steps."""
    import numpy as np

    from sieveline import operators as O

    draw = np.random.default_rng(3)
    middles = draw.standard_normal((4, 64))
    vectors = [middles[i % 4] + draw.standard_normal(64) * (0, 0.8, 1.2)[i % 3] for i in range(90)]
    rows = [(i * 7 + 1, (v / np.linalg.norm(v)).astype(np.float32).tolist(), i % 4) for i, v in enumerate(vectors)]
    spark.createDataFrame([*rows, (5, None, 0)], "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    e = np.array([r[1] for r in rows], np.float64)
    signs = np.einsum("nd,rbd->nrb", e, np.random.Generator(np.random.Philox(key=7)).standard_normal((12, 4, 64))) >= 0
    close = np.round(e @ e.T, 6) >= 0.5
    met = (signs[:, None] == signs[None]).all(axis=3).any(axis=2)
    for name, n in (("BLOCK_ROWS", 30), ("STEP_ROWS", 4), ("MEET_ROWS", 16), ("PAIR_ROWS", 50)):
        monkeypatch.setattr(O.pairs, name, n, raising=False)
    r = catalogue.queries()["block_embedding_buckets"](spark, str(tmp_path)).first()
    assert (r.exact, r.found) == (close.sum(), (close & met).sum()) and r.exact > r.found > 90


def test_vectors_of_texts_need_no_shuffle(spark):
    import hashlib
    from collections import Counter

    from sieveline import operators as O

    texts = ["", None, "ab", "abc", "ABCABC abc", "naïve 🎉🎉🎉 x", "a\nb\nc", "large ring"]
    d = spark.createDataFrame(list(enumerate(texts)), "id long, t string").coalesce(1)
    out = O.hashed_vectors(d, "id", "t")
    for i, vector in out.collect():
        t = (texts[i] or "").lower()
        grams = [t[j : j + 3] for j in range(len(t) - 2)] if len(t) >= 3 else [t]
        counts = Counter(int(hashlib.md5(g.encode()).hexdigest()[:8], 16) % 64 for g in grams)
        norm = sum(c * c for c in counts.values()) ** 0.5
        assert list(vector) == [counts[j] / norm for j in range(64)]
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Explode" not in plan and "explode" not in plan
