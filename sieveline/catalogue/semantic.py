"""One query per operator variant."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import operators as O
from ..functions.prompts import Template, conform, parse_schema
from ..functions.text import pack_prompt, register_sql, token_count, truncate_middle
from ..model import Profile, SimulatedModel, Task, ledger
from ..operators.pairs import cosine, normalized, resolve_stepwise
from ..plans import directives as D
from ..plans.optimizer import required_sample, size_biased_sample
from ..workloads import inputs as W
from .registry import query, slot, spans, toks

CONTACT_SQL = {t: W.CLAUSES[t] for t in W.CONTACTS}
FLAT = ["doc_id", "x.type", "x.span"]


def flat(df, name="items"):
    return df.select("doc_id", F.explode(name).alias("x")).select(*FLAT)


@query(spans(CONTACT_SQL))
def map_extract_contacts(spark, sf):
    return flat(O.sem_map(W.documents(spark, sf), W.extraction(W.CONTACTS)))


@query(f"SELECT doc_id, lang, len({toks('text')})::BIGINT AS n FROM documents")
def map_drop_keys(spark, sf):
    task = Task("n", "text", lambda c: token_count(c).cast("long"), T.LongType())
    return O.sem_map(W.documents(spark, sf), task, drop_keys=("text", "source"))


@query("SELECT doc_id, 'Language: ' || CASE WHEN lang = 'en' THEN 'English' ELSE 'other (' || lang || ')' END || ' from ' || source AS prompt FROM documents")
def map_template_conditional(spark, sf):
    t = Template("Language: {% if lang = 'en' %}English{% else %}other ({{ input.lang }}){% endif %} from {{ input.source }}")
    t.check(["lang", "source"])
    return W.documents(spark, sf).select("doc_id", t.render().alias("prompt"))


@query("SELECT conv_id, 'Turns: ' || string_agg('[' || role || '] ', '' ORDER BY turn) AS prompt FROM conversations GROUP BY conv_id")
def map_template_loop(spark, sf):
    t = Template("Turns: {% for e in turns %}[{{ e.role }}] {% endfor %}")
    g = W.table(spark, sf, "conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role"))).alias("turns"))
    return g.select("conv_id", t.render().alias("prompt"))


@query(f"SELECT doc_id, regexp_matches(text, '{W.CLAUSES['abuse']}') AS toxic, length(text)::BIGINT AS chars, CASE WHEN len({toks('text')}) > 500 THEN 'long' ELSE 'short' END AS size FROM documents")
def parallel_map_profile(spark, sf):
    tasks = [
        Task("toxic", "text", lambda c: c.rlike(W.CLAUSES["abuse"]), T.BooleanType()),
        Task("chars", "text", lambda c: F.length(c).cast("long"), T.LongType()),
        Task("size", "text", lambda c: F.when(token_count(c) > 500, "long").otherwise("short"), T.StringType()),
    ]
    return O.sem_parallel_map(W.documents(spark, sf), tasks).select("doc_id", "toxic", "chars", "size")


@query(f"SELECT doc_id, lang FROM documents WHERE regexp_matches(text, '{W.CLAUSES['abuse']}')")
def filter_toxic(spark, sf):
    task = Task("toxic", "text", lambda c: c.rlike(W.CLAUSES["abuse"]), T.BooleanType())
    return O.sem_filter(W.documents(spark, sf), task).select("doc_id", "lang")


@query(f"SELECT source, count(*)::BIGINT AS n, sum(len({toks('text')}))::BIGINT AS n_tokens FROM documents GROUP BY source")
def reduce_by_source(spark, sf):
    d = W.documents(spark, sf).withColumn("k", token_count(F.col("text")))
    total = lambda rows: F.struct(F.size(rows).cast("long").alias("n"), F.aggregate(rows, F.lit(0).cast("long"), lambda a, r: a + r["k"]).alias("n_tokens"))
    merge = lambda xs: F.struct(F.aggregate(xs, F.lit(0).cast("long"), lambda a, x: a + x["n"]).alias("n"), F.aggregate(xs, F.lit(0).cast("long"), lambda a, x: a + x["n_tokens"]).alias("n_tokens"))
    return O.sem_reduce(d, ["source"], ["k"], total, merge=merge).select("source", "answer.*")


@query("SELECT conv_id, string_agg(role || ':' || substr(text, 1, 12), ' | ' ORDER BY turn) AS summary FROM conversations GROUP BY conv_id")
def reduce_ordered_dialogue(spark, sf):
    join = lambda rows: F.array_join(F.transform(rows, lambda r: F.concat(r["role"], F.lit(":"), F.substring(r["text"], 1, 12))), " | ")
    return O.sem_reduce(W.table(spark, sf, "conversations"), ["conv_id"], ["role", "text"], join, "summary", ["turn"])


@query("SELECT user_id, strftime(ts, '%Y-%m-%d') AS day, count(*)::BIGINT AS n, max(value) AS top FROM events GROUP BY ALL")
def reduce_user_day(spark, sf):
    e = W.table(spark, sf, "events").withColumn("day", F.date_format("ts", "yyyy-MM-dd"))
    both = lambda rows: F.struct(F.size(rows).cast("long").alias("n"), F.array_max(F.transform(rows, lambda r: r["value"])).alias("top"))
    return O.sem_reduce(e, ["user_id", "day"], ["value"], both).select("user_id", "day", "answer.*")


@query("SELECT string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types FROM events")
def reduce_global(spark, sf):
    """The whole table is one group, summarised in parts and merged."""
    kinds = lambda rows: F.array_distinct(F.transform(rows, lambda r: r["event_type"]))
    merge = lambda xs: F.array_join(F.array_sort(F.array_distinct(F.flatten(xs))), ",")
    return O.sem_reduce(W.table(spark, sf, "events"), [], ["event_type"], kinds, "types", merge=merge)


def _placed_events(spark, sf):
    """Events with their place in their type by time, numbered once for all folds over them."""
    e = W.table(spark, sf, "events").select("event_type", "user_id", "ts", "event_id")
    return O.numbered(e, ["event_type"], ["ts", "event_id"], "place").select("event_type", "user_id", "place")


def _repeated(users):
    """Of sorted users those that equal the one before them."""
    return F.filter(users, lambda u, i: (i > 0) & u.eqNullSafe(F.get(users, i - 1)))


def _once(value, use):
    """``use`` of a value that is made once: as a lambda's own variable."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _repeat_users(placed, size):
    """Users named in more than one event of their type; the scratchpad holds all seen so far."""
    zero = F.struct(F.array().cast("array<bigint>").alias("out"), F.array().cast("array<bigint>").alias("seen"))

    def step(acc, rows):
        def after(users):
            again = F.array_union(_repeated(users), F.array_intersect(users, acc["seen"]))
            return F.struct(F.array_union(acc["out"], again).alias("out"), F.array_union(acc["seen"], users).alias("seen"))

        return _once(F.sort_array(F.transform(rows, lambda r: r["user_id"])), after)

    def merge_all(states):
        # Each scratchpad names a user once, so that equal neighbours come from two of them.
        of = lambda k: F.flatten(F.transform(states, lambda s: s[k]))
        return _once(F.sort_array(of("seen")), lambda users: F.struct(F.array_union(of("out"), _repeated(users)).alias("out"), F.array_distinct(users).alias("seen")))

    f = O.fold(placed, ["event_type"], ["user_id"], [], size, zero, step, lambda s: F.sort_array(s["out"]), "users", segment=max(8, 32 // size), places="place", merge_all=merge_all)
    return f.filter(F.size("users") > 0)


_REPEAT_SQL = "SELECT event_type, count(*)::BIGINT AS n, sum(user_id)::BIGINT AS users FROM (SELECT event_type, user_id FROM events GROUP BY ALL HAVING count(*) > 1) GROUP BY event_type"


@query(f"SELECT r.*, c.n_calls FROM ({_REPEAT_SQL}) r JOIN (SELECT event_type, ceil(count(*) / 41.0)::BIGINT AS n_calls FROM events GROUP BY 1) c USING (event_type)")
def fold_repeat_users(spark, sf):
    f = _repeat_users(_placed_events(spark, sf), 41).filter("event_type IS NOT NULL")
    total = F.aggregate("users", F.lit(None).cast("long"), lambda a, x: F.coalesce(a + x, a, x))
    return f.select("event_type", F.size("users").cast("long").alias("n"), total.alias("users"), "n_calls")


@query(f"SELECT b.size, r.event_type, r.n FROM (VALUES (1), (7), (64)) b(size) CROSS JOIN ({_REPEAT_SQL}) r")
def fold_batch_invariance(spark, sf):
    out, placed = None, _placed_events(spark, sf)
    for size in (1, 7, 64):
        f = _repeat_users(placed, size).select(F.lit(size).alias("size"), "event_type", F.size("users").cast("long").alias("n"))
        out = f if out is None else out.unionByName(f)
    return out


_MEAN = f"(SELECT greatest(avg(len({toks('text')})), 1) AS mean FROM documents)"


@query(f"SELECT p AS percent, greatest(1, floor(4000 * p / 100.0::DOUBLE / mean))::INT AS batch FROM (VALUES (20), (40), (60), (75), (90)) v(p), {_MEAN}")
def fold_batch_candidates(spark, sf):
    """Batches that fill shares of the context window with documents of mean length."""
    sizes = D.fold_batches(4000, D.mean_tokens(W.documents(spark, sf), "text"))
    return spark.createDataFrame(list(zip((20, 40, 60, 75, 90), sizes)), "percent int, batch int")


@query("SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY event_type")
def tree_reduce_counts(spark, sf):
    e = W.table(spark, sf, "events").withColumn("n", F.lit(1).cast("long"))
    return O.tree_reduce(e, ["event_type"], "n", ["event_id"], 32, lambda vs: F.aggregate(vs, F.lit(0).cast("long"), lambda a, x: a + x))


@query("WITH s AS (SELECT DISTINCT p_name FROM part) SELECT p_name AS clean, count(*)::BIGINT AS n_variants FROM s, (VALUES (0), (1), (2)) GROUP BY p_name")
def resolve_part_names(spark, sf):
    """Three spellings of every part name come back as one canonical value."""
    p = W.table(spark, sf, "part").select("p_name").distinct()
    noisy = p.select("p_name", F.explode(F.array(F.struct(F.col("p_name").alias("v"), F.lit(3).alias("c")), F.struct(F.upper("p_name").alias("v"), F.lit(1).alias("c")), F.struct(F.concat("p_name", F.lit("!")).alias("v"), F.lit(1).alias("c")))).alias("x"))
    rows = noisy.select(F.col("x.v").alias("name"), F.explode(F.sequence(F.lit(1), F.col("x.c"))).alias("i"))
    out = O.resolve(rows, "name", O.normalized_pairs(rows, "name"), lambda x, y: normalized(x) == normalized(y), "clean")
    return out.select("clean", "name").distinct().groupBy("clean").agg(F.count(F.lit(1)).alias("n_variants"))


@query("SELECT substr(n_name, 1, 6) AS key, min(n_name) AS canonical, count(*)::BIGINT AS n FROM nation GROUP BY 1")
def resolve_components(spark, sf):
    """Clusters of a chain of links: neighbours in order that share six letters."""
    from pyspark.sql import Window

    n = W.table(spark, sf, "nation").withColumn("key", F.substring("n_name", 1, 6))
    links = n.withColumn("x", F.lag("n_name").over(Window.partitionBy("key").orderBy("n_name"))).filter("x is not null").select("x", F.col("n_name").alias("y"))
    labels = O.components(links)
    return n.join(labels, n["n_name"] == labels["node"], "left").select("key", F.coalesce("label", "n_name").alias("canonical")).groupBy("key", "canonical").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT count(DISTINCT md5(lower(trim(text))))::BIGINT AS n_texts FROM documents")
def resolve_near_copies(spark, sf):
    d = W.documents(spark, sf).select("doc_id", F.md5("text").alias("h"), F.md5(F.lower(F.trim("text"))).alias("n"))
    pairs = d.groupBy("n").agg(F.min("h").alias("x"), F.collect_set("h").alias("ys")).select("x", F.explode("ys").alias("y")).filter("x != y")
    return O.resolve(d, "h", pairs, lambda x, y: x != y).agg(F.countDistinct("h").alias("n_texts"))


@query("SELECT upper(n_name) AS a, upper(r_name) AS b, count(*)::BIGINT AS n FROM nation JOIN region ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey GROUP BY ALL")
def resolve_two_keys(spark, sf):
    """Two keys resolved as one: pairs of values, each in the plain or the lower-cased spelling."""
    n, r, c = (W.table(spark, sf, x) for x in ("nation", "region", "customer"))
    j = c.join(n, c["c_nationkey"] == n["n_nationkey"]).join(r, n["n_regionkey"] == r["r_regionkey"])
    low = F.col("c_custkey") % 3 == 0
    noisy = j.select(F.when(low, F.lower("n_name")).otherwise(F.col("n_name")).alias("a"), F.when(low, F.lower("r_name")).otherwise(F.col("r_name")).alias("b"))
    same = lambda x, y: (F.lower(x["a"]) == F.lower(y["a"])) & (F.lower(x["b"]) == F.lower(y["b"]))
    noisy = O.resolve_jointly(noisy, ["a", "b"], normalized, same)
    return noisy.select(F.upper("a").alias("a"), F.upper("b").alias("b")).groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


_PARITY = "CASE WHEN n_nationkey % 2 = 0 THEN 0 ELSE 1 END"


@query(f"WITH n AS (SELECT *, {_PARITY} AS p FROM nation), l AS (SELECT p, min(n_name) AS x FROM n GROUP BY p), s AS (SELECT l.p, n.n_regionkey AS r FROM l JOIN n ON n.n_name = l.x) SELECT (SELECT count(*) FROM nation)::BIGINT - (SELECT count(*) - count(DISTINCT n.p) FROM n JOIN s ON n.p = s.p AND n.n_regionkey = s.r)::BIGINT AS clusters")
def resolve_context(spark, sf):
    """Names whose numbers have one parity may be the same; only the regions that stand beside them tell."""
    n = W.table(spark, sf, "nation").join(W.table(spark, sf, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_name", "r_name")
    odd = lambda x: (F.regexp_extract(x, "[0-9]+", 0).cast("int") % 2).cast("string")
    out = O.resolve(n, "n_name", O.keyed_pairs(n, "n_name", odd), lambda x, y, cx, cy: cx == cy, context="r_name")
    return out.agg(F.countDistinct("n_name").alias("clusters"))


@query(f"SELECT count(DISTINCT n_regionkey * 2 + {_PARITY})::BIGINT AS clusters FROM nation")
def resolve_transitivity_skip(spark, sf):
    """Pairs inside a region; those of unlike parity are refused, the others settled by the strongest first."""
    n = W.table(spark, sf, "nation").select("n_name", "n_regionkey")
    a, b = n.alias("a"), n.alias("b")
    pairs = a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_name") < F.col("b.n_name"))).select(F.col("a.n_name").alias("x"), F.col("b.n_name").alias("y"))
    pairs = pairs.withColumn("sim", F.conv(F.substring(F.md5(F.concat("x", "y")), 1, 4), 16, 10).cast("double") / 65536)
    odd = lambda x: F.regexp_extract(x, "[0-9]+", 0).cast("int") % 2
    links, _ = resolve_stepwise(pairs, lambda x, y: odd(x) == odd(y))
    labels = O.components(links)
    return n.join(labels, n["n_name"] == labels["node"], "left").agg(F.countDistinct(F.coalesce("label", "n_name")).alias("clusters"))


def passage_pairs(spark, sf):
    return O.all_words_pairs(W.documents(spark, sf), "doc_id", "text", W.table(spark, sf, "benchmark").withColumnRenamed("text", "label"), "item_id", "label")


def _passages(spark, sf, how="inner"):
    d, b = W.documents(spark, sf), W.table(spark, sf, "benchmark").withColumnRenamed("text", "label")
    return O.equijoin(d, b, "doc_id", "item_id", passage_pairs(spark, sf), lambda m: F.contains("text", "label"), how)


_PASSAGE_SQL = "SELECT d.doc_id, b.item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)"


@query(_PASSAGE_SQL)
def equijoin_passages(spark, sf):
    return _passages(spark, sf).select("doc_id", "item_id")


@query(f"SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM ({_PASSAGE_SQL}))")
def equijoin_semi(spark, sf):
    return _passages(spark, sf, "semi").select("doc_id", "lang")


@query(f"SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM ({_PASSAGE_SQL}))")
def equijoin_anti(spark, sf):
    return _passages(spark, sf, "anti").select("doc_id", "lang")


@query(f"SELECT d.doc_id, p.item_id FROM documents d LEFT JOIN ({_PASSAGE_SQL}) p USING (doc_id)")
def equijoin_left(spark, sf):
    return _passages(spark, sf, "left").select("doc_id", "item_id")


@query(f"SELECT doc_id, item_id, rank::INT AS rank FROM (SELECT p.doc_id, p.item_id, row_number() OVER (PARTITION BY p.doc_id ORDER BY length(b.text) DESC, p.item_id) AS rank FROM ({_PASSAGE_SQL}) p JOIN benchmark b USING (item_id)) WHERE rank <= 2")
def equijoin_topk(spark, sf):
    return O.sem_rank(_passages(spark, sf), ["doc_id"], F.length("label"), ["item_id"], 2).select("doc_id", "item_id", "rank")


_WORDS = "list_distinct(list_filter(string_split_regex(lower({}), '[^a-zà-ÿß0-9]+'), lambda w: w <> ''))"


@query(f"WITH d AS (SELECT doc_id, unnest({_WORDS.format('text')}) AS w FROM documents), b AS (SELECT item_id, unnest({_WORDS.format('text')}) AS w FROM benchmark), n AS (SELECT item_id, count(*) AS n FROM b GROUP BY 1), f AS (SELECT w, count(*) AS c FROM d WHERE w IN (SELECT w FROM b) GROUP BY 1), r AS (SELECT item_id, arg_min(b.w, (coalesce(c, 0), b.w)) AS w FROM b LEFT JOIN f USING (w) GROUP BY 1), p AS (SELECT doc_id, item_id FROM d JOIN r USING (w)) SELECT p.doc_id, p.item_id FROM p JOIN b USING (item_id) JOIN d ON d.doc_id = p.doc_id AND d.w = b.w JOIN n ON n.item_id = p.item_id GROUP BY p.doc_id, p.item_id HAVING count(*) = max(n)")
def block_all_words(spark, sf):
    return passage_pairs(spark, sf)


@query("SELECT min(p_name) AS x, max(v) AS y FROM (SELECT DISTINCT p_name, upper(p_name) AS v FROM part) GROUP BY p_name HAVING min(p_name) <> max(v)")
def block_normalized(spark, sf):
    p = W.table(spark, sf, "part").select(F.explode(F.array("p_name", F.upper("p_name"))).alias("v"))
    pairs = O.normalized_pairs(p, "v")
    return pairs.select(F.greatest("x", "y").alias("x"), F.least("x", "y").alias("y"))


_DOT = "list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE))"


@query(f"SELECT a.vec_id AS a_id, b.vec_id AS b_id FROM embeddings a, embeddings b WHERE a.vec_id % 20 = 0 AND round({_DOT}, 6) >= 0.3")
def block_embedding_exact(spark, sf):
    e = W.table(spark, sf, "embeddings")
    left = e.filter("vec_id % 20 = 0").select(F.col("vec_id").alias("a_id"), "embedding")
    right = e.select(F.col("vec_id").alias("b_id"), "embedding")
    return O.cosine_pairs(left, right, "a_id", "b_id", "embedding", 0.3).select("a_id", "b_id")


@query()
def block_embedding_buckets(spark, sf):
    """Recall of sign buckets against the exact pairs, of every vector with all."""
    e = W.table(spark, sf, "embeddings")
    left = e.select(F.col("vec_id").alias("a_id"), "embedding")
    right = e.select(F.col("vec_id").alias("b_id"), "embedding")
    exact = O.cosine_pairs(left, right, "a_id", "b_id", "embedding", 0.5).select("a_id", "b_id")
    near = O.cosine_pairs(left, right, "a_id", "b_id", "embedding", 0.5, rounds=12, bits=4).select("a_id", "b_id").withColumn("hit", F.lit(1))
    return exact.join(near, ["a_id", "b_id"], "left").agg(F.count(F.lit(1)).alias("exact"), F.sum("hit").alias("found"))


_LIKELY = f"SELECT a_id, b_id, sim, m FROM (SELECT a.vec_id AS a_id, b.vec_id AS b_id, round({_DOT}, 6) AS sim, a.label = b.label AS m FROM embeddings a, embeddings b WHERE a.vec_id % 20 = 0 AND a.vec_id <> b.vec_id) ORDER BY sim DESC, a_id, b_id LIMIT 300"


def _likely(spark, sf):
    """The 300 most similar pairs of every 20th vector with all others; a pair is true if the labels agree."""
    e = W.table(spark, sf, "embeddings").select("vec_id", "embedding", "label")
    a, b = e.select(F.col("vec_id").alias("a_id"), "embedding", F.col("label").alias("la")).filter("a_id % 20 = 0"), e.select(F.col("vec_id").alias("b_id"), "embedding", F.col("label").alias("lb"))
    # No more than 300 of the best pairs can be of one vector, which itself comes first.
    near = O.similar(a, b, "a_id", "b_id", "embedding", k=301).filter("a_id != b_id")
    sample = O.likely_pairs(near, "sim", 300, ["a_id", "b_id"])
    return sample.join(a.select("a_id", "la"), "a_id").join(b.select("b_id", "lb"), "b_id").withColumn("match", F.col("la") == F.col("lb"))


@query(f"WITH p AS ({_LIKELY}), t AS (SELECT sim, row_number() OVER (ORDER BY sim DESC) AS r, count(*) OVER () AS n FROM p WHERE m) SELECT max(CASE WHEN r = ceil(n * 0.95::DOUBLE) THEN sim END) AS threshold, count(*)::BIGINT AS true_pairs FROM t")
def tune_threshold_embeddings(spark, sf):
    """The largest cosine threshold that keeps 95 % of the true pairs among the likely ones."""
    return O.tune_threshold(_likely(spark, sf), "sim", "match")


_BOTH = "WITH a AS (SELECT doc_id, md5(text) AS h, length(text) AS n, lang FROM documents), s AS (SELECT x.doc_id AS x, y.doc_id AS y FROM a x JOIN a y ON x.h = y.h AND x.doc_id < y.doc_id), l AS (SELECT x.doc_id AS x, y.doc_id AS y FROM a x JOIN a y ON x.n = y.n AND x.lang = y.lang AND x.doc_id < y.doc_id) "


@query(_BOTH + "SELECT (SELECT count(*) FROM (SELECT * FROM s UNION SELECT * FROM l))::BIGINT AS either, (SELECT count(*) FROM (SELECT * FROM s INTERSECT SELECT * FROM l))::BIGINT AS both")
def block_combined(spark, sf):
    """Two code rules, equal digest and equal length in one language: pairs of either and of both."""
    d = W.documents(spark, sf).select("doc_id", F.md5("text").alias("h"), F.length("text").alias("n"), "lang")

    def rule(*on):
        b = d.toDF(*[f"y_{c}" for c in d.columns])
        cond = F.col("doc_id") < F.col("y_doc_id")
        for c in on:
            cond = cond & (F.col(c) == F.col(f"y_{c}"))
        return d.join(b, cond).select(F.col("doc_id").alias("x"), F.col("y_doc_id").alias("y"))

    rules = [rule("h"), rule("n", "lang")]
    count = lambda how: O.combined(rules, ["x", "y"], how).agg(F.count(F.lit(1)))
    return count("or").toDF("either").crossJoin(count("and").toDF("both"))


@query("SELECT conv_id, turn, role FROM conversations")
def unnest_turns(spark, sf):
    g = W.table(spark, sf, "conversations").groupBy("conv_id").agg(F.collect_list(F.struct("turn", "role")).alias("t"))
    return O.unnest_fields(O.unnest(g, "t"), "t")


@query("SELECT d.doc_id, s.type, s.span FROM documents d LEFT JOIN (" + spans(CONTACT_SQL) + ") s USING (doc_id)")
def unnest_outer(spark, sf):
    m = O.sem_map(W.documents(spark, sf), W.extraction(W.CONTACTS))
    return O.unnest(m, "items", keep_empty=True).select("doc_id", "items.type", "items.span")


@query("SELECT event_id, (props::JSON->>'k')::BIGINT AS k FROM events")
def unnest_dict_props(spark, sf):
    e = W.table(spark, sf, "events").withColumn("p", conform(F.col("props"), parse_schema("{k: int}")))
    return O.unnest_fields(e.select("event_id", "p"), "p")


_SPLIT = f"SELECT doc_id, i + 1 AS split_chunk_num, array_to_string(list_slice(t, i * 100 + 1, i * 100 + 100), ' ') AS text_chunk FROM (SELECT doc_id, {toks('text')} AS t FROM documents), range(0, ceil(len(t) / 100.0)::BIGINT) r(i)"


@query(f"SELECT doc_id, split_chunk_num::INT AS split_chunk_num, text_chunk FROM ({_SPLIT})")
def split_tokens(spark, sf):
    return O.split_tokens(W.documents(spark, sf), "text", 100).select("doc_id", "split_chunk_num", "text_chunk")


_LINES = "SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: trim(x) <> '') AS t FROM documents"


@query(f"SELECT doc_id, (i + 1)::INT AS n, t[i + 1] AS piece FROM ({_LINES}), range(0, len(t)) r(i)")
def split_delimiter(spark, sf):
    return O.split_delimiter(W.documents(spark, sf), "text", "\n").select("doc_id", F.col("split_chunk_num").alias("n"), F.col("text_chunk").alias("piece"))


@query(f"SELECT doc_id, (i + 1)::INT AS n, array_to_string(list_slice(t, i * 3 + 1, i * 3 + 3), chr(10)) AS piece FROM ({_LINES}), range(0, ceil(len(t) / 3.0)::BIGINT) r(i)")
def split_delimiter_group(spark, sf):
    return O.split_delimiter(W.documents(spark, sf), "text", "\n", 3).select("doc_id", F.col("split_chunk_num").alias("n"), F.col("text_chunk").alias("piece"))


def _gathered(spark, sf, p, **more):
    c = O.split_tokens(W.documents(spark, sf), "text", 100)
    for k, v in more.items():
        c = c.withColumn(k, v)
    return O.gather(c, "split_id", "split_chunk_num", "text_chunk", p).select("doc_id", "split_chunk_num", F.md5("text_chunk_rendered").alias("rendered"))


_WRAP = "md5(CASE WHEN {p} <> '' THEN '<previous>' || {p} || '</previous>' ELSE '' END || '<chunk>' || text_chunk || '</chunk>' || CASE WHEN {n} <> '' THEN '<next>' || {n} || '</next>' ELSE '' END)"


def _gather_sql(p: str, n: str = "''", extra: str = "") -> str:
    return f"SELECT doc_id, split_chunk_num::INT AS split_chunk_num, {_WRAP.format(p='p', n='n')} AS rendered FROM (SELECT *, {p} AS p, {n} AS n FROM (SELECT *, {extra or '0 AS z'} , count(*) OVER (PARTITION BY doc_id) AS total, list(text_chunk) OVER (PARTITION BY doc_id ORDER BY split_chunk_num ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS xs FROM ({_SPLIT})))"


def _gap(count: str) -> str:
    return f"CASE WHEN {count} > 0 THEN ['[... ' || ({count}) || ' chunks ...]'] ELSE []::VARCHAR[] END"


_I = "split_chunk_num"


@query(_gather_sql(f"array_to_string(list_concat({_gap(f'{_I} - 2')}, list_slice(xs, greatest({_I} - 1, 1), {_I} - 1)), chr(10))", f"array_to_string(list_concat(list_slice(xs, {_I} + 1, {_I} + 1), {_gap(f'total - {_I} - 1')}), chr(10))"))
def gather_prev_next(spark, sf):
    return _gathered(spark, sf, O.Peripheral(O.Side(tail=1), O.Side(head=1)))


@query(_gather_sql(f"array_to_string(list_concat(list_slice(xs, 1, least(1, {_I} - 1)), list_transform(list_slice(xs, 2, greatest({_I} - 3, 0)), lambda x: substr(x, 1, 8)), list_slice(xs, greatest(2, {_I} - 2), {_I} - 1)), chr(10))", f"array_to_string({_gap(f'total - {_I}')}, chr(10))"))
def gather_head_middle_tail(spark, sf):
    p = O.Peripheral(O.Side(head=1, tail=2, middle=True, middle_key="short"))
    return _gathered(spark, sf, p, short=F.substring("text_chunk", 1, 8))


_HALF = f"list_slice(string_split(xs[{_I} - 1], ' '), len(string_split(xs[{_I} - 1], ' ')) - ceil(len(string_split(xs[{_I} - 1], ' ')) * 0.5)::BIGINT + 1, len(string_split(xs[{_I} - 1], ' ')))"


@query(_gather_sql(f"CASE WHEN {_I} > 1 THEN array_to_string({_HALF}, ' ') ELSE '' END", f"array_to_string({_gap(f'total - {_I}')}, chr(10))"))
def gather_fraction(spark, sf):
    return _gathered(spark, sf, O.Peripheral(O.Side(fraction=0.5)))


@query(_gather_sql(f"array_to_string(list_transform(list_slice(xs, 1, {_I} - 1), lambda x: substr(x, 1, 8)), chr(10))", f"array_to_string({_gap(f'total - {_I}')}, chr(10))"))
def gather_summaries(spark, sf):
    return _gathered(spark, sf, O.Peripheral(O.Side(middle=True, middle_key="short")), short=F.substring("text_chunk", 1, 8))


@query("SELECT conv_id, turn, coalesce(lag(role) OVER (PARTITION BY conv_id ORDER BY turn), '') AS before FROM conversations")
def gather_turns(spark, sf):
    c = W.table(spark, sf, "conversations")
    g = O.gather(c, "conv_id", "turn", "role", O.Peripheral(O.Side(tail=1)), "r")
    return g.select("conv_id", "turn", F.regexp_replace(F.regexp_extract("r", "(?s)<previous>(.*)</previous>", 1), "(?s)^.*\n", "").alias("before"))


@query("SELECT r_name || '/' || n_name || '/' || c_name AS customer, '# ' || r_name || ' > ## ' || n_name AS lineage FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def gather_header_lineage(spark, sf):
    rows = W.ledger(spark, sf).withColumn("headers", F.array(F.struct("level", F.col("line").alias("header"))))
    out = O.header_lineage(rows, "region", "pos", "headers")
    low = out.filter("level = 3")
    n = F.regexp_extract("lineage", "> ## (.*)$", 1)
    return low.select(F.concat_ws("/", "region", n, F.substring("line", 5, 100)).alias("customer"), "lineage")


_SIM = SimulatedModel(Profile("s", 10**6, keep=700, per_hundred_tokens=0, per_ask=0, floor=0, hallucination=0, gleaning_bonus=0), "0")


def _kept(turn: int, bound: int) -> str:
    key = f"'0|s|' || doc_id || '|' || type || '|' || span || '|{turn}'"
    return f"{slot(key)} < {bound}"


_ANY = f"SELECT DISTINCT doc_id FROM ({spans(CONTACT_SQL)})"


@query(
    f"WITH g AS ({spans(CONTACT_SQL)}), a AS (SELECT doc_id, sum(({_kept(0, 700)})::INT) AS n0, sum(({_kept(1, 700)})::INT) AS n1 FROM g GROUP BY doc_id) "
    "SELECT doc_id, (CASE WHEN n0 > 0 THEN 1 ELSE 2 END)::INT AS attempts, (CASE WHEN n0 > 0 THEN n0 ELSE n1 END)::INT AS n FROM a"
)
def validate_retry(spark, sf):
    """Documents with contacts must give some; those whose answer is empty are asked once more."""
    task = W.extraction(W.CONTACTS)
    d = W.documents(spark, sf).filter(F.size(W.items(F.col("text"), W.CONTACTS)) > 0)
    out = O.validate_retry(d, task, _SIM, ["size(items) > 0"], 1)
    return out.select("doc_id", "attempts", F.size("items").alias("n"))


@query(f"SELECT doc_id, CASE WHEN len(t) <= 50 THEN text ELSE array_to_string(list_slice(t, 1, 25), ' ') || ' [...] ' || array_to_string(list_slice(t, len(t) - 24, len(t)), ' ') END AS cut FROM (SELECT doc_id, text, {toks('text')} AS t FROM documents)")
def truncate_middle_50(spark, sf):
    return W.documents(spark, sf).select("doc_id", truncate_middle(F.col("text"), 50).alias("cut"))


@query(f"SELECT doc_id, (len({toks('text')}) > 48)::BOOLEAN AS was_cut FROM documents")
def pack_prompt_tiers(spark, sf):
    d = W.documents(spark, sf).select("doc_id", "lang", "text")
    p = pack_prompt(d, ["doc_id"], ["lang"], 50)
    return p.select("doc_id", F.contains("prompt", F.lit("[...]")).alias("was_cut"))


@query(f"SELECT count(*)::BIGINT AS n, sum(len({toks('text')}))::BIGINT AS total, max(len({toks('text')}))::BIGINT AS longest FROM documents")
def token_stats(spark, sf):
    register_sql(spark)
    W.documents(spark, sf).createOrReplaceTempView("__docs")
    return spark.sql("SELECT count(*) AS n, cast(sum(sem_tokens(text)) AS bigint) AS total, cast(max(sem_tokens(text)) AS bigint) AS longest FROM __docs")


@query("SELECT doc_id FROM documents ORDER BY -ln((('0x' || substr(md5('0|' || doc_id), 1, 8))::BIGINT + 1.0) / 4294967297.0) / greatest(n_chars, 1), doc_id LIMIT 50")
def sample_size_biased(spark, sf):
    return size_biased_sample(W.table(spark, sf, "documents"), "doc_id", F.col("n_chars"), 50).select("doc_id")


@query("WITH s AS (SELECT avg((lang = 'en')::INT) AS a, sum((lang = 'en' AND contains(text, '.'))::INT) / sum((lang = 'en')::INT) AS b FROM documents) SELECT 20::BIGINT AS base, ceil(20 / (a * b))::BIGINT AS grown FROM s")
def selectivity_scaling(spark, sf):
    """The sample that two filters after each other ask for: their selectivities are measured."""
    d = W.documents(spark, sf)
    n, first, second = d.agg(F.count(F.lit(1)), F.sum((F.col("lang") == "en").cast("int")), F.sum(((F.col("lang") == "en") & F.contains("text", F.lit("."))).cast("int"))).first()
    return spark.createDataFrame([(20, required_sample(20, [first / n, second / first]))], "base long, grown long")


@query(f"WITH m AS (SELECT mean FROM {_MEAN}), c AS (SELECT 4000 * (15 + 15 * i) // 100 AS n FROM range(5) r(i) UNION SELECT floor(mean * (15 + 17 * i) / 100)::BIGINT FROM m, range(6) r(i)) SELECT DISTINCT greatest(1, n)::BIGINT AS n FROM c WHERE n <= 4000")
def chunk_candidates(spark, sf):
    """Chunk sizes to try for documents of the table's mean length."""
    return spark.createDataFrame([(n,) for n in D.chunk_sizes(4000, D.mean_tokens(W.documents(spark, sf), "text"))], "n long")


@query(f"SELECT share, (3 + CASE WHEN r > 1.5 THEN (floor(sqrt(r)) > 1)::INT + (r > 10)::INT + (r > 5)::INT ELSE 0 END)::INT AS shapes FROM (SELECT share, mean / greatest(1, floor(mean * share / 100)) AS r FROM {_MEAN}, (VALUES (90), (40), (15), (5)) s(share))")
def gather_candidates(spark, sf):
    """How many context shapes are tried as chunks get smaller against the table's mean document."""
    mean = D.mean_tokens(W.documents(spark, sf), "text")
    return spark.createDataFrame([(s, len(D.gather_shapes(mean, max(1, int(mean * s / 100)), "s"))) for s in (90, 40, 15, 5)], "share int, shapes int")


@query(f"SELECT count(*)::BIGINT AS calls, sum(least(len({toks('text')}), 4000))::BIGINT AS tokens_in FROM documents")
def metric_cost(spark, sf):
    task = W.extraction(W.CONTACTS)
    model = SimulatedModel()
    return ledger(O.sem_map(W.documents(spark, sf), task, model), task, model).select("calls", "tokens_in")


@query("SELECT vec_id, round(list_sum(list_transform(list_zip(embedding, embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)), 4) AS norm FROM embeddings")
def vector_norms(spark, sf):
    return W.table(spark, sf, "embeddings").select("vec_id", F.round(cosine(F.col("embedding"), F.col("embedding")), 4).alias("norm"))
