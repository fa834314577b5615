"""Blocking, resolve, equijoin and map-search-filter: everything that compares pairs.

Unblocked pairs are never enumerated. Rules become joins: normalised equality is a hash
key, "all words of the label" meets on the label's rarest word only, cosine blocking
compares hashed vectors inside sign buckets (several rounds) or exactly by matrix products
with blocks of the smaller side.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..store import cut, stored
from .components import components  # noqa: F401

#: Vectors of the smaller side that are sent to the tasks at once; rows of the other side in one product.
BLOCK_ROWS, STEP_ROWS = 16_384, 256
#: Vectors that meet a block's buckets at once, and pairs found there that go out at once.
MEET_ROWS, PAIR_ROWS = 2_048, 65_536


def words(text: Column) -> Column:
    """Distinct lower-cased runs of letters of the languages served."""
    return F.array_distinct(F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-zà-ÿß0-9]+"), lambda w: w != ""))


def normalized(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), "[^a-z0-9]+", " "))


def normalized_pairs(df: DataFrame, key: str) -> DataFrame:
    """Distinct value pairs (x, y), x < y, that are equal after normalisation: each with its class's least only."""
    return keyed_pairs(df, key, normalized)


def keyed_pairs(df: DataFrame, key: str, rule: Callable[[Column], Column]) -> DataFrame:
    """Distinct value pairs (x, y), x < y, on which a code rule agrees: each with its class's least only."""
    values = df.select(F.col(key).alias("v")).distinct().withColumn("n", rule(F.col("v")))
    least = values.groupBy("n").agg(F.min("v").alias("x"))
    return values.join(least, "n").filter("x < v").select("x", F.col("v").alias("y"))


def all_words_pairs(left: DataFrame, left_id: str, text: str, right: DataFrame, right_id: str, label: str) -> DataFrame:
    """(left_id, right_id) where all words of the label stand in the text.

    Each label probes with its rarest word of the left corpus alone; the other words are
    checked on the pairs that this finds, and no pair of the rule can be missed. Texts stay
    at their scan as long as labels and found pairs are small enough for Spark to broadcast:
    both are stored, so that it knows. Labels without any word match nothing.
    """
    lw = left.select(left_id, words(F.col(text)).alias("lw"))
    index = lw.select(left_id, F.explode("lw").alias("w"))
    rw = right.select(right_id, words(F.col(label)).alias("rw"))
    probe = stored(rw.select(right_id, F.explode("rw").alias("w")), "probe")
    counts = index.join(probe.select("w").distinct(), "w", "left_semi").groupBy("w").agg(F.count(F.lit(1)).alias("n"))
    rarest = stored(probe.join(counts, "w", "left").groupBy(right_id).agg(F.min_by("w", F.struct(F.coalesce("n", F.lit(0)), "w")).alias("w")), "rarest")
    found = stored(index.join(rarest, "w").select(left_id, right_id), "pairs")
    checked = lw.join(found, left_id).join(rw, right_id)
    return checked.filter(F.size(F.array_except("rw", "lw")) == 0).select(left_id, right_id)


def combined(rules: list[DataFrame], keys: list[str], how: str = "or") -> DataFrame:
    """Candidate pairs that any rule (``or``) or all of them (``and``) propose."""
    out = rules[0].select(*keys).distinct()
    for r in rules[1:]:
        other = r.select(*keys).distinct()
        out = out.unionByName(other).distinct() if how == "or" else out.join(other, keys, "left_semi")
    return out


def text_vector(text: Column, dims: int = 64) -> Column:
    """L2-normalised counts of a text's hashed character trigrams, lower-cased; a shorter text is one of its own."""
    slots: dict = {}

    def slot(gram: str) -> int:
        return int(hashlib.md5(gram.encode()).hexdigest()[:8], 16) % dims

    @F.arrow_udf("array<double>")
    def vectors(texts: pa.Array) -> pa.Array:
        rows = texts.to_pylist()
        sizes = np.array([len(t) for t in rows], np.int64)
        chars = np.frombuffer("".join(rows).encode("utf-32-le"), np.uint32).astype(np.int64)
        row = np.repeat(np.arange(len(rows)), sizes)
        # A trigram is a number of three code points; it must not go over into the next text.
        inside = np.flatnonzero(row[2:] == row[:-2]) if len(row) > 2 else np.zeros(0, np.int64)
        grams, at = np.unique((chars[inside] << 42) | (chars[inside + 1] << 21) | chars[inside + 2], return_inverse=True)
        for g in grams.tolist():
            if g not in slots:
                slots[g] = slot("".join(chr(g >> n & 0x1FFFFF) for n in (42, 21, 0)))
        found = np.array([slots[g] for g in grams.tolist()], np.int64)[at] if len(grams) else inside
        counts = np.bincount(row[inside] * dims + found, minlength=len(rows) * dims).reshape(-1, dims).astype(np.float64)
        for i in np.flatnonzero(sizes < 3).tolist():
            counts[i, slot(rows[i])] = 1.0
        counts /= np.sqrt((counts * counts).sum(axis=1, keepdims=True))
        ends = pa.array(np.arange(len(rows) + 1, dtype=np.int32) * dims)
        return pa.ListArray.from_arrays(ends, pa.array(counts.ravel()))

    return vectors(F.lower(F.coalesce(text, F.lit(""))))


def hashed_vectors(df: DataFrame, id_col: str, text: str, dims: int = 64) -> DataFrame:
    """(id, vector) of each row: see :func:`text_vector`."""
    return df.select(id_col, text_vector(F.col(text), dims).alias("vector"))


def cosine(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda acc, x: acc + x)


def _blocks(right: DataFrame, right_id: str, vector: str) -> Iterator[tuple[list, np.ndarray]]:
    """Ids in order and vectors of one block of the right side after the other."""
    right = stored(right.filter(F.col(vector).isNotNull()).select(right_id, vector), "vectors")
    n = max(1, math.ceil(right.count() / BLOCK_ROWS))
    for k in range(n):
        part = right.filter(F.pmod(F.xxhash64(right_id), F.lit(n)) == k) if n > 1 else right
        rows = sorted(part.toLocalIterator(), key=lambda r: r[0])
        if rows:
            yield [r[0] for r in rows], np.array([r[1] for r in rows], np.float64)


def _codes(planes: np.ndarray, vectors: np.ndarray) -> np.ndarray:
    """The number that the signs of each vector make in each round; a sum a vector, so that blocks do not matter."""
    signs = np.einsum("nd,rbd->nrb", vectors, planes) >= 0
    return signs @ (1 << np.arange(planes.shape[1]))


def _reaching(sims: np.ndarray, threshold: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Rows, columns and values of what reaches the threshold to six places; only what comes near it is rounded."""
    at = np.flatnonzero(sims.ravel() >= threshold - 1e-6)
    values = np.round(sims.ravel()[at], 6)
    at, values = at[values >= threshold], values[values >= threshold]
    return at // sims.shape[1], at % sims.shape[1], values


def _meeting(planes: np.ndarray, block: np.ndarray) -> Callable:
    """Places and similarities of the pairs of vectors and a block that share a bucket and reach a threshold.

    A pair comes from the first round in which it meets, so that none is held to be compared with the others.
    """
    codes = _codes(planes, block)
    buckets = [{c: np.flatnonzero(column == c) for c in np.unique(column).tolist()} for column in codes.T]

    def pairs(vectors, threshold):
        own, found, n = _codes(planes, vectors), [], 0
        for r, members in enumerate(buckets):
            for c in np.unique(own[:, r]).tolist():
                if c not in members:
                    continue
                rows, cols = np.flatnonzero(own[:, r] == c), members[c]
                there = block[cols].T
                for at in range(0, len(rows), STEP_ROWS):
                    i, j, s = _reaching(vectors[rows[at : at + STEP_ROWS]] @ there, threshold)
                    i, j = rows[at + i], cols[j]
                    new = ~(own[i, :r] == codes[j, :r]).any(axis=1)
                    found.append((i[new], j[new], s[new]))
                    n += len(found[-1][0])
                    if n >= PAIR_ROWS:
                        yield tuple(map(np.concatenate, zip(*found)))
                        found, n = [], 0
        if n:
            yield tuple(map(np.concatenate, zip(*found)))

    return pairs


def similar(left: DataFrame, right: DataFrame, left_id: str, right_id: str, vector: str, threshold: float | None = None, k: int | None = None, planes: np.ndarray | None = None) -> DataFrame:
    """(left_id, right_id, sim): dot products that reach a threshold, or the k largest of each left row.

    Blocks of at most about :data:`BLOCK_ROWS` vectors of the right side go to the tasks of
    the left side one by one, so that neither side has to fit anywhere and no pair that
    fails is ever a row. Ties go to the smaller id. Null vectors have no pairs. With
    ``planes`` (rounds, bits, dims) only pairs of equal signs in some round are compared.
    """
    schema = T.StructType([T.StructField(left_id, left.schema[left_id].dataType), T.StructField(right_id, right.schema[right_id].dataType), T.StructField("sim", T.DoubleType())])
    kinds = [pa.from_numpy_dtype(np.int64) if isinstance(f.dataType, T.LongType) else pa.int32() if isinstance(f.dataType, T.IntegerType) else pa.string() for f in schema.fields[:2]]
    slim = left.filter(F.col(vector).isNotNull()).select(left_id, vector)

    def product(ids, block):
        met = None if planes is None else _meeting(planes, block)
        step = MEET_ROWS if met else STEP_ROWS

        def run(batches):
            others = pa.array(ids, kinds[1])
            for batch in batches:
                for at in range(0, batch.num_rows, step):
                    own, vectors = (batch.column(i).slice(at, step).to_pylist() for i in range(2))
                    vectors = np.array(vectors, np.float64)
                    if k is None:
                        mine = pa.array(own, kinds[0])
                        for i, j, s in met(vectors, threshold) if met else [_reaching(vectors @ block.T, threshold)]:
                            yield pa.RecordBatch.from_arrays([mine.take(pa.array(i)), others.take(pa.array(j)), pa.array(s)], names=schema.names)
                        continue
                    rows: list = []
                    for i, s in enumerate(np.round(vectors @ block.T, 6)):
                        least = np.partition(s, len(s) - k)[len(s) - k] if len(s) > k else -np.inf
                        pick = np.flatnonzero(s >= least)
                        pick = pick[np.argsort(-s[pick], kind="stable")[:k]]
                        rows += [(own[i], ids[j], float(s[j])) for j in pick.tolist()]
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 3, (*kinds, pa.float64()))], names=schema.names)

        return run

    out = None
    for ids, block in _blocks(right, right_id, vector):
        part = slim.mapInArrow(product(ids, block), schema)
        out = part if out is None else out.unionByName(part)
    return left.sparkSession.createDataFrame([], schema) if out is None else out


def cosine_pairs(left: DataFrame, right: DataFrame, left_id: str, right_id: str, vector: str, threshold: float, rounds: int | None = None, bits: int = 8, dims: int = 64) -> DataFrame:
    """(left_id, right_id, sim) of unit vectors whose cosine, to six places, reaches the threshold.

    With ``rounds`` None the comparison is exact, by blocks of the right side. Else
    candidates share the signs of ``bits`` fixed random projections in at least one of
    ``rounds`` rounds. Candidates are compared where they meet, inside a block of the right
    side: only pairs that reach the threshold are rows.
    """
    if rounds is None:
        return similar(left, right, left_id, right_id, vector, threshold)
    planes = np.random.Generator(np.random.Philox(key=7)).standard_normal((rounds, bits, dims))
    pairs = similar(left, right, left_id, right_id, vector, threshold, planes=planes)
    return pairs.dropDuplicates([left_id, right_id])


def likely_pairs(pairs: DataFrame, sim: str, n: int, ties: list[str]) -> DataFrame:
    """The n most similar pairs, which are those that a judge is asked about; a task keeps n rows, nothing is sorted whole."""
    return pairs.orderBy(F.col(sim).desc(), *ties).limit(n)


def tune_threshold(judged: DataFrame, sim: str, match: str, recall: float = 0.95) -> DataFrame:
    """The largest threshold that keeps ``recall`` of the true pairs of a judged sample; null without any."""
    w = Window.orderBy(F.col(sim).desc())
    true = judged.filter(match).withColumn("r", F.row_number().over(w)).withColumn("m", F.count(F.lit(1)).over(Window.partitionBy(F.lit(0))))
    return true.agg(F.max(F.when(F.col("r") == F.ceil(F.col("m") * F.lit(recall)), F.col(sim))).alias("threshold"), F.count(F.lit(1)).alias("true_pairs"))


def resolve(df: DataFrame, key: str, candidates: DataFrame, compare: Callable[..., Column], into: str | None = None, context: str | None = None) -> DataFrame:
    """Replace fuzzy-equal values of ``key`` by a canonical one; the number of rows stays.

    ``candidates`` are value pairs (x, y) from blocking. Pairs that compare equal are links
    between values; the canonical value of a cluster is the most frequent, then shortest,
    then smallest. The mapping is joined back on the value. With ``context`` the comparison
    also gets a record's text for either value: that of its least row.
    """
    if context:
        around = df.filter(F.col(key).isNotNull()).groupBy(F.col(key).alias("__v")).agg(F.min(context).alias("__c"))
        for side in "xy":
            candidates = candidates.join(around.select(F.col("__v").alias(side), F.col("__c").alias(f"c{side}")), side)
        links = candidates.filter(compare(F.col("x"), F.col("y"), F.col("cx"), F.col("cy")))
    else:
        links = candidates.filter(compare(F.col("x"), F.col("y")))
    counts = df.groupBy(F.col(key).alias("v")).agg(F.count(F.lit(1)).alias("c")).filter("v is not null")
    labels = components_of(links)
    named = counts.join(labels, F.col("v") == F.col("node"), "left").withColumn("label", F.coalesce("label", "v"))
    best = named.groupBy("label").agg(F.min_by("v", F.struct(-F.col("c"), F.length("v"), "v")).alias("canonical"))
    mapping = named.join(best, "label").select(F.col("v").alias("__v"), "canonical")
    out = df.join(mapping, df[key] == F.col("__v"), "left").drop("__v")
    return out.withColumn(into or key, F.col("canonical")).drop("canonical")


def resolve_jointly(df: DataFrame, keys: list[str], rule: Callable[[Column], Column], compare: Callable[[Column, Column], Column]) -> DataFrame:
    """Several keys as one: the tuples of their values are blocked by a rule a key, compared and replaced together.

    ``compare`` gets two structs with the keys as fields. Tuples are carried as JSON.
    """
    kind = T.StructType([T.StructField(k, df.schema[k].dataType) for k in keys])
    packed = df.withColumn("__joint", F.to_json(F.struct(*keys), {"ignoreNullFields": "false"}))
    unpack = lambda x: F.from_json(x, kind)
    pairs = keyed_pairs(packed, "__joint", lambda x: F.to_json(F.struct(*[rule(unpack(x)[k]).alias(k) for k in keys])))
    out = resolve(packed, "__joint", pairs, lambda x, y: compare(unpack(x), unpack(y)))
    out = out.withColumn("__joint", unpack(F.col("__joint")))
    return out.withColumns({k: F.col(f"__joint.{k}") for k in keys}).drop("__joint")


def components_of(links: DataFrame) -> DataFrame:
    return components(links.select("x", "y"))


def resolve_stepwise(pairs: DataFrame, compare: Callable[[Column, Column], Column], rounds: int = 4) -> tuple[DataFrame, int]:
    """Transitivity skip: compare the most similar open pairs first, contract, drop pairs inside a component.

    Pairs are (x, y, sim). Returns the accepted links and the number of comparisons made.
    """
    links, compared = None, 0
    open_pairs = cut(pairs)
    for i in range(rounds):
        bound = 1.0 - (i + 1) / rounds if i + 1 < rounds else -2.0
        now = cut(open_pairs.filter(F.col("sim") >= bound))
        compared += now.count()
        good = now.filter(compare(F.col("x"), F.col("y"))).select("x", "y")
        links = cut(good if links is None else links.unionByName(good))
        labels = components(links)
        rest = open_pairs.filter(F.col("sim") < bound)
        for side in "xy":
            rest = rest.join(labels.select(F.col("node").alias(side), F.col("label").alias(f"l{side}")), side, "left")
        open_pairs = cut(rest.filter("lx is null or ly is null or lx != ly").select("x", "y", "sim"))
    return links, compared


def equijoin(left: DataFrame, right: DataFrame, left_id: str, right_id: str, candidates: DataFrame, compare: Callable[[DataFrame], Column] | None = None, how: str = "inner") -> DataFrame:
    """Semantic join over blocked candidate pairs: inner, left, semi or anti."""
    pairs = candidates.select(left_id, right_id).distinct()
    merged = left.join(pairs, left_id).join(right, right_id)
    hits = merged.filter(compare(merged)) if compare else merged
    if how == "inner":
        return hits
    ids = hits.select(left_id).distinct()
    if how in ("semi", "anti"):
        return left.join(ids, left_id, f"left_{how}")
    return hits.unionByName(left.join(ids, left_id, "left_anti"), allowMissingColumns=True)


def nearest(left: DataFrame, right: DataFrame, right_id: str, vector: str, k: int) -> list[DataFrame]:
    """The left side without its vector, and with ``near``: the k most similar (right_id, sim) of each row, in order.

    One frame for each block of the right side. Null vectors have no row. Ties go to the smaller id.
    """
    slim = left.filter(F.col(vector).isNotNull())
    kept = [c for c in left.columns if c != vector]
    kind = right.schema[right_id].dataType
    schema = T.StructType([left.schema[c] for c in kept] + [T.StructField("near", T.ArrayType(T.StructType([T.StructField(right_id, kind), T.StructField("sim", T.DoubleType())])))])

    def product(ids, block):
        def run(batches):
            names = pa.array(ids)
            for batch in batches:
                for at in range(0, batch.num_rows, STEP_ROWS):
                    step = batch.slice(at, STEP_ROWS)
                    vectors = step.column(len(kept)).flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(step.num_rows, -1)
                    sims = np.round(vectors @ block.T, 6)
                    if sims.shape[1] > k:
                        rows, cols = np.nonzero(sims >= np.partition(sims, -k, axis=1)[:, -k, None])
                    else:
                        rows, cols = np.nonzero(np.isfinite(sims))
                    order = np.lexsort((cols, -sims[rows, cols], rows))
                    rows, cols = rows[order], cols[order]
                    first = np.arange(len(rows)) - np.searchsorted(rows, rows) < k
                    rows, cols = rows[first], cols[first]
                    ends = pa.array(np.searchsorted(rows, np.arange(step.num_rows + 1)).astype(np.int32))
                    pairs = pa.StructArray.from_arrays([names.take(pa.array(cols)), pa.array(sims[rows, cols])], names=[right_id, "sim"])
                    yield pa.RecordBatch.from_arrays([*step.columns[:-1], pa.ListArray.from_arrays(ends, pairs)], names=[*kept, "near"])

        return run

    return [slim.select(*kept, vector).mapInArrow(product(ids, block), schema) for ids, block in _blocks(right, right_id, vector)]


def map_search_filter(left: DataFrame, left_id: str, right: DataFrame, right_id: str, vector: str, k: int, keep: Column) -> DataFrame:
    """The search baseline: the k most similar labels of each row, then a filter, ranked by similarity."""
    blocks = nearest(left, right, right_id, vector, k)
    w = Window.partitionBy(left_id).orderBy(F.col("sim").desc(), right_id)
    kept = [c for c in left.columns if c != vector]
    if len(blocks) == 1:
        near = blocks[0].select(*kept, F.inline("near"))
    else:
        # Each block of labels gave its own k.
        near = similar(left, right, left_id, right_id, vector, k=k) if not blocks else reduce(DataFrame.unionByName, [b.select(left_id, F.inline("near")) for b in blocks])
        near = near.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).drop("rank")
        near = left.drop(vector).join(near, left_id)
    hits = near.join(right.drop(vector), right_id).filter(keep)
    return hits.withColumn("rank", F.row_number().over(w))
