"""Accuracy and cost measures; each gives a DataFrame, never a number of the driver."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .functions.text import jaccard


def span_prf(pred: DataFrame, gold: DataFrame, unit: str = "doc_id", threshold: float = 0.15) -> DataFrame:
    """Precision, recall and F1 by unit: same document and type, token Jaccard strictly above the threshold.

    Rows are (doc_id, type, span). Units are those that have a prediction or a gold span.
    """
    p = pred.select("doc_id", "type", "span").distinct().withColumn("pid", F.xxhash64("doc_id", "type", "span"))
    g = gold.select("doc_id", "type", F.col("span").alias("gspan")).distinct().withColumn("gid", F.xxhash64("doc_id", "type", "gspan"))
    hits = p.join(g, ["doc_id", "type"]).filter(jaccard(F.col("span"), F.col("gspan")) > threshold).select(F.col("doc_id"), "type", "pid", "gid")
    found = hits.groupBy(unit).agg(F.countDistinct("pid").alias("tp"), F.countDistinct("gid").alias("covered"))
    out = p.groupBy(unit).agg(F.count(F.lit(1)).alias("n_pred")).join(g.groupBy(unit).agg(F.count(F.lit(1)).alias("n_gold")), unit, "full").join(found, unit, "left").fillna(0)
    precision = F.when(F.col("n_pred") > 0, F.col("tp") / F.col("n_pred")).otherwise(0.0)
    recall = F.when(F.col("n_gold") > 0, F.col("covered") / F.col("n_gold")).otherwise(0.0)
    out = out.withColumn("precision", precision).withColumn("recall", recall)
    f1 = F.when(F.col("precision") + F.col("recall") > 0, 2 * F.col("precision") * F.col("recall") / (F.col("precision") + F.col("recall"))).otherwise(0.0)
    return out.withColumn("f1", f1)


def averaged(prf: DataFrame) -> DataFrame:
    return prf.agg(*[F.round(F.avg(c), 6).alias(c) for c in ("precision", "recall", "f1")])


def average_chars(pred: DataFrame, col: str = "span") -> DataFrame:
    return pred.agg(F.round(F.avg(F.length(col)), 6).alias("avg_chars"))


def rate(df: DataFrame, test: Column, name: str, by: list[str] | None = None) -> DataFrame:
    """Share of rows that pass a test, say that a type is off the list or a span not in its source."""
    return df.groupBy(*(by or [])).agg(F.round(F.avg(F.coalesce(test, F.lit(False)).cast("int")), 6).alias(name))


def missing_rate(pred: DataFrame, source: DataFrame, keys: list[str], name: str = "hallucination") -> DataFrame:
    """Share of predicted keys that the source does not have."""
    known = source.select(*keys).distinct().withColumn("__known", F.lit(True))
    return rate(pred.join(known, keys, "left"), F.col("__known").isNull(), name)


def label_accuracy(pred: DataFrame, truth: DataFrame, keys: list[str], label: str, true_label: str) -> DataFrame:
    """Accuracy on those keys only that the truth has."""
    return rate(pred.join(truth, keys), F.col(label) == F.col(true_label), "accuracy")


def kendall_tau(df: DataFrame, group: list[str], position: str, value: str, variant: str = "a") -> DataFrame:
    """Kendall's tau of output position against a value in each group.

    Pairs are compared inside one sorted array a group; lists here are what a model
    returns, short. For long ones see :func:`kendall_tau_large`.
    """
    rows = df.groupBy(*group).agg(F.array_sort(F.collect_list(F.struct(F.col(position).alias("p"), F.col(value).alias("v")))).alias("r"))

    def against(r):
        return F.aggregate(F.transform(r, lambda a, i: F.aggregate(F.slice(r, i + 2, F.size(r)), F.lit(0.0), lambda acc, b: acc + F.when(b["v"] > a["v"], 1.0).when(b["v"] < a["v"], -1.0).otherwise(0.0))), F.lit(0.0), lambda acc, x: acc + x)

    n = F.size("r").cast("double")
    pairs = n * (n - 1) / 2
    if variant == "b":
        ties = F.aggregate(F.transform("r", lambda a, i: F.size(F.filter(F.slice("r", i + 2, F.size("r")), lambda b: b["v"] == a["v"]))), F.lit(0), lambda acc, x: acc + x)
        below = F.sqrt(pairs * (pairs - ties))
    else:
        below = pairs
    return rows.select(*group, F.when(below > 0, F.round(against(F.col("r")) / below, 6)).alias("tau"))


def kendall_tau_large(df: DataFrame, group: list[str], position: str, value: str) -> DataFrame:
    """Tau a of long lists: inversions by merge counting, O(n log n) a group."""
    import numpy as np
    import pandas as pd

    def count(v):
        if len(v) < 2:
            return v, 0.0
        (a, x), (b, y) = count(v[: len(v) // 2]), count(v[len(v) // 2 :])
        greater = len(b) * len(a) - np.searchsorted(b, a, "right").sum() * 1.0
        less = np.searchsorted(b, a, "left").sum() * 1.0
        return np.sort(np.concatenate([a, b]), kind="stable"), x + y + greater - less

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        v = pdf.sort_values([position, value])[value].to_numpy()
        s, n = count(v)[1], len(v)
        return pd.DataFrame({**{g: [pdf[g].iloc[0]] for g in group}, "tau": [round(s / (n * (n - 1) / 2), 6) if n > 1 else None]})

    schema = ", ".join([*(f"{g} {df.schema[g].dataType.simpleString()}" for g in group), "tau double"])
    return df.select(*group, position, value).groupBy(*group).applyInPandas(run, schema)


def rank_precision(ranked: DataFrame, gold: DataFrame, doc: str, item: str, ks: tuple[int, ...] = (5, 10, 25)) -> DataFrame:
    """Mean over documents with a relevant item of hits in the first k by min(k, relevant)."""
    hits = ranked.join(gold.select(doc, item).distinct(), [doc, item])
    relevant = gold.select(doc, item).distinct().groupBy(doc).agg(F.count(F.lit(1)).alias("r"))
    per = relevant.join(hits.groupBy(doc).agg(*[F.sum((F.col("rank") <= k).cast("int")).alias(f"h{k}") for k in ks]), doc, "left").fillna(0)
    return per.agg(*[F.round(F.avg(F.col(f"h{k}") / F.least(F.lit(k), F.col("r"))), 6).alias(f"rp_at_{k}") for k in ks])


def verified_precision(pred: DataFrame, source: DataFrame, keys: list[str], value: str, text: str, gazetteer: DataFrame, place: str) -> DataFrame:
    """Distinct values; right if the source text has them and the gazetteer knows them."""
    seen = pred.join(source.select(*keys, text), keys).join(gazetteer.select(F.col(place).alias("__place")).distinct(), F.col(value) == F.col("__place"), "left")
    per = seen.groupBy(value).agg(F.max((F.contains(F.col(text), F.col(value)) & F.col("__place").isNotNull()).cast("int")).alias("ok"))
    return per.agg(F.round(F.avg("ok"), 6).alias("precision"), F.count(F.lit(1)).alias("distinct_found"))


def agreement(df: DataFrame, a: str, b: str) -> DataFrame:
    """Share of equal verdicts and Cohen's kappa of two judges."""
    r = df.agg(F.avg((F.col(a) == F.col(b)).cast("double")).alias("po"), F.avg(F.col(a).cast("double")).alias("pa"), F.avg(F.col(b).cast("double")).alias("pb"))
    pe = F.col("pa") * F.col("pb") + (1 - F.col("pa")) * (1 - F.col("pb"))
    return r.select(F.round("po", 6).alias("agreement"), F.round(F.when(pe < 1, (F.col("po") - pe) / (1 - pe)), 6).alias("kappa"))


def criterion_pass(df: DataFrame, criteria: dict[str, Column]) -> DataFrame:
    return df.agg(*[F.round(F.avg(F.coalesce(c, F.lit(False)).cast("int")), 6).alias(n) for n, c in criteria.items()])


def share_better(plans: DataFrame, col: str, reference: float) -> DataFrame:
    return rate(plans, F.col(col) > reference, f"better_{col}")


def improvement(new: Column, old: Column) -> Column:
    return F.round(new / old - 1, 6)


def pair_prf(labels: DataFrame, truth: DataFrame, item: str, cluster: str, true_cluster: str) -> DataFrame:
    """Pairwise precision and recall of merged items, from cluster sizes alone (no pairs are made)."""
    both = labels.join(truth, item)
    pairs = lambda *cols: both.groupBy(*cols).agg(F.count(F.lit(1)).alias("n")).agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("p"))
    a, b, c = (pairs(cluster, true_cluster).withColumnRenamed("p", "both"), pairs(cluster).withColumnRenamed("p", "made"), pairs(true_cluster).withColumnRenamed("p", "true"))
    return a.crossJoin(b).crossJoin(c).select(F.round(F.col("both") / F.col("made"), 6).alias("pair_precision"), F.round(F.col("both") / F.col("true"), 6).alias("pair_recall"))


def blocking_stats(candidates: DataFrame, gold: DataFrame, keys: list[str], n_pairs: Column) -> DataFrame:
    """Recall of true pairs and the share of all pairs that blocking spares."""
    hit = gold.join(candidates.select(*keys).distinct(), keys, "left_semi").agg(F.count(F.lit(1)).alias("hit"))
    return hit.crossJoin(gold.agg(F.count(F.lit(1)).alias("gold"))).crossJoin(candidates.agg(F.count(F.lit(1)).alias("n"))).select(F.round(F.col("hit") / F.col("gold"), 6).alias("recall"), F.round(1 - F.col("n") / n_pairs, 6).alias("reduction"))

