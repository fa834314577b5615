"""The registered queries of the training-data operators and their SQL."""

from __future__ import annotations

from functools import partial

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, chroma, html, jaccard, langid, mixing, pii, quality, suffixes, warc
from ..store import scratch, stored
from .common import table

VOCABULARY = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
PATTERN = public_tokenizers.PATTERN


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffixes.remove_repeats(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = quality.score(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return scored.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = langid.split(F.col("doc_id"))
    model = langid.learn(docs.filter(~held & F.col("doc_id").isNotNull()))
    return langid.identify(docs.select("doc_id", held.alias("held_out"), "text"), model).select("doc_id", "held_out", "lang_pred", "score")


def op4_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard.near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op5_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    first = F.get("positions", F.lit(0))["position"].alias("position")
    rows = mixed.select("doc_id", "size", "source_size", "target", "taken", F.size("positions").cast("long").alias("copies"), first)
    return rows.orderBy("position", "doc_id")


def op6_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = html.extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
    return pages.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))


def op7_chroma(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprints of a recording of each vector; every 20th id's second take is aligned with all recordings.

    The tables hold no audio, so a vector is played as a tune; a second take is an excerpt of it
    with noise, off the grid of frames.
    """
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    prints = stored(chroma.fingerprint(vectors, "embedding", chroma.tune).drop("embedding"), "prints")
    asked = vectors.filter(F.col("vec_id") % 20 == 0)
    takes = chroma.fingerprint(asked, "embedding", partial(chroma.tune, first=12, last=52, noise=0.02, lead=200))
    best = chroma.search(prints, takes, "vec_id").select("query", "n_matches", F.col("id").alias("match_id"), "offset", "votes", "overlap", "bit_errors")
    codes = F.array_join(F.transform("codes", lambda c: F.lower(F.lpad(F.hex(c.cast("long").bitwiseAND(0xFFFFFFFF)), 8, "0"))), "")
    rows = prints.select("vec_id", "n_frames", F.size("codes").cast("long").alias("n_codes"), F.sha2(codes.cast("binary"), 256).alias("codes_sha256"))
    return rows.join(best, F.col("vec_id") == F.col("query"), "left").drop("query")


def op8_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find(table(spark, sf_dir, "documents").select("doc_id", "text"))
    scores = F.array_join(F.transform("spans", lambda s: s["score"].cast("string")), ",").alias("scores")
    return pii.digests(found, more=[scores])


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    plan = warc.record_plan(table(spark, sf_dir, "pages"))
    folder = scratch(spark, "archives")
    return warc.read_archives(warc.write_archives(plan, folder)).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return bpe.digests(bpe.round_trip(docs, VOCABULARY, PATTERN))


QUERIES = {
    f.__name__: f
    for f in (op1_suffix_dedup, op2_quality_rules, op3_language_id, op4_ngram_jaccard, op5_mix_sources, op6_html_text, op7_chroma, op8_personal_data, op9_warc, op10_byte_bpe)
}
_WORDS = r"list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '')"
_STOPS = ", ".join(f"'{w}'" for w in sorted(set(" ".join(quality.STOP_WORDS.values()).split())))
_SYMBOLS = " + ".join(f"(length(b) - length(replace(b, '{c}', '')))" for c in quality.SYMBOLS)

#: DuckDB twins where SQL can express the operator.
ORACLES = {
    "op2_quality_rules": f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t, {_WORDS} AS w FROM documents),
p AS (SELECT r, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3] || ' ' || w[i + 4] AS g FROM d, range(1, len(w) - 3) x(i)),
q AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS c FROM p) WHERE c > 1),
c AS (SELECT r, count(DISTINCT i + k) AS n FROM q, range(0, 5) y(k) GROUP BY r),
l AS (SELECT r, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS l FROM d),
m AS (SELECT d.doc_id, len(w)::BIGINT AS n_words, regexp_replace(t, '[\\x20\\x09-\\x0D]+', '', 'g') AS b, coalesce(c.n, 0)::BIGINT AS n_repeat_words, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, len(l) AS n_lines,
  len(list_intersect(list_transform(w, lambda x: lower(x)), [{_STOPS}])) AS stops, len(list_filter(w, lambda x: right(x, 1) IN ('!', '?', '#', '*', '$', '%', '&', '|', '<', '>'))) AS odd
  FROM d JOIN l USING (r) LEFT JOIN c USING (r)),
n AS (SELECT *, length(b)::BIGINT AS word_chars, ({_SYMBOLS})::BIGINT AS n_symbols, length(regexp_replace(b, '\\P{{Lu}}+', '', 'g')) AS up, length(regexp_replace(b, '\\P{{L}}+', '', 'g')) AS letters, (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND word_chars / n_words BETWEEN 2 AND 25 AND n_symbols / n_words <= 0.3 AND n_dup_lines <= 0.5 * n_lines AND up <= 0.6 * letters AND odd <= 0.5 * n_words AND letters >= 0.4 * word_chars AND stops >= 1 AS kept FROM n""",
    "op5_mix_sources": f"""
WITH d AS (SELECT doc_id, source, len({_WORDS})::BIGINT AS size FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS l, [3, 1, 2][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3] AS w FROM d GROUP BY source),
f AS (SELECT *, (1.5::DOUBLE * sum(l) OVER ()::DOUBLE - 2 * coalesce(sum(l) OVER b, 0)::DOUBLE) / (sum(w) OVER () - coalesce(sum(w) OVER b, 0))::DOUBLE AS level, row_number() OVER (ORDER BY l::DOUBLE / w, source NULLS LAST) AS k FROM s WINDOW b AS (ORDER BY l::DOUBLE / w, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
v AS (SELECT level FROM f WHERE w * level <= 2 * l ORDER BY k LIMIT 1),
t AS (SELECT source, l, CASE w WHEN 3 THEN 0.5::DOUBLE WHEN 1 THEN 1::DOUBLE ELSE 2::DOUBLE END AS tilt, least((2 * l)::DOUBLE, coalesce(w * (SELECT level FROM v), (2 * l)::DOUBLE)) AS target FROM f),
c AS (SELECT d.*, t.l, t.target, t.tilt, floor(t.target + 0.5)::BIGINT AS goal, coalesce(sum(size) OVER (PARTITION BY d.source ORDER BY md5(coalesce(doc_id::VARCHAR, '')), doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS c FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
p AS (SELECT *, greatest(0, least(c + size, goal) - c) AS a, greatest(0, least(c + size, goal - l) - c) AS b FROM c)
SELECT doc_id, size, l AS source_size, target, (a + b)::BIGINT AS taken, ((a > 0)::INT + (b > 0)::INT)::BIGINT AS copies, CASE WHEN a + b > 0 THEN 2 * (share * (tilt + 1) / 2) / (tilt + sqrt(greatest(tilt * tilt + 4 * ((1 - tilt) / 2) * (share * (tilt + 1) / 2), 0))) END AS position
FROM (SELECT *, (c + CASE WHEN a > 0 THEN 0 ELSE l END)::DOUBLE / greatest(goal, 1)::DOUBLE AS share FROM p)""",
    "op9_warc": """
WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
f AS (SELECT h, min(page_id) AS lead FROM p WHERE strlen(h) >= 100 GROUP BY h)
SELECT page_id, strlen(p.h)::BIGINT AS payload_bytes, sha256(p.h) AS payload_digest, CASE WHEN lead IS NULL OR lead IS NOT DISTINCT FROM page_id THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN lead IS DISTINCT FROM page_id THEN lead END AS refers_to FROM p LEFT JOIN f ON p.h = f.h""",
}
