"""Quality rules (operator 2): a threshold table compiled into one Spark projection.

:data:`MEASURES` names the measures as Catalyst expressions over the words, lines and
characters of a text; :data:`RULES` is the table of thresholds. :func:`compile_rules`
turns a table into a single boolean expression, and :func:`score` into one projection
without any user function, shuffle or join.

Defined results: null text has no words and no lines and fails the base rules. Repeated
rows are scored alike, empty tables give empty results, other columns are carried on
request and never clash since measures are computed in nested projections.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WHITE, words

#: Characters that count as symbols.
SYMBOLS = "#*$%&|<>"
#: Frequent function words of the four languages served.
STOP_WORDS = {
    "en": "the of and to in a is that for it as was with be by on not he his but at are this have from or had an they which one you were all her she there would their",
    "de": "der die das und in zu den von ist mit des sich dem nicht ein eine als auch es an auf für im",
    "fr": "de la le et les des en un une du que est pour qui dans par sur pas au plus avec ce se il",
    "es": "de la que el en y a los se del las un por con no una su para es al lo como más",
}
WINDOW = 5

#: measure, comparison that fails a text, threshold. Base rules come first.
BASE_RULES = [
    ("n_words", "<", 10),
    ("repeat_word_percent", ">", 20),
]
RULES = [
    ("mean_word_chars", "<", 2.0),
    ("mean_word_chars", ">", 25.0),
    ("symbols_per_word", ">", 0.3),
    ("dup_line_share", ">", 0.5),
    ("upper_share", ">", 0.6),
    ("punct_word_share", ">", 0.5),
    ("letter_share", "<", 0.4),
    ("stop_words", "<", 1),
]


def _with_repeats(df: DataFrame) -> DataFrame:
    """Add ``n_repeat_words``: words inside 5-word windows that occur at least twice.

    Only texts whose window hashes are not all distinct go further: their (hash, position)
    pairs are sorted, those that equal a neighbour are marked, and the union of the marked
    stretches is summed over the sorted positions. Each step is a column of its own, since
    an expression that is named several times would be computed as often.
    """
    w, n = F.col("__w"), F.size("__w")
    at = lambda a, i: F.get(a, i)
    hashes = F.when(n > WINDOW, F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*[at(w, i + k) for k in range(WINDOW)])))
    out = df.withColumn("__h", hashes)
    pairs = F.when(F.size(F.array_distinct("__h")) < F.size("__h"), F.sort_array(F.transform("__h", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))
    out = out.withColumn("__s", pairs)
    s = F.col("__s")
    near = lambda x, i: F.coalesce(x["h"] == at(s, i - 1)["h"], F.lit(False)) | F.coalesce(x["h"] == at(s, i + 1)["h"], F.lit(False))
    out = out.withColumn("__at", F.sort_array(F.transform(F.filter(s, near), lambda x: x["i"])))
    steps = F.transform("__at", lambda x, i: F.least(F.lit(WINDOW), F.coalesce(at(F.col("__at"), i + 1) - x, F.lit(WINDOW))))
    total = F.aggregate(steps, F.lit(0).cast("long"), lambda acc, x: acc + x)
    return out.withColumn("n_repeat_words", F.coalesce(total, F.lit(0).cast("long"))).drop("__h", "__s", "__at")


def measures(df: DataFrame, text_col: str = "text") -> DataFrame:
    """Add the integer counts that all rules derive from; ``__w`` and ``__t`` are helpers."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    bare = text
    for c in [" ", *WHITE]:
        bare = F.replace(bare, F.lit(c), F.lit(""))
    symbols = F.lit(0).cast("long")
    for c in SYMBOLS:
        symbols = symbols + F.length(F.col("__b")) - F.length(F.replace(F.col("__b"), F.lit(c), F.lit("")))
    lines = F.filter(F.split(F.col("__t"), "\n"), lambda x: F.length(F.btrim(x, F.lit(" " + "".join(WHITE)))) > 0)
    stops = F.array(*map(F.lit, sorted(set(" ".join(STOP_WORDS.values()).split()))))
    out = _with_repeats(df.withColumn("__t", text).withColumn("__w", words(F.col(text_col))).withColumn("__b", bare).withColumn("__l", lines))
    head = F.transform(F.col("__w"), lambda x: F.substring(x, -1, 1))
    return out.select(
        "*",
        F.size("__w").cast("long").alias("n_words"),
        F.length("__b").cast("long").alias("word_chars"),
        symbols.alias("n_symbols"),
        (F.size("__l") - F.size(F.array_distinct("__l"))).cast("long").alias("n_dup_lines"),
        F.size("__l").cast("long").alias("n_lines"),
        F.size(F.array_intersect(F.transform("__w", lambda x: F.lower(x)), stops)).cast("long").alias("n_stop_words"),
        F.size(F.filter(head, lambda x: x.isin(*"!?#*$%&|<>"))).cast("long").alias("n_odd_ends"),
        F.length(F.regexp_replace("__b", r"\P{Lu}+", "")).cast("long").alias("n_upper"),
        F.length(F.regexp_replace("__b", r"\P{L}+", "")).cast("long").alias("n_letters"),
    ).drop("__t", "__w", "__b", "__l")


#: Measures as expressions over the counts.
MEASURES = {
    "n_words": lambda: F.col("n_words"),
    "repeat_word_percent": lambda: F.when(F.col("n_words") > 0, 100 * F.col("n_repeat_words") / F.col("n_words")).otherwise(0.0),
    "mean_word_chars": lambda: F.when(F.col("n_words") > 0, F.col("word_chars") / F.col("n_words")).otherwise(0.0),
    "symbols_per_word": lambda: F.when(F.col("n_words") > 0, F.col("n_symbols") / F.col("n_words")).otherwise(0.0),
    "dup_line_share": lambda: F.when(F.col("n_lines") > 0, F.col("n_dup_lines") / F.col("n_lines")).otherwise(0.0),
    "upper_share": lambda: F.when(F.col("n_letters") > 0, F.col("n_upper") / F.col("n_letters")).otherwise(0.0),
    "punct_word_share": lambda: F.when(F.col("n_words") > 0, F.col("n_odd_ends") / F.col("n_words")).otherwise(0.0),
    "letter_share": lambda: F.when(F.col("word_chars") > 0, F.col("n_letters") / F.col("word_chars")).otherwise(0.0),
    "stop_words": lambda: F.col("n_stop_words"),
}


def compile_rules(rules: list[tuple[str, str, float]]) -> Column:
    """True where any rule of the table fails."""
    failed = F.lit(False)
    for name, sign, bound in rules:
        value = MEASURES[name]()
        failed = failed | {"<": value < bound, ">": value > bound}[sign]
    return failed


def score(df: DataFrame, text_col: str = "text", base: list = BASE_RULES, rules: list = RULES) -> DataFrame:
    """Rows with all counts, ``base_failed`` and ``kept``."""
    counted = measures(df, text_col)
    return counted.withColumn("base_failed", compile_rules(base)).withColumn("kept", ~F.col("base_failed") & ~compile_rules(rules))
