"""Personal data (operator 8), all in Catalyst: patterns propose, validators confirm, context scores.

Each :class:`Kind` has a pattern that proposes spans, a validator over the matched string
(octets, Luhn, digit counts, mod 97, number plans) and a score, which context words raise when
they stand near the span. Spans of added kinds that stay under :data:`MIN_SCORE` are dropped: a
long mixed string alone is no secret, beside the word "token" it is one. Positions are code points, end exclusive. The patterns are written so that a
regular-expression engine cannot backtrack or recurse over long runs: possessive loops, and
a look-behind that lets a match start only where a run starts or the last match ended.

Texts that lack a character which every match needs skip the pattern.

Defined results: null text is an empty one without spans. Rows are judged one by one, so
ties, repeated rows and extra columns do not matter, and an empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Characters on either side of a span in which context words count, and what they add to its score.
CONTEXT, BOOST = 40, 0.3
#: Least score of a span of an added kind.
MIN_SCORE = 0.5


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def luhn(x: Column) -> Column:
    """Whether the digits of x pass the Luhn check (an empty string passes)."""
    d = F.reverse(_digits(x))
    places = F.filter(F.sequence(F.lit(1), F.greatest(F.length(d), F.lit(1))), lambda i: i <= F.length(d))

    def add(acc, i):
        v = F.substring(d, i, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1)
        return acc + F.when(v > 9, v - 9).otherwise(v)

    return F.aggregate(places, F.lit(0), add) % 10 == 0


def mod97(x: Column) -> Column:
    """Whether an account number (letters and digits, blanks ignored) leaves 1 modulo 97."""
    s = F.upper(F.regexp_replace(x, "[^0-9A-Za-z]", ""))
    moved = F.concat(F.substring(s, 5, 64), F.substring(s, 1, 4))

    def step(acc, i):
        c = F.ascii(F.substring(moved, i, F.lit(1)))
        return F.when(c >= 65, (acc * 100 + (c - 55)) % 97).otherwise((acc * 10 + (c - 48)) % 97)

    return F.aggregate(F.sequence(F.lit(1), F.greatest(F.length(moved), F.lit(1))), F.lit(0), step) == 1


#: Registered account number lengths by country.
ACCOUNT_LENGTHS = (
    "AD24 AE23 AL28 AT20 AZ28 BA20 BE16 BG22 BH22 BI27 BR29 BY28 CH21 CR22 CY28 CZ24 DE22 DJ27 DK18 DO28 EE20 EG29 ES24 FI18 FK18 FO18 "
    "FR27 GB22 GE22 GI23 GL18 GR27 GT28 HR21 HU28 IE22 IL23 IQ23 IS26 IT27 JO30 KW30 KZ20 LB28 LC32 LI21 LT20 LU20 LV21 LY25 MC27 MD24 "
    "ME22 MK19 MN20 MR27 MT31 MU30 NI28 NL18 NO15 OM23 PK24 PL28 PS29 PT25 QA29 RO24 RS22 RU33 SA24 SC31 SD18 SE24 SI19 SK24 SM27 SO23 "
    "ST25 SV28 TL23 TN24 TR26 UA29 VA22 VG24 XK20 YE30"
)


def account(x: Column) -> Column:
    """Length of the account number that x starts with, 0 for none.

    Every end of a group of 15 to 34 letters and digits so far is tried by mod 97; of those that
    pass, the one of the country's registered length counts, else the longest.
    """
    parts = F.split(x, " ")
    heads = F.transform(F.sequence(F.lit(1), F.size(parts)), lambda k: F.array_join(F.slice(parts, F.lit(1), k), " "))
    bare = lambda h: F.length(F.replace(h, F.lit(" "), F.lit("")))
    good = F.filter(heads, lambda h: F.when(h.rlike("^[A-Z0-9 ]+$") & bare(h).between(15, 34), mod97(h)).otherwise(False))
    ends = F.transform(good, lambda h: F.struct(F.contains(F.lit(ACCOUNT_LENGTHS), F.concat(F.substring(h, 1, 2), bare(h).cast("string"))).alias("known"), F.length(h).alias("n")))
    return F.coalesce(F.array_max(ends)["n"], F.lit(0))


def octets(x: Column) -> Column:
    def small(part):
        bare = F.ltrim(part, F.lit("0"))
        return F.when(F.length(bare) <= 3, F.when(bare == "", 0).otherwise(bare.cast("int")) <= 255).otherwise(F.lit(False))

    return F.forall(F.split(x, "[.]"), small)


def digit_count(low: int, high: int) -> Callable[[Column], Column]:
    return lambda x: F.length(_digits(x)).between(low, high)


@dataclass(frozen=True)
class Kind:
    name: str
    pattern: str
    #: A substring or class that every match needs; texts without it are skipped.
    needs: str
    valid: Callable[[Column], Column]
    words: tuple[str, ...] = field(default=())
    base: bool = True
    #: Length of the span that starts a proposed string, 0 for none. The pattern then consumes a
    #: character and proposes by its group 1, so that proposals may overlap.
    cut: Callable[[Column], Column] | None = None
    #: Score without a context word near.
    alone: float = 0.65


def number_plan(x: Column) -> Column:
    """Whether area and exchange of a ten-digit number start with 2 to 9."""
    return _digits(x).rlike("^[2-9][0-9]{2}[2-9][0-9]{6}$")


def mixed(digits: int) -> Callable[[Column], Column]:
    """Whether a string has so many digits, four letters and eight different characters."""

    def valid(x: Column) -> Column:
        classes = (F.length(_digits(x)) >= digits) & (F.length(F.regexp_replace(x, "[^A-Za-z]", "")) >= 4)
        return classes & (F.size(F.array_distinct(F.split(x, ""))) >= 8)

    return valid


BASE = (
    Kind("email", r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@", lambda x: F.lit(True), ("mail", "contact", "write")),
    Kind("ip", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", r"[0-9]\.[0-9]", octets, ("ip", "host", "server", "address")),
    Kind("card", r"[0-9](?:[ -]?[0-9])++", r"[0-9][ -]?[0-9][ -]?[0-9][ -]?[0-9]", lambda x: F.when(digit_count(13, 19)(x), luhn(x)).otherwise(False), ("card", "visa", "credit", "pay")),
    Kind("phone", r"\+[0-9][ ().0-9-]+[0-9]", r"\+[0-9]", digit_count(9, 15), ("phone", "call", "tel", "mobile")),
)
#: Kinds that the method adds to the base ones.
ADDED = (
    Kind("iban", r"(?<![A-Za-z0-9])(?=([A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]){11,30}+[A-Za-z0-9]?))[A-Z]", r"[A-Z]{2}[0-9]{2}", lambda x: account(x) > 0, ("iban", "account", "bank"), False, account),
    Kind("local_phone", r"\([0-9]{3}\) [0-9]{3}-[0-9]{4}(?![0-9])", r"\([0-9]{3}\)", number_plan, ("phone", "call", "tel"), False),
    Kind("access_key", r"(?<![A-Za-z0-9])AKIA[0-9A-Z]{16}(?![A-Za-z0-9])", "AKIA", mixed(1), ("key", "secret"), False),
    Kind("secret", r"(?<![A-Za-z0-9])[A-Za-z0-9]{20,}+", r"[A-Za-z0-9]{20}", mixed(4), ("token", "secret", "password", "api_key", "apikey", "api key", "credential"), False, None, 0.3),
)
KINDS = BASE + ADDED


def _running(lengths: Column, block: int = 64) -> Column:
    """Sums of all elements before each one, in two levels so that long lists stay cheap."""
    n = F.size(lengths)
    total = lambda a: F.aggregate(a, F.lit(0), lambda acc, x: acc + x)
    starts = F.filter(F.sequence(F.lit(0), n, F.lit(block)), lambda i: i < n)
    sums = F.transform(starts, lambda i: total(F.slice(lengths, i + 1, block)))
    offsets = F.aggregate(sums, F.array(F.lit(0)), lambda acc, x: F.concat(acc, F.array(F.element_at(acc, -1) + x)))
    parts = F.zip_with(starts, offsets, lambda i, o: F.when(i.isNotNull(), F.transform(F.slice(lengths, i + 1, block), lambda _, k: o + total(F.slice(lengths, i + 1, k)))).otherwise(F.array().cast("array<int>")))
    return F.flatten(parts)


def _spans(kind: Kind, text: Column, matches: Column, pieces: Column) -> Column:
    """Valid spans from the matches and the pieces of text between them."""
    # Piece i and match i alternate; the start of match i is all before it.
    size = lambda m: F.lit(1) if kind.cut else F.length(m)
    rows = F.zip_with(pieces, matches, lambda p, m: F.struct(F.length(p).alias("gap"), F.when(m.isNotNull(), size(m)).otherwise(0).alias("len"), m.alias("m")))
    before = _running(F.transform(rows, lambda r: r["gap"] + r["len"]))
    placed = F.zip_with(rows, before, lambda r, b: F.struct(r["m"].alias("m"), (b + r["gap"]).alias("start"), (b + r["gap"] + r["len"]).alias("end")))
    good = F.filter(placed, lambda r: F.when(r["m"].isNotNull(), kind.valid(r["m"])).otherwise(False))
    if kind.cut:
        good = F.transform(good, lambda r: F.struct(r["start"].alias("start"), (r["start"] + kind.cut(r["m"])).alias("end")))
        # Of spans that overlap the first stays.
        none = F.array().cast("array<struct<start:int,end:int>>")
        good = F.aggregate(good, none, lambda acc, r: F.when((F.size(acc) > 0) & (r["start"] < F.coalesce(F.get(acc, F.size(acc) - 1)["end"], F.lit(0))), acc).otherwise(F.concat(acc, F.array(r))))

    def scored(r):
        left = F.greatest(r["start"] - CONTEXT, F.lit(0))
        around = F.lower(F.concat(F.substring(text, left + 1, r["start"] - left), F.lit(" "), F.substring(text, r["end"] + 1, F.lit(CONTEXT))))
        near = F.lit(False)
        for w in kind.words:
            near = near | F.contains(around, F.lit(w))
        return F.struct(F.lit(kind.name).alias("kind"), r["start"].alias("start"), r["end"].alias("end"), F.when(near, round(kind.alone + BOOST, 2)).otherwise(kind.alone).alias("score"))

    return F.transform(good, scored)


def find(df: DataFrame, text_col: str = "text", kinds: tuple[Kind, ...] = KINDS, min_score: float = MIN_SCORE, spans_col: str = "spans") -> DataFrame:
    """Add ``spans_col``: array of (kind, start, end, score), by kind as listed, then start.

    Spans scored under ``min_score`` are left out, those of base kinds never.
    """
    out = df.withColumn("__t", F.coalesce(F.col(text_col), F.lit("")))
    empty = F.array().cast("array<struct<kind:string,start:int,end:int,score:double>>")
    texts, found = F.col("__t"), []
    for k in kinds:
        needed = F.contains(texts, F.lit(k.needs)) if len(k.needs) == 1 else texts.rlike(k.needs)
        out = out.withColumn(f"__m_{k.name}", F.when(needed, F.regexp_extract_all(texts, F.lit(k.pattern), F.lit(1 if k.cut else 0))))
    for k in kinds:
        matches = F.col(f"__m_{k.name}")
        some = F.exists(matches, k.valid)
        out = out.withColumn(f"__p_{k.name}", F.when(F.coalesce(some, F.lit(False)), F.split(texts, k.pattern)))
    for k in kinds:
        spans = F.when(F.col(f"__p_{k.name}").isNotNull(), _spans(k, texts, F.col(f"__m_{k.name}"), F.col(f"__p_{k.name}"))).otherwise(empty)
        found.append(spans if k.base or min_score <= 0 else F.filter(spans, lambda s: s["score"] >= min_score))
    out = out.withColumn(spans_col, F.concat(*found))
    return out.drop("__t", *[f"__{x}_{k.name}" for k in kinds for x in "mp"])


def listed(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def digests(found: DataFrame, id_col: str = "doc_id", more: list[Column] = []) -> DataFrame:  # noqa: B006
    """Counts by base kind, the digest of the base spans, all spans as text and more columns."""
    names = [k.name for k in BASE]
    base = F.filter("spans", lambda s: s["kind"].isin(*names))
    count = lambda n: F.size(F.filter("spans", lambda s: s["kind"] == n)).cast("long").alias(f"n_{n}")
    return found.select(id_col, *map(count, names), F.sha2(listed(base).cast("binary"), 256).alias("base_sha256"), listed(F.col("spans")).alias("spans"), *more)


def redact(df: DataFrame, text_col: str = "text", kinds: tuple[Kind, ...] = KINDS) -> DataFrame:
    """Replace every span of the text by ``[KIND]``; spans that overlap become one, named by the first."""
    found = find(df, text_col, kinds, spans_col="__spans")
    text = F.col(text_col)
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))
    ordered = F.sort_array(F.transform("__spans", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))

    def step(acc, s):
        new = s["start"] >= acc["at"]
        piece = F.concat(acc["out"], F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), F.lit("["), F.upper(s["kind"]), F.lit("]"))
        return F.struct(F.when(new, piece).otherwise(acc["out"]).alias("out"), F.greatest(acc["at"], s["end"]).alias("at"))

    found = found.withColumn("__s", ordered)
    clean = F.aggregate("__s", start, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text))))
    return found.withColumn(text_col, F.when(F.size("__s") > 0, clean).otherwise(text)).drop("__spans", "__s")
