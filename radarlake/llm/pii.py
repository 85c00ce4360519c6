"""Personal data: regular expressions propose spans, checksums confirm them, context words weigh them.

Only DataFrame functions: a match's place is the summed length of the pieces that
`split` leaves before it and of the matches before it, in code points. The patterns are
written so that the engine never tries a start that must fail (`\\G` or a look-behind
opens a run, possessive loops never give back), which keeps them linear in the text
and gives the same leftmost matches.

Nulls count as empty text, an empty text has no spans, repeated rows repeat, input
columns named like a result column stay as they are in `annotate` unless they are
asked for under that name (then the result replaces them).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_LOCAL = r"A-Za-z0-9._%+-"
#: Kind, pattern, and the sign that a text must hold for a match (none: any text is searched).
PATTERNS = (
    ("email", rf"(?:\G|(?<![{_LOCAL}]))[{_LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@"),
    ("ip", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", "."),
    ("card", r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){15,18}+(?![\x20-]?[0-9])", None),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", "+"),
)
IBAN = ("iban", r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?", None)
BASE_KINDS = tuple(kind for kind, _, _ in PATTERNS)
#: Words near a span that speak for or against it.
SUPPORT = {
    "email": "mail|contact|write|address",
    "ip": "host|server|address|login|client",
    "card": "card|visa|pay|credit|debit",
    "phone": "phone|call|tel|mobile|fax|dial",
    "iban": "iban|account|bank|transfer",
}
AGAINST = "example|sample|version|dummy|order no|invoice no"
CONTEXT = 40
START_SCORE, STEP = 0.7, 0.2

_digits = lambda c: F.regexp_replace(c, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the Luhn sum."""
    n = F.length(digits)

    def step(acc, i):
        d = F.substr(digits, n - i, F.lit(1)).cast("int")
        twice = F.when(d > 4, d * 2 - 9).otherwise(d * 2)
        return acc + F.when(i % 2 == 1, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(0), n - 1), F.lit(0), step) % 10 == 0


def mod97(code: Column) -> Column:
    """Whether an account number with country and check digits in front leaves 1 modulo 97."""
    turned = F.concat(F.substr(code, F.lit(5)), F.substr(code, F.lit(1), F.lit(4)))

    def step(acc, c):
        v = F.when(c >= "A", F.ascii(c) - 55).otherwise(F.ascii(c) - 48)
        return (acc * F.when(v > 9, 100).otherwise(10) + v) % 97

    return F.aggregate(F.split(turned, ""), F.lit(0), step) == 1


def _valid(kind: str, match: Column) -> Column:
    if kind == "ip":
        return match.rlike(r"^(?:0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])(?:\.|$)){4}$")
    if kind == "card":
        digits = _digits(match)
        return F.length(digits).between(16, 19) & luhn(digits)
    if kind == "phone":
        return F.length(_digits(match)).between(8, 15)
    if kind == "iban":
        code = F.replace(match, F.lit(" "), F.lit(""))
        return F.length(code).between(15, 34) & mod97(code)
    return F.lit(True)


def _spans(text: Column, kind: str, pattern: str, sign: str | None) -> Column:
    """Confirmed spans of a kind as an array of (kind, start, end, score), by start."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    between = F.split(text, pattern, -1)
    total = lambda a: F.aggregate(a, F.lit(0), lambda acc, x: acc + F.length(x))

    def place(match, i):
        start = total(F.slice(between, 1, i + 1)) + total(F.slice(found, 1, i))
        return F.struct(start.alias("start"), match.alias("match"))

    def judged(s):
        start, end = s["start"], s["start"] + F.length(s["match"])
        low = F.greatest(start - CONTEXT, F.lit(0))
        near = F.lower(F.concat(F.substr(text, low + 1, start - low), F.lit(" "), F.substr(text, end + 1, F.lit(CONTEXT))))
        score = START_SCORE + F.when(near.rlike(SUPPORT[kind]), STEP).otherwise(0.0) - F.when(near.rlike(AGAINST), STEP).otherwise(0.0)
        return F.struct(F.lit(kind).alias("kind"), start.alias("start"), end.alias("end"), F.round(score, 2).alias("score"))

    spans = F.transform(F.filter(F.transform(found, place), lambda s: _valid(kind, s["match"])), judged)
    none = F.array().cast("array<struct<kind:string,start:int,end:int,score:double>>")
    may = text.contains(sign) if sign else text.rlike("[0-9]{2}" if kind == "iban" else "[0-9]")
    return F.when(may, spans).otherwise(none)


def find(text: Column) -> Column:
    """All spans of a text column: base kinds in their order, then account numbers; by start within a kind."""
    safe = F.coalesce(text, F.lit(""))
    return F.concat(*(_spans(safe, *p) for p in (*PATTERNS, IBAN)))


def annotate(df: DataFrame, text: str = "text", into: str = "pii") -> DataFrame:
    """The rows with the column `into`: an array of (kind, start, end, score)."""
    return df.withColumn(into, find(F.col(text)))


def _written(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def digest(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Counts and spans per row; `scored` adds each span's score, `n_strong` counts scores of 0.7 and more."""
    # two steps keep the span array one value that the columns share
    spans = df.select(key, find(F.col(text)).alias("s")).withColumn("b", F.filter("s", lambda s: s["kind"] != "iban"))
    count = lambda kind: F.size(F.filter("s", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return spans.select(
        key,
        *(count(kind) for kind in (*BASE_KINDS, "iban")),
        F.sha2(_written(F.col("b")).cast("binary"), 256).alias("base_sha256"),
        _written(F.col("s")).alias("spans"),
        F.array_join(F.transform("s", lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"], s["score"])), ",").alias("scored"),
        F.size(F.filter("s", lambda s: s["score"] >= START_SCORE)).cast("long").alias("n_strong"),
    )


def redact(df: DataFrame, text: str = "text", mask: str = "[%s]", least: float = 0.0) -> DataFrame:
    """The rows with each span of at least the score `least` replaced by its kind in brackets; nulls stay null.

    Overlapping spans are masked as one under the kind that starts first.
    """
    spans = F.array_sort(
        F.filter(find(F.col(text)), lambda s: s["score"] >= least),
        lambda a, b: F.when(a["start"] != b["start"], a["start"] - b["start"]).otherwise(b["end"] - a["end"]),
    )
    start = F.struct(F.lit("").alias("done"), F.lit(0).alias("at"))
    c = F.col(text)

    def step(acc, s):
        named = F.format_string(mask, s["kind"])
        cut = F.concat(acc["done"], F.substr(c, acc["at"] + 1, s["start"] - acc["at"]), named)
        return F.when(
            s["start"] >= acc["at"], F.struct(cut.alias("done"), s["end"].alias("at"))
        ).otherwise(F.struct(acc["done"].alias("done"), F.greatest(acc["at"], s["end"]).alias("at")))

    masked = F.aggregate(spans, start, step, lambda acc: F.concat(acc["done"], F.substr(c, acc["at"] + 1)))
    return df.withColumn(text, F.when(F.size(spans) > 0, masked).otherwise(c))
