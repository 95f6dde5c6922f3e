"""Personal data: patterns propose spans, checksums confirm them, context scores them.

Built-in functions only. Places come from splitting a text at a pattern: the
lengths of what lies between matches and of the matches, summed up, are their
starts. Patterns use possessive loops, which match as the plain ones (what
follows can't be part of the loop) but neither recurse nor go back.
"""

from __future__ import annotations

import functools
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._spark import masked

#: Kinds in the order of the result; the first four are the base.
BASE_KINDS = ["email", "ip", "card", "phone"]
#: Characters before a span in which a context word is looked for; score from which a span of the method's own kinds counts.
REACH, LEAST_SCORE = 40, 0.5
#: Spans appended to one array before the next is begun (appending copies).
RUN = 256


@dataclass(frozen=True)
class Kind:
    """pattern proposes; ``likely`` is a cheap test of the text; ``score`` of a confirmed match, plus ``lift`` beside a context word."""

    name: str
    pattern: str
    likely: str
    context: str
    score: float
    lift: float


#: Patterns, context words and scores. An email may begin only where no local part goes on, or right after the last match.
KINDS = [
    Kind("email", r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@", r"mail|contact|write", 0.9, 0.1),
    Kind("ip", r"[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)", r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]", r"\bip\b|address|host|server", 0.6, 0.3),
    Kind("card", r"[0-9](?:[ -]?[0-9]){13,}+", r"[0-9](?:[ -]?[0-9]){13}", r"card|visa|credit|pay", 0.7, 0.3),
    Kind("phone", r"\+[0-9][ ().0-9-]+[0-9]", "+", r"phone|call|tel|mobile|fax", 0.7, 0.3),
    Kind("iban", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])", r"[A-Z]{2}[0-9]{2} ?[A-Z0-9]{4}", r"iban|bank|account|konto", 0.8, 0.2),
    Kind("secret", r"(?<=[:=][\"' ]{0,3})[A-Za-z0-9_+/.~!@#$%^&*=-]{4,}+", r"(?i)(?:token|secret|password|passwd|pwd|(?:api|access).?key)[\"' ]*+[:=]", r"(?:token|secret|password|passwd|pwd|api.?key|access.?key)[\"' ]*[:=][\"' ]*$", 0.2, 0.7),
    Kind("key", r"(?<![A-Za-z0-9])(?:AKIA[0-9A-Z]{16}+|gh[pousr]_[A-Za-z0-9]{36,}+|sk-[A-Za-z0-9_-]{20,}+|xox[abprs]-[A-Za-z0-9-]{10,}+|eyJ[A-Za-z0-9_-]{8,}+\.[A-Za-z0-9_-]{8,}+\.[A-Za-z0-9_-]{8,}+)", r"AKIA|gh[pousr]_|sk-|xox[abprs]-|eyJ", r"key|token|secret", 0.8, 0.2),
]


def luhn(digits: Column) -> Column:
    """The Luhn checksum of a string of digits holds."""

    def add(total: Column, digit: Column, place: Column) -> Column:
        d = digit.cast("int") * F.when(place % 2 == 1, 2).otherwise(1)
        return total + F.when(d > 9, d - 9).otherwise(d)

    placed = F.transform(F.reverse(F.filter(F.split(digits, ""), lambda x: x != "")), lambda x, i: F.struct(x.alias("d"), i.alias("i")))
    return F.aggregate(placed, F.lit(0), lambda t, x: add(t, x["d"], x["i"])) % 10 == 0


def mod97(code: Column) -> Column:
    """An account number's check digits hold: rotated by four, letters as 10 to 35, the number is 1 modulo 97."""
    plain = F.replace(code, F.lit(" "), F.lit(""))
    moved = F.concat(F.substring(plain, 5, 100), F.substring(plain, 1, 4))
    step = lambda t, c: F.when(c.between("0", "9"), (t * 10 + F.ascii(c) - 48) % 97).otherwise((t * 100 + F.ascii(c) - 55) % 97)
    return F.aggregate(F.filter(F.split(moved, ""), lambda x: x != ""), F.lit(0), step) == 1


def _confirmed(kind: str, match: Column) -> Column:
    digits = F.regexp_replace(match, "[^0-9]", "")
    if kind == "ip":
        return F.forall(F.split(match, r"\."), lambda p: (F.length(F.ltrim(p, F.lit("0"))) <= 3) & (F.concat(F.lit("0"), F.right(p, F.lit(3))).cast("int") <= 255))
    if kind == "card":
        return F.length(digits).between(14, 19) & luhn(F.when(F.length(digits) <= 19, digits).otherwise(""))
    if kind == "phone":
        return F.length(digits).between(10, 15)
    if kind == "iban":
        return F.length(F.replace(match, F.lit(" "), F.lit(""))).between(15, 34) & mod97(match)
    return F.lit(True)


_SPAN = "struct<start:int,stop:int,score:double>"


def _find(text: Column, kind: Kind) -> Column:
    """Confirmed spans of a kind in order: array of start, stop (code points, past the end), score."""
    parts = F.split(text, kind.pattern, -1)
    matches = F.regexp_extract_all(text, F.lit(kind.pattern), F.lit(0))
    pairs = F.filter(F.zip_with(parts, matches, lambda p, m: F.struct(F.length(p).alias("gap"), p.alias("before"), m.alias("m"))), lambda x: x["m"].isNotNull())
    none = F.array().cast(f"array<{_SPAN}>")
    zero = F.struct(F.lit(0).alias("at"), none.alias("run"), F.array().cast(f"array<array<{_SPAN}>>").alias("done"))

    def step(a: Column, x: Column) -> Column:
        start = a["at"] + x["gap"]
        stop = start + F.length(x["m"])
        near = F.rlike(F.right(F.lower(x["before"]), F.lit(REACH)), F.lit(kind.context))
        score = F.lit(kind.score) + F.when(near, kind.lift).otherwise(0.0)
        span = F.struct(start.alias("start"), stop.alias("stop"), score.alias("score"))
        run = F.when(_confirmed(kind.name, x["m"]) & (F.lit(kind.name in BASE_KINDS) | (score >= LEAST_SCORE)), F.concat(a["run"], F.array(span))).otherwise(a["run"])
        full = F.size(a["run"]) >= RUN
        return F.when(full, F.struct(a["at"].alias("at"), none.alias("run"), F.concat(a["done"], F.array(a["run"])).alias("done"))).otherwise(a).withField("at", stop).withField("run", F.when(full & (F.size(run) > F.size(a["run"])), F.array(span)).when(full, none).otherwise(run))

    found = F.aggregate(pairs, zero, step, lambda a: F.flatten(F.concat(a["done"], F.array(a["run"]))))
    likely = F.contains(text, F.lit(kind.likely)) if len(kind.likely) == 1 else F.rlike(text, F.lit(kind.likely))
    return F.when(likely, found).otherwise(none)


def with_spans(df: DataFrame, text: str = "text", to: str = "__pii") -> DataFrame:
    """Adds ``to``: a struct with an array of spans for each kind."""
    own = df.columns
    t = "__pii_text"
    # A generator of one row, so that uses of the struct don't repeat what is below it.
    return df.withColumn(t, F.coalesce(F.col(text), F.lit(""))).select(*own, F.explode(F.array(F.struct(*(_find(F.col(t), k).alias(k.name) for k in KINDS)))).alias(to))


def all_spans(kinds: list[str], pii: str = "__pii") -> Column:
    """Spans of kinds as one array of start, order of kind, stop, kind; sorted by start, then kind."""
    order = {k.name: i for i, k in enumerate(KINDS)}
    named = lambda k: lambda x: F.struct(x["start"].alias("start"), F.lit(order[k]).alias("order"), x["stop"].alias("stop"), F.lit(k).alias("kind"))
    return F.sort_array(F.concat(*(F.transform(F.col(f"{pii}.{k}"), named(k)) for k in kinds)))


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["stop"].cast("string"))), ",")


def find_personal_data(docs: DataFrame) -> DataFrame:
    """Per row: doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_iban, n_secret, n_key, n_spans (of all kinds).

    spans lists kind:start:end, code points, end exclusive.

    Defined cases: null or empty text has no spans and the hash of the empty
    string. Rows stand alone, so doc_id may be null or repeat. An empty table gives no rows.
    """
    df = with_spans(docs.select(F.col("doc_id").cast("long"), "text"))
    n = lambda k: F.size(f"__pii.{k}").cast("long").alias(f"n_{k}")
    return df.select("doc_id", *map(n, BASE_KINDS), F.sha2(_listed(all_spans(BASE_KINDS)).cast("binary"), 256).alias("base_sha256"), _listed(all_spans([k.name for k in KINDS])).alias("spans"), n("iban"), n("secret"), n("key"), functools.reduce(lambda x, y: x + y, (F.size(f"__pii.{k.name}") for k in KINDS)).cast("long").alias("n_spans"))


def redact(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with every span of its text as [KIND]; overlapping spans become one, named by the first. Null stays null; rows stand alone; an empty table gives no rows."""
    rows, own = masked(docs)
    text = own[text]
    df = with_spans(rows, text)
    spans = all_spans([k.name for k in KINDS])
    # What stays, from the end of one span to the start of the next, and what stands for spans, alternating.
    zero = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("run"), F.array().cast("array<array<string>>").alias("done"))

    def step(a: Column, x: Column) -> Column:
        piece = F.array(F.substring(F.col(text), a["at"] + 1, x["start"] - a["at"]), F.concat(F.lit("["), F.upper(x["kind"]), F.lit("]")))
        full = F.size(a["run"]) >= RUN
        apart = x["start"] >= a["at"]
        return F.struct(
            F.greatest(a["at"], x["stop"]).alias("at"),
            F.when(apart & full, piece).when(apart, F.concat(a["run"], piece)).otherwise(a["run"]).alias("run"),
            F.when(apart & full, F.concat(a["done"], F.array(a["run"]))).otherwise(a["done"]).alias("done"),
        )

    def end(a: Column) -> Column:
        return F.array_join(F.flatten(F.concat(a["done"], F.array(a["run"]), F.array(F.array(F.substring(F.col(text), a["at"] + 1, F.length(F.col(text))))))), "")

    clean = F.when(F.size(spans) > 0, F.aggregate(spans, zero, step, end)).otherwise(F.col(text))
    return df.select(*(clean.alias(c) if c == text else F.col(c) for c in own.values())).toDF(*own)
