"""Personal data spans with DataFrame functions only: patterns propose, checksums confirm, context adjusts.

Offsets come without Python: the text split at a pattern gives the gaps, the extracted matches lie between
them, and running lengths of both are code-point offsets. Patterns are written so that a scan is linear: a run
is entered only at its start (or where the last match ended) and repeated groups never give back.

Edge cases: null text has no spans; a match that fails its check is dropped and not retried; repeated rows
give repeated results; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_of

CHUNK = 512
KINDS = ["email", "ip", "card", "phone", "iban"]  # in the order of the digest; the last is added by checksum
_LOCAL = "[A-Za-z0-9._%+-]"
PATTERNS = {
    "email": rf"(?:\G|(?<!{_LOCAL})){_LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"[0-9](?:[\x20-]?+[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "iban": r"\b[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?\b",
}
# A cheap test that a text may hold the kind at all.
HINTS = {"email": "@", "phone": "+"}
# Words that raise a span's score when they stand shortly before it.
CONTEXT = {
    "email": "mail|contact|write|kontakt|correo|courriel",
    "ip": "ip|host|server|address|adresse",
    "card": "card|visa|credit|payment|karte|carte|tarjeta",
    "phone": "phone|call|tel|mobile|fax|anruf|llam",
    "iban": "iban|account|bank|konto|compte|cuenta",
}
# Kinds without a checksum or a telling form stay under SURE unless a context word stands before them.
BASE_SCORE = {"email": 0.9, "ip": 0.4, "card": 0.8, "phone": 0.4, "iban": 0.85}
SURE, RAISE = 0.5, 0.15


def digits_of(match: Column) -> Column:
    return F.regexp_replace(match, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether a digit string passes the Luhn check."""
    n = F.length(digits)
    digit = lambda i: F.substring(digits, i, F.lit(1)).cast("int")

    def value(i: Column) -> Column:
        twice = digit(i) * 2
        return F.when(F.pmod(n - i, F.lit(2)) == 1, F.when(twice > 9, twice - 9).otherwise(twice)).otherwise(digit(i))

    return F.aggregate(F.sequence(F.lit(1), n), F.lit(0), lambda a, i: a + value(i)) % 10 == 0


def mod97(match: Column) -> Column:
    """Whether an account number passes the mod-97 check: letters count 10 to 35, the first four characters go last."""
    plain = F.regexp_replace(match, r"\x20", "")
    turned = F.concat(F.substring(plain, F.lit(5), F.length(plain)), F.substring(plain, 1, 4))

    def step(a: Column, i: Column) -> Column:
        code = F.ascii(F.substring(turned, i, F.lit(1)))
        return F.when(code >= 65, (a * 100 + code - 55) % 97).otherwise((a * 10 + code - 48) % 97)

    return (F.length(plain) >= 15) & (F.length(plain) <= 34) & (F.aggregate(F.sequence(F.lit(1), F.length(turned)), F.lit(0), step) == 1)


def confirmed(kind: str, match: Column) -> Column:
    if kind == "ip":
        small = lambda p: F.coalesce(p.try_cast("int"), F.lit(256)) <= 255
        return F.forall(F.split(match, r"\."), small)
    if kind == "card":
        d = digits_of(match)
        return F.when(F.length(d).between(12, 19), luhn(d)).otherwise(F.lit(False))
    if kind == "phone":
        return F.length(digits_of(match)).between(9, 15)
    if kind == "iban":
        return mod97(match)
    return F.lit(True)


def proposals(kind: str, text: Column) -> Column:
    """Array of (start, end, match, before): all matches of the kind's pattern, in order; ``before`` is the gap's end."""
    gaps, found = F.split(text, PATTERNS[kind], -1), F.regexp_extract_all(text, F.lit(PATTERNS[kind]), F.lit(0))
    both = F.zip_with(F.slice(gaps, F.lit(1), F.size(found)), found, lambda g, m: F.struct(g.alias("g"), m.alias("m")))
    none = F.expr("cast(array() as array<struct<s:int,e:int,m:string,before:string>>)")

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["g"])
        end = start + F.length(x["m"])
        one = F.struct(start.alias("s"), end.alias("e"), x["m"].alias("m"), F.right(x["g"], F.lit(40)).alias("before"))
        return F.struct(end.alias("at"), F.concat(acc["done"], F.array(one)).alias("done"))

    # arrays grow by copies, so matches are numbered in chunks: texts with very many stay far from quadratic
    def chunk(acc: Column, c: Column) -> Column:
        inner = F.aggregate(F.slice(both, c * CHUNK + 1, F.lit(CHUNK)), F.struct(acc["at"].alias("at"), none.alias("done")), step)
        return F.struct(inner["at"].alias("at"), F.concat(acc["done"], inner["done"]).alias("done"))

    chunks = F.sequence(F.lit(0), F.floor((F.size(found) - 1) / CHUNK).cast("int"))
    start = F.struct(F.lit(0).alias("at"), none.alias("done"))
    return F.when(F.size(found) > 0, F.aggregate(chunks, start, chunk, lambda acc: acc["done"])).otherwise(none)


def _scored(kind: str, spans: Column) -> Column:
    """Confirmed spans with their score: a context word shortly before raises the kind's base score."""

    def one(x: Column) -> Column:
        near = F.lower(x["before"]).rlike(f"(?:^|[^a-z])(?:{CONTEXT[kind]})")
        score = F.when(near, F.least(F.lit(1.0), F.lit(BASE_SCORE[kind]) + RAISE)).otherwise(F.lit(BASE_SCORE[kind]))
        return F.struct(x["s"].alias("start"), F.lit(KINDS.index(kind)).alias("ord"), F.lit(kind).alias("kind"), x["e"].alias("end"), score.alias("score"))

    return F.transform(spans, one)


def find_spans(docs: DataFrame, kinds: list[str] | None = None) -> DataFrame:
    """doc_id and ``spans``: array of (start, ord, kind, end, score) in the order of start, then kind."""
    kinds = kinds or KINDS
    text = text_of()
    nothing = F.expr("cast(array() as array<struct<start:int,ord:int,kind:string,end:int,score:double>>)")
    raw_type = "array<struct<s:int,e:int,m:string,before:string>>"
    df = docs.select("doc_id", text.alias("text"))
    for kind in kinds:
        maybe = F.contains(F.col("text"), F.lit(HINTS[kind])) if kind in HINTS else F.col("text").rlike({"ip": r"[0-9]\.[0-9]", "card": r"[0-9][\x20-]?[0-9]", "iban": r"[A-Z]{2}[0-9]{2}"}[kind])
        df = df.withColumn(f"raw_{kind}", F.when(maybe, proposals(kind, F.col("text"))).otherwise(F.expr(f"cast(array() as {raw_type})")))
    parts = []
    for kind in kinds:
        parts.append(_scored(kind, F.filter(F.col(f"raw_{kind}"), lambda x: confirmed(kind, x["m"]))))  # noqa: B023  called at once
    return df.select("doc_id", F.array_sort(F.concat(nothing, *parts)).alias("spans"))


def digest(found: DataFrame) -> DataFrame:
    """Counts of the base kinds, the digest of the base spans, all spans as text, and how many spans reach SURE with their context."""
    base = F.filter("spans", lambda s: s["ord"] < 4)
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("spans", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    return found.select("doc_id", *[count(k) for k in KINDS[:4]], F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"), F.size(F.filter("spans", lambda s: s["score"] >= SURE)).cast("long").alias("n_sure"))


def masked(docs: DataFrame, least_score: float = SURE) -> DataFrame:
    """doc_id and text with every span of at least ``least_score`` replaced by its kind in brackets; overlapping spans merge into the first."""
    found = find_spans(docs).withColumn("spans", F.filter("spans", lambda s: s["score"] >= least_score))
    start = F.expr("struct(cast(0 as int) as at, '' as made, text as text)")

    def step(acc: Column, s: Column) -> Column:
        later = s["start"] >= acc["at"]
        made = F.concat(acc["made"], F.substring(acc["text"], acc["at"] + 1, s["start"] - acc["at"]), F.lit("["), s["kind"], F.lit("]"))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(later, made).otherwise(acc["made"]).alias("made"), acc["text"].alias("text"))

    both = docs.select("doc_id", text_of().alias("text")).join(found, "doc_id")
    return both.select("doc_id", F.aggregate("spans", start, step, lambda a: F.concat(a["made"], F.substring(a["text"], a["at"] + 1, F.length(a["text"])))).alias("text"))
