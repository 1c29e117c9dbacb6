"""Personal data by patterns, checksums and context words, in Catalyst expressions alone.

A pattern proposes spans, a validator confirms them (Luhn for cards, mod 97 for IBANs, ranges for
addresses), and words near by move the score: terms that go with the kind raise it, terms that
speak against it (order or version numbers, say) lower it.  The base kinds need no context to stay;
added kinds stay from ``threshold`` on.

Positions come from the gaps: splitting at a pattern gives the texts between its matches, whose
lengths and the matches' own add up to starts and ends in code points.  Patterns are possessive and
anchored at the start of a run of their characters or the last match's end, which finds the same
spans as the plain ones, in linear time and without recursion however long the text.

Defined results: a null text is an empty one and has no spans; ties cannot occur within a kind
(matches do not overlap), spans of different kinds may overlap; repeated rows give repeated rows;
extra columns pass through, but for one with the result's name, which is replaced.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Kind:
    """One kind of personal data.  ``base`` kinds stay whatever their score."""

    name: str
    pattern: str
    near: str
    against: str = ""
    base: bool = True
    prior: float = 0.9


# The patterns of the base kinds, each in its possessive form, and of the added ones.
EMAIL = Kind("email", r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "mail|contact|write|kontakt|correo")
IP = Kind("ip", r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", "ip|address|host|server|login", "version|release|build")
CARD = Kind("card", r"[0-9](?:[\x20-]?+[0-9])++", "card|visa|credit|karte|tarjeta|carte", "order|invoice|isbn|serial")
PHONE = Kind("phone", r"\+[0-9][\x20().0-9-]+[0-9]", "phone|tel|call|mobile|fax|whatsapp", "order|invoice|serial")
IBAN = Kind("iban", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?+[A-Z0-9]){11,30}+(?![A-Za-z0-9])", "iban|account|bank|konto|cuenta|compte", base=False, prior=0.8)
LOCAL_PHONE = Kind("local_phone", r"(?<![0-9A-Za-z+.-])(?:\([0-9]{3}\)\x20?|[0-9]{3}[\x20.-])[0-9]{3}[\x20.-][0-9]{4}(?![0-9A-Za-z])", "phone|tel|call|mobile|fax|whatsapp|cell", "order|invoice|serial|part", base=False, prior=0.3)
TAX_ID = Kind("tax_id", r"(?<![0-9A-Za-z-])(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}(?![0-9A-Za-z-])", "ssn|social|security|tax", "order|invoice|serial|part", base=False, prior=0.4)
BASE_KINDS = (EMAIL, IP, CARD, PHONE)
KINDS = (*BASE_KINDS, IBAN, LOCAL_PHONE, TAX_ID)

SPAN = "array<struct<kind:string,start:int,end:int,score:double>>"
#: Matches are numbered in blocks of this many: adding to an array copies it, and blocks keep the copies short.
_BLOCK = 128


def luhn(digits: Column) -> Column:
    """Whether a string of digits has a valid Luhn checksum."""
    places = F.split(F.reverse(digits), "")
    doubled = F.transform(places, lambda d, i: F.when(i % 2 == 0, d.cast("int")).otherwise(d.cast("int") * 2))
    return F.aggregate(doubled, F.lit(0), lambda total, d: total + F.when(d > 9, d - 9).otherwise(d)) % 10 == 0


def mod97(account: Column) -> Column:
    """Whether an IBAN (no blanks) has the remainder 1: its head goes last, letters count from 10."""
    turned = F.concat(F.substring(account, 5, 40), F.substring(account, 1, 4))
    value = lambda c: F.when(c.between("0", "9"), c.cast("int")).otherwise(F.ascii(c) - 55)
    step = lambda rest, c: F.when(value(c) > 9, (rest * 100 + value(c)) % 97).otherwise((rest * 10 + value(c)) % 97)
    return F.aggregate(F.split(turned, ""), F.lit(0), step) == 1


def _valid(kind: str, match: Column) -> Column:
    digits = F.regexp_replace(match, "[^0-9]", "")
    if kind == "ip":
        part = lambda p: F.regexp_replace(p, "^0+(?=[0-9])", "")
        return F.forall(F.split(match, r"\."), lambda p: F.when(F.length(part(p)) <= 3, part(p).cast("int") <= 255).otherwise(False))
    if kind == "card":
        return F.when(F.length(digits).between(16, 19), luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(digits).between(8, 15)
    if kind == "iban":
        return mod97(F.replace(match, F.lit(" "), F.lit("")))
    return F.lit(True)


def _score(kind: Kind, before: Column, after: Column) -> Column:
    """Prior, plus 0.4 for a word of the kind near by, less 0.3 for one that speaks against it."""
    around = F.lower(F.concat(F.substring(before, -40, 40), F.lit(" "), F.substring(after, 1, 24)))
    score = F.lit(kind.prior) + F.when(around.rlike(rf"\b(?:{kind.near})"), 0.4).otherwise(0.0)
    if kind.against:
        score = score - F.when(around.rlike(rf"\b(?:{kind.against})"), 0.3).otherwise(0.0)
    return F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.round(score, 3)))


def _spans(text: Column, kind: Kind, threshold: float) -> Column:
    """Valid spans of one kind, by start: numbered in blocks, each a fold over its matches."""
    found = F.regexp_extract_all(text, F.lit(kind.pattern), F.lit(0))
    gaps = F.split(text, kind.pattern, -1)

    def place(matches: Column, between: Column) -> Column:
        empty = F.expr("cast(array() as array<struct<start:int,match:string,before:string,after:string>>)")

        def one(state: Column, i: Column) -> Column:
            start = state["at"] + F.length(F.get(between, i))
            item = F.struct(start.alias("start"), F.get(matches, i).alias("match"), F.get(between, i).alias("before"), F.get(between, i + 1).alias("after"))
            return F.struct((start + F.length(F.get(matches, i))).alias("at"), F.array_append(state["got"], item).alias("got"))

        def block(state: Column, b: Column) -> Column:
            last = F.least((b + 1) * _BLOCK, F.size(matches)) - 1
            inner = F.aggregate(F.sequence(b * _BLOCK, last), F.struct(state["at"].alias("at"), empty.alias("got")), one)
            return F.aggregate(F.array(inner), state, lambda s, x: F.struct(x["at"].alias("at"), F.array_append(s["got"], x["got"]).alias("got")))

        blocks = F.sequence(F.lit(0), F.floor((F.size(matches) - 1) / _BLOCK).cast("int"))
        start = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<array<struct<start:int,match:string,before:string,after:string>>>)").alias("got"))
        return F.flatten(F.aggregate(blocks, start, block, lambda s: s["got"]))

    placed = F.aggregate(F.array(F.struct(found.alias("m"), gaps.alias("g"))), F.expr("cast(array() as array<struct<start:int,match:string,before:string,after:string>>)"), lambda _, x: F.when(F.size(x["m"]) > 0, place(x["m"], x["g"])).otherwise(_))
    sure = F.filter(placed, lambda x: _valid(kind.name, x["match"]))
    scored = F.transform(sure, lambda x: F.struct(F.lit(kind.name).alias("kind"), x["start"].alias("start"), (x["start"] + F.length(x["match"])).alias("end"), _score(kind, x["before"], x["after"]).alias("score")))
    kept = scored if kind.base else F.filter(scored, lambda s: s["score"] >= threshold)
    return F.when(text.rlike(kind.pattern), kept).otherwise(F.expr(f"cast(array() as {SPAN})"))


def find_spans(df: DataFrame, *, text: str = "text", result: str = "pii_spans", kinds: tuple[Kind, ...] = KINDS, threshold: float = 0.7) -> DataFrame:
    """Adds ``result``: array of (kind, start, end, score), by kind in the order of ``kinds``, then by start."""
    whole = F.coalesce(F.col(text), F.lit(""))
    return df.withColumn(result, F.concat(*(_spans(whole, k, threshold) for k in kinds)))


def count_of(spans: str, kind: Kind) -> Column:
    """How many spans are of a kind."""
    return F.size(F.filter(spans, lambda s: s["kind"] == kind.name)).cast("long")


def span_text(spans: Column) -> Column:
    """``kind:start:end``, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(text: Column, spans: Column) -> Column:
    """The text with each span replaced by ``<KIND>``; of overlapping spans, the one that starts first and then is longest."""
    ordered = F.array_sort(spans, lambda a, b: F.when(a["start"] != b["start"], a["start"] - b["start"]).otherwise(b["end"] - a["end"]))
    first = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<string>)").alias("parts"))
    tag = lambda s: F.concat(F.lit("<"), F.upper(s["kind"]), F.lit(">"))
    step = lambda st, s: F.when(s["start"] < st["at"], st).otherwise(F.struct(s["end"].alias("at"), F.concat(st["parts"], F.array(F.substring(text, st["at"] + 1, s["start"] - st["at"]), tag(s))).alias("parts")))
    done = lambda st: F.concat(F.array_join(st["parts"], ""), F.substring(text, st["at"] + 1, F.length(text)))
    return F.when(F.size(spans) == 0, text).otherwise(F.aggregate(ordered, first, step, done))
