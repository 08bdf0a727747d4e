"""Personal data: regular expressions propose spans, checksums confirm them, words nearby move the score.

All of it is DataFrame functions. The text is split at each kind's matches, so that the lengths of the
pieces give the places of all matches in one pass; no pattern runs again from inside a match. The patterns
are written so that the engine neither recurses over a long match nor starts anew inside a long run.

The four base kinds are always kept once their own check holds (parts of an address, Luhn, digits of a
number). Kinds beyond these start from a score of their own, gain with a word of context nearby and count
from the threshold on: IBANs that pass mod 97, national numbers of the form 3-2-4 digits, and telephone
numbers without a country's prefix.

Results on odd input: null or empty text has no spans; ids and repeated rows pass as they are; an empty
table gives no rows; further columns are not read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

THRESHOLD = 0.5
#: Characters before and after a span in which a word of context counts.
NEAR = 40
#: Matches that are placed one after another before their places are moved together.
RUN = 256


@dataclass(frozen=True)
class Kind:
    name: str
    pattern: str
    needs: str | re.Pattern  # a text without this cheap sign has no match; empty for the sign of long numbers
    check: object  # Column of the match -> Column of boolean
    score: float
    context: str  # lower-case words
    bonus: float = 0.4
    base: bool = False


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _count(m: Column, low: int, high: int) -> Column:
    return F.length(_digits(m)).between(low, high)


def _parts(m: Column) -> Column:
    bare = F.transform(F.split(m, r"\."), lambda x: F.regexp_replace(x, "^0+(?=[0-9])", ""))
    return F.forall(bare, lambda x: (F.length(x) < 3) | ((F.length(x) == 3) & (x <= "255")))


def _card(m: Column) -> Column:
    return _count(m, 14, 19) & F.call_function("luhn_check", _digits(m))


def _mod97(m: Column) -> Column:
    """Remainder 1 of the number that is read after the first four characters have gone to the end and letters stand for 10 to 35."""
    bare = F.regexp_replace(m, " ", "")
    turned = F.concat(F.substring(bare, 5, 64), F.substring(bare, 1, 4))
    code = lambda c: F.when(c.between("A", "Z"), F.ascii(c) - 55).otherwise(F.ascii(c) - 48)
    value = F.aggregate(F.split(turned, ""), F.lit(0), lambda acc, c: F.when(c == "", acc).otherwise(F.pmod(acc * F.when(c.between("A", "Z"), 100).otherwise(10) + code(c), F.lit(97))).cast("int"))
    return F.length(bare).between(15, 34) & (value == 1)


#: Order is that of kinds which start at the same place.
KINDS = (
    Kind("email", r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@", lambda m: F.lit(True), 0.9, r"\b(mail|e-mail|contact|write)\b", base=True),
    Kind("ip", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", ".", _parts, 0.6, r"\b(ip|address|host|server)\b", base=True),
    Kind("card", r"[0-9](?:[\x20-]?[0-9])++", "", _card, 0.8, r"\b(card|visa|credit|payment|mastercard)\b", base=True),
    Kind("phone", r"\+[0-9][\x20().0-9-]+[0-9]", "+", lambda m: _count(m, 10, 15), 0.7, r"\b(phone|tel|call|mobile|fax)\b", base=True),
    Kind("iban", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}+(?:\x20?[A-Z0-9]{1,3})?+(?![A-Za-z0-9])", "", _mod97, 0.8, r"\b(iban|account|bank|konto)\b"),
    Kind("national_id", r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])", "-", lambda m: ~m.rlike("^(000|666|9)|-00-|-0000$"), 0.3, r"\b(ssn|social security)\b"),
    Kind("local_phone", r"(?<![0-9+)(-])(?<!\+[0-9]{1,3}\x20)\(?[0-9]{3}\)?[\x20.-][0-9]{3}[.-][0-9]{4}(?![0-9.-])", re.compile("[0-9]{3}[.-][0-9]{4}"), lambda m: _count(m, 10, 10), 0.3, r"\b(phone|tel|telephone|call|mobile|fax)\b"),
)


def _spans(text: Column, k: int, kind: Kind) -> Column:
    """Array of (start, kind number, end, kind, score) of the kind's confirmed matches, places in code points."""
    pattern = F.lit(kind.pattern)
    found = F.regexp_extract_all(text, pattern, F.lit(0))
    pieces = F.split(text, kind.pattern, -1)
    #: Running place: the n-th match begins after the first n pieces and the n-1 matches before it. An accumulator is copied at every step, so matches are
    #: placed within runs of RUN first, and the runs then moved to where they begin.
    none = F.array().cast("array<struct<start:int,m:string>>")
    start = F.struct(F.lit(0).alias("at"), none.alias("out"))
    step = lambda acc, x: F.struct((acc["at"] + F.length(x["p"]) + F.length(x["m"])).alias("at"), F.concat(acc["out"], F.array(F.struct((acc["at"] + F.length(x["p"])).alias("start"), x["m"].alias("m")))).alias("out"))
    pairs = F.zip_with(F.slice(pieces, 1, F.size(found)), found, lambda p, m: F.struct(p.alias("p"), m.alias("m")))
    runs = F.transform(F.sequence(F.lit(0), F.floor((F.size(found) - 1) / RUN).cast("int")), lambda i: F.aggregate(F.slice(pairs, i * RUN + 1, F.lit(RUN)), start, step))
    moved = lambda acc, r: F.struct((acc["at"] + r["at"]).alias("at"), F.concat(acc["out"], F.array(F.transform(r["out"], lambda x: F.struct((x["start"] + acc["at"]).alias("start"), x["m"].alias("m"))))).alias("out"))
    first = F.struct(F.lit(0).alias("at"), F.array().cast("array<array<struct<start:int,m:string>>>").alias("out"))
    placed = F.when(F.size(found) > 0, F.aggregate(runs, first, moved, lambda acc: F.flatten(acc["out"]))).otherwise(none)
    good = F.filter(placed, lambda x: kind.check(x["m"]))

    def scored(x):
        around = F.lower(F.substring(text, F.greatest(x["start"] + 1 - NEAR, F.lit(1)), F.length(x["m"]) + 2 * NEAR))
        score = F.least(F.lit(1.0), F.lit(kind.score) + F.when(around.rlike(kind.context), kind.bonus).otherwise(0.0))
        return F.struct(x["start"].alias("start"), F.lit(k).alias("k"), (x["start"] + F.length(x["m"])).alias("end"), F.lit(kind.name).alias("kind"), score.alias("score"))

    out = F.transform(good, scored)
    if not kind.base:
        out = F.filter(out, lambda s: s["score"] >= THRESHOLD)
    needs = kind.needs or re.compile("[0-9]{2}|[0-9][ -][0-9]")
    sign = F.contains(text, F.lit(needs)) if isinstance(needs, str) else text.rlike(needs.pattern)
    return F.coalesce(F.when(sign, out), F.array().cast("array<struct<start:int,k:int,end:int,kind:string,score:double>>"))


def find(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, spans): spans in order of start and kind, each with its score."""
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("t"))
    parts = rows.select("doc_id", *(_spans(F.col("t"), k, kind).alias(kind.name) for k, kind in enumerate(KINDS)))
    return parts.select("doc_id", F.array_sort(F.concat(*(F.col(k.name) for k in KINDS))).alias("spans"))


def joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def mask(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, text) with every span replaced by its kind in angle brackets; of overlapping spans the first counts."""
    rows = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("t"))
    parts = rows.select("doc_id", "t", *(_spans(F.col("t"), k, kind).alias(kind.name) for k, kind in enumerate(KINDS)))
    spans = F.array_sort(F.concat(*(F.col(k.name) for k in KINDS)))
    step = lambda acc, s: F.when(s["start"] < acc["at"], acc).otherwise(F.struct(s["end"].alias("at"), F.concat(acc["out"], F.substring(F.col("t"), acc["at"] + 1, s["start"] - acc["at"]), F.lit("<"), s["kind"], F.lit(">")).alias("out")))
    return parts.select("doc_id", F.aggregate(spans, F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), step, lambda acc: F.concat(acc["out"], F.substring(F.col("t"), acc["at"] + 1, F.length(F.col("t"))))).alias("text"))
