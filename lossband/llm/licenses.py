"""License scan by canonical digest: texts that are one license, whatever its spelling, case and copyright lines.

Both sides are brought to one form by DataFrame functions alone: copyright lines go, case, punctuation and
white space are levelled, equivalent spellings become one. An entire text then matches a license if the
digests are equal, in one hash join; lines that speak of a license take part as texts of their own, so that
notices are found too.

Results on odd input: null or empty text, and text that the form leaves nothing of, match nothing; a
license without text is left out; licenses of the same form are reported together, in order of name;
repeated rows match alike; an empty table gives no rows; further columns are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Spellings that count as one, as patterns of whole words and what stands for them; each is one pass.
SPELLINGS = (
    (r"\blicence(s|d|e|es)?\b", "license$1"), (r"\b(off|def)ence(s)?\b", "$1ense$2"), (r"\bpractise(s|d)?\b", "practice$1"), (r"\b(acknowledg|judg)ment(s)?\b", "$1ement$2"), (r"\b(catalog|analog)ue(s)?\b", "$1$2"),
    (r"\b(cent|calib)re(s)?\b", "$1er$2"), (r"\b(analy|author|capital|categor|emphas|initial|maxim|minim|optim|organ|real|recogn|util)is(e|ed|es|ing|ation|ations)\b", "$1iz$2"), (r"\b(cancel|label|model|signal)l(ed|ing)\b", "$1$2"),
    (r"\bfavour(s|ed|ite|able)?\b", "favor$1"), (r"\blabour(s|ed)?\b", "labor$1"), (r"\bfulfil(ment|s)?\b", "fulfill$1"), (r"\bprogramme(s)?\b", "program$1"), (r"\bartefact(s)?\b", "artifact$1"), (r"\bwhilst\b", "while"), (r"\bwilful(ly)?\b", "willful$1"),
    (r"\bcopyright owner(s)?\b", "copyright holder$1"), (r"\bsub licens(e|es|ed|able|ing)\b", "sublicens$1"), (r"\bnon commercial(ly)?\b", "noncommercial$1"), (r"\bper cent\b", "percent"), (r"\bhttps\b", "http"),
)
ANY = "|".join(a for a, _ in SPELLINGS)


def with_digest(rows: DataFrame, column: str, out: str) -> DataFrame:
    """``rows`` with the canonical digest of ``column``: null for null and for text of which nothing is left.

    The levelled text is a column of its own, so that no pass over it is planned twice; the spellings' passes
    run only where one of them occurs.
    """
    x = F.lower(F.col(column).cast("string"))
    x = F.regexp_replace(x, r"(?m)^[^\p{L}\p{N}\n]*(?:copyright|\(c\)|©|&copy;)(?: \(c\)| ©|)[^\n]*(?:[0-9]{4}|reserved)[^\n]*(?:\n|$)", "\n")
    x = F.regexp_replace(x, r"(?m)^[^\p{L}\p{N}\n]*all rights reserved\.?[^\S\n]*$", "")
    x = F.trim(F.regexp_replace(x, r"[^\p{L}\p{N}]+", " "))
    level, one = f"{out}_level", f"{out}_one"
    spelled = F.col(level)
    for a, b in SPELLINGS:
        spelled = F.regexp_replace(spelled, a, b)
    rows = rows.withColumn(level, x).withColumn(one, F.when(F.col(level).rlike(ANY), spelled).otherwise(F.col(level)))
    return rows.withColumn(out, F.when(F.length(one) > 0, F.sha2(one, 256))).drop(level, one)


#: A line is looked up by itself if it holds one of these.
SIGNS = r"(?i)licen[cs]e|copyright|permission|spdx"


def known_forms(licenses: DataFrame, name: str = "name", body: str = "text") -> DataFrame:
    """(form, names): one row for each canonical digest."""
    known = with_digest(licenses.select(F.col(name).cast("string").alias("name"), F.col(body).alias("body")), "body", "form")
    return known.where("form is not null and name is not null").groupBy("form").agg(F.array_sort(F.collect_set("name")).alias("names"))


def scan(docs: DataFrame, licenses: DataFrame, doc_id: str = "doc_id", text: str = "text", name: str = "name", body: str = "text") -> DataFrame:
    """(doc_id, form_sha256, licenses, notices) of every row.

    ``licenses`` names what the entire text is, ``notices`` what single lines of it are; both are arrays in
    order of name.
    """
    whole = F.col(text).cast("string")
    lines = F.filter(F.split(F.when(whole.rlike(SIGNS), whole), "\n"), lambda x: x.rlike(SIGNS))
    units = F.concat(F.array(F.struct(F.lit(True).alias("entire"), whole.alias("t"))), F.coalesce(F.transform(lines, lambda x: F.struct(F.lit(False).alias("entire"), x.alias("t"))), F.array().cast("array<struct<entire:boolean,t:string>>")))
    # Numbered before the lines are taken apart, so that all units of a row carry its number.
    rows = docs.select(F.col(doc_id).alias("doc_id"), units.alias("units")).withColumn("row", F.monotonically_increasing_id())
    rows = rows.select("doc_id", "row", F.explode("units").alias("u"))
    rows = with_digest(rows.select("doc_id", "row", F.col("u.entire").alias("entire"), F.col("u.t").alias("t")), "t", "form").drop("t")
    found = rows.join(known_forms(licenses, name, body), "form", "left")
    names = lambda entire: F.array_sort(F.array_distinct(F.flatten(F.collect_list(F.when(F.col("entire") == entire, F.col("names"))))))
    return found.groupBy("row").agg(F.any_value("doc_id").alias("doc_id"), F.max(F.when(F.col("entire"), F.col("form"))).alias("form_sha256"), names(True).alias("licenses"), names(False).alias("notices")).drop("row")
