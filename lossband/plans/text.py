"""The same selection for documents: mean surprise under a frozen word model, middle of every source."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tokens(text: str) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), "[^a-z]+"), lambda w: w != "")


def unigram(reference: DataFrame, text: str = "text") -> DataFrame:
    """(word, bits): minus log2 of each word's share in the reference texts, with one count added."""
    counts = reference.select(F.explode(tokens(text)).alias("word")).groupBy("word").agg(F.count("*").alias("n"))
    total = counts.agg(F.sum("n").alias("all"), F.count("*").alias("words"))
    return counts.crossJoin(F.broadcast(total)).select("word", (-F.log2((F.col("n") + 1) / (F.col("all") + F.col("words") + 1))).alias("bits"), (F.log2(F.col("all") + F.col("words") + 1)).alias("unknown"))  # total is one row


def score(docs: DataFrame, model: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """A score table of documents: rfl is the mean bits of the document's words; documents without words cannot be scored.

    Words are counted within a document before they meet the model, so a common word is one row a document.
    """
    words = docs.select(F.col(doc_id).alias("doc_id"), F.col(source).alias("source"), F.explode_outer(tokens(text)).alias("word")).groupBy("doc_id", "source", "word").agg(F.count("word").alias("n"))
    unknown = model.agg(F.coalesce(F.max("unknown"), F.lit(0.0)).alias("miss"))
    rows = words.join(model.select("word", "bits"), "word", "left").crossJoin(F.broadcast(unknown))  # one row
    out = rows.groupBy("doc_id", "source").agg(F.sum("n").alias("m"), F.sum(F.col("n") * F.coalesce("bits", "miss")).alias("bits"))
    return out.select("source", F.col("doc_id").cast("string").alias("series_id"), F.lit(0).cast("long").alias("origin"), "m", F.when(F.col("m") > 0, F.col("bits") / F.col("m")).alias("rfl"), F.when(F.col("m") > 0, "ok").otherwise("unscorable").alias("status"))
