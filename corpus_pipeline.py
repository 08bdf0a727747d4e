"""Five operators one after another over ``documents``: quality, exact and near duplicates, mixing, byte-level BPE.

A row is known by its id and a hash of its text, so that rows that share an id are judged one by one.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lossband.llm import exact_dedup, mixing, near_dedup, quality, queries
from lossband.llm.common import Scratch, shared_dir, table, text_key

#: Similarity of near duplicates, in percent, over word shingles of five.
PERCENT, SHINGLE = 80, 5


def _names(n: int) -> list[str]:
    """Names that no column of the documents has."""
    return [f"own_{uuid.uuid4().hex[:12]}" for _ in range(n)]


def _keyed(docs: DataFrame, doc: str, key: str) -> DataFrame:
    return docs.withColumn(doc, F.col("doc_id").cast("long")).withColumn(key, text_key(F.col("text")))


def _stay(docs: DataFrame, decided: DataFrame, same: list[str], label: str) -> DataFrame:
    """Rows of ``docs`` that ``decided(doc_id, text_key, kept, *same)`` keeps; of rows with one id that agree in ``same`` one stays, rows without an id all do."""
    decided = Scratch(docs.sparkSession, label).keep(decided.where("doc_id is not null").select("doc_id", "text_key", "kept", *same), "decided")
    doc, key = _names(2)
    as_own = [F.col("doc_id").alias(doc), F.col("text_key").alias(key)]
    gone = decided.where("not kept").select(*as_own)
    texts = decided.where("kept").groupBy("doc_id", "text_key", *same).count()
    tied = texts.groupBy("doc_id", *same).agg(F.min("text_key").alias("one"), F.sum("count").alias("n")).where("n > 1").select("doc_id", "one", *same)
    rows = _keyed(docs, doc, key)
    if tied.isEmpty():
        return rows.join(gone, [doc, key], "left_anti").select(*(docs[c] for c in docs.columns))
    more = texts.join(tied, ["doc_id", *same]).select("doc_id", "text_key", "one", "count")
    gone = gone.union(more.where("text_key <> one").select(*as_own))
    twice = more.where("text_key = one and count > 1").select(*as_own)
    rows = rows.join(gone, [doc, key], "left_anti")
    whole = F.struct(*(docs[c] for c in docs.columns))
    one = rows.join(twice, [doc, key], "left_semi").groupBy(doc, key).agg(F.min_by(whole, F.to_json(whole)).alias(doc + "x")).select(f"{doc}x.*")
    return rows.join(twice, [doc, key], "left_anti").select(*(docs[c] for c in docs.columns)).union(one)


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject.

    Null text is scored as empty text; rows are judged one by one, so that repeated rows, ties and rows
    without an id are all scored; an empty table gives no rows.
    """
    return quality.with_score(docs, queries.quality_forest(spark, docs, sf_dir), least=queries.LEAST_SCORE)


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, one row of the document with the largest id.

    Null text is empty text; rows that share an id but not the text are judged apart; of rows with one id and
    equal texts the first in order of text hash and JSON form stays; rows without an id stay; an empty table
    gives no rows.
    """
    return _stay(docs, exact_dedup.exact_dedup(docs), ["digest"], "stage-exact")


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: the one with the smallest id.

    Texts without words are like nothing; different texts of the id that stays all do, as they are one
    document, and of its rows with the same shingles one stays; rows without an id stay; an empty table gives
    no rows.
    """
    return _stay(docs, near_dedup.near_dedup(docs, size=SHINGLE, percent=PERCENT), ["mark"], "stage-near")


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """As many copies of each document as the mix takes.

    Rows that agree in id, text and source are one unit, so they are taken equally often; null or empty text
    has no words and is not taken, nor is a row without an id; a null source is a source; an empty table gives
    no rows.
    """
    doc, key, of, times = _names(4)
    sized = mixing.words(docs.withColumn(key, text_key(F.col("text"))), keep=[key])
    units = sized.groupBy("doc_id", key, "sources").agg(F.sum("size").alias("size"))
    rows, _ = mixing.mix(units, keep=[key])
    taken = rows.where("copies > 0 and doc_id is not null").select(F.col("doc_id").alias(doc), key, F.element_at("sources", 1).alias(of), F.col("copies").alias(times))
    mine = _keyed(docs, doc + "x", key + "x").withColumn(of + "x", F.col("source").cast("string"))
    out = mine.join(taken, (mine[doc + "x"] == taken[doc]) & (mine[key + "x"] == taken[key]) & mine[of + "x"].eqNullSafe(taken[of]))
    return out.withColumn(doc, F.explode(F.sequence(F.lit(1), F.col(times)))).select(*(docs[c] for c in docs.columns))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and decoded bytes, one row for each row of ``docs``, repeated ones too.

    Null text is empty text and has no ids; a row without an id is encoded like others; an empty table gives
    no rows.
    """
    return queries.op4_bpe(spark, sf_dir, docs)


STAGES = [("quality", keep_good), ("exact_dedup", drop_copies), ("near_dedup", drop_near_copies), ("mixing", mix_sources), ("byte_bpe", encode)]

#: No SQL expresses the fitted trees, and so the rows that reach the later stages; tests/llm checks them by brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, each one's rows written to the shared folder and read again."""
    docs, root = table(spark, sf_dir, "documents"), f"{shared_dir(spark).rstrip('/')}/lossband-tables/pipeline-{uuid.uuid4().hex[:12]}"
    for name, stage in STAGES:
        before = len(Scratch.made)
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{root}/{name}")
        docs = spark.read.schema(out.schema).parquet(f"{root}/{name}")
        # What the stage wrote for itself has been read.
        for scratch in Scratch.made[before:]:
            scratch.clear()
        del Scratch.made[before:]
    return docs
