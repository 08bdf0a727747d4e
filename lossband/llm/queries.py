"""The thin queries opN_<name> over whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

import re
from fractions import Fraction

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, byte_bpe, exact_dedup, html_text, licenses, mixing, near_dedup, pii, quality, url_filter
from .common import table
from .license_texts import TEXTS

#: Rules of op2, in the order given.
RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))
#: A document whose score is below this is rejected.
LEAST_SCORE = 0.3


def op1_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find(table(spark, sf_dir, "documents"))
    base = lambda name: F.size(F.filter("spans", lambda s: s["kind"] == name)).cast("long").alias(f"n_{name}")
    kinds = [k.name for k in pii.KINDS if k.base]
    own = F.filter("spans", lambda s: s["kind"].isin(kinds))
    return found.select("doc_id", *map(base, kinds), F.sha2(pii.joined(own), 256).alias("base_sha256"), pii.joined(F.col("spans")).alias("spans"))


def op2_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages"), RULES).select("page_id", "host", "path", "rule", "verdict")


def held_out(doc_id="doc_id"):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0


def quality_forest(spark: SparkSession, docs: DataFrame, sf_dir: str) -> quality.Forest:
    return quality.fit_on(docs, table(spark, sf_dir, "labels"), use=~held_out())


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    rows = docs.select("doc_id", F.col("text").cast("binary").alias("text"))
    scored = quality.with_score(rows, quality_forest(spark, docs, sf_dir))
    return scored.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= LEAST_SCORE).cast("int").alias("predicted"))


def op4_bpe(spark: SparkSession, sf_dir: str, docs: DataFrame | None = None) -> DataFrame:
    docs = table(spark, sf_dir, "documents") if docs is None else docs
    return byte_bpe.encode_table(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, ids=False).drop("exact")


def op5_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return ann.nearest(vectors, vectors.where("vec_id % 20 = 0"), k=20)


#: Notices of public licenses, and the licenses' names.
NOTICES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("MIT", "Released under the MIT License."),
)


def known_licenses(spark: SparkSession) -> DataFrame:
    """(name, text): the notices, full texts of public licenses, and those that the public tokenizers come with."""
    with open(public_tokenizers.path("LICENSES.txt"), encoding="utf-8") as f:
        parts = re.split(r"(?m)^[\w.*]+:\n", f.read())
    full = [(("Apache-2.0" if "Apache License" in x[:400] else "MIT" if "Permission is hereby granted" in x else "other"), x) for x in parts if len(x) > 400]
    return spark.createDataFrame([*NOTICES, *TEXTS, *full], "name string, text string")


def op6_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licenses.scan(table(spark, sf_dir, "documents"), known_licenses(spark))
    return found.select("doc_id", F.array_join("licenses", ",").alias("licenses"), F.array_join("notices", ",").alias("notices"), "form_sha256")


def op7_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def op8_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_dedup(table(spark, sf_dir, "documents")).select("doc_id", "keep_id", "group_size", "kept", F.lower(F.hex("digest")).alias("text_sha256"))


def op9_near(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_dedup(table(spark, sf_dir, "documents"), size=3, percent=85).drop("text_key", "mark")


def op10_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixed(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def mixed(docs: DataFrame) -> DataFrame:
    rows, about = mixing.mix(mixing.words(docs), share=Fraction(3, 2), weights=(5, 2, 1), most=2)
    of = F.element_at("sources", 1)
    return rows.withColumn("one", of).join(about, F.col("one").eqNullSafe(F.col("source")), "left")


QUERIES = {"op1_pii": op1_pii, "op2_urls": op2_urls, "op3_quality": op3_quality, "op4_bpe": op4_bpe, "op5_ann": op5_ann, "op6_licenses": op6_licenses, "op7_html": op7_html, "op8_exact": op8_exact, "op9_near": op9_near, "op10_mix": op10_mix}

ORACLES = {
    "op8_exact": """
        with d as (select doc_id, sha256(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')) as text_sha256 from documents),
        g as (select text_sha256, max(doc_id) as keep_id, count(*) as group_size from d group by 1)
        select doc_id, keep_id, group_size, doc_id = keep_id as kept, text_sha256 from d join g using (text_sha256)""",
}
