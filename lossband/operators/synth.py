"""Series of three known kinds in four sources, without random state, so that no partitioning changes a value."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

KINDS = ("repetitive", "learnable", "abrupt")


def _uniform(*keys) -> Column:
    return (F.pmod(F.xxhash64(*keys), F.lit(1 << 30)) + 0.5) / float(1 << 30)


def noise(*keys) -> Column:
    """Standard normal by two uniforms."""
    a, b = _uniform(*keys, F.lit(1)), _uniform(*keys, F.lit(2))
    return F.sqrt(-2 * F.log(a)) * F.cos(2 * math.pi * b)


def planted(spark: SparkSession, series: int = 48, length: int = 512, sources: int = 4, seed: int = 0, season: int = 16) -> DataFrame:
    """(source, series_id, t, y, kind): pure cycles; trends with drifting cycles and noise; flat series that jump at an unannounced slot.

    Sources differ in scale by factors of ten; about one slot in twenty is missing.
    """
    rows = spark.range(series * sources * length).select(F.floor(F.col("id") / length).cast("long").alias("s"), (F.col("id") % length).alias("t"))
    rows = rows.withColumns({"k": F.pmod(F.col("s"), F.lit(3)), "src": F.pmod(F.floor(F.col("s") / 3), F.lit(sources))})
    s, t = F.col("s"), F.col("t")
    e = noise(F.lit(seed), s, t)
    angle = 2 * math.pi * t / season + 6.28 * _uniform(F.lit(seed), s)
    calm = 10 + 3 * F.sin(angle) + 0.01 * e
    lively = 10 + 0.01 * t + (2 + F.sin(2 * math.pi * t / 200)) * F.sin(angle) + 0.3 * e
    jump = F.floor(length * (0.3 + 0.6 * _uniform(F.lit(seed), s, F.lit(7))))
    sudden = 10 + 0.05 * e + F.when(t >= jump, 8 * noise(F.lit(seed), s, F.lit(9), F.floor(t / 5))).otherwise(0.0)
    y = F.when(F.col("k") == 0, calm).when(F.col("k") == 1, lively).otherwise(sudden) * F.pow(F.lit(10.0), F.col("src"))
    gone = _uniform(F.lit(seed), s, t, F.lit(3)) < 0.05
    kind = F.element_at(F.array(*map(F.lit, KINDS)), (F.col("k") + 1).cast("int"))
    return rows.select(F.concat(F.lit("planted"), "src").alias("source"), F.col("s").cast("string").alias("series_id"), "t", F.when(~gone, F.round(y * 1000).cast("long")).alias("y"), kind.alias("kind"))


def sinusoids(spark: SparkSession, series: int, length: int, waves: int = 5, seed: int = 0) -> DataFrame:
    """Smooth series: sums of seeded sinusoids, near to draws of a Gaussian process."""
    rows = spark.range(series * length).select(F.floor(F.col("id") / length).cast("long").alias("s"), (F.col("id") % length).alias("t"))
    y = sum((noise(F.lit(seed), "s", F.lit(k)) * F.sin(2 * math.pi * F.col("t") * _uniform(F.lit(seed), "s", F.lit(100 + k)) / 12 + 6.28 * _uniform(F.lit(seed), "s", F.lit(200 + k))) for k in range(waves)), F.lit(0.0))
    return rows.select(F.lit("sinusoids").alias("source"), F.col("s").cast("string").alias("series_id"), "t", F.round(y * 1000).cast("long").alias("y"))


def skewed(spark: SparkSession, big: int = 9_000, small: int = 200) -> DataFrame:
    """A score table of one source with nine tenths of the windows and many sources of one to three."""
    one = spark.range(big).select(F.lit("big").alias("source"), (F.col("id") % 7).cast("string").alias("series_id"), F.col("id").alias("origin"))
    many = spark.range(small * 3).where("id % 3 <= pmod(xxhash64(floor(id / 3)), 3)").select(F.concat(F.lit("small"), F.floor(F.col("id") / 3)).alias("source"), F.lit("0").alias("series_id"), (F.col("id") % 3).alias("origin"))
    return one.unionByName(many).withColumn("rfl", F.pmod(F.xxhash64("source", "origin"), F.lit(997)).cast("double")).withColumns({"m": F.lit(1).cast("long"), "status": F.lit("ok")})
