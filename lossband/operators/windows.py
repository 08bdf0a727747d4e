"""Candidate windows: names, arrays, overlap, the held-out last horizon, and clean evaluation sets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

KEY = ["source", "series_id", "origin"]


def lengths(grid: DataFrame) -> DataFrame:
    """(source, series_id, length) of every series; slots run from 0."""
    return grid.groupBy("source", "series_id").agg((F.max("t") + 1).alias("length"))


def window_keys(series: DataFrame, context: int, horizon: int, stride: int = 1, held_out: bool = False) -> DataFrame:
    """(source, series_id, origin) of the windows of series with ``length``; none reaches into the last horizon if ``held_out``.

    The bound is part of the sequence, so windows that do not count are never made.
    """
    last = F.col("length") - context - horizon * (2 if held_out else 1)
    return series.where(last >= 0).select("source", "series_id", F.explode(F.sequence(F.lit(0).cast("long"), last, F.lit(stride).cast("long"))).alias("origin"))


def validation_keys(series: DataFrame, context: int, horizon: int) -> DataFrame:
    """The one window of each series whose future is its last complete horizon."""
    return series.where(F.col("length") >= context + horizon).select("source", "series_id", (F.col("length") - context - horizon).alias("origin"))


def short_context_keys(series: DataFrame, least: int, most: int, horizon: int, stride: int = 1) -> DataFrame:
    """(…, origin, context): windows whose context is as long as the series allows, from ``least`` up to ``most`` slots."""
    ends = series.where(F.col("length") >= least + horizon).select("source", "series_id", F.explode(F.sequence(F.lit(least).cast("long"), F.col("length") - horizon, F.lit(stride).cast("long"))).alias("end"))
    context = F.least("end", F.lit(most))
    return ends.select("source", "series_id", (F.col("end") - context).alias("origin"), context.alias("context"))


def materialize(packed: DataFrame, keys: DataFrame, context: int, horizon: int, chunk: int) -> DataFrame:
    """Context, future and mask arrays of the named windows; ``packed`` has a halo of context + horizon - 1 slots."""
    at = keys.withColumn("chunk", F.floor(F.col("origin") / chunk))
    rows = at.join(packed, ["source", "series_id", "chunk"])
    begin = (F.col("origin") - F.col("t0") + 1).cast("int")
    return rows.select(
        *KEY,
        F.slice("values", begin, context).alias("context"),
        F.slice("values", begin + context, horizon).alias("future"),
        F.slice("observed", begin + context, horizon).alias("mask"),
    )


def overlap_report(keys: DataFrame, context: int, horizon: int) -> DataFrame:
    """By source: neighbouring windows, and the slots they share with the one before, in all."""
    gap = F.col("origin") - F.lag("origin").over(Window.partitionBy("source", "series_id").orderBy("origin"))
    shared = F.when(gap.isNotNull(), F.greatest(F.lit(0), F.lit(context + horizon) - gap))
    rows = keys.select("source", shared.alias("shared"))
    return rows.groupBy("source").agg(F.count("shared").alias("pairs"), F.sum("shared").alias("shared_slots"), (F.count("*") * (context + horizon)).alias("window_slots"))


def decontaminate_series(tasks: DataFrame, train: DataFrame) -> DataFrame:
    """Tasks whose series no training window comes from."""
    return tasks.join(train.select("source", "series_id").distinct(), ["source", "series_id"], "left_anti")


def decontaminate_interval(tasks: DataFrame, train: DataFrame, span: int) -> DataFrame:
    """Tasks (…, lo, hi) that share no slot with a training window [origin, origin + span) of their series.

    Both sides are cut into cells of ``span`` slots, so that the overlap is found by an equality join.
    """
    cells = lambda lo, hi: F.explode(F.sequence(F.floor(lo / span), F.floor(hi / span)))
    tried = tasks.withColumn("cell", cells(F.col("lo"), F.col("hi")))
    used = train.select("source", "series_id", F.col("origin").alias("from"), (F.col("origin") + span - 1).alias("to"))
    used = used.withColumn("cell", cells(F.col("from"), F.col("to")))
    hit = tried.join(used, ["source", "series_id", "cell"]).where((F.col("lo") <= F.col("to")) & (F.col("from") <= F.col("hi")))
    return tasks.join(hit.select(*tasks.columns).distinct(), tasks.columns, "left_anti")


def describe(keys: DataFrame) -> DataFrame:
    """By source, and for the whole corpus (source null): series and windows."""
    by = keys.groupBy("source", "series_id").agg(F.count("*").alias("windows"))
    return by.rollup("source").agg(F.count("*").alias("series"), F.sum("windows").alias("windows"), F.grouping("source").cast("int").alias("whole"))


def dedupe(arrays: DataFrame) -> DataFrame:
    """One window (of smallest name) for each different content of context and future, with the number of repeats."""
    return arrays.groupBy("source", "context", "future").agg(F.min(F.struct("series_id", "origin")).alias("first"), F.count("*").alias("repeats")).select("source", "first.series_id", "first.origin", "repeats")
