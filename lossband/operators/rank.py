"""Exact ranks of scores within a source or over all of them, three ways.

``local`` sorts each source in one task. ``distributed`` range-partitions once, numbers the rows of every
partition and adds what lies before it; a source of any size is spread over tasks. ``cutoffs`` finds only
the scores at wanted ranks: a band around each from approximate quantiles, an exact count below it, and a
sort of the band alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import keep

KEY = ["series_id", "origin"]


def scorable(scores: DataFrame) -> DataFrame:
    return scores.where("status = 'ok'") if "status" in scores.columns else scores.where("rfl is not null")


def _by(by) -> list[str]:
    return [by] if isinstance(by, str) else list(by or [])


def tie_key(by: list[str]) -> list[str]:
    """Order of equal scores: by name. Over all sources, the source comes first."""
    return KEY if "source" in by else ["source", *KEY]


def local(scores: DataFrame, by="source") -> DataFrame:
    """Adds n, rank_key (ties by name) and rank_max (rows whose score is not above)."""
    by = _by(by)
    if not by:
        raise ValueError("one task would sort everything; rank all sources with 'distributed'")
    rows = scorable(scores)
    w = Window.partitionBy(*by)
    # The frame of the default order takes in all rows of equal score, so its count is the rank of the last of them.
    return rows.select("*", F.count("*").over(w).alias("n"), F.row_number().over(w.orderBy("rfl", *tie_key(by))).alias("rank_key"), F.count("*").over(w.orderBy("rfl")).alias("rank_max")).withColumn("rank_key", F.col("rank_key").cast("long"))


def distributed(scores: DataFrame, by="source", parts: int | None = None, ties: bool = True) -> DataFrame:
    """Same columns as ``local`` by one range shuffle.

    With ``ties`` rows of equal score share a partition and rank_max is filled; without, ranges also go by
    name, so that a large group of equal scores is cut, and rank_max is left out. The numbered rows are
    written before they are counted: ranges come from a sample and must not be drawn twice.
    """
    by = _by(by)
    rows = scorable(scores)
    spark = scores.sparkSession
    parts = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    order = [*by, "rfl", *tie_key(by)]
    dealt = rows.repartitionByRange(parts, *(by + ["rfl"] if ties else order)).sortWithinPartitions(*order)
    numbered = keep(dealt.withColumn("at", F.monotonically_increasing_id()), "ranked")
    numbered = numbered.withColumn("part", F.shiftright("at", 33))
    # One row for each partition and source in it: at most partitions + sources rows.
    heads = numbered.groupBy("part", *by).agg(F.min("at").alias("first"), F.count("*").alias("rows"))
    heads = heads.withColumn("all", F.lit(0)) if not by else heads
    w = Window.partitionBy(*(by or ["all"]))
    heads = heads.withColumns({"before": F.coalesce(F.sum("rows").over(w.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)), "n": F.sum("rows").over(w)})
    out = numbered.join(F.broadcast(heads.select("part", *by, "first", "before", "n")), ["part", *by]).withColumn("rank_key", F.col("at") - F.col("first") + F.col("before") + 1)
    if ties:
        # Equal scores lie in one partition, side by side.
        out = out.withColumn("rank_max", F.max("rank_key").over(Window.partitionBy("part", *by, "rfl")))
    return out.drop("part", "at", "first", "before").select(*rows.columns, "n", "rank_key", *(["rank_max"] if ties else []))


def ranked(scores: DataFrame, by="source", method: str = "distributed", ties: bool = False) -> DataFrame:
    """n and rank_key of every row; rank_max too with ``ties``, which keeps rows of equal score in one partition."""
    return local(scores, by) if method == "local" and _by(by) else distributed(scores, by, ties=ties)


def cutoffs(scores: DataFrame, wanted: Column, by="source", slack: float = 0.02, accuracy: int = 1_000) -> DataFrame:
    """(by, n, rank, rfl, series_id, origin): the row at each rank of ``wanted``, an array expression of n.

    One pass sketches quantiles, one counts below the bands and takes the bands' rows, which alone are
    sorted. A rank that its band misses is looked for again with a wider one, so the result is exact.
    """
    by = _by(by)
    rows = scorable(scores)
    group = by or ["all"]
    rows = rows if by else rows.withColumn("all", F.lit(0))
    n = rows.groupBy(*group).agg(F.count("*").alias("n"), F.min("rfl").alias("least"), F.max("rfl").alias("most"))
    goals = n.select("*", F.explode(wanted).alias("rank")).where(F.col("rank").between(1, F.col("n")))
    goals = keep(goals.select(*group, "n", F.col("rank").cast("long").alias("rank"), "least", "most").distinct(), "goals")
    found = None
    while True:
        # A grid of quantiles by group; the band of a rank lies between the grid points around it.
        steps = [min(1.0, i * slack) for i in range(int(1 / slack) + 2)]
        grid = rows.groupBy(*group).agg(F.percentile_approx("rfl", steps, accuracy).alias("q"))
        last = len(steps) - 1
        share = F.col("rank") / F.col("n")
        low = F.floor(share / slack - 2).cast("int")
        high = F.ceil(share / slack + 2).cast("int")
        bands = goals.join(grid, group).select(*group, "n", "rank", F.when(low < 0, F.col("least")).otherwise(F.col("q")[F.greatest(low, F.lit(0))]).alias("lo"), F.when(high >= last, F.col("most")).otherwise(F.col("q")[F.least(high, F.lit(last))]).alias("hi"))
        bands = keep(bands, "bands")
        met = rows.join(F.broadcast(bands), group)  # groups x wanted ranks
        below = met.where("rfl < lo").groupBy(*group, "rank").agg(F.count("*").alias("below"))
        inside = met.where("rfl between lo and hi").select(*group, F.col("n").alias("total"), "rank", "rfl", *(["source"] if "source" not in group else []), *KEY)
        # However many rows a band has, they are dealt over all tasks.
        nth = distributed(inside, [*group, "rank"], ties=False).drop("n")
        hit = nth.join(F.broadcast(below), [*group, "rank"], "left").where(F.col("rank_key") + F.coalesce("below", F.lit(0)) == F.col("rank"))
        hit = keep(hit.withColumnRenamed("total", "n").select(*group, "n", "rank", "rfl", *(["source"] if "source" not in group else []), *KEY), "cut")
        found = hit if found is None else found.unionByName(hit)
        goals = keep(goals.join(hit.select(*group, "rank"), [*group, "rank"], "left_anti"), "goals")
        if goals.isEmpty():
            return found if by else found.drop("all")
        slack, accuracy = min(0.5, slack * 4), accuracy * 4
