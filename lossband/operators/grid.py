"""Series on a regular grid of slots, with missing values, from raw rows and from the given tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import load


@dataclass(frozen=True)
class Corpus:
    """A named collection of series of ``length`` slots, with the context, horizon and season it is used at."""

    name: str
    length: int
    context: int
    horizon: int
    season: int


CORPORA = {
    c.name: c
    for c in (
        Corpus("events_hourly", 720, 48, 24, 24),
        Corpus("events_user_hourly", 720, 48, 24, 24),
        Corpus("orders_weekly", 343, 52, 13, 13),
        Corpus("supplier_weekly", 357, 52, 13, 13),
        Corpus("brand_weekly", 357, 52, 13, 13),
        Corpus("embedding_axis", 64, 32, 8, 8),
    )
}


def _cells(rows: DataFrame, source: Column, series_id: Column, slot: Column, value: Column, length: int | None) -> DataFrame:
    cells = rows.select(source.cast("string").alias("source"), series_id.cast("string").alias("series_id"), slot.cast("long").alias("t"), value.cast("long").alias("y"))
    inside = F.col("t") >= 0 if length is None else F.col("t").between(0, length - 1)
    cells = cells.where(inside & F.col("source").isNotNull() & F.col("series_id").isNotNull())
    return cells.groupBy("source", "series_id", "t").agg(F.sum("y").alias("y"))


def regularize(rows: DataFrame, source: Column, series_id: Column, slot: Column, value: Column, length: int | None) -> DataFrame:
    """(source, series_id, t, y) for every series and every slot 0..length-1; y is the sum of the slot's values, null without any.

    Without a ``length`` every series runs to the last slot that any row has. Each observed slot brings forth the
    empty ones up to the next, and the first one those before it, so the work is in proportion to the slots, no
    join meets the grid, and no series is held as one row.
    """
    sums = _cells(rows, source, series_id, slot, value, length)
    end = F.lit(length).cast("long")
    if length is None:
        # One number, of all rows.
        last = rows.agg(F.max(slot.cast("long"))).first()[0]
        end = F.lit((last if last is not None else -1) + 1).cast("long")
    at = Window.partitionBy("source", "series_id").orderBy("t")
    first = F.when(F.lag("t").over(at).isNull(), F.lit(0)).otherwise(F.col("t")).cast("long")
    gaps = sums.select("source", "series_id", F.col("t").alias("own"), "y", first.alias("from"), (F.coalesce(F.lead("t").over(at), end) - 1).alias("to"))
    slots = gaps.select("source", "series_id", "own", "y", F.explode(F.sequence("from", "to")).alias("t"))
    return slots.select("source", "series_id", "t", F.when(F.col("t") == F.col("own"), F.col("y")).alias("y"))


def regularize_join(rows: DataFrame, source: Column, series_id: Column, slot: Column, value: Column, length: int) -> DataFrame:
    """Same result by a left join of all slots with the sums."""
    sums = _cells(rows, source, series_id, slot, value, length)
    slots = sums.select("source", "series_id").distinct().select("source", "series_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(length - 1).cast("long"))).alias("t"))
    return slots.join(sums, ["source", "series_id", "t"], "left")


def impute(grid: DataFrame, how: str) -> DataFrame:
    """The grid with its empty slots filled: ``ffill`` by the last observed value, ``mean`` by that of the observed values before, ``zero``."""
    before = Window.partitionBy("source", "series_id").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    fill = {"ffill": lambda: F.last("y", ignorenulls=True).over(before), "mean": lambda: F.coalesce(F.col("y").cast("double"), F.avg("y").over(before)), "zero": lambda: F.coalesce("y", F.lit(0))}
    return grid.withColumn("y", fill[how]())


def observed_mask(grid: DataFrame) -> DataFrame:
    return grid.withColumn("observed", F.col("y").isNotNull().cast("tinyint"))


def cents(value: str) -> Column:
    return F.round(F.col(value) * 100).cast("long")


def week(date: str) -> Column:
    """Weeks since Monday 1995-01-02, rounded down before it too."""
    return F.floor(F.datediff(F.col(date), F.lit("1995-01-02").cast("date")) / 7)


def hour(ts: str) -> Column:
    return F.expr(f"timestampdiff(HOUR, TIMESTAMP_NTZ'2024-01-01 00:00:00', {ts})")


def build(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The grid of a corpus by name, from the tables in ``sf_dir``."""
    t = lambda x: load(spark, sf_dir, x)
    length = CORPORA[name].length
    if name == "events_hourly":
        return regularize(t("events"), F.col("event_type"), F.col("event_type"), hour("ts"), cents("value"), length)
    if name == "events_user_hourly":
        return regularize(t("events"), F.col("event_type"), F.concat_ws("-", "event_type", F.pmod("user_id", F.lit(8))), hour("ts"), cents("value"), length)
    if name == "orders_weekly":
        # Dimension tables are small against orders; the size of each decides at run time whether it is broadcast.
        rows = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
        return regularize(rows, F.col("r_name"), F.concat_ws("-", "n_name", "c_mktsegment"), week("o_orderdate"), cents("o_totalprice"), length)
    if name == "supplier_weekly":
        rows = t("lineitem").join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey"))
        return regularize(rows, F.col("n_name"), F.col("l_suppkey"), week("l_shipdate"), F.col("l_quantity"), length)
    if name == "brand_weekly":
        rows = t("lineitem").join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
        return regularize(rows, F.col("p_type"), F.concat_ws("-", "p_brand", "p_type"), week("l_shipdate"), F.col("l_quantity"), length)
    rows = t("embeddings").select("label", "vec_id", F.posexplode("embedding").alias("pos", "v"))
    return rows.select(F.col("label").cast("string").alias("source"), F.col("vec_id").cast("string").alias("series_id"), F.col("pos").cast("long").alias("t"), F.round(F.col("v").cast("double") * 1_000_000).cast("long").alias("y"))


def user_sequence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ragged series: each user's events in order, one slot an event."""
    rows = load(spark, sf_dir, "events")
    nth = F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")) - 1
    return rows.select(F.pmod("user_id", F.lit(5)).cast("string").alias("source"), F.col("user_id").cast("string").alias("series_id"), nth.cast("long").alias("t"), cents("value").alias("y"))


def pack(grid: DataFrame, chunk: int, halo: int = 0) -> DataFrame:
    """(source, series_id, chunk, t0, values, observed): arrays of ``chunk`` slots and the ``halo`` slots that follow.

    A long series spans many rows; the halo lets every window that begins in a chunk be read from one row.
    """
    own = F.floor(F.col("t") / chunk)
    first = F.greatest(F.lit(0), F.ceil((F.col("t") - chunk - halo + 1) / chunk))
    spread = grid.select("source", "series_id", "t", "y", F.explode(F.sequence(first, own)).alias("chunk"))
    rows = spread.groupBy("source", "series_id", "chunk").agg(F.array_sort(F.collect_list(F.struct("t", "y"))).alias("cells"))
    return rows.select("source", "series_id", "chunk", F.col("cells")[0]["t"].alias("t0"), F.transform("cells", lambda c: c["y"].cast("double")).alias("values"), F.transform("cells", lambda c: c["y"].isNotNull().cast("tinyint")).alias("observed"))


def unpack(packed: DataFrame, chunk: int) -> DataFrame:
    """The grid back from its chunks, without their halos; values as doubles."""
    rows = packed.select("source", "series_id", "chunk", "t0", F.posexplode("values").alias("i", "y"))
    rows = rows.select("source", "series_id", (F.col("t0") + F.col("i")).alias("t"), "y", "chunk")
    return rows.where(F.floor(F.col("t") / chunk) == F.col("chunk")).drop("chunk")
