"""Grids, windows, holdout, overlap."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import grid as g
from ..operators import windows as w
from .common import cells_sql, grid, keys_sql

C, H = 48, 24


def _lengths(spark, sf, name="events_hourly"):
    return w.lengths(grid(spark, sf, name))


def _keys(spark, sf, held_out=True):
    return w.window_keys(_lengths(spark, sf), C, H, held_out=held_out)


def window_arrays(spark, sf):
    """Sums over the arrays of every window."""
    cells = grid(spark, sf)
    keys = w.window_keys(w.lengths(cells), C, H)
    rows = w.materialize(g.pack(cells, 256, C + H - 1), keys, C, H, 256)
    plus = lambda a: F.aggregate(F.transform(a, lambda x: F.coalesce(x, F.lit(0.0))), F.lit(0.0), lambda s, x: s + x)
    return rows.select("source", "series_id", "origin", plus("context").cast("long").alias("context_sum"), plus("future").cast("long").alias("future_sum"), F.aggregate("mask", F.lit(0), lambda s, x: s + x.cast("int")).cast("long").alias("m"))


def holdout_split(spark, sf):
    series = _lengths(spark, sf)
    train = w.window_keys(series, C, H, held_out=True).withColumn("split", F.lit("train"))
    return train.unionByName(w.validation_keys(series, C, H).withColumn("split", F.lit("validation")))


def decontaminate_series(spark, sf):
    keys = _keys(spark, sf)
    tasks = _lengths(spark, sf, "events_hourly").select("source", "series_id").unionByName(_lengths(spark, sf, "orders_weekly").select("source", "series_id"))
    return w.decontaminate_series(tasks, keys)


def decontaminate_interval(spark, sf):
    """Tasks that no training window touches."""
    series = _lengths(spark, sf)
    tasks = series.select("source", "series_id", F.explode(F.array(*(F.struct(F.lit(a).cast("long").alias("lo"), F.lit(a + 9).cast("long").alias("hi")) for a in range(0, 720, 40)))).alias("x")).select("source", "series_id", "x.*")
    return w.decontaminate_interval(tasks, w.window_keys(series, C, H, held_out=True), C + H)


def impute(how):
    def run(spark, sf):
        rows = g.impute(grid(spark, sf, "supplier_weekly"), how).select("source", "series_id", "t", "y")
        return rows.withColumn("y", F.round("y", 6)) if how == "mean" else rows

    return run


def dedupe_windows(spark, sf):
    """Windows of three slots with the same content in one source: the first by name, and how often it occurs."""
    cells = grid(spark, sf, "supplier_weekly")
    rows = w.materialize(g.pack(cells, 256, 2), w.window_keys(w.lengths(cells), 2, 1), 2, 1, 256)
    return w.dedupe(rows).where("repeats > 1")


HORIZONS, CAP = (64, 96, 128), 2_048


def horizon_windows(spark, sf):
    """Windows at the horizons of the three target families, contexts as long as the series allows up to the cap."""
    series, out = _lengths(spark, sf), None
    for h in HORIZONS:
        one = w.short_context_keys(series, h, CAP, h).groupBy("source").agg(F.lit(h).alias("horizon"), F.count("*").alias("windows"), F.min("context").alias("least"), F.max("context").alias("most"), F.sum("context").alias("slots"))
        out = one if out is None else out.unionByName(one)
    return out


def scale_context_std(spark, sf):
    past = Window.partitionBy("source", "series_id").orderBy("t").rowsBetween(0, C - 1)
    rows = grid(spark, sf).select("source", "series_id", F.col("t").alias("origin"), F.avg("y").over(past).alias("mean"), F.stddev_pop("y").over(past).alias("spread"))
    return rows.where(F.col("origin") <= 720 - C - H).select("source", "series_id", "origin", F.round("mean", 4).alias("mean"), F.round("spread", 4).alias("spread"))


def pack_roundtrip(spark, sf):
    cells = grid(spark, sf)
    return g.unpack(g.pack(cells, 100, 7), 100).select("source", "series_id", "t", F.col("y").cast("long").alias("y"))


QUERIES = {f"grid_{k}": (lambda s, d, k=k: g.build(s, d, k)) for k in g.CORPORA} | {
    "grid_join_equals_map": lambda s, d: g.regularize_join(g.load(s, d, "events"), F.col("event_type"), F.col("event_type"), g.hour("ts"), g.cents("value"), 720),
    "user_sequence": g.user_sequence,
    "window_keys_events": lambda s, d: _keys(s, d, False),
    "window_keys_stride": lambda s, d: w.window_keys(_lengths(s, d), C, H, stride=24),
    "window_arrays": window_arrays,
    "window_overlap": lambda s, d: w.overlap_report(w.window_keys(_lengths(s, d), C, H, stride=10), C, H),
    "window_short_context": lambda s, d: w.short_context_keys(_lengths(s, d), 8, C, H, 3),
    "holdout_split": holdout_split,
    "decontaminate_series": decontaminate_series,
    "decontaminate_interval": decontaminate_interval,
    **{f"impute_{how}": impute(how) for how in ("ffill", "mean", "zero")},
    "dedupe_windows": dedupe_windows,
    "window_horizons": horizon_windows,
    "grid_bounds_of_data": lambda s, d: g.regularize(g.load(s, d, "orders"), F.col("o_orderstatus"), F.col("o_orderpriority"), g.week("o_orderdate"), g.cents("o_totalprice"), None),
    "scale_context_std": scale_context_std,
    "pack_roundtrip": pack_roundtrip,
    "corpus_stats": lambda s, d: w.describe(_keys(s, d)),
    "observed_mask": lambda s, d: g.observed_mask(grid(s, d, "orders_weekly")).groupBy("source").agg(F.sum("observed").alias("observed"), F.count("*").alias("slots")),
}

_E = cells_sql("events_hourly")
_LEN = "len as (select source, series_id, max(t) + 1 as length from cells group by 1, 2)"
ORACLES = {f"grid_{k}": f"with {cells_sql(k)} select * from cells" for k in g.CORPORA} | {
    "grid_join_equals_map": f"with {_E} select * from cells",
    "user_sequence": "select cast(user_id % 5 as varchar) as source, cast(user_id as varchar) as series_id, row_number() over (partition by user_id order by ts, event_id) - 1 as t, cast(round(value * 100) as bigint) as y from events",
    "window_keys_events": f"with {_E}, {keys_sql('events_hourly', held_out=False)} select * from keys",
    "window_keys_stride": f"with {_E} select source, series_id, unnest(range(0, {720 - C - H + 1}, 24)) as origin from series",
    "window_arrays": f"""with {_E}, k as (select source, series_id, unnest(range(0, {720 - C - H + 1})) as origin from series)
        select k.source, k.series_id, k.origin, coalesce(cast(sum(y) filter (t < origin + {C}) as bigint), 0) as context_sum, coalesce(cast(sum(y) filter (t >= origin + {C}) as bigint), 0) as future_sum, count(y) filter (t >= origin + {C}) as m
        from k join cells c on c.source = k.source and c.series_id = k.series_id and t >= origin and t < origin + {C + H} group by 1, 2, 3""",
    "window_overlap": f"""with {_E}, k as (select source, series_id, unnest(range(0, {720 - C - H + 1}, 10)) as origin from series)
        select source, cast(sum(n - 1) as bigint) as pairs, cast(sum((n - 1) * {C + H - 10}) as bigint) as shared_slots, cast(sum(n * {C + H}) as bigint) as window_slots from (select source, series_id, count(*) as n from k group by 1, 2) group by 1""",
    "window_short_context": f"""with {_E}, e as (select source, series_id, unnest(range(8, {720 - H + 1}, 3)) as e from series) select source, series_id, e - least(e, {C}) as origin, least(e, {C}) as context from e""",
    "holdout_split": f"""with {_E}, {keys_sql('events_hourly')} select source, series_id, origin, 'train' as split from keys union all select source, series_id, {720 - C - H}, 'validation' from series""",
    "decontaminate_series": f"with {cells_sql('orders_weekly')} select source, series_id from series",
    "decontaminate_interval": f"""with {_E}, k as (select source, series_id, origin from (select source, series_id, unnest(range(0, {720 - C - 2 * H + 1})) as origin from series)),
        tasks as (select source, series_id, lo, lo + 9 as hi from (select source, series_id, unnest(range(0, 720, 40)) as lo from series))
        select * from tasks x where not exists (select 1 from k where k.source = x.source and k.series_id = x.series_id and k.origin <= x.hi and x.lo <= k.origin + {C + H - 1})""",
    "impute_ffill": f"with {cells_sql('supplier_weekly')} select source, series_id, t, last_value(y ignore nulls) over (partition by source, series_id order by t rows unbounded preceding) as y from cells",
    "impute_mean": f"with {cells_sql('supplier_weekly')} select source, series_id, t, round(coalesce(y, avg(y) over (partition by source, series_id order by t rows unbounded preceding)), 6) as y from cells",
    "impute_zero": f"with {cells_sql('supplier_weekly')} select source, series_id, t, coalesce(y, 0) as y from cells",
    "dedupe_windows": f"""with {cells_sql('supplier_weekly')}, x as (select source, series_id, t as origin, y as a, lead(y) over s as b, lead(y, 2) over s as c from cells window s as (partition by source, series_id order by t))
        select source, min(struct_pack(series_id := series_id, origin := origin)).series_id as series_id, min(struct_pack(series_id := series_id, origin := origin)).origin as origin, count(*) as repeats from x where origin < {g.CORPORA['supplier_weekly'].length - 2} group by source, a, b, c having count(*) > 1""",
    "window_horizons": f"with {_E} " + " union all ".join(f"select source, {h} as horizon, count(*) as windows, min(least(e, {CAP})) as least, max(least(e, {CAP})) as most, cast(sum(least(e, {CAP})) as bigint) as slots from (select source, unnest(range({h}, {720 - h + 1})) as e from series) group by 1" for h in HORIZONS),
    "grid_bounds_of_data": """with raw as (select o_orderstatus as source, o_orderpriority as series_id, cast(floor(date_diff('day', date '1995-01-02', cast(o_orderdate as date)) / 7.0) as bigint) as t, cast(round(o_totalprice * 100) as bigint) as y from orders),
        obs as (select source, series_id, t, cast(sum(y) as bigint) as y from raw where t >= 0 group by 1, 2, 3), slots as (select unnest(range(0, (select max(t) + 1 from raw))) as t)
        select s.source, s.series_id, g.t, o.y from (select distinct source, series_id from obs) s cross join slots g left join obs o on o.source = s.source and o.series_id = s.series_id and o.t = g.t""",
    "scale_context_std": f"""with {_E}, w as (select source, series_id, t as origin, avg(y) over f as mean, stddev_pop(y) over f as spread from cells window f as (partition by source, series_id order by t rows between current row and {C - 1} following))
        select source, series_id, origin, round(mean, 4) as mean, round(spread, 4) as spread from w where origin <= {720 - C - H}""",
    "pack_roundtrip": f"with {_E} select * from cells",
    "corpus_stats": f"""with {_E}, {keys_sql('events_hourly')}, b as (select source, series_id, count(*) as windows from keys group by 1, 2)
        select source, count(*) as series, cast(sum(windows) as bigint) as windows, cast(grouping(source) as integer) as whole from b group by rollup (source)""",
    "observed_mask": f"with {cells_sql('orders_weekly')} select source, count(y) as observed, count(*) as slots from cells group by 1",
}
