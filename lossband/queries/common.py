"""Corpora and score tables for the queries, and the same as SQL, written in the exploded form on purpose."""

from __future__ import annotations

from ..operators import grid as g
from ..operators.scoring import SeasonalNaive, score

_RAW = {
    "events_hourly": "select event_type as source, event_type as series_id, date_diff('hour', timestamp '2024-01-01', ts) as t, cast(round(value * 100) as bigint) as y from events",
    "events_user_hourly": "select event_type as source, event_type || '-' || (user_id % 8) as series_id, date_diff('hour', timestamp '2024-01-01', ts) as t, cast(round(value * 100) as bigint) as y from events",
    "orders_weekly": """select r_name as source, n_name || '-' || c_mktsegment as series_id, cast(floor(date_diff('day', date '1995-01-02', cast(o_orderdate as date)) / 7.0) as bigint) as t, cast(round(o_totalprice * 100) as bigint) as y
        from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey""",
    "supplier_weekly": """select n_name as source, cast(l_suppkey as varchar) as series_id, cast(floor(date_diff('day', date '1995-01-02', cast(l_shipdate as date)) / 7.0) as bigint) as t, cast(l_quantity as bigint) as y
        from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey""",
    "brand_weekly": """select p_type as source, p_brand || '-' || p_type as series_id, cast(floor(date_diff('day', date '1995-01-02', cast(l_shipdate as date)) / 7.0) as bigint) as t, cast(l_quantity as bigint) as y
        from lineitem join part on l_partkey = p_partkey""",
    "embedding_axis": """select cast(label as varchar) as source, cast(vec_id as varchar) as series_id, cast(t as bigint) as t, cast(round(cast(embedding[t + 1] as double) * 1000000) as bigint) as y
        from (select label, vec_id, embedding, unnest(range(0, 64)) as t from embeddings)""",
}


def cells_sql(name: str) -> str:
    """CTEs ending in cells(source, series_id, t, y)."""
    n = g.CORPORA[name].length
    return f"""raw as ({_RAW[name]}),
        obs as (select source, series_id, t, cast(sum(y) as bigint) as y from raw where t between 0 and {n - 1} group by 1, 2, 3),
        series as (select distinct source, series_id from obs),
        cells as (select s.source, s.series_id, g.t, o.y from series s cross join (select unnest(range(0, {n})) as t) g left join obs o on o.source = s.source and o.series_id = s.series_id and o.t = g.t)"""


def keys_sql(name: str, context=None, horizon=None, held_out=True) -> str:
    c = g.CORPORA[name]
    context, horizon = context or c.context, horizon or c.horizon
    return f"keys as (select source, series_id, unnest(range(0, {c.length - context - horizon * (2 if held_out else 1) + 1})) as origin from series)"


def errors_sql(name: str, context=None, horizon=None, season=None, held_out=True) -> str:
    """CTEs ending in errors(source, series_id, origin, h, yf, e): one row a window and slot of the future, seasonal naive."""
    c = g.CORPORA[name]
    context, horizon, season = context or c.context, horizon or c.horizon, season or c.season
    return f"""{cells_sql(name)}, {keys_sql(name, context, horizon, held_out)},
        ahead as (select source, series_id, origin, unnest(range(0, {horizon})) as h from keys),
        errors as (select k.source, k.series_id, k.origin, k.h, f.y as yf, f.y - b.y as e from ahead k
            join cells f on f.source = k.source and f.series_id = k.series_id and f.t = k.origin + {context} + k.h
            join cells b on b.source = k.source and b.series_id = k.series_id and b.t = k.origin + {context} + k.h - {season} * (k.h // {season} + 1))"""


def scores_sql(name: str, value: str = "cast(e as hugeint) * e", **kw) -> str:
    """CTEs ending in scores(source, series_id, origin, m, rfl), rfl null where nothing is observed."""
    return f"""{errors_sql(name, **kw)},
        scores as (select source, series_id, origin, count(e) as m, case when count(e) > 0 then cast(sum({value}) as double) / count(e) end as rfl from errors group by 1, 2, 3),
        ok as (select * from scores where rfl is not null)"""


def grid(spark, sf_dir, name="events_hourly"):
    return g.build(spark, sf_dir, name)


def naive(spark, sf_dir, name="events_hourly", **options):
    c = g.CORPORA[name]
    return score(grid(spark, sf_dir, name), SeasonalNaive(c.season), c.context, c.horizon, **options)


def plain(df):
    """Columns that the score oracles return."""
    return df.select("source", "series_id", "origin", "m", "rfl")
