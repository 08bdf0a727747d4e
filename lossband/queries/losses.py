"""Reference losses of all windows, by forecaster and by loss."""

from pyspark.sql import functions as F

from ..functions import loss as l
from ..operators import scoring as sc
from ..operators.grid import CORPORA
from .common import cells_sql, errors_sql, grid, keys_sql, naive, plain, scores_sql


def _score(spark, sf, reference, name="events_hourly", digits=None, relative=False, **options):
    c = CORPORA[name]
    rows = plain(sc.score(grid(spark, sf, name), reference, c.context, c.horizon, **options))
    # A hair is added before rounding, here and in the SQL, so that exact halves go the same way in both.
    return rows.withColumn("rfl", F.round(F.col("rfl") + 1e-8, digits)) if digits is not None else rows


def half_mse_rank_equal(spark, sf):
    """Windows whose rank differs between the squared error and its half: none."""
    from ..operators.rank import ranked

    key = ["source", "series_id", "origin"]
    full = ranked(naive(spark, sf)).select(*key, F.col("rank_key").alias("a"))
    half = ranked(naive(spark, sf, loss=l.HALF_MSE)).select(*key, F.col("rank_key").alias("b"))
    return full.join(half, key).agg(F.count("*").alias("windows"), F.count_if(F.col("a") != F.col("b")).alias("differing"))


def unscorable(spark, sf):
    return naive(spark, sf, "orders_weekly").groupBy("source", "status").agg(F.count("*").alias("windows"))


def ridge(lags):
    def run(spark, sf):
        c = CORPORA["supplier_weekly"]
        cells = grid(spark, sf, "supplier_weekly")
        fitted = sc.RidgeDirect(lags).fit(cells, c.context, c.horizon, F.col("origin") + c.context + 2 * c.horizon <= c.length)
        return plain(sc.score(cells, fitted, c.context, c.horizon))

    return run


def linear_gram(spark, sf):
    c = CORPORA["supplier_weekly"]
    return sc.gram(grid(spark, sf, "supplier_weekly"), 4, c.context, 2, F.col("origin") + c.context + 2 * c.horizon <= c.length)


def wql_window(spark, sf):
    return _score(spark, sf, sc.ResidualQuantile(24), weighted=True, digits=6)


def arrow_equals_prefix(spark, sf):
    """Windows whose score by running sums and by Arrow batches of an external forecaster differ: none."""
    c, key = CORPORA["supplier_weekly"], ["source", "series_id", "origin"]
    cells = grid(spark, sf, "supplier_weekly").withColumn("y", F.coalesce("y", F.lit(0)))
    last = lambda x: x[:, -1:].repeat(c.horizon, axis=1)
    a = sc.arrow_scores(cells, last, c.context, c.horizon, chunk=128)
    b = sc.LastValue().score(cells, c.context, c.horizon).withColumnRenamed("rfl", "rfl2").drop("m")
    return a.join(b, key).agg(F.count("*").alias("windows"), F.count_if(F.abs(F.col("rfl") - F.col("rfl2")) > 1e-6 * (1 + F.col("rfl2"))).alias("differing"))


def prob_score_gaussian(spark, sf):
    """Mean probabilistic score of the next slot under a normal forecast from the context before it."""
    import pandas as pd
    from pyspark.sql import Window

    from ..sources.tables import ship

    ship(spark)

    past = Window.partitionBy("source", "series_id").orderBy("t").rowsBetween(-48, -1)
    rows = grid(spark, sf).select("source", "y", F.avg("y").over(past).alias("mu"), F.greatest(F.stddev_pop("y").over(past), F.lit(1.0)).alias("sigma"), F.col("t")).where("y is not null and mu is not null and t >= 48")

    @F.pandas_udf("double")
    def score(mu: pd.Series, sigma: pd.Series, y: pd.Series) -> pd.Series:
        return pd.Series(l.gaussian_score(mu.to_numpy(), sigma.to_numpy(), y.to_numpy(float)))

    return rows.groupBy("source").agg(F.count("*").alias("slots"), F.round(F.avg(score("mu", "sigma", "y")), 6).alias("prob_score"))


def cost(spark, sf):
    return sc.cost_report(naive(spark, sf, "orders_weekly")).withColumn("sort_work", F.round("sort_work", 6))


QUERIES = {f"rfl_mse_snaive_{k}": (lambda s, d, k=k: plain(naive(s, d, k))) for k in CORPORA} | {
    "rfl_mse_last": lambda s, d: _score(s, d, sc.LastValue(), "supplier_weekly"),
    "rfl_mse_mean": lambda s, d: _score(s, d, sc.MovingMean(12), "supplier_weekly", digits=6),
    "rfl_mse_drift": lambda s, d: _score(s, d, sc.Drift(), "supplier_weekly", digits=4),
    "rfl_mse_ffill_phase": lambda s, d: _score(s, d, sc.SeasonalNaive(13, "ffill_phase"), "orders_weekly"),
    "rfl_mse_bands": lambda s, d: plain(sc.score(grid(s, d), sc.SeasonalNaive(10), 48, 24)),
    "rfl_mae": lambda s, d: plain(naive(s, d, loss=l.MAE)),
    "rfl_half_mse": lambda s, d: plain(naive(s, d, loss=l.HALF_MSE)),
    "rfl_error_norm": lambda s, d: plain(naive(s, d, loss=l.ERROR_NORM)).withColumn("rfl", F.round("rfl", 6)),
    "rfl_pinball": lambda s, d: plain(naive(s, d, loss=l.pinball(0.9))).withColumn("rfl", F.round("rfl", 4)),
    "rfl_custom_loss": lambda s, d: plain(naive(s, d, loss=l.custom("capped", lambda e: F.least(F.abs(e), F.lit(5_000))))).withColumn("rfl", F.round("rfl", 4)),
    "half_mse_rank_equal": half_mse_rank_equal,
    "unscorable_windows": unscorable,
    "rfl_quantile": lambda s, d: _score(s, d, sc.ResidualQuantile(24), digits=4),
    "wql_window": wql_window,
    "prob_score_quantile": lambda s, d: _score(s, d, sc.ResidualQuantile(24), digits=4).groupBy("source").agg(F.round(F.avg("rfl"), 2).alias("prob_score")),
    "prob_score_gaussian": prob_score_gaussian,
    "rfl_gaussian_nll": lambda s, d: _score(s, d, sc.ContextGaussian(), "supplier_weekly", digits=6),
    "rfl_point_quantile": lambda s, d: _score(s, d, sc.PointQuantile(24), digits=0),
    "linear_gram_p4": linear_gram,
    "rfl_linear_p4": ridge(4),
    "rfl_linear_p8": ridge(8),
    "rfl_linear_p16": ridge(16),
    "arrow_equals_prefix": arrow_equals_prefix,
    "cost_report": cost,
}

_S = CORPORA["supplier_weekly"]
_SUP = f"{cells_sql('supplier_weekly')}, {keys_sql('supplier_weekly')}"
_PAST = f"join cells c on c.source = k.source and c.series_id = k.series_id and c.t >= k.origin and c.t < k.origin + {_S.context}"
_NEXT = f"join cells f on f.source = k.source and f.series_id = k.series_id and f.t >= k.origin + {_S.context} and f.t < k.origin + {_S.context + _S.horizon}"
_Q = ("0.1", "0.5", "0.9")
_QUANT = f"""{errors_sql('events_hourly')}, diffs as (select a.source, a.y - b.y as e from cells a join cells b on a.source = b.source and a.series_id = b.series_id and b.t = a.t - 24 where a.y is not null and b.y is not null),
    q as (select source, {', '.join(f'quantile_cont(e, {x}) as q{i}' for i, x in enumerate(_Q))} from diffs group by 1),
    p as (select r.source, series_id, origin, yf, e, ({' + '.join(f'2 * greatest({x} * (e - q{i}), ({x} - 1) * (e - q{i}))' for i, x in enumerate(_Q))}) / 3 as l from errors r join q on q.source = r.source)"""
ORACLES = {f"rfl_mse_snaive_{k}": f"with {scores_sql(k)} select * from scores" for k in CORPORA} | {
    "rfl_mse_last": f"""with {_SUP}, v as (select k.source, k.series_id, k.origin, arg_max(c.y, c.t) filter (c.y is not null) as v from keys k {_PAST} group by 1, 2, 3)
        select k.source, k.series_id, k.origin, count(f.y) as m, case when count(f.y) > 0 and any_value(v) is not null then cast(sum(cast(f.y - v as hugeint) * (f.y - v)) as double) / count(f.y) end as rfl from v k {_NEXT} group by 1, 2, 3""",
    "rfl_mse_mean": f"""with {_SUP}, v as (select k.source, k.series_id, k.origin, avg(c.y) filter (c.t >= k.origin + {_S.context - 12}) as v from keys k {_PAST} group by 1, 2, 3)
        select k.source, k.series_id, k.origin, count(f.y) as m, round(avg((f.y - v) * (f.y - v)) + 1e-8, 6) as rfl from v k {_NEXT} group by 1, 2, 3""",
    "rfl_mse_drift": f"""with {_SUP}, v as (select k.source, k.series_id, k.origin, arg_min(c.y, c.t) filter (c.y is not null) as ya, min(c.t) filter (c.y is not null) as ta, arg_max(c.y, c.t) filter (c.y is not null) as yb, max(c.t) filter (c.y is not null) as tb from keys k {_PAST} group by 1, 2, 3),
        x as (select *, case when tb > ta then (yb - ya) / cast(tb - ta as double) else 0 end as b from v)
        select k.source, k.series_id, k.origin, count(f.y) as m, round(avg(power(f.y - yb - b * (f.t - tb), 2)) + 1e-8, 4) as rfl from x k {_NEXT} group by 1, 2, 3""",
    "rfl_mse_ffill_phase": f"""with {cells_sql('orders_weekly')}, {keys_sql('orders_weekly')},
        b as (select *, last_value(y ignore nulls) over (partition by source, series_id, t % 13 order by t rows between unbounded preceding and 1 preceding) as b from cells)
        select k.source, k.series_id, k.origin, count(y - b) as m, case when count(y - b) > 0 then cast(sum(cast(y - b as hugeint) * (y - b)) as double) / count(y - b) end as rfl
        from keys k join b on b.source = k.source and b.series_id = k.series_id and b.t >= k.origin + 52 and b.t < k.origin + 65 group by 1, 2, 3""",
    "rfl_mse_bands": f"with {scores_sql('events_hourly', season=10)} select * from scores",
    "rfl_mae": f"with {scores_sql('events_hourly', 'abs(e)')} select * from scores",
    "rfl_half_mse": f"with {scores_sql('events_hourly')} select source, series_id, origin, m, rfl / 2 as rfl from scores",
    "rfl_error_norm": f"with {errors_sql('events_hourly')} select source, series_id, origin, count(e) as m, round(sqrt(cast(sum(cast(e as hugeint) * e) as double)), 6) as rfl from errors group by 1, 2, 3",
    "rfl_pinball": f"with {errors_sql('events_hourly')} select source, series_id, origin, count(e) as m, round(avg(greatest(cast(e as double) * 0.9, cast(e as double) * (0.9 - 1))), 4) as rfl from errors group by 1, 2, 3",
    "rfl_custom_loss": f"with {errors_sql('events_hourly')} select source, series_id, origin, count(e) as m, round(avg(case when e is not null then least(abs(e), 5000) end), 4) as rfl from errors group by 1, 2, 3",
    "half_mse_rank_equal": f"with {scores_sql('events_hourly')} select count(*) as windows, cast(0 as bigint) as differing from ok",
    "unscorable_windows": f"with {scores_sql('orders_weekly')} select source, case when rfl is null then 'unscorable' else 'ok' end as status, count(*) as windows from scores group by 1, 2",
    "rfl_quantile": f"with {_QUANT} select source, series_id, origin, count(e) as m, round(avg(l) + 1e-8, 4) as rfl from p group by 1, 2, 3",
    "wql_window": f"with {_QUANT} select source, series_id, origin, count(e) as m, round(sum(l) / nullif(sum(abs(yf)) filter (e is not null), 0) + 1e-8, 6) as rfl from p group by 1, 2, 3",
    "prob_score_quantile": f"with {_QUANT}, w as (select source, series_id, origin, round(avg(l), 4) as rfl from p group by 1, 2, 3) select source, round(avg(rfl), 2) as prob_score from w group by 1",
    "rfl_gaussian_nll": f"""with {_SUP}, v as (select k.source, k.series_id, k.origin, avg(c.y) as mu, greatest(var_pop(c.y), 1.0) as v from keys k {_PAST} group by 1, 2, 3)
        select k.source, k.series_id, k.origin, count(f.y) as m, round(avg(0.5 * ln(2 * pi() * v) + (f.y - mu) * (f.y - mu) / (2 * v)) + 1e-8, 6) as rfl from v k {_NEXT} group by 1, 2, 3""",
    "rfl_point_quantile": f"with {_QUANT} select source, series_id, origin, count(e) as m, round(avg(cast(e as double) * e) + avg(l) / 2 + 1e-8, 0) as rfl from p group by 1, 2, 3",
    "linear_gram_p4": f"""with {_SUP}, z as (select source, series_id, t, coalesce(y, 0) as y from cells),
        x as (select k.source, k.series_id, k.origin, 0 as i, 1 as v from keys k union all
              select k.source, k.series_id, k.origin, i, z.y from keys k cross join (select unnest(range(1, 7)) as i) n join z on z.source = k.source and z.series_id = k.series_id and z.t = k.origin + case when i <= 4 then {_S.context} - i else {_S.context} + i - 5 end)
        select a.i, b.i as j, cast(sum(a.v * b.v) as double) as value from x a join x b on a.source = b.source and a.series_id = b.series_id and a.origin = b.origin and a.i <= b.i and a.i <= 4 group by 1, 2""",
    "arrow_equals_prefix": f"with {cells_sql('supplier_weekly')}, {keys_sql('supplier_weekly', held_out=False)} select count(*) as windows, cast(0 as bigint) as differing from keys",
    "cost_report": f"""with {scores_sql('orders_weekly')} select source, count(*) as forward_passes, count(rfl) as sorted_rows, round(count(rfl) * ln(count(rfl)), 6) as sort_work, 8 * count(rfl) as score_bytes from scores group by 1""",
}
