"""Gradients of linear forecasters, what bounds their size, and how they agree with the pool's.

Both linear models have closed forms, so no Jacobian is stored. With a feature vector x of the context,
residuals r of the observed slots and M of them, half the mean squared error has the gradient -J'r / M.
Separate weights for every slot make JJ' a multiple |x|^2 of the identity, so the squared norm equals
2 |x|^2 loss / M. One shared gain times a basis b makes JJ' = bb' of rank one: the lower bound is 0 and the
upper one |b|^2 in place of |x|^2.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.rank import ranked


def _sum(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, x: s + x)


def _dot(a: Column, b: Column) -> Column:
    return _sum(F.zip_with(a, b, lambda x, y: x * y))


def residuals(windows: DataFrame, forecast: Column) -> DataFrame:
    """Adds ``r`` (0 where nothing is observed), ``m`` and ``half_mse`` to rows with future and mask arrays."""
    r = F.transform(F.arrays_zip(F.col("future").alias("y"), forecast.alias("f"), F.col("mask").alias("k")), lambda z: F.when(z["k"] == 1, z["y"] - z["f"]).otherwise(0.0))
    rows = windows.withColumn("r", r).withColumn("m", _sum(F.transform("mask", lambda k: k.cast("double"))))
    return rows.where("m > 0").withColumn("half_mse", _dot(F.col("r"), F.col("r")) / F.col("m") / 2)


def window_gradient(rows: DataFrame, features: Column) -> DataFrame:
    """Adds ``g``, the gradient for separate weights, slot by slot, and ``norm2``, its squared length."""
    g = F.flatten(F.transform("r", lambda r: F.transform(features, lambda x: -(r * x) / F.col("m"))))
    rows = rows.withColumn("x", features).withColumn("g", g)
    return rows.withColumn("norm2", _dot(F.col("g"), F.col("g")))


def gradient_bounds(rows: DataFrame) -> DataFrame:
    """Adds lower, upper and ok: for separate weights both bounds are the squared length itself."""
    bound = 2 * _dot(F.col("x"), F.col("x")) * F.col("half_mse") / F.col("m")
    return rows.withColumns({"lower": bound, "upper": bound}).withColumn("ok", F.abs(F.col("norm2") - bound) <= 1e-9 * (1 + bound))


def rank_one_bounds(rows: DataFrame, basis: Column) -> DataFrame:
    """For one gain times ``basis``: the squared gradient and its bounds 0 and 2 |b|^2 loss / M."""
    b = F.transform(F.arrays_zip(basis.alias("b"), F.col("mask").alias("k")), lambda z: F.when(z["k"] == 1, z["b"]).otherwise(0.0))
    rows = rows.withColumn("b", b).withColumn("g1", -_dot(F.col("r"), F.col("b")) / F.col("m"))
    upper = 2 * _dot(F.col("b"), F.col("b")) * F.col("half_mse") / F.col("m")
    rows = rows.withColumns({"norm2": F.col("g1") * F.col("g1"), "lower": F.lit(0.0), "upper": upper})
    return rows.withColumn("ok", (F.col("norm2") >= 0) & (F.col("norm2") <= F.col("upper") * (1 + 1e-9) + 1e-12))


def self_bound(rows: DataFrame) -> DataFrame:
    """The one-sided inequality |g|^2 <= 2 beta loss, beta being the largest curvature |x|^2 / M."""
    beta = _dot(F.col("x"), F.col("x")) / F.col("m")
    return rows.withColumn("beta", beta).withColumn("ok", F.col("norm2") <= 2 * beta * F.col("half_mse") * (1 + 1e-9) + 1e-12)


def pool_gradient(rows: DataFrame) -> DataFrame:
    """One row: the mean gradient, as an array. Its length is that of the parameters."""
    mean = rows.select(F.posexplode("g").alias("i", "v")).groupBy("i").agg(F.avg("v").alias("v"))
    return mean.agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "v"))), lambda s: s["v"]).alias("pool"))


def alignment(rows: DataFrame) -> DataFrame:
    """Adds ``inner``: the product of each window's gradient with the pool's; a step on it moves the pool's risk by minus that, to first order."""
    return rows.crossJoin(F.broadcast(pool_gradient(rows))).withColumn("inner", _dot(F.col("g"), F.col("pool")))  # one row


def one_step(x: np.ndarray, y: np.ndarray, w: np.ndarray, at: int, eta: float) -> tuple[float, float]:
    """Change of the pool's risk after one step on window ``at``: predicted to first order, and measured."""
    risk = lambda v: 0.5 * np.mean((y - x @ v) ** 2)
    grads = -(y - x @ w)[:, :, None] * x[:, None, :] / y.shape[1]
    step = grads[at].T
    return float(-eta * (grads.mean(0).T * step).sum()), float(risk(w - eta * step) - risk(w))


def conditioning_report(scores: DataFrame) -> DataFrame:
    """By source: spread of the number of observed slots, which the bounds divide by."""
    q = [0.0, 0.25, 0.5, 0.75, 1.0]
    return scores.groupBy("source").agg(*(F.percentile("m", F.lit(p)).alias(f"m_{int(100 * p)}") for p in q))


def by_decile(scores: DataFrame, value: str, groups: int = 10) -> DataFrame:
    """(source, decile, windows, mean): ``value`` by tenth of each source's ranking; tenths as ntile gives them."""
    rows = ranked(scores, "source")
    n, r = F.col("n"), F.col("rank_key")
    size, more = F.floor(n / groups), n % groups
    tile = F.when(r <= more * (size + 1), F.floor((r - 1) / (size + 1))).otherwise(more + F.floor((r - 1 - more * (size + 1)) / F.greatest(size, F.lit(1)))) + 1
    return rows.withColumn("decile", tile.cast("int")).groupBy("source", "decile").agg(F.count("*").alias("windows"), F.avg(value).alias("mean"))


def last_features(grid: DataFrame, lags: int, context: int, horizon: int, also: tuple[str, ...] = ()) -> DataFrame:
    """Rows (key, x, future, mask) from the grid: the last ``lags`` context values and a constant, missing as 0; and the columns ``also`` of the slot that the window begins at."""
    w = Window.partitionBy("source", "series_id").orderBy("t")
    z = F.coalesce("y", F.lit(0)).cast("double")
    rows = grid.withColumn("z", z)
    x = F.array(F.lit(1.0), *(F.lead("z", context - k).over(w) for k in range(1, lags + 1)))
    future = F.array(*(F.lead("z", context + h).over(w) for h in range(horizon)))
    mask = F.array(*(F.lead(F.col("y").isNotNull().cast("int"), context + h).over(w) for h in range(horizon)))
    return rows.select("source", "series_id", F.col("t").alias("origin"), x.alias("x"), future.alias("future"), mask.alias("mask"), *also).where(F.element_at("mask", horizon).isNotNull())
