"""Reference loss of every window: one frozen forecaster, one scalar a window, windows never stored.

Sums over a window's future come from running sums along the series, so a window costs a constant amount
whatever its horizon. All window functions of a plan share one partitioning and one sort by series.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..functions.loss import MSE, ErrorLoss, mean_where
from ..sources.tables import ship
from .grid import pack

BIG = "decimal(38,0)"
#: Any long; the product of two is a BIG.
WHOLE = "decimal(19,0)"
#: Windows that a worker scores before it hands them back.
SLICE = 32_768


def series():
    """One series in order of slots."""
    return Window.partitionBy("source", "series_id").orderBy("t")


def running():
    return series().rowsBetween(Window.unboundedPreceding, 0)


def between(total: str, first: int, last: int) -> Column:
    """Sum over the slots t + first .. t + last from the running sum ``total`` (null where the series ends before)."""
    return F.lead(total, last).over(series()) - (F.lead(total, first - 1).over(series()) if first > 0 else F.coalesce(F.lag(total, 1 - first).over(series()), F.lit(0)))


def finish(rows: DataFrame, reference_id: str) -> DataFrame:
    """Score rows with their status; windows without an observed slot or a forecast cannot be scored."""
    bad = F.col("rfl").isNull() | F.isnan("rfl")
    return rows.select(
        F.lit(reference_id).alias("reference_id"), "source", "series_id", "origin", F.col("m").cast("long").alias("m"),
        F.when(~bad, F.col("rfl")).alias("rfl"), F.when(bad, "unscorable").otherwise("ok").alias("status"),
    )


@dataclass(frozen=True)
class SeasonalNaive:
    """Repeats the season before; beyond one season, that of whole seasons before.

    ``pairwise`` drops a slot whose basis is missing. ``ffill_phase`` takes the latest earlier value of the
    same phase instead, so that only the future decides which slots count.
    """

    season: int
    missing: str = "pairwise"

    @property
    def id(self) -> str:
        return f"seasonal_naive_{self.season}" + ("" if self.missing == "pairwise" else f"_{self.missing}")

    def error(self, grid: DataFrame, ahead: int) -> DataFrame:
        """The grid with ``e<ahead>``: truth less the value ``ahead`` seasons before."""
        if self.missing == "pairwise":
            basis = F.lag("y", self.season * ahead).over(series())
        else:
            phase = Window.partitionBy("source", "series_id", F.pmod("t", F.lit(self.season))).orderBy("t")
            basis = F.last("y", ignorenulls=True).over(phase.rowsBetween(Window.unboundedPreceding, -ahead))
        return grid.withColumn(f"e{ahead}", F.col("y") - basis)

    def score(self, grid: DataFrame, context: int, horizon: int, loss: ErrorLoss = MSE, shift: Column | None = None) -> DataFrame:
        """(source, series_id, origin, m, rfl) for every slot that a whole window begins at; ``shift`` is added to the forecast."""
        bands = -(-horizon // self.season)
        for j in range(1, bands + 1):
            grid = self.error(grid, j)
        names = []
        for j in range(1, bands + 1):
            e = F.col(f"e{j}") if shift is None else F.col(f"e{j}") - shift
            value = F.when(e.isNotNull(), loss.of(e)).cast(BIG if loss.exact and shift is None else "double")
            grid = grid.withColumns({f"s{j}": F.sum(F.coalesce(value, F.lit(0))).over(running()), f"n{j}": F.count(f"e{j}").over(running())})
            names.append((j, context + (j - 1) * self.season, context + min(j * self.season, horizon) - 1))
        total = sum((between(f"s{j}", a, b) for j, a, b in names[1:]), between(f"s{names[0][0]}", *names[0][1:]))
        m = sum((between(f"n{j}", a, b) for j, a, b in names[1:]), between(f"n{names[0][0]}", *names[0][1:]))
        rows = grid.select("source", "series_id", F.col("t").alias("origin"), total.cast("double").alias("total"), m.alias("m"))
        return rows.where("m is not null").select("source", "series_id", "origin", "m", loss.finish(F.col("total"), F.col("m")).alias("rfl"))


def _moments(grid: DataFrame) -> DataFrame:
    # Products are of decimals: the square of a sum of many rows is beyond a long.
    y, t, seen = F.col("y").cast(WHOLE), F.col("t").cast(WHOLE), F.col("y").isNotNull().cast("long")
    sums = {"n0": seen, "n1": seen * t, "n2": F.when(F.col("y").isNotNull(), t * t).otherwise(0), "y1": F.coalesce(y, F.lit(0)), "y2": F.coalesce(y * y, F.lit(0)), "ty": F.coalesce(t * y, F.lit(0))}
    return grid.withColumns({k: F.sum(v.cast(BIG)).over(running()) for k, v in sums.items()})


def _future(context: int, horizon: int) -> dict[str, Column]:
    return {f"f_{k}": between(k, context, context + horizon - 1) for k in ("n0", "n1", "n2", "y1", "y2", "ty")}


class _Constant:
    """A forecast that is the same for every slot of the horizon: the squared error needs two sums only."""

    def basis(self, context: int) -> Column:
        raise NotImplementedError

    def score(self, grid: DataFrame, context: int, horizon: int) -> DataFrame:
        rows = _moments(grid).withColumns(_future(context, horizon) | {"v": self.basis(context)})
        n, s1, s2, v = F.col("f_n0"), F.col("f_y1"), F.col("f_y2"), F.col("v")
        total = s2 - 2 * v * s1 + n * v * v
        return rows.where("f_n0 is not null").select("source", "series_id", F.col("t").alias("origin"), n.cast("long").alias("m"), F.when((n > 0) & v.isNotNull(), total.cast("double") / n.cast("long")).alias("rfl"))


@dataclass(frozen=True)
class LastValue(_Constant):
    """The last observed value of the context."""

    id: str = "last_value"

    def basis(self, context):
        # The last value of the frame is found from its first row, so that a row stands for its origin.
        return F.last("y", ignorenulls=True).over(series().rowsBetween(0, context - 1))


@dataclass(frozen=True)
class MovingMean(_Constant):
    """Mean of the observed values among the last k slots of the context."""

    k: int

    @property
    def id(self):
        return f"moving_mean_{self.k}"

    def basis(self, context):
        n, s = between("n0", context - self.k, context - 1), between("y1", context - self.k, context - 1)
        return F.when(n > 0, s.cast("double") / n.cast("double"))

    def score(self, grid, context, horizon):
        rows = _moments(grid).withColumns(_future(context, horizon) | {"v": self.basis(context)})
        n, s1, s2, v = (F.col(x).cast("double") for x in ("f_n0", "f_y1", "f_y2", "v"))
        total = s2 - 2 * v * s1 + n * v * v
        return rows.where("f_n0 is not null").select("source", "series_id", F.col("t").alias("origin"), F.col("f_n0").cast("long").alias("m"), F.when((n > 0) & v.isNotNull(), total / n).alias("rfl"))


@dataclass(frozen=True)
class Drift:
    """The line through the first and the last observed value of the context, continued."""

    id: str = "drift"

    def score(self, grid: DataFrame, context: int, horizon: int) -> DataFrame:
        frame = series().rowsBetween(0, context - 1)
        at = F.when(F.col("y").isNotNull(), F.struct("t", "y"))
        rows = _moments(grid).withColumns(_future(context, horizon) | {"a": F.first(at, ignorenulls=True).over(frame), "b": F.last(at, ignorenulls=True).over(frame)})
        n, n1, n2, y1, y2, ty = (F.col(f"f_{k}").cast("double") for k in ("n0", "n1", "n2", "y1", "y2", "ty"))
        ta, tb, ya, yb = F.col("a.t"), F.col("b.t"), F.col("a.y"), F.col("b.y")
        slope = F.when(tb > ta, (yb - ya) / (tb - ta)).otherwise(F.lit(0.0))
        v = yb.cast("double") - slope * tb
        total = y2 - 2 * v * y1 - 2 * slope * ty + n * v * v + 2 * v * slope * n1 + slope * slope * n2
        return rows.where("f_n0 is not null").select("source", "series_id", F.col("t").alias("origin"), F.col("f_n0").cast("long").alias("m"), F.when((n > 0) & yb.isNotNull(), F.greatest(total, F.lit(0.0)) / n).alias("rfl"))


@dataclass(frozen=True)
class ContextGaussian:
    """A normal forecast with mean and variance of the context's observed values; the loss is minus log density."""

    floor: float = 1.0
    id: str = "context_gaussian"

    def score(self, grid: DataFrame, context: int, horizon: int) -> DataFrame:
        past = {f"c_{k}": between(k, 0, context - 1) for k in ("n0", "y1", "y2")}
        rows = _moments(grid).withColumns(_future(context, horizon) | past)
        cn, c1, c2, n, s1, s2 = (F.col(k).cast("double") for k in ("c_n0", "c_y1", "c_y2", "f_n0", "f_y1", "f_y2"))
        # Nested structs of columns would repeat the sums; names keep each of them evaluated once.
        rows = rows.withColumn("mu", F.when(cn > 0, c1 / cn)).withColumn("var", F.when(cn > 0, F.greatest(c2 / cn - F.col("mu") * F.col("mu"), F.lit(self.floor))))
        mu, var = F.col("mu"), F.col("var")
        rfl = 0.5 * F.log(2 * np.pi * var) + (s2 - 2 * mu * s1 + n * mu * mu) / n / (2 * var)
        return rows.where("f_n0 is not null").select("source", "series_id", F.col("t").alias("origin"), F.col("f_n0").cast("long").alias("m"), F.when((n > 0) & mu.isNotNull(), rfl).alias("rfl"))


@dataclass(frozen=True)
class ResidualQuantile:
    """Seasonal naive plus, for each level, the quantile of the source's seasonal differences.

    ``offsets`` has one row a source; it is fitted once and only read afterwards. The loss is the mean
    pinball loss over levels (doubled: a common estimate of the probabilistic score).
    """

    season: int
    levels: tuple = (0.1, 0.5, 0.9)

    @property
    def id(self):
        return f"residual_quantile_{self.season}"

    def fit(self, grid: DataFrame) -> DataFrame:
        rows = SeasonalNaive(self.season).error(grid, 1).where("e1 is not null")
        return rows.groupBy("source").agg(*(F.percentile("e1", F.lit(q)).alias(f"q{i}") for i, q in enumerate(self.levels)))

    def score(self, grid: DataFrame, context: int, horizon: int, offsets: DataFrame | None = None, weighted: bool = False) -> DataFrame:
        """``weighted``: doubled pinball sums over the sum of absolute truth, else doubled mean pinball; both averaged over levels."""
        if horizon > self.season:
            raise ValueError("the horizon goes beyond one season")
        offsets = self.fit(grid) if offsets is None else offsets
        rows = SeasonalNaive(self.season).error(grid, 1).join(F.broadcast(offsets), "source", "left")  # one row a source
        loss = sum((2 * F.greatest((F.col("e1") - F.col(f"q{i}")) * q, (F.col("e1") - F.col(f"q{i}")) * (q - 1)) for i, q in enumerate(self.levels)), F.lit(0.0)) / len(self.levels)
        rows = rows.withColumns({"l": F.sum(F.coalesce(loss, F.lit(0.0))).over(running()), "n": F.count("e1").over(running()), "a": F.sum(F.when(F.col("e1").isNotNull(), F.abs("y")).otherwise(0)).over(running())})
        ends = (context, context + horizon - 1)
        rows = rows.select("source", "series_id", F.col("t").alias("origin"), between("n", *ends).alias("m"), between("l", *ends).alias("total"), between("a", *ends).alias("size"))
        by = F.col("size") if weighted else F.col("m")
        return rows.where("m is not null").select("source", "series_id", "origin", "m", F.when((F.col("m") > 0) & (by > 0), F.greatest("total", F.lit(0.0)) / by).alias("rfl"))


@dataclass(frozen=True)
class PointQuantile:
    """Mean squared error of the seasonal naive forecast plus the mean pinball loss of its quantiles."""

    season: int
    levels: tuple = (0.1, 0.5, 0.9)

    @property
    def id(self):
        return f"point_quantile_{self.season}"

    def score(self, grid: DataFrame, context: int, horizon: int) -> DataFrame:
        point = SeasonalNaive(self.season).score(grid, context, horizon).withColumnRenamed("rfl", "p")
        spread = ResidualQuantile(self.season, self.levels).score(grid, context, horizon).select("source", "series_id", "origin", F.col("rfl").alias("q"))
        return point.join(spread, ["source", "series_id", "origin"]).select("source", "series_id", "origin", "m", (F.col("p") + F.col("q") / 2).alias("rfl"))


def lag_rows(grid: DataFrame, lags: int, context: int, horizon: int, last: Column | None = None) -> DataFrame:
    """(source, series_id, origin, x): x holds a constant, the last ``lags`` context values, newest first, and the
    ``horizon`` future values of each window; missing values count as 0. ``last`` says which origins count."""
    rows = grid.withColumn("z", F.coalesce("y", F.lit(0)).cast("long"))
    cols = [F.lit(1).cast("long"), *(F.lead("z", context - k).over(series()) if context - k else F.col("z") for k in range(1, lags + 1)), *(F.lead("z", context + h).over(series()) for h in range(horizon))]
    x = rows.select("source", "series_id", F.col("t").alias("origin"), F.array(*cols).alias("x")).where(F.col("x")[lags + horizon].isNotNull())
    return x if last is None else x.where(last)


def gram(grid: DataFrame, lags: int, context: int, horizon: int, last: Column | None = None) -> DataFrame:
    """(i, j, value): exact sums over windows of the products x[i] * x[j] that a fit reads (see ``lag_rows``)."""
    n = lags + 1
    pairs = F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in range(n) for j in range(i, n + horizon)))
    rows = lag_rows(grid, lags, context, horizon, last).select("x", F.explode(pairs).alias("p")).select("p.*", F.element_at("x", F.col("p.i") + 1).alias("a"), F.element_at("x", F.col("p.j") + 1).alias("b"))
    return rows.groupBy("i", "j").agg(F.sum((F.col("a") * F.col("b")).cast(BIG)).cast("double").alias("value"))


@dataclass(frozen=True)
class RidgeDirect:
    """One linear forecast for each slot of the horizon from the last ``lags`` context values and a constant."""

    lags: int
    ridge: float = 1.0
    weights: tuple = field(default=(), repr=False)

    @property
    def id(self):
        return f"ridge_{self.lags}"

    def fit(self, grid: DataFrame, context: int, horizon: int, last: Column | None = None) -> RidgeDirect:
        """Every partition sums its products, Spark sums those, and the driver solves; what reaches it depends on
        lags and horizon only. The solution is kept frozen."""
        ship(grid.sparkSession)
        n = self.lags + 1

        def work(batches):
            total = np.zeros((n, n + horizon))
            for b in batches:
                if len(b):
                    x = np.stack(b["x"].to_numpy()).astype(float)
                    total += x[:, :n].T @ x
            yield pd.DataFrame({"k": np.arange(total.size), "v": total.ravel()})

        g = np.zeros(n * (n + horizon))
        for r in lag_rows(grid, self.lags, context, horizon, last).select("x").mapInPandas(work, "k int, v double").groupBy("k").agg(F.sum("v").alias("v")).collect():
            g[r["k"]] = r["v"]
        g = g.reshape(n, n + horizon)
        a = g[:, :n]
        scale = max(np.trace(a[1:, 1:]) / max(self.lags, 1), 1.0)
        penalty = np.diag([0.0] + [self.ridge * 1e-6 * scale] * self.lags)
        w = np.linalg.lstsq(a + penalty, g[:, n:], rcond=None)[0]
        return RidgeDirect(self.lags, self.ridge, tuple(map(tuple, w)))

    def predict(self, contexts: np.ndarray) -> np.ndarray:
        w = np.asarray(self.weights)
        last = np.nan_to_num(contexts[:, ::-1][:, : self.lags])
        return w[0] + last @ w[1:]

    def score(self, grid: DataFrame, context: int, horizon: int) -> DataFrame:
        return arrow_scores(grid, self.predict, context, horizon)


def arrow_scores(grid: DataFrame, predict, context: int, horizon: int, loss=None, chunk: int = 4_096) -> DataFrame:
    """Scores of any forecaster ``predict(rows x context) -> rows x horizon`` in Arrow batches of packed chunks.

    Missing values are NaN. ``loss(forecast, future, mask) -> rows`` defaults to the masked mean squared
    error. A long series is spread over chunks that carry a halo, so no worker holds it whole.
    """
    ship(grid.sparkSession)
    span = context + horizon
    rows = pack(grid, chunk, span - 1).select("source", "series_id", "chunk", "t0", "values", "observed")

    def batch(out):
        at = pa.array(np.repeat(np.arange(len(out)), [len(o[2]) for o in out]))
        return pa.RecordBatch.from_arrays([*(pa.array([o[k] for o in out], pa.string()).take(at) for k in (0, 1)), *(pa.array(np.concatenate([o[k] for o in out])) for k in (2, 3, 4))], ["source", "series_id", "origin", "m", "rfl"])

    def work(batches):
        for b in batches:
            out, held = [], 0
            for i in range(b.num_rows):
                y = np.array(b.column(4)[i].values.to_numpy(zero_copy_only=False), float)
                if len(y) < span:
                    continue
                w = np.lib.stride_tricks.sliding_window_view(y, span)[:chunk]
                mask = ~np.isnan(w[:, context:])
                forecast = predict(w[:, :context])
                value = loss(forecast, w[:, context:], mask) if loss else mean_where((np.where(mask, w[:, context:], 0.0) - forecast) ** 2, mask)
                t0 = b.column(3)[i].as_py()
                out.append((b.column(0)[i].as_py(), b.column(1)[i].as_py(), np.arange(t0, t0 + len(w)), mask.sum(axis=1), value))
                held += len(w)
                # What a worker holds is bounded by rows, not by the series that came in one batch.
                if held >= SLICE:
                    yield batch(out)
                    out, held = [], 0
            if out:
                yield batch(out)

    return rows.mapInArrow(work, "source string, series_id string, origin long, m long, rfl double")


SCALINGS = ("context_std", "context_meanabs", "series_std")


def scales(grid: DataFrame, context: int, scaling: str) -> DataFrame:
    """(source, series_id, origin, scale): spread or mean size of the observed context, or spread of the whole series."""
    past = series().rowsBetween(0, context - 1)
    whole = Window.partitionBy("source", "series_id")
    made = {"context_std": lambda: F.stddev_pop("y").over(past), "context_meanabs": lambda: F.avg(F.abs("y")).over(past), "series_std": lambda: F.stddev_pop("y").over(whole)}
    return grid.select("source", "series_id", F.col("t").alias("origin"), made[scaling]().alias("scale"))


def scaled(scores: DataFrame, grid: DataFrame, context: int, scaling: str, power: int = 2) -> DataFrame:
    """Scores as if every window had been divided by its scale: a squared loss by the scale's square (``power`` 1 for absolute ones).

    Windows without a scale above 0 cannot be scored. Joins one number a window.
    """
    rows = scores.join(scales(grid, context, scaling), ["source", "series_id", "origin"], "left")
    value = F.when(F.col("scale") > 0, F.col("rfl") / F.pow("scale", F.lit(power)))
    rows = rows.withColumn("rfl", value)
    return rows.withColumn("status", F.when(F.col("rfl").isNull(), "unscorable").otherwise("ok")).select(*scores.columns)


def score(grid: DataFrame, reference, context: int, horizon: int, held_out: bool = True, stride: int = 1, scaling: str = "none", **options) -> DataFrame:
    """Score table of ``reference`` over all windows of ``grid``; none whose future reaches into the last horizon if ``held_out``."""
    rows = reference.score(grid, context, horizon, **options)
    if held_out:
        # Every slot with a whole window has a row, so the last origin tells the length; the partitioning is the one at hand.
        last = F.max("origin").over(Window.partitionBy("source", "series_id"))
        rows = rows.withColumn("last", last).where(F.col("origin") + horizon <= F.col("last")).drop("last")
    if stride > 1:
        rows = rows.where(F.col("origin") % stride == 0)
    out = finish(rows, reference.id)
    return out if scaling == "none" else scaled(out, grid, context, scaling)


def observed(scores: DataFrame, name: str = "scores"):
    """The score table, and an Observation that holds windows, scorable ones and the mean loss once the table has been written."""
    seen = Observation(name)
    ok = F.col("status") == "ok"
    return scores.observe(seen, F.count("*").alias("windows"), F.count_if(ok).alias("scorable"), F.avg("rfl").alias("mean")), seen


def store(scores: DataFrame, path: str) -> None:
    from ..sources.tables import store_scores

    store_scores(scores, path)


def amortisation(scores: DataFrame, targets: int, ratios: int) -> DataFrame:
    """By source: forward passes of one score table, those that scoring for every target and ratio anew would take, and the difference."""
    uses = targets * ratios
    rows = scores.groupBy("source").agg(F.count("*").alias("passes"))
    return rows.select("source", F.lit(uses).alias("selections"), "passes", (F.col("passes") * uses).alias("without_reuse"), (F.col("passes") * (uses - 1)).alias("saved"))


def cost_report(scores: DataFrame) -> DataFrame:
    """By source: forward passes, scalars that ranking sorts, n ln n of the sort, bytes of the stored scalars."""
    ok = F.count(F.when(F.col("status") == "ok", 1))
    rows = scores.groupBy("source").agg(F.count("*").alias("forward_passes"), ok.alias("sorted_rows"))
    n = F.col("sorted_rows")
    return rows.select("source", "forward_passes", "sorted_rows", F.when(n > 0, n * F.log(n)).otherwise(0.0).alias("sort_work"), (8 * n).alias("score_bytes"))
