"""Small targets that train inside Spark on a selection, so that every comparison runs from end to end."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import ship
from .theory import last_features

KEY = ["source", "series_id", "origin"]
#: Windows that the driver holds at once while it trains.
DRAW = 200_000


@dataclass(frozen=True)
class TrainSpec:
    """Budget and optimiser of a run; equal for all selections that are compared."""

    steps: int = 100
    batch: int = 512
    rate: float = 1e-2
    warmup: int = 10
    clip: float = 1.0
    decay: float = 0.01
    seed: int = 0

    def rate_at(self, step: int) -> float:
        """Linear warm-up, then half a cosine down to zero."""
        if step < self.warmup:
            return self.rate * (step + 1) / self.warmup
        return self.rate * 0.5 * (1 + math.cos(math.pi * (step - self.warmup) / max(1, self.steps - self.warmup)))


def examples(grid: DataFrame, keys: DataFrame, lags: int, context: int, horizon: int, also: tuple[str, ...] = ()) -> DataFrame:
    """Scaled rows of the named windows: features and futures over the mean absolute feature, so that sources compare.

    Slots that a named window begins at are marked on the grid, with the columns ``also`` of ``keys``, before any array
    is made. Marks and slots are dealt once, by series, and meet there: neither is broadcast, and the windows of the
    features read each series where it lies.
    """
    none = lambda df, c: F.lit(None).cast(df.schema[c].dataType).alias(c)
    slots = grid.select("source", "series_id", "t", "y", F.lit(True).alias("slot"), F.lit(False).alias("named"), *(none(keys, c) for c in also))
    marks = keys.select("source", "series_id", F.col("origin").alias("t"), none(grid, "y"), F.lit(False).alias("slot"), F.lit(True).alias("named"), *also)
    dealt = slots.unionByName(marks).repartition("source", "series_id").groupBy("source", "series_id", "t")
    marked = dealt.agg(F.max("y").alias("y"), F.max("slot").alias("slot"), F.max("named").alias("named"), *(F.first(c, ignorenulls=True).alias(c) for c in also)).where("slot")
    rows = last_features(marked, lags, context, horizon, ("named", *also)).where("named")
    size = F.greatest(F.aggregate(F.slice("x", 2, lags), F.lit(0.0), lambda a, v: a + F.abs(v)) / lags, F.lit(1e-9))
    scale = lambda a: F.transform(a, lambda v: v / F.col("size"))
    return rows.withColumn("size", size).select(*KEY, "size", F.concat(F.array(F.lit(1.0)), scale(F.slice("x", 2, lags))).alias("x"), scale(F.col("future")).alias("future"), "mask", *also)


def fit_ridge(rows: DataFrame, lags: int, horizon: int, ridge: float = 1.0) -> np.ndarray:
    """Closed form: every partition sums its products, Spark sums the partitions, and the driver solves.

    What reaches the driver are (lags + 1) x (lags + 1 + horizon) numbers, whatever the number of rows.
    """
    ship(rows.sparkSession)
    n = lags + 1

    def work(batches):
        a = np.zeros((n, n + horizon))
        for b in batches:
            if len(b):
                x, y, m = (np.stack(b[c].to_numpy()).astype(float) for c in ("x", "future", "mask"))
                a += np.hstack([x.T @ x, x.T @ np.where(m == 1, y, 0.0)])
        yield pd.DataFrame({"i": np.arange(a.size), "v": a.ravel()})

    sums = rows.select("x", "future", "mask").mapInPandas(work, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).collect()
    a = np.zeros(n * (n + horizon))
    for r in sums:
        a[r["i"]] = r["v"]
    a = a.reshape(n, n + horizon)
    return np.linalg.solve(a[:, :n] + ridge * np.eye(n), a[:, n:])


def _batches(rows: DataFrame, seed: int, batch: int, need: int):
    """Batches (x, y, m) in the seeded order of windows, over and over; at most ``DRAW`` windows are fetched at once."""
    at = F.struct(F.xxhash64(*KEY, F.lit(seed)).alias("h"), *KEY)
    ordered = rows.select(at.alias("at"), "x", "future", "mask")
    kinds = dict(rows.select(*KEY).dtypes)
    left, last, only = None, None, None
    while True:
        if only is None:
            after = ordered if last is None else ordered.where(F.col("at") > F.struct(F.lit(last["h"]).alias("h"), *(F.lit(last[c]).cast(kinds[c]).alias(c) for c in KEY)))
            part = after.orderBy("at").limit(min(need, DRAW)).collect()
            if not part and last is None:
                return
            if last is None and (len(part) < DRAW or need <= DRAW):
                only = part
            last = part[-1]["at"] if len(part) == DRAW else None
        else:
            part = only
        if not part:
            continue
        arrays = [np.array([r[c] for r in part], float) for c in ("x", "future", "mask")]
        left = arrays if left is None else [np.concatenate(z) for z in zip(left, arrays)]
        while len(left[0]) >= batch:
            yield [z[:batch] for z in left]
            left = [z[batch:] for z in left]


def _losses(rows: DataFrame, weights: list[np.ndarray]) -> list[float]:
    """Mean squared error over all observed slots of ``rows``, for each of the weights, in one pass."""
    ship(rows.sparkSession)

    def work(batches):
        out, n = np.zeros(len(weights)), 0.0
        for b in batches:
            if len(b):
                x, y, m = (np.stack(b[c].to_numpy()).astype(float) for c in ("x", "future", "mask"))
                out += [(((x @ w - y) * m) ** 2).sum() for w in weights]
                n += m.sum()
        yield pd.DataFrame({"i": np.arange(len(weights)), "v": out, "n": n})

    sums = rows.select("x", "future", "mask").mapInPandas(work, "i int, v double, n double").groupBy("i").agg(F.sum("v").alias("v"), F.sum("n").alias("n")).collect()
    return [r["v"] / max(r["n"], 1) for r in sorted(sums, key=lambda r: r["i"])]


def fit_sgd(rows: DataFrame, lags: int, horizon: int, spec: TrainSpec, validation: DataFrame | None = None, every: int = 10):
    """AdamW on batches of the seeded order of windows; returns weights and [(step, loss of the validation rows)].

    The batches of the run are windows in the order of a hash, fetched in blocks; gradients are sums over a
    batch. The validation loss is over all rows of ``validation``.
    """
    rng = np.random.default_rng(spec.seed)
    n = lags + 1
    w = rng.standard_normal((n, horizon)) * 0.01
    first, second, logged = np.zeros_like(w), np.zeros_like(w), []
    for step, (x, y, m) in zip(range(spec.steps), _batches(rows, spec.seed, spec.batch, spec.steps * spec.batch)):
        r = (x @ w - y) * m
        g = x.T @ (r / np.maximum(m.sum(1, keepdims=True), 1)) / len(x)
        g *= min(1.0, spec.clip / max(float(np.linalg.norm(g)), 1e-12))
        first, second = 0.9 * first + 0.1 * g, 0.999 * second + 0.001 * g * g
        lr = spec.rate_at(step)
        w = w - lr * (first / (1 - 0.9 ** (step + 1)) / (np.sqrt(second / (1 - 0.999 ** (step + 1))) + 1e-8) + spec.decay * w)
        if (step + 1) % every == 0 or step == 0:
            logged.append((step + 1, w))
    if validation is None or not logged or validation.isEmpty():
        return w, []
    return w, list(zip([n for n, _ in logged], _losses(validation, [v for _, v in logged])))


def forecast_errors(rows: DataFrame, w: np.ndarray) -> DataFrame:
    """(key, size, h, y, e): errors of the forecasts in the scale of the data, observed slots only."""
    cols = [F.array(*(F.lit(float(v)) for v in w[:, h])) for h in range(w.shape[1])]
    forecast = F.array(*(F.aggregate(F.zip_with("x", c, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v) for c in cols))
    z = rows.select(*KEY, "size", F.posexplode(F.arrays_zip(F.col("future").alias("y"), forecast.alias("f"), F.col("mask").alias("k"))).alias("h", "z"))
    return z.where("z.k = 1").select(*KEY, "size", "h", (F.col("z.y") * F.col("size")).alias("y"), ((F.col("z.y") - F.col("z.f")) * F.col("size")).alias("e"))


def budget_report(kept: int, spec: TrainSpec) -> dict:
    """What a run sees: windows drawn, how many of them differ, and passes over the selection."""
    drawn = spec.steps * spec.batch
    return {"steps": spec.steps, "batch": spec.batch, "drawn": drawn, "distinct": min(drawn, kept), "epochs": drawn / kept if kept else None}
