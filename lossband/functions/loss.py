"""Masked losses: as functions of the error of one slot, as array expressions, and in numpy for batches."""

from __future__ import annotations

import math
from dataclasses import dataclass
from typing import Callable

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class ErrorLoss:
    """A loss that is the mean over observed slots of a function of the error (truth minus forecast).

    ``exact`` tells that integer errors give integer values, so that sums can be kept exactly.
    """

    name: str
    of: Callable[[Column], Column]
    exact: bool = False
    after: Callable[[Column, Column], Column] | None = None  # from (sum, observed) to the loss; None: their quotient

    def finish(self, total: Column, m: Column) -> Column:
        value = self.after(total, m) if self.after else total / m
        return F.when(m > 0, value)


MSE = ErrorLoss("mse", lambda e: e * e, True)
HALF_MSE = ErrorLoss("half_mse", lambda e: e * e, True, lambda s, m: s / m / 2)
MAE = ErrorLoss("mae", F.abs, True)
ERROR_NORM = ErrorLoss("error_norm", lambda e: e * e, True, lambda s, m: F.sqrt(s))


def pinball(level: float) -> ErrorLoss:
    return ErrorLoss(f"pinball_{level:g}", lambda e: F.greatest(e * level, e * (level - 1)))


def custom(name: str, of: Callable[[Column], Column]) -> ErrorLoss:
    """Any Column-valued function of the error."""
    return ErrorLoss(name, of)


# ---- over arrays -------------------------------------------------------------------------------


def masked_mean(values: Column, mask: Column) -> Column:
    """Mean of ``values`` where ``mask`` is 1; null if it is nowhere."""
    m = F.aggregate(mask, F.lit(0), lambda a, x: a + x.cast("int"))
    total = F.aggregate(F.zip_with(values, mask, lambda v, b: F.when(b == 1, v).otherwise(0.0)), F.lit(0.0), lambda a, x: a + x)
    return F.when(m > 0, total / m)


def array_loss(loss: ErrorLoss, forecast: Column, future: Column, mask: Column) -> Column:
    errors = F.zip_with(future, forecast, lambda y, f: loss.of(y - f).cast("double"))
    m = F.aggregate(mask, F.lit(0), lambda a, x: a + x.cast("int"))
    total = F.aggregate(F.zip_with(errors, mask, lambda v, b: F.when(b == 1, v).otherwise(0.0)), F.lit(0.0), lambda a, x: a + x)
    return loss.finish(total, m)


# ---- in numpy, rows of windows -------------------------------------------------------------------


def mean_where(values: np.ndarray, mask: np.ndarray) -> np.ndarray:
    m = mask.sum(axis=1)
    return np.where(m > 0, np.where(mask, values, 0.0).sum(axis=1) / np.maximum(m, 1), np.nan)


def np_mse(forecast, future, mask):
    return mean_where((np.where(mask, future, 0.0) - forecast) ** 2, mask)


def np_pinball(forecast, future, mask, level):
    e = np.where(mask, future, 0.0) - forecast
    return mean_where(np.maximum(level * e, (level - 1) * e), mask)


def np_wql(quantiles: np.ndarray, future, mask, levels) -> np.ndarray:
    """``quantiles`` is levels x rows x horizon: doubled pinball sums over absolute sums of truth, mean of levels."""
    y = np.where(mask, future, 0.0)
    size = np.abs(y).sum(axis=1)
    per = []
    for q, level in zip(quantiles, levels):
        e = np.where(mask, y - q, 0.0)
        per.append(2 * np.maximum(level * e, (level - 1) * e).sum(axis=1))
    return np.where(size > 0, np.mean(per, axis=0) / np.where(size > 0, size, 1), np.nan)


_erf = np.vectorize(math.erf, otypes=[float])


def normal_cdf(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + _erf(np.asarray(x, float) / math.sqrt(2)))


def gaussian_score(mu, sigma, y) -> np.ndarray:
    """Probabilistic score of a normal forecast at y, in closed form."""
    z = (y - mu) / sigma
    return sigma * (z * (2 * normal_cdf(z) - 1) + 2 * np.exp(-z * z / 2) / math.sqrt(2 * math.pi) - 1 / math.sqrt(math.pi))


def sample_score(samples: np.ndarray, y: float) -> float:
    """Probabilistic score of equally likely samples: mean distance to y less half their mean distance."""
    s = np.sort(np.asarray(samples, float))
    n = len(s)
    pairs = 2 * (s * (2 * np.arange(1, n + 1) - n - 1)).sum() / n**2
    return float(np.abs(s - y).mean() - pairs / 2)


def gaussian_nll(mu: Column, var: Column, y: Column) -> Column:
    return 0.5 * F.log(2 * math.pi * var) + (y - mu) * (y - mu) / (2 * var)


def student_nll(mu: Column, scale: Column, df: float, y: Column) -> Column:
    const = math.lgamma(df / 2) - math.lgamma((df + 1) / 2) + 0.5 * math.log(df * math.pi)
    z = (y - mu) / scale
    return F.lit(const) + F.log(scale) + (df + 1) / 2 * F.log(1 + z * z / df)
