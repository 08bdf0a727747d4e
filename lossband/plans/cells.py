"""Targets of three families trained on many selections at once, and judged on held-out horizons of any corpus.

A cell is one target on one selection. Each window carries the numbers of the cells that select it, so that fitting,
residuals and judging read the windows once each for all cells of a corpus, whatever the number of cells.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from statistics import NormalDist

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators import select as sel
from ..operators.rank import cutoffs, scorable
from ..schema import Alpha
from ..sources.tables import keep, ship
from .target import KEY

LEVELS = tuple(q / 10 for q in range(1, 10))
#: Residuals are counted in bins of equal width of their inverse hyperbolic sine; those beyond the ends (11,000
#: times the context's size) count in the outermost bins.
BINS, REACH = 1024, 10.0
#: Cells that one number holds a bit each of.
WORD = 62


@dataclass(frozen=True)
class Cell:
    """A target of a family, and the reference, rule, ratio and seed of the selection that it is trained on."""

    family: str
    reference: str
    strategy: str
    alpha: str = "1"
    seed: int = 0


#: Rules that read one ranking: what it is grouped by, and whether its order is that of a seeded hash.
RANKING = {"central": ("source", False), "bottom": ("source", False), "top": ("source", False), "global": (None, False), "random_stratified": ("source", True), "random_global": (None, True)}


def _hit(strategy: str, alpha: Alpha) -> Column:
    n, rank = F.col("n"), F.col("rank")
    if strategy in ("central", "global"):
        return sel.by_count(n, rank, alpha)
    return rank > n - sel.kept(n, alpha) if strategy == "top" else rank <= sel.kept(n, alpha)


def _ends(strategy: str, alpha: Alpha) -> list[Column]:
    """The ranks after which the rule begins or stops to hold."""
    n = F.col("n")
    if strategy in ("central", "global"):
        return [sel.skipped(n, alpha), sel.skipped(n, alpha) + sel.kept(n, alpha)]
    return [n - sel.kept(n, alpha) if strategy == "top" else sel.kept(n, alpha)]


def _any(masks) -> Column:
    return reduce(lambda a, m: a.bitwiseOR(m), masks, F.lit(0).cast("long"))


def memberships(scores: dict[str, DataFrame], cells: list[Cell]) -> DataFrame:
    """(key, cells): the numbers of the cells that select each window.

    All rankings of all rules are cut in one pass: their rows carry the number of the ranking and the group that they
    are ranked in. Between two ranks at which a rule changes all windows have the same cells, so a window's place
    between the windows at those ranks, a few a group, tells its cells, and no ranking is sorted or stored as a whole.
    Random orders are those of the upper 53 bits of a seeded hash.
    """
    rankings: dict[tuple, list[int]] = {}
    for i, c in enumerate(cells):
        by, shuffled = RANKING.get(c.strategy, ("full", False))
        rankings.setdefault((c.reference, by, shuffled, c.seed if shuffled else 0), []).append(i)
    numbers, words = {r: k for k, r in enumerate(rankings)}, range(-(-len(cells) // WORD))
    bits = lambda i, k: F.lit(1 << i % WORD if i // WORD == k else 0).cast("long")
    value = lambda shuffled, seed: (F.shiftright(F.xxhash64(*KEY, F.lit(seed)), 11) if shuffled else F.col("rfl")).cast("double")
    group = lambda by: F.col("source") if by else F.lit("")
    rows = {r: scorable(scores[r]).select(*KEY, "rfl") for r in dict.fromkeys(c.reference for c in cells)}
    cut = {r: k for r, k in numbers.items() if r[1] != "full"}
    if cut:
        placed = [rows[r[0]].select(*KEY, F.lit(k).alias("ranking"), group(r[1]).alias("group"), value(*r[2:]).alias("rfl")) for r, k in cut.items()]
        own = lambda of: F.coalesce(*(F.when(F.col("ranking") == k, of(rankings[r])) for r, k in cut.items()))
        wanted = own(lambda members: F.array(*(e for i in members for e in _ends(cells[i].strategy, Alpha.of(cells[i].alpha))), F.col("n")))
        ends = cutoffs(reduce(DataFrame.unionByName, placed), wanted, ["ranking", "group"], slack=0.005)
        ends = ends.select("ranking", "group", "n", "rank", F.struct("rfl", *KEY).alias("upto"))
        # From after one end to the next, and the last end is the last rank: a few rows a group.
        masks = {f"w{k}": own(lambda members: _any(F.when(_hit(cells[i].strategy, Alpha.of(cells[i].alpha)), bits(i, k)).otherwise(0) for i in members)) for k in words}
        spans = keep(ends.withColumn("after", F.lag("upto").over(Window.partitionBy("ranking", "group").orderBy("rank"))).withColumns(masks), "spans")
    out = []
    for reference, one in rows.items():
        mine = {k: r for r, k in numbers.items() if r[0] == reference}
        for k, (_, by, shuffled, seed) in mine.items():
            if by != "full":
                place = F.struct(value(shuffled, seed).alias("rfl"), *KEY)
                span = F.broadcast(spans.where(F.col("ranking") == k).select(F.col("group").alias("g"), "after", "upto", *(F.col(f"w{j}").alias(f"w{k}_{j}") for j in words)))
                one = one.join(span, (F.col("g") == group(by)) & (F.col("after").isNull() | (place > F.col("after"))) & (place <= F.col("upto"))).drop("g", "after", "upto")
        of = lambda j: _any(F.col(f"w{k}_{j}") if r[1] != "full" else _any(bits(i, j) for i in rankings[r]) for k, r in mine.items())  # noqa: E731, B023
        out.append(one.select(*KEY, *(of(j).alias(f"w{j}") for j in words)).where(_any(F.col(f"w{j}") for j in words) != 0))
    # A window has one row a reference; they meet where its series is.
    sums = reduce(DataFrame.unionByName, out).repartition("source", "series_id").groupBy(*KEY).agg(*(F.bit_or(f"w{k}").alias(f"w{k}") for k in words))
    return sums.select(*KEY, F.array_compact(F.array(*(F.when(F.col(f"w{i // WORD}").bitwiseAND(bits(i, i // WORD)) != 0, F.lit(i)) for i in range(len(cells))))).alias("cells"))


def sizes(members: DataFrame) -> DataFrame:
    """(cell, kept, shared): windows of each cell, and how many of them cell 0 has as well."""
    return members.select(F.explode("cells").alias("cell"), F.array_contains("cells", 0).cast("long").alias("both")).groupBy("cell").agg(F.count("*").alias("kept"), F.sum("both").alias("shared"))


def _arrays(b: pd.DataFrame):
    return (np.stack(b[c].to_numpy()).astype(float) for c in ("x", "future", "mask"))


def _of(b: pd.DataFrame, count: int) -> np.ndarray:
    """rows x cells: which cells select which rows."""
    out = np.zeros((len(b), count), bool)
    lists = b["cells"].to_numpy()
    out[np.repeat(np.arange(len(b)), [len(v) for v in lists]), np.concatenate(lists)] = True
    return out


def fit_linear(pool: DataFrame, count: int, lags: int, horizon: int, ridge: float = 1.0) -> np.ndarray:
    """cells x (lags + 1) x horizon: for each slot the ridge solution over the windows whose slot was observed.

    What reaches the driver are horizon x (lags + 1) x (lags + 2) sums a cell.
    """
    ship(pool.sparkSession)
    n = lags + 1

    def work(batches):
        a = np.zeros((count, horizon, n, n + 1))
        for b in batches:
            if len(b):
                x, y, m = _arrays(b)
                of = _of(b, count)
                squares, y = (x[:, :, None] * x[:, None, :]).reshape(len(x), n * n), np.where(m == 1, y, 0.0)
                for i in range(count):
                    mine = of[:, i]
                    a[i, :, :, :n] += (m[mine].T @ squares[mine]).reshape(horizon, n, n)
                    a[i, :, :, n] += y[mine].T @ x[mine]
        yield pd.DataFrame({"i": np.arange(a.size), "v": a.ravel()})

    a = np.zeros(count * horizon * n * (n + 1))
    for r in pool.select("x", "future", "mask", "cells").mapInPandas(work, "i int, v double").groupBy("i").agg(F.sum("v").alias("v")).collect():
        a[r["i"]] = r["v"]
    a = a.reshape(count, horizon, n, n + 1)
    w = np.linalg.solve(a[..., :n] + ridge * np.eye(n), a[..., n:])
    return w[..., 0].transpose(0, 2, 1)


def residual_counts(pool: DataFrame, weights: np.ndarray) -> DataFrame:
    """(cell, h, bin, n, squares): residuals of each cell's own windows, counted in bins."""
    ship(pool.sparkSession)
    count, _, horizon = weights.shape

    def work(batches):
        n, squares = np.zeros((count, horizon, BINS), np.int64), np.zeros((count, horizon, BINS))
        for b in batches:
            if len(b):
                x, y, m = _arrays(b)
                of = _of(b, count)
                for i in range(count):
                    e = y[of[:, i]] - x[of[:, i]] @ weights[i]
                    at = np.clip(((np.arcsinh(e) + REACH) * (BINS / (2 * REACH))).astype(int), 0, BINS - 1)
                    seen, at = m[of[:, i]] == 1, at + BINS * np.arange(horizon)
                    n[i] += np.bincount(at[seen], minlength=horizon * BINS).reshape(horizon, BINS)
                    squares[i] += np.bincount(at[seen], e[seen] ** 2, minlength=horizon * BINS).reshape(horizon, BINS)
        cell, h, k = np.nonzero(n)
        yield pd.DataFrame({"cell": cell, "h": h, "bin": k, "n": n[cell, h, k], "squares": squares[cell, h, k]})

    rows = pool.select("x", "future", "mask", "cells").mapInPandas(work, "cell int, h int, bin int, n long, squares double")
    return rows.groupBy("cell", "h", "bin").agg(F.sum("n").alias("n"), F.sum("squares").alias("squares"))


def offsets(pool: DataFrame, weights: np.ndarray, cells: list[Cell]) -> np.ndarray:
    """cells x levels x horizon: what each family adds to its point forecast for the quantiles.

    A linear target has no spread; the quantile target takes quantiles of its residuals, exact but for the width of
    a bin; the Gaussian target takes the quantiles of a normal of their mean square.
    """
    count, _, horizon = weights.shape
    out = np.zeros((count, len(LEVELS), horizon))
    if all(c.family == "linear" for c in cells):
        return out
    counts = residual_counts(pool, weights)
    own = Window.partitionBy("cell", "h")  # no more rows than bins
    upto = F.sum("n").over(own.orderBy("bin"))
    rows = counts.withColumns({"upto": upto, "all": F.sum("n").over(own), "square": F.sum("squares").over(own) / F.sum("n").over(own)})
    levels = F.explode(F.array(*(F.struct(F.lit(k).alias("k"), F.lit(q).alias("q")) for k, q in enumerate(LEVELS)))).alias("l")
    hit = rows.select("*", levels).where((F.col("upto") >= F.col("l.q") * F.col("all")) & (F.col("upto") - F.col("n") < F.col("l.q") * F.col("all")))
    inside = (F.col("l.q") * F.col("all") - F.col("upto") + F.col("n")) / F.col("n")
    for r in hit.select("cell", "h", "l.k", ((F.col("bin") + inside) * (2 * REACH / BINS) - REACH).alias("at"), "square").collect():
        family = cells[r["cell"]].family
        if family == "quantile":
            out[r["cell"], r["k"], r["h"]] = np.sinh(r["at"])
        elif family == "gaussian":
            out[r["cell"], r["k"], r["h"]] = NormalDist().inv_cdf(LEVELS[r["k"]]) * r["square"] ** 0.5
    return out


def judged(held: DataFrame, weights: np.ndarray, spread: np.ndarray) -> list[dict]:
    """For each cell the mean squared error, absolute error and doubled pinball loss (mean over levels) of the observed slots, in the context's size."""
    ship(held.sparkSession)
    count = len(weights)

    def work(batches):
        out = np.zeros((count, 4))
        q = np.array(LEVELS)[None, :, None]
        for b in batches:
            if len(b):
                x, y, m = _arrays(b)
                for i in range(count):
                    e = y - x @ weights[i]
                    d = e[:, None, :] - spread[i]
                    pinball = 2 * np.maximum(q * d, (q - 1) * d).mean(axis=1)
                    out[i] += m.sum(), (m * e * e).sum(), (m * np.abs(e)).sum(), (m * pinball).sum()
        yield pd.DataFrame({"cell": np.arange(count), **{k: out[:, j] for j, k in enumerate(("n", "se", "ae", "pl"))}})

    sums = held.select("x", "future", "mask").mapInPandas(work, "cell int, n double, se double, ae double, pl double")
    means = sums.groupBy("cell").agg(F.sum("n").alias("n"), *((F.try_divide(F.sum(k), F.sum("n"))).alias(k) for k in ("se", "ae", "pl")))
    return [r.asDict() for r in means.orderBy("cell").collect()]


def with_cells(pool: DataFrame, members: DataFrame) -> DataFrame:
    return keep(pool.join(members.hint("merge"), KEY), "cells")
