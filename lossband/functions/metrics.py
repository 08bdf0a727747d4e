"""Accuracy of forecasts, agreement of scores, and diversity of what was kept."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..operators.rank import ranked, scorable
from ..sources.tables import keep

KEY = ["source", "series_id", "origin"]


def point_metrics(errors: DataFrame, by) -> DataFrame:
    """MSE and MAE over the rows of ``errors(…, e)`` with an error; ``by`` names the task."""
    return errors.where("e is not null").groupBy(*by).agg(F.count("*").alias("slots"), F.avg(F.col("e") * F.col("e")).alias("mse"), F.avg(F.abs("e")).alias("mae"))


def scaled_point_error(errors: DataFrame, insample: DataFrame, by) -> DataFrame:
    """Mean absolute error over that of seasonal differences in the training part; both by task."""
    a = errors.where("e is not null").groupBy(*by).agg(F.avg(F.abs("e")).alias("mae"))
    b = insample.where("e is not null").groupBy(*by).agg(F.avg(F.abs("e")).alias("scale"))
    return a.join(b, list(by)).select(*by, F.try_divide("mae", "scale").alias("spe"))


def relative(metrics: DataFrame, baseline: str, by=("task_id", "metric")) -> DataFrame:
    """``metrics(task_id, metric, model, value)`` divided by those of the model ``baseline``."""
    base = metrics.where(F.col("model") == baseline).select(*by, F.col("value").alias("base"))
    return metrics.join(base, list(by)).select(*by, "model", F.try_divide("value", "base").alias("ratio"))


def geomean(ratios: DataFrame, by=("metric", "model")) -> DataFrame:
    """Geometric mean over tasks; a ratio that is not above 0 counts as missing and is told."""
    return ratios.groupBy(*by).agg(F.exp(F.avg(F.when(F.col("ratio") > 0, F.log("ratio")))).alias("geomean"), F.count_if(F.col("ratio") > 0).alias("tasks"), F.count_if(F.coalesce(F.col("ratio"), F.lit(0.0)) <= 0).alias("left_out"))


def average_rank(scores: DataFrame, name: str, by=None) -> DataFrame:
    """Key and average rank: the mean of the ranks that rows of equal score take up."""
    rows = ranked(scores, by, ties=True)
    group = [by] if isinstance(by, str) else list(by or [])
    tied = Window.partitionBy(*group, "rfl")
    first = F.min("rank_key").over(tied)
    return rows.select(*KEY, ((F.col("rank_max") + first) / 2).alias(name))


def spearman(a: DataFrame, b: DataFrame, by=None) -> DataFrame:
    """Rank correlation over the windows that both can score; one row, or one a group."""
    # Joined and written once: both rankings and the samples that their ranges come from read it.
    pair = keep(scorable(a).select(*KEY, F.col("rfl").alias("a")).join(scorable(b).select(*KEY, F.col("rfl").alias("b")), KEY), "pair")
    rows = average_rank(pair.select(*KEY, F.col("a").alias("rfl")), "x", by).join(average_rank(pair.select(*KEY, F.col("b").alias("rfl")), "y", by), KEY)
    agg = (F.count("*").alias("windows"), F.corr("x", "y").alias("rho"))
    return rows.groupBy(by).agg(*agg) if by else rows.agg(*agg)


def spearman_matrix(scores: dict[str, DataFrame]) -> DataFrame:
    """(a, b, rho) for all pairs of references; each is ranked once, over the windows that all of them can score."""
    names = sorted(scores)
    rows = keep(reduce(lambda p, q: p.join(q, KEY), (scorable(scores[n]).select(*KEY, F.col("rfl").alias(n)) for n in names)), "matrix")
    table = reduce(lambda p, q: p.join(q, KEY), (average_rank(rows.select(*KEY, F.col(n).alias("rfl")), n) for n in names))
    pairs = [(a, b) for i, a in enumerate(names) for b in names[i + 1 :]]
    got = table.agg(*(F.corr(a, b).alias(f"{a}|{b}") for a, b in pairs))
    return got.unpivot([], [f"{a}|{b}" for a, b in pairs], "pair", "rho").select(F.split("pair", r"\|")[0].alias("a"), F.split("pair", r"\|")[1].alias("b"), "rho")


def overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """Sizes of two selections, of what they share, and the share of their union."""
    x = a.select(*KEY).withColumn("x", F.lit(1))
    y = b.select(*KEY).withColumn("y", F.lit(1))
    both = x.join(y, KEY, "full")
    out = both.agg(F.count("x").alias("a"), F.count("y").alias("b"), F.count_if(F.col("x").isNotNull() & F.col("y").isNotNull()).alias("both"), F.count("*").alias("either"))
    return out.withColumn("jaccard", F.try_divide("both", "either"))


def diversity(report: DataFrame) -> DataFrame:
    """From a share report: sources, vanished sources, smallest share kept, distance of the shares, their entropy."""
    p, q = F.col("p_before"), F.coalesce("p_after", F.lit(0.0))
    return report.agg(
        F.count("*").alias("sources"), F.count_if(F.col("kept") == 0).alias("vanished"), F.min(F.col("kept") / F.col("n")).alias("least_retention"), F.max(F.col("kept") / F.col("n")).alias("most_retention"),
        (F.sum(F.abs(p - q)) / 2).alias("total_variation"), (-F.sum(F.when(q > 0, q * F.log(q)).otherwise(0.0))).alias("entropy"),
    )


def margins(metrics: DataFrame, of: str, against: str) -> DataFrame:
    """Absolute and relative gain of model ``of`` over ``against``; positive is better, lower values being better."""
    wide = metrics.where(F.col("model").isin(of, against)).groupBy("task_id", "metric").pivot("model", [of, against]).agg(F.first("value"))
    a, b = F.col(f"`{of}`"), F.col(f"`{against}`")
    return wide.select("task_id", "metric", (b - a).alias("absolute"), F.try_divide(100 * (b - a), b).alias("percent"))


def rounded(df: DataFrame, digits: int, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(F.col(n), digits) for n in names})


def weighted_quantile_loss(rows: DataFrame, levels: dict[str, float], by) -> DataFrame:
    """Ratio of sums by task: doubled pinball losses of the columns ``levels`` over the absolute truth ``y``, mean of levels."""

    def part(q: str, level: float) -> Column:
        e = F.col("y") - F.col(q)
        return F.sum(2 * F.greatest(e * level, e * (level - 1)))

    total = sum((part(q, t) for q, t in levels.items()), F.lit(0.0)) / len(levels)
    return rows.where("y is not null").groupBy(*by).agg(F.try_divide(total, F.sum(F.abs("y"))).alias("wql"))
