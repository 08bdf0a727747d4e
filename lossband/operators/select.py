"""Which windows stay: the middle of every source, other parts of the ranking, random and full baselines.

All rules read (source, series_id, origin, rfl, status) and use integers only. With alpha = p / q the count
rule keeps m = max(1, nearest(alpha n)) windows after leaving out (n - m) div 2 below; the CDF rule keeps
the rows whose share of scores not above lies between (1 - alpha) / 2 and (1 + alpha) / 2.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..schema import Alpha
from ..sources.tables import keep
from .rank import _by, cutoffs, distributed, ranked, scorable, tie_key

KEYS = ["source", "series_id", "origin"]


def kept(n: Column, alpha: Alpha) -> Column:
    return F.greatest(F.lit(1).cast("long"), F.floor((n * (2 * alpha.num) + alpha.den) / (2 * alpha.den)).cast("long"))


def skipped(n: Column, alpha: Alpha) -> Column:
    return F.floor((n - kept(n, alpha)) / 2).cast("long")


def by_count(n: Column, rank: Column, alpha: Alpha) -> Column:
    below = skipped(n, alpha)
    return (rank > below) & (rank <= below + kept(n, alpha))


def by_cdf(n: Column, rank: Column, alpha: Alpha) -> Column:
    p, q = alpha.num, alpha.den
    return (n * (q - p) <= rank * (2 * q)) & (rank * (2 * q) <= n * (q + p))


def cdf_ends(rows: DataFrame, alphas: list[Alpha], by) -> DataFrame:
    """(by, i, lo, hi) for each ratio: the CDF rule keeps the scores from ``lo`` on that lie below ``hi`` (null: all).

    The share of scores not above s grows with s, so the rule is a range of scores. Its ends are the scores at two
    ranks of ``rows`` (which has n and rank_key): rows of equal score need not meet for that.
    """
    by = _by(by)
    ends = []
    for i, a in enumerate(alphas):
        # Exact integer division, so that no rounding moves an end.
        first = F.greatest(F.expr(f"(n * {a.den - a.num} + {2 * a.den - 1}) div {2 * a.den}"), F.lit(1).cast("long"))
        after = F.expr(f"(n * {a.den + a.num}) div {2 * a.den}") + 1
        ends.append(F.struct(F.lit(i).alias("i"), first.alias("first"), after.alias("after")))
    goals = rows.select(*by, "rank_key", "rfl", F.explode(F.array(*ends)).alias("x")).where("rank_key in (x.first, x.after)")
    at = lambda c: F.max(F.when(F.col("rank_key") == F.col(f"x.{c}"), F.col("rfl")))
    return goals.groupBy(*by, F.col("x.i").alias("i")).agg(at("first").alias("lo"), at("after").alias("hi"))


def _by_scores(rows: DataFrame, alphas: list[Alpha], by) -> DataFrame:
    """``rows`` with ``i`` for each ratio whose CDF rule keeps them."""
    by = _by(by)
    rows = keep(rows, "ranked")
    ends = F.broadcast(cdf_ends(rows, alphas, by))  # a row a group and ratio
    met = rows.join(ends, by) if by else rows.crossJoin(ends)
    return met.where((F.col("rfl") >= F.col("lo")) & (F.col("hi").isNull() | (F.col("rfl") < F.col("hi")))).drop("lo", "hi")


def central(scores: DataFrame, alpha, by="source", rule: str = "count", method: str = "distributed") -> DataFrame:
    """The middle share of every group of ``by``, or of everything if that is None."""
    alpha = Alpha.of(alpha)
    rows = ranked(scores, by, method)
    return rows.where(by_count(F.col("n"), F.col("rank_key"), alpha)) if rule == "count" else _by_scores(rows, [alpha], by).drop("i")


def central_by_cutoffs(scores: DataFrame, alpha, by="source") -> DataFrame:
    """Same rows as ``central`` by count, without a sort of all scores: two cuts a group and a filter."""
    alpha, by = Alpha.of(alpha), _by(by)
    n = F.col("n")
    wanted = F.array(skipped(n, alpha) + 1, skipped(n, alpha) + kept(n, alpha))
    cuts = cutoffs(scores, wanted, by)
    place = lambda: F.struct("rfl", *tie_key(by))
    rows = scorable(scores)
    group = by or ["all"]
    if not by:
        rows, cuts = rows.withColumn("all", F.lit(0)), cuts.withColumn("all", F.lit(0))
    ends = cuts.groupBy(*group).agg(F.min(place()).alias("lo"), F.max(place()).alias("hi"))
    return rows.join(F.broadcast(ends), group).where(place().between(F.col("lo"), F.col("hi"))).select(*scores.columns)


def bottom(scores: DataFrame, alpha, by="source", method: str = "distributed") -> DataFrame:
    alpha = Alpha.of(alpha)
    return ranked(scores, by, method).where(F.col("rank_key") <= kept(F.col("n"), alpha))


def top(scores: DataFrame, alpha, by="source", method: str = "distributed") -> DataFrame:
    alpha = Alpha.of(alpha)
    return ranked(scores, by, method).where(F.col("rank_key") > F.col("n") - kept(F.col("n"), alpha))


def interval(scores: DataFrame, low, high, by="source", method: str = "distributed") -> DataFrame:
    """Rows whose rank r of n has low < r / n <= high."""
    low, high = Fraction(str(low)), Fraction(str(high))
    n, r = F.col("n"), F.col("rank_key")
    return ranked(scores, by, method).where((r * low.denominator > n * low.numerator) & (r * high.denominator <= n * high.numerator))


def sweep(scores: DataFrame, alphas, by="source", rule: str = "count", method: str = "distributed") -> DataFrame:
    """(alpha_num, alpha_den, key...): several ratios from one ranking."""
    rows = ranked(scores, by, method)
    alphas = [Alpha.of(a) for a in alphas]
    named = [F.struct(F.lit(a.num).alias("alpha_num"), F.lit(a.den).alias("alpha_den")) for a in alphas]
    if rule == "cdf":
        rows = _by_scores(rows, alphas, by).withColumn("a", F.element_at(F.array(*named), F.col("i") + 1))
        return rows.select("a.*", *scores.columns, "n", "rank_key")
    hits = F.array_compact(F.array(*(F.when(by_count(F.col("n"), F.col("rank_key"), a), x) for a, x in zip(alphas, named))))
    return rows.select(F.explode(hits).alias("a"), *scores.columns, "n", "rank_key").select("a.*", *scores.columns, "n", "rank_key")


def full(scores: DataFrame) -> DataFrame:
    return scorable(scores)


# ---- baselines ---------------------------------------------------------------------------------


def lcg(seed: int, *keys: str) -> Column:
    """Small arithmetic hash of integer columns that any SQL engine can repeat."""
    out = F.lit(seed * 69_621 % 2_147_483_647).cast("long")
    for k in keys:
        out = F.pmod(out * 48_271 + F.pmod(F.col(k).cast("long"), F.lit(2_147_483_647)) * 16_807 + 12_345, F.lit(2_147_483_647))
    return out


def _shuffled(scores: DataFrame, seed: int, hashed: Column | None) -> DataFrame:
    place = F.xxhash64(*KEYS, F.lit(seed)) if hashed is None else hashed
    return scorable(scores).withColumnRenamed("rfl", "score").withColumn("rfl", place)


def random_global(scores: DataFrame, alpha, seed: int = 0, hashed: Column | None = None) -> DataFrame:
    """As many windows of the whole pool as ``central`` keeps of it, in the order of a seeded hash; exact size."""
    alpha = Alpha.of(alpha)
    rows = distributed(_shuffled(scores, seed, hashed), None, ties=False)
    return rows.where(F.col("rank_key") <= kept(F.col("n"), alpha)).drop("rfl").withColumnRenamed("score", "rfl")


def random_stratified(scores: DataFrame, alpha, seed: int = 0, by="source", hashed: Column | None = None) -> DataFrame:
    alpha = Alpha.of(alpha)
    rows = distributed(_shuffled(scores, seed, hashed), by, ties=False)
    return rows.where(F.col("rank_key") <= kept(F.col("n"), alpha)).drop("rfl").withColumnRenamed("score", "rfl")


def random_bernoulli(scores: DataFrame, alpha, seed: int = 0) -> DataFrame:
    """Each window by itself, without a shuffle; the size is only about alpha n."""
    alpha = Alpha.of(alpha)
    return scorable(scores).where(F.pmod(F.xxhash64(*KEYS, F.lit(seed)), F.lit(1_000_003)) * alpha.den < F.lit(alpha.num) * 1_000_003)


def importance(scores: DataFrame, alpha, seed: int = 0, by="source") -> DataFrame:
    """Without replacement, with chances in proportion to the score: the smallest exponential times go first."""
    alpha = Alpha.of(alpha)
    u = (F.pmod(F.xxhash64(*KEYS, F.lit(seed)), F.lit(2**53)) + 1) / F.lit(float(2**53 + 1))
    rows = scorable(scores).withColumnRenamed("rfl", "score").withColumn("rfl", -F.log(u) / F.greatest(F.col("score").cast("double"), F.lit(1e-300)))
    return distributed(rows, by, ties=False).where(F.col("rank_key") <= kept(F.col("n"), alpha)).drop("rfl").withColumnRenamed("score", "rfl")


def share_report(scores: DataFrame, chosen: DataFrame, by: str = "source") -> DataFrame:
    """By source: windows before and after, and shares of the whole; sources that vanish keep a row."""
    before = scorable(scores).groupBy(by).agg(F.count("*").alias("n"))
    after = chosen.groupBy(by).agg(F.count("*").alias("kept"))
    rows = before.join(after, by, "left").select(by, "n", F.coalesce("kept", F.lit(0)).alias("kept"))
    # One row a source from here on: the sums over all of them are two numbers, added to every row.
    sums = rows.agg(F.sum("n").alias("all_n"), F.sum("kept").alias("all_kept"))
    rows = rows.crossJoin(F.broadcast(sums))
    return rows.select(by, "n", "kept", (F.col("n") / F.col("all_n")).alias("p_before"), F.try_divide("kept", "all_kept").alias("p_after"))
