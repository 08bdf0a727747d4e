"""Selections, baselines, reports."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import functions as F

from ..functions import metrics as mt
from ..operators import select as sel
from ..operators.grid import CORPORA
from ..operators.rank import cutoffs, distributed, local
from ..schema import Alpha
from ..sources.tables import keep
from .common import naive, plain, scores_sql

ALPHAS = {"40": "2/5", "60": "3/5", "80": "4/5"}
KEYS = ["source", "series_id", "origin"]


def _ranks(df):
    return df.select(*KEYS, "n", "rank_key", "rank_max")


def select_ties(spark, sf):
    """Weekly orders are full of equal scores on small data: both rules, kept windows by source."""
    scores = naive(spark, sf, "orders_weekly")
    a = sel.central(scores, "3/5", rule="count").groupBy("source").agg(F.count("*").alias("by_count"))
    b = sel.central(scores, "3/5", rule="cdf").groupBy("source").agg(F.count("*").alias("by_cdf"))
    return a.join(b, "source", "full")


def select_tiny_source(spark, sf):
    """One window a source: counting keeps it, the CDF rule drops it."""
    scores = naive(spark, sf).where("origin = 100")
    a = sel.central(scores, "4/5", rule="count").agg(F.count("*").alias("by_count"))
    b = sel.central(scores, "4/5", rule="cdf").agg(F.count("*").alias("by_cdf"))
    return a.crossJoin(b)  # one row each


def select_strat_two_keys(spark, sf):
    scores = naive(spark, sf).withColumn("day", F.pmod(F.floor(F.col("origin") / 24), F.lit(7)))
    return plain(sel.central(scores, "4/5", by=["source", "day"]))


def lcg_scores(spark, sf):
    return naive(spark, sf, "supplier_weekly").withColumn("id", F.col("series_id").cast("long"))


def share_report(rule, by):
    def run(spark, sf):
        scores = naive(spark, sf)
        return mt.rounded(sel.share_report(scores, sel.central(scores, "3/5", by=by, rule=rule)), 9, "p_before", "p_after")

    return run


def transfer_overlap(spark, sf):
    from ..operators.scoring import LastValue, score
    from .common import grid

    c = CORPORA["supplier_weekly"]
    a = naive(spark, sf, "supplier_weekly")
    b = score(grid(spark, sf, "supplier_weekly"), LastValue(), c.context, c.horizon)
    return mt.rounded(mt.overlap(sel.central(a, "4/5"), sel.central(b, "4/5")), 9, "jaccard")


def retention_grid_sizes(spark, sf):
    """Windows kept in every cell of the retention grid; equal sizes are what makes random a fair control.

    Each corpus is scored once, and each ranking serves all ratios.
    """
    out = None
    for name in ("events_hourly", "supplier_weekly", "embedding_axis"):
        scores = keep(naive(spark, sf, name), "scores")
        hashed = scores.withColumn("rfl", F.when(F.col("rfl").isNotNull(), F.xxhash64(*KEYS).cast("double")))
        for how, rows in (("central", sel.sweep(scores, ALPHAS.values())), ("global", sel.sweep(scores, ALPHAS.values(), by=None)), ("random_stratified", sel.sweep(hashed, ALPHAS.values()))):
            one = rows.groupBy((F.col("alpha_num") * 100 / F.col("alpha_den")).cast("int").alias("percent")).agg(F.count("*").alias("kept")).select(F.lit(name).alias("corpus"), F.lit(how).alias("strategy"), "percent", "kept")
            out = one if out is None else out.unionByName(one)
    return out


def region_loss_summary(spark, sf):
    """Scores of the lowest, middle and highest part of every source, from one ranking."""
    rows = keep(distributed(naive(spark, sf, "supplier_weekly")), "ranked")
    n, r, out = F.col("n"), F.col("rank_key"), None
    for label in ("40", "80"):
        a = Alpha.of(ALPHAS[label])
        for name, test in (("bottom", r <= sel.kept(n, a)), ("top", r > n - sel.kept(n, a)), ("central", sel.by_count(n, r, a))):
            one = rows.where(test).agg(F.lit(name).alias("region"), F.lit(int(label)).alias("percent"), F.count("*").alias("windows"), F.min("rfl").alias("least"), F.max("rfl").alias("most"), F.round(F.avg("rfl"), 6).alias("mean"))
            out = one if out is None else out.unionByName(one)
    return out


def diversity_strat_vs_global(spark, sf):
    """Shares of sources under both rules, each corpus scored once and ranked once by each rule."""
    out = None
    for name in ("events_hourly", "supplier_weekly"):
        scores = keep(naive(spark, sf, name), "scores")
        for how, by in (("stratified", "source"), ("global", None)):
            rows = keep(distributed(scores, by), "ranked")
            for label, alpha in ALPHAS.items():
                d = mt.diversity(sel.share_report(scores, rows.where(sel.by_count(F.col("n"), F.col("rank_key"), Alpha.of(alpha)))))
                one = mt.rounded(d, 6, "least_retention", "most_retention", "total_variation", "entropy").select(F.lit(name).alias("corpus"), F.lit(how).alias("strategy"), F.lit(int(label)).alias("percent"), "*")
                out = one if out is None else out.unionByName(one)
    return out


def case_windows(spark, sf):
    """Windows of least, middle and largest score of every source."""
    rows = distributed(naive(spark, sf))
    which = F.when(F.col("rank_key") == 1, "least").when(F.col("rank_key") == F.col("n"), "largest").when(F.col("rank_key") == F.floor((F.col("n") + 1) / 2), "middle")
    return plain(rows.withColumn("which", which).where("which is not null")).join(rows.select(*KEYS, which.alias("which")), KEYS)


def cutoff_rows(spark, sf):
    n = F.col("n")
    return cutoffs(naive(spark, sf), F.array(F.floor((n + 9) / 10), F.floor((n + 1) / 2), n)).select("source", "n", "rank", "rfl", "series_id", "origin")


def importance_sizes(spark, sf):
    return sel.importance(naive(spark, sf), "2/5").groupBy("source").agg(F.count("*").alias("kept"))


def nested(spark, sf):
    """Windows of a smaller selection that a larger one lacks: none, for both rules."""
    scores = naive(spark, sf)
    out = None
    for rule in ("count", "cdf"):
        small, large = (sel.central(scores, a, rule=rule).select(*KEYS) for a in ("2/5", "3/5"))
        one = small.exceptAll(large).agg(F.lit(rule).alias("rule"), F.count("*").alias("lacking"))
        out = one if out is None else out.unionByName(one)
    return out


QUERIES = {
    "percentile_rank": lambda s, d: distributed(naive(s, d)).select(*KEYS, (F.col("rank_max") / F.col("n")).alias("r")),
    "rank_distributed": lambda s, d: _ranks(distributed(naive(s, d))),
    "rank_local": lambda s, d: _ranks(local(naive(s, d))),
    "rank_global": lambda s, d: _ranks(distributed(naive(s, d), None)),
    "rank_cutoffs": cutoff_rows,
    "select_central_by_cutoffs": lambda s, d: plain(sel.central_by_cutoffs(naive(s, d), "4/5")),
    "select_global_count_80": lambda s, d: plain(sel.central(naive(s, d), "4/5", by=None)),
    "select_interval_20_70": lambda s, d: plain(sel.interval(naive(s, d), "0.2", "0.7")),
    "select_sweep": lambda s, d: sel.sweep(naive(s, d), ["2/5", "3/5", "4/5"]).select("alpha_num", "alpha_den", *KEYS),
    "select_strat_two_keys": select_strat_two_keys,
    "select_ties": select_ties,
    "select_tiny_source": select_tiny_source,
    "select_full": lambda s, d: plain(sel.full(naive(s, d, "orders_weekly"))),
    "select_random_lcg": lambda s, d: plain(sel.random_global(lcg_scores(s, d), "2/5", hashed=sel.lcg(3, "id", "origin"))),
    "select_random_strat_lcg": lambda s, d: plain(sel.random_stratified(lcg_scores(s, d), "2/5", hashed=sel.lcg(3, "id", "origin"))),
    "select_random_global": lambda s, d: plain(sel.random_global(naive(s, d), "2/5")),
    "select_random_stratified": lambda s, d: plain(sel.random_stratified(naive(s, d), "2/5")),
    "select_random_bernoulli": lambda s, d: plain(sel.random_bernoulli(naive(s, d), "2/5")),
    "select_importance": lambda s, d: plain(sel.importance(naive(s, d), "2/5")),
    "importance_sizes": importance_sizes,
    "select_error_norm_top": lambda s, d: sel.top(naive(s, d).withColumn("rfl", F.sqrt(F.col("rfl") * F.col("m"))), "2/5").select(*KEYS),
    "select_nested": nested,
    "share_report_strat": share_report("count", "source"),
    "share_report_global": share_report("count", None),
    "share_report_cdf": share_report("cdf", "source"),
    "transfer_overlap": transfer_overlap,
    "retention_grid_sizes": retention_grid_sizes,
    "region_loss_summary": region_loss_summary,
    "diversity_strat_vs_global": diversity_strat_vs_global,
    "case_windows": case_windows,
}


def _ranked_sql(name="events_hourly", by="source", scores=None):
    part = f"partition by {by}" if by else ""
    tie = "series_id, origin" if by and "source" in by else "source, series_id, origin"
    return f"""{scores or scores_sql(name)}, ranked as (select *, count(*) over ({part}) as n, row_number() over ({part} order by rfl, {tie}) as rank_key, count(*) over ({part} order by rfl range between unbounded preceding and current row) as rank_max from ok)"""


def _kept(p, q):
    return f"greatest(1, (2 * {p} * n + {q}) // (2 * {q}))"


def _central(rule, alpha):
    p, q = Fraction(alpha).numerator, Fraction(alpha).denominator
    if rule == "cdf":
        return f"{q - p} * n <= {2 * q} * rank_max and {2 * q} * rank_max <= {q + p} * n"
    below = f"((n - {_kept(p, q)}) // 2)"
    return f"rank_key > {below} and rank_key <= {below} + {_kept(p, q)}"


_OUT = "source, series_id, origin, m, rfl"
_LCG = "(((cast({a} as bigint) * 48271 + cast(series_id as bigint) * 16807 + 12345) % 2147483647) * 48271 + origin * 16807 + 12345) % 2147483647".format(a=3 * 69621 % 2147483647)


def _share_sql(where, by="source"):
    return f"""with {_ranked_sql(by=by)}, a as (select source, count(*) as n, count(*) filter ({where}) as kept from (select * from ranked) r group by 1)
        select source, n, kept, round(n / cast(sum(n) over () as double), 9) as p_before, round(kept / cast(sum(kept) over () as double), 9) as p_after from a"""


def _sizes_sql():
    cells = []
    for name in ("events_hourly", "supplier_weekly", "embedding_axis"):
        for label, alpha in ALPHAS.items():
            p, q = Fraction(alpha).numerator, Fraction(alpha).denominator
            x = f"with {scores_sql(name)}, a as (select source, count(*) as n from ok group by 1)"
            for how in ("central", "random_stratified"):
                cells.append(f"(({x} select '{name}' as corpus, '{how}' as strategy, {label} as percent, cast(sum({_kept(p, q)}) as bigint) as kept from a))")
            cells.append(f"(({x}, b as (select sum(n) as n from a) select '{name}', 'global', {label}, cast({_kept(p, q)} as bigint) from b))")
    return " union all ".join(f"select * from {c}" for c in cells)


def _regions_sql():
    x, parts = _ranked_sql("supplier_weekly"), []
    for label in ("40", "80"):
        p, q = Fraction(ALPHAS[label]).numerator, Fraction(ALPHAS[label]).denominator
        for name, where in (("bottom", f"rank_key <= {_kept(p, q)}"), ("top", f"rank_key > n - {_kept(p, q)}"), ("central", _central("count", ALPHAS[label]))):
            parts.append(f"select '{name}' as region, {label} as percent, count(*) as windows, min(rfl) as least, max(rfl) as most, round(avg(rfl), 6) as mean from ranked where {where}")
    return f"with {x} " + " union all ".join(parts)


def _diversity_sql():
    parts = []
    for name in ("events_hourly", "supplier_weekly"):
        for label, alpha in ALPHAS.items():
            for how, by in (("stratified", "source"), ("global", None)):
                parts.append(
                    f"""select * from (with {_ranked_sql(name, by)}, a as (select source, count(*) as n, count(*) filter ({_central('count', alpha)}) as kept from ranked group by 1),
                    b as (select *, n / cast(sum(n) over () as double) as p, kept / cast(sum(kept) over () as double) as q from a)
                    select '{name}' as corpus, '{how}' as strategy, {label} as percent, count(*) as sources, count(*) filter (kept = 0) as vanished, round(min(kept / cast(n as double)), 6) as least_retention, round(max(kept / cast(n as double)), 6) as most_retention,
                    round(sum(abs(p - q)) / 2, 6) as total_variation, round(-sum(case when q > 0 then q * ln(q) else 0 end), 6) as entropy from b)"""
                )
    return " union all ".join(parts)


_R = _ranked_sql()
ORACLES = {
    "percentile_rank": f"with {scores_sql('events_hourly')} select source, series_id, origin, cume_dist() over (partition by source order by rfl) as r from ok",
    "rank_distributed": f"with {_R} select source, series_id, origin, n, rank_key, rank_max from ranked",
    "rank_local": f"with {_R} select source, series_id, origin, n, rank_key, rank_max from ranked",
    "rank_global": f"with {_ranked_sql(by=None)} select source, series_id, origin, n, rank_key, rank_max from ranked",
    "rank_cutoffs": f"with {_R} select source, n, rank_key as rank, rfl, series_id, origin from ranked where rank_key in ((n + 9) // 10, (n + 1) // 2, n)",
    "select_central_by_cutoffs": f"with {_R} select {_OUT} from ranked where {_central('count', '4/5')}",
    "select_global_count_80": f"with {_ranked_sql(by=None)} select {_OUT} from ranked where {_central('count', '4/5')}",
    "select_interval_20_70": f"with {_R} select {_OUT} from ranked where rank_key * 5 > n and rank_key * 10 <= 7 * n",
    "select_sweep": f"with {_R} " + " union all ".join(f"select {a[0]} as alpha_num, {a[2]} as alpha_den, source, series_id, origin from ranked where {_central('count', a)}" for a in ALPHAS.values()),
    "select_strat_two_keys": f"with {_ranked_sql(by='source, (origin // 24) % 7')} select {_OUT} from ranked where {_central('count', '4/5')}",
    "select_ties": f"with {_ranked_sql('orders_weekly')}, a as (select source, count(*) filter ({_central('count', '3/5')}) as by_count, count(*) filter ({_central('cdf', '3/5')}) as by_cdf from ranked group by 1) select source, nullif(by_count, 0) as by_count, nullif(by_cdf, 0) as by_cdf from a",
    "select_tiny_source": f"with {scores_sql('events_hourly')} select count(*) as by_count, cast(0 as bigint) as by_cdf from ok where origin = 100",
    "select_full": f"with {scores_sql('orders_weekly')} select * from ok",
    "select_random_lcg": f"with {scores_sql('supplier_weekly')}, r as (select *, count(*) over () as n, row_number() over (order by {_LCG}, source, series_id, origin) as k from ok) select {_OUT} from r where k <= {_kept(2, 5)}",
    "select_random_strat_lcg": f"with {scores_sql('supplier_weekly')}, r as (select *, count(*) over (partition by source) as n, row_number() over (partition by source order by {_LCG}, series_id, origin) as k from ok) select {_OUT} from r where k <= {_kept(2, 5)}",
    "importance_sizes": f"with {scores_sql('events_hourly')}, a as (select source, count(*) as n from ok group by 1) select source, cast({_kept(2, 5)} as bigint) as kept from a",
    "select_error_norm_top": f"with {_ranked_sql(scores=scores_sql('events_hourly').replace('ok as (select * from scores', 'ok as (select source, series_id, origin, m, sqrt(rfl * m) as rfl from scores'))} select source, series_id, origin from ranked where rank_key > n - {_kept(2, 5)}",
    "select_nested": "select 'count' as rule, cast(0 as bigint) as lacking union all select 'cdf', 0",
    "share_report_strat": _share_sql(_central("count", "3/5")),
    "share_report_global": _share_sql(_central("count", "3/5"), None),
    "share_report_cdf": _share_sql(_central("cdf", "3/5")),
    "retention_grid_sizes": _sizes_sql(),
    "region_loss_summary": _regions_sql(),
    "diversity_strat_vs_global": _diversity_sql(),
    "case_windows": f"with {_R} select {_OUT}, case when rank_key = 1 then 'least' when rank_key = n then 'largest' else 'middle' end as which from ranked where rank_key in (1, n, (n + 1) // 2)",
}

for _label, _alpha in ALPHAS.items():
    for _rule in ("count", "cdf"):
        QUERIES[f"select_strat_{_rule}_{_label}"] = lambda s, d, a=_alpha, r=_rule: plain(sel.central(naive(s, d), a, rule=r))
        ORACLES[f"select_strat_{_rule}_{_label}"] = f"with {_R} select {_OUT} from ranked where {_central(_rule, _alpha)}"
    QUERIES[f"select_global_cdf_{_label}"] = lambda s, d, a=_alpha: plain(sel.central(naive(s, d), a, by=None, rule="cdf"))
    ORACLES[f"select_global_cdf_{_label}"] = f"with {_ranked_sql(by=None)} select {_OUT} from ranked where {_central('cdf', _alpha)}"
    if _label != "60":
        _p, _q = Fraction(_alpha).numerator, Fraction(_alpha).denominator
        QUERIES[f"select_bottom_{_label}"] = lambda s, d, a=_alpha: plain(sel.bottom(naive(s, d), a))
        QUERIES[f"select_top_{_label}"] = lambda s, d, a=_alpha: plain(sel.top(naive(s, d), a))
        ORACLES[f"select_bottom_{_label}"] = f"with {_R} select {_OUT} from ranked where rank_key <= {_kept(_p, _q)}"
        ORACLES[f"select_top_{_label}"] = f"with {_R} select {_OUT} from ranked where rank_key > n - {_kept(_p, _q)}"
