"""Accuracy, agreement, theory, experiments, and the text, conversation and page analogues."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import metrics as mt
from ..functions.loss import MSE
from ..operators import select as sel
from ..operators import synth
from ..operators import windows as w
from ..operators.grid import CORPORA
from ..operators.rank import distributed
from ..operators.scoring import SCALINGS, ContextGaussian, Drift, LastValue, MovingMean, SeasonalNaive, amortisation, score
from ..plans import experiment as ex
from ..plans import target as tg
from ..plans import text as tx
from ..plans import theory as th
from ..sources.tables import keep, load
from .common import cells_sql, grid, keys_sql, naive, scores_sql
from .selection import _LCG

S = CORPORA["supplier_weekly"]

def region_errors(spark, sf):
    """(task_id, metric, model, value): held-out errors, by source and share, of a target trained on each region of the ranking.

    The target has one coefficient, in whole thousandths: what the value a season before is multiplied by. It is fitted by
    least squares on the futures of a region's windows, so all sums are integers and each error is one division.
    """
    at, ends = Window.partitionBy("source", "series_id").orderBy("t"), (S.context, S.context + S.horizon - 1)
    pairs = grid(spark, sf, S.name).withColumn("b", F.lag("y", S.season).over(at))
    seen = F.col("y").isNotNull() & F.col("b").isNotNull()
    pairs = keep(pairs.select("source", "series_id", "t", F.when(seen, F.col("y")).alias("y"), F.when(seen, F.col("b")).alias("b")), "pairs")
    ahead = lambda v: F.coalesce(F.sum(v).over(at.rowsBetween(*ends)), F.lit(0))
    sums = pairs.select("source", "series_id", F.col("t").alias("origin"), ahead(F.col("y") * F.col("b")).alias("yb"), ahead(F.col("b") * F.col("b")).alias("bb"))
    scores = keep(naive(spark, sf, S.name), "scores")
    drawn = scores.withColumn("id", F.col("series_id").cast("long")).withColumn("rfl", F.when(F.col("rfl").isNotNull(), sel.lcg(3, "id", "origin").cast("double"))).drop("id")
    n, rank, chosen = F.col("n"), F.col("rank_key"), None
    for rows, kinds in ((scores, ("bottom", "top", "central")), (drawn, ("random",))):
        hits = []
        for percent in (40, 80):
            alpha = sel.Alpha.of(f"{percent}/100")
            test = {"bottom": rank <= sel.kept(n, alpha), "random": rank <= sel.kept(n, alpha), "top": rank > n - sel.kept(n, alpha), "central": sel.by_count(n, rank, alpha)}
            hits += [F.when(test[k], F.struct(F.lit(k).alias("model"), F.lit(percent).alias("percent"))) for k in kinds]
        one = distributed(rows, ties=False).select("source", "series_id", "origin", F.array_compact(F.array(*hits)).alias("hits"))
        chosen = one if chosen is None else chosen.unionByName(one)
    # The keys grow with the data, so they are merged.
    met = sums.join(chosen.hint("merge"), ["source", "series_id", "origin"]).select("source", "yb", "bb", F.explode("hits").alias("x"))
    fitted = met.groupBy("source", "x.model", "x.percent").agg(F.sum("yb").alias("yb"), F.sum("bb").alias("bb"))
    fitted = fitted.select("source", "model", "percent", F.expr("(2000 * yb + bb) div nullif(2 * bb, 0)").alias("k"))
    e = 1000 * F.col("y") - F.col("k") * F.col("b")
    held = pairs.where((F.col("t") >= S.length - S.horizon) & F.col("y").isNotNull()).join(F.broadcast(fitted), "source")  # eight rows a source
    errors = held.groupBy("source", "model", "percent").agg(F.count("*").alias("n"), F.sum(e * e).alias("se"), F.sum(F.abs(e)).alias("ae"))
    both = F.map_from_arrays(F.array(F.lit("mse"), F.lit("mae")), F.array(F.col("se").cast("double") / F.col("n") / 1e6, F.col("ae").cast("double") / F.col("n") / 1e3))
    return errors.select(F.concat_ws("/", "source", "percent").alias("task_id"), "model", F.explode(both).alias("metric", "value"))


def margins_table(spark, sf):
    return mt.rounded(mt.margins(region_errors(spark, sf), "central", "random"), 6, "absolute", "percent").where("absolute is not null")


def central_counts(spark, sf):
    """How often the central region is strictly best, tied for best, or beaten among the four regions."""
    rows = region_errors(spark, sf).withColumn("others", F.min(F.when(F.col("model") != "central", F.col("value"))).over(Window.partitionBy("task_id", "metric")))
    rows = rows.where("model = 'central'").withColumn("percent", F.split("task_id", "/")[1].cast("int"))
    return rows.groupBy("percent").agg(F.count_if(F.col("value") < F.col("others")).alias("best"), F.count_if(F.col("value") == F.col("others")).alias("tied"), F.count_if(F.col("value") > F.col("others")).alias("beaten"))


# ---- forecasts of the held-out horizon by simple models, as rows of errors --------------------------


def held_errors(spark, sf, name="supplier_weekly"):
    """(source, model, y, e) on the last horizon of each series: seasonal naive and last value."""
    c = CORPORA[name]
    at = Window.partitionBy("source", "series_id").orderBy("t")
    last = F.last(F.when(F.col("t") < c.length - c.horizon, F.col("y")), ignorenulls=True).over(at.rowsBetween(Window.unboundedPreceding, 0))
    rows = grid(spark, sf, name).select("source", "y", "t", F.lag("y", c.season).over(at).alias("snaive"), last.alias("last"))
    rows = rows.where(F.col("t") >= c.length - c.horizon).select("source", "y", F.explode(F.map_from_arrays(F.array(F.lit("snaive"), F.lit("last")), F.array("snaive", "last"))).alias("model", "f"))
    return rows.select("source", "model", "y", (F.col("y") - F.col("f")).alias("e"))


def insample(spark, sf, name="supplier_weekly"):
    c = CORPORA[name]
    return SeasonalNaive(c.season).error(grid(spark, sf, name), 1).where(F.col("t") < c.length - c.horizon).select("source", F.col("e1").alias("e"))


def budget_report(spark, sf):
    """What the steps of a run see of the windows that three ratios keep of every source."""
    n, spec = F.col("n"), tg.TrainSpec()
    per = naive(spark, sf, S.name).where("status = 'ok'").groupBy("source").agg(F.count("*").alias("n"))
    ratios = F.explode(F.array(*(F.struct(F.lit(p).alias("percent"), sel.kept(n, sel.Alpha.of(f"{p}/100")).alias("kept")) for p in (40, 60, 80))))
    rows = per.select("source", ratios.alias("r")).select("source", "r.percent", "r.kept")
    drawn = F.lit(spec.steps * spec.batch).cast("long")
    return rows.select("source", "percent", "kept", F.lit(spec.steps).alias("steps"), F.lit(spec.batch).alias("batch"), drawn.alias("drawn"), F.least(drawn, F.col("kept")).alias("distinct"), (drawn / F.col("kept")).alias("epochs"))


def eval_spe(spark, sf):
    errors = held_errors(spark, sf)
    return mt.rounded(mt.scaled_point_error(errors, insample(spark, sf).crossJoin(F.broadcast(spark.createDataFrame([("snaive",), ("last",)], "model string"))), ["source", "model"]), 6, "spe")


def long_metrics(spark, sf):
    m = mt.point_metrics(held_errors(spark, sf), ["source", "model"])
    return m.select(F.col("source").alias("task_id"), "model", F.explode(F.map_from_arrays(F.array(F.lit("mse"), F.lit("mae")), F.array("mse", "mae"))).alias("metric", "value"))


def eval_prob_score(spark, sf):
    """Weighted quantile loss of the seasonal naive value as every quantile, with source offsets in fixed steps."""
    c = S
    at = Window.partitionBy("source", "series_id").orderBy("t")
    rows = grid(spark, sf, S.name).select("source", "t", "y", F.lag("y", c.season).over(at).alias("b")).where((F.col("t") >= c.length - c.horizon) & F.col("b").isNotNull())
    rows = rows.select("source", "y", (F.col("b") - 10).alias("q1"), F.col("b").alias("q5"), (F.col("b") + 10).alias("q9"))
    return mt.rounded(mt.weighted_quantile_loss(rows, {"q1": 0.1, "q5": 0.5, "q9": 0.9}, ["source"]), 6, "wql")


def two_scores(spark, sf):
    return naive(spark, sf, S.name), score(grid(spark, sf, S.name), LastValue(), S.context, S.horizon)


def spearman_cross(spark, sf):
    cells = grid(spark, sf, S.name)
    tables = {r.id: score(cells, r, S.context, S.horizon) for r in (SeasonalNaive(S.season), LastValue(), MovingMean(12), Drift(), ContextGaussian())}
    return mt.rounded(mt.spearman_matrix({k: v.withColumn("rfl", F.round("rfl", 4)) for k, v in tables.items()}), 5, "rho")


def spearman_sizes(spark, sf):
    """Three sizes of the linear family: their scores rank windows alike."""
    return mt.rounded(mt.spearman_matrix(ex.score_all(spark, sf, S.name, ("linear_mini", "linear_small", "linear_base"))), 6, "rho")


# ---- theory ------------------------------------------------------------------------------------


def _gradient_rows(spark, sf):
    rows = th.last_features(grid(spark, sf, S.name), 3, S.context, 4)
    x = F.col("x")
    last = F.array(*(x[1] for _ in range(4)))
    return th.window_gradient(th.residuals(rows, last), x)


#: The bounds, each checked for every window.
CHECKS = {"gradient_identity": th.gradient_bounds, "gradient_bound_rank1": lambda rows: th.rank_one_bounds(rows, F.array(*(F.lit(float(v)) for v in (1, 2, 3, 4)))), "self_bounding": th.self_bound}


def _ok(rows):
    return rows.agg(F.count("*").alias("windows"), F.count_if(~F.col("ok")).alias("violations"))


def gradient_alignment(spark, sf):
    rows = th.alignment(_gradient_rows(spark, sf))
    return rows.groupBy("source").agg(F.count("*").alias("windows"), F.round(F.avg("inner"), 2).alias("mean_inner"))


def alignment_by_rank(spark, sf):
    rows = th.alignment(_gradient_rows(spark, sf)).withColumn("rfl", 2 * F.col("half_mse"))
    return th.by_decile(rows, "inner")


def planted_mix(spark, sf):
    """Kinds of planted windows among those that each rule keeps; the middle should hold more learnable ones."""
    cells = synth.planted(spark)
    kinds = cells.select("source", "series_id", "kind").distinct()
    scores = score(cells.drop("kind"), SeasonalNaive(16), 64, 16)
    out = None
    for k, rows in ex.strategies(scores, "2/5").items():
        one = rows.join(kinds, ["source", "series_id"]).groupBy("kind").agg(F.count("*").alias("windows")).withColumn("strategy", F.lit(k))
        out = one if out is None else out.unionByName(one)
    return out


# ---- analogues -----------------------------------------------------------------------------------


def doc_rfl(spark, sf):
    return tx.score(load(spark, sf, "documents"), tx.unigram(load(spark, sf, "benchmark")))


def doc_select_quality(spark, sf):
    """Share of good documents among the middle of every source and among the rest."""
    scores = doc_rfl(spark, sf).withColumn("rfl", F.round("rfl", 9))
    chosen = sel.central(scores, "3/5").select(F.col("series_id").cast("long").alias("doc_id")).withColumn("kept", F.lit(1))
    rows = scores.where("status = 'ok'").select(F.col("series_id").cast("long").alias("doc_id")).join(chosen, "doc_id", "left").join(load(spark, sf, "labels"), "doc_id")
    return rows.groupBy((F.col("kept").isNotNull()).alias("kept")).agg(F.count("*").alias("labelled"), F.round(F.avg("quality"), 6).alias("good"))


def conv_windows(spark, sf):
    """Two turns of context and the reply."""
    at = Window.partitionBy("conv_id").orderBy("turn")
    rows = load(spark, sf, "conversations").select("conv_id", "turn", "role", F.length("text").alias("reply_chars"), F.sum(F.length("text")).over(at.rowsBetween(-2, -1)).alias("context_chars"), F.count("*").over(at.rowsBetween(-2, -1)).alias("context_turns"))
    return rows.where("context_turns = 2")


def page_hosts(spark, sf):
    rows = load(spark, sf, "pages").select(F.regexp_extract("url", "://([^/?#]*)", 1).alias("source"), F.length("html").alias("n"))
    return rows.groupBy("source").agg(F.count("*").alias("pages"), F.sum("n").alias("chars"))


def zero_shot(spark, sf):
    """Errors of untrained forecasters on the last horizon of every task of the suite, relative to the seasonal naive one."""
    return mt.rounded(mt.relative(ex.suite_errors(spark, sf), "snaive"), 6, "ratio")


def zero_shot_mean(spark, sf):
    return mt.rounded(mt.geomean(mt.relative(ex.suite_errors(spark, sf), "snaive")), 5, "geomean")


QUERIES = {
    "eval_mse": lambda s, d: mt.rounded(mt.point_metrics(held_errors(s, d), ["source", "model"]).select("source", "model", "slots", "mse"), 4, "mse"),
    "eval_mae": lambda s, d: mt.rounded(mt.point_metrics(held_errors(s, d), ["source", "model"]).select("source", "model", "slots", "mae"), 6, "mae"),
    "eval_spe": eval_spe,
    "eval_relative": lambda s, d: mt.rounded(mt.relative(long_metrics(s, d), "snaive"), 6, "ratio"),
    "eval_geomean": lambda s, d: mt.rounded(mt.geomean(mt.relative(long_metrics(s, d), "snaive")), 6, "geomean"),
    "eval_prob_score": eval_prob_score,
    "eval_512_96_windows": lambda s, d: w.window_keys(w.lengths(grid(s, d)), 512, 96).groupBy("source").agg(F.count("*").alias("windows")),
    "spearman_pair": lambda s, d: mt.rounded(mt.spearman(*two_scores(s, d)), 6, "rho"),
    "spearman_per_source": lambda s, d: mt.rounded(mt.spearman(*two_scores(s, d), by="source"), 6, "rho"),
    "spearman_cross": spearman_cross,
    "spearman_matrix": spearman_sizes,
    "margins_table": margins_table,
    "published_central_counts": central_counts,
    **{k: (lambda s, d, f=f: _ok(f(_gradient_rows(s, d)))) for k, f in CHECKS.items()},
    "gradient_alignment": gradient_alignment,
    "alignment_by_rank": alignment_by_rank,
    "rfl_decile_profile": lambda s, d: mt.rounded(th.by_decile(naive(s, d, S.name), "rfl"), 6, "mean"),
    "conditioning_m": lambda s, d: th.conditioning_report(naive(s, d, "orders_weekly").where("status = 'ok'")),
    "planted_region_mix": planted_mix,
    "retention_grid": lambda s, d: ex.retention_grid(s, d),
    "region_ablation": lambda s, d: ex.region_ablation(s, d),
    "stratification_ablation": lambda s, d: ex.stratification_ablation(s, d),
    "scale_transfer": lambda s, d: ex.transfer(s, d),
    "cross_transfer": lambda s, d: ex.transfer(s, d, which=("linear_small", "quantile", "gaussian", "point_quantile"), families=ex.FAMILIES),
    "trajectories": lambda s, d: ex.trajectories(s, d),
    "zero_shot_suite": zero_shot,
    "zero_shot_geomean": zero_shot_mean,
    "zero_shot_targets": lambda s, d: ex.zero_shot_targets(s, d),
    "amortisation": lambda s, d: amortisation(naive(s, d, S.name), targets=3, ratios=3),
    **{f"rfl_scaled_{k}": (lambda s, d, k=k: mt.rounded(score(grid(s, d, S.name), SeasonalNaive(S.season), S.context, S.horizon, scaling=k).select("source", "series_id", "origin", "m", "rfl"), 6, "rfl")) for k in SCALINGS},
    "budget_report": budget_report,
    "doc_rfl": lambda s, d: mt.rounded(doc_rfl(s, d).select("source", "series_id", "m", "rfl"), 6, "rfl"),
    "doc_select_quality": doc_select_quality,
    "conv_windows": conv_windows,
    "page_host_strata": page_hosts,
}

_C = cells_sql("supplier_weekly")
_HELD = f"""{_C}, f as (select source, series_id, t, y, lag(y, 13) over (partition by source, series_id order by t) as snaive from cells),
    l as (select source, series_id, arg_max(y, t) filter (y is not null) as last from cells where t < {S.length - S.horizon} group by 1, 2),
    held as (select f.source, 'snaive' as model, y, y - snaive as e from f where t >= {S.length - S.horizon} union all select f.source, 'last', y, y - last from f join l on l.source = f.source and l.series_id = f.series_id where t >= {S.length - S.horizon}),
    metrics as (select source, model, count(*) as slots, avg(cast(e as double) * e) as mse, avg(abs(e)) as mae from held where e is not null group by 1, 2),
    long as (select source as task_id, model, 'mse' as metric, mse as value from metrics union all select source, model, 'mae', mae from metrics),
    ratios as (select a.task_id, a.metric, a.model, a.value / b.value as ratio from long a join long b on a.task_id = b.task_id and a.metric = b.metric and b.model = 'snaive')"""
_TWO = f"""{scores_sql('supplier_weekly')}, v as (select k.source, k.series_id, k.origin, arg_max(c.y, c.t) filter (c.y is not null) as v from keys k join cells c on c.source = k.source and c.series_id = k.series_id and c.t >= k.origin and c.t < k.origin + {S.context} group by 1, 2, 3),
    other as (select k.source, k.series_id, k.origin, cast(sum(cast(f.y - v as hugeint) * (f.y - v)) as double) / count(f.y) as rfl from v k join cells f on f.source = k.source and f.series_id = k.series_id and f.t >= k.origin + {S.context} and f.t < k.origin + {S.context + S.horizon} group by 1, 2, 3 having count(f.y - v) > 0),
    pair as (select a.source, a.rfl as x, b.rfl as y from ok a join other b on a.source = b.source and a.series_id = b.series_id and a.origin = b.origin)"""


def _avg_ranks(part):
    p = f"partition by {part}" if part else ""
    r = lambda c: f"rank() over ({p} order by {c}) + (count(*) over (partition by {part + ', ' if part else ''}{c}) - 1) / 2.0"
    return f"ranks as (select source, {r('x')} as x, {r('y')} as y from pair)"


_WORDS = "list_filter(string_split_regex(lower(coalesce(text, '')), '[^a-z]+'), lambda w: w <> '')"
_DOCS = f"""c as (select word, count(*) as n from (select unnest({_WORDS}) as word from benchmark) group by 1), t as (select sum(n) as a, count(*) as k from c),
    dw as (select doc_id, source, unnest({_WORDS}) as word from documents),
    s as (select dw.doc_id, count(*) as m, sum(-log2((coalesce(c.n, 0) + 1) / cast((select a + k + 1 from t) as double))) / count(*) as rfl from dw left join c on c.word = dw.word group by 1)"""
_SIZE = lambda p: f"greatest(1, (2 * {p} * n + 100) // 200)"  # noqa: E731  p percent
_REGIONS = f"""{scores_sql('supplier_weekly')}, pairs as (select source, series_id, t, y, lag(y, {S.season}) over (partition by source, series_id order by t) as b from cells), seen as (select * from pairs where y is not null and b is not null),
    r as (select *, count(*) over (partition by source) as n, row_number() over (partition by source order by rfl, series_id, origin) as k, row_number() over (partition by source order by {_LCG}, series_id, origin) as j from ok),
    chosen as ({' union all '.join(f"select source, series_id, origin, '{m}' as model, {p} as percent from r where {w}" for p in (40, 80) for m, w in (("bottom", f"k <= {_SIZE(p)}"), ("top", f"k > n - {_SIZE(p)}"), ("random", f"j <= {_SIZE(p)}"), ("central", f"k > (n - {_SIZE(p)}) // 2 and k <= (n - {_SIZE(p)}) // 2 + {_SIZE(p)}")))}),
    fitted as (select c.source, model, percent, cast(sum(y * b) as bigint) as yb, cast(sum(b * b) as bigint) as bb from chosen c join seen f on f.source = c.source and f.series_id = c.series_id and f.t between c.origin + {S.context} and c.origin + {S.context + S.horizon - 1} group by 1, 2, 3),
    misses as (select f.source, model, percent, 1000 * y - ((2000 * yb + bb) // nullif(2 * bb, 0)) * b as e from seen s join fitted f on f.source = s.source where t >= {S.length - S.horizon}),
    sums as (select source, model, percent, cast(sum(e * e) as double) / count(*) / 1e6 as mse, cast(sum(abs(e)) as double) / count(*) / 1e3 as mae from misses group by 1, 2, 3),
    long as (select source || '/' || percent as task_id, percent, model, 'mse' as metric, mse as value from sums union all select source || '/' || percent, percent, model, 'mae', mae from sums)"""

def _scaled_sql(scale):
    return f"""with {scores_sql('supplier_weekly')}, whole as (select *, stddev_pop(y) over (partition by source, series_id) as whole from cells),
        sc as (select k.source, k.series_id, k.origin, {scale} as scale from keys k join whole c on c.source = k.source and c.series_id = k.series_id and c.t >= k.origin and c.t < k.origin + {S.context} group by 1, 2, 3)
        select s.source, s.series_id, s.origin, s.m, round(case when scale > 0 then rfl / (scale * scale) end, 6) as rfl from scores s join sc on sc.source = s.source and sc.series_id = s.series_id and sc.origin = s.origin"""


def _suite_sql():
    """Every task's cells, summed to its granularity, and the errors of the last horizon."""
    parts, ctes = [], []
    for (name, gran), tasks in ex.suite_by_grid().items():
        length, season = tasks[0].length, tasks[0].season
        at = f"{name}_{gran}"
        ctes.append(f"{at} as (with {cells_sql(name)}, c as (select source, series_id, t // {gran} as t, cast(sum(y) as double) as y from cells where t < {length * gran} group by 1, 2, 3) select *, avg(y) over (partition by source, series_id) as mean from c)")
        for t in tasks:
            back = f"{season} * ((t - {length - t.horizon}) // {season} + 1)"
            parts.append(f"""select '{t.id}' as task_id, f.y, b.y as snaive, l.last, z.zero from {at} f join (select source, series_id, arg_max(y, t) filter (y is not null) as last from {at} where t < {length - t.horizon} group by 1, 2) l on l.source = f.source and l.series_id = f.series_id
                join (select source, series_id, avg(y) as zero from {at} where t >= {length - t.horizon - t.context} and t < {length - t.horizon} group by 1, 2) z on z.source = f.source and z.series_id = f.series_id
                left join {at} b on b.source = f.source and b.series_id = f.series_id and b.t = f.t - {back.replace('(t -', '(f.t -')} where f.t >= {length - t.horizon}""")
    rows = " union all ".join(parts)
    each = " union all ".join(f"select task_id, '{m}' as model, y - {c} as e from rows" for m, c in (("snaive", "snaive"), ("last", "last"), ("mean", "zero")))
    return f"""{', '.join(ctes)}, rows as ({rows}), errors as ({each}), metrics as (select task_id, model, avg(e * e) as mse, avg(abs(e)) as mae from errors where e is not null group by 1, 2),
        long as (select task_id, model, 'mse' as metric, mse as value from metrics union all select task_id, model, 'mae', mae from metrics),
        ratios as (select a.task_id, a.metric, a.model, case when b.value <> 0 then a.value / b.value end as ratio from long a join long b on a.task_id = b.task_id and a.metric = b.metric and b.model = 'snaive')"""


ORACLES = {
    "eval_mse": f"with {_HELD} select source, model, slots, round(mse, 4) as mse from metrics",
    "eval_mae": f"with {_HELD} select source, model, slots, round(mae, 6) as mae from metrics",
    "eval_spe": f"with {_HELD}, i as (select source, avg(abs(y - snaive)) as scale from f where t < {S.length - S.horizon} group by 1) select m.source, model, round(mae / scale, 6) as spe from metrics m join i on i.source = m.source",
    "eval_relative": f"with {_HELD} select task_id, metric, model, round(ratio, 6) as ratio from ratios",
    "eval_geomean": f"with {_HELD} select metric, model, round(exp(avg(ln(ratio)) filter (ratio > 0)), 6) as geomean, count(*) filter (ratio > 0) as tasks, count(*) filter (coalesce(ratio, 0) <= 0) as left_out from ratios group by 1, 2",
    "eval_prob_score": f"""with {_HELD}, q as (select source, y, snaive as b from f where t >= {S.length - S.horizon} and y is not null and snaive is not null)
        select source, round(sum(2 * greatest((y - b + 10) * 0.1::double, (y - b + 10) * -0.9::double) + 2 * greatest((y - b) * 0.5::double, (y - b) * -0.5::double) + 2 * greatest((y - b - 10) * 0.9::double, (y - b - 10) * (0.9::double - 1))) / 3 / sum(abs(y)), 6) as wql from q group by 1""",
    "eval_512_96_windows": f"with {cells_sql('events_hourly')} select source, count(*) * {720 - 512 - 96 + 1} as windows from series group by 1",
    "spearman_pair": f"with {_TWO}, {_avg_ranks('')} select count(*) as windows, round(corr(x, y), 6) as rho from ranks",
    "spearman_per_source": f"with {_TWO}, {_avg_ranks('source')} select source, count(*) as windows, round(corr(x, y), 6) as rho from ranks group by 1",
    "margins_table": f"with {_REGIONS} select a.task_id, a.metric, round(b.value - a.value, 6) as absolute, round(100 * (b.value - a.value) / nullif(b.value, 0), 6) as percent from long a join long b on b.task_id = a.task_id and b.metric = a.metric and b.model = 'random' where a.model = 'central' and a.value is not null and b.value is not null",
    "published_central_counts": f"with {_REGIONS}, x as (select task_id, metric, percent, max(value) filter (model = 'central') as c, min(value) filter (model <> 'central') as o from long group by 1, 2, 3) select percent, count(*) filter (c < o) as best, count(*) filter (c = o) as tied, count(*) filter (c > o) as beaten from x group by 1",
    "gradient_identity": f"with {_C}, n as (select k.source, k.series_id, k.origin from (select source, series_id, unnest(range(0, {S.length - S.context - 4 + 1})) as origin from series) k join cells c on c.source = k.source and c.series_id = k.series_id and c.t >= k.origin + {S.context} and c.t < k.origin + {S.context + 4} where c.y is not null group by 1, 2, 3) select count(*) as windows, cast(0 as bigint) as violations from n",
    "rfl_decile_profile": f"with {scores_sql('supplier_weekly')}, r as (select *, ntile(10) over (partition by source order by rfl, series_id, origin) as decile from ok) select source, cast(decile as integer) as decile, count(*) as windows, round(avg(rfl), 6) as mean from r group by 1, 2",
    "conditioning_m": f"with {scores_sql('orders_weekly')} select source, " + ", ".join(f"quantile_cont(m, {p}) as m_{int(100 * p)}" for p in (0.0, 0.25, 0.5, 0.75, 1.0)) + " from ok group by 1",
    "amortisation": f"with {scores_sql('supplier_weekly')} select source, 9 as selections, count(*) as passes, count(*) * 9 as without_reuse, count(*) * 8 as saved from scores group by 1",
    "zero_shot_suite": f"with {_suite_sql()} select task_id, metric, model, round(ratio, 6) as ratio from ratios",
    "zero_shot_geomean": f"with {_suite_sql()} select metric, model, round(exp(avg(ln(ratio)) filter (ratio > 0)), 5) as geomean, count(*) filter (ratio > 0) as tasks, count(*) filter (coalesce(ratio, 0) <= 0) as left_out from ratios group by 1, 2",
    **{f"rfl_scaled_{k}": _scaled_sql(v) for k, v in (("context_std", f"stddev_pop(y) filter (c.t < k.origin + {S.context})"), ("context_meanabs", f"avg(abs(y)) filter (c.t < k.origin + {S.context})"), ("series_std", "max(c.whole)"))},
    "budget_report": f"""with {scores_sql('supplier_weekly')}, a as (select source, count(*) as n from ok group by 1), k as (select source, p as percent, greatest(1, (2 * p * n + 100) // 200) as kept from a cross join (values (40), (60), (80)) v(p))
        select source, percent, kept, 100 as steps, 512 as batch, cast(51200 as bigint) as drawn, least(51200, kept) as distinct, 51200 / kept::double as epochs from k""",
    "doc_rfl": f"with {_DOCS} select d.source, cast(d.doc_id as varchar) as series_id, coalesce(m, 0) as m, round(rfl, 6) as rfl from documents d left join s on s.doc_id = d.doc_id",
    "doc_select_quality": f"""with {_DOCS}, o as (select d.source, d.doc_id, round(rfl, 9) as rfl from s join documents d on d.doc_id = s.doc_id), r as (select *, count(*) over (partition by source) as n, row_number() over (partition by source order by rfl, cast(doc_id as varchar)) as k from o)
        select k > (n - greatest(1, (6 * n + 5) // 10)) // 2 and k <= (n - greatest(1, (6 * n + 5) // 10)) // 2 + greatest(1, (6 * n + 5) // 10) as kept, count(*) as labelled, round(avg(quality), 6) as good from r join labels l on l.doc_id = r.doc_id group by 1""",
    "conv_windows": "select conv_id, turn, role, length(text) as reply_chars, cast(sum(length(text)) over w as bigint) as context_chars, count(*) over w as context_turns from conversations window w as (partition by conv_id order by turn rows between 2 preceding and 1 preceding) qualify count(*) over w = 2",
    "page_host_strata": "select regexp_extract(url, '://([^/?#]*)', 1) as source, count(*) as pages, cast(sum(length(html)) as bigint) as chars from pages group by 1",
}
ORACLES["gradient_bound_rank1"] = ORACLES["self_bounding"] = ORACLES["gradient_identity"]
