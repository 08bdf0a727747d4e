"""The experiments, each as a long table of results; nothing here asserts who wins."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import select as sel
from ..operators import synth
from ..operators.grid import CORPORA, Corpus, build
from ..operators.scoring import ContextGaussian, PointQuantile, ResidualQuantile, RidgeDirect, SeasonalNaive, score
from ..operators.windows import lengths, validation_keys
from ..sources.tables import keep
from . import cells as cl
from . import target as tg

PLANTED = Corpus("planted", 320, 64, 16, 16)


def corpus(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, Corpus]:
    if name == "planted":
        return synth.planted(spark, series=6, length=PLANTED.length).drop("kind"), PLANTED
    return build(spark, sf_dir, name), CORPORA[name]


STRATEGIES = ("central", "global", "bottom", "top", "random_stratified", "random_global")


def strategies(scores: DataFrame, alpha, seed: int = 0, kinds=STRATEGIES) -> dict[str, DataFrame]:
    make = {
        "central": lambda: sel.central(scores, alpha), "global": lambda: sel.central(scores, alpha, by=None), "bottom": lambda: sel.bottom(scores, alpha), "top": lambda: sel.top(scores, alpha),
        "random_stratified": lambda: sel.random_stratified(scores, alpha, seed), "random_global": lambda: sel.random_global(scores, alpha, seed),
    }
    return {k: make[k]() for k in kinds}


class Judge:
    """The held-out horizons of a corpus and the seasonal naive error on them, prepared once for all targets.

    Targets are judged on the slots that the seasonal naive forecast has a value for, so that ratios compare like with like.
    """

    def __init__(self, grid: DataFrame, c: Corpus, lags: int):
        keys = validation_keys(lengths(grid), c.context, c.horizon)
        # A window whose features are all missing or zero has no unit to be judged in.
        held = keep(tg.examples(grid, keys, lags, c.context, c.horizon).where("size > 1e-6"), "named")
        naive = SeasonalNaive(c.season).error(grid, 1).select("source", "series_id", "t", "e1")
        slot = F.col("t") - F.col("origin") - c.context
        # Neither side is broadcast: one is the whole corpus, the other has a row a series, and their files say little of either.
        inside = naive.join(held.select(*tg.KEY).hint("merge"), ["source", "series_id"]).where(slot.between(0, c.horizon - 1))
        errors = inside.groupBy(*tg.KEY).agg(F.array_sort(F.collect_list(F.struct("t", "e1")))["e1"].alias("naive"))  # one entry a slot of the horizon
        held = held.join(errors.hint("merge"), tg.KEY).withColumn("mask", F.zip_with("mask", "naive", lambda m, e: F.when(e.isNotNull(), m).otherwise(0)))
        self.plan, self.held = held, keep(held, "held")
        self.base = self.held.select("size", F.explode("naive").alias("e")).agg(F.avg(F.abs(F.col("e") / F.col("size")))).first()[0]

    def __call__(self, weights, spread) -> list[tuple]:
        """For each cell: MSE in the scale of the context; absolute error and quantile loss relative to the absolute error of the seasonal naive forecast."""
        share = lambda v: v / self.base if v is not None and self.base else None
        found = {r["cell"]: (r["se"], share(r["ae"]), share(r["pl"])) for r in cl.judged(self.held, weights, spread)}
        return [found.get(i, (None, None, None)) for i in range(len(weights))]


FAMILIES = ("linear", "quantile", "gaussian")
#: Corpora of the given tables, and the planted one beside them.
EVERY = ("supplier_weekly", "orders_weekly", "events_hourly", "brand_weekly", "embedding_axis", "planted")
RATIOS = ("2/5", "3/5", "4/5")


def of_family(family: str, grid: DataFrame, c: Corpus):
    """The reference of a target's own family; the linear one is fitted to windows before the held-out ones."""
    if family == "linear":
        return RidgeDirect(8).fit(grid, c.context, c.horizon, F.col("origin") + c.context + 2 * c.horizon <= c.length)
    return ResidualQuantile(c.season) if family == "quantile" else ContextGaussian()


class Run:
    """All cells of one training corpus: scores, selections and fitted targets, each made in one pass over the windows."""

    def __init__(self, spark, sf_dir, name: str, cells: list[cl.Cell], lags: int = 8, horizon: int | None = None, make=None):
        grid, c = corpus(spark, sf_dir, name)
        self.grid, self.c, self.cells, self.lags = keep(grid, "grid"), corpus_horizon(c, horizon), cells, lags
        self.scores = {r: keep(score(self.grid, (make or of_family)(r, self.grid, self.c), self.c.context, self.c.horizon), f"scores-{r}") for r in dict.fromkeys(x.reference for x in cells)}
        members = keep(cl.memberships(self.scores, cells), "members")
        found = {r["cell"]: (r["kept"], r["shared"]) for r in cl.sizes(members).collect()}
        self.kept, self.shared = ([found.get(i, (0, 0))[k] for i in range(len(cells))] for k in (0, 1))
        # A window without a unit cannot be trained on, as it cannot be judged.
        pool = keep(tg.examples(self.grid, members, lags, self.c.context, self.c.horizon, ("cells",)).where("size > 1e-6"), "cells")
        self.weights = cl.fit_linear(pool, len(cells), lags, self.c.horizon)
        self.spread = cl.offsets(pool, self.weights, cells)

    def judged_by(self, judge: Judge) -> list[tuple]:
        return judge(self.weights, self.spread)


def corpus_horizon(c: Corpus, horizon: int | None) -> Corpus:
    return c if horizon is None else replace(c, horizon=horizon)


def cells_of(families, kinds, alphas, seeds=(0,)) -> list[cl.Cell]:
    """Everything, and each rule at each ratio, for each family with the reference of its own; seeds matter to random rules only."""
    out = []
    for f in families:
        out.append(cl.Cell(f, f, "full"))
        out += [cl.Cell(f, f, k, a, s) for k in kinds for a in alphas for s in (seeds if k.startswith("random") else seeds[:1])]
    return out


RESULT = "corpus string, task string, family string, strategy string, alpha string, seed int, kept long, mse double, relative double, relative_prob double"


def _own(spark, sf_dir, names, cells) -> DataFrame:
    """Each corpus' cells, judged on its own held-out horizons."""
    out = []
    for name in names:
        run = Run(spark, sf_dir, name, cells)
        out += [(name, name, c.family, c.strategy, c.alpha, c.seed, n, *r) for c, n, r in zip(cells, run.kept, run.judged_by(Judge(run.grid, run.c, run.lags)))]
    return spark.createDataFrame(out, RESULT)


def _elsewhere(spark, sf_dir, train: str, tasks, cells, horizon: int) -> DataFrame:
    """The cells of one corpus, judged on several; features and futures are in units of the context's size, so one target fits any corpus."""
    run, out = Run(spark, sf_dir, train, cells, horizon=horizon), []
    for name in tasks:
        grid, c = (run.grid, run.c) if name == train else corpus(spark, sf_dir, name)
        judge = Judge(keep(grid, "task"), corpus_horizon(c, horizon), run.lags)
        out += [(train, name, c.family, c.strategy, c.alpha, c.seed, n, *r) for c, n, r in zip(cells, run.kept, run.judged_by(judge))]
    return spark.createDataFrame(out, RESULT)


def retention_grid(spark, sf_dir, names=("supplier_weekly", "orders_weekly", "events_hourly", "planted"), families=FAMILIES, alphas=RATIOS, seeds=(0, 1)) -> DataFrame:
    """Targets of three families on everything, on random shares and on the middle shares of their own reference's scores."""
    return _own(spark, sf_dir, names, cells_of(families, ("central", "random_global"), alphas, seeds))


def region_ablation(spark, sf_dir, train: str = "supplier_weekly", tasks=EVERY[:5], families=FAMILIES, alphas=("2/5", "4/5"), horizon: int = 8) -> DataFrame:
    """Lowest, highest, random and middle shares of one corpus, judged on five."""
    return _elsewhere(spark, sf_dir, train, tasks, cells_of(families, ("bottom", "top", "random_stratified", "central"), alphas), horizon)


def stratification_ablation(spark, sf_dir, names=EVERY, families=("linear",), alphas=RATIOS) -> DataFrame:
    """The middle of every source against the middle of everything, at three ratios on every corpus."""
    return _own(spark, sf_dir, names, cells_of(families, ("central", "global"), alphas))


SIZES = {"linear_mini": 4, "linear_small": 8, "linear_base": 16}


def references(grid: DataFrame, c: Corpus, which=None) -> dict:
    """Forecasters of one family in three sizes, and of four families; only those of ``which`` are fitted."""
    train = F.col("origin") + c.context + 2 * c.horizon <= c.length
    ridge = {n: RidgeDirect(k).fit(grid, c.context, c.horizon, train) for n, k in SIZES.items() if which is None or n in which}
    rest = {"quantile": ResidualQuantile(c.season), "gaussian": ContextGaussian(), "point_quantile": PointQuantile(c.season), "naive": SeasonalNaive(c.season)}
    return ridge | {k: r for k, r in rest.items() if which is None or k in which}


def score_all(spark, sf_dir, name: str, which=None) -> dict[str, DataFrame]:
    """One score table a reference over one grid that is written once."""
    grid, c = corpus(spark, sf_dir, name)
    grid = keep(grid, "grid")
    return {k: keep(score(grid, r, c.context, c.horizon), f"scores-{k}") for k, r in references(grid, c, which).items()}


def transfer(spark, sf_dir, name: str = "supplier_weekly", which=("linear_mini", "linear_small", "linear_base"), alpha="4/5", families=("linear",)) -> DataFrame:
    """(family, reference, kept, overlap, mse, relative, relative_prob): targets trained on what each reference selects; ``overlap`` is the share of it that the first reference selects too."""
    cells = [cl.Cell(f, r, "central", alpha) for f in families for r in which]
    run = Run(spark, sf_dir, name, cells, make=lambda reference, grid, c: references(grid, c, (reference,))[reference])
    rows = zip(cells, run.kept, run.shared, run.judged_by(Judge(run.grid, run.c, run.lags)))
    out = [(x.family, x.reference, n, both / n if n else None, *r) for x, n, both, r in rows]
    return spark.createDataFrame(out, "family string, reference string, kept long, overlap double, mse double, relative double, relative_prob double")


def trajectories(spark, sf_dir, name: str = "supplier_weekly", alphas=("2/5", "4/5"), kinds=("central", "bottom", "top", "random_stratified"), spec: tg.TrainSpec = tg.TrainSpec(), seeds=(0, 1), lags: int = 8) -> DataFrame:
    """(strategy, alpha, seed, step, val_loss): the same steps on everything and on every selection, one validation set for all."""
    grid, c = corpus(spark, sf_dir, name)
    grid = keep(grid, "grid")
    scores = keep(score(grid, SeasonalNaive(c.season), c.context, c.horizon), "scores")
    usable = lambda keys: tg.examples(grid, keys, lags, c.context, c.horizon).where("size > 1e-6")
    held, pool = keep(usable(validation_keys(lengths(grid), c.context, c.horizon)), "held"), keep(usable(sel.full(scores)), "pool")
    out = []
    for seed in seeds:
        cells = {("full", "1"): pool} | {(k, a): pool.join(rows.select(*tg.KEY).hint("merge"), tg.KEY, "left_semi") for a in alphas for k, rows in strategies(scores, a, seed, kinds).items()}
        for (k, a), rows in cells.items():
            _, curve = tg.fit_sgd(rows, lags, c.horizon, replace(spec, seed=seed), held)
            out += [(k, a, seed, step, loss) for step, loss in curve]
    return spark.createDataFrame(out, "strategy string, alpha string, seed int, step int, val_loss double")


@dataclass(frozen=True)
class Task:
    """The last ``horizon`` slots of every series of a corpus whose slots are summed in groups of ``granularity``."""

    id: str
    corpus: str
    granularity: int
    length: int
    context: int
    horizon: int
    season: int


def task_suite() -> list[Task]:
    """Every corpus at several granularities and horizons."""
    out = []
    for c in CORPORA.values():
        if c.name == "events_user_hourly":
            continue
        for g in (1, 2, 4) if c.name != "embedding_axis" else (1, 2):
            length, season = c.length // g, max(1, c.season // g)
            for label, horizon in (("short", max(1, season // 2)), ("medium", season), ("long", 2 * season)):
                context = min(2 * c.context // g, length - 2 * horizon)
                if context >= season:
                    out.append(Task(f"{c.name}/{g}/{label}", c.name, g, length, context, horizon, season))
    return out


def suite_by_grid() -> dict[tuple[str, int], list[Task]]:
    out: dict[tuple[str, int], list[Task]] = {}
    for t in task_suite():
        out.setdefault((t.corpus, t.granularity), []).append(t)
    return out


def coarser(grid: DataFrame, granularity: int, length: int) -> DataFrame:
    """Sums of ``granularity`` slots; a group without an observed slot is missing, one that the series ends in is left out."""
    slot = F.floor(F.col("t") / granularity).cast("long")
    return grid.where(F.col("t") < length * granularity).groupBy("source", "series_id", slot.alias("t")).agg(F.sum("y").alias("y"))


def suite_errors(spark, sf_dir) -> DataFrame:
    """(task_id, model, metric, value): mean squared and absolute error of forecasters that need no training, for every task.

    All tasks of one grid read it once: the forecasts of each are window functions over the series.
    """
    at, out = Window.partitionBy("source", "series_id").orderBy("t"), None
    whole = Window.partitionBy("source", "series_id")
    for (name, g), tasks in suite_by_grid().items():
        rows = coarser(build(spark, sf_dir, name), g, tasks[0].length).withColumn("y", F.col("y").cast("double"))
        forecasts = []
        for task in tasks:
            start, named = task.length - task.horizon, F.lit(task.id).alias("task_id")
            past = F.when(F.col("t") < start, F.col("y"))
            recent = F.when((F.col("t") >= start - task.context) & (F.col("t") < start), F.col("y"))
            bands = [F.when(F.floor((F.col("t") - start) / task.season) == k - 1, F.lag("y", k * task.season).over(at)) for k in range(1, -(-task.horizon // task.season) + 1)]
            by = F.array(F.struct(named, F.lit("snaive").alias("model"), F.coalesce(*bands).alias("f")), F.struct(named, F.lit("last").alias("model"), F.max_by("y", F.when(past.isNotNull(), F.col("t"))).over(whole).alias("f")), F.struct(named, F.lit("mean").alias("model"), F.avg(recent).over(whole).alias("f")))
            forecasts.append(F.when(F.col("t") >= start, by))
        made = rows.select("y", F.flatten(F.array_compact(F.array(*forecasts))).alias("made"))
        one = made.select("y", F.explode("made").alias("x")).select("x.task_id", "x.model", (F.col("y") - F.col("x.f")).alias("e"))
        out = one if out is None else out.unionByName(one)
    sums = out.where("e is not null").groupBy("task_id", "model").agg(F.avg(F.col("e") * F.col("e")).alias("mse"), F.avg(F.abs("e")).alias("mae"))
    return sums.select("task_id", "model", F.explode(F.map_from_arrays(F.array(F.lit("mse"), F.lit("mae")), F.array("mse", "mae"))).alias("metric", "value"))


def zero_shot_targets(spark, sf_dir, train: str = "supplier_weekly", families=FAMILIES, alphas=("2/5", "4/5"), kinds=("central", "random_stratified"), horizon: int = 8) -> DataFrame:
    """(family, strategy, alpha, kept, tasks, geomean, geomean_prob): targets trained on selections of one corpus, judged on those that they never saw.

    Each task is the last ``horizon`` slots of another corpus; errors are relative to the seasonal naive one, and means
    over tasks are geometric. A task whose ratio is missing or 0 is left out of its mean.
    """
    rows = _elsewhere(spark, sf_dir, train, [n for n in EVERY if n != train], cells_of(families, kinds, alphas), horizon)
    mean = lambda c: F.exp(F.avg(F.when(F.col(c) > 0, F.log(c))))
    return rows.groupBy("family", "strategy", "alpha", "kept").agg(F.count_if(F.col("relative") > 0).alias("tasks"), mean("relative").alias("geomean"), mean("relative_prob").alias("geomean_prob"))


def choose_proxy(spark, sf_dir, name: str, cheap: str = "linear_mini", dear: str = "linear_base", share: int = 16, least: float = 0.9) -> tuple[str, float]:
    """The cheap reference if its scores rank a pilot of the series (one in ``share`` by hash) like the dear one's."""
    from ..functions.metrics import spearman

    grid, c = corpus(spark, sf_dir, name)
    refs = references(keep(grid, "grid"), c, (cheap, dear))
    pilot = keep(grid.where(F.pmod(F.xxhash64("source", "series_id"), F.lit(share)) == 0), "pilot")
    a, b = (score(pilot, refs[k], c.context, c.horizon) for k in (cheap, dear))
    rho = spearman(a, b).first()["rho"]
    return (cheap if rho is not None and rho >= least else dear), rho
