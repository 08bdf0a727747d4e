"""Cases small enough to check by hand."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from lossband.functions import loss as l
from lossband.functions import metrics as mt
from lossband.operators import rank, scoring
from lossband.operators import select as sel
from lossband.operators import windows as w
from lossband.plans import target, theory
from lossband.schema import Alpha


def series(spark, ys, name="s", source="a"):
    return spark.createDataFrame([(source, name, t, y) for t, y in enumerate(ys)], "source string, series_id string, t long, y long")


def table(spark, **sources):
    return spark.createDataFrame([(s, "0", i, float(v)) for s, vs in sources.items() for i, v in enumerate(vs)], "source string, series_id string, origin long, rfl double").withColumns({"m": F.lit(1).cast("long"), "status": F.lit("ok")})


def kept(df):
    out = {}
    for r in df.collect():
        out.setdefault(r["source"], []).append(r["origin"])
    return {k: sorted(v) for k, v in out.items()}


def test_last_value_losses(spark):
    g = series(spark, [2, 4, 6, 7, None, 9])
    got = [(r["origin"], r["m"], r["rfl"]) for r in scoring.score(g, scoring.LastValue(), 2, 2, held_out=False).orderBy("origin").collect()]
    assert got == [(0, 2, 6.5), (1, 1, 1.0), (2, 1, 4.0)]
    assert [r["origin"] for r in scoring.score(g, scoring.LastValue(), 2, 2).collect()] == [0]
    assert [r["origin"] for r in w.validation_keys(w.lengths(g), 2, 2).collect()] == [2]


def test_half_of_the_squared_error(spark):
    g = series(spark, [1, 2, 3, 5, 8, 13])
    a = {r["origin"]: r["rfl"] for r in scoring.SeasonalNaive(1).score(g, 2, 1).collect()}
    b = {r["origin"]: r["rfl"] for r in scoring.SeasonalNaive(1).score(g, 2, 1, l.HALF_MSE).collect()}
    assert a == {0: 1.0, 1: 4.0, 2: 9.0, 3: 25.0} and b == {k: v / 2 for k, v in a.items()}


def test_nothing_observed(spark):
    got = scoring.score(series(spark, [1, 2, None, None, None]), scoring.LastValue(), 2, 2, held_out=False).orderBy("origin").collect()
    assert [(r["m"], r["rfl"], r["status"]) for r in got] == [(0, None, "unscorable"), (0, None, "unscorable")]


def test_masked_values_do_not_count(spark):
    a = scoring.score(series(spark, [1, 2, 5, None, 4]), scoring.LastValue(), 2, 2, held_out=False).orderBy("origin").collect()
    assert (a[0]["m"], a[0]["rfl"]) == (1, 9.0)


@pytest.mark.parametrize("method", ["local", "distributed"])
def test_two_rules(spark, method):
    t = table(spark, a=range(10), b=[1], c=[5, 5, 5, 5])
    assert kept(sel.central(t, "4/5", method=method)) == {"a": list(range(1, 9)), "b": [0], "c": [0, 1, 2]}
    assert kept(sel.central(t, "4/5", rule="cdf", method=method)) == {"a": list(range(9))}


@pytest.mark.parametrize("method", ["local", "distributed"])
def test_ties_and_rounding(spark, method):
    t = table(spark, a=[1, 1, 1, 1, 2, 3, 4, 5, 6, 7])
    assert kept(sel.central(t, "3/5", rule="cdf", method=method)) == {"a": list(range(8))}
    assert kept(sel.central(t, "3/5", method=method)) == {"a": [2, 3, 4, 5, 6, 7]}
    five = table(spark, a=range(5))
    assert kept(sel.central(five, "2/5", method=method)) == {"a": [1, 2]}
    assert kept(sel.central(five, "1/2", method=method)) == {"a": [1, 2, 3]}
    assert kept(sel.central(table(spark, a=range(3)), "1/100", method=method)) == {"a": [1]}
    assert kept(sel.central(five, 1, method=method)) == {"a": [0, 1, 2, 3, 4]}


def test_regions(spark):
    t = table(spark, a=range(10))
    assert kept(sel.bottom(t, "2/5")) == {"a": [0, 1, 2, 3]}
    assert kept(sel.top(t, "2/5")) == {"a": [6, 7, 8, 9]}
    assert kept(sel.central(t, "2/5")) == {"a": [3, 4, 5, 6]}
    assert kept(sel.interval(t, "0.2", "0.5")) == {"a": [2, 3, 4]}


def test_global_against_stratified(spark):
    t = table(spark, a=range(1, 11), b=range(101, 111))
    assert kept(sel.central(t, "2/5")) == {"a": [3, 4, 5, 6], "b": [3, 4, 5, 6]}
    assert kept(sel.central(t, "2/5", by=None)) == {"a": [6, 7, 8, 9], "b": [0, 1, 2, 3]}
    t = table(spark, a=range(1, 11), b=[11, 12], c=range(13, 23), d=range(1000, 1005))
    assert "d" not in kept(sel.central(t, "1/2", by=None)) and len(kept(sel.central(t, "1/2"))["d"]) == 3


def test_alpha():
    assert Alpha.of(0.8) == Alpha(4, 5) and Alpha.of("0.25") == Alpha(1, 4)
    for bad in (0, 1.5, 1 / 3):
        with pytest.raises(ValueError):
            Alpha.of(bad)


def test_rank_correlation(spark):
    a, b = table(spark, a=[1, 2, 3, 4]), table(spark, a=[10, 30, 20, 40])
    assert abs(mt.spearman(a, b).first()["rho"] - 0.8) < 1e-12
    a, b = table(spark, a=[1, 1, 2]), table(spark, a=[1, 2, 3])
    assert abs(mt.spearman(a, b).first()["rho"] - 0.8660254) < 1e-6


def test_geometric_mean(spark):
    rows = spark.createDataFrame([("t1", "x", "m", 2.0), ("t2", "x", "m", 0.5)], "task_id string, metric string, model string, ratio double")
    assert abs(mt.geomean(rows).first()["geomean"] - 1) < 1e-12


def test_gradients(spark):
    rows = spark.createDataFrame([([1.0, 2.0], [3.0, -1.0], [1, 1])], "x array<double>, future array<double>, mask array<int>")
    r = theory.residuals(rows, F.array(F.lit(0.0), F.lit(0.0)))
    g = theory.gradient_bounds(theory.window_gradient(r, F.col("x"))).first()
    assert (g["half_mse"], g["norm2"], g["lower"], g["ok"]) == (2.5, 12.5, 12.5, True)
    one = theory.rank_one_bounds(r.withColumn("x", F.col("x")), F.col("x")).first()
    assert (one["g1"], one["norm2"], one["upper"], one["ok"]) == (-0.5, 0.25, 12.5, True)


def test_one_step_is_first_order():
    rng = np.random.default_rng(0)
    x, y, v = rng.standard_normal((50, 3)), rng.standard_normal((50, 2)), rng.standard_normal((3, 2))
    gap = [abs(a - b) for a, b in (theory.one_step(x, y, v, 4, eta) for eta in (0.1, 0.05))]
    assert 3.5 < gap[0] / gap[1] < 4.5


def test_losses():
    assert np.isclose(l.np_pinball(np.array([[0.0]]), np.array([[2.0]]), np.array([[True]]), 0.9), 1.8)
    assert np.isclose(l.np_pinball(np.array([[0.0]]), np.array([[-2.0]]), np.array([[True]]), 0.9), 0.2)
    assert abs(l.normal_cdf(1.96) - 0.975) < 1e-4
    samples = np.random.default_rng(0).standard_normal(20_000)
    assert abs(l.sample_score(samples, 0.7) - l.gaussian_score(0.0, 1.0, np.array(0.7))) < 0.01
    assert np.isclose(l.np_wql(np.array([[[1.0, 1.0]]]), np.array([[2.0, 0.0]]), np.array([[True, True]]), [0.5])[0], 1.0)


def test_array_and_prefix_losses_agree(spark):
    g = series(spark, [3, 1, 4, 1, 5, 9, 2, 6, 5, 3, 5])
    last = lambda x: x[:, -1:].repeat(2, axis=1)
    a = {r["origin"]: r["rfl"] for r in scoring.arrow_scores(g, last, 3, 2, chunk=4).collect()}
    b = {r["origin"]: r["rfl"] for r in scoring.LastValue().score(g, 3, 2).collect()}
    rows = theory.last_features(g, 1, 3, 2)
    c = {r["origin"]: r["v"] for r in rows.select("origin", l.array_loss(l.MSE, F.array(F.col("x")[1], F.col("x")[1]), F.col("future"), F.col("mask")).alias("v")).collect()}
    assert a == b == c


def test_training(spark):
    ys = [round(1000 * (5 + np.sin(t / 3))) for t in range(200)]
    g = series(spark, ys)
    keys = w.window_keys(w.lengths(g), 16, 4, held_out=True)
    rows = target.examples(g, keys, 8, 16, 4)
    fitted = target.fit_ridge(rows, 8, 4, 1e-6)
    held = target.examples(g, w.validation_keys(w.lengths(g), 16, 4), 8, 16, 4)
    assert target.forecast_errors(held, fitted).agg(F.max(F.abs("e"))).first()[0] < 60
    _, curve = target.fit_sgd(rows, 8, 4, target.TrainSpec(steps=60, batch=64), held)
    assert curve[-1][1] < curve[0][1]
    assert target.budget_report(100, target.TrainSpec())["epochs"] == 512


def test_sparse_cutoffs_equal_sorting(spark):
    from lossband.operators.synth import skewed

    t = skewed(spark, 3000, 40)
    a = sel.central(t, "4/5").select("source", "origin").collect()
    b = sel.central_by_cutoffs(t, "4/5").select("source", "origin").collect()
    c = sel.central(t, "4/5", method="local").select("source", "origin").collect()
    assert sorted(a) == sorted(b) == sorted(c)
    n = F.col("n")
    one = rank.cutoffs(t, F.array(F.floor((n + 1) / 2)), None).first()
    pooled = sorted((r["rfl"], r["source"], r["series_id"], r["origin"]) for r in t.collect())
    assert (one["rfl"], one["source"], one["series_id"], one["origin"]) == pooled[(len(pooled) + 1) // 2 - 1]
