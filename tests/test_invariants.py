"""What must hold for any scores."""

import random

import pytest
from pyspark.sql import functions as F

from lossband.operators import select as sel
from lossband.schema import Alpha

KEY = ["source", "series_id", "origin"]


@pytest.fixture(scope="module")
def scores(spark):
    rng = random.Random(0)
    rows = [(s, str(i % 3), i, float(rng.randrange(40)) * scale) for s, n, scale in (("a", 83, 1), ("b", 40, 100), ("c", 7, 3)) for i in range(n)]
    return spark.createDataFrame(rows, "source string, series_id string, origin long, rfl double").withColumns({"m": F.lit(1).cast("long"), "status": F.lit("ok")}).cache()


def keys(df):
    return set(map(tuple, df.select(*KEY).collect()))


def test_exact_sizes(scores):
    n = {r["source"]: r["count"] for r in scores.groupBy("source").count().collect()}
    for alpha in ("2/5", "3/5", "4/5"):
        for make in (sel.central, sel.bottom, sel.top, sel.random_stratified):
            got = {r["source"]: r["count"] for r in make(scores, alpha).groupBy("source").count().collect()}
            assert got == {s: Alpha.of(alpha).kept(k) for s, k in n.items()}
        assert sel.random_global(scores, alpha).count() == Alpha.of(alpha).kept(sum(n.values()))


def test_nested(scores):
    for rule in ("count", "cdf"):
        assert keys(sel.central(scores, "2/5", rule=rule)) <= keys(sel.central(scores, "3/5", rule=rule)) <= keys(sel.central(scores, 1, rule=rule))


def test_sweep_equals_single_runs(scores):
    rows = sel.sweep(scores, ["2/5", "4/5"])
    for a in ("2/5", "4/5"):
        assert keys(rows.where(F.col("alpha_num") == int(a[0]))) == keys(sel.central(scores, a))


def test_monotone_and_scaled_scores(scores):
    cubed = scores.withColumn("rfl", F.col("rfl") ** 3 + 1)
    assert keys(sel.central(cubed, "3/5")) == keys(sel.central(scores, "3/5"))
    one = scores.withColumn("rfl", F.when(F.col("source") == "a", F.col("rfl") * 1000).otherwise(F.col("rfl")))
    assert keys(sel.central(one, "3/5")) == keys(sel.central(scores, "3/5"))
    assert keys(sel.central(one, "3/5", by=None)) != keys(sel.central(scores, "3/5", by=None))


def test_sources_do_not_meet(scores):
    more = scores.unionByName(scores.where("source = 'a'").withColumn("origin", F.col("origin") + 1000).withColumn("rfl", F.lit(0.5)))
    b = lambda df: {k for k in keys(df) if k[0] != "a"}
    assert b(sel.central(more, "3/5")) == b(sel.central(scores, "3/5"))


def test_partitions_do_not_matter(scores):
    assert keys(sel.central(scores.repartition(7), "3/5")) == keys(sel.central(scores.coalesce(1), "3/5"))


def test_share_report(scores):
    r = sel.share_report(scores, sel.central(scores, "3/5")).collect()
    assert abs(sum(x["p_before"] for x in r) - 1) < 1e-12 and abs(sum(x["p_after"] for x in r) - 1) < 1e-12
    assert all(abs(x["kept"] - 0.6 * x["n"]) <= 0.5 for x in r)


def test_rule_sizes_for_all_small_sources():
    for n in range(1, 200):
        last = 0
        for i in range(1, 21):
            a = Alpha(i, 20)
            m, low = a.kept(n), a.skipped(n)
            cdf = sum((20 - i) * n <= 40 * r <= (20 + i) * n for r in range(1, n + 1))
            assert low + m <= n and abs(cdf - m) <= 1 and m >= last
            last = m
