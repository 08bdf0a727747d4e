"""Queries over every window, against counts of the windows that there are."""

import pytest
from pyspark.sql import functions as F

from lossband import queries

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def q():
    return queries.queries()


def test_gradients_of_every_window(spark, q):
    from lossband.operators.grid import CORPORA

    c, have = CORPORA["supplier_weekly"], {}
    for r in q["grid_supplier_weekly"](spark, SF).where("y is not null").collect():
        have.setdefault((r["source"], r["series_id"]), set()).add(r["t"])
    want = {}
    for (source, _), t in have.items():
        want[source] = want.get(source, 0) + sum(any(o + c.context + h in t for h in range(4)) for o in range(c.length - c.context - 3))
    for name in ("gradient_identity", "gradient_bound_rank1", "self_bounding"):
        (r,) = q[name](spark, SF).collect()
        assert (r["windows"], r["violations"]) == (sum(want.values()), 0)
    assert {r["source"]: r["windows"] for r in q["gradient_alignment"](spark, SF).collect()} == want
    got = {}
    for r in q["alignment_by_rank"](spark, SF).collect():
        got[r["source"]] = got.get(r["source"], 0) + r["windows"]
    assert got == want


def test_arrays_of_every_window(spark, q):
    series = {}
    for r in q["grid_events_hourly"](spark, SF).collect():
        series.setdefault((r["source"], r["series_id"]), {})[r["t"]] = r["y"]
    want = {}
    for key, y in series.items():
        for o in range(720 - 72 + 1):
            a = [y.get(t) for t in range(o, o + 72)]
            want[*key, o] = (sum(v or 0 for v in a[:48]), sum(v or 0 for v in a[48:]), sum(v is not None for v in a[48:]))
    assert {tuple(r)[:3]: tuple(r)[3:] for r in q["window_arrays"](spark, SF).collect()} == want


def test_tasks_that_no_training_window_touches(spark, q):
    """Training windows cover slots 0 to 695 without a gap, so only tasks behind them are clean."""
    series = q["grid_events_hourly"](spark, SF).select("source", "series_id").distinct().count()
    got = q["decontaminate_interval"](spark, SF).collect()
    assert {r["lo"] for r in got} <= set(range(696, 720)) and len(got) == series * sum(lo > 695 for lo in range(0, 720, 40))


def test_training_sees_all_windows_and_all_validation_rows(spark, monkeypatch):
    import numpy as np

    from lossband.plans import target as tg

    rows = spark.range(0, 60_000, 1, 4).selectExpr("'a' as source", "'b' as series_id", "id as origin", "array(1.0D, id % 7) as x", "array(id / 1000.0D) as future", "array(1) as mask")
    spec = tg.TrainSpec(steps=10, batch=64)
    w, curve = tg.fit_sgd(rows.where("origin < 300"), 1, 1, spec, rows)
    i = np.arange(60_000)
    assert abs(curve[-1][1] / np.mean((w[0, 0] + w[1, 0] * (i % 7) - i / 1000) ** 2) - 1) < 1e-9
    monkeypatch.setattr(tg, "DRAW", 100)
    again, _ = tg.fit_sgd(rows.where("origin < 300"), 1, 1, spec)
    assert np.allclose(w, again)


def test_a_score_that_half_of_a_source_shares(spark):
    """Equal scores need not meet in one task: ranks, both rules and cuts stay exact."""
    from lossband.operators import select as sel
    from lossband.operators.rank import distributed, local

    rows = spark.range(20_000).selectExpr("case when id < 15000 then 'big' else 'small' end as source", "cast(pmod(id, 7) as string) as series_id", "id as origin", "case when pmod(id, 2) = 0 then 5.0D else cast(pmod(id * 7919, 1009) as double) / 100 end as rfl", "1L as m", "'ok' as status")
    key = ["source", "series_id", "origin"]
    want = local(rows)
    plain = distributed(rows, ties=False).select(*key, "n", "rank_key")
    assert plain.exceptAll(want.select(*key, "n", "rank_key")).isEmpty()
    parts = distributed(rows, parts=8, ties=False).groupBy(F.spark_partition_id()).count()
    assert parts.agg({"count": "max"}).first()[0] < 8_000
    for alpha in ("1/10", "2/5", "4/5", "1"):
        a = sel.Alpha.of(alpha)
        by_cdf = want.where(sel.by_cdf(F.col("n"), F.col("rank_max"), a)).select(*key)
        got = sel.central(rows, alpha, rule="cdf").select(*key)
        assert got.exceptAll(by_cdf).isEmpty() and by_cdf.exceptAll(got).isEmpty()
        cut = sel.central_by_cutoffs(rows, alpha).select(*key)
        assert cut.exceptAll(want.where(sel.by_count(F.col("n"), F.col("rank_key"), a)).select(*key)).isEmpty()


def test_a_series_of_a_million_slots(spark):
    from lossband.operators.grid import regularize

    rows = spark.createDataFrame([("a", "x", 5, 1), ("a", "x", 999_999, 2), ("a", "x", 5, 3), ("b", "y", 0, 4)], "s string, i string, t long, v long")
    got = regularize(rows, F.col("s"), F.col("i"), F.col("t"), F.col("v"), None)
    assert got.groupBy("source").agg(F.count("*").alias("n"), F.min("t"), F.max("t"), F.sum("y"), F.count("y")).orderBy("source").collect() == [("a", 1_000_000, 0, 999_999, 6, 2), ("b", 1_000_000, 0, 999_999, 4, 1)]


def test_counts_of_a_written_score_table_and_shards(spark, tmp_path):
    from lossband.operators import scoring
    from lossband.operators.grid import build
    from lossband.sources.tables import write_shards

    scores, seen = scoring.observed(scoring.score(build(spark, SF, "events_hourly"), scoring.SeasonalNaive(24), 48, 24))
    write_shards(scores, str(tmp_path / "shards"), 4, rows_per_file=200)
    back = spark.read.parquet(str(tmp_path / "shards"))
    assert seen.get["windows"] == back.count() == 3125 and seen.get["scorable"] == back.where("status = 'ok'").count()
    assert back.groupBy(F.input_file_name()).count().agg({"count": "max"}).first()[0] <= 200


def test_targets_on_tasks_they_never_saw(spark):
    from lossband.plans.experiment import zero_shot_targets

    got = zero_shot_targets(spark, SF).collect()
    assert [r["strategy"] for r in got] == ["full", "central", "random_stratified", "central", "random_stratified"]
    assert all(r["tasks"] >= 4 and 0.3 < r["geomean"] < 3 for r in got), got
    assert got[1]["kept"] == got[2]["kept"] < got[3]["kept"] == got[4]["kept"] < got[0]["kept"]
