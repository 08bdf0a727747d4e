"""Many targets at once: selections, fits, spreads and judgements against plain versions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from lossband.operators import select as sel
from lossband.operators.scoring import ContextGaussian, SeasonalNaive, score
from lossband.operators import synth
from lossband.operators.windows import lengths, validation_keys
from lossband.plans import cells as cl
from lossband.plans import experiment as ex
from lossband.plans import target as tg
from lossband.sources.tables import keep

LAGS, CONTEXT, HORIZON = 4, 32, 8
CELLS = [cl.Cell("linear", "a", "full"), cl.Cell("quantile", "a", "central", "2/5"), cl.Cell("gaussian", "b", "global", "3/5"), cl.Cell("linear", "b", "top", "1/5"), cl.Cell("linear", "a", "bottom", "1/5"), cl.Cell("quantile", "b", "random_stratified", "2/5", 3), cl.Cell("gaussian", "a", "random_global", "4/5", 1)]


@pytest.fixture(scope="module")
def made(spark):
    grid = synth.planted(spark, series=3, length=120).drop("kind")
    scores = {"a": score(grid, SeasonalNaive(16), CONTEXT, HORIZON), "b": score(grid, ContextGaussian(), CONTEXT, HORIZON)}
    members = cl.memberships(scores, CELLS)
    pool = cl.with_cells(tg.examples(grid, members, LAGS, CONTEXT, HORIZON).where("size > 1e-6"), members)
    return grid, scores, members, pool


def test_one_ranking_gives_the_rows_of_each_rule(made):
    _, scores, members, _ = made
    got = [(i, *r) for r in members.select(F.explode("cells").alias("i"), *tg.KEY).collect() for i, r in [(r[0], r[1:])]]
    rules = {"central": sel.central, "top": sel.top, "bottom": sel.bottom, "full": lambda t, a: sel.full(t), "global": lambda t, a: sel.central(t, a, by=None)}
    for i, c in enumerate(CELLS):
        table = scores[c.reference]
        rows = rules[c.strategy](table, c.alpha) if c.strategy in rules else getattr(sel, c.strategy)(table, c.alpha, c.seed)
        assert sorted(g[1:] for g in got if g[0] == i) == sorted(map(tuple, rows.select(*tg.KEY).collect())), c


def test_sizes_and_overlap(made):
    members = made[2]
    rows = [set(r["cells"]) for r in members.collect()]
    for r in cl.sizes(members).collect():
        assert (r["kept"], r["shared"]) == (sum(r["cell"] in x for x in rows), sum({0, r["cell"]} <= x for x in rows))


def test_fits_and_spreads(made):
    pool = made[3]
    w = cl.fit_linear(pool, len(CELLS), LAGS, HORIZON)
    spread = cl.offsets(pool, w, CELLS)
    rows = pool.collect()
    for i, c in enumerate(CELLS):
        mine = [r for r in rows if i in r["cells"]]
        x, y, m = (np.array([r[k] for r in mine], float) for k in ("x", "future", "mask"))
        for h in range(HORIZON):
            on = m[:, h] == 1
            want = np.linalg.solve(x[on].T @ x[on] + np.eye(LAGS + 1), x[on].T @ y[on, h])
            assert np.allclose(w[i][:, h], want, rtol=1e-6, atol=1e-8)
            e = y[on, h] - x[on] @ want
            if c.family == "linear":
                assert not spread[i].any()
            elif c.family == "gaussian":
                assert spread[i][8, h] == pytest.approx(1.2815515655446004 * (e**2).mean() ** 0.5, rel=1e-6)
            else:
                # A bin's width of the truth: the counted share below each quantile brackets its level.
                for q, at in zip(cl.LEVELS, spread[i][:, h]):
                    width = 0.03 * np.hypot(1, at)
                    assert (e < at - width).mean() <= q <= (e <= at + width).mean()


def test_judged(spark, made):
    grid, _, _, pool = made
    held = tg.examples(grid, validation_keys(lengths(grid), CONTEXT, HORIZON), LAGS, CONTEXT, HORIZON).where("size > 1e-6")
    w = cl.fit_linear(pool, len(CELLS), LAGS, HORIZON)
    spread = cl.offsets(pool, w, CELLS)
    x, y, m = (np.array([r[k] for r in held.collect()], float) for k in ("x", "future", "mask"))
    for r in cl.judged(held, w, spread):
        i = r["cell"]
        e = (y - x @ w[i])[m == 1]
        assert (r["se"], r["ae"]) == (pytest.approx((e**2).mean()), pytest.approx(np.abs(e).mean()))
        if CELLS[i].family == "linear":
            # Without a spread the quantile loss is the absolute error.
            assert r["pl"] == pytest.approx(r["ae"])
        loss = [2 * max(q * (v - s[h]), (q - 1) * (v - s[h])) for k, q in enumerate(cl.LEVELS) for s in [spread[i][k]] for j in range(len(y)) for h in range(HORIZON) if m[j, h] == 1 for v in [(y - x @ w[i])[j, h]]]
        assert r["pl"] == pytest.approx(np.mean(loss))


def test_empty_selection_and_table(spark, made):
    grid, scores, _, _ = made
    none = {k: v.where("false") for k, v in scores.items()}
    members = cl.memberships(none, CELLS)
    assert members.count() == 0 and cl.sizes(members).count() == 0
    pool = cl.with_cells(tg.examples(grid, members, LAGS, CONTEXT, HORIZON), members)
    w = cl.fit_linear(pool, len(CELLS), LAGS, HORIZON)
    assert not w.any() and not cl.offsets(pool, w, CELLS).any()


def test_judge_uses_the_slots_of_the_naive_forecast(spark):
    c = ex.Corpus("planted", 120, CONTEXT, HORIZON, 16)
    grid = synth.planted(spark, series=3, length=120).drop("kind")
    judge = ex.Judge(grid, c, LAGS)
    for r in judge.held.collect():
        assert len(r["naive"]) == HORIZON and all(e is not None for e, m in zip(r["naive"], r["mask"]) if m)
    # A target that says the truth of nothing but zero has its own error over that of the naive forecast.
    rows = judge(np.zeros((1, LAGS + 1, HORIZON)), np.zeros((1, 9, HORIZON)))
    truth = [abs(v) for r in judge.held.collect() for v, m in zip(r["future"], r["mask"]) if m]
    assert rows[0][1] == pytest.approx(np.mean(truth) / judge.base)


def test_windows_are_never_broadcast(spark, made):
    """Keys of windows are small files of many rows, which a plan would send to the driver and to every executor."""
    grid, members = made[0], keep(made[2], "members")
    for rows in (tg.examples(grid, members, LAGS, CONTEXT, HORIZON), ex.Judge(grid, ex.Corpus("planted", 120, CONTEXT, HORIZON, 16), LAGS).plan):
        assert "Broadcast" not in rows._jdf.queryExecution().executedPlan().toString()
    plain = cl.with_cells(tg.examples(grid, members.select(*tg.KEY).unionByName(members.select(*tg.KEY)), LAGS, CONTEXT, HORIZON), members)
    at_once = tg.examples(grid, members, LAGS, CONTEXT, HORIZON, ("cells",))
    assert plain.count() == at_once.count() and plain.select(*at_once.columns).exceptAll(at_once).isEmpty()


def test_rankings_are_cut_and_not_sorted_as_a_whole(spark, monkeypatch):
    """Only windows near a rank at which a rule changes are sorted and written, and more cells fit than one number has bits."""
    from lossband.operators import rank

    rows = spark.range(0, 40_000, 1, 4).selectExpr("concat('s', id % 3) as source", "cast(id % 40 as string) as series_id", "id as origin", "cast(pmod(id * 7919, 10007) as double) as rfl", "1L as m", "'ok' as status")
    cells = [cl.Cell("linear", "a", k, f"{p}/12") for k in ("central", "global", "bottom", "top", "random_stratified", "random_global") for p in range(1, 12)] + [cl.Cell("linear", "b", "full"), cl.Cell("linear", "b", "central", "1/12")]
    stored = []
    plain = rank.keep

    def counted(df, name):
        out = plain(df, name)
        stored.append(out.count())
        return out

    monkeypatch.setattr(rank, "keep", counted)
    few = [c for c in cells if c.alpha in ("4/12", "1")]
    assert keep(cl.memberships({"a": rows, "b": rows}, few), "few").count() == 40_000
    # Six rankings of all windows would be 240,000 rows.
    assert max(stored) < 40_000
    got = {tuple(r)[:3]: r["cells"] for r in cl.memberships({"a": rows, "b": rows.where("source <> 's1'")}, cells).collect()}
    table = [(r["source"], r["series_id"], r["origin"], r["rfl"]) for r in rows.collect()]
    assert all(x == sorted(set(x)) for x in got.values())
    assert {k for k, x in got.items() if 66 in x} == {t[:3] for t in table if t[0] != "s1"}
    for i, c in enumerate(cells[:44]):
        want, a = set(), sel.Alpha.of(c.alpha)
        for s in [None] if c.strategy == "global" else ["s0", "s1", "s2"]:
            mine = sorted((t for t in table if s in (None, t[0])), key=lambda t: (t[3], *t[:3]))
            first = {"top": len(mine) - a.kept(len(mine)), "bottom": 0}.get(c.strategy, a.skipped(len(mine)))
            want |= {t[:3] for t in mine[first : first + a.kept(len(mine))]}
        assert {k for k, x in got.items() if i in x} == want, c


def test_squares_beyond_a_long(spark):
    """Sums of many rows a slot: their squares, and their products with the slot, do not fit a long."""
    at = range(CONTEXT + 3 * HORIZON)
    y = [4_000_000_000 + 1_000_003 * (t * t % 17) for t in at]
    grid = spark.createDataFrame([("a", "x", t, v) for t, v in zip(at, y)], "source string, series_id string, t long, y long")
    got = {r["origin"]: r["rfl"] for r in score(grid, ContextGaussian(), CONTEXT, HORIZON).collect()}
    assert len(got) == HORIZON + 1
    for o, loss in got.items():
        past, future = np.array(y[o : o + CONTEXT], float), np.array(y[o + CONTEXT : o + CONTEXT + HORIZON], float)
        assert loss == pytest.approx(0.5 * np.log(2 * np.pi * past.var()) + ((future - past.mean()) ** 2).mean() / (2 * past.var()), rel=1e-3)
