"""What plans must and must not hold at scale."""

import io
from contextlib import redirect_stdout

from lossband.operators import rank, scoring
from lossband.queries.common import grid

SF = "/root/testdata/sf0.001"


def plan(df):
    out = io.StringIO()
    with redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


def test_scoring_adds_no_shuffle_to_the_grid(spark):
    g = grid(spark, SF)
    a = plan(g).count("Exchange (")
    b = plan(scoring.score(g, scoring.SeasonalNaive(24), 48, 24)).count("Exchange (")
    assert b == a


def test_scan_reads_only_what_it_needs(spark):
    text = plan(grid(spark, SF))
    assert "props" not in text and "user_id" not in text


def test_no_window_without_partition(spark):
    scores = scoring.score(grid(spark, SF), scoring.SeasonalNaive(24), 48, 24)
    for by in ("source", None):
        assert "Exchange SinglePartition" not in plan(rank.distributed(scores, by, parts=3)).replace("ENSURE_REQUIREMENTS", "")


def test_bounds_are_part_of_the_sequence(spark):
    from lossband.operators.windows import lengths, window_keys

    assert "Join" not in plan(window_keys(lengths(grid(spark, SF)), 48, 24, held_out=True))
