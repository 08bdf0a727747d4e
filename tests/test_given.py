"""Reports that once were made of literals, on the given tables."""

import oracle
import pytest

from lossband import queries

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["budget_report", "margins_table", "published_central_counts"])
def test_reads_given_tables(spark, name):
    df = queries.queries()[name](spark, SF)
    assert any("lineitem" in f or "lossband-tables" in f for f in df.inputFiles())
    assert oracle.differences(df, oracle.views(SF), queries.oracles()[name]) == ""
