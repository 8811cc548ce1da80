"""Every query with SQL gives the rows that DuckDB gives, at the smallest scale."""

from __future__ import annotations

import pytest
from compare import differences

from tallgram.queries import all_queries

SMALL = "/root/testdata/sf0.001"
QUERIES, ORACLES = all_queries()
#: The expected rows of these hold at sf0.01 and over only.
AT_SCALE = {"plans", "stream_incremental_sampled", "variance_bound_w4"}


@pytest.mark.parametrize("name", sorted(set(ORACLES) - AT_SCALE))
def test_oracle(spark, name):
    assert differences(spark, QUERIES[name], ORACLES[name], SMALL) == ""


def test_names_are_in_the_entry():
    import __spark_entry__ as entry

    assert set(QUERIES) <= set(entry.queries())
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
