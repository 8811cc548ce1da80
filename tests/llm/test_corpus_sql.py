"""Corpus queries with SQL give what DuckDB gives."""

from __future__ import annotations

import pytest
from compare import differences

from tallgram.llm import queries as corpus


@pytest.mark.parametrize("name", sorted(corpus.oracle_sql()))
def test_oracle(spark, name):
    assert differences(spark, corpus.queries()[name], corpus.oracle_sql()[name], "/root/testdata/sf0.001") == ""
