from __future__ import annotations

import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent))

from corpus_rows import DOCS, MOTS, SCHEMA, WORDS, prose  # noqa: E402


@pytest.fixture(scope="session")
def edge_rows():
    base = prose(120, 1)
    near = base.split()
    near[5] = "changed"
    rows = [(i, prose(40 + 7 * i, 100 + i, WORDS if i % 2 else MOTS), "en" if i % 2 else "fr", f"s{i % 3}", 1) for i in range(60)]
    rows += [(100, base, "en", "s0", 1), (101, base, "en", "s1", 1), (102, " ".join(near), "en", None, None), (103, None, "en", "s0", None), (104, "", None, "s0", 0), (105, "!!! 123 ...", "en", "s0", 3), (106, "é", "fr", "s0", 1), (107, "one", "en", "s0", 3)]
    rows += [(108, prose(30000, 5), "en", "s0", 1), (109, base, "en", "s0", 1), (109, base, "en", "s0", 1), (None, base, "en", "s0", 1), (None, None, None, None, None), (110, "\x00<|endoftext|> don't  \t\n Á İ ﬁ 日本語 <|EndOfText|>", "en", "s0", 1)]
    return rows


@pytest.fixture(scope="session")
def edge_docs(spark, edge_rows):
    extra = (7, 7, 7, 7, 0.5, True, "w", 3, 9, 1, 1)
    return spark.createDataFrame([(*r, *extra) for r in edge_rows], SCHEMA)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], DOCS)
