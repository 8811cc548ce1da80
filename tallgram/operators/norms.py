"""Column norms: one row a column, and attached to the entries of every row."""

from __future__ import annotations

import weakref

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Columns up to which norms travel as one broadcast array (8 bytes each).
BROADCAST_COLUMNS = 1_000_000

#: Arrays of norms that are known already, as long as their DataFrame lives: each is computed once.
_known: weakref.WeakKeyDictionary[DataFrame, DataFrame] = weakref.WeakKeyDictionary()


def column_norms(matrix: DataFrame) -> DataFrame:
    """(col, nnz, sumsq, norm). Sums meet by column after a partial sum in each task."""
    entries = matrix.select(F.inline("entries"))
    return entries.groupBy("col").agg(F.count("*").alias("nnz"), F.sum(F.col("val") * F.col("val")).alias("sumsq")).withColumn("norm", F.sqrt("sumsq"))


def _one_row(norms: DataFrame) -> DataFrame | None:
    """All norms as one array, or None if there are more than BROADCAST_COLUMNS columns. One job for each norms table."""
    if norms not in _known:
        found = norms.select("col", "norm").limit(BROADCAST_COLUMNS + 1).toArrow()
        col = found.column("col").to_numpy()
        if len(col) > BROADCAST_COLUMNS or (len(col) and col.max() >= BROADCAST_COLUMNS):
            _known[norms] = None
        else:
            values = np.zeros(int(col.max()) + 1 if len(col) else 0)
            values[col] = found.column("norm").to_numpy()
            _known[norms] = norms.sparkSession.createDataFrame(pa.table({"norms": pa.array([values], pa.list_(pa.float64()))}))
    return _known[norms]


def attach(matrix: DataFrame, norms: DataFrame) -> DataFrame:
    """Row form (and any other columns) whose entries also carry the norm of their column. Narrow: the norms are broadcast once.

    Over BROADCAST_COLUMNS columns, entries meet their norm by a join and rows are put together again.
    """
    one_row, others = _one_row(norms), [c for c in matrix.columns if c not in ("row_id", "entries")]
    if one_row is None:
        entries = matrix.select("row_id", *others, F.inline("entries")).join(norms.select("col", "norm"), "col")
        return entries.groupBy("row_id", *others).agg(F.sort_array(F.collect_list(F.struct("col", "val", "norm"))).alias("entries"))
    with_norm = F.transform("entries", lambda e: F.struct(e["col"].alias("col"), e["val"].alias("val"), F.get("norms", e["col"]).alias("norm")))
    return matrix.crossJoin(F.broadcast(one_row)).select("row_id", *others, F.filter(with_norm, lambda e: e["norm"] > 0).alias("entries"))
