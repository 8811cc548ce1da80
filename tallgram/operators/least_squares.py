"""Least squares through the normal equations: Gram matrix times x = right side."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.operators.gram import exact_gram, gram_from_cosines
from tallgram.operators.norms import column_norms
from tallgram.operators.sampling import sampled_cosines
from tallgram.operators.spectral import dense


def right_side(matrix: DataFrame, response: str = "y") -> DataFrame:
    """(col, value): each column times the response. One sum by column."""
    entries = matrix.select(F.col(response).cast("double").alias("y"), F.inline("entries"))
    return entries.groupBy("col").agg(F.sum(F.col("val") * F.col("y")).alias("value"))


def normal_equations(matrix: DataFrame, n: int, response: str = "y", gamma: float | None = None, seed: int = 7, draw: str = "xxhash64") -> DataFrame:
    """(col, coefficient). matrix: row form with a response column.

    gamma=None sums the Gram matrix exactly; otherwise it is sampled, for which no
    error bound is known. A singular matrix gets the solution of least length.
    """
    norms = column_norms(matrix)
    if gamma is None:
        upper = exact_gram(matrix.select("row_id", "entries")).select("i", "j", "dot").unionByName(norms.select(F.col("col").alias("i"), F.col("col").alias("j"), F.col("sumsq").alias("dot")))
    else:
        upper = gram_from_cosines(sampled_cosines(matrix.select("row_id", "entries"), gamma, seed, norms, draw).select("i", "j", "cos"), norms)
    gram, right = dense(upper, n), np.zeros(n)
    for r in right_side(matrix, response).collect():
        right[r["col"]] = r["value"]
    x = np.linalg.lstsq(gram, right, rcond=None)[0]
    return matrix.sparkSession.createDataFrame([(c, float(v)) for c, v in enumerate(x)], "col int, coefficient double")
