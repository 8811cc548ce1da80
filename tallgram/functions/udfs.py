"""User-defined functions: conveniences off the main path, and the SQL surface."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.DoubleType())
def cosine_udf(a: pd.Series, b: pd.Series) -> pd.Series:
    """Cosine of two array columns; null if either is null or has no length."""

    def one(x, y):
        if x is None or y is None:
            return None
        x, y = np.asarray(x, dtype=float), np.asarray(y, dtype=float)
        w = np.sqrt((x * x).sum()) * np.sqrt((y * y).sum())
        return float((x * y).sum() / w) if w else None

    return pd.Series([one(x, y) for x, y in zip(a, b, strict=True)], dtype=object)


@F.pandas_udf(T.DoubleType())
def l2_norm_udaf(v: pd.Series) -> float:
    """Norm of a group's values (a grouped aggregate)."""
    return float(np.sqrt((v.to_numpy(dtype=float) ** 2).sum()))


@F.udtf(returnType=T.StructType([T.StructField("i", T.IntegerType()), T.StructField("j", T.IntegerType()), T.StructField("v", T.DoubleType())]))
class EmitPairs:
    """Table function over a row's entries: every pair i < j with its product."""

    def eval(self, entries):
        items = sorted((e["col"], e["val"]) for e in entries or [])
        for k, (i, a) in enumerate(items):
            for j, b in items[k + 1 :]:
                yield i, j, a * b


def register(spark: SparkSession) -> None:
    """emit_pairs (table function), cosine and unit_draw for SQL."""
    spark.udtf.register("emit_pairs", EmitPairs)
    spark.udf.register("cosine", cosine_udf)
    spark.sql("create or replace temporary function unit_draw(seed int, a bigint, b bigint, c bigint) returns double return shiftrightunsigned(xxhash64(seed, a, b, c), 11) * pow(2D, -53)")


def expand_pairs_arrow(matrix: DataFrame) -> DataFrame:
    """(i, j, v) of every in-row pair by numpy on Arrow batches: for rows so long that generators fall behind."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("entries")
            flat, bounds = lists.flatten(), lists.offsets.to_numpy()
            col, val = flat.field("col").to_numpy(), flat.field("val").to_numpy()
            bounds = bounds - bounds[0]
            for a, b in zip(bounds[:-1], bounds[1:], strict=True):
                p, q = np.triu_indices(b - a, 1)
                if len(p):
                    yield pa.RecordBatch.from_arrays([pa.array(col[a:b][p]), pa.array(col[a:b][q]), pa.array(val[a:b][p] * val[a:b][q])], names=["i", "j", "v"])

    return matrix.select("entries").mapInArrow(run, "i int, j int, v double")
