"""Matrix forms, their conversion, cleaning, scaling and profile.

*Triplets* are (row_id, col, val). *Row form* is (row_id, entries), entries sorted
by col, without zeros and with each col once. Pairs form inside a row, so in row
form nothing but sums moves afterwards; getting there is the one shuffle of all
entries, and a matrix stored in row form never needs it again.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

TRIPLETS = T.StructType([T.StructField("row_id", T.LongType()), T.StructField("col", T.IntegerType()), T.StructField("val", T.DoubleType())])
ENTRY = T.StructType([T.StructField("col", T.IntegerType(), False), T.StructField("val", T.DoubleType(), False)])
ROW_FORM = T.StructType([T.StructField("row_id", T.LongType()), T.StructField("entries", T.ArrayType(ENTRY, False))])


def drop_invalid(triplets: DataFrame, on_bad: str = "drop") -> DataFrame:
    """Without zeros (-0.0 too), nulls, NaN and infinities; on_bad="raise" fails on the last three."""
    val = F.col("val")
    bad = F.col("row_id").isNull() | F.col("col").isNull() | val.isNull() | F.isnan(val) | (F.abs(val) == F.lit(float("inf")))
    if on_bad == "raise":
        checked = F.when(bad, F.raise_error(F.lit("null, NaN or infinite matrix entry"))).otherwise(val)
        return triplets.withColumn("val", checked).where(F.col("val") != 0)
    if on_bad != "drop":
        raise ValueError("on_bad is 'drop' or 'raise'")
    return triplets.where(~bad & (val != 0))


def to_row_form(triplets: DataFrame) -> DataFrame:
    """Row form of triplets: duplicates summed, zeros dropped. One shuffle, by row."""
    one_place = triplets.select(F.col("row_id").cast("long"), F.col("col").cast("int"), F.col("val").cast("double")).repartition("row_id")
    summed = one_place.groupBy("row_id", "col").agg(F.sum("val").alias("val")).where("val <> 0")
    return summed.groupBy("row_id").agg(F.sort_array(F.collect_list(F.struct("col", "val"))).alias("entries"))


def to_triplets(matrix: DataFrame) -> DataFrame:
    return matrix.select("row_id", F.inline("entries"))


def row_as_map(matrix: DataFrame) -> DataFrame:
    """(row_id, map of col to val), for export."""
    return matrix.select("row_id", F.map_from_entries("entries").alias("row"))


def dense_rows(df: DataFrame, row_id: str, values: str) -> DataFrame:
    """Row form of an array column: position is the column, zeros are dropped. Narrow."""
    entry = F.transform(F.col(values), lambda x, i: F.struct(i.cast("int").alias("col"), x.cast("double").alias("val")))
    return df.select(F.col(row_id).cast("long").alias("row_id"), F.filter(entry, lambda e: (e["val"] != 0) & ~F.isnan(e["val"])).alias("entries"))


def column_dictionary(labelled: DataFrame, label: str = "label") -> DataFrame:
    """(label, col): labels in order, numbered from 0. As many rows as the matrix has columns."""
    labels = labelled.select(label).where(F.col(label).isNotNull()).distinct()
    return labels.select(F.col(label), (F.row_number().over(Window.orderBy(label)) - 1).alias("col"))


def encode_columns(labelled: DataFrame, label: str = "label") -> tuple[DataFrame, DataFrame]:
    """Triplets with numbered columns, and the dictionary. labelled: row_id, label, val."""
    dictionary = column_dictionary(labelled, label)
    return labelled.join(F.broadcast(dictionary), label).select("row_id", "col", "val"), dictionary


def min_support(labelled: DataFrame, k: int, label: str = "label") -> DataFrame:
    """Rows whose label occurs k times or more."""
    often = labelled.groupBy(label).agg(F.count("*").alias("_n")).where(F.col("_n") >= k).select(label)
    return labelled.join(often, label, "left_semi")


#: Columns of a row that was dealt out: first entries to skip, and how many are its own.
SPLIT = ("head_from", "head_count")


def split_heavy(matrix: DataFrame, heads: int) -> DataFrame:
    """Rows of more than ``heads`` entries dealt out: each piece has all entries but only ``heads`` first partners of its own.

    Pairs form inside a row, so a row of L entries is one task's L^2/2 pairs; its
    pieces lie in several tasks. Only rows over the bound move. Norms must come from
    the matrix as it was; draws, and so results, stay the same.
    """
    pieces = F.explode(F.sequence(F.lit(0), F.size("entries") - 1, F.lit(int(heads))))
    light = matrix.where(F.size("entries") <= heads).select("*", F.lit(0).alias(SPLIT[0]), F.size("entries").alias(SPLIT[1]))
    heavy = matrix.where(F.size("entries") > heads).select("*", pieces.alias(SPLIT[0]), F.lit(int(heads)).alias(SPLIT[1]))
    return light.unionByName(heavy.repartition("row_id", SPLIT[0]))


def cap_rows(matrix: DataFrame, most: int) -> DataFrame:
    """Without rows of more than ``most`` entries. Changes the matrix: results are of what is left."""
    return matrix.where(F.size("entries") <= most)


def keep_entries(matrix: DataFrame, predicate) -> DataFrame:
    """Entries for which predicate(entry column) holds."""
    return matrix.withColumn("entries", F.filter("entries", predicate))


def map_values(matrix: DataFrame, value) -> DataFrame:
    """Entries with value(val column) for val; zeros go."""
    changed = F.transform("entries", lambda e: F.struct(e["col"].alias("col"), value(e["val"]).cast("double").alias("val")))
    return matrix.withColumn("entries", F.filter(changed, lambda e: e["val"] != 0))


def binarise(matrix: DataFrame) -> DataFrame:
    return map_values(matrix, lambda v: F.lit(1.0))


def clip_entries(matrix: DataFrame, low: float, high: float) -> DataFrame:
    return map_values(matrix, lambda v: F.least(F.greatest(v, F.lit(low)), F.lit(high)))


def _per_row(value) -> Column:
    return F.transform("entries", value)


def max_abs(matrix: DataFrame) -> float:
    """Largest magnitude, 0 for an empty matrix. One scan, one number a partition."""
    return matrix.agg(F.max(F.array_max(_per_row(lambda e: F.abs(e["val"]))))).first()[0] or 0.0


def scale_entries(matrix: DataFrame, by: float | None = None) -> DataFrame:
    """Entries divided by the largest magnitude (or by ``by``), so they lie in [-1, 1]."""
    by = max_abs(matrix) if by is None else by
    return matrix if not by else map_values(matrix, lambda v: v / F.lit(float(by)))


def profile(matrix: DataFrame) -> DataFrame:
    """One row: m, n, nnz, row_max (L), least (smallest magnitude), most, smallest, exact emissions, density.

    ``h`` is least/most, the smallest magnitude after scaling.
    """
    size = F.size("entries").cast("long")
    magnitudes = _per_row(lambda e: F.abs(e["val"]))
    rows = matrix.agg(
        F.count("*").alias("m"), F.sum(size).alias("nnz"), F.max(size).alias("row_max"), F.min(F.array_min(magnitudes)).alias("least"), F.max(F.array_max(magnitudes)).alias("most"),
        F.min(F.array_min(_per_row(lambda e: e["val"]))).alias("smallest"), F.sum(F.expr("size(entries) * (size(entries) - 1L) div 2")).alias("pairs"),
    )
    columns = matrix.select(F.explode(_per_row(lambda e: e["col"])).alias("col")).agg(F.count_distinct("col").alias("n"))
    both = rows.crossJoin(columns)
    return both.select("m", "n", F.coalesce("nnz", F.lit(0)).alias("nnz"), F.coalesce("row_max", F.lit(0)).alias("row_max"), "least", "most", "smallest", F.coalesce("pairs", F.lit(0)).alias("pairs"), (F.col("least") / F.col("most")).alias("h"), (F.col("nnz") / (F.col("m") * F.col("n"))).alias("density"))
