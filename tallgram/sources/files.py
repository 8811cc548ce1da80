"""Files of matrices: reading triplets in several formats, and sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallgram.operators.matrix import ROW_FORM, TRIPLETS

_DDL = "row_id long, col int, val double"


def load_triplets(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Triplets from csv (with header), json, orc, parquet or text (fields split by tabs)."""
    if fmt == "csv":
        return spark.read.schema(TRIPLETS).option("header", True).csv(path)
    if fmt == "text":
        fields = F.split("value", "\t")
        return spark.read.text(path).select(fields[0].cast("long").alias("row_id"), fields[1].cast("int").alias("col"), fields[2].cast("double").alias("val"))
    if fmt in ("json", "orc", "parquet"):
        return spark.read.schema(TRIPLETS).format(fmt).load(path)
    raise ValueError(f"unknown format {fmt!r}")


def save_triplets(triplets: DataFrame, path: str, fmt: str = "parquet") -> None:
    rows = triplets.select("row_id", "col", "val")
    if fmt == "csv":
        rows.write.option("header", True).csv(path)
    elif fmt == "text":
        rows.select(F.concat_ws("\t", *[F.col(c).cast("string") for c in rows.columns])).write.text(path)
    else:
        rows.write.format(fmt).save(path)


def save_rows(matrix: DataFrame, path: str, by: str | None = None) -> None:
    """Row form as Parquet, in folders of ``by`` if given: stored once, read without a shuffle."""
    writer = matrix.write
    (writer.partitionBy(by) if by else writer).parquet(path)


def load_rows(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(ROW_FORM).parquet(path)


def save_bucketed(triplets: DataFrame, name: str, n: int) -> None:
    """A table bucketed and sorted by row, so that later joins and groupings by row need no shuffle."""
    triplets.write.bucketBy(n, "row_id").sortBy("row_id", "col").mode("overwrite").saveAsTable(name)


def save_pairs(pairs: DataFrame, path: str, block: int = 1000) -> None:
    """Pairs in folders of ``block`` first columns each. A folder is one task's: otherwise every task would leave a file in each."""
    pairs.withColumn("i_block", F.expr(f"i div {int(block)}")).repartition("i_block").write.partitionBy("i_block").parquet(path)


def load_pairs(spark: SparkSession, path: str, i_from: int | None = None, i_to: int | None = None, block: int = 1000) -> DataFrame:
    """Pairs back, only the folders between two first columns if given."""
    rows = spark.read.parquet(path)
    if i_from is not None:
        rows = rows.where((F.col("i_block") >= i_from // block) & (F.col("i") >= i_from))
    if i_to is not None:
        rows = rows.where((F.col("i_block") <= i_to // block) & (F.col("i") <= i_to))
    return rows.drop("i_block")
