"""A Gram matrix kept up to date by a stream.

A Gram matrix is a sum over rows, so each micro-batch adds its own sums. Kept
products are weighted by one over the probability they were drawn with, which makes
the sum unbiased whatever norms were used at the time: old norms only cost variance.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallgram.functions.draws import unit_draw
from tallgram.operators.gram import all_pairs
from tallgram.operators.norms import attach

#: Smallest probability of a draw: bounds the weight of a product when norms are out of date.
LEAST_P = 1e-4


def weighted_products(rows: DataFrame, norms: DataFrame, gamma: float, seed: int, draw: str = "xxhash64") -> DataFrame:
    """(i, j, dot, n): sums of kept products over their probability, of these rows alone."""
    p = F.greatest(F.lit(LEAST_P), F.least(F.lit(1.0), F.lit(float(gamma)) / (F.col("norm_i") * F.col("norm_j"))))
    pairs = all_pairs(attach(rows, norms), "norm").withColumn("p", p)
    kept = pairs.where((F.col("p") >= 1) | (unit_draw(seed, "row_id", "i", "j", kind=draw) < F.col("p")))
    return kept.groupBy("i", "j").agg(F.sum(F.col("a") * F.col("b") / F.col("p")).alias("dot"), F.count("*").alias("n"))


def start_incremental_gram(rows: DataFrame, norms: DataFrame, gamma: float, seed: int, path: str, checkpoint: str, draw: str = "xxhash64"):
    """Write the sums of each micro-batch to path/batch=<id>, replacing what a failed attempt left. Returns the query.

    rows: a stream in row form whose rows are complete.
    """

    def write(batch: DataFrame, batch_id: int) -> None:
        weighted_products(batch, norms, gamma, seed, draw).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return rows.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def current_gram(spark: SparkSession, path: str) -> DataFrame:
    """(i, j, dot, n) over all batches so far."""
    return spark.read.parquet(path).groupBy("i", "j").agg(F.sum("dot").alias("dot"), F.sum("n").alias("n"))
