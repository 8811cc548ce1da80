"""Cost measures: emissions, values of a key, draws, and what is expected of them."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.operators.gram import all_pairs
from tallgram.operators.norms import attach, column_norms
from tallgram.operators.sampling import pair_emissions, staged_emissions, thinned_emissions


def _kept(matrix: DataFrame, method: str, gamma: float, seed: int, norms: DataFrame | None, draw: str) -> DataFrame:
    if method == "exact":
        return all_pairs(matrix).select("i", "j")
    kinds = {"pair": pair_emissions, "staged": staged_emissions, "thinned": thinned_emissions}
    return kinds[method](matrix, gamma, seed, norms, draw).select("i", "j")


def emissions(matrix: DataFrame, method: str, gamma: float = math.inf, seed: int = 7, norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """One row: method, emissions (records before any combining), n_keys, max_key (values of the fullest key)."""
    keys = _kept(matrix, method, gamma, seed, norms, draw).groupBy("i", "j").agg(F.count("*").alias("n"))
    return keys.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("emissions"), F.count("*").alias("n_keys"), F.coalesce(F.max("n"), F.lit(0)).alias("max_key")).select(F.lit(method).alias("method"), "*")


def combined_records(matrix: DataFrame, method: str, gamma: float = math.inf, seed: int = 7, draw: str = "xxhash64") -> DataFrame:
    """One row: records that are left for the shuffle when each task sums its own first."""
    kept = _kept(matrix, method, gamma, seed, None, draw).withColumn("task", F.spark_partition_id())
    return kept.select("task", "i", "j").distinct().agg(F.count("*").alias("records"))


def shuffled(df: DataFrame, last: bool = True) -> tuple[int, int]:
    """(records, bytes) that the last exchange of df's plan (or all of them) wrote to shuffle files, after running it.

    Read from the metrics of the plan that ran: bytes are those of serialised, compressed
    records, what a network would carry.
    """
    execution = df._jdf.queryExecution()
    execution.toRdd().count()
    found: list[tuple[int, int]] = []

    def walk(node) -> None:
        kind = node.getClass().getSimpleName()
        if kind == "AdaptiveSparkPlanExec":
            return walk(node.executedPlan())
        if kind.endswith("QueryStageExec"):
            return walk(node.plan())
        if kind == "ShuffleExchangeExec":
            metrics = node.metrics()
            found.append(tuple(int(metrics.apply(k).value()) for k in ("shuffleRecordsWritten", "shuffleBytesWritten")))
        children = node.children()
        for k in range(children.size()):
            walk(children.apply(k))

    walk(execution.executedPlan())
    found = found[:1] if last else found
    return sum(r for r, _ in found), sum(b for _, b in found)


def expected_emissions(matrix: DataFrame, gamma: float, norms: DataFrame | None = None, method: str = "pair", row_share: float = 1.0, seed: int = 7) -> DataFrame:
    """One row: expected emissions, and the naive number of products.

    row_share < 1 reads a hash sample of the rows and scales up: what the planner uses.
    """
    from tallgram.functions.draws import unit_draw

    norms = column_norms(matrix) if norms is None else norms
    rows = matrix if row_share >= 1 else matrix.where(unit_draw(seed, F.lit("rows"), "row_id") < row_share)
    pairs = all_pairs(attach(rows, norms), "norm")
    g, root = F.lit(float(gamma)), F.lit(math.sqrt(gamma))
    p = F.least(F.lit(1.0), g / (F.col("norm_i") * F.col("norm_j"))) if method == "pair" else F.least(F.lit(1.0), root / F.col("norm_i")) * F.least(F.lit(1.0), root / F.col("norm_j"))
    return pairs.agg((F.coalesce(F.sum(p), F.lit(0.0)) / F.lit(row_share)).alias("expected"), (F.count("*") / F.lit(row_share)).alias("naive"))


def naive_cost(matrix: DataFrame) -> DataFrame:
    """One row: products of the baseline, and rows (the most values one key can get)."""
    return matrix.agg(F.sum(F.expr("size(entries) * (size(entries) - 1L) div 2")).alias("emissions"), F.count("*").alias("key_limit"))


def draw_count(matrix: DataFrame, method: str, gamma: float = math.inf, seed: int = 7, norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """One row: random draws. pair: one a pair; staged: one an entry, one a later partner of a kept entry; thinned: one an entry."""
    from tallgram.operators.sampling import _kept_entries

    size = F.size("entries").cast("long")
    if method == "pair":
        return matrix.agg(F.sum(F.expr("size(entries) * (size(entries) - 1L) div 2")).alias("draws"))
    if method == "thinned":
        return matrix.agg(F.sum(size).alias("draws"))
    rows = _kept_entries(attach(matrix, column_norms(matrix) if norms is None else norms), gamma, seed, "first", draw, "heads")
    later = F.aggregate("heads", F.lit(0).cast("long"), lambda n, h: n + F.size(F.filter("entries", lambda e: e["col"] > h["col"])).cast("long"))
    return rows.agg(F.sum(size + later).alias("draws"))


def max_abs_entry(matrix: DataFrame) -> DataFrame:
    return matrix.agg(F.max(F.array_max(F.transform("entries", lambda e: F.abs(e["val"])))).alias("most"))

