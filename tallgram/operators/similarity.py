"""Similar columns: pairs of cosine s or more, wanted pairs, and best partners."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from tallgram.functions.draws import unit_draw
from tallgram.operators.gram import all_pairs, mirror
from tallgram.operators.norms import attach, column_norms
from tallgram.operators.sampling import estimate, pair_emissions
from tallgram.plans.planner import alpha_for, gamma_for_similarity

#: Pairs up to which a wanted-pair list is broadcast (16 bytes each); beyond it is joined by shuffle.
BROADCAST_PAIRS = 2_000_000


def similar_columns(matrix: DataFrame, s: float, alpha: float | None = None, delta: float = 0.5, fail: float = 0.1, method: str = "pair", seed: int = 7, draw: str = "xxhash64", verify: bool = False) -> DataFrame:
    """(i, j, cos) of pairs whose estimate is at least s (1 - delta), cos the estimate.

    Entries must not be negative; budgets are for entries scaled into [0, 1], so gamma
    grows with the square of the largest. Columns of one value only (0/1 matrices)
    can't reach a cosine over the ratio of their norms: such pairs aren't drawn at
    all. With verify, the candidates are summed exactly in a second scan and those of
    cosine s or more stay, cos then being exact.
    """
    from tallgram.operators.matrix import profile

    found = profile(matrix).first()
    if (found["smallest"] or 0) < 0:
        raise ValueError("negative entries: no guarantee for single pairs")
    norms = column_norms(matrix)
    n = found["n"]
    alpha = alpha_for(delta, fail, max(1, n * (n - 1) // 2)) if alpha is None else alpha
    gamma = gamma_for_similarity(s, alpha, method, found["h"] or 1.0) * float(found["most"] or 1.0) ** 2
    if method == "pair":
        kept = pair_emissions(matrix, gamma, seed, norms, draw, least_ratio=s if found["least"] == found["most"] else 0.0)
        sums = kept.groupBy("i", "j").agg(F.sum("v").alias("v"), F.max("w").alias("w"))
        estimates = sums.select("i", "j", (F.col("v") / F.least(F.lit(float(gamma)), F.col("w"))).alias("cos"))
    else:
        estimates = estimate(matrix, method, gamma, seed, norms, draw)
    similar = estimates.where(F.col("cos") >= s * (1 - delta)).select("i", "j", "cos")
    return exact_of(matrix, similar.select("i", "j"), norms).where(F.col("cos") >= s) if verify else similar


def _wanted(pairs: DataFrame) -> DataFrame:
    # kept, since the list is counted, then used: what it comes from would run again each time
    return pairs.select(F.least("i", "j").alias("i"), F.greatest("i", "j").alias("j")).where("i <> j").distinct().persist()


def _wanted_products(matrix: DataFrame, wanted: DataFrame, norms: DataFrame) -> DataFrame:
    """Products of the wanted pairs only: (row_id, i, j, v, w).

    Up to BROADCAST_PAIRS, the list is a broadcast hash table, which pairs meet inside the
    stage that forms them: one look-up a pair, however many partners a column has.
    Beyond that, pairs are joined by a shuffle.
    """
    rows = attach(matrix, norms)
    w = (F.col("norm_i") * F.col("norm_j")).alias("w")
    few = wanted.count() <= BROADCAST_PAIRS
    met = all_pairs(rows, "norm").join(F.broadcast(wanted) if few else wanted, ["i", "j"], "left_semi")
    return met.select("row_id", "i", "j", (F.col("a") * F.col("b")).alias("v"), w)


def exact_of(matrix: DataFrame, pairs: DataFrame, norms: DataFrame | None = None) -> DataFrame:
    """(i, j, cos, dot) of the given pairs, exact; pairs that never co-occur have no row."""
    products = _wanted_products(matrix, _wanted(pairs), column_norms(matrix) if norms is None else norms)
    sums = products.groupBy("i", "j").agg(F.sum("v").alias("dot"), F.max("w").alias("w"))
    return sums.select("i", "j", (F.col("dot") / F.col("w")).alias("cos"), "dot")


def entry_estimates(matrix: DataFrame, pairs: DataFrame, gamma: float, seed: int = 7, norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """(i, j, cos, dot, n_kept) of the given pairs only; 0 where nothing was kept."""
    g = F.lit(float(gamma))
    wanted = _wanted(pairs)
    products = _wanted_products(matrix, wanted, column_norms(matrix) if norms is None else norms)
    kept = products.where((F.col("w") <= g) | (unit_draw(seed, "row_id", "i", "j", kind=draw) < g / F.col("w")))
    sums = kept.groupBy("i", "j").agg(F.sum("v").alias("v"), F.count("*").alias("n_kept"), F.max("w").alias("w"))
    found = sums.select("i", "j", (F.col("v") / F.least(g, F.col("w"))).alias("cos"), (F.col("v") / F.least(g, F.col("w")) * F.col("w")).alias("dot"), "n_kept")
    return wanted.join(found, ["i", "j"], "left").select("i", "j", F.coalesce("cos", F.lit(0.0)).alias("cos"), F.coalesce("dot", F.lit(0.0)).alias("dot"), F.coalesce("n_kept", F.lit(0)).alias("n_kept"))


def top_k_similar(cosines: DataFrame, k: int) -> DataFrame:
    """(i, j, cos, rank): the k best partners of every column, ties by the smaller partner."""
    best = Window.partitionBy("i").orderBy(F.desc("cos"), "j")
    return mirror(cosines.select("i", "j", "cos")).withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def norm_compatible_pairs(norms: DataFrame, s: float) -> DataFrame:
    """(i, j) whose norms allow a cosine of s between 0/1 columns: smaller over larger norm is s or more.

    Norms are sorted into geometric bands of ratio s, so only columns of the same or
    neighbouring bands meet.
    """
    banded = norms.where("norm > 0").select("col", "norm", F.floor(F.log("norm") / F.log(F.lit(1 / s))).alias("band"))
    left = banded.select(F.col("col").alias("x"), F.col("norm").alias("norm_x"), F.explode(F.array(F.col("band") - 1, F.col("band"), F.col("band") + 1)).alias("band"))
    right = banded.select(F.col("col").alias("y"), F.col("norm").alias("norm_y"), "band")
    near = F.least("norm_x", "norm_y") >= F.greatest("norm_x", "norm_y") * F.lit(s)
    return left.join(right, "band").where((F.col("x") < F.col("y")) & near).select(F.col("x").alias("i"), F.col("y").alias("j"))


def pair_recall(estimates: DataFrame, exact: DataFrame, s: float) -> DataFrame:
    """One row: n_similar (pairs of exact cosine s or more), n_found, n_common, precision, recall."""
    a = estimates.where(F.col("cos") >= s).select("i", "j", F.lit(1).alias("found"))
    b = exact.where(F.col("cos") >= s).select("i", "j", F.lit(1).alias("similar"))
    counts = a.join(b, ["i", "j"], "full").agg(F.count("similar").alias("n_similar"), F.count("found").alias("n_found"), F.count(F.col("similar") + F.col("found")).alias("n_common"))
    ratio = lambda of: F.col("n_common") / F.nullif(of, F.lit(0))
    return counts.select("*", ratio("n_found").alias("precision"), ratio("n_similar").alias("recall"))
