"""Accuracy measures of repeated estimates against exact cosines.

A pair that a seed never kept has estimate 0 and no row. All measures here start
from the grid of seeds and co-occurring pairs, so such pairs count.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.operators.differences import sampled_difference_norms
from tallgram.operators.spectral import dense, sparse_norms, spectral_norm


def grid(estimates: DataFrame, exact: DataFrame, seeds: list[int]) -> DataFrame:
    """(seed, i, j, exact, cos): every seed for every co-occurring pair, 0 where nothing was kept."""
    cells = exact.select("i", "j", F.col("cos").alias("exact"), F.explode(F.array(*[F.lit(s) for s in seeds])).alias("seed"))
    return cells.join(estimates.select("seed", "i", "j", "cos"), ["seed", "i", "j"], "left").select("seed", "i", "j", "exact", F.coalesce("cos", F.lit(0.0)).alias("cos"))


def entry_moments(cells: DataFrame) -> DataFrame:
    """(i, j, bias, variance, fourth): moments over seeds about the exact value."""
    off = F.col("cos") - F.col("exact")
    return cells.groupBy("i", "j").agg(F.avg(off).alias("bias"), F.avg(off * off).alias("variance"), F.avg(off * off * off * off).alias("fourth"))


def moment_bounds(gamma: float) -> tuple[float, float]:
    """Bounds on variance and fourth central moment of an entry (the latter with its count of paired indices right)."""
    return 1 / gamma, 3 / gamma**2 + 1 / gamma**3


def tail_rates(cells: DataFrame, delta: float, s: float = 0.0) -> DataFrame:
    """One row: share of (pair, seed) over (1 + delta) and under (1 - delta) times the exact value, pairs of cosine s or more."""
    over, under = F.col("cos") > F.col("exact") * (1 + delta), F.col("cos") < F.col("exact") * (1 - delta)
    return cells.where(F.col("exact") >= s).agg(F.count("*").alias("cells"), F.avg(over.cast("double")).alias("over"), F.avg(under.cast("double")).alias("under"))


#: Columns up to which differences are decomposed as dense matrices in the driver (8 n^2 bytes); beyond, by Lanczos steps.
DENSE_COLUMNS = 1_000


def gram_norm(gram: DataFrame, n: int) -> float:
    """Spectral norm of a Gram matrix (i <= j, dot)."""
    return spectral_norm(dense(gram, n)) if n <= DENSE_COLUMNS else sparse_norms(gram, n, ["dot"])[0]


def spectral_errors(estimates: DataFrame, norms: DataFrame, gram: DataFrame, n: int, seeds: list[int], base: float | None = None) -> list[float]:
    """Relative spectral error under each seed; cosines are scaled back by the norms, the diagonal is exact.

    base is the norm of the exact matrix, where it is known. All seeds' differences
    are made in one pass; an estimate has no pair that the exact matrix lacks.
    """
    base = gram_norm(gram, n) if base is None else base
    if not base:
        return [0.0] * len(seeds)
    names = [f"d{k}" for k in range(len(seeds))]
    wide = estimates.groupBy("i", "j").agg(*[F.max(F.when(F.col("seed") == int(s), F.col("cos"))).alias(d) for s, d in zip(seeds, names, strict=True)])
    of = lambda k: norms.select(F.col("col").alias(k), F.col("norm").alias(f"norm_{k}"))
    pairs = gram.where("i < j").join(wide, ["i", "j"], "left").join(of("i"), "i").join(of("j"), "j")
    off = pairs.select("i", "j", *[(F.coalesce(d, F.lit(0.0)) * F.col("norm_i") * F.col("norm_j") - F.col("dot")).alias(d) for d in names])
    if n > DENSE_COLUMNS:
        return [x / base for x in sparse_norms(off, n, names)]
    off = off.persist()
    errors = [spectral_norm(dense(off, n, d)) / base for d in names]
    off.unpersist()
    return errors


def sampled_errors(triplets: DataFrame, n: int, runs: list[tuple[str, float]], seeds: list[int]) -> list[list[float]]:
    """``spectral_errors`` of ``sampling.repeated_estimates`` for each of runs (method, gamma), for many columns: no pairs in an exchange."""
    base, found = sampled_difference_norms(triplets, n, runs, seeds)
    return [[x / base if base else 0.0 for x in of] for of in found]


def success_rate(errors: list[float], eps: float) -> float:
    return sum(e <= eps for e in errors) / max(1, len(errors))


def cosine_error(estimate: np.ndarray, exact: np.ndarray) -> float:
    """Spectral norm of the difference of two cosine matrices."""
    return spectral_norm(estimate - exact)


def sigma_errors(sigma_estimate: np.ndarray, sigma: np.ndarray) -> np.ndarray:
    """Differences of squared singular values; none exceeds the spectral norm of the Gram difference."""
    return np.abs(sigma_estimate**2 - sigma**2)


def concentration_bound(moments: DataFrame) -> DataFrame:
    """One row: largest row root mean square, largest column one, and the fourth-moment term, and their sum.

    The right side of the moment inequality for the spectral norm of a matrix of
    independent centred entries, up to its constant; symmetric, so rows and columns agree.
    """
    both = moments.select("i", "j", "variance", "fourth").unionByName(moments.select(F.col("j").alias("i"), F.col("i").alias("j"), "variance", "fourth"))
    rows = both.groupBy("i").agg(F.sum("variance").alias("v"), F.sum("fourth").alias("q"))
    sums = rows.agg(F.sqrt(F.max("v")).alias("row_term"), F.pow(F.sum("q"), F.lit(0.25)).alias("fourth_term"))
    return sums.select("row_term", F.col("row_term").alias("column_term"), "fourth_term", (2 * F.col("row_term") + F.col("fourth_term")).alias("total"))
