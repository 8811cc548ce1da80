"""Norm-weighted sampling of in-row products.

A product of columns i and j is kept with a probability p that falls with the norms
of both; what is kept counts 1/p. The estimate of the dot product is unbiased for
any p, and its records don't grow with the number of rows. Methods differ in how
the draw is made:

pair      one draw for each pair, p = min(1, gamma / (norm_i norm_j))
staged    a draw for the first entry, then one for each partner
thinned   one draw for each entry; what survives pairs up
uniform   one draw for each pair with the same p everywhere (for contrast)

All methods draw before the products leave their row, so the draw sits right above
the generators, inside the stage that reads the rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tallgram.functions.draws import unit_draw
from tallgram.operators.gram import all_pairs
from tallgram.operators.matrix import SPLIT
from tallgram.operators.norms import attach, column_norms


def _rows(matrix: DataFrame, norms: DataFrame | None) -> DataFrame:
    return attach(matrix, column_norms(matrix) if norms is None else norms)


def _gamma(gamma: float) -> Column:
    if not gamma > 0:
        raise ValueError("gamma must be positive")
    return F.lit(float(gamma))


Seed = int | Column


def pair_emissions(matrix: DataFrame, gamma: float, seed: Seed, norms: DataFrame | None = None, draw: str = "xxhash64", least_ratio: float = 0.0) -> DataFrame:
    """Kept products: (i, j, v, w), w the product of the norms, and other columns of the matrix.

    least_ratio > 0 leaves out pairs whose smaller norm is less than that share of the larger.
    """
    g = _gamma(gamma)
    pairs = all_pairs(_rows(matrix, norms), "norm").withColumn("w", F.col("norm_i") * F.col("norm_j"))
    if least_ratio > 0:
        pairs = pairs.where(F.least("norm_i", "norm_j") >= F.greatest("norm_i", "norm_j") * F.lit(float(least_ratio)))
    if math.isfinite(gamma):
        pairs = pairs.where((F.col("w") <= g) | (unit_draw(seed, "row_id", "i", "j", kind=draw) < g / F.col("w")))
    return pairs.select(*_others(matrix), "i", "j", (F.col("a") * F.col("b")).alias("v"), "w")


def _others(matrix: DataFrame) -> list[str]:
    return [c for c in matrix.columns if c not in ("row_id", "entries", *SPLIT)]


def sampled_cosines(matrix: DataFrame, gamma: float, seed: int = 7, norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """(i, j, cos, dot, n_kept, p, is_exact). Where gamma >= w every product is kept and the cosine is exact.

    gamma = inf keeps all products of all pairs: the exact cosines.
    """
    g = _gamma(gamma)
    sums = pair_emissions(matrix, gamma, seed, norms, draw).groupBy("i", "j").agg(F.sum("v").alias("v"), F.count("*").alias("n_kept"), F.max("w").alias("w"))
    cos = F.col("v") / F.least(g, F.col("w"))
    return sums.select("i", "j", cos.alias("cos"), (cos * F.col("w")).alias("dot"), "n_kept", F.least(F.lit(1.0), g / F.col("w")).alias("p"), (g >= F.col("w")).alias("is_exact"))


def _kept_entries(rows: DataFrame, gamma: float, seed: Seed, salt: str, draw: str, name: str) -> DataFrame:
    """rows with an array of the entries that survive their own draw, keep rate min(1, sqrt(gamma)/norm)."""
    s = F.lit(math.sqrt(gamma))
    survives = lambda e: (e["norm"] <= s) | (unit_draw(seed, F.lit(salt), F.col("row_id"), e["col"], kind=draw) < s / e["norm"])
    return rows.withColumn(name, F.filter("entries", survives))


def staged_emissions(matrix: DataFrame, gamma: float, seed: Seed, norms: DataFrame | None = None, draw: str = "xxhash64", order: str = "upper") -> DataFrame:
    """Products kept by two draws in turn, already normalised: (i, j, v)."""
    _gamma(gamma)
    s = F.lit(math.sqrt(gamma))
    if order not in ("upper", "both"):
        raise ValueError("order is 'upper' or 'both'")
    others, rows = _others(matrix), _rows(matrix, norms)
    split = SPLIT[0] in rows.columns
    own = F.slice("entries", F.col(SPLIT[0]) + 1, F.col(SPLIT[1])) if split else F.col("entries")
    skipped = F.col(SPLIT[0]) if split else F.lit(0)
    first = rows.select("row_id", *others, "entries", skipped.alias("_skipped"), F.posexplode(own).alias("_at", "a"))
    first = first.where((F.col("a.norm") <= s) | (unit_draw(seed, F.lit("first"), F.col("row_id"), F.col("a.col"), kind=draw) < s / F.col("a.norm")))
    # entries are in order of columns: the later partners are a slice
    partners = F.slice("entries", F.col("_at") + F.col("_skipped") + 2, F.size("entries")) if order == "upper" else F.col("entries")
    survives = (F.col("b.norm") <= s) | (unit_draw(seed, F.lit("second"), F.col("row_id"), F.col("a.col"), F.col("b.col"), kind=draw) < s / F.col("b.norm"))
    both = first.select("row_id", *others, "a", F.explode(partners).alias("b")).where((F.col("b.col") != F.col("a.col")) & survives)
    v = F.col("a.val") * F.col("b.val") / (F.least(s, F.col("a.norm")) * F.least(s, F.col("b.norm")))
    return both.select(*others, F.least("a.col", "b.col").alias("i"), F.greatest("a.col", "b.col").alias("j"), v.alias("v"))


def staged_cosines(matrix: DataFrame, gamma: float, seed: int = 7, norms: DataFrame | None = None, draw: str = "xxhash64", order: str = "upper") -> DataFrame:
    """(i, j, cos, n_kept). order="both" draws each pair from either side and averages."""
    share = 0.5 if order == "both" else 1.0
    kept = staged_emissions(matrix, gamma, seed, norms, draw, order)
    return kept.groupBy("i", "j").agg((F.sum("v") * F.lit(share)).alias("cos"), F.count("*").alias("n_kept"))


def thinned_emissions(matrix: DataFrame, gamma: float, seed: Seed, norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """Products of entries that both survived one draw each, normalised: (i, j, v)."""
    _gamma(gamma)
    s = F.lit(math.sqrt(gamma))
    if SPLIT[0] in matrix.columns:
        raise ValueError("thinned rows are short: thin the matrix as it is")
    others = _others(matrix)
    kept = _kept_entries(_rows(matrix, norms), gamma, seed, "entry", draw, "heads").where(F.size("heads") > 1)
    pairs = all_pairs(kept.select("row_id", *others, F.col("heads").alias("entries")), "norm")
    return pairs.select(*others, "i", "j", (F.col("a") * F.col("b") / (F.least(s, F.col("norm_i")) * F.least(s, F.col("norm_j")))).alias("v"))


def thinned_cosines(matrix: DataFrame, gamma: float, seed: int = 7, norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """(i, j, cos, n_kept)."""
    return thinned_emissions(matrix, gamma, seed, norms, draw).groupBy("i", "j").agg(F.sum("v").alias("cos"), F.count("*").alias("n_kept"))


def uniform_cosines(matrix: DataFrame, p: float, seed: int = 7, norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """(i, j, cos, n_kept): every product kept with the same probability p."""
    if not 0 < p <= 1:
        raise ValueError("p must be over 0 and at most 1")
    pairs = all_pairs(_rows(matrix, norms), "norm").where(unit_draw(seed, "row_id", "i", "j", kind=draw) < F.lit(float(p)))
    v = F.col("a") * F.col("b") / (F.col("norm_i") * F.col("norm_j"))
    return pairs.groupBy("i", "j").agg((F.sum(v) / F.lit(float(p))).alias("cos"), F.count("*").alias("n_kept"))


def estimate(matrix: DataFrame, method: str, gamma: float, seed: int = 7, norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """(i, j, cos, n_kept) by the named method."""
    methods = {"pair": sampled_cosines, "staged": staged_cosines, "thinned": thinned_cosines}
    if method not in methods:
        raise ValueError(f"unknown method {method!r}: one of {sorted(methods)}")
    return methods[method](matrix, gamma, seed, norms, draw).select("i", "j", "cos", "n_kept")


def repeated_estimates(matrix: DataFrame, method: str, gamma: float, seeds: list[int], norms: DataFrame | None = None, draw: str = "xxhash64") -> DataFrame:
    """(seed, i, j, cos, n_kept) for several seeds, from one scan: the seed is a column of the rows and part of the key.

    A pair that a seed never kept has no row under it.
    """
    norms = column_norms(matrix) if norms is None else norms
    rows = matrix.select("row_id", "entries", F.explode(F.array(*[F.lit(int(s)) for s in seeds])).alias("seed"))
    seed = F.col("seed")
    if method == "pair":
        kept = pair_emissions(rows, gamma, seed, norms, draw).withColumn("v", F.col("v") / F.least(_gamma(gamma), F.col("w")))
    elif method == "staged":
        kept = staged_emissions(rows, gamma, seed, norms, draw)
    elif method == "thinned":
        kept = thinned_emissions(rows, gamma, seed, norms, draw)
    else:
        raise ValueError(f"unknown method {method!r}: one of ['pair', 'staged', 'thinned']")
    return kept.groupBy("seed", "i", "j").agg(F.sum("v").alias("cos"), F.count("*").alias("n_kept"))


def central(estimates: DataFrame, seeds: list[int]) -> DataFrame:
    """(seed, i, j, cos, n_kept) of the seed whose median distance to the others is least; of equals the smallest seed.

    Each estimate is good with probability over one half, so the good ones lie close
    together and the one in their middle is good with high probability. Distances are
    sums of squared differences over all pairs, a pair without a row counting as 0.
    """
    value = lambda s: F.coalesce(F.max(F.when(F.col("seed") == s, F.col("cos"))), F.lit(0.0))
    wide = estimates.groupBy("i", "j").agg(*[value(s).alias(f"s{k}") for k, s in enumerate(seeds)])
    sums = [F.sum(F.pow(F.col(f"s{a}") - F.col(f"s{b}"), F.lit(2.0))).alias(f"d{a}_{b}") for a in range(len(seeds)) for b in range(a)]
    if len(seeds) < 2:
        return estimates
    far = wide.agg(*sums).first()
    distance = lambda a, b: far[f"d{max(a, b)}_{min(a, b)}"] or 0.0
    middle = {s: sorted(distance(a, b) for b in range(len(seeds)) if b != a)[(len(seeds) - 1) // 2] for a, s in enumerate(seeds)}
    return estimates.where(F.col("seed") == min(seeds, key=lambda s: (middle[s], s)))


def averaged(estimates: DataFrame, n_seeds: int) -> DataFrame:
    """Mean over seeds, missing rows counted as 0: variance falls with the number of seeds."""
    return estimates.groupBy("i", "j").agg((F.sum("cos") / F.lit(n_seeds)).alias("cos"), F.sum("n_kept").alias("n_kept"))
