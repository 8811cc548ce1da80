"""Exact Gram matrices: the all-products baseline and the ways to compare it with."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.operators.matrix import SPLIT
from tallgram.operators.norms import _one_row, attach, column_norms


def all_pairs(matrix: DataFrame, *carried: str) -> DataFrame:
    """Every in-row pair i < j: (row_id, i, j, a, b and, for carried fields x, x_i and x_j).

    Entries are in order of their columns, so each meets those after it only. Two
    generators, inside one generated-code stage with what follows. Other columns of
    the matrix are kept. Of a row dealt out by ``matrix.split_heavy`` only its own
    share of first entries is used.
    """
    others = [c for c in matrix.columns if c not in ("row_id", "entries", *SPLIT)]
    own = F.slice("entries", F.col(SPLIT[0]) + 1, F.col(SPLIT[1])) if SPLIT[0] in matrix.columns else F.col("entries")
    skipped = F.col(SPLIT[0]) if SPLIT[0] in matrix.columns else F.lit(0)
    first = matrix.select("row_id", *others, "entries", skipped.alias("_skipped"), F.posexplode(own).alias("_at", "_a"))
    # fields of the first entry become columns before the second generator, which then carries no struct along
    mine = [F.col("_a.col").alias("i"), F.col("_a.val").alias("a"), *[F.col(f"_a.{c}").alias(f"{c}_i") for c in carried]]
    later = F.slice("entries", F.col("_at") + F.col("_skipped") + 2, F.size("entries")).alias("_later")
    both = first.select("row_id", *others, *mine, later).select("row_id", *others, "i", "a", *[f"{c}_i" for c in carried], F.explode("_later").alias("_b"))
    return both.select("row_id", *others, "i", F.col("_b.col").alias("j"), "a", F.col("_b.val").alias("b"), *[c for x in carried for c in (f"{x}_i", F.col(f"_b.{x}").alias(f"{x}_j"))])


def exact_gram(matrix: DataFrame, combine: bool = True) -> DataFrame:
    """(i, j, dot, n_terms) for i < j: every product is emitted and summed.

    combine=False ships each product to its key before any sum, the literal cost
    model; the default lets tasks sum first.
    """
    products = all_pairs(matrix).select("i", "j", (F.col("a") * F.col("b")).alias("v"))
    if not combine:
        products = products.repartition("i", "j")
    return products.groupBy("i", "j").agg(F.sum("v").alias("dot"), F.count("*").alias("n_terms"))


def exact_cosines(matrix: DataFrame, norms: DataFrame | None = None) -> DataFrame:
    """(i, j, cos, dot) of all co-occurring pairs, exact."""
    rows = attach(matrix, column_norms(matrix) if norms is None else norms)
    pairs = all_pairs(rows, "norm").select("i", "j", (F.col("a") * F.col("b")).alias("v"), (F.col("norm_i") * F.col("norm_j")).alias("w"))
    return pairs.groupBy("i", "j").agg(F.sum("v").alias("dot"), F.max("w").alias("w")).select("i", "j", (F.col("dot") / F.col("w")).alias("cos"), "dot")


def exact_gram_join(triplets: DataFrame, strategy: str = "merge") -> DataFrame:
    """The same by a self-join on row_id, which shuffles all entries: what the row form saves."""
    left = triplets.select("row_id", F.col("col").alias("i"), F.col("val").alias("a"))
    right = triplets.select("row_id", F.col("col").alias("j"), F.col("val").alias("b")).hint(strategy)
    pairs = left.join(right, "row_id").where("i < j")
    return pairs.groupBy("i", "j").agg(F.sum(F.col("a") * F.col("b")).alias("dot"), F.count("*").alias("n_terms"))


def exact_gram_blocks(matrix: DataFrame, n: int, block: int = 512) -> DataFrame:
    """The same by dense partial sums: each task keeps block x block tiles of the triangle, summed by tile.

    Communicates up to n^2/2 numbers a task, whatever the sparsity.
    """

    def tiles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            lists = batch.column("entries")
            flat = lists.flatten()
            col, val = flat.field("col").to_numpy(), flat.field("val").to_numpy()
            bounds = lists.offsets.to_numpy() - lists.offsets[0].as_py()
            for at in range(0, batch.num_rows, 512):
                lo, hi = bounds[at], bounds[min(at + 512, batch.num_rows)]
                row = np.repeat(np.arange(min(512, batch.num_rows - at)), np.diff(bounds[at : at + 513]))
                dense = np.zeros((row[-1] + 1 if len(row) else 0, n))
                dense[row, col[lo:hi]] = val[lo:hi]
                for p in range(0, n, block):
                    for q in range(p, n, block):
                        part = dense[:, p : p + block].T @ dense[:, q : q + block]
                        sums[p, q] = part if (p, q) not in sums else sums[p, q] + part
        for (p, q), part in sums.items():
            r, c = np.nonzero(part)
            keep = r + p < c + q
            yield pa.RecordBatch.from_arrays([pa.array((r + p)[keep].astype(np.int32)), pa.array((c + q)[keep].astype(np.int32)), pa.array(part[r, c][keep])], names=["i", "j", "v"])

    return matrix.select("entries").mapInArrow(tiles, "i int, j int, v double").groupBy("i", "j").agg(F.sum("v").alias("dot"))


def gram_from_cosines(cosines: DataFrame, norms: DataFrame) -> DataFrame:
    """Upper triangle (i <= j, dot): cosine times both norms, and the exact diagonal from the norms.

    Norms come as one broadcast array; over BROADCAST_COLUMNS columns they are joined.
    """
    one_row = _one_row(norms)
    if one_row is not None:
        both = cosines.crossJoin(F.broadcast(one_row)).withColumns({"norm_i": F.get("norms", "i"), "norm_j": F.get("norms", "j")})
    else:
        side = lambda k: norms.select(F.col("col").alias(k), F.col("norm").alias(f"norm_{k}"))
        both = cosines.join(side("i"), "i").join(side("j"), "j")
    upper = both.select("i", "j", (F.col("cos") * F.col("norm_i") * F.col("norm_j")).alias("dot"))
    return upper.unionByName(norms.select(F.col("col").alias("i"), F.col("col").alias("j"), F.col("sumsq").alias("dot")))


def mirror(pairs: DataFrame) -> DataFrame:
    """Pairs in both directions; a diagonal stays single."""
    swapped = pairs.where("i <> j").select(*[F.col("j").alias("i") if c == "i" else F.col("i").alias("j") if c == "j" else F.col(c) for c in pairs.columns])
    return pairs.unionByName(swapped)
