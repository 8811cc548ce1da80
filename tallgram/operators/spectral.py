"""Singular values and right singular vectors from a Gram matrix of n columns.

The Gram matrix has n^2 numbers whatever the number of rows, so one machine holds
and decomposes it up to DENSE_COLUMNS columns; beyond, power iteration multiplies
it by vectors where it lies.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Columns up to which the Gram matrix comes to the driver (8 n^2 bytes: 800 MB at 10,000).
DENSE_COLUMNS = 10_000


def dense(upper: DataFrame, n: int, value: str = "dot") -> np.ndarray:
    """Symmetric n x n array of (i, j, value) with i <= j; absent pairs are 0."""
    if n > DENSE_COLUMNS:
        raise ValueError(f"{n} columns are over DENSE_COLUMNS; use top_by_power_iteration")
    table = upper.select("i", "j", value).toArrow()
    out = np.zeros((n, n))
    i, j, v = (table.column(k).to_numpy() for k in range(3))
    out[i, j] = v
    out[j, i] = v
    return out


def decompose(gram: np.ndarray, k: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Singular values (falling) and right vectors as columns.

    A sampled Gram matrix may have negative eigenvalues: they count as 0. The entry
    of largest magnitude of each vector is positive.
    """
    if not len(gram):
        return np.zeros(0), np.zeros((0, 0))
    values, vectors = np.linalg.eigh(gram)
    order = np.argsort(-values, kind="stable")[: k or len(values)]
    values, vectors = np.clip(values[order], 0, None), vectors[:, order]
    lead = vectors[np.abs(vectors).argmax(axis=0), np.arange(vectors.shape[1])]
    return np.sqrt(values), vectors * np.where(lead < 0, -1.0, 1.0)


def spectral_factors(upper: DataFrame, n: int, k: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(rank, sigma) and (rank, col, weight) of a Gram matrix (i, j, dot) with its diagonal. Ranks begin at 1."""
    spark = upper.sparkSession
    sigma, v = decompose(dense(upper, n), k)
    ranks = np.arange(1, len(sigma) + 1, dtype=np.int32)
    values = spark.createDataFrame(pa.table({"rank": ranks, "sigma": sigma}))
    # as Arrow, 16 bytes a weight: rows of Python objects would be ten times that
    weights = spark.createDataFrame(pa.table({"rank": np.repeat(ranks, n), "col": np.tile(np.arange(n, dtype=np.int32), len(ranks)), "weight": v.T.ravel()}))
    return values, weights


def power_sums(upper: DataFrame) -> DataFrame:
    """One row (first, second): sums of the eigenvalues and of their squares of a Gram matrix (i <= j, dot), negative ones with their sign.

    They are the trace and the sum of squares of all entries, so no decomposition is
    needed, whatever the number of columns: nothing but two sums moves.
    """
    square = F.col("dot") * F.col("dot")
    of = F.when(F.col("i") == F.col("j"), square).otherwise(2 * square)
    return upper.agg(F.coalesce(F.sum(F.when(F.col("i") == F.col("j"), F.col("dot"))), F.lit(0.0)).alias("first"), F.coalesce(F.sum(of), F.lit(0.0)).alias("second"))


def left_factor(matrix: DataFrame, values: DataFrame, vectors: DataFrame, k: int) -> DataFrame:
    """(row_id, rank, weight): the rows of U for the first k singular values. Narrow: V travels as one array of n x k numbers.

    n is at most DENSE_COLUMNS here, since V comes from a decomposition in the driver.
    """
    sigma = {r["rank"]: r["sigma"] for r in values.where((F.col("rank") <= k) & (F.col("sigma") > 0)).collect()}
    found = vectors.where(F.col("rank").isin(list(sigma))).toArrow()
    ranks, col, weight = (found.column(c).to_numpy() for c in ("rank", "col", "weight"))
    n = int(col.max()) + 1 if len(col) else 0
    table = {r: np.zeros(n) for r in sorted(sigma)}
    for r in table:
        table[r][col[ranks == r]] = weight[ranks == r] / sigma[r]
    one = matrix.sparkSession.createDataFrame(pa.table({"factors": pa.array([[{"rank": r, "of": v.tolist()} for r, v in table.items()]], pa.list_(pa.struct([("rank", pa.int32()), ("of", pa.list_(pa.float64()))])))}))
    rows = matrix.crossJoin(F.broadcast(one)).select("row_id", "entries", F.explode("factors").alias("f"))
    weight = F.aggregate("entries", F.lit(0.0), lambda a, e: a + e["val"] * F.coalesce(F.get("f.of", e["col"]), F.lit(0.0)))
    return rows.select("row_id", F.col("f.rank").alias("rank"), weight.alias("weight"))


def spectral_norm(symmetric: np.ndarray) -> float:
    return float(np.abs(np.linalg.eigvalsh(symmetric)).max()) if len(symmetric) else 0.0


def spectral_error(estimate: np.ndarray, exact: np.ndarray) -> float:
    """Norm of the difference over norm of the exact matrix."""
    base = spectral_norm(exact)
    return spectral_norm(estimate - exact) / base if base else 0.0


#: Bytes of packed entries up to which a sparse matrix is multiplied in the driver.
LOCAL_BYTES = 192 << 20
_PACK = 250_000
#: Columns up to which a connected part of a sparse matrix is decomposed as a dense block, in a task.
BLOCK_COLUMNS = 1_000


def _packed(entries: DataFrame, values: list[str]) -> DataFrame:
    """(n, i, j, v): runs of up to _PACK entries as bytes, in order of i, so that a multiplication moves no rows."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0

        def block() -> pa.RecordBatch:
            t = pa.Table.from_batches(held)
            i, j = (t.column(c).to_numpy().astype(np.int32) for c in ("i", "j"))
            v, at = np.stack([t.column(c).to_numpy() for c in values], axis=1), np.argsort(i, kind="stable")
            return pa.RecordBatch.from_pylist([{"n": len(i), "i": i[at].tobytes(), "j": j[at].tobytes(), "v": v[at].tobytes()}], schema=pa.schema([("n", pa.int64()), ("i", pa.binary()), ("j", pa.binary()), ("v", pa.binary())]))

        for batch in batches:
            held.append(batch)
            rows += batch.num_rows
            if rows >= _PACK:
                yield block()
                held, rows = [], 0
        if rows:
            yield block()

    return entries.select("i", "j", *values).mapInArrow(pack, "n long, i binary, j binary, v binary")


def _times(i: np.ndarray, j: np.ndarray, v: np.ndarray, x: np.ndarray, out: np.ndarray) -> None:
    """out += the symmetric matrices of these entries (i < j or i = j, i in order) times x, column k of v with column k of x."""
    starts = np.flatnonzero(np.r_[True, i[1:] != i[:-1]])
    out[i[starts]] += np.add.reduceat(v * x[j], starts, axis=0)
    below = v * x[i] * (i != j)[:, None]
    for k in range(v.shape[1]):
        out[:, k] += np.bincount(j, below[:, k], len(out))


def _joined(labels: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Labels (each the smallest column of its part) after the parts of i and j have met."""
    while True:
        a, b = labels[i], labels[j]
        if (a == b).all():
            return labels
        np.minimum.at(labels, np.maximum(a, b), np.minimum(a, b))
        while (labels != (further := labels[labels])).any():
            labels = further


def _parts(packed: DataFrame, n: int) -> np.ndarray:
    """The smallest column of each column's connected part. A task sends at most n pairs."""

    def forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        labels = np.arange(n)
        for batch in batches:
            for i, j, _ in _unpacked(batch, 0):
                labels = _joined(labels, i, j)
        at = np.flatnonzero(labels != np.arange(n))
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(labels[at])], names=["i", "j"])

    found = packed.mapInArrow(forest, "i long, j long").distinct().toArrow()
    return _joined(np.arange(n), found.column("i").to_numpy(), found.column("j").to_numpy())


def sparse_norms(entries: DataFrame, n: int, values: list[str], tol: float = 1e-6) -> list[float]:
    """Spectral norms of symmetric n x n matrices, one for each column of values: entries (i, j, ...) with i <= j.

    The norm is the largest of the norms of the connected parts. Parts of up to
    BLOCK_COLUMNS columns are gathered into dense blocks, which tasks decompose. Larger
    ones take Lanczos steps: the entries stay where they are (or come packed to the
    driver, up to LOCAL_BYTES), and a step moves one vector a matrix, until the residual
    is within tol of the value, whose own error is of the order of the residual's square.
    """
    packed = _packed(entries, values).persist()
    try:
        count = packed.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        if not count:
            return [0.0] * len(values)
        parts = _parts(packed, n)
        size = np.bincount(parts, minlength=n)
        fits = size <= BLOCK_COLUMNS
        block = np.where(fits, (np.cumsum(size * fits) - 1) // BLOCK_COLUMNS, -1)[parts].astype(np.int32)
        found = np.zeros(len(values))
        if (block >= 0).any():
            found = _block_norms(packed, block, values)
        if (block < 0).any():
            if count * 8 * (1 + len(values)) <= LOCAL_BYTES:
                blocks = [x for batch in packed.toArrow().to_batches() for x in _unpacked(batch, len(values), block)]

                def multiply(x: np.ndarray) -> np.ndarray:
                    out = np.zeros_like(x)
                    for each in blocks:
                        _times(*each, x, out)
                    return out
            else:
                multiply = _spark_multiply(packed, values, block)
            found = np.maximum(found, _lanczos(multiply, (block < 0)[:, None], len(values), tol))
        return [float(x) for x in found]
    finally:
        packed.unpersist()


def _block_norms(packed: DataFrame, block: np.ndarray, values: list[str]) -> np.ndarray:
    """Largest norm over the dense blocks, for each column of values."""

    def entries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, j, v in _unpacked(batch, len(values)):
                keep = block[i] >= 0
                yield pa.RecordBatch.from_arrays([pa.array(block[i][keep]), pa.array(i[keep]), pa.array(j[keep]), *[pa.array(v[keep, k]) for k in range(len(values))]], names=["block", "i", "j", *values])

    def norms(table: pa.Table) -> pa.Table:
        i, j = (table.column(c).to_numpy() for c in ("i", "j"))
        columns = np.unique(np.r_[i, j])
        i, j, out = np.searchsorted(columns, i), np.searchsorted(columns, j), {}
        for c in values:
            dense = np.zeros((len(columns), len(columns)))
            dense[i, j] = dense[j, i] = table.column(c).to_numpy()
            out[c] = [spectral_norm(dense)]
        return pa.table(out)

    each = ", ".join(f"{c} double" for c in values)
    rows = packed.mapInArrow(entries, f"block int, i int, j int, {each}").groupBy("block").applyInArrow(norms, each)
    return np.array([x or 0.0 for x in rows.agg(*[F.max(c) for c in values]).first()])


def _unpacked(batch: pa.RecordBatch, s: int, block: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, v) of packed rows; with block, only entries of columns in no block."""
    of = lambda c, k, t: np.frombuffer(batch.column(c)[k].as_buffer(), t)
    for k in range(batch.num_rows):
        i, j, v = of("i", k, np.int32), of("j", k, np.int32), of("v", k, np.float64).reshape(len(of("i", k, np.int32)), -1)[:, :s]
        keep = slice(None) if block is None or (block < 0).all() else block[i] < 0
        if len(i[keep]):
            yield i[keep], j[keep], v[keep]


def _spark_multiply(packed: DataFrame, values: list[str], block: np.ndarray):
    names = [f"y{k}" for k in range(len(values))]
    sc = packed.sparkSession.sparkContext

    def multiply(x: np.ndarray) -> np.ndarray:
        shared = sc.broadcast(x)

        def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            out = np.zeros_like(shared.value)
            for batch in batches:
                for each in _unpacked(batch, out.shape[1], block):
                    _times(*each, shared.value, out)
            at = np.flatnonzero(out.any(axis=1))
            yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), *[pa.array(out[at, k]) for k in range(out.shape[1])]], names=["col", *names])

        sums = packed.mapInArrow(part, "col int, " + ", ".join(f"{y} double" for y in names)).groupBy("col").agg(*[F.sum(y).alias(y) for y in names]).toArrow()
        shared.destroy()
        out = np.zeros_like(x)
        out[sums.column("col").to_numpy()] = np.stack([sums.column(y).to_numpy() for y in names], axis=1)
        return out

    return multiply


def _lanczos(multiply, among: np.ndarray, s: int, tol: float, most: int = 5000) -> list[float]:
    """Largest magnitudes of the eigenvalues of s symmetric matrices at once; extremes need no reorthogonalising."""
    n = len(among)
    q = np.random.default_rng(1).standard_normal((n, s)) * among
    q /= np.linalg.norm(q, axis=0)
    before, beta, a, b = np.zeros((n, s)), np.zeros(s), [], []
    found: list[float | None] = [None] * s
    for step in range(1, most + 1):
        w = multiply(q) - beta * before
        a.append((q * w).sum(axis=0))
        w -= a[-1] * q
        beta = np.linalg.norm(w, axis=0)
        b.append(beta)
        if step < 10 or step % max(5, step // 10) == 0:
            for k in (k for k in range(s) if found[k] is None):
                t = np.diag([x[k] for x in a]) + np.diag([x[k] for x in b[:-1]], 1) + np.diag([x[k] for x in b[:-1]], -1)
                theta, vectors = np.linalg.eigh(t)
                top = int(np.abs(theta).argmax())
                if beta[k] * abs(vectors[-1, top]) <= tol * abs(theta[top]):
                    found[k] = float(abs(theta[top]))
        if None not in found:
            return found
        before, q = q, w / np.where(beta > 0, beta, 1.0)
    raise RuntimeError(f"no convergence in {most} steps")


def top_by_power_iteration(both: DataFrame, rounds: int = 30, seed: int = 1) -> tuple[float, DataFrame]:
    """Largest eigenvalue and (col, x) of a symmetric matrix given in both directions (i, j, dot).

    Each round is one join with the vector and one sum by row; only the norm of the
    vector comes to the driver.
    """
    from tallgram.functions.draws import unit_draw

    vector = both.select(F.col("i").alias("col")).distinct().withColumn("x", unit_draw(seed, "col") + F.lit(0.5))
    value = 0.0
    for _ in range(rounds):
        image = both.join(vector, F.col("j") == F.col("col")).groupBy("i").agg(F.sum(F.col("dot") * F.col("x")).alias("x")).withColumnRenamed("i", "col")
        image = image.checkpoint() if both.sparkSession.sparkContext._jsc.sc().getCheckpointDir().isDefined() else image.persist()
        norm = image.agg(F.sqrt(F.sum(F.col("x") * F.col("x")))).first()[0] or 0.0
        if not norm:
            return 0.0, image
        converged = abs(norm - value) <= 1e-12 * norm
        vector, value = image.withColumn("x", F.col("x") / F.lit(norm)), norm
        if converged:
            break
    return value, vector


def explained_energy(values: DataFrame) -> DataFrame:
    """(rank, sigma, energy): running share of the sum of squares."""
    upto = Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    square = F.col("sigma") * F.col("sigma")
    return values.select("rank", "sigma", (F.sum(square).over(upto) / F.sum(square).over(Window.partitionBy())).alias("energy"))
