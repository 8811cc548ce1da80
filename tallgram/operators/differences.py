"""Spectral norms of the differences between sampled and exact Gram matrices, without an exchange of pairs.

All products of a row are formed and drawn where the row lies; draws are those of
``functions.draws`` of kind "xxhash64", bit by bit. Two forms, by size:

* Up to TASK_COLUMNS columns, and LOCAL_BYTES of packed entries, a task makes a
  difference (a method and budget under one seed) as a dense matrix and takes all
  Lanczos steps itself.
* Beyond, draws are made once and kept as bits beside their row: for each seed a bit
  for each product. A Lanczos step multiplies every row's small matrix by the vectors
  and moves nothing but the vectors, whatever the number of pairs.

A product that is certain to be kept at weight 1 differs by 0 and takes part in neither.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.operators.spectral import LOCAL_BYTES, _lanczos

#: Columns up to which a difference is a dense matrix in a task (8 n^2 bytes, of which half are touched: 256 MB).
TASK_COLUMNS = 8_000
#: Entries that are packed together, and places of a record's matrices.
CHUNK, CELLS = 1 << 19, 1 << 16
#: Bytes of the tasks' sums that meet in the driver; more meet in an exchange first.
SUMS_BYTES = 128 << 20
#: Records that travel to Python together, each of some CELLS bits for a seed.
_RECORDS = 64

Run = tuple[str, float]

# --- draws ---

_P1, _P2, _P3, _P4, _P5 = (np.uint64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
_SALTS = {"pair": [()], "staged": [("first",), ("second",)], "thinned": [("entry",)]}


def _turned(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def _mixed(h: np.ndarray) -> np.ndarray:
    h ^= h >> np.uint64(33)
    h *= _P2
    h ^= h >> np.uint64(29)
    h *= _P3
    h ^= h >> np.uint64(32)
    return h


def _hash_int(x: np.ndarray, state: np.ndarray) -> np.ndarray:
    """xxhash64 of ints after ``state``, the hash of what comes before them. x: unsigned, 64 bits, times _P1 already."""
    h = state + (_P5 + np.uint64(4))
    h ^= x
    h = _turned(h, 23)
    h *= _P2
    h += _P3
    return _mixed(h)


def _hash_long(x: np.ndarray, state: np.ndarray) -> np.ndarray:
    h = (state + (_P5 + np.uint64(8))) ^ (_turned(x.astype(np.uint64) * _P2, 31) * _P1)
    return _mixed(_turned(h, 27) * _P1 + _P4)


def _unit(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(11)) * 2.0**-53


def _begun(matrix: DataFrame, method: str, seeds: list[int]) -> list[list[np.ndarray]]:
    """For each seed, hashes of the seed and the words that come before a row's number in a draw."""
    columns = [F.xxhash64(F.lit(int(s)), *[F.lit(x) for x in words]) for s in seeds for words in _SALTS[method]]
    found = np.array(matrix.sparkSession.range(1).select(*[c.alias(f"h{k}") for k, c in enumerate(columns)]).first(), np.int64).astype(np.uint64)
    return [list(x) for x in found.reshape(len(seeds), -1, 1)]


class _Entries:
    """Entries of some rows and the draws of one method: row number, column, value and norm of each."""

    def __init__(self, method: str, gamma: float, row: np.ndarray, col: np.ndarray, val: np.ndarray, norm: np.ndarray) -> None:
        self.method, self.gamma, self.row, self.val, self.norm = method, gamma, row, val, norm
        self.col = col.astype(np.int64).astype(np.uint64) * _P1
        self.root = math.sqrt(gamma)
        # the weight of a kept product that isn't certain is that of one entry times that of the other
        self.weight = val * (norm / self.root if method == "pair" else np.maximum(1.0, norm / self.root))

    def seeded(self, begun: list[np.ndarray]) -> tuple[np.ndarray | None, np.ndarray | None]:
        """(whether each entry survives its own draw, the hash before a partner's column), as the method has them."""
        hashed = [_hash_int(self.col, _hash_long(self.row, h)) for h in begun]
        if self.method == "pair":
            return None, hashed[0]
        with np.errstate(divide="ignore"):
            own = (self.norm <= self.root) | (_unit(hashed[0]) < self.root / self.norm)
        return own, hashed[1] if self.method == "staged" else None

    def uncertain(self, e: np.ndarray, at: np.ndarray) -> np.ndarray:
        if self.method == "pair":
            return self.norm[e] * self.norm[at] > self.gamma
        return (self.norm[e] > self.root) | (self.norm[at] > self.root)

    def kept(self, seeded: tuple[np.ndarray | None, np.ndarray | None], e: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Whether products of entries e and later partners at, uncertain ones, are kept."""
        own, state = seeded
        if self.method == "thinned":
            return own[e] & own[at]
        draw = _unit(_hash_int(self.col[at], state[e]))
        if self.method == "pair":
            return draw < self.gamma / (self.norm[e] * self.norm[at])
        return own[e] & ((self.norm[at] <= self.root) | (draw < self.root / self.norm[at]))


# --- rows as packed records ---

_PACKED = "r int, l int, rows binary, cols binary, vals binary"


def _packed(triplets: DataFrame) -> DataFrame:
    """Row form as records of r rows of l entries each, in order of columns; no values: all are 1.

    Duplicates are summed and zeros dropped. One shuffle of the entries, by row. Records
    have about equally many places in their matrices, a longer row has one of its own.
    """

    def records(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        for batch in batches:
            held.append([batch.column(c).to_numpy() for c in ("row_id", "col", "val")])
            if sum(len(x[0]) for x in held) >= CHUNK:
                row, col, val = (np.concatenate(x) for x in zip(*held, strict=True))
                whole = int(np.searchsorted(row, row[-1]))  # the last row may go on
                held = [[x[whole:] for x in (row, col, val)]]
                yield from packed(row[:whole], col[:whole], val[:whole])
        if held:
            yield from packed(*(np.concatenate(x) for x in zip(*held, strict=True)))

    def packed(row, col, val):
        if not len(row):
            return
        new = np.flatnonzero(np.concatenate([[True], (row[1:] != row[:-1]) | (col[1:] != col[:-1])]))
        row, col, val = row[new], col[new], np.add.reduceat(val, new)
        if not val.all():
            row, col, val = (x[val != 0] for x in (row, col, val))
        begin = np.flatnonzero(np.concatenate([np.ones(min(1, len(row)), bool), row[1:] != row[:-1]]))
        sizes = np.diff(np.append(begin, len(row)))
        for width in np.unique(sizes).tolist():
            alike, many = np.flatnonzero(sizes == width), max(1, CELLS // width**2)
            for lo in range(0, len(alike), many):
                first = begin[alike[lo : lo + many]]
                place = first[:, None] + np.arange(width)
                yield _record([len(first), width, row[first].tobytes(), col[place].astype(np.int32).tobytes(), b"" if (val[place] == 1).all() else val[place].tobytes()], _PACKED)

    rows = triplets.select(F.col("row_id").cast("long"), F.col("col").cast("int"), F.col("val").cast("double"))
    return rows.repartition("row_id").sortWithinPartitions("row_id", "col").mapInArrow(records, _PACKED)


def _record(values: list, schema: str) -> pa.RecordBatch:
    fields = [x.split() for x in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([v], pa.int32() if t == "int" else pa.binary()) for v, (_, t) in zip(values, fields, strict=True)], names=[x for x, _ in fields])


def _read(batch: pa.RecordBatch, k: int, *names: str) -> list[np.ndarray]:
    types = {"rows": np.int64, "cols": np.int32, "vals": np.float64}
    found = {c: np.frombuffer(batch.column(c)[k].as_buffer(), types.get(c, np.uint8)) for c in ("cols", *names)}
    cols = found["cols"].astype(np.int64)
    if "vals" in found and not len(found["vals"]):
        found["vals"] = np.ones(len(cols))
    return [batch.column("r")[k].as_py(), batch.column("l")[k].as_py(), cols, *[found[c] for c in names]]


def _entries(batch: pa.RecordBatch, k: int, norms: np.ndarray, method: str, gamma: float) -> tuple[int, int, np.ndarray, _Entries]:
    r, width, cols, rows, vals = _read(batch, k, "rows", "vals")
    return r, width, cols, _Entries(method, gamma, np.repeat(rows, width), cols, vals, norms[cols])


def _products(r: int, width: int) -> Iterator[tuple[int, int, np.ndarray, np.ndarray, np.ndarray]]:
    """(first entry, entries, entry and later partner of each product, place in the matrices): all of a record, some entries of every row at a time."""
    heads, base = max(1, min(width, CELLS // (r * width))), np.arange(r)[:, None]
    for first in range(0, width, heads):
        count = min(heads, width - first)
        a, b = np.nonzero(np.arange(width) > np.arange(first, first + count)[:, None])
        yield first, count, *((base * x + y).ravel() for x, y in ((width, first + a), (width, b), (count * width, a * width + b)))


# --- differences in tasks ---


def _dense_norm(upper: np.ndarray, tol: float) -> float:
    """Norm of the symmetric matrix whose upper triangle this is, with half its diagonal."""
    n, stripe = len(upper), 64

    def multiply(x: np.ndarray) -> np.ndarray:
        x, out = np.ascontiguousarray(x[:, 0]), np.zeros(n)
        for a in range(0, n, stripe):  # read once for both directions
            part = upper[a : a + stripe, a:]
            out[a : a + stripe] += part @ x[a:]
            out[a:] += x[a : a + stripe] @ part
        return out[:, None]

    return _lanczos(multiply, np.ones((n, 1), bool), 1, tol)[0]


def _in_tasks(packed: DataFrame, n: int, norm: np.ndarray, runs: list[tuple[str, float, list]], tol: float) -> list[float]:
    """Norm of the exact matrix, and of the difference for each of runs (method, gamma, a seed's hashes)."""
    spark = packed.sparkSession
    shared = spark.sparkContext.broadcast((packed.toArrow().combine_chunks(), norm))

    def one(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in batch.column("id").to_pylist():
                found = exact() if k == 0 else difference(*runs[k - 1])
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int64()), pa.array([found])], names=["id", "norm"])

    def records() -> Iterator[tuple[pa.RecordBatch, int]]:
        return ((batch, k) for batch in shared.value[0].to_batches() for k in range(batch.num_rows))

    def exact() -> float:
        upper = np.zeros((n, n))
        cell = upper.reshape(-1)
        for record in records():
            r, width, cols, vals = _read(*record, "vals")
            np.add.at(cell, cols * (n + 1), vals * vals / 2)
            for _, _, e, at, _ in _products(r, width):
                np.add.at(cell, cols[e] * n + cols[at], vals[e] * vals[at])
        return _dense_norm(upper, tol)

    def difference(method: str, gamma: float, begun: list[np.ndarray]) -> float:
        upper = np.zeros((n, n))
        cell = upper.reshape(-1)
        for record in records():
            r, width, cols, entries = _entries(*record, shared.value[1], method, gamma)
            seeded = entries.seeded(begun)
            for _, _, e, at, _ in _products(r, width):
                drawn = np.flatnonzero(entries.uncertain(e, at))
                e, at = e[drawn], at[drawn]
                np.add.at(cell, cols[e] * n + cols[at], entries.kept(seeded, e, at) * (entries.weight[e] * entries.weight[at]) - entries.val[e] * entries.val[at])
        return _dense_norm(upper, tol)

    try:
        found = spark.range(0, len(runs) + 1, 1, len(runs) + 1).mapInArrow(one, "id long, norm double").collect()
    finally:
        shared.destroy()
    return [r["norm"] for r in sorted(found, key=lambda r: r["id"])]


# --- steps over rows ---

_DRAWN = "r int, l int, first int, heads int, rows binary, cols binary, vals binary, uncertain binary, kept binary"


def _drawn(packed: DataFrame, norms, method: str, gamma: float, begun: list[list[np.ndarray]]) -> DataFrame:
    """Records of matrices as bits, r rows by some entries from ``first`` on by l partners: which products are uncertain, and which each seed keeps."""

    def records(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                r, width, _, entries = _entries(batch, k, norms.value, method, gamma)
                if width < 2:
                    continue
                seeded, same = [entries.seeded(h) for h in begun], [batch.column(c)[k].as_py() for c in ("rows", "cols", "vals")]
                for first, count, e, at, cell in _products(r, width):
                    drawn = np.flatnonzero(entries.uncertain(e, at))
                    e, at, cell = e[drawn], at[drawn], cell[drawn]
                    bits = np.zeros((1 + len(seeded), r * count * width), bool)
                    bits[0, cell] = True
                    for s, x in enumerate(seeded):
                        bits[1 + s, cell[entries.kept(x, e, at)]] = True
                    if count == width:  # whole matrices are stored in both directions
                        bits = bits.reshape(-1, r, width, width)
                        bits = (bits | bits.transpose(0, 1, 3, 2)).reshape(1 + len(seeded), -1)
                    bits = np.packbits(bits, axis=1)
                    if len(drawn):
                        yield _record([r, width, first, count, *same, bits[0].tobytes(), bits[1:].tobytes()], _DRAWN)

    return packed.mapInArrow(records, _DRAWN)


def _times_drawn(batch: pa.RecordBatch, k: int, method: str, gamma: float, norms: np.ndarray, x: np.ndarray, out: np.ndarray) -> None:
    """out += this record's differences times x, both a row for each seed."""
    s, first, count = len(x), batch.column("first")[k].as_py(), batch.column("heads")[k].as_py()
    r, width, cols, entries = _entries(batch, k, norms, method, gamma)
    uncertain, kept = _read(batch, k, "uncertain", "kept")[3:]
    own = slice(first, first + count)
    matrices = lambda bits: np.unpackbits(bits, count=r * count * width).astype(np.float64).reshape(r, count, width)
    vals, weight, at = entries.val.reshape(r, width), entries.weight.reshape(r, width), x[:, cols].reshape(s, r, width)

    def times(bits: np.ndarray, v: np.ndarray) -> np.ndarray:
        if count == width:
            return np.matmul(bits, v)
        y = np.matmul(bits.transpose(0, 2, 1), v[:, own])
        y[:, own] += np.matmul(bits, v)
        return y

    # exact products under all seeds at once
    y = np.moveaxis(times(matrices(uncertain), np.moveaxis(at * vals, 0, 2)), 2, 0) * -vals
    for one, (z, plane) in enumerate(zip(at * weight, kept.reshape(s, -1), strict=True)):
        y[one] += times(matrices(plane), z[:, :, None])[:, :, 0] * weight
    for one in range(s):
        np.add.at(out[one], cols, y[one].ravel())


def _times_rows(batch: pa.RecordBatch, k: int, x: np.ndarray, out: np.ndarray) -> None:
    """out += the exact matrix of this record's rows times x."""
    r, width, cols, vals = _read(batch, k, "vals")
    vals = vals.reshape(r, width)
    for one in range(len(x)):
        np.add.at(out[one], cols, ((x[one, cols].reshape(r, width) * vals).sum(axis=1, keepdims=True) * vals).ravel())


def _add_squares(batch: pa.RecordBatch, k: int, x: np.ndarray, out: np.ndarray) -> None:
    _, _, cols, vals = _read(batch, k, "vals")
    np.add.at(out[0], cols, vals * vals)


def _sums(records: DataFrame, add: Callable, x: np.ndarray) -> np.ndarray:
    """Sum over all records of what ``add(batch, k, x, out)`` adds to out for record k; x and the sum have a row for each of several matrices."""
    sc, (s, n) = records.sparkSession.sparkContext, x.shape
    shared = sc.broadcast(x)

    def part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out = np.zeros((s, n))
        for batch in batches:
            for k in range(batch.num_rows):
                add(batch, k, shared.value, out)
        for one in range(s):
            yield _record([one, out[one].tobytes()], "part int, y binary")

    def met(table: pa.Table) -> pa.Table:
        return pa.table([table.column("part")[:1], pa.array([sum(np.frombuffer(y.as_buffer()) for y in table.column("y")).tobytes()], pa.binary())], names=["part", "y"])

    found, out = records.mapInArrow(part, "part int, y binary"), np.zeros((s, n))
    if 2 * sc.defaultParallelism * x.nbytes > SUMS_BYTES:
        found = found.groupBy("part").applyInArrow(met, "part int, y binary")
    for one, y in zip(*(c.to_pylist() for c in found.toArrow().columns), strict=True):
        out[one] += np.frombuffer(y)
    shared.destroy()
    return out


def _steps(records: DataFrame, n: int, s: int, add: Callable, tol: float) -> list[float]:
    """Norms of s matrices, each a sum over records."""
    return _lanczos(lambda x: _sums(records, add, np.ascontiguousarray(x.T)).T.copy(), np.ones((n, 1), bool), s, tol)


def sampled_difference_norms(triplets: DataFrame, n: int, runs: list[Run], seeds: list[int], tol: float = 1e-6) -> tuple[float, list[list[float]]]:
    """Norm of the exact Gram matrix, and for each of runs (method, gamma) the norms of the estimates' differences from it under each seed.

    Estimates are those of ``sampling.repeated_estimates`` scaled back by the norms, with
    the exact diagonal. n: columns, numbered from 0.
    """
    spark, name = triplets.sparkSession, "spark.sql.execution.arrow.maxRecordsPerBatch"
    begun, before = {m: _begun(triplets, m, seeds) for m in {m for m, _ in runs}}, spark.conf.get(name)
    # records about equal in work are dealt over all cores
    packed = _packed(triplets).repartition(2 * spark.sparkContext.defaultParallelism).persist()
    try:
        size = packed.agg(F.coalesce(F.sum(F.length("rows") + F.length("cols") + F.length("vals")), F.lit(0))).first()[0]
        if not size:
            return 0.0, [[0.0] * len(seeds) for _ in runs]
        spark.conf.set(name, _RECORDS)
        norm = np.sqrt(_sums(packed, _add_squares, np.zeros((1, n)))[0])
        if n <= TASK_COLUMNS and size <= LOCAL_BYTES:
            base, *errors = _in_tasks(packed, n, norm, [(m, g, h) for m, g in runs for h in begun[m]], tol)
            return base, [errors[k : k + len(seeds)] for k in range(0, len(errors), len(seeds))]
        base, errors, shared = _steps(packed, n, 1, _times_rows, tol)[0], [], spark.sparkContext.broadcast(norm)
        for method, gamma in runs:
            drawn = _drawn(packed, shared, method, gamma, begun[method]).persist()

            def add(batch, k, x, out, method=method, gamma=gamma):
                _times_drawn(batch, k, method, gamma, shared.value, x, out)

            errors.append(_steps(drawn, n, len(seeds), add, tol))
            drawn.unpersist()
        shared.destroy()
        return base, errors
    finally:
        packed.unpersist()
        spark.conf.set(name, before)
