"""All-pairs work of wide matrices by tiles of columns: entries move, pairs don't.

The other operators sum products by pair in an exchange. That is small where columns
are few, but where most pairs of many columns co-occur it moves about as many sums as
there are products. Here columns are cut into B blocks; a tile is a pair of blocks, and
one task gets all entries of both, so it has whole columns: their norms and all
products of their pairs. An entry is sent to B tiles, and what a task makes leaves it as
a stream of a few columns' pairs at a time. Every product is formed, none is left out.

Draws are those of ``functions.draws`` of kind "md5", bit by bit.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Entries of a block and products of a tile, about; blocks up to FEW_BLOCKS are made for tiles of SMALL_PRODUCTS already.
BLOCK_ENTRIES, TILE_PRODUCTS = 4_000_000, 64_000_000
FEW_BLOCKS, SMALL_PRODUCTS = 8, 2_000_000
#: Columns that are counted together when blocks are cut.
BUCKET = 64
#: Pairs whose sums a task holds at once, products it forms at once, and draws it makes at once.
CELLS, CHUNK, DRAWS = 1 << 18, 1 << 19, 1 << 14

_PARTS = "tile int, rows binary, p_counts binary, p_cols binary, p_vals binary, q_counts binary, q_cols binary, q_vals binary"


def blocks(matrix: DataFrame, count: int | None = None) -> list[int]:
    """First columns of blocks of about equal numbers of entries. One job; a number for each BUCKET columns comes to the driver."""
    entries = matrix.select(F.size("entries").alias("n"), F.explode(F.transform("entries", lambda e: e["col"])).alias("col"))
    found = entries.groupBy(F.expr(f"col div {BUCKET}").alias("b")).agg(F.count("*").alias("nnz"), F.sum("n").alias("s")).toArrow().sort_by("b")
    at, nnz = found.column("b").to_numpy(), found.column("nnz").to_numpy()
    products = (int(found.column("s").to_numpy().sum()) - int(nnz.sum())) / 2
    for_tiles = lambda most: math.ceil(math.sqrt(2 * products / most + 0.25) - 0.5)  # noqa: E731  B (B + 1) / 2 tiles
    if count is None:
        count = max(1, math.ceil(int(nnz.sum()) / BLOCK_ENTRIES), for_tiles(TILE_PRODUCTS), min(FEW_BLOCKS, for_tiles(SMALL_PRODUCTS)))
    ends = np.searchsorted(np.cumsum(nnz), np.arange(1, count) * int(nnz.sum()) / count) + 1
    return sorted({0, *(int(at[e]) * BUCKET for e in ends if e < len(at))})


def _split(bounds: list[int]) -> Callable:
    """Rows to records of tiles: what many rows have in a tile's two blocks, as packed arrays."""
    first = np.array(bounds)
    pairs = [(p, q) for p in range(len(bounds)) for q in range(p, len(bounds))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists, rows = batch.column("entries"), batch.column("row_id").to_numpy()
            flat = lists.flatten()
            col, val = flat.field("col").to_numpy(), flat.field("val").to_numpy()
            bounds_of = lists.offsets.to_numpy().astype(np.int64) - lists.offsets[0].as_py()
            lo = 0
            while lo < len(rows):
                hi = max(lo + 1, int(np.searchsorted(bounds_of, bounds_of[lo] + CHUNK, side="right")) - 1)
                yield from records(rows[lo:hi], np.diff(bounds_of[lo : hi + 1]), col[bounds_of[lo] : bounds_of[hi]], val[bounds_of[lo] : bounds_of[hi]])
                lo = hi

    def records(rows, sizes, col, val):
        row = np.repeat(np.arange(len(rows)), sizes)
        block = np.searchsorted(first, col, side="right") - 1
        parts = []
        for b, base in enumerate(bounds):
            own = np.flatnonzero(block == b)
            v = val[own]
            narrow = np.uint16 if b + 1 < len(bounds) and bounds[b + 1] - base <= 1 << 16 else np.uint32
            parts.append((np.bincount(row[own], minlength=len(rows)).astype(np.uint32).tobytes(), (col[own] - base).astype(narrow).tobytes(), b"" if (v == 1).all() else v.tobytes()))
        for t, (p, q) in enumerate(pairs):
            if parts[p][1] or parts[q][1]:
                values = [t, np.ascontiguousarray(rows, np.int64).tobytes(), *parts[p], *(parts[q] if q > p else (b"", b"", b""))]
                yield pa.RecordBatch.from_arrays([pa.array([v], pa.int32() if k == 0 else pa.binary()) for k, v in enumerate(values)], names=[x.split()[0] for x in _PARTS.split(", ")])

    return run


class _Side:
    """Entries of one block in order of rows: where each row's begin, columns (counted from the block's first), values (None: all 1), and norms."""

    def __init__(self, base: int, narrow: bool, counts: list[bytes], cols: list[bytes], vals: list[bytes]) -> None:
        self.base = base
        self.counts = np.concatenate([np.frombuffer(x, np.uint32) for x in counts]).astype(np.int64)
        self.begin = np.cumsum(self.counts) - self.counts
        parts = [np.frombuffer(x, np.uint16 if narrow else np.uint32) for x in cols]
        self.col = np.concatenate(parts).astype(np.int64)
        self.row = np.repeat(np.arange(len(self.counts)), self.counts)
        self.val = np.concatenate([np.frombuffer(v) if v else np.ones(len(c)) for v, c in zip(vals, parts, strict=True)]) if any(vals) else None
        self.n = int(self.col.max()) + 1 if len(self.col) else 0
        self.norm = np.sqrt(np.bincount(self.col, None if self.val is None else self.val * self.val, minlength=self.n))


class _Tile:
    """Two blocks of columns over all rows; partner i of a pair is of block p, j of block q."""

    def __init__(self, rows: np.ndarray, p: _Side, q: _Side) -> None:
        self.rows, self.p, self.q = rows, p, q
        at = np.arange(len(p.col))
        # within one block an entry meets those after it in its row
        self.begin = at + 1 if p is q else q.begin[p.row]
        self.many = (p.begin + p.counts)[p.row] - at - 1 if p is q else q.counts[p.row]
        self.order = np.argsort(p.col, kind="stable")
        self.first = np.concatenate([[0], np.cumsum(np.bincount(p.col, minlength=p.n))])

    def stripes(self) -> Iterator[tuple[int, int, np.ndarray]]:
        """(first column, end, entries of these columns), columns of p in order."""
        width = max(1, CELLS // max(1, self.q.n))
        for x in range(0, self.p.n if self.q.n else 0, width):
            end = min(x + width, self.p.n)
            yield x, end, self.order[self.first[x] : self.first[end]]

    def products(self, entries: np.ndarray, most: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(entries of p, partners of each, their places in q), about ``most`` products at a time."""
        ends = np.cumsum(self.many[entries])
        lo = 0
        while lo < len(entries):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + most, side="right")))
            e = entries[lo:hi]
            k = self.many[e]
            total = int(k.sum())
            if total:
                yield e, k, np.repeat(self.begin[e] - (np.cumsum(k) - k), k) + np.arange(total)
            lo = hi

    def value(self, e: np.ndarray, k: np.ndarray, at: np.ndarray) -> np.ndarray | None:
        """Products' values, None if all are 1."""
        if self.p.val is None and self.q.val is None:
            return None
        a = np.repeat(np.ones(len(e)) if self.p.val is None else self.p.val[e], k)
        return a if self.q.val is None else a * self.q.val[at]

    def cell(self, x: int, e: np.ndarray, k: np.ndarray, at: np.ndarray) -> np.ndarray:
        return np.repeat((self.p.col[e] - x) * self.q.n, k) + self.q.col[at]

    def sums(self, x: int, end: int, entries: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(products, their sum) of each pair of a stripe, columns of p by columns of q."""
        shape = (end - x) * self.q.n
        count, dot = np.zeros(shape, np.int64), None if self.p.val is None and self.q.val is None else np.zeros(shape)
        for e, k, at in self.products(entries, CHUNK):
            cell = self.cell(x, e, k, at)
            count += np.bincount(cell, minlength=shape)
            if dot is not None:
                dot += np.bincount(cell, self.value(e, k, at), minlength=shape)
        count = count.reshape(end - x, self.q.n)
        return count, count if dot is None else dot.reshape(count.shape)

    def weight(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        return self.p.norm[x] * self.q.norm[y]


def _by_tile(matrix: DataFrame, work: Callable[[_Tile], Iterator[dict[str, np.ndarray]]], schema: str, bounds: list[int] | None = None) -> DataFrame:
    """What ``work`` makes of each tile: arrays of the schema's columns, again and again."""
    bounds = blocks(matrix) if bounds is None else bounds
    pairs = [(p, q) for p in range(len(bounds)) for q in range(p, len(bounds))]
    narrow = [b + 1 < len(bounds) and bounds[b + 1] - bounds[b] <= 1 << 16 for b in range(len(bounds))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got: dict[int, list[list[bytes]]] = {}
        for batch in batches:
            for t, *values in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                for held, v in zip(got.setdefault(t, [[] for _ in values]), values, strict=True):
                    held.append(v)
        while got:
            t, (rows, pn, pc, pv, qn, qc, qv) = got.popitem()
            (b, c), rows = pairs[t], np.concatenate([np.frombuffer(x, np.int64) for x in rows])
            p = _Side(bounds[b], narrow[b], pn, pc, pv)
            tile = _Tile(rows, p, p if b == c else _Side(bounds[c], narrow[c], qn, qc, qv))
            del pn, pc, pv, qn, qc, qv
            for made in work(tile):
                if len(made["i"]):
                    yield pa.RecordBatch.from_arrays([pa.array(v) for v in made.values()], names=list(made))

    return matrix.select("row_id", "entries").mapInArrow(_split(bounds), _PARTS).repartitionById(len(pairs), F.col("tile")).mapInArrow(run, schema)


def half_up(x: np.ndarray, digits: int | None) -> np.ndarray:
    """Rounded as SQL does, here since decimals for each value take longer than all else; None: as it is."""
    return x if digits is None or x.dtype.kind != "f" else np.copysign(np.floor(np.abs(x) * 10.0**digits + 0.5) / 10.0**digits, x)


def exact_cosines(matrix: DataFrame, digits: int | None = None, bounds: list[int] | None = None) -> DataFrame:
    """(i, j, cos, dot) of all co-occurring pairs, exact, as ``gram.exact_cosines``; no exchange of pairs."""

    def work(t: _Tile) -> Iterator[dict[str, np.ndarray]]:
        for x, end, entries in t.stripes():
            count, dot = t.sums(x, end, entries)
            a, b = np.nonzero(count)
            found = dot[a, b]
            a += x
            yield {"i": (a + t.p.base).astype(np.int32), "j": (b + t.q.base).astype(np.int32), "cos": half_up(found / t.weight(a, b), digits), "dot": half_up(found, digits).astype(np.float64)}

    return _by_tile(matrix, work, "i int, j int, cos double, dot double", bounds)


def top_k_similar(matrix: DataFrame, k: int, digits: int, bounds: list[int] | None = None) -> DataFrame:
    """(i, j, cos, rank): the k best partners of every column by exact cosines of so many digits, ties by the smaller partner.

    Tiles leave their k best of each column and side; only these meet in an exchange.
    """

    def better(best: np.ndarray, who: np.ndarray, cos: np.ndarray, of: int) -> None:
        """Takes partner ``of`` with these cosines among the k best, which are in order; an equal one that came earlier stays before it."""
        at = np.flatnonzero(cos > best[-1])
        if len(at):
            both = np.vstack([best[:, at], cos[at]])
            order = np.argsort(-both, axis=0, kind="stable")[:k]
            best[:, at] = np.take_along_axis(both, order, 0)
            who[:, at] = np.take_along_axis(np.vstack([who[:, at], np.full(len(at), of)]), order, 0)

    def work(t: _Tile) -> Iterator[dict[str, np.ndarray]]:
        best, who = np.full((k, t.q.n), -np.inf), np.full((k, t.q.n), -1)
        for x, end, entries in t.stripes():
            count, dot = t.sums(x, end, entries)
            with np.errstate(all="ignore"):
                cos = half_up(dot / (t.p.norm[x:end, None] * t.q.norm), digits)
            cos[count == 0] = -np.inf
            for r in range(end - x):
                better(best, who, cos[r], x + r)
            own = []
            for _ in range(min(k, t.q.n)):
                top = cos.argmax(1)  # of equal ones the first
                own.append((top, cos[np.arange(end - x), top]))
                cos[np.arange(end - x), top] = -np.inf
            y, c = (np.concatenate(v) for v in zip(*own, strict=True))
            i = np.tile(np.arange(x, end), len(own))
            yield found(i[c > -np.inf] + t.p.base, y[c > -np.inf] + t.q.base, c[c > -np.inf])
        r, y = np.nonzero(who >= 0)
        yield found(y + t.q.base, who[r, y] + t.p.base, best[r, y])

    def found(i, j, cos):
        return {"i": i.astype(np.int32), "j": j.astype(np.int32), "cos": cos}

    order = Window.partitionBy("i").orderBy(F.desc("cos"), "j")
    return _by_tile(matrix, work, "i int, j int, cos double", bounds).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


# --- draws ---

_K = [int(abs(math.sin(s + 1)) * 2**32) for s in range(64)]
_TURN = [(7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)]
_WORD = [(s, (5 * s + 1) % 16, (3 * s + 5) % 16, 7 * s % 16) for s in range(16)]
#: Bytes of a message of one MD5 block, without its length.
_ROOM = 56


def _first_words(words: list[np.ndarray | np.uint32 | None], n: int) -> np.ndarray:
    """First word (as in the digest's hex) of the MD5 of n one-block messages given by their 16 words: arrays, numbers or None for 0.

    It is settled three steps before the end.
    """
    state = [np.full(n, x, np.uint32) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)]
    a, b, c, d = state
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for s in range(61):
        r = s // 16
        if r == 0:
            np.bitwise_xor(c, d, out=f), np.bitwise_and(f, b, out=f), np.bitwise_xor(f, d, out=f)
        elif r == 1:
            np.bitwise_xor(b, c, out=f), np.bitwise_and(f, d, out=f), np.bitwise_xor(f, c, out=f)
        elif r == 2:
            np.bitwise_xor(b, c, out=f), np.bitwise_xor(f, d, out=f)
        else:
            np.invert(d, out=f), np.bitwise_or(f, b, out=f), np.bitwise_xor(f, c, out=f)
        m, number = words[_WORD[s % 16][r]], _K[s]
        if isinstance(m, np.ndarray):
            np.add(f, m, out=f)
        elif m is not None:
            number = (number + int(m)) & 0xFFFFFFFF
        np.add(f, np.uint32(number), out=f), np.add(f, a, out=f)
        turn = _TURN[r][s % 4]
        np.left_shift(f, np.uint32(turn), out=g), np.right_shift(f, np.uint32(32 - turn), out=f), np.bitwise_or(f, g, out=f)
        np.add(f, b, out=a)  # the oldest word makes room for the new one
        a, b, c, d = d, a, b, c
    return (b + np.uint32(0x67452301)).byteswap()


class _Draws:
    """Draws of a tile's products under one seed: the MD5 of ``seed|row|i|j``, its first 13 hex digits over 2^52."""

    def __init__(self, t: _Tile, seed: int) -> None:
        self.t, self.seed = t, seed
        self.row, self.row_n = self.table([f"{seed}|{r}|" for r in t.rows.tolist()])
        self.i, self.i_n = self.table([f"{t.p.base + x}|" for x in range(t.p.n)])
        self.j, self.j_n = self.table([f"{t.q.base + y}" for y in range(t.q.n)], b"\x80")
        self.shifted: dict[int, np.ndarray] = {}

    @staticmethod
    def table(texts: list[str], end: bytes = b"") -> tuple[np.ndarray, np.ndarray]:
        """Texts as rows of bytes, filled up with 0, and their lengths."""
        raw = [x.encode() + end for x in texts]
        width = max(map(len, raw), default=1)
        return np.frombuffer(b"".join(x.ljust(width, b"\0") for x in raw), np.uint8).reshape(len(raw), width), np.array([len(x) for x in raw], np.int64) - len(end)

    def suffix(self, shift: int) -> np.ndarray:
        """Words of each j, from the byte ``shift`` of the first word on."""
        if shift not in self.shifted:
            wide = np.zeros((len(self.j), -(-(shift + self.j.shape[1]) // 4) * 4), np.uint8)
            wide[:, shift : shift + self.j.shape[1]] = self.j
            self.shifted[shift] = np.ascontiguousarray(wide.view("<u4").T)
        return self.shifted[shift]

    def under(self, e: np.ndarray, at: np.ndarray, p: np.ndarray) -> np.ndarray:
        """Whether the draw of each product (entry of t.p, place in t.q) is less than p."""
        row, i = self.t.p.row[e], self.t.p.col[e]
        kind = self.row_n[row] * 64 + self.i_n[i]
        if len(kind) and (kind != kind[0]).any():
            out = np.zeros(len(e), bool)
            for one in np.unique(kind):
                own = np.flatnonzero(kind == one)
                out[own] = self.alike(row[own], i[own], at[own], p[own])
            return out
        return self.alike(row, i, at, p)

    def alike(self, row: np.ndarray, i: np.ndarray, at: np.ndarray, p: np.ndarray) -> np.ndarray:
        """The same for products whose texts have the same length before j."""
        if not len(row):
            return np.zeros(0, bool)
        # texts before j are made once for each entry: a run of equal (row, i)
        new = np.flatnonzero(np.concatenate([[True], (row[1:] != row[:-1]) | (i[1:] != i[:-1])]))
        runs = np.diff(np.concatenate([new, [len(row)]]))
        r, x, n_row = row[new], i[new], int(self.row_n[row[0]])
        before = n_row + int(self.i_n[i[0]])
        text = np.zeros((len(new), _ROOM), np.uint8)
        text[:, :n_row], text[:, n_row:before] = self.row[r, :n_row], self.i[x, : before - n_row]
        heads = text.view("<u4")
        words: list[np.ndarray | np.uint32 | None] = [None] * 16
        for k in range(-(-before // 4)):
            head = heads[:, k]
            words[k] = np.repeat(head, runs) if (head != head[0]).any() else head[0]
        y = self.t.q.col[at]
        for k, tail in enumerate(self.suffix(before % 4), before // 4):
            if k < 14:
                words[k] = tail[y] if words[k] is None else tail[y] | words[k]
        words[14] = ((self.j_n[y] + before) * 8).astype(np.uint32)
        word, line = _first_words(words, len(row)).astype(np.float64), p * 2.0**32
        kept = word < line
        for one in np.flatnonzero(kept & (word + 1 > line)):  # the first 32 bits leave it open
            digest = hashlib.md5(f"{self.seed}|{self.t.rows[row[one]]}|{self.t.p.base + i[one]}|{self.t.q.base + y[one]}".encode()).hexdigest()
            kept[one] = int(digest[:13], 16) / float(1 << 52) < p[one]
        return kept


def _kept(t: _Tile, draws: _Draws, gamma: float, e: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Which products the pair draw keeps."""
    w = t.weight(t.p.col[e], t.q.col[at])
    kept = w <= gamma
    drawn = np.flatnonzero(~kept)
    for lo in range(0, len(drawn), DRAWS):
        own = drawn[lo : lo + DRAWS]
        kept[own] = draws.under(e[own], at[own], gamma / w[own])
    return kept


def sampled_cosines(matrix: DataFrame, gamma: float, seed: int = 7, digits: tuple[int, int] | None = None, bounds: list[int] | None = None) -> DataFrame:
    """(i, j, cos, dot, n_kept, p, is_exact) as ``sampling.sampled_cosines`` with draws of kind "md5"; no exchange of pairs.

    digits: to which cos and dot, and p, are rounded.
    """
    if not gamma > 0:
        raise ValueError("gamma must be positive")
    most, last = digits or (None, None)

    def work(t: _Tile) -> Iterator[dict[str, np.ndarray]]:
        draws = _Draws(t, seed)
        for x, end, entries in t.stripes():
            shape = (end - x) * t.q.n
            count, v = np.zeros(shape, np.int64), np.zeros(0)
            for e, k, at in t.products(entries, CHUNK):
                cell, value = t.cell(x, e, k, at), t.value(e, k, at)
                kept = np.flatnonzero(_kept(t, draws, gamma, np.repeat(e, k), at))
                count += np.bincount(cell[kept], minlength=shape)
                if value is not None:
                    v = (v if len(v) else np.zeros(shape)) + np.bincount(cell[kept], value[kept], minlength=shape)
            a, b = np.nonzero(count.reshape(end - x, t.q.n))
            cell, n = a * t.q.n + b, count[a * t.q.n + b]
            a += x
            w = t.weight(a, b)
            cos = (v[cell] if len(v) else n) / np.minimum(gamma, w)
            p = half_up(np.minimum(1.0, gamma / w), last)
            yield {"i": (a + t.p.base).astype(np.int32), "j": (b + t.q.base).astype(np.int32), "cos": half_up(cos, most), "dot": half_up(cos * w, most), "n_kept": n, "p": p, "is_exact": gamma >= w}

    return _by_tile(matrix, work, "i int, j int, cos double, dot double, n_kept long, p double, is_exact boolean", bounds)


def cells(matrix: DataFrame, gamma: float, seeds: list[int], least: float, bounds: list[int] | None = None) -> DataFrame:
    """(seed, i, j, exact, cos) of ``accuracy.grid`` for the pairs of exact cosine ``least`` or more, pair draws of kind "md5".

    Exact cosines come first, of all pairs; draws are made for pairs that are in the result.
    """

    def work(t: _Tile) -> Iterator[dict[str, np.ndarray]]:
        draws: list[_Draws] = []
        for x, end, entries in t.stripes():
            count, dot = t.sums(x, end, entries)
            a, b = np.nonzero(count)
            exact = dot[a, b] / t.weight(a + x, b)
            a, b, exact = a[exact >= least], b[exact >= least], exact[exact >= least]
            if not len(a):
                continue
            draws = draws or [_Draws(t, s) for s in seeds]
            place = np.full((end - x) * t.q.n, -1)
            place[a * t.q.n + b] = np.arange(len(a))
            wanted = np.zeros(end - x, bool)
            wanted[a] = True
            cos = np.zeros((len(seeds), len(a)))
            for e, k, at in t.products(entries[wanted[t.p.col[entries] - x]], CHUNK):
                to, value = place[t.cell(x, e, k, at)], t.value(e, k, at)
                own = np.flatnonzero(to >= 0)
                e, at, to = np.repeat(e, k)[own], at[own], to[own]
                v = (1.0 if value is None else value[own]) / np.minimum(gamma, t.weight(t.p.col[e], t.q.col[at]))
                for s in range(len(seeds)):
                    kept = np.flatnonzero(_kept(t, draws[s], gamma, e, at))
                    cos[s] += np.bincount(to[kept], v[kept], minlength=len(a))
            i, j = ((z + base).astype(np.int32) for z, base in ((a + x, t.p.base), (b, t.q.base)))
            n = len(seeds)
            yield {"seed": np.repeat(np.array(seeds, np.int32), len(a)), "i": np.tile(i, n), "j": np.tile(j, n), "exact": np.tile(exact, n), "cos": cos.ravel()}

    return _by_tile(matrix, work, "seed int, i int, j int, exact double, cos double", bounds)
