"""Pieces that the corpus operators share: tables, the shared folder, Arrow text blocks.

Everything here is either a plan builder (takes and returns DataFrames) or a
vectorised helper that runs inside an Arrow batch. Nothing collects rows.
"""

from __future__ import annotations

import atexit
import ctypes
import gc
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python worker handles at once; bounds its memory.
BLOCK_BYTES = 3 << 20


#: Rows of an Arrow batch at most: rows are whole texts here, and batches live in both the JVM and the worker.
BATCH_ROWS = 2000


def bounded_batches(spark: SparkSession) -> None:
    """Lower the session's Arrow batch rows to BATCH_ROWS if they are more (a setting that may change at any time)."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key))
    if now <= 0 or now > BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    bounded_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors see: ``spark.checkpoint.dir`` of the session.

    Where it is unset and the session is local (tests), a temporary folder is
    made, set as the checkpoint folder and removed at exit. On a cluster without
    the setting there is no safe choice, so this raises.
    """
    known = spark.conf.get("spark.checkpoint.dir", None)
    if known:
        return known.rstrip("/")
    sc = spark.sparkContext
    if getattr(sc, "_tallgram_shared", None) is None:
        if not sc.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc._tallgram_shared = tempfile.mkdtemp(prefix="tallgram-")
        atexit.register(shutil.rmtree, sc._tallgram_shared, True)
        sc.setCheckpointDir(sc._tallgram_shared)
    return f"file://{sc._tallgram_shared}"


def scratch(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/tallgram/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it back: a lineage cut that any executor can redo from."""
    spark = df.sparkSession
    bounded_batches(spark)
    path = scratch(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def split_rule(modulus: int, remainder: int, doc_id: str = "doc_id"):
    """True where crc32(doc_id as text) mod modulus equals remainder (null ids: false)."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % modulus == remainder, F.lit(False))


# --- Arrow blocks -----------------------------------------------------------


#: What operators remember in a worker between tasks: owner to a function that forgets it.
remembered: dict[str, Callable[[], None]] = {}


def trim() -> None:
    """Give freed memory back: a worker lives on after its task, beside others."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (OSError, AttributeError):  # not glibc
        pass


def blocks(batches: Iterator[pa.RecordBatch], text: str = "text", max_bytes: int = BLOCK_BYTES, owner: str = "") -> Iterator[pa.RecordBatch]:
    """Cut batches into runs of rows whose text is about max_bytes (one row at least).

    What other owners remember in this worker is forgotten first.
    """
    for name, forget in remembered.items():
        if name != owner:
            forget()
    trim()
    yield from _cut(batches, text, max_bytes)
    trim()


def _cut(batches: Iterator[pa.RecordBatch], text: str, max_bytes: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        run = np.cumsum(sizes)
        at = 0
        while at < batch.num_rows:
            base = run[at - 1] if at else 0
            to = max(at + 1, int(np.searchsorted(run, base + max_bytes, side="right")))
            yield batch.slice(at, to - at)
            at = to


def text_bytes(column: pa.Array) -> tuple[bytes, np.ndarray]:
    """UTF-8 of all rows back to back, and n+1 offsets. Null counts as empty."""
    column = pc.fill_null(column, "") if column.null_count else column
    column = column.cast(pa.large_string())
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    raw = data.slice(offsets[0], offsets[-1] - offsets[0]).to_pybytes() if data is not None and len(column) else b""
    return raw, offsets - offsets[0] if len(column) else np.zeros(1, dtype=np.int64)


#: ASCII letters lowered, digits and all bytes of non-ASCII characters kept, the rest blank.
WORD_BYTES = bytes(i + 32 if 65 <= i <= 90 else i if 48 <= i <= 57 or 97 <= i <= 122 or i >= 128 else 32 for i in range(256))
#: ASCII letters lowered; blanks are the six ASCII white-space characters.
LOWER_BYTES = bytes(i + 32 if 65 <= i <= 90 else 32 if 9 <= i <= 13 else i for i in range(256))

_SEED = np.random.Generator(np.random.PCG64(20240229))
_BYTE_VALUES = _SEED.integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INVERSE = pow(_BASE, -1, 1 << 64)
_powers: dict[str, np.ndarray] = {}
remembered["words"] = _powers.clear


def _powers_of(which: str, n: int) -> np.ndarray:
    have = _powers.get(which)
    if have is None or len(have) < n:
        size = max(n, 1 << 20)
        base = np.uint64(_BASE if which == "up" else _BASE_INVERSE)
        have = np.full(size, base, dtype=np.uint64)
        have[0] = 1
        have = np.multiply.accumulate(have)
        _powers[which] = have
    return have[:n]


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (shift-xor-multiply); uint64 in and out."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x = x * np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


class Words:
    """The words of a block of texts: byte ranges, the row of each, and a 64-bit hash of each.

    raw is the block after ``translate``: words are the runs without byte 32.
    """

    def __init__(self, column: pa.Array, bytes_table: bytes = WORD_BYTES):
        raw, offsets = text_bytes(column)
        self.raw = raw.translate(bytes_table)
        data = np.frombuffer(self.raw, dtype=np.uint8)
        self.rows = len(offsets) - 1
        inside = np.zeros(len(data) + 1, dtype=bool)
        inside[:-1] = data != 32
        before = np.zeros(len(data) + 1, dtype=bool)
        before[1:] = inside[:-1]
        first = inside & ~before
        first[offsets[:-1][offsets[:-1] < len(data)]] |= inside[offsets[:-1][offsets[:-1] < len(data)]]
        self.start = np.flatnonzero(first)
        ends = before & (~inside | first)
        # a text that begins inside a run of word bytes ends the word of the text before it
        self.end = np.flatnonzero(ends)
        self.per_row = np.diff(np.searchsorted(self.start, offsets))
        self.row = np.repeat(np.arange(self.rows), self.per_row)
        self._data = data

    def hashes(self) -> np.ndarray:
        """Polynomial hash over random byte values mod 2^64, moved to position 0, then mixed with the length."""
        n = len(self._data)
        total = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum(_BYTE_VALUES[self._data] * _powers_of("up", n), out=total[1:])
        value = (total[self.end] - total[self.start]) * _powers_of("down", n + 1)[self.start]
        return mix64(value ^ mix64((self.end - self.start).astype(np.uint64)))

    def word(self, i: int) -> bytes:
        return self.raw[self.start[i] : self.end[i]]
