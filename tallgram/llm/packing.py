"""Vector bin packing of token sequences (operator 5).

Every item has a vector of demands: tokens, segments (1) and loss-bearing tokens.
A sequence has a limit in each dimension. The open sequence takes, again and
again, the item that fits and whose demand has the largest dot product with what
is left of the sequence, each dimension weighted by its mean demand; when none
fits, items that may be cut give a head that fills the gap, and the sequence is
closed. Items come in windows of a bounded number, so memory doesn't grow with a
partition, and no row leaves its partition: there is no shuffle.

Null texts are empty and give one piece (the end id alone). An empty table gives
no piece. Equal documents are packed like any other.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.llm.common import blocks
from tallgram.llm.tokens import TOKEN_BLOCK_BYTES, Encoder, vocabulary_path

SEQUENCE = 2048
#: Items that wait for a place at once.
WINDOW = 800


@dataclass(frozen=True)
class Limits:
    tokens: int = SEQUENCE
    segments: int = 256
    loss_tokens: int = SEQUENCE

    def array(self) -> np.ndarray:
        return np.array([self.tokens, self.segments, self.loss_tokens], dtype=np.float64)


@dataclass
class Packer:
    """Places items one sequence after another. place() results are (item, start in item, length, sequence, offset)."""

    limits: Limits = field(default_factory=Limits)
    cut: bool = True
    least_cut: int = 8
    sequences: int = 0
    window: int = WINDOW

    def __post_init__(self) -> None:
        self.demand = np.zeros((0, 3))
        self.item = np.zeros(0, dtype=np.int64)
        self.begin = np.zeros(0, dtype=np.int64)
        self._room = self.limits.array()
        self._offset = 0

    def add(self, item: np.ndarray, tokens: np.ndarray, loss: np.ndarray, begin: np.ndarray) -> None:
        if not self.cut and (np.any(tokens > self.limits.tokens) or np.any(loss > self.limits.loss_tokens)):
            raise ValueError("an item is over the limits and may not be cut")
        self.demand = np.concatenate([self.demand, np.column_stack([tokens, np.ones(len(tokens)), loss]).astype(np.float64)])
        self.item, self.begin = np.concatenate([self.item, item]), np.concatenate([self.begin, begin])

    def _close(self) -> None:
        if self._offset:
            self.sequences += 1
            self._offset, self._room = 0, self.limits.array()

    def place(self, down_to: int) -> list[tuple[int, int, int, int, int]]:
        """Place waiting items until down_to or fewer are left."""
        placed = []
        if len(self.item) <= down_to:
            return placed
        whole = self.limits.array()
        weight = self.demand.mean(axis=0) / whole
        alive = np.ones(len(self.item), dtype=bool)
        left = len(self.item)
        demand, begin = self.demand, self.begin
        while left > down_to:
            fits = alive & (demand <= self._room).all(axis=1)
            at = np.flatnonzero(fits)
            if len(at):
                k = at[int(np.argmax((demand[at] / whole) @ (weight * self._room / whole)))]
                n = int(demand[k, 0])
                placed.append((int(self.item[k]), int(begin[k]), n, self.sequences, self._offset))
                alive[k] = False
                left -= 1
                self._room = self._room - demand[k]
                self._offset += n
            else:
                gap = int(min(self._room[0], self._room[2])) if self._room[1] >= 1 else 0
                at = np.flatnonzero(alive)
                if self.cut and gap >= self.least_cut and len(at):
                    k = at[int(np.argmax(demand[at, 0]))]
                    if demand[k, 2] == demand[k, 0]:  # loss-bearing throughout: any cut keeps the two alike
                        placed.append((int(self.item[k]), int(begin[k]), gap, self.sequences, self._offset))
                        begin[k] += gap
                        demand[k, 0] -= gap
                        demand[k, 2] -= gap
                        self._offset += gap
                self._close()
                continue
            if self._room[0] < 1 or self._room[1] < 1:
                self._close()
        self.demand, self.item, self.begin = demand[alive], self.item[alive], begin[alive]
        return placed

    def finish(self) -> list[tuple[int, int, int, int, int]]:
        placed = self.place(0)
        self._close()
        return placed


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
_NAMES = [x.split()[0] for x in PIECES.split(", ")]


def pack_documents(docs: DataFrame, limits: Limits = Limits(), vocabulary: str | None = None) -> DataFrame:
    """Pieces of all docs (doc_id, text): full sequences are cut off long documents, the rest is packed.

    sequence_id is the partition number times 2^32 plus the number of the sequence
    in its partition, so a redone task gives the same ids.
    """
    vocabulary = vocabulary or vocabulary_path()

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, base = Encoder.at(vocabulary), TaskContext.get().partitionId() << 32
        packer = Packer(limits)
        waiting: dict[int, tuple[int | None, int, np.ndarray, int]] = {}  # item -> doc, start of its ids, ids, doc's total
        serial = items_seen = 0

        def rows(placed: list[tuple[int, int, int, int, int]]) -> pa.RecordBatch:
            out = []
            for item, begin, n, sequence, offset in placed:
                doc, low, ids, total = waiting[item]
                out.append((doc, begin, n, zlib.crc32(ids[begin - low : begin - low + n]), total, base + sequence, offset))
                if begin + n == total:
                    del waiting[item]
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*out, strict=True) if out else [[]] * 7)], names=_NAMES)

        for block in blocks(batches, max_bytes=TOKEN_BLOCK_BYTES, owner="tokens"):
            ids, offsets = encoder.encode(block.column("text"))
            ids = ids.astype("<u4")
            keys = block.column("doc_id").to_pylist()
            full = []
            items, lengths, begins = [], [], []
            for doc, a, b in zip(keys, offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                total, at = b - a, 0
                while total - at >= limits.tokens:
                    full.append((doc, at, limits.tokens, zlib.crc32(ids[a + at : a + at + limits.tokens]), total, serial, 0))
                    serial += 1
                    at += limits.tokens
                if at < total:
                    waiting[items_seen] = (doc, at, ids[a + at : b].copy(), total)
                    items.append(items_seen)
                    items_seen += 1
                    lengths.append(total - at)
                    begins.append(at)
            if full:
                columns = list(zip(*full, strict=True))
                # full sequences take the odd numbers of the partition, packed ones the even numbers
                columns[5] = tuple(base + 2 * s + 1 for s in columns[5])
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=_NAMES)
            length = np.array(lengths, dtype=np.int64)
            packer.add(np.array(items, dtype=np.int64), length, length, np.array(begins, dtype=np.int64))
            if len(packer.item) > packer.window:
                yield rows([(i, b, n, 2 * s, o) for i, b, n, s, o in packer.place(packer.window // 2)])
        last = packer.finish()
        if last:
            yield rows([(i, b, n, 2 * s, o) for i, b, n, s, o in last])

    return docs.select("doc_id", "text").mapInArrow(pack, PIECES)


def pack_examples(examples: DataFrame, limits: Limits) -> DataFrame:
    """Place whole instruction examples (example_id, n_tokens, loss_tokens) under all three limits, uncut.

    Examples over a limit get sequence_id null, and so do those with a null count.
    Returns example_id, n_tokens, loss_tokens, sequence_id, offset.
    """
    names = ["example_id", "n_tokens", "loss_tokens", "sequence_id", "offset"]

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base = TaskContext.get().partitionId() << 32
        packer = Packer(limits, cut=False)
        known: dict[int, tuple] = {}
        serial = 0

        def rows(placed) -> pa.RecordBatch:
            out = [(*known.pop(i), base + s, o) for i, _, _, s, o in placed]
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (zip(*out, strict=True) if out else [[]] * 5)], names=names)

        for batch in batches:
            odd, good = [], []
            for key, n, loss in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                if n is None or loss is None or not 0 < n <= limits.tokens or not 0 <= loss <= min(n, limits.loss_tokens):
                    odd.append((key, n, loss, None, None))
                else:
                    known[serial] = (key, n, loss)
                    good.append((serial, n, loss))
                    serial += 1
            if odd:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*odd, strict=True)], names=names)
            if good:
                item, n, loss = (np.array(c, dtype=np.int64) for c in zip(*good, strict=True))
                packer.add(item, n, loss, np.zeros(len(item), dtype=np.int64))
            if len(packer.item) > packer.window:
                yield rows(packer.place(packer.window // 2))
        yield rows(packer.finish())

    columns = [F.col(c).cast("long").alias(c) for c in names[:3]]
    return examples.select(*columns).mapInArrow(pack, ", ".join(f"{n} long" for n in names))
