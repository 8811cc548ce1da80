"""Benchmark decontamination with suffix arrays of the training texts (operator 7).

Each block of documents is a shard: its words become numbers, and the places at
which a known run of words is long enough are sorted by the words that follow, a
suffix array to the depth of the longest window. Every test suffix is found by
binary search in every shard; the places in the found range are verbatim matches.
Neighbouring matches on one diagonal join to longest matches with their places.

Only test words get numbers, so places that cannot match never enter the array,
and nothing is shuffled. Test items go to the workers in chunks of ``CHUNK_BYTES``,
each a broadcast of its own. A task reads its documents once: for each block of
texts it opens one chunk after another, holds one of them at a time, and adds what
that chunk hits to the rows of the block. So results don't depend on the size of
the benchmark, and neither does a task's memory.

Words are compared by 64-bit hashes. Defined results: null and empty texts have no
words and no hit; items without words match nothing; items shorter than a window
are one window; equal items are reported under each of their ids; repeated
documents are reported each.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.llm.common import Words, blocks

WINDOW = 10
#: Bytes of test text that one broadcast index covers (its index takes about 30 times as much).
CHUNK_BYTES = 4 << 20


@dataclass
class Tests:
    """Windows of test items over their own word numbers."""

    ids: list
    vocabulary: np.ndarray  # sorted word hashes; the number of a word is its place plus one
    depth: int
    lengths: np.ndarray  # words of each distinct window
    low: np.ndarray  # keys of windows as bytes, and the largest keys that begin with them
    high: np.ndarray
    at_window: np.ndarray  # occurrences: window, item, first word in the item; sorted by window
    at_item: np.ndarray
    at_word: np.ndarray
    begin: np.ndarray  # first occurrence of each window

    @classmethod
    def of(cls, ids: list, texts: list[str | None], window: int = WINDOW) -> Tests:
        words = Words(pa.array(texts, pa.string()))
        vocabulary, number = np.unique(words.hashes(), return_inverse=True)
        number = number.astype(np.uint32) + np.uint32(1)
        first = np.cumsum(words.per_row) - words.per_row
        place, length, item = [], [], []
        for i, n in enumerate(words.per_row.tolist()):
            size = min(n, window)
            if size:
                many = n - size + 1
                place.append(first[i] + np.arange(many))
                length.append(np.full(many, size))
                item.append(np.full(many, i))
        if not place:
            none = np.zeros(0, dtype=np.int64)
            return cls(ids, vocabulary, window, none, none, none, none, none, none, none)
        place, length, item = np.concatenate(place), np.concatenate(length), np.concatenate(item)
        depth = int(length.max())
        steps = np.arange(depth)
        within = steps[None, :] < length[:, None]
        rows = np.where(within, number[np.minimum(place[:, None] + steps, len(number) - 1)], 0).astype(np.uint32)
        keys, which = np.unique(np.column_stack([rows, length.astype(np.uint32)]), axis=0, return_inverse=True)
        which = which.ravel()
        lengths = keys[:, -1].astype(np.int64)
        keys = keys[:, :-1]
        order = np.argsort(which, kind="stable")
        top = np.where(steps[None, :] < lengths[:, None], keys, np.uint32(0xFFFFFFFF))
        return cls(ids, vocabulary, depth, lengths, _bytes(keys), _bytes(top), which[order], item[order], (place - first[item])[order], np.searchsorted(which[order], np.arange(len(keys) + 1)))


def _bytes(rows: np.ndarray) -> np.ndarray:
    """Rows of word numbers as byte strings that sort like them."""
    wide = np.ascontiguousarray(rows.astype(">u4"))
    return wide.view(f"S{4 * rows.shape[1]}").ravel()


@dataclass
class Shard:
    """A block of documents: word numbers, and the suffix array of the places that can match."""

    row: np.ndarray
    first: np.ndarray
    per_row: np.ndarray
    places: np.ndarray
    keys: np.ndarray

    @classmethod
    def of(cls, words: Words, h: np.ndarray, tests: Tests) -> Shard:
        first = np.cumsum(words.per_row) - words.per_row
        none = np.zeros(0, dtype=np.int64)
        if not len(tests.lengths) or not len(words.start):
            return cls(words.row, first, words.per_row, none, np.zeros(0, dtype="S4"))
        at = np.searchsorted(tests.vocabulary, h)
        at[at == len(tests.vocabulary)] = 0
        number = np.where(tests.vocabulary[at] == h, at + 1, 0).astype(np.uint32)
        # how many known words follow at each place inside its document
        n = len(number)
        stop = number == 0
        breaks = np.flatnonzero(stop)
        upto = np.full(n, n, dtype=np.int64)
        if len(breaks):
            k = np.searchsorted(breaks, np.arange(n))
            upto = np.where(k < len(breaks), breaks[np.minimum(k, len(breaks) - 1)], n)
        run = np.minimum(upto, (first + words.per_row)[words.row]) - np.arange(n)
        places = np.flatnonzero(run >= tests.lengths.min())
        steps = np.arange(tests.depth)
        parts = []
        for low in range(0, len(places), 1 << 18):  # bounds the key matrix
            p = places[low : low + (1 << 18)]
            parts.append(_bytes(np.where(steps[None, :] < run[p][:, None], number[np.minimum(p[:, None] + steps, n - 1)], 0)))
        keys = np.concatenate(parts) if parts else np.zeros(0, dtype=f"S{4 * tests.depth}")
        order = np.argsort(keys, kind="stable")
        return cls(words.row, first, words.per_row, places[order], keys[order])

    def search(self, tests: Tests) -> tuple[np.ndarray, np.ndarray]:
        """(place, window) of every occurrence of a test window in the shard."""
        if not len(self.places):
            return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64)
        low = np.searchsorted(self.keys, tests.low, side="left")
        high = np.searchsorted(self.keys, tests.high, side="right")
        many = np.maximum(0, high - low)
        window = np.repeat(np.arange(len(many)), many)
        return self.places[np.arange(many.sum()) + np.repeat(low - np.cumsum(many) + many, many)], window


def _covered(shard: Shard, tests: Tests, place: np.ndarray, window: np.ndarray) -> np.ndarray:
    """Which words of the shard lie in an occurrence."""
    edge = np.zeros(len(shard.row) + 1, dtype=np.int64)
    np.add.at(edge, place, 1)
    np.add.at(edge, place + tests.lengths[window], -1)
    return np.cumsum(edge[:-1]) > 0


def digest(items: list) -> str:
    return hashlib.sha256(",".join(sorted(str(i) for i in items)).encode()).hexdigest()


class Indexes:
    """The test indexes of a benchmark, one broadcast a chunk: ``each`` opens them in a task, one at a time."""

    def __init__(self, benchmark: DataFrame, window: int):
        spark = benchmark.sparkSession
        rows = benchmark.select("item_id", "text").where("text is not null")
        size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
        n = max(1, -(-size // CHUNK_BYTES))
        self.chunks = []
        for k in range(n):  # one chunk at a time is in the driver
            part = rows if n == 1 else rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k)
            found = part.toArrow()
            self.chunks.append(spark.sparkContext.broadcast(Tests.of(found.column("item_id").to_pylist(), found.column("text").to_pylist(), window)))

    @property
    def block_bytes(self) -> int:
        """Text of a block: more where several chunks must be opened for it."""
        return (2 if len(self.chunks) == 1 else 8) << 20

    def each(self) -> Iterator[Tests]:
        for chunk in self.chunks:
            yield chunk.value
            if len(self.chunks) > 1:  # a worker keeps a broadcast it has opened; the file stays for the next block
                chunk.__dict__.pop("_value", None)


@dataclass
class Matches:
    """Longest verbatim matches of a block: row, item, first word in the document and in the item, words."""

    row: np.ndarray
    item: np.ndarray
    doc_word: np.ndarray
    item_word: np.ndarray
    n_words: np.ndarray

    @classmethod
    def of(cls, shard: Shard, tests: Tests, place: np.ndarray, window: np.ndarray) -> Matches:
        """Occurrences that follow one another in both texts join to one match."""
        many = np.diff(tests.begin)[window] if len(place) else np.zeros(0, dtype=np.int64)
        at = np.arange(many.sum()) + np.repeat(tests.begin[window] - np.cumsum(many) + many, many) if len(place) else many
        place, size = np.repeat(place, many), np.repeat(tests.lengths[window], many)
        item, word = tests.at_item[at], tests.at_word[at]
        order = np.lexsort([place, place - word, item])
        place, size, item, word = place[order], size[order], item[order], word[order]
        new = np.ones(len(place), dtype=bool)
        new[1:] = (item[1:] != item[:-1]) | ((place - word)[1:] != (place - word)[:-1]) | (place[1:] != place[:-1] + 1) | (shard.row[place[1:]] != shard.row[place[:-1]])
        begin = np.flatnonzero(new)
        last = np.append(begin[1:], len(place))[: len(begin)] - 1
        row = shard.row[place[begin]]
        return cls(row, item[begin], place[begin] - shard.first[row], word[begin], place[last] + size[last] - place[begin])


_RESULT = "doc_id long, n_words long, n_hit long, n_items long, items_sha256 string, contaminated boolean, longest long, low array<bigint>, high array<bigint>"
_KINDS = [pa.int64()] * 4 + [pa.string(), pa.bool_(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64())]


def _ranges(covered: np.ndarray) -> tuple[list[int], list[int]]:
    """Begin and end of each run of covered words of one document."""
    edge = np.diff(np.concatenate([[0], covered.astype(np.int8), [0]]))
    return np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist()


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated, longest, low, high of every row.

    longest: words of the longest verbatim match; low, high: hit word ranges. One
    narrow pass over docs, whatever the number of chunks.
    """
    indexes = Indexes(benchmark, window)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, max_bytes=indexes.block_bytes, owner="words"):
            words = Words(batch.column("text"))
            hashes = words.hashes()
            covered = np.zeros(len(words.row), dtype=bool)
            longest = np.zeros(batch.num_rows, dtype=np.int64)
            items: dict[int, set[str]] = {}
            for tests in indexes.each():
                shard = Shard.of(words, hashes, tests)
                place, found = shard.search(tests)
                if not len(place):
                    continue
                covered |= _covered(shard, tests, place, found)
                matches = Matches.of(shard, tests, place, found)
                np.maximum.at(longest, matches.row, matches.n_words)
                for r, i in zip(matches.row.tolist(), matches.item.tolist(), strict=True):
                    items.setdefault(r, set()).add(str(tests.ids[i]))
            first = np.cumsum(words.per_row) - words.per_row
            nothing = digest([])
            out = []
            for r, (doc, n) in enumerate(zip(batch.column("doc_id").to_pylist(), words.per_row.tolist(), strict=True)):
                if r not in items:
                    out.append((doc, n, 0, 0, nothing, False, 0, [], []))
                    continue
                low, high = _ranges(covered[first[r] : first[r] + n])
                out.append((doc, n, sum(high) - sum(low), len(items[r]), digest(list(items[r])), True, int(longest[r]), low, high))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), _KINDS, strict=True)], names=["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated", "longest", "low", "high"])

    return docs.select("doc_id", "text").mapInArrow(run, _RESULT)


def longest_matches(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, item_id (text), doc_word, item_word, n_words of every longest verbatim match of a window or more."""
    schema = pa.schema([("doc_id", pa.int64()), ("item_id", pa.string()), ("doc_word", pa.int64()), ("item_word", pa.int64()), ("n_words", pa.int64())])
    indexes = Indexes(benchmark, window)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, max_bytes=indexes.block_bytes, owner="words"):
            words = Words(batch.column("text"))
            hashes, doc_ids = words.hashes(), batch.column("doc_id").to_pylist()
            for tests in indexes.each():
                shard = Shard.of(words, hashes, tests)
                m = Matches.of(shard, tests, *shard.search(tests))
                yield pa.RecordBatch.from_arrays([pa.array([doc_ids[r] for r in m.row], pa.int64()), pa.array([str(tests.ids[i]) for i in m.item], pa.string()), pa.array(m.doc_word), pa.array(m.item_word), pa.array(m.n_words)], schema=schema)

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, item_id string, doc_word long, item_word long, n_words long")


def keep_uncontaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """Rows of docs, all columns, without an occurrence of a test window. One narrow pass."""
    indexes = Indexes(benchmark, window)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, max_bytes=indexes.block_bytes, owner="words"):
            words = Words(batch.column("text"))
            hashes, keep = words.hashes(), np.ones(batch.num_rows, dtype=bool)
            for tests in indexes.each():
                shard = Shard.of(words, hashes, tests)
                keep[shard.row[shard.search(tests)[0]]] = False
            yield batch.filter(pa.array(keep))

    return docs.mapInArrow(run, docs.schema)
