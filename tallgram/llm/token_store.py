"""Token-id shards with a minimal perfect hash index (operator 4).

A store is a Parquet folder in which one row is one *segment*: a raw payload of
little-endian ids (2 or 4 bytes each), the document keys in payload order, and an
index. The index is a minimal perfect hash: keys fall into small buckets, each
bucket has a pilot number under which all its keys land on free slots, and slot s
holds (fingerprint, row, first id, number of ids). A lookup is two hashes and one
comparison, whatever the size; a key that was never stored fails the fingerprint
but for one chance in 2^32, and keyed access compares the stored key as well.

Segments are in ascending document order: (part, seg) orders them, and parts are
the range partitions of doc_id. Null texts are empty (only the end id); null ids
come first and repeated ids keep their own entries (their occurrence number is
part of the key); an empty table gives an empty store.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tallgram.llm.common import blocks, mix64, scratch
from tallgram.llm.tokens import Encoder, vocabulary_path

KEYS_PER_BUCKET = 4
#: Text of a segment at most, and chunks a worker remembers while it writes.
SEGMENT_BYTES = 12 << 20
ENCODER_MEMORY = 1_000_000
_NULL_KEY = np.uint64(0x5851F42D4C957F2D)
_SLOT = np.dtype([("fingerprint", "<u4"), ("row", "<u4"), ("first", "<u8"), ("count", "<u4")])
#: Wanted ids up to which keyed access broadcasts them (8 bytes each); beyond it segments and ids meet by a shuffle.
BROADCAST_IDS = 1_000_000

STORE_SCHEMA = "part int, seg int, before long, n_tokens long, width int, doc_ids array<bigint>, payload binary, index binary"


def key_hashes(ids: list[int | None], occurrence: np.ndarray | None = None) -> np.ndarray:
    """64-bit keys of document ids; occurrence tells repeated ids apart."""
    value = np.fromiter((0 if i is None else i for i in ids), dtype=np.int64, count=len(ids)).astype(np.uint64)
    value = mix64(value + np.uint64(0x9E3779B97F4A7C15))
    value[np.fromiter((i is None for i in ids), dtype=bool, count=len(ids))] = _NULL_KEY
    return value if occurrence is None else mix64(value ^ mix64(occurrence.astype(np.uint64)))


def _slots(keys: np.ndarray, pilots: np.ndarray, salt: int, n: int) -> np.ndarray:
    return mix64(keys ^ mix64(pilots.astype(np.uint64) + np.uint64(salt << 32))) % np.uint64(n)


def _buckets(keys: np.ndarray, salt: int, n_buckets: int) -> np.ndarray:
    return mix64(keys + np.uint64(2 * salt + 1)) % np.uint64(n_buckets)


def build_index(keys: np.ndarray, first: np.ndarray, count: np.ndarray) -> bytes:
    """The index of distinct keys as bytes: header (n, buckets, salt), pilots, slots."""
    n = len(keys)
    if not n:
        return np.zeros(3, dtype="<u4").tobytes()
    if len(np.unique(keys)) != n:
        raise ValueError("keys of one segment must differ")
    n_buckets = -(-n // KEYS_PER_BUCKET)
    for salt in range(64):
        bucket = _buckets(keys, salt, n_buckets).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        sizes = np.bincount(bucket, minlength=n_buckets)
        begin = np.cumsum(sizes) - sizes
        taken = np.zeros(n, dtype=bool)
        pilots = np.zeros(n_buckets, dtype="<u4")
        place = np.empty(n, dtype=np.int64)
        done = True
        for b in np.argsort(-sizes, kind="stable"):
            size = sizes[b]
            if not size:
                break
            mine = order[begin[b] : begin[b] + size]
            found, low, width = False, 0, 16
            while not found and low < (1 << 20):
                tries = np.arange(low, low + width)
                at = _slots(keys[mine][None, :], tries[:, None], salt, n).astype(np.int64)
                good = ~taken[at].any(axis=1)
                if size > 1:
                    ranked = np.sort(at, axis=1)
                    good &= (ranked[:, 1:] != ranked[:, :-1]).all(axis=1)
                if good.any():
                    k = int(np.argmax(good))
                    pilots[b], found = tries[k], True
                    taken[at[k]] = True
                    place[mine] = at[k]
                low, width = low + width, min(4096, width * 4)
            if not found:
                done = False
                break
        if done:
            slots = np.zeros(n, dtype=_SLOT)
            slots["fingerprint"][place] = (mix64(keys + np.uint64(77)) >> np.uint64(32)).astype(np.uint32)
            slots["row"][place], slots["first"][place], slots["count"][place] = np.arange(n), first, count
            return np.array([n, n_buckets, salt], dtype="<u4").tobytes() + pilots.tobytes() + slots.tobytes()
    raise ValueError("no perfect hash found")


def lookup(index: bytes, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(known, row, first, count) of each key: constant time a key."""
    n, n_buckets, salt = (int(x) for x in np.frombuffer(index, dtype="<u4", count=3))
    if not n:
        none = np.zeros(len(keys), dtype=np.int64)
        return none.astype(bool), none, none, none
    pilots = np.frombuffer(index, dtype="<u4", count=n_buckets, offset=12)
    slots = np.frombuffer(index, dtype=_SLOT, count=n, offset=12 + 4 * n_buckets)
    hit = slots[_slots(keys, pilots[_buckets(keys, salt, n_buckets).astype(np.int64)], salt, n).astype(np.int64)]
    known = hit["fingerprint"] == (mix64(keys + np.uint64(77)) >> np.uint64(32)).astype(np.uint32)
    return known, hit["row"].astype(np.int64), hit["first"].astype(np.int64), hit["count"].astype(np.int64)


def _occurrences(ids: list[int | None]) -> np.ndarray:
    """How many equal ids come before each entry of an ascending list."""
    out = np.zeros(len(ids), dtype=np.int64)
    for i in range(1, len(ids)):
        if ids[i] == ids[i - 1]:
            out[i] = out[i - 1] + 1
    return out


def write_token_store(docs: DataFrame, path: str, vocabulary: str | None = None) -> str:
    """Encode docs (doc_id, text) and write the store to path. One shuffle, by doc_id range; returns path."""
    vocabulary = vocabulary or vocabulary_path()

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, part, before = Encoder.at(vocabulary, ENCODER_MEMORY), TaskContext.get().partitionId(), 0
        for seg, block in enumerate(blocks(batches, max_bytes=SEGMENT_BYTES, owner="tokens")):
            ids, offsets = encoder.encode(block.column("text"))
            keys = block.column("doc_id").to_pylist()
            width = 2 if len(ids) and ids.max() < 1 << 16 else 4
            index = build_index(key_hashes(keys, _occurrences(keys)), offsets[:-1], np.diff(offsets))
            yield pa.RecordBatch.from_pylist(
                [{"part": part, "seg": seg, "before": before, "n_tokens": len(ids), "width": width, "doc_ids": keys, "payload": ids.astype(f"<u{width}").tobytes(), "index": index}],
                schema=pa.schema([("part", pa.int32()), ("seg", pa.int32()), ("before", pa.int64()), ("n_tokens", pa.int64()), ("width", pa.int32()), ("doc_ids", pa.list_(pa.int64())), ("payload", pa.binary()), ("index", pa.binary())]),
            )
            before += len(ids)

    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = docs.select("doc_id", "text", F.xxhash64("text").alias("tie"))
    ordered = rows.repartitionByRange(n, "doc_id", "tie").sortWithinPartitions("doc_id", "tie").select("doc_id", "text")
    ordered.mapInArrow(encode, STORE_SCHEMA).write.option("compression", "zstd").parquet(path)
    return path


def read_token_store(spark, path: str) -> DataFrame:
    return spark.read.schema(STORE_SCHEMA).parquet(path)


def part_starts(store: DataFrame) -> dict[int, int]:
    """Ids before each part: one number a range partition, read from the small columns only."""
    totals = store.groupBy("part").agg(F.sum("n_tokens").alias("n")).collect()
    out, run = {}, 0
    for r in sorted(totals, key=lambda r: r["part"]):
        out[r["part"]] = run
        run += r["n"]
    return out


def document_digests(store: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every stored document, each found through the index of its segment."""
    starts = part_starts(store)

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                keys = row["doc_ids"]
                known, at, first, count = lookup(row["index"], key_hashes(keys, _occurrences(keys)))
                if not known.all() or (at != np.arange(len(keys))).any():
                    raise ValueError(f"segment {row['part']}/{row['seg']}: a stored key isn't in the index")
                ids = np.frombuffer(row["payload"], dtype=f"<u{row['width']}").astype("<u4")
                base = starts[row["part"]] + row["before"]
                sums = [zlib.crc32(ids[a : a + n]) for a, n in zip(first.tolist(), count.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(first + base), pa.array(count), pa.array(sums, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return store.mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def _holder(low: np.ndarray, high: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """For each id the first of the ascending spans [low, high] that can hold it, or -1."""
    at = np.searchsorted(high, ids, side="left")
    inside = at < len(high)
    inside[inside] = low[at[inside]] <= ids[inside]
    return np.where(inside, at, -1)


def _asked(spans: DataFrame, wanted: DataFrame) -> DataFrame:
    """(part, seg, asked): the wanted ids of each segment that can hold them, every id in one segment.

    Parts and segments are in ascending order of ids, so two binary searches find the
    segment: in the bounds of the parts (one row a range partition, in the driver),
    then in those of the part's segments, where ids and segments of the part meet.
    """
    parts = spans.groupBy("part").agg(F.min("low").alias("low"), F.max("high").alias("high")).orderBy("part").toArrow()
    part, low, high = (parts.column(c).to_numpy() for c in ("part", "low", "high"))

    def to_part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id").to_numpy()
            at = _holder(low, high, ids)
            yield pa.RecordBatch.from_arrays([pa.array(part[at[at >= 0]].astype(np.int32)), pa.array(ids[at >= 0])], names=["of_part", "doc_id"])

    def to_segment(asked: pa.Table, there: pa.Table) -> pa.Table:
        there = there.sort_by("seg")
        ids = asked.column("doc_id").to_numpy()
        at = _holder(there.column("low").to_numpy(), there.column("high").to_numpy(), ids)
        part = there.column("part")[0].as_py() if len(there) else 0
        return pa.table({"part": pa.array(np.full(int((at >= 0).sum()), part), pa.int32()), "seg": pa.array(there.column("seg").to_numpy()[at[at >= 0]], pa.int32()), "doc_id": pa.array(ids[at >= 0], pa.int64())})

    placed = wanted.mapInArrow(to_part, "of_part int, doc_id long")
    return placed.groupBy("of_part").cogroup(spans.groupBy("part")).applyInArrow(to_segment, "part int, seg int, doc_id long").groupBy("part", "seg").agg(F.collect_list("doc_id").alias("asked"))


def fetch(store: DataFrame, wanted: DataFrame) -> DataFrame:
    """doc_id and ids of the wanted documents (column doc_id), through the index: one row for each stored id.

    Payloads of segments that can't hold a wanted id aren't decoded. A repeated id
    gives its first entry; ids that aren't stored give no row.
    """
    ids = wanted.select(F.col("doc_id").cast("long").alias("doc_id")).where("doc_id is not null").distinct()
    spans = store.select("part", "seg", F.array_min("doc_ids").alias("low"), F.array_max("doc_ids").alias("high")).where("low is not null")
    asked = _asked(spans, ids)
    if ids.count() <= BROADCAST_IDS:
        asked = F.broadcast(asked)
    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int64()))])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                keys, own = row["asked"], row["doc_ids"]
                known, at, first, count = lookup(row["index"], key_hashes(keys, np.zeros(len(keys), dtype=np.int64)))
                tokens = np.frombuffer(row["payload"], dtype=f"<u{row['width']}").astype(np.int64)
                found = [(k, tokens[a : a + n].tolist()) for k, ok, r, a, n in zip(keys, known, at, first, count, strict=True) if ok and own[r] == k]
                yield pa.RecordBatch.from_pylist([{"doc_id": k, "ids": v} for k, v in found], schema=schema)

    return store.join(asked, ["part", "seg"]).select("asked", "doc_ids", "width", "payload", "index").mapInArrow(read, "doc_id long, ids array<bigint>")


def token_digests(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """Write the store to the shared folder, read it back, and digest each document."""
    path = write_token_store(docs, scratch(docs.sparkSession, "tokens"), vocabulary)
    return document_digests(read_token_store(docs.sparkSession, path))
