"""Media columns: lossless storage and signature sniffing (operator 3).

A payload is kept as the 8-bit samples of a mono wave file: RIFF header, ``fmt ``
and ``data`` chunks. Readers trust no declared type: an Aho-Corasick automaton
finds magic bytes anywhere in a value, a validator of that format checks structure
and lengths, the first valid format at position 0 is the true type, and valid
formats further in are embedded media, which are carved out: their checksums are
part of the feature. Validators remember what they have read, so many magic bytes in
one long value cost one pass over it.

Defined results: null is the empty payload; texts are padded with zero bytes to a
positive multiple of 64; equal texts give equal values; unknown bytes have the
type ``application/octet-stream``; magic bytes that fail their validator are no
medium.
"""

from __future__ import annotations

import bisect
import hashlib
import struct
import zlib
from collections.abc import Callable, Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from tallgram.llm.common import blocks, stored

UNIT = 64
SAMPLE_RATE = 8000


def wave_of(payload: bytes) -> bytes:
    """payload as unsigned 8-bit mono samples; odd lengths get the pad byte that RIFF asks for."""
    odd = len(payload) & 1
    head = struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(payload) + odd, b"WAVE", b"fmt ", 16, 1, 1, SAMPLE_RATE, SAMPLE_RATE, 1, 8, b"data", len(payload))
    return head + payload + b"\0" * odd


def wave_samples(stored_bytes: bytes) -> bytes:
    """The samples of an 8-bit wave file, its structure checked."""
    end = _riff(Value(stored_bytes), 0)
    if end is None or stored_bytes[8:12] != b"WAVE":
        raise ValueError("not a whole wave file")
    at = 12
    while at + 8 <= end:
        name, size = struct.unpack_from("<4sI", stored_bytes, at)
        if name == b"data":
            return stored_bytes[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    raise ValueError("no data chunk")


class Value(bytes):
    """Bytes with what validators of one format learn about them, so that many magic bytes cost one pass, not one each."""

    def next_of(self, mark: bytes, at: int) -> int:
        """The first place of mark from ``at`` on, or -1. All places are found once."""
        known = self.__dict__.setdefault("marks", {})
        if mark not in known:
            places, i = [], self.find(mark)
            while i >= 0:
                places.append(i)
                i = self.find(mark, i + 1)
            known[mark] = places
        places = known[mark]
        k = bisect.bisect_left(places, at)
        return places[k] if k < len(places) else -1

    def chain(self, name: str, at: int, step: Callable[[int], tuple[int, bool] | None]) -> int | None:
        """Follow step (place to next place and whether that ends the medium) to its end; ends are remembered by place."""
        known: dict[int, int | None] = self.__dict__.setdefault(name, {})
        path, end = [], None
        while at not in known:
            path.append(at)
            found = step(at)
            if found is None:
                break
            at, last = found
            if last:
                end = at
                break
        else:
            end = known[at]
        for place in path:
            known[place] = end
        return end


# Validators: (value, position of the magic's format start) -> end of the medium, or None.


def _riff(b: Value, at: int) -> int | None:
    if at + 12 > len(b):
        return None
    end = at + 8 + struct.unpack_from("<I", b, at + 4)[0]
    if end > len(b) or b[at + 8 : at + 12] not in (b"WAVE", b"AVI ", b"WEBP"):
        return None

    def step(k: int) -> tuple[int, bool] | None:
        if k + 8 > end:
            return None
        size = struct.unpack_from("<I", b, k + 4)[0]
        k += 8 + size + (size & 1)
        return (k, k == end) if k <= end else None

    return end if end == at + 12 or b.chain(f"riff{end}", at + 12, step) == end else None


def _png(b: Value, at: int) -> int | None:
    if at + 33 > len(b) or b[at + 8 : at + 16] != b"\0\0\0\rIHDR" or zlib.crc32(b[at + 12 : at + 29]) != struct.unpack_from(">I", b, at + 29)[0]:
        return None

    def step(k: int) -> tuple[int, bool] | None:
        if k + 12 > len(b):
            return None
        size, name = struct.unpack_from(">I4s", b, k)
        end = k + 12 + size
        if end > len(b) or not name.isalpha() or zlib.crc32(memoryview(b)[k + 4 : end - 4]) != struct.unpack_from(">I", b, end - 4)[0]:
            return None
        return end, name == b"IEND"

    return b.chain("png", at + 33, step)


def _gif(b: Value, at: int) -> int | None:
    if at + 13 > len(b) or b[at + 3 : at + 6] not in (b"87a", b"89a"):
        return None

    def blocks_end(k: int) -> int | None:
        def step(k: int) -> tuple[int, bool] | None:
            if k >= len(b):
                return None
            return (k + 1 + b[k], False) if b[k] else (k + 1, True)

        return b.chain("gif-blocks", k, step)

    def step(k: int) -> tuple[int, bool] | None:
        if k >= len(b):
            return None
        kind, end = b[k], None
        if kind == 0x3B:
            return k + 1, True
        if kind == 0x21:
            end = blocks_end(k + 2)
        elif kind == 0x2C and k + 10 <= len(b):
            end = blocks_end(k + 11 + (3 << ((b[k + 9] & 7) + 1) if b[k + 9] & 128 else 0))
        return None if end is None else (end, False)

    return b.chain("gif", at + 13 + (3 << ((b[at + 10] & 7) + 1) if b[at + 10] & 128 else 0), step)


def _jpeg(b: Value, at: int) -> int | None:
    def step(k: int) -> tuple[int, bool] | None:
        if k + 4 > len(b) or b[k] != 0xFF or b[k + 1] in (0xD9, 0x00, 0xFF):
            return None
        size = struct.unpack_from(">H", b, k + 2)[0]
        if size < 2:
            return None
        if b[k + 1] != 0xDA:
            return k + 2 + size, False
        end = b.next_of(b"\xff\xd9", k + 2 + size)
        return (end + 2, True) if end >= 0 else None

    return b.chain("jpeg", at + 2, step)


def _bmp(b: Value, at: int) -> int | None:
    if at + 26 > len(b):
        return None
    size, zero, data, header = struct.unpack_from("<IIII", b, at + 2)
    return at + size if zero == 0 and header in (12, 40, 52, 56, 108, 124) and 14 + header <= data <= size and at + size <= len(b) else None


def _zip(b: Value, at: int) -> int | None:
    if at + 30 > len(b) or struct.unpack_from("<H", b, at + 4)[0] > 63:
        return None
    end = b.next_of(b"PK\x05\x06", at)
    if end < 0 or end + 22 > len(b):
        return None
    size, offset, note = struct.unpack_from("<IIH", b, end + 12)
    return end + 22 + note if at + offset + size == end and end + 22 + note <= len(b) else None


def _pdf(b: Value, at: int) -> int | None:
    if not b[at + 5 : at + 6].isdigit():
        return None
    end, table = b.next_of(b"%%EOF", at), b.next_of(b"startxref", at)
    return end + 5 if end >= 0 and 0 <= table < end else None


def _gzip(b: Value, at: int) -> int | None:
    if at + 18 > len(b) or b[at + 3] & 0xE0:
        return None
    reader, here = zlib.decompressobj(31), memoryview(b)[at:]
    try:
        while len(here) and not reader.eof:  # in pieces: neither the rest of the value nor what it unpacks to is held
            part, here = here[: 1 << 16], here[1 << 16 :]
            while len(part) and not reader.eof:
                reader.decompress(part, 1 << 20)
                part = reader.unconsumed_tail
    except zlib.error:
        return None
    return len(b) - len(here) - len(reader.unused_data) if reader.eof else None


def _crc_table(bits: int, polynomial: int) -> list[int]:
    top, mask, out = 1 << (bits - 1), (1 << bits) - 1, []
    for byte in range(256):
        value = byte << (bits - 8)
        for _ in range(8):
            value = ((value << 1) ^ polynomial if value & top else value << 1) & mask
        out.append(value)
    return out


_CRC8, _CRC16 = _crc_table(8, 0x07), _crc_table(16, 0x8005)  # fixed values: the polynomials of flac frames
_FLAC_BLOCKS = {1: 192, **{k: 576 << (k - 2) for k in range(2, 6)}, **{k: 256 << (k - 8) for k in range(8, 16)}}


def _flac_header(b: bytes, at: int) -> tuple[int, int] | None:
    """(bytes of the frame header, samples of the frame) if a frame begins here: its checksum is right."""
    if b[at : at + 1] != b"\xff" or at + 6 > len(b) or b[at + 1] & 0xFE != 0xF8 or b[at + 3] & 1:
        return None
    block, rate, channels, width = b[at + 2] >> 4, b[at + 2] & 15, b[at + 3] >> 4, b[at + 3] >> 1 & 7
    if not block or rate == 15 or channels > 10 or width in (3, 7):
        return None
    lead = b[at + 4]
    more = 0 if lead < 0x80 else next((k for k in range(1, 7) if lead >> (6 - k) & 1 == 0), 7) if lead >= 0xC0 else 7
    if more > 6:
        return None
    k = at + 5 + more
    samples = _FLAC_BLOCKS.get(block, 0)
    if block in (6, 7):
        n = block - 5
        samples, k = int.from_bytes(b[k : k + n], "big") + 1, k + n
    k += {12: 1, 13: 2, 14: 2}.get(rate, 0)
    check = 0
    for x in b[at:k]:
        check = _CRC8[check ^ x]
    return (k + 1 - at, samples) if k < len(b) and b[k] == check else None


def _flac_frames(b: Value, at: int, left: int) -> int | None:
    """The end of the frames from ``at`` on: every frame's checksum is right, and they hold the samples the head tells (0: unknown)."""
    known, end = left > 0, None
    while True:
        head = _flac_header(b, at)
        if head is None:
            return end if not known and end is not None else None
        left -= head[1]
        check, k, found = 0, at, None
        for k in range(at, len(b)):  # a frame with its own checksum has the checksum 0
            check = (check << 8 & 0xFFFF) ^ _CRC16[(check >> 8) ^ b[k]]
            if not check and k >= at + head[0] + 2 and ((known and left <= 0) or k + 1 == len(b) or _flac_header(b, k + 1) or not known):
                found = k + 1
                break
        if found is None:
            return None
        end = at = found
        if known and left <= 0:
            return end


def _flac(b: Value, at: int) -> int | None:
    inner, samples = at + 4, 0
    if b[inner : inner + 4] not in (b"\0\0\0\x22", b"\x80\0\0\x22") or inner + 38 > len(b):
        return None
    least, most = struct.unpack_from(">HH", b, inner + 4)
    samples = int.from_bytes(b[inner + 17 : inner + 22], "big") & ((1 << 36) - 1)
    if least < 16 or most < least:
        return None
    while inner + 4 <= len(b):
        last, size = b[inner] & 128, int.from_bytes(b[inner + 1 : inner + 4], "big")
        inner += 4 + size
        if last:
            known = b.__dict__.setdefault("flac", {})
            if (inner, samples) not in known:
                known[inner, samples] = _flac_frames(b, inner, samples) if inner < len(b) else None
            return known[inner, samples]
    return None


def _ogg(b: Value, at: int) -> int | None:
    """Pages one after another; their end is that of the last whole page."""
    known, path = b.__dict__.setdefault("ogg", {}), []
    k, end = at, None
    while k not in known and b[k : k + 5] == b"OggS\0" and k + 27 <= len(b):
        n = b[k + 26]
        size = 27 + n + sum(b[k + 27 : k + 27 + n])
        if k + size > len(b):
            return None
        path.append(k)
        k = end = k + size
    end = known.get(k) or end
    for place in path:
        known[place] = end
    return end


#: fixed values: magic bytes, type, validator
SIGNATURES: tuple[tuple[bytes, str, Callable[[Value, int], int | None]], ...] = (
    (b"RIFF", "audio/wav", _riff),
    (b"\x89PNG\r\n\x1a\n", "image/png", _png),
    (b"GIF8", "image/gif", _gif),
    (b"\xff\xd8\xff", "image/jpeg", _jpeg),
    (b"BM", "image/bmp", _bmp),
    (b"PK\x03\x04", "application/zip", _zip),
    (b"%PDF-", "application/pdf", _pdf),
    (b"\x1f\x8b\x08", "application/gzip", _gzip),
    (b"fLaC", "audio/flac", _flac),
    (b"OggS", "audio/ogg", _ogg),
)
_RIFF_TYPES = {b"WAVE": "audio/wav", b"AVI ": "video/avi", b"WEBP": "image/webp"}
_machine: ahocorasick.Automaton | None = None


def _automaton() -> ahocorasick.Automaton:
    global _machine
    if _machine is None:
        _machine = ahocorasick.Automaton()
        for k, (magic, _, _) in enumerate(SIGNATURES):
            _machine.add_word(magic.decode("latin-1"), k)
        _machine.make_automaton()
    return _machine


def sniff(value: bytes) -> list[tuple[int, int, str]]:
    """(start, end, type) of every valid medium in value, outer before inner.

    Search goes on inside a found medium, so embedded ones are found as well. A
    validator that failed at one place is asked again at the next.
    """
    found, value = [], Value(value)
    for last, k in _automaton().iter(value.decode("latin-1")):
        magic, kind, valid = SIGNATURES[k]
        start = last - len(magic) + 1
        end = valid(value, start)
        if end is not None:
            found.append((start, end, _RIFF_TYPES[value[start + 8 : start + 12]] if valid is _riff else kind))
    return sorted(found, key=lambda f: (f[0], -f[1]))


def true_type(value: bytes, found: list[tuple[int, int, str]]) -> str:
    return found[0][2] if found and found[0][0] == 0 else "application/octet-stream"


def carve(value: bytes, found: list[tuple[int, int, str]] | None = None) -> list[tuple[int, str, bytes]]:
    """(start, type, bytes) of the embedded media of value (not value itself), in order of their places."""
    return [(a, kind, value[a:b]) for a, b, kind in (sniff(value) if found is None else found) if a or b < len(value)]


def store_media(docs: DataFrame, declared: str = "audio/wav") -> DataFrame:
    """doc_id, n_bytes, declared_type, media (wave file of the padded UTF-8 text) of every document."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            raw = [(t or "").encode() for t in batch.column("text").to_pylist()]
            media = [wave_of(r + b"\0" * (max(UNIT, -(-len(r) // UNIT) * UNIT) - len(r))) for r in raw]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([len(r) for r in raw], pa.int64()), pa.array([declared] * len(raw)), pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "declared_type", "media"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, declared_type string, media binary")


def feature_of(samples: bytes, kind: str, embedded: list[tuple[int, str, bytes]]) -> str:
    """Type, entropy of the samples in bits, mean, share of zeros, and the carved media: type, place, length, checksum."""
    counts = np.bincount(np.frombuffer(samples, dtype=np.uint8), minlength=256)
    share = counts[counts > 0] / max(1, len(samples))
    entropy = float(-(share * np.log2(share)).sum())
    mean = float((counts * np.arange(256)).sum() / max(1, len(samples)))
    inside = ",".join(f"{t}@{a}+{len(part)}#{zlib.crc32(part):08x}" for a, t, part in embedded)
    return f"type={kind};entropy={entropy:.6f};mean={mean:.6f};zeros={counts[0] / max(1, len(samples)):.6f};embedded={inside}"


def sniff_media(media: DataFrame) -> DataFrame:
    """Read stored media back: checks, digests, true types and features of each row."""
    names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "true_type", "declared_ok", "n_embedded"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "media"):
            out = []
            for doc, n, declared, value in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                found = sniff(value)
                kind = true_type(value, found)
                samples = wave_samples(value)
                inner = carve(value, found)
                out.append((doc, n, len(samples), hashlib.sha256(samples).hexdigest(), zlib.crc32(samples[-UNIT:]), len(value), hashlib.sha256(value).hexdigest(), feature_of(samples, kind, inner), kind, kind == declared, len(inner)))
            kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.bool_(), pa.int32()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)

    return media.select("doc_id", "n_bytes", "declared_type", "media").mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, true_type string, declared_ok boolean, n_embedded int")


def media_digests(docs: DataFrame) -> DataFrame:
    """Store every text as a media column in the shared folder, then read the stored bytes back."""
    return sniff_media(stored(store_media(docs), "media"))
