"""Media columns: signature sniffing, validation, type correction and carving.

An Aho-Corasick automaton over the bytes finds the magic numbers of the known formats wherever they stand. At each
hit the format's validator walks the structure (chunk sizes, checksums, block lengths, end markers) and gives the length of
the object or rejects the hit. An object at offset 0 decides the type of the value, whatever was declared; the
others that do not lie inside an accepted one before them are carved as embedded media with offset and length.

Payloads of text are stored losslessly as 8-bit mono PCM in a RIFF/WAVE container and read back through the same
validator. Defined cases: null text is an empty payload; null or empty media has type null and nothing carved.
"""

from __future__ import annotations

import bisect
import hashlib
import re
import struct
import zlib
from collections.abc import Callable

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wavemotif.llm.common import documents, map_batches, utf8

BLOCK = 192
RATE = 8000
#: Bytes that a step of inflating gives at most.
INFLATED = 1 << 20


class Value(bytes):
    """A value whose end markers are looked for once, however many hits ask for the next one."""

    def next(self, marker: bytes, at: int) -> int:
        """The first place of marker at or after at, or -1."""
        known = self.__dict__.setdefault("places", {})
        if marker not in known:
            known[marker] = [m.start() for m in re.finditer(re.escape(marker), self, re.S)]
        i = bisect.bisect_left(known[marker], at)
        return known[marker][i] if i < len(known[marker]) else -1



def _wav(b: Value, at: int) -> int | None:
    if b[at + 8 : at + 12] != b"WAVE" or len(b) < at + 12:
        return None
    end, p, seen = at + 8 + int.from_bytes(b[at + 4 : at + 8], "little"), at + 12, set()
    if end > len(b):
        return None
    while p + 8 <= end:
        seen.add(b[p : p + 4])
        n = int.from_bytes(b[p + 4 : p + 8], "little")
        p += 8 + n + n % 2
    return end - at if p in (end, end + 1) and {b"fmt ", b"data"} <= seen else None


def _png(b: Value, at: int) -> int | None:
    p, first = at + 8, True
    while p + 12 <= len(b):
        n = int.from_bytes(b[p : p + 4], "big")
        kind, end = b[p + 4 : p + 8], p + 12 + n
        if end > len(b) or (first and (kind != b"IHDR" or n != 13)) or zlib.crc32(b[p + 4 : p + 8 + n]) != int.from_bytes(b[end - 4 : end], "big"):
            return None
        if kind == b"IEND":
            return end - at
        p, first = end, False
    return None


def _gif(b: Value, at: int) -> int | None:
    def blocks(p: int) -> int:
        while p < len(b) and b[p]:
            p += 1 + b[p]
        return p + 1

    if len(b) < at + 13:
        return None
    p = at + 13 + (3 << ((b[at + 10] & 7) + 1)) * (b[at + 10] >> 7)
    while p < len(b):
        if b[p] == 0x3B:
            return p + 1 - at
        if b[p] == 0x21:
            p = blocks(p + 2)
        elif b[p] == 0x2C and p + 10 < len(b):
            p = blocks(p + 11 + (3 << ((b[p + 9] & 7) + 1)) * (b[p + 9] >> 7))
        else:
            return None
    return None


def _jpeg(b: Value, at: int) -> int | None:
    p = at + 2
    while p + 4 <= len(b) and b[p] == 0xFF and 0xC0 <= b[p + 1] <= 0xFE and not 0xD0 <= b[p + 1] <= 0xD9:
        kind, n = b[p + 1], int.from_bytes(b[p + 2 : p + 4], "big")
        if n < 2:
            return None
        p += 2 + n
        if kind == 0xDA:
            end = b.next(b"\xff\xd9", p)
            return end + 2 - at if end >= 0 else None
    return None


def _bmp(b: Value, at: int) -> int | None:
    if len(b) < at + 30:
        return None
    size, start, header = int.from_bytes(b[at + 2 : at + 6], "little"), int.from_bytes(b[at + 10 : at + 14], "little"), int.from_bytes(b[at + 14 : at + 18], "little")
    return size if header in (12, 40, 108, 124) and 14 + header <= start <= size <= len(b) - at and b[at + 6 : at + 10] == b"\0" * 4 else None


def _gzip(b: Value, at: int) -> int | None:
    if len(b) < at + 18 or (flags := b[at + 3]) & 0xE0:  # reserved flags
        return None
    p = at + 10
    if flags & 4:
        p += 2 + int.from_bytes(b[p : p + 2], "little")
    for bit in (8, 16):  # name, comment
        if flags & bit:
            if (end := b.next(b"\0", p)) < 0:
                return None
            p = end + 1
    p += flags & 2
    d, rest, step, crc, size = zlib.decompressobj(-15), b"", 256, 0, 0
    try:
        while not d.eof and (rest or p < len(b)):
            if not rest:
                rest, p, step = b[p : p + step], p + step, min(2 * step, 65536)  # most hits are none, and fail early
            out = d.decompress(rest, INFLATED)
            rest, crc, size = d.unconsumed_tail, zlib.crc32(out, crc), size + len(out)
    except zlib.error:
        return None
    end = min(p, len(b)) - len(d.unused_data)
    return end + 8 - at if d.eof and b[end : end + 8] == struct.pack("<II", crc, size & 0xFFFFFFFF) else None


def _pdf(b: Value, at: int) -> int | None:
    end = b.next(b"%%EOF", at)
    return end + 5 - at if end >= 0 and 0 <= b.next(b"startxref", at) <= end - 9 else None


def _zip(b: Value, at: int) -> int | None:
    end = b.next(b"PK\5\6", at)
    if end < 0 or end + 22 > len(b):
        return None
    size, start, note = struct.unpack("<IIH", b[end + 12 : end + 22])
    return end + 22 + note - at if at + start + size == end and end + 22 + note <= len(b) else None


# fixed values: magic numbers
FORMATS: tuple[tuple[str, bytes, Callable[[Value, int], int | None]], ...] = (
    ("audio/wav", b"RIFF", _wav),
    ("image/png", b"\x89PNG\r\n\x1a\n", _png),
    ("image/gif", b"GIF87a", _gif),
    ("image/gif", b"GIF89a", _gif),
    ("image/jpeg", b"\xff\xd8\xff", _jpeg),
    ("image/bmp", b"BM", _bmp),
    ("application/gzip", b"\x1f\x8b\x08", _gzip),
    ("application/pdf", b"%PDF-", _pdf),
    ("application/zip", b"PK\3\4", _zip),
)


def magic() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for i, (_, sign, _) in enumerate(FORMATS):
        a.add_word(sign.decode("latin-1"), i)
    a.make_automaton()
    return a


def sniff(value: bytes, signs: ahocorasick.Automaton) -> tuple[str | None, list[tuple[str, int, int]]]:
    """The type by structure, and embedded media as (type, offset, length). The value itself is not listed."""
    value = Value(value)
    kind, found, inside = None, [], 0
    for end, i in signs.iter(value.decode("latin-1")):
        name, sign, valid = FORMATS[i]
        at = end + 1 - len(sign)
        if at and at < inside or not (n := valid(value, at)):
            continue
        if not at:
            kind = kind or name
        else:
            found.append((name, at, n))
            inside = at + n
    return kind, found


def to_wav(payload: bytes) -> bytes:
    n = len(payload)
    return b"RIFF" + struct.pack("<I", 36 + n + n % 2) + b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, RATE, RATE, 1, 8) + b"data" + struct.pack("<I", n) + payload + b"\0" * (n % 2)


def wav_samples(stored: bytes) -> bytes:
    """The data chunk of a valid file."""
    p = 12
    while stored[p : p + 4] != b"data":
        n = int.from_bytes(stored[p + 4 : p + 8], "little")
        p += 8 + n + n % 2
    return stored[p + 8 : p + 8 + int.from_bytes(stored[p + 4 : p + 8], "little")]


def sniff_column(df: DataFrame, media: str = "media", declared: str = "declared", key: str = "doc_id") -> DataFrame:
    """doc_id, declared, actual, corrected, embedded(type, offset, length, bytes) a row of a table with a binary column."""
    signs = None

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        nonlocal signs
        signs = signs or magic()
        said, out, parts = batch.column("declared").to_pylist(), [], []
        values = [x or b"" for x in batch.column("media").to_pylist()]
        for v in values:
            kind, found = sniff(v, signs)
            out.append(kind)
            parts.append([{"type": t, "offset": a, "length": n, "bytes": v[a : a + n]} for t, a, n in found])
        part = pa.struct([("type", pa.string()), ("offset", pa.int64()), ("length", pa.int64()), ("bytes", pa.binary())])
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("declared"), pa.array(out, pa.string()), pa.array([o is not None and o != s for o, s in zip(out, said, strict=True)], pa.bool_()), pa.array(parts, pa.list_(part))], ["doc_id", "declared", "actual", "corrected", "embedded"])

    rows = df.select(F.col(key).cast("long").alias("doc_id"), F.col(media).cast("binary").alias("media"), F.col(declared).cast("string").alias("declared"))
    return map_batches(rows, fn, "doc_id long, declared string, actual string, corrected boolean, embedded array<struct<type: string, offset: long, length: long, bytes: binary>>")


def text_media(docs: DataFrame) -> DataFrame:
    """Each whole text padded with spaces to a positive multiple of BLOCK bytes, stored as audio, sniffed and read back; its features."""
    signs = None

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        nonlocal signs
        signs = signs or magic()
        rows = []
        for raw in utf8(batch):
            stored = to_wav(raw + b" " * (-len(raw) % BLOCK or BLOCK * (not raw)))
            kind, found = sniff(stored, signs)
            if kind != "audio/wav":
                raise ValueError(f"stored media was read as {kind}")
            payload = wav_samples(stored)
            x = np.frombuffer(payload, np.uint8)
            wave = x.astype(np.int16) - 128
            zero = int(np.count_nonzero(np.diff(wave < 0)))
            feature = f"type={kind};rate={RATE};samples={len(x)};sum={int(x.sum(dtype=np.int64))};energy={int((wave.astype(np.int64) ** 2).sum())};peak={int(x.max())};crossings={zero};embedded={len(found)}"
            rows.append((len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(stored), hashlib.sha256(stored).hexdigest(), feature))
        cols = list(zip(*rows, strict=True)) or [()] * 7
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(c, k) for c, k in zip(cols, kinds, strict=True)]], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    return map_batches(documents(docs), fn, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
