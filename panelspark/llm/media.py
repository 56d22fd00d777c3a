"""Media columns: what a binary value really is, by its signature and structure, not by its declared type.

One Aho-Corasick automaton finds the magic bytes of all known formats in one pass, wherever they lie. A validator
for each format then confirms structure and lengths; only what it confirms counts. The format that starts at byte 0
corrects the declared type, others are embedded media and can be carved out.

Null values are empty, and of type `unknown`. Equal bytes give equal results. Values without any confirmed format
keep no declared type: the corrected type is `unknown` and `declared_ok` is false.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import byte_view, shipped

# Magic bytes and how far before them the file starts.
MAGIC = [
    (b"RIFF", "riff", 0),
    (b"\x89PNG\r\n\x1a\n", "png", 0),
    (b"\xff\xd8\xff", "jpeg", 0),
    (b"GIF87a", "gif", 0),
    (b"GIF89a", "gif", 0),
    (b"BM", "bmp", 0),
    (b"%PDF-", "pdf", 0),
    (b"PK\x03\x04", "zip", 0),
    (b"\x1f\x8b\x08", "gzip", 0),
    (b"fLaC", "flac", 0),
    (b"OggS", "ogg", 0),
    (b"ID3", "mp3", 0),
    (b"ftyp", "mp4", 4),
]
UNIT = 576
RATE = 8000
_AUTOMATON = None


def automaton():
    """Over latin-1 text, so that each byte is one symbol."""
    global _AUTOMATON
    if _AUTOMATON is None:
        import ahocorasick

        a = ahocorasick.Automaton()
        for magic, kind, before in MAGIC:
            a.add_word(magic.decode("latin-1"), (kind, len(magic), before))
        a.make_automaton()
        _AUTOMATON = a
    return _AUTOMATON


def _riff(b: bytes, at: int):
    if len(b) < at + 12:
        return None
    size, form = struct.unpack_from("<I4s", b, at + 4)
    end = at + 8 + size
    if end > len(b) or size < 4 or form not in (b"WAVE", b"AVI ", b"WEBP"):
        return None
    place, chunks = at + 12, {}
    while place + 8 <= end:
        name, n = struct.unpack_from("<4sI", b, place)
        if place + 8 + n > end:
            return None
        chunks.setdefault(name, (place + 8, n))
        place += 8 + n + (n & 1)
    kind = {b"WAVE": "wav", b"AVI ": "avi", b"WEBP": "webp"}[form]
    if kind == "wav" and not (b"fmt " in chunks and b"data" in chunks and chunks[b"fmt "][1] >= 16):
        return None
    return kind, end, chunks


def _png(b: bytes, at: int):
    place, first = at + 8, True
    while place + 12 <= len(b):
        n, name = struct.unpack_from(">I4s", b, place)
        if place + 12 + n > len(b) or (first and (name != b"IHDR" or n != 13)):
            return None
        if zlib.crc32(b[place + 4 : place + 8 + n]) != struct.unpack_from(">I", b, place + 8 + n)[0]:
            return None
        place, first = place + 12 + n, False
        if name == b"IEND":
            return "png", place, {}
    return None


def _jpeg(b: bytes, at: int):
    place = at + 2
    while place + 2 <= len(b) and b[place] == 0xFF:
        kind = b[place + 1]
        if kind == 0xD9:
            return "jpeg", place + 2, {}
        if place + 4 > len(b):
            return None
        n = struct.unpack_from(">H", b, place + 2)[0]
        if n < 2 or place + 2 + n > len(b):
            return None
        place += 2 + n
        if kind == 0xDA:  # entropy-coded data up to the next marker that is not stuffing or a restart
            while True:
                place = b.find(b"\xff", place)
                if place < 0 or place + 1 >= len(b):
                    return None
                if b[place + 1] == 0 or 0xD0 <= b[place + 1] <= 0xD7:
                    place += 2
                    continue
                break
    return None


def _gif(b: bytes, at: int):
    if len(b) < at + 14:
        return None
    flags = b[at + 10]
    place = at + 13 + (3 << ((flags & 7) + 1) if flags & 0x80 else 0)

    def blocks(p):
        while p < len(b) and b[p]:
            p += 1 + b[p]
        return p + 1

    while place < len(b):
        if b[place] == 0x3B:
            return "gif", place + 1, {}
        if b[place] == 0x21:
            place = blocks(place + 2)
        elif b[place] == 0x2C and place + 10 < len(b):
            local = b[place + 9]
            place = blocks(place + 10 + (3 << ((local & 7) + 1) if local & 0x80 else 0) + 1)
        else:
            return None
    return None


def _bmp(b: bytes, at: int):
    if len(b) < at + 54:
        return None
    size, zero, start, header = struct.unpack_from("<IIII", b, at + 2)
    ok = zero == 0 and header in (12, 40, 52, 56, 108, 124) and 14 + header <= start <= size and at + size <= len(b)
    return ("bmp", at + size, {}) if ok else None


@lru_cache(maxsize=8)
def _last(b: bytes, mark: bytes, end: int | None = None) -> int:
    """Where a mark stands last; remembered, so that many starts in one value cost one search."""
    return b.rfind(mark, 0, len(b) if end is None else end)


def _pdf(b: bytes, at: int):
    end = _last(b, b"%%EOF")
    return ("pdf", end + 5, {}) if end > at and _last(b, b"startxref", end) > at else None


def _zip(b: bytes, at: int):
    end = _last(b, b"PK\x05\x06")
    if end < at or end + 22 > len(b):
        return None
    size, start, note = struct.unpack_from("<IIH", b, end + 12)
    return ("zip", end + 22 + note, {}) if at + start + size == end and end + 22 + note <= len(b) else None


def _gzip(b: bytes, at: int):
    try:
        d = zlib.decompressobj(31)
        place = at
        while place < len(b) and not d.eof:  # decoded in small steps and dropped, so that memory stays bounded
            d.decompress(b[place : place + 65536], 1 << 20)
            while d.unconsumed_tail and not d.eof:
                d.decompress(d.unconsumed_tail, 1 << 20)
            place += 65536
        return ("gzip", min(place, len(b)) - len(d.unused_data), {}) if d.eof else None
    except zlib.error:
        return None


def _flac(b: bytes, at: int):
    return ("flac", len(b), {}) if len(b) >= at + 42 and b[at + 4] & 0x7F == 0 and b[at + 5 : at + 8] == b"\x00\x00\x22" else None


def _ogg(b: bytes, at: int):
    place = at
    while b[place : place + 4] == b"OggS" and place + 27 <= len(b) and b[place + 4] == 0:
        table = b[place + 27 : place + 27 + b[place + 26]]
        if len(table) < b[place + 26] or place + 27 + len(table) + sum(table) > len(b):
            break
        place += 27 + len(table) + sum(table)
    return ("ogg", place, {}) if place > at else None


def _mp3(b: bytes, at: int):
    if len(b) < at + 10 or b[at + 3] > 4 or any(x & 0x80 for x in b[at + 6 : at + 10]):
        return None
    size = (b[at + 6] << 21) | (b[at + 7] << 14) | (b[at + 8] << 7) | b[at + 9]
    frame = at + 10 + size
    return ("mp3", len(b), {}) if frame + 2 <= len(b) and b[frame] == 0xFF and b[frame + 1] & 0xE0 == 0xE0 else None


def _mp4(b: bytes, at: int):
    place, names = at, []
    while place + 8 <= len(b):
        n, name = struct.unpack_from(">I4s", b, place)
        if n < 8 or place + n > len(b) or not name.isalnum():
            break
        names.append(name)
        place += n
    return ("mp4", place, {}) if len(names) >= 2 and names[0] == b"ftyp" else None


CHECKS = {"riff": _riff, "png": _png, "jpeg": _jpeg, "gif": _gif, "bmp": _bmp, "pdf": _pdf, "zip": _zip, "gzip": _gzip, "flac": _flac, "ogg": _ogg, "mp3": _mp3, "mp4": _mp4}


def sniff(b: bytes) -> list[tuple[str, int, int, dict]]:
    """Confirmed media as (type, start, end, parts) in order of start; what lies inside another is listed too."""
    found, packed = [], 0
    for last, (kind, n, before) in automaton().iter(b.decode("latin-1")):
        at = last - n + 1 - before
        if kind == "gzip" and at < packed:  # bytes of a stream that has been decoded
            continue
        if at >= 0 and (got := CHECKS[kind](b, at)):
            found.append((got[0], at, got[1], got[2]))
            packed = max(packed, got[1]) if kind == "gzip" else packed
    return found


def stored(payload: bytes) -> bytes:
    """The payload as the samples of a mono 8-bit PCM wave file; lossless."""
    head = struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(payload) + (len(payload) & 1), b"WAVE", b"fmt ", 16, 1, 1, RATE, RATE, 1, 8, b"data", len(payload))
    return head + payload + b"\0" * (len(payload) & 1)


def read_back(media: bytes) -> tuple[bytes, list]:
    """The samples of the stored bytes, located by signature and validator, and all that was found."""
    found = sniff(media)
    start, n = next(parts[b"data"] for kind, at, _, parts in found if kind == "wav" and at == 0)
    return media[start : start + n], found


def features(payload: bytes, found: list) -> str:
    """Level, mean and zero crossings of the samples, and the embedded media, as text."""
    x = np.frombuffer(payload, np.uint8)
    total, squares = int(x.sum(dtype=np.int64)), int((x.astype(np.int64) ** 2).sum())
    up = x >= 128
    crossings = int(np.count_nonzero(up[1:] != up[:-1]))
    inner = ";".join(f"{k}@{a}+{e - a}" for k, a, e, _ in found if a > 0)
    return f"wav/u8/{RATE}/{len(x)}/sum={total}/sq={squares}/zc={crossings}/in={inner}"


def digests(batches):
    for batch in batches:
        data, off = byte_view(batch.column(1))
        out: list[tuple] = []
        for i in range(batch.num_rows):
            raw = data[off[i] : off[i + 1]].tobytes()
            missing = -len(raw) % UNIT or (UNIT if not raw else 0)
            media = stored(raw + b"\xff" * missing)
            payload, found = read_back(media)
            out.append((len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(media), hashlib.sha256(media).hexdigest(), features(payload, found)))
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        columns = list(zip(*out, strict=True)) if out else [[]] * 7
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])


def text_media(docs: DataFrame) -> DataFrame:
    """Stores each text of docs(doc_id, text) as media, reads it back through the sniffer and describes it. Narrow."""
    return docs.select("doc_id", "text").mapInArrow(shipped("panelspark.llm.media", "digests"), "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def sniffed(batches):
    part = pa.struct([("type", pa.string()), ("start", pa.int64()), ("end", pa.int64())])
    for batch in batches:
        kinds, right, inner = [], [], []
        for declared, b in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
            found = sniff(b or b"")
            kind = next((k for k, a, _, _ in found if a == 0), "unknown")
            kinds.append(kind)
            right.append(declared is not None and declared.rpartition("/")[2].lower().replace("jpg", "jpeg") == kind)
            inner.append([{"type": k, "start": a, "end": e} for k, a, e, _ in found if a > 0])
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(kinds, pa.string()), pa.array(right, pa.bool_()), pa.array(inner, pa.list_(part))], ["id", "media_type", "declared_ok", "embedded"])


def corrected(rows: DataFrame, key: str, declared: str, content: str) -> DataFrame:
    """The true type, whether the declared one was right, and the embedded media (type, start, end) of binary rows."""
    from pyspark.sql import functions as F

    picked = rows.select(F.col(key).cast("long").alias("id"), F.col(declared).cast("string").alias("declared"), F.col(content).cast("binary").alias("content"))
    return picked.mapInArrow(shipped("panelspark.llm.media", "sniffed"), "id long, media_type string, declared_ok boolean, embedded array<struct<type: string, start: long, end: long>>")


def carved_out(batches):
    for batch in batches:
        out = []
        for r, b in enumerate(batch.column(1).to_pylist()):
            out += [(r, n, k, a, e, b[a:e]) for n, (k, a, e, _) in enumerate(x for x in sniff(b or b"") if x[1] > 0)]
        rows, number, kinds, starts, ends, content = zip(*out, strict=True) if out else [()] * 6
        yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(rows, pa.int64())), pa.array(number, pa.int32()), pa.array(kinds, pa.string()), pa.array(starts, pa.int64()), pa.array(ends, pa.int64()), pa.array(content, pa.binary())], ["id", "number", "media_type", "start", "end", "content"])


def carved(rows: DataFrame, key: str, content: str) -> DataFrame:
    """The media embedded in binary rows: (id, number, media_type, start, end, content), one row each, in order of start; what
    starts at byte 0 is the value itself and is left out. Null and unknown values give no rows."""
    from pyspark.sql import functions as F

    picked = rows.select(F.col(key).cast("long").alias("id"), F.col(content).cast("binary").alias("content"))
    return picked.mapInArrow(shipped("panelspark.llm.media", "carved_out"), "id long, number int, media_type string, start long, end long, content binary")
