"""Media columns: payload storage and signature sniffing.

The magic bytes of all formats stand in one Aho-Corasick automaton, so a payload is read once whatever
the number of formats. A hit is only a candidate: the format's validator must confirm the structure and
give the length before a declared type is corrected or an embedded object is carved out.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from canopy.llm.common import ship

#: Magic bytes by format.
MAGIC = {
    "png": (b"\x89PNG\r\n\x1a\n",),
    "jpeg": (b"\xff\xd8\xff",),
    "gif": (b"GIF87a", b"GIF89a"),
    "riff": (b"RIFF",),
    "pdf": (b"%PDF-",),
    "zip": (b"PK\x03\x04",),
    "gzip": (b"\x1f\x8b\x08",),
    "bmp": (b"BM",),
    "flac": (b"fLaC",),
    "ogg": (b"OggS",),
}
UNIT = 64
RATE = 8000
WAV_HEAD = 44


def automaton() -> ahocorasick.Automaton:
    out = ahocorasick.Automaton()
    for kind, magics in MAGIC.items():
        for m in magics:
            out.add_word(m.decode("latin-1"), (kind, len(m)))
    out.make_automaton()
    return out


def png_length(b: bytes, at: int) -> int:
    p, seen = at + 8, False
    while p + 12 <= len(b):
        n, kind = struct.unpack_from(">I4s", b, p)
        if p + 12 + n > len(b) or not kind.isalpha() or (not seen and (kind != b"IHDR" or n != 13)):
            return 0
        if zlib.crc32(b[p + 4 : p + 8 + n]) != struct.unpack_from(">I", b, p + 8 + n)[0]:
            return 0
        seen, p = True, p + 12 + n
        if kind == b"IEND":
            return p - at
    return 0


def jpeg_length(b: bytes, at: int) -> int:
    p = at + 2
    while p + 4 <= len(b) and b[p] == 0xFF:
        mark = b[p + 1]
        if mark == 0xD9:
            return p + 2 - at
        size = struct.unpack_from(">H", b, p + 2)[0]
        if size < 2 or p + 2 + size > len(b):
            return 0
        p += 2 + size
        if mark == 0xDA:
            while (p := b.find(b"\xff", p)) >= 0 and p + 1 < len(b) and (b[p + 1] == 0 or 0xD0 <= b[p + 1] <= 0xD7):
                p += 2
            if p < 0:
                return 0
    return 0


def gif_length(b: bytes, at: int) -> int:
    if at + 13 > len(b):
        return 0
    flags = b[at + 10]
    p = at + 13 + (3 << ((flags & 7) + 1) if flags & 0x80 else 0)

    def blocks(p: int) -> int:
        while p < len(b):
            if not b[p]:
                return p + 1
            p += b[p] + 1
        return len(b) + 1

    images = 0
    while p < len(b):
        if b[p] == 0x3B:
            return p + 1 - at if images else 0
        if b[p] == 0x21:
            p = blocks(p + 2)
        elif b[p] == 0x2C and p + 10 <= len(b):
            local = b[p + 9]
            p = blocks(p + 11 + (3 << ((local & 7) + 1) if local & 0x80 else 0))
            images += 1
        else:
            return 0
    return 0


def riff_length(b: bytes, at: int) -> int:
    if at + 12 > len(b):
        return 0
    size = struct.unpack_from("<I", b, at + 4)[0]
    end = at + 8 + size
    if size < 4 or end > len(b) or b[at + 8 : at + 12] not in (b"WAVE", b"WEBP", b"AVI "):
        return 0
    p, chunks = at + 12, 0
    while p + 8 <= end:
        n = struct.unpack_from("<I", b, p + 4)[0]
        p += 8 + n + (n & 1)
        chunks += 1
    return 8 + size if chunks and p in (end, end + 1) else 0


def pdf_length(b: bytes, at: int) -> int:
    """To the last end mark before the next header whose startxref points into the file, so updates belong to it."""
    if at + 8 > len(b) or not b[at + 5 : at + 6].isdigit() or b[at + 6 : at + 7] != b".":
        return 0
    stop = b.find(b"%PDF-", at + 5)
    stop = len(b) if stop < 0 else stop
    end = b.rfind(b"%%EOF", at, stop)
    while end > 0:
        words = b[max(at, end - 64) : end].split()
        if len(words) > 1 and words[-2] == b"startxref" and words[-1].isdigit() and int(words[-1]) < end - at:
            return end + 5 - at
        end = b.rfind(b"%%EOF", at, end)
    return 0


def zip_length(b: bytes, at: int) -> int:
    """To the first end record whose directory closes the archive; a stored archive's own end record doesn't."""
    end = at + 30
    while (end := b.find(b"PK\x05\x06", end)) >= 0 and end + 22 <= len(b):
        size, start, note = struct.unpack_from("<IIH", b, end + 12)
        if at + start + size == end and end + 22 + note <= len(b):
            return end + 22 + note - at
        end += 4
    return 0


def gzip_length(b: bytes, at: int) -> int:
    """Inflated a bounded piece at a time, so a small payload cannot fill a worker."""
    d = zlib.decompressobj(31)
    try:
        for p in range(at, len(b), 1 << 16):
            rest = b[p : p + (1 << 16)]
            while rest and not d.eof:
                d.decompress(rest, 1 << 20)
                rest = d.unconsumed_tail
            if d.eof:
                return min(len(b), p + (1 << 16)) - len(d.unused_data) - at
    except zlib.error:
        return 0
    return 0


def bmp_length(b: bytes, at: int) -> int:
    if at + 54 > len(b):
        return 0
    size, zero, start, head = struct.unpack_from("<IIII", b, at + 2)
    return size if zero == 0 and head in (40, 108, 124) and 14 + head <= start <= size <= len(b) - at else 0


def flac_length(b: bytes, at: int) -> int:
    """Metadata blocks only: frames carry no total length, so a stream runs to the payload's end."""
    p, first = at + 4, True
    while p + 4 <= len(b):
        head, n = b[p], int.from_bytes(b[p + 1 : p + 4], "big")
        if first and (head & 0x7F or n != 34) or p + 4 + n > len(b):
            return 0
        first, p = False, p + 4 + n
        if head & 0x80:
            return len(b) - at
    return 0


def ogg_length(b: bytes, at: int) -> int:
    p = at
    while b[p : p + 4] == b"OggS" and p + 27 <= len(b) and b[p + 4] == 0:
        segments = b[p + 26]
        n = 27 + segments + sum(b[p + 27 : p + 27 + segments])
        if p + n > len(b):
            return 0
        last, p = b[p + 5] & 4, p + n
        if last:
            return p - at
    return 0


VALID = {"png": png_length, "jpeg": jpeg_length, "gif": gif_length, "riff": riff_length, "pdf": pdf_length, "zip": zip_length, "gzip": gzip_length, "bmp": bmp_length, "flac": flac_length, "ogg": ogg_length}


def sniff(payload: bytes, finder: ahocorasick.Automaton) -> list[tuple[int, int, str]]:
    """(start, length, format) of every confirmed object, leftmost first; objects inside others are listed too."""
    found = []
    for last, (kind, n) in finder.iter(payload.decode("latin-1")):
        at = last - n + 1
        if length := VALID[kind](payload, at):
            found.append((at, length, {b"WAVE": "wav", b"WEBP": "webp", b"AVI ": "avi"}[payload[at + 8 : at + 12]] if kind == "riff" else kind))
    return sorted(found)


def corrected_type(declared: str | None, payload: bytes, finder: ahocorasick.Automaton) -> str | None:
    """The confirmed type at byte 0 where there is one, else what was declared."""
    return next((kind for at, _, kind in sniff(payload, finder) if at == 0), declared)


def to_wav(payload: bytes) -> bytes:
    """One 8-bit sample for each byte."""
    return struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(payload), b"WAVE", b"fmt ", 16, 1, 1, RATE, RATE, 1, 8, b"data", len(payload)) + payload


def from_wav(media: bytes) -> bytes:
    """The samples, found by walking the chunks."""
    p = 12
    while p + 8 <= len(media):
        kind, n = struct.unpack_from("<4sI", media, p)
        if kind == b"data":
            return media[p + 8 : p + 8 + n]
        p += 8 + n + (n & 1)
    raise ValueError("no data chunk")


def signal(samples: bytes) -> str:
    """Peak, root mean square and sign changes of 8-bit samples around their middle."""
    x = np.frombuffer(samples, np.uint8).astype(np.int64) - 128
    return f"peak={int(np.abs(x).max())},rms={float(np.sqrt((x * x).mean())):.3f},crossings={int((np.diff(x >= 0)).sum())}"


#: What a text column's payload is declared to be before it is sniffed.
DECLARED = "text"
COLUMNS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_embedded long, declared_type string, corrected_type string, carved_sha256 string"


def to_batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    names = [c.split()[0] for c in schema.split(", ")]
    kinds = [{"string": pa.string(), "long": pa.int64(), "binary": pa.binary()}[c.split()[1]] for c in schema.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(zip(*rows) if rows else [[]] * len(names), kinds)], names)


def store_and_sniff(docs: DataFrame) -> DataFrame:
    """Each text as a WAV of 8-bit samples, read back and sniffed.

    Null and empty texts are 64 zero bytes; equal texts give equal values, repeated rows too; other columns are ignored; an
    empty table gives no rows. feature tells the stored form's confirmed type, measures of the samples and each
    carved object as format@start+length (starts count from the payload's first byte). The payload is declared as
    text; a confirmed object at its first byte corrects that. carved_sha256 hashes the carved objects' bytes, in order.
    """
    ship(docs.sparkSession)

    def run(batches):
        finder = automaton()
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column("doc_id").to_pylist(), pc.fill_null(batch.column("text"), "").cast(pa.large_binary())):
                raw = text.as_py()
                payload = raw + bytes(-len(raw) % UNIT or (UNIT if not raw else 0))
                media = to_wav(payload)
                found = sniff(media, finder)
                back = from_wav(media)
                inner = [(at - WAV_HEAD, n, k) for at, n, k in found if at >= WAV_HEAD]
                kind = next((k for at, n, k in found if at == 0 and n == len(media)), "unknown")
                feature = f"{kind}:{RATE}x1x8:{signal(back)}:" + ",".join(f"{k}@{at}+{n}" for at, n, k in inner)
                carved = hashlib.sha256(b"".join(back[at : at + n] for at, n, _ in inner)).hexdigest()
                corrected = next((k for at, _, k in inner if at == 0), DECLARED)
                rows.append((doc, len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(media), hashlib.sha256(media).hexdigest(), feature, len(inner), DECLARED, corrected, carved))
            yield to_batch(rows, COLUMNS)

    return docs.select("doc_id", "text").mapInArrow(run, COLUMNS)


OBJECTS = "id long, declared string, corrected string, start long, length long, kind string, object binary"


def carve(media: DataFrame, key: str, payload: str, declared: str) -> DataFrame:
    """A row for each confirmed object inside a binary column, with its bytes and the payload's corrected type.

    corrected is the format confirmed at byte 0, else what was declared; a payload without objects gives one row whose
    start is null. Null payloads count as empty; repeated rows give repeated objects; an empty table gives no rows.
    """
    ship(media.sparkSession)

    def run(batches):
        finder = automaton()
        for batch in batches:
            for i in range(batch.num_rows):
                who, raw, said = (batch.column(c)[i].as_py() for c in ("id", "payload", "declared"))
                raw = raw or b""
                corrected = corrected_type(said, raw, finder)
                found = sniff(raw, finder) or [(None, None, None)]
                for f in range(0, len(found), 64):
                    yield to_batch([(who, said, corrected, at, n, kind, None if at is None else raw[at : at + n]) for at, n, kind in found[f : f + 64]], OBJECTS)

    return media.selectExpr(f"cast(`{key}` as long) as id", f"cast(`{payload}` as binary) as payload", f"cast(`{declared}` as string) as declared").mapInArrow(run, OBJECTS)
