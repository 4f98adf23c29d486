"""Media columns: what a binary value really is, and what media it holds inside.

An Aho-Corasick automaton finds every magic number in one pass over the bytes;
a validator per format confirms structure and length, so a chance occurrence of
a magic number is not taken for media. ``sniff`` corrects declared types and
``carve`` cuts out embedded media (matches inside an accepted one are nested and
not listed again). Payloads are stored as 8-bit mono PCM in RIFF/WAVE.

Confirmed lengths: containers by their own sizes and checksums, JPEG by its segments up
to the end mark, PDF by the last end mark whose cross-reference offset holds (the
first end mark where none is given), FLAC by its metadata blocks and the header
and frame checksums of all samples that it announces.

Defined results: null or empty bytes have type 'empty'; bytes that no validator
accepts at offset 0 have type 'unknown' and keep nothing of the declared type;
strings count as their UTF-8 bytes; equal bytes give equal rows; extra columns pass
through ``sniff`` untouched (but for its own three).
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, plus, slices, table

#: Magic numbers of the formats.
MAGIC = {
    "png": b"\x89PNG\r\n\x1a\n",
    "gif87": b"GIF87a",
    "gif89": b"GIF89a",
    "jpeg": b"\xff\xd8\xff",
    "wav": b"RIFF",
    "bmp": b"BM",
    "pdf": b"%PDF-",
    "zip": b"PK\x03\x04",
    "gzip": b"\x1f\x8b\x08",
    "flac": b"fLaC",
    "ogg": b"OggS",
    "pgm": b"P5",
}
#: Media type of each format.
MIME = {"png": "image/png", "gif": "image/gif", "jpeg": "image/jpeg", "wav": "audio/wav", "bmp": "image/bmp", "pdf": "application/pdf", "zip": "application/zip", "gzip": "application/gzip", "flac": "audio/flac", "ogg": "audio/ogg", "pgm": "image/x-portable-graymap"}


def _png(b, at):
    p = at + 8
    if b[p + 4 : p + 8] != b"IHDR":
        return 0
    while p + 12 <= len(b):
        (n,) = struct.unpack_from(">I", b, p)
        if p + 12 + n > len(b) or struct.unpack_from(">I", b, p + 8 + n)[0] != zlib.crc32(b[p + 4 : p + 8 + n]):
            return 0
        p += 12 + n
        if b[p - n - 8 : p - n - 4] == b"IEND":
            return p - at
    return 0


def _blocks(b, p):
    while p < len(b):
        n = b[p]
        p += n + 1
        if not n:
            return p
    return 0


def _gif(b, at):
    if at + 13 > len(b):
        return 0
    flags = b[at + 10]
    p = at + 13 + (3 << ((flags & 7) + 1) if flags & 128 else 0)
    while p < len(b):
        if b[p] == 0x3B:
            return p + 1 - at
        if b[p] == 0x21:
            p = _blocks(b, p + 2)
        elif b[p] == 0x2C and p + 10 < len(b):
            flags = b[p + 9]
            p = _blocks(b, p + 11 + (3 << ((flags & 7) + 1) if flags & 128 else 0))
        else:
            return 0
        if not p:
            return 0
    return 0


def _jpeg(b, at):
    p = at + 2
    while p + 4 <= len(b) and b[p] == 0xFF:
        kind = b[p + 1]
        if kind in (0x00, 0x01, 0xD8) or 0xD0 <= kind <= 0xD7:
            return 0
        (n,) = struct.unpack_from(">H", b, p + 2)
        if n < 2:
            return 0
        p += 2 + n
        if kind == 0xDA:
            end = b.find(b"\xff\xd9", p)
            return end + 2 - at if end >= 0 else 0
    return 0


def _wav(b, at):
    if at + 12 > len(b) or b[at + 8 : at + 12] != b"WAVE":
        return 0
    size = struct.unpack_from("<I", b, at + 4)[0] + 8
    if size < 44 or at + size > len(b):
        return 0
    p, seen = at + 12, set()
    while p + 8 <= at + size:
        seen.add(b[p : p + 4])
        n = struct.unpack_from("<I", b, p + 4)[0]
        p += 8 + n + (n & 1)
    return size if {b"fmt ", b"data"} <= seen and p <= at + size + 1 else 0


def _bmp(b, at):
    if at + 26 > len(b):
        return 0
    size, zero, start, head = struct.unpack_from("<IIII", b, at + 2)
    return size if zero == 0 and head in (12, 40, 52, 56, 108, 124) and 14 + head <= start <= size <= len(b) - at else 0


PDF_END = re.compile(rb"(?:startxref\s+(\d{1,12})\s+)?%%EOF")
PDF_TABLE = re.compile(rb"\s*(?:xref\b|\d+\s+\d+\s+obj\b)")


def _pdf(b, at):
    if not b[at + 5 : at + 6].isdigit():
        return 0
    after = b.find(b"%PDF-", at + 5)  # another document starts there
    first = last = 0
    for m in PDF_END.finditer(b, at, after if after >= 0 else len(b)):
        first = first or m.end() - at
        if m[1] and PDF_TABLE.match(b, at + int(m[1]), m.start()):
            last = m.end() - at
    return last or first


def _zip(b, at):
    end = b.find(b"PK\x05\x06", at)
    if end < 0 or end + 22 > len(b) or at + 30 > len(b):
        return 0
    note = struct.unpack_from("<H", b, end + 20)[0]
    size, start = struct.unpack_from("<II", b, end + 12)
    return end + 22 + note - at if end + 22 + note <= len(b) and start + size == end - at else 0


def _gzip(b, at):
    d, p = zlib.decompressobj(31), at
    try:
        while p < len(b) and not d.eof:
            d.decompress(b[p : p + 65536])
            p += 65536
    except zlib.error:
        return 0
    return min(p, len(b)) - at - len(d.unused_data) if d.eof else 0


def _crc_table(bits: int, poly: int) -> list[int]:
    top, mask, out = 1 << (bits - 1), (1 << bits) - 1, []
    for i in range(256):
        c = i << (bits - 8)
        for _ in range(8):
            c = ((c << 1) ^ poly if c & top else c << 1) & mask
        out.append(c)
    return out


CRC8, CRC16 = _crc_table(8, 0x07), _crc_table(16, 0x8005)
#: Samples of a block by the code in a frame header (6 and 7: in the header itself).
BLOCK_SIZES = {1: 192, **{k: 576 << (k - 2) for k in range(2, 6)}, **{k: 256 << (k - 8) for k in range(8, 16)}}


def _flac_header(b, p):
    """(samples, header bytes) of the frame header at p, or None."""
    if p + 6 > len(b) or b[p] != 0xFF or b[p + 1] & 0xFE != 0xF8 or b[p + 2] >> 4 == 0 or b[p + 2] & 15 == 15 or b[p + 3] >> 4 > 10 or b[p + 3] & 1:
        return None
    size, rate, q = b[p + 2] >> 4, b[p + 2] & 15, p + 4
    lead = 8 - (b[q] ^ 0xFF).bit_length()  # the number is coded like a UTF-8 character
    if lead == 1 or lead > 7:
        return None
    q += max(1, lead)
    samples = BLOCK_SIZES.get(size)
    if size in (6, 7):
        samples = int.from_bytes(b[q : q + size - 5], "big") + 1
        q += size - 5
    q += {12: 1, 13: 2, 14: 2}.get(rate, 0)
    crc = 0
    for x in b[p:q]:
        crc = CRC8[crc ^ x]
    return (samples, q + 1 - p) if q < len(b) and b[q] == crc else None


def _flac(b, at):
    p, info = at + 4, None
    while True:  # metadata blocks
        if p + 4 > len(b):
            return 0
        kind, n = b[p], int.from_bytes(b[p + 1 : p + 4], "big")
        if info is None:
            if kind & 127 or n != 34:
                return 0
            info = b[p + 4 : p + 38]
        p += 4 + n
        if kind & 128:
            break
    if p > len(b) or len(info) < 34:
        return 0
    left = int.from_bytes(info[13:18], "big") & ((1 << 36) - 1)
    least = int.from_bytes(info[4:7], "big")
    while left > 0:  # a frame ends where its running checksum is zero and the next header, or nothing more, follows
        head = _flac_header(b, p)
        if not head:
            return 0
        left -= head[0]
        crc, ends = 0, []
        for q in range(p, len(b)):
            crc = (crc << 8 & 0xFF00) ^ CRC16[crc >> 8 ^ b[q]]
            if crc == 0 and q + 1 - p >= max(least, head[1] + 2):
                if left > 0 and _flac_header(b, q + 1):
                    ends = [q + 1]
                    break
                if left <= 0:
                    ends.append(q + 1)
                    if len(ends) == 1 and least:
                        break
        if not ends:
            return 0
        p = ends[-1] if ends[-1] == len(b) else ends[0]
    return p - at


def _ogg(b, at):
    p = at
    while b[p : p + 4] == b"OggS" and p + 27 <= len(b) and b[p + 4] == 0:
        n = b[p + 26]
        size = 27 + n + sum(b[p + 27 : p + 27 + n])
        if p + size > len(b):
            break
        last, p = b[p + 5] & 4, p + size
        if last:
            return p - at
    return 0


def _pgm(b, at):
    fields = b[at : at + 64].split(None, 4)
    if len(fields) < 4 or not all(x.isdigit() for x in fields[1:4]) or fields[0] != b"P5" or int(fields[3]) > 255:
        return 0
    p = at + 2
    for x in fields[1:4]:
        p = b.index(x, p) + len(x)
    size = p + 1 - at + int(fields[1]) * int(fields[2])
    return size if at + size <= len(b) else 0


CHECKS = {"png": _png, "gif87": _gif, "gif89": _gif, "jpeg": _jpeg, "wav": _wav, "bmp": _bmp, "pdf": _pdf, "zip": _zip, "gzip": _gzip, "flac": _flac, "ogg": _ogg, "pgm": _pgm}


def automaton():
    import ahocorasick

    a = ahocorasick.Automaton()
    for name, magic in MAGIC.items():
        a.add_word(magic.decode("latin-1"), (name, len(magic)))
    a.make_automaton()
    return a


def found(auto, data: bytes) -> list[tuple[int, int, str]]:
    """(offset, length, format) of all media in data, outermost only, in order."""
    out, free = [], 0
    for end, (name, n) in auto.iter(data.decode("latin-1")):
        at = end - n + 1
        if at >= free and (size := CHECKS[name](data, at)):
            out.append((at, size, name[:3] if name.startswith("gif") else name))
            free = at + size
    return out


def _rows(column: str, pick):
    def run(batches):
        auto = automaton()
        for batch in batches:
            yield from pick(auto, batch, batch.column(batch.schema.get_field_index(column)))

    return run


def sniffed(column: str, declared: str | None = None):
    """The step of sniff, from batches to batches."""

    def pick(auto, batch, values):
        kinds, sizes, fixed = [], [], []
        said = batch.column(batch.schema.get_field_index(declared)).to_pylist() if declared else [None] * batch.num_rows
        for v, d in zip(values, said, strict=True):
            data = v.as_py()
            data = data.encode() if isinstance(data, str) else data or b""
            first = next((x for x in found(auto, data) if x[0] == 0), None)
            kind = MIME[first[2]] if first else "unknown" if data else "empty"
            kinds.append(kind)
            sizes.append(first[1] if first else 0)
            fixed.append(bool(d) and d != kind)
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(kinds, pa.string()), pa.array(sizes, pa.int64()), pa.array(fixed, pa.bool_())], names=[*batch.schema.names, "sniffed_type", "sniffed_length", "type_corrected"])

    return _rows(column, pick)


def sniff(df: DataFrame, column: str, declared: str | None = None) -> DataFrame:
    """Adds sniffed_type, sniffed_length, type_corrected (the declared type differs) to every row."""
    df = df.drop("sniffed_type", "sniffed_length", "type_corrected")
    return df.mapInArrow(sniffed(column, declared), plus(df.schema, sniffed_type="string", sniffed_length="long", type_corrected="boolean"))


def carved(key: str, column: str, *more: str):
    """The step of carve, from batches to batches."""

    def pick(auto, batch, values):
        where, rows = [], []
        for i, v in enumerate(values):
            data = v.as_py()
            data = data.encode() if isinstance(data, str) else data
            for at, n, name in found(auto, data) if data else ():
                where.append(i)
                rows.append((at, n, MIME[name], data[at : at + n]))
        if rows:
            own = [batch.column(batch.schema.get_field_index(c)).take(pa.array(where)) for c in (key, *more)]
            cols = [pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.string(), pa.binary()), strict=True)]
            yield pa.RecordBatch.from_arrays([own[0], *cols, *own[1:]], names=["key", "offset", "length", "media_type", "content", *more])

    return _rows(column, pick)


def carve(df: DataFrame, key: str, column: str, *more: str) -> DataFrame:
    """One row per embedded medium: key, offset, length, media_type, content, and further columns of its row."""
    kinds = {c: df.schema[c].dataType.simpleString() for c in (key, *more)}
    schema = f"key {kinds[key]}, offset long, length long, media_type string, content binary" + "".join(f", {c} {kinds[c]}" for c in more)
    return df.mapInArrow(carved(key, column, *more), schema)


def to_wave(payload: bytes) -> bytes:
    """8-bit mono samples at 8 kHz; the payload has an even length."""
    return b"RIFF" + struct.pack("<I", 36 + len(payload)) + b"WAVEfmt " + struct.pack("<IHHIIHH", 16, 1, 1, 8000, 8000, 1, 8) + b"data" + struct.pack("<I", len(payload)) + payload


def wave_samples(data: bytes) -> bytes:
    """The samples of a stored wave, found through its own chunk headers."""
    p = 12
    while p + 8 <= len(data):
        n = struct.unpack_from("<I", data, p + 4)[0]
        if data[p : p + 4] == b"data":
            return data[p + 8 : p + 8 + n]
        p += 8 + n + (n & 1)
    return b""


def pack_texts(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_bytes, media): every whole text as bytes, padded to a positive multiple of 64, in a stored wave."""

    def run(batches):
        for whole in batches:
            for batch in slices(whole, text):
                data = [(v.as_py() or "").encode() for v in batch.column(batch.schema.get_field_index(text))]
                media = [to_wave(x + bytes(-len(x) % 64 or (0 if x else 64))) for x in data]
                yield pa.RecordBatch.from_arrays([batch.column(batch.schema.get_field_index(key)), pa.array([len(x) for x in data], pa.int64()), pa.array(media, pa.binary())], names=["key", "n_bytes", "media"])

    return docs.select(key, text).mapInArrow(run, f"key {docs.schema[key].dataType.simpleString()}, n_bytes long, media binary")


#: The types that stored texts are declared as, right for one in four.
DECLARED = ("application/octet-stream", "image/png", "audio/wav", "audio/flac")


def digested(batches):
    """The digest columns of stored waves in batches (key, offset, content, media_type, n_bytes, declared, type_corrected) that start their value."""
    auto = automaton()
    for batch in batches:
        col = {n: batch.column(i) for i, n in enumerate(batch.schema.names)}
        col = {n: c.filter(pc.equal(col["offset"], 0)) for n, c in col.items()}
        rows = []
        for v, kind, said, fixed in zip(col["content"], *(col[c].to_pylist() for c in ("media_type", "declared", "type_corrected")), strict=True):
            data = v.as_py()
            payload = wave_samples(data)
            feature = f"{kind};declared={said};corrected={fixed};embedded={len(found(auto, payload))};distinct={len(set(payload))};crc={zlib.crc32(payload):08x}"
            rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(data), hashlib.sha256(data).hexdigest(), feature))
        cols = list(zip(*rows, strict=True)) if rows else [()] * 6
        yield pa.RecordBatch.from_arrays([col["key"], col["n_bytes"], *(pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()), strict=True)), col["media_type"]], names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "media_type"])


def op6_media_columns(spark, sf_dir) -> DataFrame:
    """Texts written as waves under types of which most are wrong, read back, sniffed, carved and digested (in one worker)."""
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    said = F.element_at(F.array(*map(F.lit, DECLARED)), (F.pmod(F.crc32("media"), F.lit(len(DECLARED))) + 1).cast("int"))
    stored = materialize(pack_texts(docs).withColumn("declared", said), "media")
    judge, cut = sniffed("media", "declared"), carved("key", "media", "n_bytes", "declared", "type_corrected")

    def run(batches):
        yield from digested(cut(judge(b for whole in batches for b in slices(whole, "media"))))

    kind = stored.schema["key"].dataType.simpleString()
    return stored.mapInArrow(run, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, media_type string")
