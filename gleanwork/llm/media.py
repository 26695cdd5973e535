"""Media columns: signature sniffing, structural validation, carving.

An Aho-Corasick automaton finds the magic bytes of all formats in one pass over a value. A format's validator then walks
the structure from there and says how long it is, or that the bytes are no such thing. The type at offset 0 corrects the
declared one; valid structures further in are carved as embedded media.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F, types as T

from .common import map_text, slices, table

UNIT = 64


class Bytes:
    """A value under inspection. Validators take it and an absolute start and give an absolute end or None.

    What they learn is kept for the value: the next place of a marker, and where chains of chunks, pages, blocks or boxes end.
    A chain is therefore walked once, however many signatures lead into it, and no tail is copied.
    """

    def __init__(self, data: bytes):
        self.data, self.view, self.n = data, memoryview(data), len(data)
        self.next: dict[bytes, int] = {}
        self.ends: dict[tuple, object] = {}
        self.archives: dict[int, int] | None = None

    def find(self, marker: bytes, at: int) -> int:
        """First place of marker from at on, else the value's length; looks are made from left to right."""
        known = self.next.get(marker, -1)
        if known < at:
            found = self.data.find(marker, at)
            known = self.next[marker] = self.n if found < 0 else found
        return known

    def chain(self, kind: str, at: int, step):
        """Follow step(at) -> (next place, None) or (None, end) and remember the end for every place passed."""
        passed = []
        while (kind, at) not in self.ends:
            passed.append(at)
            nxt, end = step(at)
            if nxt is None:
                break
            at = nxt
        else:
            end = self.ends[kind, at]
        for p in passed:
            self.ends[kind, p] = end
        return end


def _png(b: Bytes, start: int) -> int | None:
    def step(at):
        n = int.from_bytes(b.view[at : at + 4], "big")
        if at + 12 + n > b.n or zlib.crc32(b.view[at + 4 : at + 8 + n]) != int.from_bytes(b.view[at + 8 + n : at + 12 + n], "big"):
            return None, None
        return (None, at + 12 + n) if b.data[at + 4 : at + 8] == b"IEND" else (at + 12 + n, None)

    return b.chain("png", start + 8, step) if b.data[start + 8 : start + 16] == b"\0\0\0\x0dIHDR" else None


def _jpeg(b: Bytes, start: int) -> int | None:
    def coded(at):
        """The next marker behind entropy-coded bytes."""
        while (at := b.data.find(b"\xff", at)) >= 0 and at + 1 < b.n:
            kind = b.data[at + 1]
            if kind not in (0, 0xFF) and not 0xD0 <= kind <= 0xD7:
                return at
            at += 2 - (kind == 0xFF)
        return None

    def step(at):
        if at + 4 > b.n or b.data[at] != 0xFF:
            return None, None
        kind = b.data[at + 1]
        if kind == 0xFF:
            return at + 1, None
        n = int.from_bytes(b.view[at + 2 : at + 4], "big")
        if kind < 0xC0 or n < 2:
            return None, None
        at += 2 + n
        if kind == 0xDA:
            at = coded(at)
            if at is None:
                return None, None
            if b.data[at + 1] == 0xD9:
                return None, at + 2
        return at, None

    return b.chain("jpeg", start + 2, step)


def _gif(b: Bytes, start: int) -> int | None:
    table = lambda flags: (3 << (flags & 7) + 1) if flags & 0x80 else 0

    def hop(at):
        if at >= b.n:
            return None, None
        return (None, at + 1) if b.data[at] == 0 else (at + b.data[at] + 1, None)

    def step(at):
        if at >= b.n:
            return None, None
        if b.data[at] == 0x3B:
            return None, at + 1
        if b.data[at] == 0x21:
            return b.chain("gif-block", at + 2, hop), None
        if b.data[at] == 0x2C and at + 10 <= b.n:
            return b.chain("gif-block", at + 11 + table(b.data[at + 9]), hop), None
        return None, None

    return b.chain("gif", start + 13 + table(b.data[start + 10]), step) if start + 13 <= b.n else None


def riff_chunks(b: memoryview) -> list[tuple[bytes, int, int]] | None:
    """(id, start, end) of the chunks of a RIFF structure at the start of b, or None if lengths do not agree."""
    if len(b) < 12:
        return None
    end = 8 + int.from_bytes(b[4:8], "little")
    if end > len(b) or end < 12:
        return None
    at, out = 12, []
    while at + 8 <= end:
        n = int.from_bytes(b[at + 4 : at + 8], "little")
        if at + 8 + n > end:
            return None
        out.append((bytes(b[at : at + 4]), at + 8, at + 8 + n))
        at += 8 + n + (n & 1)
    return out if at in (end, end + 1) and out else None


def _riff(form: bytes, needs: set[bytes]):
    def check(b: Bytes, start: int) -> int | None:
        chunks = riff_chunks(b.view[start:])
        if chunks is None or not needs & {c for c, _, _ in chunks}:
            return None
        return start + 8 + int.from_bytes(b.view[start + 4 : start + 8], "little")

    return check


def _bmp(b: Bytes, start: int) -> int | None:
    head = b.view[start : start + 26]
    if len(head) < 26:
        return None
    size, first, header = int.from_bytes(head[2:6], "little"), int.from_bytes(head[10:14], "little"), int.from_bytes(head[14:18], "little")
    return start + size if 26 <= size <= b.n - start and first < size and header in (12, 40, 52, 56, 64, 108, 124) and not any(head[6:10]) else None


def _gzip(b: Bytes, start: int) -> int | None:
    if b.n - start < 18 or b.data[start + 3] & 0xE0:
        return None
    d = zlib.decompressobj(31)
    try:
        for i in range(start, b.n, 1 << 16):
            part = b.view[i : i + (1 << 16)]
            while not d.eof:
                full = len(d.decompress(part, 1 << 20)) == 1 << 20  # output is dropped: only the end is of interest
                part = d.unconsumed_tail
                if not part and not full:
                    break
            if d.eof:
                return min(b.n, i + (1 << 16)) - len(d.unused_data)
    except zlib.error:
        pass
    return None


def _zip(b: Bytes, start: int) -> int | None:
    """An end record says where its archive starts, so all end records of the value are read once."""
    if b.archives is None:
        b.archives, at = {}, -1
        while (at := b.data.find(b"PK\x05\x06", at + 1)) >= 0:
            if at + 22 <= b.n:
                size, listing, note = struct.unpack("<IIH", b.view[at + 12 : at + 22])
                base = at - listing - size
                if base >= 0 and at + 22 + note <= b.n and b.data[base + listing : base + listing + 4] == b"PK\x01\x02":
                    b.archives.setdefault(base, at + 22 + note)
    return b.archives.get(start)


def _pdf(b: Bytes, start: int) -> int | None:
    end = b.find(b"%%EOF", start)
    return end + 5 if end < b.n and b.find(b"startxref", start) < end else None


def _ogg(b: Bytes, start: int) -> int | None:
    def step(at):
        if at + 27 > b.n or b.data[at : at + 4] != b"OggS" or b.data[at + 4]:
            return None, None
        body = at + 27 + b.data[at + 26]
        if body > b.n:
            return None, None
        end = body + sum(b.view[at + 27 : body])
        if end > b.n:
            return None, None
        return (None, end) if b.data[at + 5] & 4 else (end, None)

    return b.chain("ogg", start, step)


def _au(b: Bytes, start: int) -> int | None:
    if b.n - start < 24:
        return None
    first, size, code = struct.unpack(">III", b.view[start + 4 : start + 16])
    return start + first + size if 24 <= first and first + size <= b.n - start and 1 <= code <= 27 else None


def _mp4(b: Bytes, start: int) -> int | None:
    """Boxes in a row, one of them moov; for every box passed it is kept where its row ends and whether a moov follows."""
    at, passed = start, []
    while (known := b.ends.get(("mp4", at))) is None:
        n, kind = int.from_bytes(b.view[at : at + 4], "big"), b.data[at + 4 : at + 8]
        if n < 8 or at + n > b.n or not kind.isalnum():
            known = (at, False)
            break
        passed.append((at, kind == b"moov"))
        at += n
    for p, moov in reversed(passed):
        known = b.ends["mp4", p] = (known[0], known[1] or moov)
    return known[0] if known[1] else None


#: type -> (magic, where the magic stands, validator, whether it is looked for inside other bytes)
FORMATS = {
    "image/png": (b"\x89PNG\r\n\x1a\n", 0, _png, True),
    "image/jpeg": (b"\xff\xd8\xff", 0, _jpeg, True),
    "image/gif": (b"GIF8", 0, _gif, True),
    "audio/wav": (b"WAVE", 8, _riff(b"WAVE", {b"data"}), True),
    "image/webp": (b"WEBP", 8, _riff(b"WEBP", {b"VP8 ", b"VP8L", b"VP8X"}), True),
    "video/avi": (b"AVI ", 8, _riff(b"AVI ", {b"LIST"}), True),
    "image/bmp": (b"BM", 0, _bmp, False),
    "application/gzip": (b"\x1f\x8b\x08", 0, _gzip, True),
    "application/zip": (b"PK\x03\x04", 0, _zip, True),
    "application/pdf": (b"%PDF-", 0, _pdf, True),
    "audio/ogg": (b"OggS", 0, _ogg, True),
    "audio/basic": (b".snd", 0, _au, True),
    "video/mp4": (b"ftyp", 4, _mp4, True),
}


class Sniffer:
    def __init__(self):
        import ahocorasick

        self.automaton = ahocorasick.Automaton()
        for kind, (magic, shift, check, inside) in FORMATS.items():
            self.automaton.add_word(magic.decode("latin-1"), (kind, len(magic), shift, check, inside))
        self.automaton.make_automaton()

    def found(self, data: bytes) -> Iterator[tuple[str, int, int]]:
        """(type, start, end) of valid structures, left to right; what lies inside one is reported too."""
        b = Bytes(data)
        for last, (kind, n, shift, check, inside) in self.automaton.iter(data.decode("latin-1")):
            start = last - n + 1 - shift
            if start < 0 or (start and not inside) or (shift == 8 and data[start : start + 4] != b"RIFF"):
                continue
            if end := check(b, start):
                yield kind, start, end

    def sniff(self, data: bytes | None, declared: str | None = None) -> dict:
        """The type at offset 0 (else application/octet-stream), whether it corrects the declared one, embedded media."""
        hits = sorted(set(self.found(data or b"")), key=lambda h: (h[1], -h[2]))
        own = next((h for h in hits if h[1] == 0), None)
        kind = own[0] if own else "application/octet-stream"
        return {"type": kind, "corrected": declared is not None and declared != kind, "length": own[2] if own else len(data or b""), "embedded": [h for h in hits if h[1] > 0]}


def write_wav(samples: bytes, rate: int = 8000) -> bytes:
    """8-bit unsigned mono PCM; an odd number of samples is padded as RIFF asks."""
    pad = b"\0" * (len(samples) & 1)
    head = b"fmt " + struct.pack("<IHHIIHH", 16, 1, 1, rate, rate, 1, 8)
    return b"RIFF" + struct.pack("<I", 4 + len(head) + 8 + len(samples) + len(pad)) + b"WAVE" + head + b"data" + struct.pack("<I", len(samples)) + samples + pad


def read_wav(data: bytes) -> bytes:
    view = memoryview(data)
    chunks = riff_chunks(view)
    if chunks is None or data[8:12] != b"WAVE":
        raise ValueError("not a whole WAV")
    return b"".join(bytes(view[a:b]) for c, a, b in chunks if c == b"data")


def payload_of(text: str | None) -> tuple[bytes, int]:
    """UTF-8 bytes, filled with 0 to a positive multiple of UNIT, and their number without the fill."""
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw + b"\0" * (max(UNIT, -(-len(raw) // UNIT) * UNIT) - len(raw)), len(raw)


def sniff_media(df: DataFrame, key: str, data: str, declared: str | None = None) -> DataFrame:
    """(key, type, corrected, length, embedded array<struct<type,start,end>>) for each row of a binary column.

    Null and empty values are application/octet-stream of length 0; repeated rows repeat; other columns are not read.
    """
    where = T.ArrayType(T.StructType([T.StructField("type", T.StringType()), T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))
    schema = T.StructType([df.schema[key], T.StructField("type", T.StringType()), T.StructField("corrected", T.BooleanType()), T.StructField("length", T.LongType()), T.StructField("embedded", where)])

    def run(batches):
        sniffer = Sniffer()
        for b in (piece for batch in batches for piece in slices(batch, "_data")):
            out = [sniffer.sniff(x, y) for x, y in zip(b.column(1).to_pylist(), b.column(2).to_pylist())]
            for o in out:
                o["embedded"] = [{"type": t, "start": s, "end": e} for t, s, e in o["embedded"]]
            yield pa.RecordBatch.from_pylist([{key: k, **o} for k, o in zip(b.column(0).to_pylist(), out)], schema=_arrow(schema))

    kind = df[declared].cast("string") if declared else F.lit(None).cast("string")
    return df.select(df[key], df[data].alias("_data"), kind.alias("_declared")).mapInArrow(run, schema)


def _arrow(schema: T.StructType):
    from pyspark.sql.pandas.types import to_arrow_schema as convert

    return convert(schema)


def text_media(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Texts stored as WAV, sniffed, read back from what the sniffer carved, and described.

    One row for each input row: sizes, hashes and features of the payload as read back and of the stored form. Null and
    empty texts store UNIT zero bytes; equal texts give equal values; other columns are not read.
    """
    schema = T.StructType([T.StructField("key", docs.schema[key].dataType), T.StructField("n_bytes", T.LongType()), T.StructField("payload_bytes", T.LongType()), T.StructField("payload_sha256", T.StringType()), T.StructField("tail_crc32", T.LongType()), T.StructField("media_bytes", T.LongType()), T.StructField("media_sha256", T.StringType()), T.StructField("feature", T.StringType())])

    def work(blocks):
        sniffer = Sniffer()
        for (keys,), texts in blocks:
            rows = [describe(sniffer, t) for t in texts]
            yield [keys, *([r[i] for r in rows] for i in range(7))]

    return map_text(docs.select(docs[key].alias("key"), docs[text].alias("text")), ["key"], "text", schema, work).withColumnRenamed("key", key)


def describe(sniffer: Sniffer, text: str | None) -> tuple:
    payload, n = payload_of(text)
    media = write_wav(payload)
    seen = sniffer.sniff(media, "application/octet-stream")
    back = read_wav(media[: seen["length"]]) if seen["type"] == "audio/wav" else b""
    level = sum(back) / len(back) if back else 0.0
    inside = ",".join(f"{t}@{a}-{b}" for t, a, b in seen["embedded"])
    feature = f"type={seen['type']};corrected={str(seen['corrected']).lower()};samples={len(back)};mean={level:.4f};peak={max(back, default=0)};embedded={inside}"
    return n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(media), hashlib.sha256(media).hexdigest(), feature


def op6_media(spark, sf_dir: str) -> DataFrame:
    return text_media(table(spark, sf_dir, "documents"))
