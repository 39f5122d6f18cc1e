"""Media columns: find magic bytes, confirm structure, correct types, carve what is embedded.

One Aho-Corasick pass locates every magic string; a validator of the format
then walks headers, chunks and checksums and returns the exact length, or
nothing, in which case the hit is dropped. A value's own type is that of a
valid object at byte 0 that covers it; valid objects inside it are carved.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from bisect import bisect_left, bisect_right
from collections.abc import Callable
from functools import cached_property, lru_cache

from pyspark.sql import DataFrame

from linkblock.llm.common import narrow, per_document, whole_id

UNKNOWN = "application/octet-stream"
#: Codes of whole, floating and extensible samples.
WAV_FORMS = (1, 3, 0xFFFE)
#: Formats whose inside is compressed: nothing is sought there.
OPAQUE = ("application/gzip", "image/png", "image/jpeg", "audio/ogg")
#: Bytes without a meaning that may follow an object up to the value's end.
PADDING = b"\0 \t\r\n"


class Marks:
    """Places of end marks in a value, each sought once however many headers ask for it."""

    def __init__(self, data: bytes):
        self.data, self.places = data, {}

    def all(self, mark: bytes) -> list[int]:
        if mark not in self.places:
            found, at = [], self.data.find(mark)
            while at >= 0:
                found.append(at)
                at = self.data.find(mark, at + 1)
            self.places[mark] = found
        return self.places[mark]

    def after(self, mark: bytes, at: int) -> int:
        """The first place of mark from `at` on, or -1."""
        found = self.all(mark)
        i = bisect_left(found, at)
        return found[i] if i < len(found) else -1

    @cached_property
    def pdf_ends(self) -> list[int]:
        """Ends of PDF bodies: an end mark that a cross-reference offset stands before, with the line's end after it."""
        found = []
        for at in self.all(b"%%EOF"):
            if b"startxref" in self.data[max(0, at - 64) : at]:
                end = at + 5
                end += self.data[end : end + 1] == b"\r"
                found.append(end + (self.data[end : end + 1] == b"\n"))
        return found

    @cached_property
    def zip_ends(self) -> dict[int, int]:
        """By the start of each archive that an end record tells of: its furthest end."""
        found: dict[int, int] = {}
        for end in self.all(b"PK\x05\x06"):
            if end + 22 <= len(self.data):
                size, start, note = struct.unpack_from("<IIH", self.data, end + 12)
                central = end - size
                if central >= start and end + 22 + note <= len(self.data) and (size == 0 or self.data[central : central + 4] == b"PK\x01\x02"):
                    found[central - start] = max(end + 22 + note, found.get(central - start, 0))
        return found


def _wav(d: bytes, at: int, marks: Marks) -> int | None:
    return size if (size := _riff(d, at, b"WAVE")) and wav_samples(d, at, at + size) is not None else None


def _webp(d: bytes, at: int, marks: Marks) -> int | None:
    return _riff(d, at, b"WEBP") if d[at + 12 : at + 15] == b"VP8" else None


def _riff(d: bytes, at: int, form: bytes) -> int | None:
    if d[at + 8 : at + 12] != form or len(d) < at + 12:
        return None
    size = 8 + struct.unpack_from("<I", d, at + 4)[0]
    return size if at + size <= len(d) else None


def wav_samples(d: bytes, start: int = 0, stop: int | None = None) -> tuple[int, int] | None:
    """Start and length of the samples of a sound file of whole or floating samples, if its chunks are sound."""
    at, described, stop = start + 12, False, len(d) if stop is None else stop
    while at + 8 <= stop:
        kind, size = d[at : at + 4], struct.unpack_from("<I", d, at + 4)[0]
        if at + 8 + size > stop:
            return None
        if kind == b"fmt ":
            if size < 16 or struct.unpack_from("<H", d, at + 8)[0] not in WAV_FORMS:
                return None
            described = True
        elif kind == b"data":
            return (at + 8, size) if described else None
        at += 8 + size + size % 2
    return None


def _png(d: bytes, at: int, marks: Marks) -> int | None:
    p, first = at + 8, True
    while p + 12 <= len(d):
        size, kind = struct.unpack_from(">I4s", d, p)
        end = p + 12 + size
        if end > len(d) or (first and (kind != b"IHDR" or size != 13)) or zlib.crc32(d[p + 4 : p + 8 + size]) != struct.unpack_from(">I", d, end - 4)[0]:
            return None
        if kind == b"IEND":
            return end - at
        p, first = end, False
    return None


def _gif(d: bytes, at: int, marks: Marks) -> int | None:
    def blocks(p: int) -> int | None:
        while p < len(d):
            if d[p] == 0:
                return p + 1
            p += 1 + d[p]
        return None

    if at + 13 > len(d):
        return None
    p = at + 13 + (3 << ((d[at + 10] & 7) + 1) if d[at + 10] & 128 else 0)
    while p is not None and p < len(d):
        if d[p] == 0x3B:
            return p + 1 - at
        if d[p] == 0x21:
            p = blocks(p + 2)
        elif d[p] == 0x2C and p + 10 <= len(d):
            p = blocks(p + 11 + (3 << ((d[p + 9] & 7) + 1) if d[p + 9] & 128 else 0))
        else:
            return None
    return None


def _jpeg(d: bytes, at: int, marks: Marks) -> int | None:
    p = at + 2
    while p + 4 <= len(d) and d[p] == 0xFF:
        mark = d[p + 1]
        if mark == 0xDA:
            end = marks.after(b"\xff\xd9", p)
            return end + 2 - at if end >= 0 else None
        if mark < 0xC0:
            return None
        p += 2 + struct.unpack_from(">H", d, p + 2)[0]
    return None


def _bmp(d: bytes, at: int, marks: Marks) -> int | None:
    if at + 30 > len(d):
        return None
    size, zero, start, head = struct.unpack_from("<IIII", d, at + 2)
    ok = zero == 0 and head in (12, 40, 52, 56, 108, 124) and 14 + head <= start < size
    return size if ok and at + size <= len(d) else None


def _pdf(d: bytes, at: int, marks: Marks) -> int | None:
    """The last body's end before the next header, as a file that was added to has several; to the value's end where only blanks follow."""
    if not d[at + 5 : at + 6].isdigit():
        return None
    ends, last = marks.pdf_ends, len(d)
    if at == 0 and ends and not d[ends[-1] :].strip():
        return len(d)
    following = marks.after(b"%PDF-", at + 1)
    i = bisect_right(ends, last if following < 0 else following) - 1
    return ends[i] - at if i >= 0 and ends[i] > at else None


def _zip(d: bytes, at: int, marks: Marks) -> int | None:
    end = marks.zip_ends.get(at)
    return end - at if end else None


def _gzip(d: bytes, at: int, marks: Marks) -> int | None:
    """One or more members in a row."""
    p, whole = at, None
    while d[p : p + 3] == b"\x1f\x8b\x08":
        z = zlib.decompressobj(31)
        try:
            while p < len(d) and not z.eof:
                z.decompress(d[p : p + 65536])
                p += 65536
        except zlib.error:
            break
        if not z.eof:
            break
        p = min(p, len(d)) - len(z.unused_data)
        whole = p - at
    return whole


def _ogg(d: bytes, at: int, marks: Marks) -> int | None:
    """Pages from a first one to a last one; later pages begin nothing."""
    p = at
    while d[p : p + 4] == b"OggS" and p + 27 <= len(d):
        n, flags = d[p + 26], d[p + 5]
        end = p + 27 + n + sum(d[p + 27 : p + 27 + n])
        if d[p + 4] != 0 or end > len(d) or (flags & 2 == 0) == (p == at):
            return None
        if flags & 4:
            return end - at
        p = end
    return None


#: Magic bytes, media type, validator.
FORMATS: tuple[tuple[bytes, str, Callable[[bytes, int, Marks], int | None]], ...] = (
    (b"RIFF", "audio/wav", _wav), (b"RIFF", "image/webp", _webp), (b"\x89PNG\r\n\x1a\n", "image/png", _png),
    (b"GIF87a", "image/gif", _gif), (b"GIF89a", "image/gif", _gif), (b"\xff\xd8\xff", "image/jpeg", _jpeg),
    (b"BM", "image/bmp", _bmp), (b"%PDF-", "application/pdf", _pdf), (b"PK\x03\x04", "application/zip", _zip),
    (b"\x1f\x8b\x08", "application/gzip", _gzip), (b"OggS", "audio/ogg", _ogg),
)


@lru_cache(1)
def _magic():
    import ahocorasick

    by: dict[bytes, list] = {}
    for magic, kind, valid in FORMATS:
        by.setdefault(magic, []).append((len(magic), kind, valid))
    a = ahocorasick.Automaton()
    for magic, found in by.items():
        a.add_word(magic.decode("latin-1"), found)
    a.make_automaton()
    return a


def sniff(data: bytes) -> list[tuple[str, int, int]]:
    """(type, start, length) of every valid object by start, the longer first; none inside a compressed one."""
    found, marks, closed = [], Marks(data), 0
    for last, rules in _magic().iter(data.decode("latin-1")):
        for size, kind, valid in rules:
            start = last - size + 1
            if start >= closed and (length := valid(data, start, marks)):
                found.append((kind, start, length))
                if kind in OPAQUE:
                    closed = start + length
    return sorted(found, key=lambda x: (x[1], -x[2]))


def own_type(data: bytes, found: list[tuple[str, int, int]]) -> str:
    """The type of the object at byte 0 that covers the value but for padding."""
    return next((kind for kind, start, length in found if start == 0 and not data[length:].strip(PADDING)), UNKNOWN)


def examine(data: bytes, declared: str | None) -> tuple[str, bool, list[tuple[str, int, int, bytes | None]]]:
    """(type, whether the declared one was wrong, carved objects (type, start, length, content)).

    Objects inside a carved one have no content of their own: it is in the
    outer one's, so what is carved is at most the value once more.
    """
    found = sniff(data)
    kind, done, carved = own_type(data, found), 0, []
    for k, s, n in found:
        if s or data[n:].strip(PADDING):
            carved.append((k, s, n, data[s : s + n] if s + n > done else None))
            done = max(done, s + n)
    return kind, declared != kind, carved


def inspect_media(df: DataFrame, id_col: str, bytes_col: str, declared_col: str) -> DataFrame:
    """doc_id, declared, media_type, corrected, and carved: [(type, start, length, content)] of a binary column (see examine()).

    Null or empty bytes: unknown type, nothing carved. A null declared type counts as wrong.
    Rows are judged alone: ties and repeated rows give repeated rows.
    """
    own = df.select(whole_id(df, id_col).alias("doc_id"), df[bytes_col].cast("binary").alias("text"), df[declared_col].cast("string").alias("declared"))

    def run(batches):
        import pyarrow as pa

        kinds = pa.list_(pa.struct([("type", pa.string()), ("start", pa.int64()), ("length", pa.int64()), ("content", pa.binary())]))
        for whole in batches:
            for at in range(0, whole.num_rows, 64):
                part = whole.slice(at, 64)
                declared = part.column("declared")
                types, wrong, objects = zip(*(examine(d or b"", said) for d, said in zip(part.column("text").to_pylist(), declared.to_pylist(), strict=True)), strict=True)
                carved = [[dict(zip(("type", "start", "length", "content"), x, strict=True)) for x in own] for own in objects]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), declared, pa.array(types, pa.string()), pa.array(wrong, pa.bool_()), pa.array(carved, kinds)], names=["doc_id", "declared", "media_type", "corrected", "carved"])

    return own.mapInArrow(run, "doc_id bigint, declared string, media_type string, corrected boolean, carved array<struct<type:string,start:bigint,length:bigint,content:binary>>")


UNIT = 576
#: What the stored form of a text is declared as before it is examined.
DECLARED = "text/plain"


def payload_of(raw: bytes) -> bytes:
    return raw + b"\xff" * (max(1, -(-len(raw) // UNIT)) * UNIT - len(raw))


def as_wav(payload: bytes, rate: int = 8000) -> bytes:
    """A mono PCM file of unsigned 8-bit samples."""
    head = struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(payload) + len(payload) % 2, b"WAVE", b"fmt ", 16, 1, 1, rate, rate, 1, 8, b"data", len(payload))
    return head + payload + b"\0" * (len(payload) % 2)


def store_texts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each text's bytes as the samples of a sound file that is declared as the text it holds, examined and read back.

    examine() corrects the declared type by the magic bytes and carves what is
    embedded; the samples are taken from where the validator found them.
    feature: corrected type, number of samples, their sum, number and bytes of
    embedded objects. Null text is empty text.
    """

    def work(raw: bytes):
        media = as_wav(payload_of(raw))
        kind, wrong, inside = examine(media, DECLARED)
        start, size = wav_samples(media)
        back = media[start : start + size]
        return (
            len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(media), hashlib.sha256(media).hexdigest(),
            f"{kind};samples={size};sum={_total(back)};embedded={len(inside)};carved={sum(len(x[3] or b'') for x in inside)};corrected={int(wrong)}",
        )

    return per_document(
        narrow(docs, id_col, text_col), work,
        "doc_id bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string",
    )


def _total(samples: bytes) -> int:
    import numpy as np

    return int(np.frombuffer(samples, np.uint8).sum(dtype=np.int64))
