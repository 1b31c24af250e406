"""Media columns: what a blob really is, by signatures, and the media embedded in it.

An Aho-Corasick automaton finds the magic bytes of all known formats in one pass. At each hit the format's validator
walks its structure and returns the true length, or nothing; a hit without valid structure is no media. A blob whose
first byte starts a valid format has that type, whatever was declared; valid media further inside are carved. Walks
that hits share are remembered for the blob, so repeated magic bytes don't make it quadratic.

Null blobs are empty. An empty or unknown blob keeps no type (``unknown``). Equal blobs give equal results. Blobs of any
length are read whole. Of two formats that begin at one place the first listed one that is valid counts. An empty table
gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
import re
import struct
import zlib
from bisect import bisect_left
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import map_columns, table
from .sharding import CRC_OF_HEX, CRC_TABLE


class Scan:
    """A blob, and what its validators remember."""

    def __init__(self, blob: bytes):
        self.blob, self.found, self.ends = blob, {}, {}

    def __len__(self) -> int:
        return len(self.blob)

    def places(self, pattern: bytes) -> list[int]:
        """Where a pattern begins, in order; searched once."""
        if pattern not in self.found:
            self.found[pattern] = [m.start() for m in re.finditer(pattern, self.blob, re.DOTALL)]
        return self.found[pattern]

    def first(self, pattern: bytes, at: int, end: int | None = None) -> int:
        """The first place from ``at`` on and before ``end``, or -1."""
        own = self.places(pattern)
        i = bisect_left(own, at)
        return own[i] if i < len(own) and (end is None or own[i] < end) else -1

    def walk(self, name: str, at: int, step: Callable[[int], tuple[bool, int]]) -> int:
        """Follows ``step`` (done, next place or result) from ``at``. Every place on the way gets the result, so a place
        is never walked from twice."""
        path, ends = [], self.ends.setdefault(name, {})
        while at not in ends:
            path.append(at)
            done, to = step(at)
            if done or to <= at:
                ends[at] = to if done else -1
                break
            at = to
        out = ends[at]
        for p in path:
            ends[p] = out
        return out


def _riff(form: bytes, needed: tuple[tuple[bytes, ...], ...]) -> Callable[[Scan, int], int]:
    """``needed``: of each group at least one chunk must be there, and not be empty."""

    def length(scan: Scan, at: int) -> int:
        blob = scan.blob
        if blob[at + 8 : at + 12] != form:
            return 0
        size = struct.unpack_from("<I", blob, at + 4)[0] + 8
        end, here, seen = at + size, at + 12, set()
        if size < 12 or end > len(blob):
            return 0
        while here + 8 <= end:
            name, n = struct.unpack_from("<4sI", blob, here)
            if here + 8 + n > end:
                return 0
            if n or name == b"data":  # a sound may be silent, but not without its format
                seen.add(blob[here + 8 : here + 12] if name == b"LIST" else name)
            here += 8 + n + n % 2
        return size if all(seen & {*group} for group in needed) and here in (end, end + 1) else 0

    return length


def _png(scan: Scan, at: int) -> int:
    blob = scan.blob

    def chunk(here: int) -> tuple[bool, int]:
        if here + 12 > len(blob):
            return True, -1
        n, name = struct.unpack_from(">I4s", blob, here)
        stop = here + 8 + n
        if stop + 4 > len(blob) or name == b"IHDR" or zlib.crc32(blob[here + 4 : stop]) != struct.unpack_from(">I", blob, stop)[0]:
            return True, -1
        return name == b"IEND", stop + 4

    here = at + 8
    if here + 25 > len(blob) or struct.unpack_from(">I4s", blob, here) != (13, b"IHDR") or zlib.crc32(blob[here + 4 : here + 21]) != struct.unpack_from(">I", blob, here + 21)[0]:
        return 0
    end = scan.walk("png", here + 25, chunk)
    return max(0, end - at)


def _gif(scan: Scan, at: int) -> int:
    blob = scan.blob
    if at + 13 > len(blob):
        return 0

    def block(here: int) -> tuple[bool, int]:
        if here >= len(blob):
            return True, -1
        return (True, here + 1) if not blob[here] else (False, here + blob[here] + 1)

    def table_size(flags: int) -> int:
        return 3 << (flags & 7) + 1 if flags & 128 else 0

    def part(here: int) -> tuple[bool, int]:
        mark = blob[here] if here < len(blob) else -1
        if mark == 0x3B:
            return True, here + 1
        if mark == 0x21:
            to = scan.walk("gif blocks", here + 2, block)
        elif mark == 0x2C and here + 10 <= len(blob):
            to = scan.walk("gif blocks", here + 11 + table_size(blob[here + 9]), block)
        else:
            return True, -1
        return (True, -1) if to < 0 else (False, to)

    end = scan.walk("gif", at + 13 + table_size(blob[at + 10]), part)
    return max(0, end - at)


#: what ends entropy-coded bytes: a marker that is neither a stuffed byte nor a restart
MARKER = rb"\xff(?=[^\x00\xd0-\xd7])"


def _jpeg(scan: Scan, at: int) -> int:
    blob = scan.blob

    def segments(scanned: bool) -> Callable[[int], tuple[bool, int]]:
        def segment(here: int) -> tuple[bool, int]:
            if here + 2 > len(blob) or blob[here] != 0xFF:
                return True, -1
            mark = blob[here + 1]
            if mark == 0xD9:
                return True, here + 2 if scanned else -1
            if mark == 0xFF:
                return False, here + 1
            if here + 4 > len(blob):
                return True, -1
            size = struct.unpack_from(">H", blob, here + 2)[0]
            if size < 2 or mark < 0xC0:
                return True, -1
            to = here + 2 + size
            if mark == 0xDA:
                to = scan.first(MARKER, to)
                if to < 0:
                    return True, -1
                return (False, to) if scanned else (True, scan.walk("jpeg scanned", to, segments(True)))
            return False, to

        return segment

    end = scan.walk("jpeg", at + 2, segments(False))
    return max(0, end - at)


def _pdf(scan: Scan, at: int) -> int:
    """Up to the last end mark: each update of a file adds a cross-reference and an end mark of its own."""
    stop = scan.first(rb"%PDF-", at + 5)
    end, here = 0, at
    while True:
        mark = scan.first(rb"%%EOF", here, None if stop < 0 else stop)
        ref = scan.first(rb"startxref", here, mark) if mark >= 0 else -1
        if ref < 0:
            return end - at if end else 0
        end = here = mark + 5


def _gzip(scan: Scan, at: int) -> int:
    blob, unpack, here = scan.blob, zlib.decompressobj(31), at
    try:
        while here < len(blob) and not unpack.eof:
            data = blob[here : here + 65536]
            while data and not unpack.eof:
                unpack.decompress(data, 1 << 20)  # bounded output: only the end of the member matters
                data = unpack.unconsumed_tail
            here += 65536
    except zlib.error:
        return 0
    return min(here, len(blob)) - at - len(unpack.unused_data) if unpack.eof else 0


def _crc_table(poly: int, bits: int) -> list[int]:
    out = []
    for i in range(256):
        v = i << bits - 8
        for _ in range(8):
            v = (v << 1 ^ (poly if v >> bits - 1 else 0)) & (1 << bits) - 1
        out.append(v)
    return out


# fixed values: the polynomials of a FLAC frame's header and of the frame, and the sizes that its codes stand for
CRC8, CRC16 = _crc_table(0x07, 8), _crc_table(0x8005, 16)
BLOCK_SIZES = {1: 192, **{i: 576 << i - 2 for i in range(2, 6)}, **{i: 256 << i - 8 for i in range(8, 16)}}


def _flac_header(blob: bytes, at: int) -> tuple[int, int]:
    """(length of a frame's header, samples in the frame), or (0, 0)."""
    if at + 6 > len(blob) or blob[at] != 0xFF or blob[at + 1] & 0xFE != 0xF8:
        return 0, 0
    size, rate, channels, depth = blob[at + 2] >> 4, blob[at + 2] & 15, blob[at + 3] >> 4, blob[at + 3] >> 1 & 7
    lead = blob[at + 4]
    more = 0 if lead < 0x80 else 7 - (lead ^ 0xFF).bit_length()  # as in UTF-8, for up to 36 bits
    if not size or rate == 15 or channels > 10 or depth == 3 or blob[at + 3] & 1 or 0x80 <= lead < 0xC0 or lead == 0xFF:
        return 0, 0
    here = at + 5 + more
    samples = BLOCK_SIZES.get(size, 0)
    if size in (6, 7):
        samples = int.from_bytes(blob[here : here + size - 5], "big") + 1
        here += size - 5
    here += {12: 1, 13: 2, 14: 2}.get(rate, 0)
    crc = 0
    for x in blob[at:here]:
        crc = CRC8[crc ^ x]
    return (here + 1 - at, samples) if here < len(blob) and blob[here] == crc else (0, 0)


def _flac(scan: Scan, at: int) -> int:
    """Metadata, then frames: one ends where its checksum comes out even and the next frame, or nothing more, follows.
    The stream's header tells how many samples there are, so the last frame is known; where it doesn't, it is the last
    that none follows."""
    blob, here, last, total = scan.blob, at + 4, False, 0
    while not last:
        if here + 4 > len(blob):
            return 0
        head = struct.unpack_from(">I", blob, here)[0]
        kind, size, last = head >> 24 & 127, head & 0xFFFFFF, bool(head >> 31)
        if here == at + 4:
            if kind != 0 or size != 34 or here + 38 > len(blob):
                return 0
            total = int.from_bytes(blob[here + 17 : here + 22], "big") & (1 << 36) - 1
            least = int.from_bytes(blob[here + 8 : here + 11], "big")
        here += 4 + size
    if here > len(blob):
        return 0

    def frame(start: int) -> tuple[int, int]:
        """(end, samples) of the frame at ``start``, or (0, 0); remembered, as walks may meet."""
        known = scan.ends.setdefault("flac", {})
        if start not in known:
            known[start] = (0, 0)
            length, samples = _flac_header(blob, start)
            crc = 0
            for i in range(start, len(blob) if length else start):
                crc = CRC16[crc >> 8 ^ blob[i]] ^ crc << 8 & 0xFFFF
                if not crc and i + 1 - start >= max(length + 3, least) and (_flac_header(blob, i + 1)[0] or i + 1 == len(blob) or done + samples == total or not total):
                    known[start] = (i + 1, samples)
                    break
        return known[start]

    done = 0
    while done < total or not total:
        end, samples = frame(here)
        if not end:
            break
        here, done = end, done + samples
    return here - at if done >= total else 0


#: (magic bytes, type, validator); the magic stands at the medium's first byte
FORMATS: list[tuple[bytes, str, Callable[[Scan, int], int]]] = [
    (b"\x89PNG\r\n\x1a\n", "png", _png),
    (b"GIF87a", "gif", _gif),
    (b"GIF89a", "gif", _gif),
    (b"\xff\xd8\xff", "jpeg", _jpeg),
    (b"%PDF-", "pdf", _pdf),
    (b"\x1f\x8b\x08", "gzip", _gzip),
    (b"fLaC", "flac", _flac),
    (b"RIFF", "wav", _riff(b"WAVE", ((b"fmt ",), (b"data",)))),
    (b"RIFF", "webp", _riff(b"WEBP", ((b"VP8 ", b"VP8L", b"VP8X"),))),
    (b"RIFF", "avi", _riff(b"AVI ", ((b"hdrl",), (b"movi",)))),
]

_AUTOMATON = None


def _automaton():
    global _AUTOMATON
    if _AUTOMATON is None:
        import ahocorasick

        _AUTOMATON = ahocorasick.Automaton()
        for magic in {m for m, _, _ in FORMATS}:
            _AUTOMATON.add_word(magic.decode("latin-1"), magic)
        _AUTOMATON.make_automaton()
    return _AUTOMATON


def sniff(blob: bytes | None) -> tuple[str, int, list[tuple[str, int, int]]]:
    """(type, its length, [(type, offset, length) of each embedded medium]); outermost media only, in order."""
    blob = blob or b""
    kind, size, inside, free, scan = "unknown", 0, [], 0, Scan(blob)
    for last, magic in _automaton().iter(blob.decode("latin-1")):
        at = last - len(magic) + 1
        if at < free:
            continue
        for m, name, validate in FORMATS:
            if m == magic and (n := validate(scan, at)):
                if at == 0:
                    kind, size, free = name, n, 1  # what it holds is searched too
                else:
                    inside.append((name, at, n))
                    free = at + n
                break
    return kind, size, inside


def corrected(declared: str | None, kind: str) -> bool:
    """Whether a declared type was wrong; one that wasn't declared isn't."""
    return declared is not None and declared != kind


def sniff_column(rows: DataFrame, key: str, blob: str, declared: str | None = None) -> DataFrame:
    """key, media_type, media_length, corrected (the declared type was wrong), embedded (array of type, position, length)."""
    embedded = pa.list_(pa.struct([("kind", pa.string()), ("position", pa.int64()), ("length", pa.int64())]))

    def run(ids, blobs, *types):
        found = [sniff(b) for b in blobs.to_pylist()]
        said = types[0].to_pylist() if types else [None] * len(found)
        wrong = [corrected(s, k) for (k, _, _), s in zip(found, said, strict=True)]
        parts = [[{"kind": k, "position": a, "length": n} for k, a, n in inside] for _, _, inside in found]
        return [ids, [k for k, _, _ in found], [n for _, n, _ in found], wrong, pa.array(parts, embedded)]

    kind = rows.schema[key].dataType.simpleString()
    schema = f"{key} {kind}, media_type string, media_length long, corrected boolean, embedded array<struct<kind:string,position:bigint,length:bigint>>"
    return map_columns(rows, run, schema, [key, blob, *([declared] if declared else [])])


RATE = 8000


def to_wav(samples: bytes) -> bytes:
    """One channel of unsigned 8-bit samples."""
    pad = b"\0" * (len(samples) % 2)
    fmt = struct.pack("<4sIHHIIHH", b"fmt ", 16, 1, 1, RATE, RATE, 1, 8)
    data = struct.pack("<4sI", b"data", len(samples)) + samples + pad
    return struct.pack("<4sI4s", b"RIFF", 4 + len(fmt) + len(data), b"WAVE") + fmt + data


def wav_samples(blob: bytes) -> tuple[dict[str, int], bytes]:
    """The format's fields and the samples of a valid WAV blob."""
    here, fields, samples = 12, {}, b""
    while here + 8 <= len(blob):
        name, n = struct.unpack_from("<4sI", blob, here)
        if name == b"fmt ":
            _, channels, rate, _, _, bits = struct.unpack_from("<HHIIHH", blob, here + 8)
            fields = {"channels": channels, "rate": rate, "bits": bits}
        elif name == b"data":
            samples = blob[here + 8 : here + 8 + n]
        here += 8 + n + n % 2
    return fields, samples


def store_texts(rows: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key and ``media``: the text's bytes as 8-bit sound, filled with zeros to a positive multiple of 64."""
    kind = rows.schema[key].dataType.simpleString()
    return map_columns(rows, lambda ids, texts: [ids, [to_wav(padded((t or "").encode())) for t in texts.to_pylist()]], f"{key} {kind}, media binary", [key, text])


def padded(raw: bytes) -> bytes:
    return raw + b"\0" * (64 - len(raw) % 64 if len(raw) % 64 or not raw else 0)


def op6_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's text stored as sound that is declared to be text; the type is corrected by sniffing, and the stored
    bytes are read back by what they are and digested."""

    def run(ids, texts):
        out = []
        for t in texts.to_pylist():
            raw = (t or "").encode()
            media = to_wav(padded(raw))
            kind, size, inside = sniff(media)
            fields, back = wav_samples(media[:size]) if kind == "wav" else ({}, media)
            feature = f"{kind} {fields.get('bits', 0)} bits {fields.get('channels', 0)} channel {fields.get('rate', 0)} Hz; {len(back)} frames; embedded: " + (",".join(f"{k}@{a}+{n}" for k, a, n in inside) or "none")
            out.append((len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature, kind, corrected("text", kind)))
        return [ids, *map(list, zip(*out, strict=True))]

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, media_type string, corrected boolean"
    return map_columns(table(spark, sf_dir, "documents"), run, schema, ["doc_id", "text"])


def _oracle() -> str:
    """Texts that hold no media themselves, as all of documents."""
    le = lambda v: f"(SELECT string_agg(lpad(hex(({v} >> (8 * i)) & 255), 2, '0'), '' ORDER BY i) FROM range(4) r(i))"
    fmt = struct.pack("<4sIHHIIHH", b"fmt ", 16, 1, 1, RATE, RATE, 1, 8).hex().upper()
    return f"""WITH b AS (SELECT doc_id, encode(coalesce(text, '')) AS raw FROM documents),
  z AS (SELECT doc_id, octet_length(raw) AS n, hex(raw) AS h, greatest(1, (octet_length(raw) + 63) // 64) * 64 AS m FROM b),
  p AS (SELECT doc_id, n, m, rpad(h, (2 * m)::INT, '0') AS h FROM z),
  w AS (SELECT *, '52494646' || {le('(m + 36)')} || '57415645{fmt}64617461' || {le('m')} || h AS media FROM p),
  tab AS ({CRC_TABLE}),
  c AS (SELECT *, right(h, 128) AS tail FROM w),
  k AS (SELECT tail, {CRC_OF_HEX.replace("length(h)", "length(tail)").replace("substr(h,", "substr(tail,")} AS crc FROM (SELECT DISTINCT tail FROM c) x, tab)
SELECT doc_id, n::BIGINT AS n_bytes, m::BIGINT AS payload_bytes, sha256(unhex(h)) AS payload_sha256, k.crc::BIGINT AS tail_crc32, (m + 44)::BIGINT AS media_bytes, sha256(unhex(media)) AS media_sha256,
  'wav 8 bits 1 channel {RATE} Hz; ' || m || ' frames; embedded: none' AS feature, 'wav' AS media_type, true AS corrected FROM c JOIN k ON k.tail = c.tail"""


QUERIES = {"op6_media": op6_media}
ORACLE = {"op6_media": _oracle()}
