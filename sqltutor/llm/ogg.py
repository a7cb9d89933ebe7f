"""Ogg media columns: pages with checksums, packets laced over pages, several logical streams, granule positions.

Writer and reader are general (any packets, any number of streams); ``media_of`` stores a text's bytes as the samples of
a mono 8-bit PCM stream beside a small comment stream, and ``features_of`` reads stored bytes back.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, text_of

FRAME, RATE, PAD = 576, 8000, 255
#: Fixed values of the Ogg page format: capture pattern, header flags, lacing limits.
CAPTURE, CONTINUED, FIRST, LAST, LACE, SEGMENTS = b"OggS", 1, 2, 4, 255, 255
PCM, NOTE = 1, 2
_HEAD = struct.Struct("<4sBBqIIIB")
_PCM_HEAD, _NOTE_HEAD = struct.Struct("<8sBBHII"), struct.Struct("<8sQ")
_TURNED = bytes(int(f"{i:08b}"[::-1], 2) for i in range(256))
_OUT = 8 << 20


class OggError(ValueError):
    pass


def page_crc(page: bytes) -> int:
    """CRC-32 with polynomial 0x04C11DB7, most significant bit first, start and final value 0.

    zlib has the same polynomial with bits mirrored, so bits are mirrored on the way in and out.
    """
    mirrored = zlib.crc32(page.translate(_TURNED), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(mirrored.to_bytes(4, "little").translate(_TURNED), "big")


@dataclass
class StreamWriter:
    """One logical stream. Packets gather until a page is full; the last page carries the end flag."""

    serial: int
    number: int = 0
    waiting: list[tuple[bytes, int]] = field(default_factory=list)

    def page(self, laces: bytes, body: bytes, granule: int, flags: int) -> bytes:
        head = _HEAD.pack(CAPTURE, 0, flags | (FIRST if self.number == 0 else 0), granule, self.serial, self.number, 0, len(laces)) + laces
        self.number += 1
        whole = head + body
        return whole[:22] + page_crc(whole).to_bytes(4, "little") + whole[26:]

    def pages(self, packets: Iterable[tuple[bytes, int]], last: bool = True) -> Iterator[bytes]:
        """``(packet, granule position after it)`` -> pages. A packet may run over as many pages as it needs."""
        laces, body, granule, carried, used = bytearray(), [], -1, False, False
        for packet, after in packets:
            used, at, left = True, 0, len(packet)
            sizes = bytes([LACE]) * (left // LACE) + bytes([left % LACE])
            while sizes:
                room = SEGMENTS - len(laces)
                if not room:
                    yield self.page(bytes(laces), b"".join(body), granule, CONTINUED if carried else 0)
                    carried, granule, body = at > 0, -1, []
                    laces.clear()
                    room = SEGMENTS
                now, sizes = sizes[:room], sizes[room:]
                laces += now
                n = sum(now)
                body.append(packet[at : at + n])
                at += n
                if not sizes:
                    granule = after
        if used or last:
            yield self.page(bytes(laces), b"".join(body), granule, (CONTINUED if carried else 0) | (LAST if last else 0))


@dataclass
class Logical:
    """What a reader knows of one logical stream."""

    packets: list[bytes] = field(default_factory=list)
    granules: list[int] = field(default_factory=list)
    pages: int = 0
    ended: bool = False
    rest: list[bytes] | None = None


def demultiplex(media: bytes) -> dict[int, Logical]:
    """Physical stream -> logical streams by serial number.

    Every page's checksum, version, sequence number, begin, continuation and end flags are verified; packets are put
    together from lacing values. ``granules`` has, per packet, the position of the page on which it ends (-1: none).
    """
    found: dict[int, Logical] = {}
    at, view = 0, memoryview(media)
    while at < len(media):
        if len(media) - at < 27:
            raise OggError("truncated page header")
        capture, version, flags, granule, serial, number, crc, n = _HEAD.unpack_from(media, at)
        if capture != CAPTURE or version:
            raise OggError(f"no page at byte {at}")
        body = at + 27 + n
        laces = media[at + 27 : body]
        end = body + sum(laces)
        if len(laces) < n or end > len(media):
            raise OggError("truncated page")
        if page_crc(b"".join((view[at : at + 22], b"\0\0\0\0", view[at + 26 : end]))) != crc:
            raise OggError(f"wrong checksum at byte {at}")
        if bool(flags & FIRST) != (serial not in found):
            raise OggError("begin flag and first page disagree")
        s = found.setdefault(serial, Logical())
        if s.ended or number != s.pages:
            raise OggError("page out of sequence")
        if bool(flags & CONTINUED) != (s.rest is not None):
            raise OggError("continuation flag and open packet disagree")
        s.pages += 1
        parts = s.rest or []
        opened = s.rest is not None
        for lace in laces:
            parts.append(media[body : body + lace])
            body += lace
            opened = lace == LACE
            if not opened:
                s.packets.append(b"".join(parts))
                s.granules.append(granule)
                parts = []
        s.rest = parts if opened else None
        s.ended = bool(flags & LAST)
        at = end
    if any(not s.ended or s.rest is not None for s in found.values()):
        raise OggError("a stream has no end")
    return found


def packet_ends(granules: list[int], frames: list[int]) -> np.ndarray:
    """Position after each packet. A page states the position after the last packet that ends on it; those before it on
    the page end earlier by the frames of the packets that follow."""
    stated, size = np.array(granules, np.int64), np.array(frames, np.int64)
    upto = np.cumsum(size)
    last = np.flatnonzero(np.append(stated[1:] != stated[:-1], True)) if len(stated) else np.zeros(0, np.int64)
    on = np.searchsorted(last, np.arange(len(stated)))
    return stated - (upto[last][on] - upto)


def pad(raw: bytes) -> bytes:
    return raw + bytes([PAD]) * (max(1, -(-len(raw) // FRAME)) * FRAME - len(raw))


def media_of(raw: bytes) -> bytes:
    """Bytes -> Ogg: both begin pages first, then audio pages, the comment page before the last of them."""
    payload = pad(raw)
    audio, note = StreamWriter(PCM), StreamWriter(NOTE)
    start = b"".join(audio.pages([(_PCM_HEAD.pack(b"PCM8mono", 8, 1, FRAME, RATE, 0), 0)], last=False))
    opening = b"".join(note.pages([(_NOTE_HEAD.pack(b"RAWBYTES", len(raw)), 0)], last=False))
    sound = list(audio.pages((payload[i : i + FRAME], i + FRAME) for i in range(0, len(payload), FRAME)))
    remark = b"".join(note.pages([(f"samples={len(payload)}".encode(), len(payload))]))
    return b"".join([start, opening, *sound[:-1], remark, sound[-1]])


def features_of(media: bytes) -> dict:
    """Stored bytes -> payload, its digests, timestamps and sound features."""
    streams = demultiplex(media)
    audio, note = streams[PCM], streams[NOTE]
    _, _, _, frame, rate, _ = _PCM_HEAD.unpack(audio.packets[0])
    n_bytes = _NOTE_HEAD.unpack(note.packets[0])[1]
    payload = b"".join(audio.packets[1:])
    if audio.granules[-1] != len(payload) or note.packets[1] != f"samples={len(payload)}".encode():
        raise OggError("granule position and samples disagree")
    ends = packet_ends(audio.granules[1:], [len(p) for p in audio.packets[1:]])
    if ends[0] != len(audio.packets[1]) or (np.diff(ends) <= 0).any():
        raise OggError("packets out of time")
    stamps = ends * 1000 // rate
    samples = np.frombuffer(payload, np.uint8)
    high = samples >= 128
    total, square = int(samples.sum(dtype=np.int64)), int((samples.astype(np.int32) ** 2).sum(dtype=np.int64))
    feature = (f"frame={frame};rate={rate};packets={len(audio.packets) - 1};pages={audio.pages};last_ms={int(stamps[-1])};times={zlib.crc32(stamps.astype("<i8").tobytes()):08x};"
               f"sum={total};energy={square};peak={int(samples.max())};crossings={int(np.count_nonzero(high[1:] != high[:-1]))}")
    return {"n_bytes": n_bytes, "payload": payload, "feature": feature}


def _store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        ids, media, held = [], [], 0
        for doc, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            ids.append(doc)
            media.append(media_of(text.as_buffer().to_pybytes() if text.is_valid else b""))
            held += len(media[-1])
            if held >= _OUT:
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(media, pa.binary())], ["doc_id", "media"])
                ids, media, held = [], [], 0
        if ids:
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(media, pa.binary())], ["doc_id", "media"])


_READ = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, error string"
_PACKETS = "doc_id long, serial long, packet long, size long, start_ms long, end_ms long"


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = []
        for doc, cell in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            media = cell.as_py()
            try:
                x = features_of(media or b"")
            except (OggError, KeyError, IndexError, struct.error) as e:
                whole = (len(media), hashlib.sha256(media).hexdigest()) if media is not None else (None, None)
                rows.append((doc, None, None, None, None, *whole, None, f"{type(e).__name__}: {e}"))
                continue
            payload = x["payload"]
            rows.append((doc, x["n_bytes"], len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]),
                         len(media), hashlib.sha256(media).hexdigest(), x["feature"], None))
        cols = list(zip(*rows, strict=True)) if rows else [[]] * 9
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)],
                                         [f.split()[0] for f in _READ.split(", ")])


def _timed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for doc, cell in zip(b.column(0).to_pylist(), b.column(1), strict=True):
            rows = []
            for serial, s in sorted(demultiplex(cell.as_py() or b"").items()):
                sizes = [len(p) for p in s.packets[1:]]
                rate = _PCM_HEAD.unpack(s.packets[0])[4] if serial == PCM else None
                ends = packet_ends(s.granules[1:], sizes) if rate else []
                rows += [(doc, serial, k + 1, n, *((int(ends[k] - n) * 1000 // rate, int(ends[k]) * 1000 // rate) if rate else (None, None))) for k, n in enumerate(sizes)]
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], [f.split()[0] for f in _PACKETS.split(", ")])


def store(docs: DataFrame) -> DataFrame:
    """``(doc_id, media binary)``: each whole text as an Ogg stream. Null and empty text: one frame of padding."""
    return docs.select("doc_id", text_of().alias("text")).mapInArrow(_store, "doc_id long, media binary")


def read_back(media: DataFrame) -> DataFrame:
    """``(doc_id, media)`` -> digests and features of what is stored. A damaged or missing stream keeps its row, with
    ``error`` and without features; all others have a null ``error``."""
    return media.select("doc_id", F.col("media")).mapInArrow(_read, _READ)


def packets(media: DataFrame) -> DataFrame:
    """One row per packet after the header of each logical stream, with its time where the stream has a rate. A damaged
    stream raises ``OggError``: filter by ``read_back``'s ``error`` first."""
    return media.select("doc_id", F.col("media")).mapInArrow(_timed, _PACKETS)


def features(docs: DataFrame) -> DataFrame:
    """One row per row of ``docs``, from streams that were written to the shared folder and read again; equal texts give
    equal values, whatever else a row holds. Empty table: no rows."""
    return read_back(Scratch(docs.sparkSession, "media").save_small(store(docs), "media"))
