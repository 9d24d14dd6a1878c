"""Media columns: the Ogg container (RFC 3533) for 8-bit sample streams.

Writing: samples are cut into packets, packets into lacing segments and pages; two logical
streams are multiplexed, the samples and an index of packet checksums.  Reading: every page
checksum is verified, packets are put together from lacing values across page ends, logical
streams are told apart by serial number, and times come from granule positions.

Defined cases: null text is an empty text; an empty text is 192 spaces; a text of any length
is stored whole (packets span pages freely); extra columns of the input are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK, RATE, PACKET = 192, 8000, 4096
# Fixed values of the container format: capture pattern, header layout, header-type flags.
CAPTURE, HEADER = b"OggS", struct.Struct("<4sBBqIIIB")
CONTINUED, FIRST, LAST = 1, 2, 4
SAMPLES, INDEX = b"\x01pcm8", b"\x01pidx"
_FLIP = bytes(int(f"{i:08b}"[::-1], 2) for i in range(256))


class OggError(ValueError):
    pass


def page_crc(data: bytes) -> int:
    """CRC with polynomial 04c11db7, most significant bit first, start 0.

    The same polynomial runs through zlib when the bits of each byte, and of the result, are reversed.
    """
    raw = zlib.crc32(data.translate(_FLIP), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(raw.to_bytes(4, "little").translate(_FLIP), "big")


class Writer:
    """Pages of one logical stream."""

    def __init__(self, serial: int) -> None:
        self.serial, self.number = serial, 0

    def page(self, lacing: bytes, body: bytes, flags: int, granule: int) -> bytes:
        head = HEADER.pack(CAPTURE, 0, flags, granule, self.serial, self.number, 0, len(lacing)) + lacing
        self.number += 1
        whole = head + body
        return whole[:22] + struct.pack("<I", page_crc(whole)) + whole[26:]

    def pages(self, packets: list[tuple[bytes, int]], first: bool = False, last: bool = False) -> Iterator[bytes]:
        """Pages holding ``packets`` (content, granule at its end); 255 segments a page at most."""
        lacing, body, done, open_packet, flags = bytearray(), bytearray(), -1, False, FIRST * first
        for content, granule in packets:
            sizes = b"\xff" * (len(content) // 255) + bytes([len(content) % 255])
            at = used = 0
            while at < len(sizes):
                if len(lacing) == 255:
                    yield self.page(bytes(lacing), bytes(body), flags, done)
                    lacing, body, done, flags = bytearray(), bytearray(), -1, CONTINUED * open_packet
                take = sizes[at : at + 255 - len(lacing)]
                n = sum(take)
                lacing += take
                body += content[used : used + n]
                at, used = at + len(take), used + n
                open_packet = at < len(sizes)
            done = granule
        yield self.page(bytes(lacing), bytes(body), flags | LAST * last, done)


def mux(payload: bytes, rate: int = RATE, packet: int = PACKET) -> bytes:
    """Two logical streams: one with ``payload`` as 8-bit samples, one with the checksum of each packet."""
    seed = zlib.crc32(payload)
    samples, index = Writer(seed), Writer(seed ^ 0x5BD1E995)
    cut = [payload[i : i + packet] for i in range(0, len(payload), packet)]
    out = [*samples.pages([(SAMPLES + struct.pack("<IIQ", rate, packet, len(payload)), 0)], first=True)]
    out += index.pages([(INDEX + struct.pack("<IQ", len(cut), len(payload)), 0)], first=True)
    at = 0
    group = 15  # packets of 17 segments: a page is filled before the next begins
    for i in range(0, len(cut), group):
        some, end = [], i + group >= len(cut)
        sums = b""
        for p in cut[i : i + group]:
            at += len(p)
            some.append((p, at))
            sums += struct.pack("<I", zlib.crc32(p))
        out += samples.pages(some, last=end)
        out += index.pages([(sums, at)], last=end)
    return b"".join(out)


def read_pages(data: bytes, strict: bool = True) -> Iterator[tuple[int, int, int, int, bytes, bytes]]:
    """(flags, granule, serial, number, lacing, body) of each page whose checksum holds.

    Strict: a page that is damaged raises; else the search goes on at the next capture pattern.
    """
    at = 0
    while at < len(data):
        try:
            if data[at : at + 4] != CAPTURE or len(data) < at + 27:
                raise OggError(f"no page at byte {at}")
            _, version, flags, granule, serial, number, crc, n = HEADER.unpack_from(data, at)
            lacing = data[at + 27 : at + 27 + n]
            end = at + 27 + n + sum(lacing)
            if version or end > len(data):
                raise OggError(f"page at byte {at} is cut short")
            if page_crc(b"".join((data[at : at + 22], b"\0\0\0\0", data[at + 26 : end]))) != crc:
                raise OggError(f"checksum of the page at byte {at}")
        except OggError:
            if strict:
                raise
            at = data.find(CAPTURE, at + 1)
            if at < 0:
                return
            continue
        yield flags, granule, serial, number, lacing, data[at + 27 + n : end]
        at = end


def demux(data: bytes, strict: bool = True) -> dict[int, dict]:
    """Logical streams by serial: packets, the granule of each (None inside a page), first and last seen."""
    streams: dict[int, dict] = {}
    for flags, granule, serial, number, lacing, body in read_pages(data, strict):
        s = streams.setdefault(serial, {"packets": [], "granules": [], "part": None, "next": 0, "pages": 0, "ended": False, "lost": 0})
        if number != s["next"]:
            if strict:
                raise OggError(f"stream {serial}: page {number} where {s['next']} is due")
            s["lost"] += 1
            s["part"] = None
        if s["pages"] == 0 and not flags & FIRST and strict:
            raise OggError(f"stream {serial} has no first page")
        s["next"], s["pages"], s["ended"] = number + 1, s["pages"] + 1, bool(flags & LAST)
        part, skip = (s["part"] or b"", s["part"] is None) if flags & CONTINUED else (b"", False)
        at, start = 0, 0
        ends = []
        for size in lacing:
            at += size
            if size < 255:
                if not skip:
                    s["packets"].append(part + body[start:at])
                    s["granules"].append(None)
                    ends.append(len(s["packets"]) - 1)
                part, skip, start = b"", False, at
        s["part"] = part + body[start:] if lacing and lacing[-1] == 255 else None
        if granule >= 0 and ends:
            s["granules"][ends[-1]] = granule
    if strict and any(not s["ended"] or s["part"] is not None for s in streams.values()):
        raise OggError("a stream has no end")
    return streams


def read_samples(data: bytes) -> tuple[bytes, dict]:
    """The samples and what the container says of them; the index stream is checked against them."""
    streams = demux(data)
    by_kind = {s["packets"][0][:5]: s for s in streams.values()}
    main, index = by_kind[SAMPLES], by_kind[INDEX]
    rate, _, total = struct.unpack("<IIQ", main["packets"][0][5:21])
    cut = main["packets"][1:]
    payload = b"".join(cut)
    if len(payload) != total or b"".join(index["packets"][1:]) != b"".join(struct.pack("<I", zlib.crc32(p)) for p in cut):
        raise OggError("the samples differ from the index")
    stamps = [g / rate for g in main["granules"] if g is not None]
    return payload, {"streams": len(streams), "pages": sum(s["pages"] for s in streams.values()), "packets": len(cut), "rate": rate, "seconds": stamps[-1], "stamps": stamps}


def features(payload: bytes, info: dict) -> str:
    x = np.frombuffer(payload, np.uint8).astype(np.int16) - 128
    crossings = int(np.count_nonzero((x[1:] < 0) != (x[:-1] < 0)))
    rms = float(np.sqrt(np.mean(x.astype(np.float64) ** 2)))
    return f"streams={info['streams']};pages={info['pages']};packets={info['packets']};seconds={info['seconds']:.4f};mean={x.mean():.4f};rms={rms:.4f};peak={int(np.abs(x).max())};crossings={crossings}"


def to_payload(text: str | None, block: int = BLOCK) -> bytes:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return raw + b" " * (-len(raw) % block if raw else block)


_OUT = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("media", pa.binary()), ("payload", pa.binary()), ("feature", pa.string())])


def ogg_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block: int = BLOCK) -> DataFrame:
    """doc_id, n_bytes, media (an Ogg file), payload (read back from it), feature.  Map-only, one text at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1)
            rows, held = [], 0
            for doc, text in zip(ids, texts, strict=True):
                text = text.as_py()
                media = mux(to_payload(text, block))
                payload, info = read_samples(media)
                rows.append((doc.as_py(), len((text or "").encode()), media, payload, features(payload, info)))
                held += len(media) + len(payload)
                if held > 1 << 23:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _OUT, strict=True)], schema=_OUT)
                    rows, held = [], 0
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _OUT, strict=True)], schema=_OUT)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "doc_id long, n_bytes long, media binary, payload binary, feature string")


def digests(stored: DataFrame) -> DataFrame:
    return stored.select(
        "doc_id",
        "n_bytes",
        F.length("payload").cast("long").alias("payload_bytes"),
        F.sha2("payload", 256).alias("payload_sha256"),
        F.crc32(F.expr("substring(payload, -16)")).alias("tail_crc32"),
        F.length("media").cast("long").alias("media_bytes"),
        F.sha2("media", 256).alias("media_sha256"),
        "feature",
    )


def expected_row(text: str | None) -> tuple:
    """What ``digests`` has to give for a text, without the container: a check for tests."""
    p = to_payload(text)
    return len((text or "").encode()), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-16:])
