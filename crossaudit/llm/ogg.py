"""Media columns: byte payloads stored as Ogg bitstreams and read back.

The payload's bytes are 8-bit samples. Blocks of samples become packets dealt in turn to two logical streams, each
with its own header packet; pages of the streams alternate. Reading verifies every page's checksum, version and sequence number,
joins packets from lacing values (also across pages), sorts pages to their streams, and takes times from granule
positions, which count a stream's samples up to the end of the last packet that ends on a page.
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

UNIT = 192
PACKET = 5 * UNIT
RATE = 8000
SERIALS = (0x51A0, 0x51A1)
HEAD = struct.Struct("<4sBBqIIIB")
INTRO = struct.Struct("<4sIHH")
CONTINUED, FIRST, LAST = 1, 2, 4

_MIRROR = bytes(int(f"{i:08b}"[::-1], 2) for i in range(256))


class OggError(ValueError):
    """The bytes are not a well-formed stream."""


def page_checksum(page: bytes) -> int:
    """CRC-32 with polynomial 0x04C11DB7, most significant bit first, start 0, no final inversion.

    It is zlib's reflected CRC over mirrored bytes, with the start and final inversions undone and the result mirrored.
    """
    mirrored = zlib.crc32(page.translate(_MIRROR), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(mirrored.to_bytes(4, "little").translate(_MIRROR), "big")


def _page(flags: int, granule: int, serial: int, sequence: int, lacing: bytes, body: bytes) -> bytes:
    head = HEAD.pack(b"OggS", 0, flags, granule, serial, sequence, 0, len(lacing))
    page = head + lacing + body
    return page[:22] + page_checksum(page).to_bytes(4, "little") + page[26:]


def _pages(packets: list[bytes], serial: int, segments: int) -> Iterator[bytes]:
    """Header page, then data pages of up to ``segments`` lacing values; the last one carries the end mark."""
    yield _page(FIRST, 0, serial, 0, bytes([INTRO.size]), INTRO.pack(b"PCM8", RATE, 1, PACKET))
    lacing, ends, samples = bytearray(), [], 0
    for p in packets:
        lacing += b"\xff" * (len(p) // 255) + bytes([len(p) % 255])
        samples += len(p)
        ends.append((len(lacing), samples))
    body, done, sequence, at = b"".join(packets), 0, 1, 0
    for start in range(0, max(1, len(lacing)), segments):
        part = bytes(lacing[start : start + segments])
        granule = -1
        while at < len(ends) and ends[at][0] <= start + len(part):
            granule = ends[at][1]
            at += 1
        flags = CONTINUED * (start > 0 and lacing[start - 1] == 255) | LAST * (start + segments >= len(lacing))
        size = sum(part)
        yield _page(flags, granule if packets else 0, serial, sequence, part, body[done : done + size])
        done += size
        sequence += 1


def mux(payload: bytes, segments: int = 255) -> bytes:
    """The payload as one physical bitstream of two logical ones."""
    packets = [payload[i : i + PACKET] for i in range(0, len(payload), PACKET)]
    streams = [list(_pages(packets[k :: len(SERIALS)], serial, segments)) for k, serial in enumerate(SERIALS)]
    out = []
    for i in range(max(map(len, streams))):
        out += [s[i] for s in streams if i < len(s)]
    return b"".join(out)


def demux(data: bytes) -> dict[int, dict]:
    """Logical streams by serial number: ``rate``, ``packets`` and, for each page with a granule, ``(page, seconds)``.

    Raises OggError on a bad capture pattern, version, checksum, sequence, continuation or ending.
    """
    streams: dict[int, dict] = {}
    at = 0
    while at < len(data):
        if at + HEAD.size > len(data):
            raise OggError("cut page header")
        mark, version, flags, granule, serial, sequence, crc, n = HEAD.unpack_from(data, at)
        if mark != b"OggS" or version:
            raise OggError(f"no page at byte {at}")
        lacing = data[at + HEAD.size : at + HEAD.size + n]
        start = at + HEAD.size + n
        end = start + sum(lacing)
        if len(lacing) < n or end > len(data):
            raise OggError("cut page")
        if page_checksum(data[at : at + 22] + bytes(4) + data[at + 26 : end]) != crc:
            raise OggError(f"checksum of the page at byte {at}")
        if bool(flags & FIRST) == (serial in streams):
            raise OggError("stream begins twice or not at all")
        s = streams.setdefault(serial, {"packets": [], "times": [], "open": b"", "next": 0, "ended": False})
        if sequence != s["next"] or s["ended"] or bool(flags & CONTINUED) != bool(s["open"]):
            raise OggError("pages out of order")
        s["next"] += 1
        piece, pos = [s["open"]], start
        for k, v in enumerate(lacing):
            piece.append(data[pos : pos + v])
            pos += v
            if v < 255:
                s["packets"].append(b"".join(piece))
                piece = []
        s["open"] = b"".join(piece)
        s["ended"] = bool(flags & LAST)
        if granule >= 0 and not flags & FIRST:
            s["times"].append((sequence, granule))
        at = end
    for s in streams.values():
        if not s["ended"] or s["open"] or not s["packets"]:
            raise OggError("stream not ended")
        kind, rate, _, _ = INTRO.unpack(s["packets"].pop(0))
        if kind != b"PCM8":
            raise OggError("unknown stream kind")
        s["rate"] = rate
        if s["times"] and s["times"][-1][1] != sum(map(len, s["packets"])):
            raise OggError("last granule position does not match the samples")
        s["times"] = [(page, g / rate) for page, g in s["times"]]
    return streams


def payload_of(streams: dict[int, dict]) -> bytes:
    """Samples in their first order: one packet from each stream in turn."""
    parts = [streams[s]["packets"] for s in sorted(streams)]
    out = [b""] * sum(map(len, parts))
    for k, p in enumerate(parts):
        out[k :: len(parts)] = p
    return b"".join(out)


def pad(raw: bytes) -> bytes:
    """Spaces up to a positive multiple of the unit."""
    return raw + b" " * (-len(raw) % UNIT or UNIT * (not raw))


def describe(payload: bytes, streams: dict[int, dict]) -> str:
    """Level, loudness, turns through the middle, distinct values and length in time of the samples."""
    x = np.frombuffer(payload, np.uint8).astype(np.int64)
    centred = x - 128
    turns = int(np.count_nonzero((centred[1:] >= 0) != (centred[:-1] >= 0)))
    seconds = sum(s["times"][-1][1] for s in streams.values())
    return f"samples={len(x)};sum={int(x.sum())};power={int((centred * centred).sum())};turns={turns};peak={int(x.max())};low={int(x.min())};values={int(np.count_nonzero(np.bincount(x)))};seconds={seconds:.6f}"


def store(df: DataFrame, text: str = "text", media: str = "media") -> DataFrame:
    """``df`` with the binary column ``media``: ``text`` as UTF-8 (null: empty), padded and stored. Other columns stay."""
    fields = [f for f in df.schema.fields if f.name != media]
    schema = type(df.schema)(list(fields)).add(media, "binary")
    names = [f.name for f in fields]

    def run(batches):
        for b in batches:
            col = b.column(b.schema.get_field_index(text))
            made = pa.array((mux(pad((t or "").encode())) for t in col.to_pylist()), pa.binary())
            yield pa.RecordBatch.from_arrays([*(b.column(b.schema.get_field_index(n)) for n in names), made], names=[*names, media])

    return df.mapInArrow(run, schema)


DIGEST = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def read_digests(df: DataFrame, keep: list[str], media: str = "media") -> DataFrame:
    """The columns ``keep`` and the digests of the payload read back from ``media``."""
    names = [x.split()[0] for x in DIGEST.split(", ")]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields if f.name in keep) + ", " + DIGEST

    def run(batches):
        for b in batches:
            rows = []
            for m in b.column(b.schema.get_field_index(media)).to_pylist():
                streams = demux(m)
                p = payload_of(streams)
                rows.append((len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-16:]), len(m), hashlib.sha256(m).hexdigest(), describe(p, streams)))
            made = [pa.array([r[k] for r in rows], pa.int64() if k in (0, 2, 3) else pa.string()) for k in range(6)]
            kept = [n for n in b.schema.names if n in keep]
            yield pa.RecordBatch.from_arrays([*(b.column(b.schema.get_field_index(n)) for n in kept), *made], names=[*kept, *names])

    return df.select(*keep, media).mapInArrow(run, schema)


def query(spark, sf_dir):
    """op8: every document's text through the container and back."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("n_bytes"), "text")
    return read_digests(store(docs).drop("text"), ["doc_id", "n_bytes"])
