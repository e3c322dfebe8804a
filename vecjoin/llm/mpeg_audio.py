"""MPEG audio columns: write, resynchronise and parse frames, tags and variable-bitrate tables.

``encode`` stores bytes losslessly as ancillary data of silent MPEG-1 Layer III frames (48 kHz, mono, CRC
protected, bitrate by need), behind an ID3v2 tag and a frame with the variable-bitrate table. ``parse`` reads
any stream of MPEG-1, 2 and 2.5 frames of Layers I to III: it finds frame headers again after junk or
damage, reads ID3v1, ID3v2, APEv2 headers and both kinds of variable-bitrate table, verifies the checksum
of each protected Layer III frame, and gives the exact duration as samples over rate and the byte offset of every
frame.

Rows: null text or audio is empty; an empty text has a payload of 192 spaces; empty or hopeless audio has no frames, zero
samples and no offsets; rows are independent, so repeats and other columns don't matter.
"""

from __future__ import annotations

import hashlib
import json
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

UNIT = 192

# Fixed values of the format: bitrates (kbit/s) by version group and layer, sampling rates (Hz) of MPEG-1.
_KBITS = {
    (1, 1): (32, 64, 96, 128, 160, 192, 224, 256, 288, 320, 352, 384, 416, 448),
    (1, 2): (32, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320, 384),
    (1, 3): (32, 40, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320),
    (2, 1): (32, 48, 56, 64, 80, 96, 112, 128, 144, 160, 176, 192, 224, 256),
    (2, 2): (8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160),
}
_RATES = (44100, 48000, 32000)


@lru_cache(maxsize=4096)
def header(word: bytes) -> tuple[int, int, int, int, int, int, bool] | None:
    """Of four bytes: version (10, 20, 25), layer, rate, frame bytes, samples, side-information bytes, protected; None if it isn't a frame header."""
    w = int.from_bytes(word, "big")
    version, layer = {3: 10, 2: 20, 0: 25}.get(w >> 19 & 3), 4 - (w >> 17 & 3)
    bits, rate, pad, mode = w >> 12 & 15, w >> 10 & 3, w >> 9 & 1, w >> 6 & 3
    if len(word) < 4 or w >> 21 != 0x7FF or version is None or layer == 4 or bits in (0, 15) or rate == 3 or w & 3 == 2:
        return None
    first = version == 10
    hz = _RATES[rate] // {10: 1, 20: 2, 25: 4}[version]
    kbit = _KBITS[(1, layer) if first else (2, 1 if layer == 1 else 2)][bits - 1]
    samples = 384 if layer == 1 else 1152 if layer == 2 or first else 576
    size = (12 * kbit * 1000 // hz + pad) * 4 if layer == 1 else samples // 8 * kbit * 1000 // hz + pad
    side = 0 if layer < 3 else (17 if mode == 3 else 32) if first else (9 if mode == 3 else 17)
    return version, layer, hz, size, samples, side, not w >> 16 & 1


def _crc_table() -> list[int]:
    table = []
    for i in range(256):
        r = i << 8
        for _ in range(8):
            r = (r << 1 ^ 0x8005) & 0xFFFF if r & 0x8000 else r << 1
        table.append(r)
    return table


_CRC = _crc_table()


@lru_cache(maxsize=4096)
def checksum(covered: bytes) -> int:
    """The frame checksum (polynomial 0x8005, from all ones) over the last header half and the side information."""
    r = 0xFFFF
    for b in covered:
        r = (r << 8 & 0xFFFF) ^ _CRC[r >> 8 ^ b]
    return r


@lru_cache(maxsize=64)
def _start(kbit_index: int) -> tuple[bytes, int]:
    """Header, checksum and empty side information of a protected mono 48 kHz frame, and what it can hold besides."""
    word = bytes((0xFF, 0xFA, kbit_index << 4 | 1 << 2, 3 << 6))
    side = bytes(17)
    return word + struct.pack(">H", checksum(word[2:] + side)) + side, header(word)[3] - 23


def _syncsafe(n: int) -> bytes:
    return bytes(n >> s & 127 for s in (21, 14, 7, 0))


def encode(payload: bytes, title: str = "payload") -> bytes:
    """A stream that holds ``payload``."""
    largest, room = _start(14)
    body, sizes, at = [], [], 0
    while at < len(payload):
        piece = payload[at : at + room]
        start, hold = next((s for s in map(_start, range(1, 15)) if s[1] >= len(piece)))
        body.append(start + piece.ljust(hold, b"\0"))
        sizes.append(len(body[-1]))
        at += len(piece)
    frames, start = len(body), _start(8)
    total = start[1] + 23 + sum(sizes)
    passed, ends = start[1] + 23, []
    for s in sizes:
        ends.append(passed)
        passed += s
    toc = bytes(min(255, 256 * ends[min(frames - 1, frames * i // 100)] // total) for i in range(100)) if frames else bytes(100)
    table = b"Xing" + struct.pack(">III", 7, frames, total) + toc
    about = f"{len(payload)}:{zlib.crc32(payload)}".encode()
    tag = b"".join(name + struct.pack(">IH", len(x) + 1, 0) + b"\3" + x for name, x in ((b"TIT2", title.encode()), (b"TXXX", b"payload\0" + about)))
    return b"ID3\4\0\0" + _syncsafe(len(tag)) + tag + start[0] + table.ljust(start[1], b"\0") + b"".join(body)


def _tags(data: bytes) -> tuple[dict[str, str], int, int]:
    """Tag texts, and the bytes where audio may begin and must end."""
    found, begin, end = {}, 0, len(data)
    while data[begin : begin + 3] == b"ID3" and len(data) >= begin + 10 and max(data[begin + 6 : begin + 10]) < 128:
        major, flags = data[begin + 3], data[begin + 5]
        size = sum(b << s for b, s in zip(data[begin + 6 : begin + 10], (21, 14, 7, 0), strict=True))
        at, stop = begin + 10, min(begin + 10 + size, end)
        while major >= 3 and at + 10 <= stop and data[at]:
            raw = data[at + 4 : at + 8]
            n = sum(b << s for b, s in zip(raw, (21, 14, 7, 0), strict=True)) if major == 4 and max(raw) < 128 else int.from_bytes(raw, "big")
            value = data[at + 10 : min(at + 10 + n, stop)]
            if data[at : at + 1] == b"T" and value:
                code = {0: "latin-1", 1: "utf-16", 2: "utf-16-be"}.get(value[0], "utf-8")
                name, text = data[at : at + 4].decode("latin-1"), value[1:].decode(code, "replace").rstrip("\0")
                if name == "TXXX" and "\0" in text:
                    name, _, text = (f"TXXX:{text.partition(chr(0))[0]}", "", text.partition("\0")[2])
                found[name] = text
            at += 10 + n
        begin = stop + (10 if flags & 16 else 0)
    if data[end - 128 : end - 125] == b"TAG" and end - 128 >= begin:
        end -= 128
        found.setdefault("ID3v1", data[end + 3 : end + 33].rstrip(b"\0 ").decode("latin-1"))
    if data[end - 32 : end - 24] == b"APETAGEX" and end - 32 >= begin:
        size, flags = int.from_bytes(data[end - 20 : end - 16], "little"), int.from_bytes(data[end - 12 : end - 8], "little")
        end = max(begin, end - size - (32 if flags >> 31 else 0))
        found["APE"] = str(size)
    return found, min(begin, end), end


def _table(frame: bytes, side: int, start: int) -> dict | None:
    """A variable-bitrate table in the first frame."""
    at = start + side
    if frame[at : at + 4] in (b"Xing", b"Info"):
        flags, at2, out = int.from_bytes(frame[at + 4 : at + 8], "big"), at + 8, {"kind": frame[at : at + 4].decode()}
        for bit, name in ((1, "frames"), (2, "bytes")):
            if flags & bit:
                out[name] = int.from_bytes(frame[at2 : at2 + 4], "big")
                at2 += 4
        if flags & 4:
            out["toc"] = list(frame[at2 : at2 + 100])
        return out
    if frame[36:40] == b"VBRI" and len(frame) >= 62:  # a shorter frame only happens to hold the mark
        size, frames = struct.unpack(">II", frame[46:54])
        entries, scale, width = struct.unpack(">HHH", frame[54:60])
        toc = [int.from_bytes(frame[62 + i * width : 62 + (i + 1) * width], "big") * scale for i in range(entries)]
        return {"kind": "VBRI", "frames": frames, "bytes": size, "toc": toc}
    return None


def parse(data: bytes) -> dict:
    """What the stream holds: tags, table, rate, samples, offsets, sizes, crc_good, crc_bad, skipped bytes, ancillary payload."""
    tags, at, end = _tags(data)
    out = {"tags": tags, "table": None, "rate": 0, "layer": 0, "samples": 0, "offsets": [], "sizes": [], "crc_good": 0, "crc_bad": 0, "skipped": 0}
    pieces, kind, found_any = [], None, False
    while at + 4 <= end:
        h = header(data[at : at + 4])
        # a header counts if the stream goes on in the same version, layer and rate, or ends, behind its frame
        if h and at + h[3] <= end and (kind is None or h[:3] == kind):
            follows = header(data[at + h[3] : at + h[3] + 4])
            sound = at + h[3] >= end - 3 or (follows is not None and follows[:3] == h[:3])
        else:
            sound = False
        if h and not sound and kind == h[:3] and at + h[3] <= end and h[6]:
            sound = checksum(data[at + 2 : at + 4] + data[at + 6 : at + 6 + h[5]]) == int.from_bytes(data[at + 4 : at + 6], "big")
        if not sound:
            ahead = data.find(b"\xff", at + 1, end)
            ahead = end if ahead < 0 else ahead
            out["skipped"] += ahead - at
            at = ahead
            continue
        kind = h[:3]
        size, start = h[3], at + (6 if h[6] else 4)
        if not found_any:
            found_any = True
            out["rate"], out["layer"] = h[2], h[1]
            out["table"] = _table(data[at : at + size], h[5], start - at)
            if out["table"]:
                at += size
                continue
        if h[6] and h[1] == 3:
            good = checksum(data[at + 2 : at + 4] + data[start : start + h[5]]) == int.from_bytes(data[at + 4 : at + 6], "big")
            out["crc_good" if good else "crc_bad"] += 1
        out["samples"] += h[4]
        out["offsets"].append(at)
        out["sizes"].append(size)
        pieces.append(data[start + h[5] : at + size])
        at += size
    out["skipped"] += max(0, end - at)
    out["ancillary"] = b"".join(pieces)
    return out


def decode(data: bytes) -> tuple[bytes, dict]:
    """The payload of a stream that ``encode`` wrote, and what ``parse`` says of it; raises ValueError if it is damaged."""
    found = parse(data)
    size, crc = map(int, found["tags"].get("TXXX:payload", "-1:0").split(":"))
    payload = found["ancillary"][: max(size, 0)]
    if len(payload) != size or zlib.crc32(payload) != crc or found["crc_bad"]:
        raise ValueError("the stream is damaged")
    return payload, found


def padded(text: bytes) -> bytes:
    return text.ljust(max(UNIT, -(-len(text) // UNIT) * UNIT), b" ")


def encode_texts(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_bytes, media: every text as audio."""

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for batch in (whole.slice(i, 1000) for i in range(0, whole.num_rows, 1000)):
                texts = [b"" if t is None else t.encode("utf-8", "surrogatepass") for t in batch.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(t) for t in texts], pa.int64()), pa.array([encode(padded(t)) for t in texts], pa.binary())], names=["doc_id", "n_bytes", "media"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(write, "doc_id long, n_bytes long, media binary")


AUDIO = "samples long, rate int, n_frames long, crc_good long, crc_bad long, skipped long, table string, tags map<string,string>, offsets array<long>"


def audio_features(audio: DataFrame, media: str = "media") -> DataFrame:
    """``audio`` with a struct column ``audio`` of what ``parse`` finds in each binary; duration is samples / rate seconds."""

    @F.pandas_udf(AUDIO)
    def look(col):
        import pandas as pd

        rows = []
        for data in col:
            p = parse(bytes(data) if data is not None else b"")
            rows.append((p["samples"], p["rate"], len(p["offsets"]), p["crc_good"], p["crc_bad"], p["skipped"], p["table"] and p["table"]["kind"], p["tags"], p["offsets"]))
        return pd.DataFrame(rows, columns=["samples", "rate", "n_frames", "crc_good", "crc_bad", "skipped", "table", "tags", "offsets"])

    return audio.withColumn("audio", look(media))


def media_digests(media: DataFrame) -> DataFrame:
    """Digests of the payload read back from ``media`` (doc_id, n_bytes, media), its durations and frame offsets."""

    def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for data in batch.column(2):
                raw = data.as_py()
                payload, p = decode(raw)
                feature = json.dumps({"samples": p["samples"], "rate": p["rate"], "frames": len(p["offsets"]), "checked": p["crc_good"], "table": p["table"]["kind"], "table_frames": p["table"]["frames"], "table_bytes": p["table"]["bytes"]}, sort_keys=True)
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(raw), hashlib.sha256(raw).hexdigest(), feature, p["samples"], p["rate"], p["offsets"]))
            cols = list(zip(*rows, strict=True)) if rows else [()] * 9
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int32(), pa.list_(pa.int64())]
            names = ["payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "duration_samples", "sample_rate", "frame_offsets"]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array(list(c), k) for c, k in zip(cols, kinds, strict=True))], names=["doc_id", "n_bytes", *names])

    return media.mapInArrow(look, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, duration_samples long, sample_rate int, frame_offsets array<long>")
