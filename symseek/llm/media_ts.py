"""Payloads in MPEG transport streams (ISO/IEC 13818-1): a writer and a reader for binary columns.

Written: one program association table, one program map table, then packetised elementary stream (PES)
packets of one private stream. A PES packet carries up to 32 units of 576 payload bytes, a presentation
timestamp (90 kHz, one unit per 1/25 s) and, in its first transport packet, the random-access flag.
The last transport packet of a PES packet is filled up by an adaptation field, so payload bytes aren't touched.

Read: the reader looks for the program tables and checks their checksums, follows the program's stream, checks
the continuity counter of each packet, reassembles the PES packets, and returns payload, timestamps and the
byte offsets of random-access points. A lost or repeated packet shows as a continuity error.

Defined results: a null text is an empty one; an empty payload is padded to one unit; equal texts give equal
streams, as nothing but the payload enters; malformed streams (bad sync bytes or tables, or wrong lengths without a continuity error) raise ValueError.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from symseek.llm.common import column_of, map_texts, records

UNIT = 576
UNITS_PER_PES = 32
# Fixed values of the format.
PACKET, SYNC, PROGRAM_PID, MAP_PID, STREAM_PID, STREAM_TYPE, STREAM_ID, CLOCK = 188, 0x47, 0x0000, 0x1000, 0x0100, 0x06, 0xBD, 90_000
_TICKS = CLOCK // 25
_BODY = PACKET - 4


def padded(text: bytes) -> bytes:
    """The text with bytes 255 up to a positive multiple of the unit."""
    return text + b"\xff" * (max(1, -(-len(text) // UNIT)) * UNIT - len(text))


def table_checksum(data: bytes) -> int:
    """CRC-32 of program tables: polynomial 0x04C11DB7, most significant bit first, all ones at the start, no inversion."""
    crc = 0xFFFFFFFF
    for byte in data:
        crc ^= byte << 24
        for _ in range(8):
            crc = (crc << 1 ^ 0x04C11DB7 if crc & 0x80000000 else crc << 1) & 0xFFFFFFFF
    return crc


def _table_packet(pid: int, table_id: int, body: bytes) -> bytes:
    head = bytes([table_id]) + struct.pack(">H", 0xB000 | len(body) + 9) + struct.pack(">HBBB", 1, 0xC1, 0, 0)
    section = head + body
    section += struct.pack(">I", table_checksum(section))
    return (struct.pack(">BHB", SYNC, 0x4000 | pid, 0x10) + b"\0" + section).ljust(PACKET, b"\xff")


_TABLES = _table_packet(PROGRAM_PID, 0, struct.pack(">HH", 1, 0xE000 | MAP_PID)) + _table_packet(
    MAP_PID, 2, struct.pack(">HHBHH", 0xE000 | STREAM_PID, 0xF000, STREAM_TYPE, 0xE000 | STREAM_PID, 0xF000)
)


def _stamp(ticks: int) -> bytes:
    """33 bits of a timestamp with their marker bits."""
    return struct.pack(">BHH", 0x21 | ticks >> 29 & 0x0E, ticks >> 14 & 0xFFFE | 1, ticks << 1 & 0xFFFE | 1)


def mux(payload: bytes) -> bytes:
    """A transport stream with the payload, whose length is a positive multiple of the unit."""
    out = [_TABLES]
    counter = 0
    for at in range(0, len(payload), UNIT * UNITS_PER_PES):
        body = payload[at : at + UNIT * UNITS_PER_PES]
        pes = struct.pack(">IHBBB", 0x100 | STREAM_ID, len(body) + 8, 0x84, 0x80, 5) + _stamp(at // UNIT * _TICKS & 0x1FFFFFFFF) + body
        # The first packet has a 2-byte adaptation field with the random-access flag, and 182 bytes of the PES packet.
        whole, rest = divmod(len(pes) - 182, _BODY)
        packets = np.empty((whole + 1, PACKET), np.uint8)
        packets[:, 0], packets[:, 1], packets[:, 2] = SYNC, STREAM_PID >> 8, STREAM_PID & 0xFF
        packets[:, 3] = 0x10 | (counter + np.arange(whole + 1)) % 16
        packets[0, 1] |= 0x40
        packets[0, 3] |= 0x20
        packets[0, 4:6] = 1, 0x40
        data = np.frombuffer(pes, np.uint8)
        packets[0, 6:] = data[:182]
        packets[1:, 4:] = data[182 : 182 + whole * _BODY].reshape(whole, _BODY)
        out.append(packets.tobytes())
        counter += whole + 1
        if rest:
            room = _BODY - rest - 1  # after the field's length byte
            field = bytes([room]) + (b"\0" + b"\xff" * (room - 1) if room else b"")
            out.append(struct.pack(">BHB", SYNC, STREAM_PID, 0x30 | counter % 16) + field + pes[-rest:])
            counter += 1
    return b"".join(out)


@dataclass
class Reading:
    payload: bytes
    timestamps: list[int]
    random_access: list[int]  # byte offsets of packets where decoding may begin
    packets: int
    continuity_errors: int


@lru_cache(maxsize=64)
def _section(packet: bytes, table_id: int) -> bytes:
    """A program table's body, between its header and its checksum."""
    at = 5 + packet[4]
    length = (packet[at + 1] << 8 | packet[at + 2]) & 0x0FFF
    section = packet[at : at + 3 + length]
    if packet[at] != table_id or len(section) < 12 or table_checksum(section[:-4]) != int.from_bytes(section[-4:], "big"):
        raise ValueError("a program table is damaged")
    return section[8:-4]


def _stream_pid(stream: bytes, pids: np.ndarray) -> int:
    """The first program's first elementary stream, by the program tables."""
    found = np.flatnonzero(pids == PROGRAM_PID)
    if not len(found):
        raise ValueError("no program association table")
    first = stream[found[0] * PACKET : (found[0] + 1) * PACKET]
    map_pid = struct.unpack(">H", _section(first, 0)[2:4])[0] & 0x1FFF
    found = np.flatnonzero(pids == map_pid)
    if not len(found):
        raise ValueError("no program map table")
    body = _section(stream[found[0] * PACKET : (found[0] + 1) * PACKET], 2)
    info = struct.unpack(">H", body[2:4])[0] & 0x0FFF
    return struct.unpack(">H", body[5 + info : 7 + info])[0] & 0x1FFF


def demux(stream: bytes) -> Reading:
    """What a transport stream holds."""
    if not stream or len(stream) % PACKET:
        raise ValueError("not a whole number of packets")
    rows = np.frombuffer(stream, np.uint8).reshape(-1, PACKET)
    if (rows[:, 0] != SYNC).any():
        raise ValueError("a sync byte is missing")
    pids = (rows[:, 1].astype(np.int32) & 0x1F) << 8 | rows[:, 2]
    pid = _stream_pid(stream, pids)
    own = np.flatnonzero(pids == pid)
    mine = rows[own]
    control = mine[:, 3] >> 4 & 3
    counters = mine[control & 1 == 1, 3] & 15
    errors = int(((counters[1:].astype(np.int16) - counters[:-1]) % 16 != 1).sum())
    start = np.where(control & 2, 5 + mine[:, 4].astype(np.int64), 4)
    flagged = (control & 2 > 0) & (mine[:, 4] > 0) & (mine[:, 5] & 0x40 > 0)
    begins = np.append(np.flatnonzero(mine[:, 1] & 0x40), len(mine))
    parts, stamps = [], []
    for a, b in zip(begins[:-1], begins[1:], strict=True):
        group = mine[a:b]
        if b - a > 2 and (start[a + 1 : b - 1] == 4).all():
            pes = group[0, start[a] :].tobytes() + group[1:-1, 4:].tobytes() + group[-1, start[b - 1] :].tobytes()
        else:
            pes = b"".join(group[i, start[a + i] :].tobytes() for i in range(b - a))
        length = int.from_bytes(pes[4:6], "big")
        if not errors and (pes[:3] != b"\0\0\1" or (length and len(pes) != 6 + length)):
            raise ValueError("an elementary packet is damaged")
        if pes[7] & 0x80:
            t = pes[9:14]
            stamps.append((t[0] >> 1 & 7) << 30 | t[1] << 22 | (t[2] >> 1) << 15 | t[3] << 7 | t[4] >> 1)
        parts.append(pes[9 + pes[8] :])
    return Reading(b"".join(parts), stamps, (own[flagged] * PACKET).tolist(), len(rows), errors)


def store_texts(df: DataFrame, *, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_bytes and media: the text's padded bytes as a transport stream."""

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = [(x or "").encode() for x in column_of(batch, "body").to_pylist()]
        return records(k=column_of(batch, "k"), n_bytes=pa.array([len(t) for t in texts], pa.int64()), media=pa.array([mux(padded(t)) for t in texts], pa.binary()))

    rows = df.select(F.col(key).alias("k"), F.col(text).alias("body"))
    return map_texts(rows, step, f"k {dict(rows.dtypes)['k']}, n_bytes long, media binary", text="body").withColumnRenamed("k", key)


def read_media(df: DataFrame, *, key: str = "doc_id", media: str = "media") -> DataFrame:
    """The stored streams read back: payload, timestamps, random_access, packets, continuity_errors, and digests of both byte strings. A null stream gives nulls; a damaged one raises."""
    kind = dict(df.dtypes)[key]

    def step(batch: pa.RecordBatch) -> pa.RecordBatch:
        stored = column_of(batch, media).to_pylist()
        got = [demux(m) if m is not None else None for m in stored]
        each = lambda f, kind: pa.array([f(m, r) if r is not None else None for m, r in zip(stored, got, strict=True)], kind)
        return records(
            k=column_of(batch, key),
            n_bytes=column_of(batch, "n_bytes"),
            payload=each(lambda m, r: r.payload, pa.binary()),
            timestamps=each(lambda m, r: r.timestamps, pa.list_(pa.int64())),
            random_access=each(lambda m, r: r.random_access, pa.list_(pa.int64())),
            packets=each(lambda m, r: r.packets, pa.int64()),
            continuity_errors=each(lambda m, r: r.continuity_errors, pa.int64()),
            tail_crc32=each(lambda m, r: zlib.crc32(r.payload[-32:]), pa.int64()),
            media_bytes=each(lambda m, r: len(m), pa.int64()),
            media_sha256=each(lambda m, r: hashlib.sha256(m).hexdigest(), pa.string()),
        )

    def pieces(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                yield step(batch.slice(at, 64))

    return df.select(key, "n_bytes", media).mapInArrow(pieces, f"k {kind}, n_bytes long, payload binary, timestamps array<long>, random_access array<long>, packets long, continuity_errors long, tail_crc32 long, media_bytes long, media_sha256 string").withColumnRenamed("k", key)
