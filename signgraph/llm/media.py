"""Media columns: MPEG transport streams.

A payload is cut into access units, each a packetised elementary packet with a presentation time; a program association
table and a program map table announce the stream. `mux` writes such a stream, `demux` reads any stream of 188-byte
packets: it parses the tables, checks continuity counters, reassembles the elementary packets and gives back access
units with time stamps and random-access marks. Null payloads are empty; repeated rows give repeated streams; other
columns of the input are ignored, so they may have any name.
"""
from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, text_view

PACKET, UNIT, TICK = 188, 32_000, 3_600
PMT_PID, ES_PID, PROGRAM, PRIVATE = 0x1000, 0x0101, 1, 0x06


def _crc_table() -> list[int]:
    out = []
    for byte in range(256):
        r = byte << 24
        for _ in range(8):
            r = ((r << 1) ^ (0x04C11DB7 if r & 0x80000000 else 0)) & 0xFFFFFFFF
        out.append(r)
    return out


_TABLE = _crc_table()


def crc32_mpeg(data: bytes) -> int:
    r = 0xFFFFFFFF
    for b in data:
        r = ((r << 8) & 0xFFFFFFFF) ^ _TABLE[(r >> 24) ^ b]
    return r


def _section(table_id: int, ident: int, body: bytes) -> bytes:
    head = bytes([table_id, 0xB0 | (len(body) + 9) >> 8, (len(body) + 9) & 255]) + ident.to_bytes(2, "big") + b"\xc1\x00\x00"
    return head + body + crc32_mpeg(head + body).to_bytes(4, "big")


def _table_packet(pid: int, section: bytes) -> bytes:
    return (bytes([0x47, 0x40 | pid >> 8, pid & 255, 0x10, 0]) + section).ljust(PACKET, b"\xff")


_PAT = _table_packet(0, _section(0, 1, PROGRAM.to_bytes(2, "big") + (0xE000 | PMT_PID).to_bytes(2, "big")))
_PMT = _table_packet(PMT_PID, _section(2, PROGRAM, (0xE000 | ES_PID).to_bytes(2, "big") + b"\xf0\x00" + bytes([PRIVATE]) + (0xE000 | ES_PID).to_bytes(2, "big") + b"\xf0\x00"))
_PLAIN = [bytes([0x47, ES_PID >> 8, ES_PID & 255, 0x10 | c]) for c in range(16)]
_FIELD = [bytes([0x47, ES_PID >> 8, ES_PID & 255, 0x30 | c]) for c in range(16)]
_START = [bytes([0x47, 0x40 | ES_PID >> 8, ES_PID & 255, 0x30 | c]) for c in range(16)]


def _stamp(pts: int) -> bytes:
    return bytes([0x21 | (pts >> 29) & 0x0E, (pts >> 22) & 255, 1 | (pts >> 14) & 0xFE, (pts >> 7) & 255, 1 | (pts << 1) & 0xFE])


def mux(payload: bytes) -> bytes:
    """The transport stream that holds payload; each access unit starts with a clock reference and is a random-access point."""
    out, c = [_PAT, _PMT], 0
    for k, at in enumerate(range(0, max(1, len(payload)), UNIT)):
        part = payload[at : at + UNIT]
        pts = (k + 1) * TICK & (1 << 33) - 1
        pes = b"\x00\x00\x01\xbd" + (len(part) + 8).to_bytes(2, "big") + b"\x84\x80\x05" + _stamp(pts) + part
        base = k * TICK & (1 << 33) - 1
        clock = ((base << 15) | 0x7E00).to_bytes(6, "big")
        room = 176
        fill = max(0, room - len(pes))
        out += (_START[c], bytes([7 + fill, 0x50]), clock, b"\xff" * fill, pes[: room - fill])
        c = (c + 1) & 15
        i, end = room, len(pes)
        while i + 184 <= end:
            out += (_PLAIN[c], pes[i : i + 184])
            c = (c + 1) & 15
            i += 184
        if i < end:
            gap = 184 - (end - i)
            out += (_FIELD[c], b"\x00" if gap == 1 else bytes([gap - 1, 0]) + b"\xff" * (gap - 2), pes[i:])
            c = (c + 1) & 15
    return b"".join(out)


def _psi(body: bytes, at: int) -> bytes:
    at += 1 + body[at]
    size = 3 + ((body[at + 1] & 0x0F) << 8 | body[at + 2])
    section = body[at : at + size]
    if len(section) < size or crc32_mpeg(section):
        raise ValueError("damaged section")
    return section


def demux(stream: bytes) -> dict:
    """Units [(pid, pts, random access, bytes)] in order of completion, and counts of packets, elementary packets and counter breaks."""
    if len(stream) % PACKET:
        raise ValueError("not whole packets")
    maps: set[int] = set()
    wanted: dict[int, int] = {}
    last: dict[int, int] = {}
    parts: dict[int, list] = {}
    marks: dict[int, bool] = {}
    units: list[tuple[int, int | None, bool, bytes]] = []
    breaks = 0

    def close(pid: int) -> None:
        if pid not in parts:
            return
        pes = b"".join(parts.pop(pid))
        if pes[:3] != b"\x00\x00\x01":
            raise ValueError("no start code")
        size, skip = int.from_bytes(pes[4:6], "big"), 9 + pes[8]
        pts = None
        if pes[7] & 0x80:
            p = pes[9:14]
            pts = (p[0] & 0x0E) << 29 | p[1] << 22 | (p[2] & 0xFE) << 14 | p[3] << 7 | p[4] >> 1
        units.append((pid, pts, marks.pop(pid, False), pes[skip : 6 + size] if size else pes[skip:]))

    for at in range(0, len(stream), PACKET):
        if stream[at] != 0x47:
            raise ValueError("lost sync")
        b1, b3 = stream[at + 1], stream[at + 3]
        pid = (b1 & 0x1F) << 8 | stream[at + 2]
        i, end, access = at + 4, at + PACKET, False
        if b3 & 0x20:
            n = stream[i]
            access = n > 0 and bool(stream[i + 1] & 0x40)
            i += 1 + n
        if not b3 & 0x10:
            continue
        count = b3 & 15
        if pid in last and count != (last[pid] + 1) & 15:
            if count == last[pid]:
                continue  # a repeated packet carries nothing new
            breaks += 1
        last[pid] = count
        if pid == 0 and b1 & 0x40:
            s = _psi(stream[i:end], 0)
            maps |= {int.from_bytes(s[k + 2 : k + 4], "big") & 0x1FFF for k in range(8, len(s) - 4, 4) if s[k : k + 2] != b"\x00\x00"}
        elif pid in maps and b1 & 0x40:
            s = _psi(stream[i:end], 0)
            k = 12 + ((s[10] & 15) << 8 | s[11])
            while k < len(s) - 4:
                wanted[int.from_bytes(s[k + 1 : k + 3], "big") & 0x1FFF] = s[k]
                k += 5 + ((s[k + 3] & 15) << 8 | s[k + 4])
        elif pid in wanted:
            if b1 & 0x40:
                close(pid)
                parts[pid], marks[pid] = [], access
            if pid in parts:
                parts[pid].append(stream[i:end])
    for pid in list(parts):
        close(pid)
    return {"packets": len(stream) // PACKET, "streams": sorted(wanted.items()), "units": units, "breaks": breaks}


def with_stream(df: DataFrame, id_col: str, payload_col: str) -> DataFrame:
    """(id, media): one transport stream for each payload."""

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([mux(x.as_py() or b"") for x in b.column(1)], pa.binary())], names=["id", "media"])

    src = df.select(F.col(id_col).alias("id"), F.col(payload_col).cast("binary").alias("p"))
    return src.mapInArrow(run, f"id {df.schema[id_col].dataType.simpleString()}, media binary")


def access_units(df: DataFrame, id_col: str = "id", media_col: str = "media") -> DataFrame:
    """(id, unit, pid, pts, random_access, data): the access units of each stored stream. A stream that cannot be parsed gives one
    row with unit -1 and nothing else; a null one has no units."""

    def units(m: bytes) -> list[tuple]:
        try:
            return [(k, *u) for k, u in enumerate(demux(m)["units"])]
        except (ValueError, IndexError):  # lost sync, a damaged section, a cut packet
            return [(-1, None, None, None, None)]

    def run(batches):
        for b in batches:
            rows = [(i.as_py(), *u) for i, m in zip(b.column(0), b.column(1), strict=True) for u in units(m.as_py() or b"")]
            cols = list(zip(*rows, strict=True)) or [[]] * 6
            kinds = [b.column(0).type, pa.int32(), pa.int32(), pa.int64(), pa.bool_(), pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=["id", "unit", "pid", "pts", "random_access", "data"])

    src = df.select(F.col(id_col).alias("id"), F.col(media_col).alias("m"))
    return src.mapInArrow(run, f"id {df.schema[id_col].dataType.simpleString()}, unit int, pid int, pts long, random_access boolean, data binary")


_OUT = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def _stored(batches):
    """Texts as media: (doc_id, n_bytes, media)."""
    for b in batches:
        data, offs = text_view(b.column(1))
        raw, size = data.tobytes(), np.diff(offs).tolist()
        media = [mux(raw[lo : lo + n] + bytes(-n % 64 if n else 64)) for lo, n in zip(offs[:-1].tolist(), size, strict=True)]
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array(size, pa.int64()), pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "media"])


def _digest(batches):
    for b in batches:
        rows = []
        for m in b.column(2):
            stored = m.as_py()
            back = demux(stored)
            got = b"".join(u[3] for u in back["units"])
            times = [u[1] for u in back["units"]]
            feature = f"packets={back['packets']};streams={','.join(f'{p:x}:{k:x}' for p, k in back['streams'])};units={len(times)};pts={times[0]}-{times[-1]};random={sum(u[2] for u in back['units'])};breaks={back['breaks']};largest={max(len(u[3]) for u in back['units'])}"
            rows.append((len(got), hashlib.sha256(got).hexdigest(), zlib.crc32(got[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), feature))
        cols = list(zip(*rows, strict=True)) or [[]] * 6
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *(pa.array(c, t) for c, t in zip(cols, kinds, strict=True))], names=[x.split()[0] for x in _OUT.split(", ")])


def op7_transport_stream(spark, sf_dir: str) -> DataFrame:
    """Each whole text stored in a media column, which a second pass reads back; digests of what it read."""
    media = documents(spark, sf_dir, F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_stored, "doc_id long, n_bytes long, media binary")
    return media.mapInArrow(_digest, _OUT)
