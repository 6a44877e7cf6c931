"""Media columns as MPEG transport streams.

`mux` stores a payload losslessly as one private-data elementary stream: a program association table, a program
map table, and packetised elementary packets (PES) of `UNIT` payload bytes with a presentation timestamp each;
the first packet of each PES has an adaptation field with a program clock reference, and every RAP_EVERY-th is a
random-access point. Tables come again before each random-access point, so a reader can join there.
`parse` reads any transport stream: finds the tables (with their CRC), checks the continuity counters,
reassembles the elementary packets and lists timestamps and random-access points.

Null text or payload counts as empty; the payload is padded to a positive multiple of 64 bytes. Broken streams
never crash `parse`: lost sync, bad tables and counter gaps are counted in its result. Each row is treated by
itself (memory: one stream at a time), so repeated rows, empty tables and other columns need no care.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Fixed values of the transport format.
PACKET, SYNC, PAT_PID, PRIVATE = 188, 0x47, 0, 0x06
PMT_PID, DATA_PID, PROGRAM = 0x0100, 0x0101, 1
UNIT, RAP_EVERY, TICKS = 32768, 4, 3600
CRC_POLY = 0x04C11DB7


def _crc_table() -> list[int]:
    out = []
    for i in range(256):
        c = i << 24
        for _ in range(8):
            c = ((c << 1) ^ CRC_POLY if c & 0x80000000 else c << 1) & 0xFFFFFFFF
        out.append(c)
    return out


_TABLE = _crc_table()


def crc32_mpeg(data: bytes) -> int:
    c = 0xFFFFFFFF
    for b in data:
        c = ((c << 8) & 0xFFFFFFFF) ^ _TABLE[(c >> 24) ^ b]
    return c


def section_packet(pid: int, table_id: int, number: int, body: bytes) -> bytes:
    """One packet that holds one table section; its continuity counter is 0 and is set by the caller."""
    head = struct.pack(">BHHBBB", table_id, 0xB000 | (len(body) + 9), number, 0xC1, 0, 0)
    section = head + body
    section += struct.pack(">I", crc32_mpeg(section))
    return (struct.pack(">BHBB", SYNC, 0x4000 | pid, 0x10, 0) + section).ljust(PACKET, b"\xff")


PAT = section_packet(PAT_PID, 0x00, 1, struct.pack(">HH", PROGRAM, 0xE000 | PMT_PID))
PMT = section_packet(PMT_PID, 0x02, PROGRAM, struct.pack(">HH", 0xE000 | DATA_PID, 0xF000) + struct.pack(">BHH", PRIVATE, 0xE000 | DATA_PID, 0xF000))


def stamp(pts: int) -> bytes:
    return bytes([0x21 | (pts >> 29) & 0x0E, (pts >> 22) & 0xFF, 0x01 | (pts >> 14) & 0xFE, (pts >> 7) & 0xFF, 0x01 | (pts << 1) & 0xFE])


def read_stamp(b: bytes) -> int:
    return (b[0] >> 1 & 7) << 30 | b[1] << 22 | b[2] >> 1 << 15 | b[3] << 7 | b[4] >> 1


def mux(payload: bytes) -> bytes:
    out, counter, tables = [], 0, 0
    for n, at in enumerate(range(0, max(len(payload), 1), UNIT)):
        part = payload[at : at + UNIT]
        rap, pts = n % RAP_EVERY == 0, (n * TICKS) & 0x1FFFFFFFF
        if rap:
            for p in (PAT, PMT):
                out.append(p[:3] + bytes([0x10 | tables & 15]) + p[4:])
            tables += 1
        pes = struct.pack(">IHBBB", 0x000001BD, len(part) + 8, 0x84, 0x80, 5) + stamp(pts) + part
        clock = bytes([pts >> 25 & 0xFF, pts >> 17 & 0xFF, pts >> 9 & 0xFF, pts >> 1 & 0xFF, (pts & 1) << 7 | 0x7E, 0])
        first = min(len(pes), PACKET - 12)
        stuff = PACKET - 12 - first
        out.append(struct.pack(">BHBBB", SYNC, 0x4000 | DATA_PID, 0x30 | counter & 15, 7 + stuff, 0x50 if rap else 0x10) + clock + b"\xff" * stuff + pes[:first])
        counter += 1
        rest = pes[first:]
        whole = len(rest) // 184
        if whole:
            block = np.empty((whole, PACKET), np.uint8)
            block[:, 0], block[:, 1], block[:, 2] = SYNC, DATA_PID >> 8, DATA_PID & 255
            block[:, 3] = 0x10 | (counter + np.arange(whole)) & 15
            block[:, 4:] = np.frombuffer(rest, np.uint8, whole * 184).reshape(whole, 184)
            out.append(block.tobytes())
            counter += whole
        if tail := rest[whole * 184 :]:
            size = 183 - len(tail)
            field_ = b"" if size == 0 else b"\x00" + b"\xff" * (size - 1)
            out.append(struct.pack(">BHBB", SYNC, DATA_PID, 0x30 | counter & 15, size) + field_ + tail)
            counter += 1
    return b"".join(out)


@dataclass
class Stream:
    """What `parse` finds. units: (pid, pts or -1, random access, packet index, payload) of each elementary packet."""

    packets: int = 0
    lost_sync: int = 0
    bad_tables: int = 0
    gaps: int = 0
    programs: dict[int, int] = field(default_factory=dict)
    streams: dict[int, int] = field(default_factory=dict)
    units: list[tuple[int, int, bool, int, bytes]] = field(default_factory=list)

    def payload(self, pid: int | None = None) -> bytes:
        return b"".join(u[4] for u in self.units if pid is None or u[0] == pid)

    def feature(self) -> str:
        raps = [u[3] for u in self.units if u[2]]
        pts = [u[1] for u in self.units]
        return f"packets={self.packets};programs={len(self.programs)};streams={len(self.streams)};units={len(self.units)};raps={len(raps)};gaps={self.gaps};first_pts={pts[0] if pts else -1};last_pts={pts[-1] if pts else -1}"


def sections(block: bytes) -> Iterator[tuple[int, bytes]]:
    at = 1 + block[0] if block else 0
    while at + 3 <= len(block) and block[at] != 0xFF:
        size = 3 + ((block[at + 1] & 15) << 8 | block[at + 2])
        yield block[at], block[at : at + size]
        at += size


def parse(data: bytes) -> Stream:
    s, n = Stream(), len(data) // PACKET
    if n == 0:
        s.lost_sync = int(bool(data))
        return s
    grid = np.frombuffer(data, np.uint8, n * PACKET).reshape(n, PACKET)
    ok = grid[:, 0] == SYNC
    s.packets, s.lost_sync = int(ok.sum()), int((~ok).sum()) + int(len(data) % PACKET > 0)
    pid = (grid[:, 1] & 0x1F).astype(np.int32) << 8 | grid[:, 2]
    pid[~ok] = -1
    has, start, counter = (grid[:, 3] & 0x10) > 0, (grid[:, 1] & 0x40) > 0, grid[:, 3] & 15
    adapt = (grid[:, 3] & 0x20) > 0
    begin = np.where(adapt, 5 + grid[:, 4].astype(np.int32), 4)

    def table(which: int, wanted: int) -> Iterator[bytes]:
        for i in np.flatnonzero((pid == which) & has & start):
            for kind, sec in sections(data[i * PACKET + begin[i] : (i + 1) * PACKET]):
                if kind == wanted:
                    if len(sec) >= 12 and crc32_mpeg(sec) == 0:
                        yield sec
                    else:
                        s.bad_tables += 1

    done: set[bytes] = set()
    for sec in table(PAT_PID, 0x00):
        if sec not in done:
            done.add(sec)
            s.programs.update({number: where & 0x1FFF for number, where in struct.iter_unpack(">HH", sec[8 : len(sec) - 4 - (len(sec) - 12) % 4]) if number})
    for where in set(s.programs.values()):
        for sec in table(where, 0x02):
            if sec in done:
                continue
            done.add(sec)
            at = 12 + ((sec[10] & 15) << 8 | sec[11])
            while at + 5 <= len(sec) - 4:
                s.streams[(sec[at + 1] & 0x1F) << 8 | sec[at + 2]] = sec[at]
                at += 5 + ((sec[at + 3] & 15) << 8 | sec[at + 4])
    for one in sorted(s.streams):
        rows = np.flatnonzero((pid == one) & has & (begin <= PACKET))
        if not len(rows):
            continue
        s.gaps += int(((counter[rows][1:] - counter[rows][:-1]) % 16 != 1).sum())
        marks = np.flatnonzero(start[rows])
        for k, m in enumerate(marks):
            own = rows[m : marks[k + 1] if k + 1 < len(marks) else len(rows)]
            plain = begin[own] == 4
            parts, i = [], 0
            while i < len(own):
                if plain[i]:
                    j = i + int(np.argmin(plain[i:])) if not plain[i:].all() else len(own)
                    parts.append(grid[own[i:j], 4:].tobytes())
                    i = j
                else:
                    parts.append(grid[own[i], begin[own[i]] :].tobytes())
                    i += 1
            pes = b"".join(parts)
            if len(pes) < 9 or pes[:3] != b"\x00\x00\x01":
                continue
            size, skip = pes[4] << 8 | pes[5], 9 + pes[8]
            pts = read_stamp(pes[9:14]) if pes[7] & 0x80 and len(pes) >= 14 else -1
            i = own[0]
            rap = bool(adapt[i] and grid[i, 4] > 0 and grid[i, 5] & 0x40)
            s.units.append((one, pts, rap, int(i), pes[skip : 6 + size] if size else pes[skip:]))
    return s


def pad(data: bytes) -> bytes:
    return data.ljust(max(64, -(-len(data) // 64) * 64), b"\x00")


def stored(docs: DataFrame, key: str = "doc_id", text: str = "text", with_media: bool = True) -> DataFrame:
    """Per row: key, n_bytes, the stream `media` (or only its digests), what is read back, and its index.

    pts: timestamps; raps: byte offset of each random-access packet in the stream."""
    kinds = "n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, pts array<long>, raps array<long>"
    schema = f"{key} {dict(docs.dtypes)[key]}, {kinds}" + ", media binary" * with_media

    def run(batches):
        for batch in batches:
            rows = []
            for text_ in batch.column(1):
                raw = (text_.as_py() or "").encode("utf-8", "surrogatepass")
                media = mux(pad(raw))
                s = parse(media)
                back = s.payload()
                rows.append((len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), s.feature(), [u[1] for u in s.units], [u[3] * PACKET for u in s.units if u[2]], media)[: 10 if with_media else 9])
            columns = list(zip(*rows, strict=True)) if rows else [[] for _ in range(9 + with_media)]
            types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, t) for c, t in zip(columns, types, strict=False)]], [key, *[f.split()[0] for f in kinds.split(", ")], "media"][: 10 + with_media])

    return docs.select(F.col(key), F.col(text)).mapInArrow(run, schema)


def op7_media_columns(spark, sf_dir: str) -> DataFrame:
    return stored(spark.read.parquet(f"{sf_dir}/documents.parquet"), with_media=False)
