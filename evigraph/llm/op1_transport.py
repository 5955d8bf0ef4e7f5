"""MPEG transport streams as a media column.

``mux`` stores a payload as a program of one data stream: PAT and PMT sections, then elementary
packets (PES) of at most PES_BYTES, each begun by a transport packet with a random-access flag
and a clock reference, with a presentation time stamp. ``demux`` reads stored bytes: program
tables with their checksums, continuity counters of each PID, reassembled packets, time stamps and
access points. Both are plain functions on bytes; ``store`` and ``read_back`` apply them to columns.

Defined cases: null text is an empty text; an empty payload still has one padding block; equal texts give
equal streams; a damaged stream gives counts of faults and the packets that are whole, no exception; columns named like results give way to them.
"""

from __future__ import annotations

import functools
import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evigraph.llm.common import documents, free

PACKET, SYNC, BLOCK = 188, 0x47, 64
PMT_PID, DATA_PID, STREAM_TYPE, STREAM_ID = 0x1000, 0x0100, 0x06, 0xBD
PES_BYTES = 32_704  # a multiple of BLOCK whose PES length field fits 16 bits
CLOCK = 90_000
TICKS = 3_600  # 25 access units a second


@functools.cache
def _crc_table() -> list[int]:
    table = []
    for i in range(256):
        c = i << 24
        for _ in range(8):
            c = (c << 1) ^ (0x04C11DB7 if c & 0x80000000 else 0)
        table.append(c & 0xFFFFFFFF)
    return table


def section_crc(data: bytes) -> int:
    """CRC-32/MPEG-2, as the program tables carry it."""
    c = 0xFFFFFFFF
    for b in data:
        c = ((c << 8) & 0xFFFFFFFF) ^ _crc_table()[(c >> 24) ^ b]
    return c


def _section(table: int, ident: int, body: bytes) -> bytes:
    head = struct.pack(">BHHBBB", table, 0xB000 | (len(body) + 9), ident, 0xC1, 0, 0) + body
    return head + struct.pack(">I", section_crc(head))


@functools.cache
def _tables() -> bytes:
    def packet(pid: int, section: bytes) -> bytes:
        return (struct.pack(">BHBB", SYNC, 0x4000 | pid, 0x10, 0) + section).ljust(PACKET, b"\xff")

    pat = _section(0, 1, struct.pack(">HH", 1, 0xE000 | PMT_PID))
    pmt = _section(2, 1, struct.pack(">HHBHH", 0xE000 | DATA_PID, 0xF000, STREAM_TYPE, 0xE000 | DATA_PID, 0xF000))
    return packet(0, pat) + packet(PMT_PID, pmt)


def _stamp(ticks: int) -> bytes:
    t = ticks & 0x1FFFFFFFF
    return struct.pack(">BHH", 0x21 | (t >> 29) & 0x0E, (t >> 14) & 0xFFFE | 1, (t << 1) & 0xFFFE | 1)


def _clock(ticks: int) -> bytes:
    return ((ticks & 0x1FFFFFFFF) << 15 | 0x7E00).to_bytes(6, "big")


def mux(payload: bytes) -> bytes:
    """Transport stream of a payload; packets of one PES are laid out as a matrix, not one by one."""
    out, counter = [_tables()], 0
    for unit, at in enumerate(range(0, max(1, len(payload)), PES_BYTES)):
        body = payload[at : at + PES_BYTES]
        ticks = unit * TICKS
        pes = struct.pack(">IHBBB", 0x100 | STREAM_ID, len(body) + 8, 0x84, 0x80, 5) + _stamp(ticks) + body
        # First packet: adaptation field of 7 bytes (flags, clock) and stuffing if all fits in it.
        first = min(len(pes), PACKET - 4 - 8)
        rest = len(pes) - first
        full, last = divmod(rest, PACKET - 4)
        n = 1 + full + (last > 0)
        m = np.full((n, PACKET), 0xFF, np.uint8)
        m[:, 0], m[:, 1], m[:, 2] = SYNC, DATA_PID >> 8, DATA_PID & 0xFF
        m[:, 3] = 0x10 | (counter + np.arange(n)) & 15
        counter = (counter + n) & 15
        data = np.frombuffer(pes, np.uint8)
        m[0, 1] |= 0x40
        m[0, 3] |= 0x20
        m[0, 4] = PACKET - 5 - first
        m[0, 5:12] = np.frombuffer(b"\x50" + _clock(ticks), np.uint8)
        m[0, PACKET - first :] = data[:first]
        if full:
            m[1 : 1 + full, 4:] = data[first : first + full * (PACKET - 4)].reshape(full, PACKET - 4)
        if last:
            pad = PACKET - 4 - last
            m[-1, 3] |= 0x20
            m[-1, 4] = pad - 1
            if pad > 1:
                m[-1, 5] = 0
            m[-1, 4 + pad :] = data[len(data) - last :]
        out.append(m.tobytes())
    return b"".join(out)


def _read_stamp(b: bytes) -> int:
    return (b[0] >> 1 & 7) << 30 | (b[1] << 7 | b[2] >> 1) << 15 | b[3] << 7 | b[4] >> 1


def _packets(stream: bytes) -> tuple[np.ndarray, np.ndarray, int]:
    """Packets as rows, their offsets, and losses of sync: after one, packets go on where two sync bytes stand a packet apart."""
    a, n = np.frombuffer(stream, np.uint8), len(stream) // PACKET
    m = a[: n * PACKET].reshape(n, PACKET)
    if len(stream) % PACKET == 0 and (m[:, 0] == SYNC).all():
        return m, np.arange(n) * PACKET, 0
    at, offsets, lost = 0, [], 0
    marks = np.flatnonzero(a == SYNC)
    sync = np.zeros(len(a) + 2 * PACKET, bool)
    sync[marks], sync[len(a) :] = True, True
    good = marks[sync[marks + PACKET]]
    while at + PACKET <= len(a):
        if sync[at]:
            offsets.append(at)
            at += PACKET
            continue
        lost += 1
        k = np.searchsorted(good, at)
        at = int(good[k]) if k < len(good) else len(a)
    lost += at < len(a)
    where = np.array(offsets, np.int64)
    return a[where[:, None] + np.arange(PACKET)], where, lost


def demux(stream: bytes) -> dict:
    """Payload, access units and faults of a stored stream."""
    got = {"packets": 0, "sync_faults": 0, "counter_faults": 0, "table_faults": 0, "programs": {}, "streams": {}, "units": [], "access_points": [], "payload": b""}
    m, where, got["sync_faults"] = _packets(stream)
    got["packets"] = len(m)
    if not len(m):
        return got
    pid = (m[:, 1].astype(np.int32) & 0x1F) << 8 | m[:, 2]
    has, field = (m[:, 3] & 0x10) > 0, (m[:, 3] & 0x20) > 0
    offset = np.where(field, 5 + m[:, 4].astype(np.int32), 4)

    def sections(table_pid: int) -> Iterator[bytes]:
        """Whole sections of a table, which may go over several packets or share one; faults are counted."""
        held = b""

        def whole(data: bytes) -> Iterator[bytes]:
            while len(data) >= 3 and data[0] != 0xFF:
                size = 3 + (int.from_bytes(data[1:3], "big") & 0xFFF)
                if size > len(data):
                    break
                if size < 12 or section_crc(data[:size]):
                    got["table_faults"] += 1
                else:
                    yield data[:size]
                data = data[size:]
            return data if data[:1] != b"\xff" else b""

        for row in np.flatnonzero((pid == table_pid) & has):
            b = m[row].tobytes()[offset[row] :]
            if start[row] and b:
                if held:  # what stands before the pointer ends the section under way
                    if (yield from whole(held + b[1 : 1 + b[0]])):
                        got["table_faults"] += 1
                held = yield from whole(b[1 + b[0] :])
            elif held:
                held = yield from whole(held + b)
        got["table_faults"] += bool(held)

    start = (m[:, 1] & 0x40) > 0
    for b in sections(0):
        for i in range(8, len(b) - 4, 4):
            got["programs"][int.from_bytes(b[i : i + 2], "big")] = int.from_bytes(b[i + 2 : i + 4], "big") & 0x1FFF
    for table_pid in sorted(set(got["programs"].values())):
        for b in sections(table_pid):
            i = 12 + (int.from_bytes(b[10:12], "big") & 0xFFF)
            while i + 5 <= len(b) - 4:
                got["streams"][int.from_bytes(b[i + 1 : i + 3], "big") & 0x1FFF] = b[i]
                i += 5 + (int.from_bytes(b[i + 3 : i + 5], "big") & 0xFFF)
    parts = []
    for data_pid in sorted(got["streams"]):
        rows = np.flatnonzero((pid == data_pid) & has)
        count = m[rows, 3] & 15
        got["counter_faults"] += int(((np.diff(count.astype(np.int16)) & 15) != 1).sum())
        heads = np.flatnonzero(start[rows])
        for a, z in zip(heads, [*heads, len(rows)][1:], strict=True):
            own = rows[a:z]
            plain = m[own, 4:]
            keep = np.arange(4, PACKET) >= offset[own][:, None]
            pes = plain[keep].tobytes()
            if len(pes) < 9 or pes[:3] != b"\0\0\1":
                got["sync_faults"] += 1
                continue
            size, head = int.from_bytes(pes[4:6], "big"), 9 + pes[8]
            body = pes[head : 6 + size] if size else pes[head:]
            pts = _read_stamp(pes[9:14]) if pes[7] & 0x80 else None
            access = bool(field[own[0]] and m[own[0], 4] > 0 and m[own[0], 5] & 0x40)
            got["units"].append((int(own[0]), pts, len(body), access))
            if access:
                got["access_points"].append((int(where[own[0]]), pts))
            parts.append(body)
    got["payload"] = b"".join(parts)
    return got


def padded(text: str | None) -> tuple[int, bytes]:
    raw = (text or "").encode("utf-8", "surrogatepass")
    return len(raw), raw.ljust(max(BLOCK, -(-len(raw) // BLOCK) * BLOCK), b"\0")


def _with(df: DataFrame, made, names: list[str]) -> DataFrame:
    """The table with the fields of a struct as columns, in place of columns that have their names."""
    held = free(df, "_made")
    own = [c for c in df.columns if c.lower() not in names]
    return df.withColumn(held, made).select(*[F.col(f"`{c}`") for c in own], *[f"{held}.{n}" for n in names])


def store(df: DataFrame, text: str = "text") -> DataFrame:
    """Adds n_bytes and the stored stream ``media``."""

    @F.pandas_udf("n_bytes long, media binary")
    def muxed(texts: pd.Series) -> pd.DataFrame:
        rows = []
        for t in texts:
            n, payload = padded(t)
            rows.append((n, mux(payload)))
        return pd.DataFrame(rows, columns=["n_bytes", "media"])

    return _with(df, muxed(F.col(text)), ["n_bytes", "media"])


READ = (
    "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, packets long, "
    "counter_faults long, other_faults long, programs map<int,int>, units array<struct<packet:int,pts:long,bytes:int,access:boolean>>"
)


def read_back(df: DataFrame, media: str = "media") -> DataFrame:
    """Adds what the stored stream holds: checksums, faults, program map and time-stamped access units."""

    @F.pandas_udf(READ)
    def read(streams: pd.Series) -> pd.DataFrame:
        rows = []
        for s in streams:
            s = bytes(s or b"")
            d = demux(s)
            p = d["payload"]
            rows.append((
                len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-BLOCK:]), len(s), hashlib.sha256(s).hexdigest(), d["packets"],
                d["counter_faults"], d["sync_faults"] + d["table_faults"], d["programs"],
                [{"packet": a, "pts": b, "bytes": c, "access": e} for a, b, c, e in d["units"]],
            ))
        return pd.DataFrame(rows, columns=[x.split()[0] for x in READ.replace("<packet:int,pts:long,bytes:int,access:boolean>", "").replace("map<int,int>", "map").split(", ")])

    return _with(df, read(F.col(media)), [f.name for f in read.returnType.fields])


def op1_transport_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text stored as a transport stream and read back."""
    out = read_back(store(documents(spark, sf_dir).select("doc_id", "text")).drop("text"))
    access = F.filter("units", lambda u: u["access"])
    seconds = F.coalesce(F.array_max(F.transform("units", lambda u: u["pts"])), F.lit(0)) / CLOCK
    return out.select(
        "doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256",
        F.concat_ws(
            ";",
            F.concat(F.lit("programs="), F.to_json("programs")),
            F.concat(F.lit("packets="), "packets"),
            F.concat(F.lit("units="), F.size("units")),
            F.concat(F.lit("access="), F.size(access)),
            F.concat(F.lit("last="), F.format_string("%.2f", seconds)),
            F.concat(F.lit("counter_faults="), "counter_faults"),
            F.concat(F.lit("other_faults="), "other_faults"),
        ).alias("feature"),
        F.transform(access, lambda u: F.struct((u["packet"] * PACKET).alias("offset"), u["pts"].alias("pts"))).alias("access_points"),
    )


QUERIES = {"op1_transport_stream": op1_transport_stream}
