"""Media columns: MPEG transport streams (operator 1).

``mux`` stores bytes losslessly as a one-program transport stream of 188-byte packets: program
association and map tables, then elementary packets (PES) with presentation and decoding times,
clock references and random-access flags.  ``demux`` reads any such stream back: it checks sync bytes,
table checksums and continuity counters, reassembles the elementary packets and lists their
times and random-access points.

Edge cases: null or empty text is an empty payload, padded to one block of 576 bytes.  A stream whose
length is no multiple of 188, whose sync byte or table checksum is wrong, or which has no program,
gives a null payload and says so in ``error``.  Continuity gaps are counted, duplicates are skipped.
Extra columns are kept by neither; output columns are fixed.  An empty table gives an empty table.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .engine import map_batches, to_arrow_schema

PACKET, BLOCK = 188, 576
PAT_PID, PMT_PID, ES_PID, PROGRAM = 0x0000, 0x1000, 0x0101, 1
PRIVATE_STREAM, PRIVATE_TYPE = 0xBD, 0x06
UNIT_BYTES, RAP_EVERY, TICKS, FIRST_PTS = 8 * BLOCK, 8, 3600, 90_000


def _crc_table() -> list[int]:
    out = []
    for i in range(256):
        c = i << 24
        for _ in range(8):
            c = ((c << 1) ^ 0x04C11DB7) & 0xFFFFFFFF if c & 0x80000000 else (c << 1) & 0xFFFFFFFF
        out.append(c)
    return out


_CRC = _crc_table()


def section_crc(data: bytes) -> int:
    """CRC-32/MPEG-2, zero over a section with its own checksum."""
    c = 0xFFFFFFFF
    for b in data:
        c = ((c << 8) & 0xFFFFFFFF) ^ _CRC[(c >> 24) ^ b]
    return c


def _section(table_id: int, ident: int, body: bytes) -> bytes:
    head = bytes([table_id]) + (0xB000 | (len(body) + 9)).to_bytes(2, "big") + ident.to_bytes(2, "big") + b"\xc1\x00\x00"
    return head + body + section_crc(head + body).to_bytes(4, "big")


def _table_packet(pid: int, section: bytes) -> bytearray:
    p = bytearray(b"\x47" + (0x4000 | pid).to_bytes(2, "big") + b"\x10\x00" + section)
    return p + b"\xff" * (PACKET - len(p))


_PAT = _table_packet(PAT_PID, _section(0, 1, PROGRAM.to_bytes(2, "big") + (0xE000 | PMT_PID).to_bytes(2, "big")))
_PMT = _table_packet(PMT_PID, _section(2, PROGRAM, (0xE000 | ES_PID).to_bytes(2, "big") + b"\xf0\x00" + bytes([PRIVATE_TYPE]) + (0xE000 | ES_PID).to_bytes(2, "big") + b"\xf0\x00"))


def _stamp(mark: int, t: int) -> bytes:
    """A 33-bit time in five bytes with its marker bits."""
    return bytes([mark << 4 | (t >> 30 & 7) << 1 | 1, t >> 22 & 255, (t >> 15 & 127) << 1 | 1, t >> 7 & 255, (t & 127) << 1 | 1])


def _unstamp(b: bytes) -> int:
    return (b[0] >> 1 & 7) << 30 | b[1] << 22 | (b[2] >> 1) << 15 | b[3] << 7 | b[4] >> 1


def _clock(t: int) -> bytes:
    """A programme clock reference: 33-bit base of 90 kHz, extension zero."""
    return (t << 15 | 0x7E00).to_bytes(6, "big")


def mux(payload: bytes) -> bytes:
    """One transport stream that holds payload (at least one byte)."""
    out, cc, tables = [], 0, 0
    for u, at in enumerate(range(0, len(payload), UNIT_BYTES)):
        data, t, rap = payload[at : at + UNIT_BYTES], FIRST_PTS + u * TICKS, u % RAP_EVERY == 0
        if rap:
            for p in (_PAT, _PMT):
                q = bytearray(p)
                q[3] |= tables & 15
                out.append(q)
            tables += 1
        dts = t - TICKS
        pes = b"\x00\x00\x01" + bytes([PRIVATE_STREAM]) + (len(data) + 13).to_bytes(2, "big") + b"\x84\xc0\x0a" + _stamp(3, t) + _stamp(1, dts) + data
        lead = b"\x07\x50" + _clock(dts - TICKS) if rap else b""
        first = 184 - len(lead)
        rest = len(pes) - first
        count = 1 + max(0, -(-rest // 184))
        stuff = 184 * (count - 1) - rest  # of the last packet; negative never occurs as units fill a packet
        if count == 1:
            raise ValueError("a unit must fill its first packet")
        m = np.empty((count, PACKET), np.uint8)
        m[:, 0], m[:, 1], m[:, 2] = 0x47, ES_PID >> 8, ES_PID & 255
        m[0, 1] |= 0x40
        m[:, 3] = 0x10 | ((cc + np.arange(count)) & 15)
        cc += count
        if lead:
            m[0, 3] |= 0x20
            m[0, 4 : 4 + len(lead)] = np.frombuffer(lead, np.uint8)
        src = np.frombuffer(pes, np.uint8)
        m[0, 4 + len(lead) :] = src[:first]
        if count > 2:
            m[1:-1, 4:] = src[first : first + 184 * (count - 2)].reshape(-1, 184)
        tail = src[first + 184 * (count - 2) :]
        if stuff:
            m[-1, 3] |= 0x20
            m[-1, 4] = stuff - 1
            m[-1, 5 : 4 + stuff] = 255
            if stuff > 1:
                m[-1, 5] = 0
        m[-1, 4 + stuff :] = tail
        out.append(m.tobytes())
    return b"".join(out)


def _sections(rows: np.ndarray, at: np.ndarray, start: np.ndarray) -> Iterator[bytes]:
    """Whole table sections out of the packets of one PID."""
    held = b""
    for r, a, s in zip(rows, at.tolist(), start.tolist()):
        data = r[a:].tobytes()
        if s:
            data = data[1 + data[0] :] if data else data
            held = b""
        elif not held:
            continue
        held += data
        while len(held) >= 3 and held[0] != 0xFF:
            size = 3 + ((held[1] & 15) << 8 | held[2])
            if len(held) < size:
                break
            yield held[:size]
            held = held[size:]


def demux(stream: bytes) -> dict:
    """Tables, counters, units and payload of a stream; see the module's head for faulty ones."""
    out = {"payload": None, "packets": len(stream) // PACKET, "programs": [], "continuity_errors": 0, "duplicates": 0, "units": [], "clocks": [], "error": None}
    if not stream or len(stream) % PACKET:
        return out | {"error": "length"}
    m = np.frombuffer(stream, np.uint8).reshape(-1, PACKET)
    if (m[:, 0] != 0x47).any():
        return out | {"error": "sync"}
    pid = (m[:, 1].astype(np.int32) & 31) << 8 | m[:, 2]
    start, cc = (m[:, 1] & 0x40) > 0, m[:, 3] & 15
    has_af, has_data = (m[:, 3] & 0x20) > 0, (m[:, 3] & 0x10) > 0
    at = np.where(has_af, 5 + m[:, 4].astype(np.int32), 4)
    if (at > PACKET).any():
        return out | {"error": "adaptation field"}
    flags = np.where(has_af & (m[:, 4] > 0), m[:, 5], 0)
    pmts, streams = {}, {}
    for s in _sections(m[(k := (pid == PAT_PID) & has_data)], at[k], start[k]):
        if len(s) < 12 or section_crc(s):
            return out | {"error": "table checksum"}
        for i in range(8, len(s) - 4, 4):
            if number := s[i] << 8 | s[i + 1]:
                pmts[(s[i + 2] & 31) << 8 | s[i + 3]] = number
    for p, number in pmts.items():
        for s in _sections(m[(k := (pid == p) & has_data)], at[k], start[k]):
            if len(s) < 16 or section_crc(s):
                return out | {"error": "table checksum"}
            i = 12 + ((s[10] & 15) << 8 | s[11])
            while i + 5 <= len(s) - 4:
                streams[(s[i + 1] & 31) << 8 | s[i + 2]] = (number, s[i])
                i += 5 + ((s[i + 3] & 15) << 8 | s[i + 4])
    out["programs"] = [{"program": n, "pid": p, "stream_type": t} for p, (n, t) in sorted(streams.items())]
    if not streams:
        return out | {"error": "no program"}
    data = []
    for p in sorted(streams):
        k = np.flatnonzero((pid == p) & has_data)
        if not len(k):
            continue
        step = (cc[k[1:]].astype(np.int16) - cc[k[:-1]]) & 15
        same = np.concatenate(([False], (step == 0) & (m[k[1:]] == m[k[:-1]]).all(axis=1)))
        broken = np.concatenate(([False], (step != 1)))
        out["duplicates"] += int(same.sum())
        out["continuity_errors"] += int((broken & ~same).sum())
        k = k[~same]
        rows, off = m[k], at[k]
        body = rows[np.arange(PACKET)[None, :] >= off[:, None]]
        ends = np.cumsum(PACKET - off)
        begins = (ends - (PACKET - off))[start[k]]
        raps, bounds = (flags[k] & 0x40)[start[k]] > 0, np.append(begins, len(body)).tolist()
        for q in k[(flags[k] & 0x10) > 0]:
            out["clocks"].append(int.from_bytes(m[q, 6:12].tobytes(), "big") >> 15)
        raw = body.tobytes()
        for i, (b, e) in enumerate(zip(bounds, bounds[1:])):
            if raw[b : b + 3] != b"\x00\x00\x01" or e - b < 9 or e - b < 9 + raw[b + 8] or raw[b + 8] < (0, 0, 5, 10)[raw[b + 7] >> 6]:
                return out | {"error": "elementary packet"}
            length, kind, head = raw[b + 4] << 8 | raw[b + 5], raw[b + 7] >> 6, raw[b + 8]
            e = b + 6 + length if length else e
            unit = raw[b + 9 + head : e]
            pts = _unstamp(raw[b + 9 : b + 14]) if kind & 2 else None
            dts = _unstamp(raw[b + 14 : b + 19]) if kind == 3 else pts
            out["units"].append({"pid": p, "pts": pts, "dts": dts, "random_access": bool(raps[i]), "size": len(unit)})
            data.append(unit)
    return out | {"payload": b"".join(data)}


def padded(data: bytes) -> bytes:
    """data with bytes 255 up to a positive multiple of the block size."""
    return data + b"\xff" * (-len(data) % BLOCK or (0 if data else BLOCK))


MUXED = "doc_id long, n_bytes long, media binary"
DEMUXED = MUXED + (
    ", payload binary, packets long, continuity_errors long, duplicates long, programs array<struct<program:int,pid:int,stream_type:int>>"
    ", units array<struct<pid:int,pts:long,dts:long,random_access:boolean,size:int>>, clocks array<long>, error string"
)


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes and the stream that stores the padded text, one row per row."""

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for lo in range(0, b.num_rows, 512):
            part = b.slice(lo, 512)
            texts = [x or b"" for x in part.column(1).cast(pa.binary()).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(x) for x in texts], pa.int64()), pa.array([mux(padded(x)) for x in texts], pa.binary())], ["doc_id", "n_bytes", "media"])

    return map_batches(docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")), run, MUXED)


def decode(media: DataFrame) -> DataFrame:
    """Streams (doc_id, n_bytes, media) with all that demux finds in them."""
    from pyspark.sql import types as T

    schema = to_arrow_schema(T.StructType.fromDDL(DEMUXED))

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for lo in range(0, b.num_rows, 512):
            part = b.slice(lo, 512)
            found = [demux(x or b"") for x in part.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), part.column(2), *(pa.array([f[n] for f in found], schema.field(n).type) for n in schema.names[3:])], schema=schema)

    return map_batches(media.select("doc_id", "n_bytes", "media"), run, DEMUXED)


DIGESTS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def digests(media: DataFrame) -> DataFrame:
    """What a catalogue keeps of each stream: digests of stored and read-back bytes, and a feature line."""

    def feature(f: dict) -> str:
        pts, rap = [u["pts"] for u in f["units"]], [i for i, u in enumerate(f["units"]) if u["random_access"]]
        return f"packets={f['packets']};programs={'+'.join(f'{p["program"]}:{p["pid"]}:{p["stream_type"]}' for p in f['programs'])};units={len(pts)};pts={pts[0]}-{pts[-1]};random_access={len(rap)};last_random_access={rap[-1] if rap else -1};clocks={len(f['clocks'])};continuity_errors={f['continuity_errors']}"

    def run(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        for lo in range(0, b.num_rows, 512):
            part = b.slice(lo, 512)
            rows = []
            for x in part.column(2).to_pylist():
                f = demux(x)
                if f["error"]:
                    raise ValueError(f["error"])
                p = f["payload"]
                rows.append((len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-32:]), len(x), hashlib.sha256(x).hexdigest(), feature(f)))
            cols = list(zip(*rows))
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *(pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())))], ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    return map_batches(media.select("doc_id", "n_bytes", "media"), run, DIGESTS)
