"""Packet capture files as a data source: spark.read.format("packet_capture").load(folder), and as a stream.

The classic capture format: a 24-byte header, then records of seconds, microseconds, kept length, full length and bytes.
Ethernet, IPv4, and TCP or UDP headers give the flow, protocol and payload; other packets keep their bytes under "other". Each file
is a partition; truncated records end a file. Files are read by the executors, so the path must be one that they
can open (a mounted folder); for other stores read with binaryFile and parse with `records`.
"""

from __future__ import annotations

import glob
import os
import struct
from collections.abc import Iterator
from datetime import datetime, timezone

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

SCHEMA = "ts timestamp, flow_key string, src string, dst string, proto string, seq bigint, payload binary"
#: First bytes of a capture in little and big endian, in microseconds and nanoseconds.
MAGIC = {0xA1B2C3D4: ("<", 1_000_000), 0xA1B23C4D: ("<", 1_000_000_000)}


def records(raw: bytes) -> Iterator[tuple]:
    """Rows of SCHEMA of a capture's bytes."""
    if len(raw) < 24:
        return
    for end in "<>":
        magic = struct.unpack(f"{end}I", raw[:4])[0]
        if magic in MAGIC:
            scale = MAGIC[magic][1]
            break
    else:
        raise ValueError("not a packet capture")
    at, seq = 24, 0
    while at + 16 <= len(raw):
        sec, frac, kept, _ = struct.unpack(f"{end}IIII", raw[at : at + 16])
        body = raw[at + 16 : at + 16 + kept]
        if len(body) < kept:
            return
        at += 16 + kept
        src, dst, proto, payload = parsed(body)
        yield datetime.fromtimestamp(sec + frac / scale, tz=timezone.utc).replace(tzinfo=None), f"{src}>{dst}", src, dst, proto, seq, payload
        seq += 1


def parsed(frame: bytes) -> tuple[str, str, str, bytes]:
    """Source, destination, protocol and payload of an Ethernet frame."""
    if len(frame) >= 34 and frame[12:14] == b"\x08\x00":
        ip = frame[14:]
        head, total, kind = (ip[0] & 15) * 4, struct.unpack(">H", ip[2:4])[0], ip[9]
        src, dst = (".".join(map(str, ip[a : a + 4])) for a in (12, 16))
        body = ip[head : total or len(ip)]
        if kind == 6 and len(body) >= 20:
            ports, rest = struct.unpack(">HH", body[:4]), body[(body[12] >> 4) * 4 :]
            return f"{src}:{ports[0]}", f"{dst}:{ports[1]}", "tcp", rest
        if kind == 17 and len(body) >= 8:
            ports = struct.unpack(">HH", body[:4])
            return f"{src}:{ports[0]}", f"{dst}:{ports[1]}", "udp", body[8:]
        return src, dst, f"ip{kind}", body
    return frame[6:12].hex(), frame[:6].hex(), "other", frame[14:]


def capture_bytes(packets: list[tuple[float, str, str, str, bytes]]) -> bytes:
    """A capture of (time, source "a.b.c.d:port", destination, "tcp" or "udp", payload): for tests and exports."""
    out = [struct.pack("<IHHiIII", 0xA1B2C3D4, 2, 4, 0, 0, 65535, 1)]
    for t, src, dst, proto, payload in packets:
        (a, p), (b, q) = (x.rsplit(":", 1) for x in (src, dst))
        ip = lambda x: bytes(map(int, x.split(".")))
        if proto == "tcp":
            body = struct.pack(">HHIIBBHHH", int(p), int(q), 0, 0, 5 << 4, 0, 0, 0, 0) + payload
        else:
            body = struct.pack(">HHHH", int(p), int(q), 8 + len(payload), 0) + payload
        frame = bytes(12) + b"\x08\x00" + struct.pack(">BBHHHBBH", 0x45, 0, 20 + len(body), 0, 0, 64, 6 if proto == "tcp" else 17, 0) + ip(a) + ip(b) + body
        out.append(struct.pack("<IIII", int(t), round(t % 1 * 1_000_000), len(frame), len(frame)) + frame)
    return b"".join(out)


class FilePartition(InputPartition):
    def __init__(self, path: str):
        self.path = path


class CaptureReader(DataSourceReader):
    def __init__(self, path: str):
        self.files = sorted(f for f in glob.glob(f"{path}/*") if os.path.isfile(f)) if os.path.isdir(path) else [path]

    def partitions(self) -> list[FilePartition]:
        return [FilePartition(f) for f in self.files]

    def read(self, partition: FilePartition) -> Iterator[tuple]:
        with open(partition.path, "rb") as f:
            yield from records(f.read())


class CaptureStream(DataSourceStreamReader):
    """Files in the order of their names; the offset is the number of files taken, each new file a partition."""

    def __init__(self, path: str):
        self.path = path

    def files(self) -> list[str]:
        return sorted(f for f in glob.glob(f"{self.path}/*") if os.path.isfile(f))

    def initialOffset(self) -> dict:  # noqa: N802
        return {"files": 0}

    def latestOffset(self) -> dict:  # noqa: N802
        return {"files": len(self.files())}

    def partitions(self, start: dict, end: dict) -> list[FilePartition]:
        return [FilePartition(f) for f in self.files()[start["files"] : end["files"]]]

    def read(self, partition: FilePartition) -> Iterator[tuple]:
        with open(partition.path, "rb") as f:
            yield from records(f.read())


class CaptureDataSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "packet_capture"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> CaptureReader:
        return CaptureReader(self.options["path"])

    def streamReader(self, schema) -> CaptureStream:  # noqa: N802
        return CaptureStream(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CaptureDataSource)


def as_trace(rows: DataFrame) -> DataFrame:
    """Trace columns of captured rows; the interval is assigned afterwards."""
    from pyspark.sql import functions as F

    return rows.select(F.lit(0).alias("interval_id"), "ts", "flow_key", "src", "dst", "proto", "seq", "payload")
