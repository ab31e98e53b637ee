"""Content-defined, overlapped blocks: an Arrow kernel for scale, and a SQL twin of it for checks.

A window is `window` positions in a row; its boundary is the position with the least boundary hash, the rightmost of equals.
A block runs from one boundary to the end of the bytes that the next boundary's hash covers, so neighbours share
overlap + 1 bytes. Only full windows count, so an excerpt never invents a boundary that a payload around it lacks.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import POS, boundary_hash, boundary_hash_column
from ..schemas import BLOCKS

WINDOW, OVERLAP = 64, 4
#: Bytes of one payload that the kernel handles at a time; longer ones go piece by piece with lead-in and carry.
PIECE = 8 << 20


def sliding_min(key: np.ndarray, window: int) -> np.ndarray:
    """Minimum of each run of `window`, by prefix and suffix minima of blocks: linear in the length."""
    n = len(key) - window + 1
    if n <= 0:
        return key[:0]
    pad = -len(key) % window
    grid = np.concatenate([key, np.full(pad, np.iinfo(np.int64).max)]).reshape(-1, window)
    prefix = np.minimum.accumulate(grid, axis=1).ravel()
    suffix = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(suffix[:n], prefix[window - 1 : window - 1 + n])


def bounds_of(data: np.ndarray, lengths: np.ndarray, window: int, width: int, instance: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Boundaries in concatenated payloads: positions in the whole array, and the payload of each."""
    h = boundary_hash(data, width, instance)
    n = len(h)
    if n < window:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    at = np.arange(n, dtype=np.int64)
    np.left_shift(h, 31, out=h)
    np.add(h, POS - 1 - at, out=h)
    least = sliding_min(h, window)
    end = np.cumsum(lengths)
    if len(lengths) > 1:  # windows that cross into the next payload don't count
        full = np.ones(len(least), bool)
        for e in end[:-1].tolist():
            full[max(0, e - window - width + 2) : e] = False
        least = least[full]
    picked = np.zeros(n, bool)
    picked[POS - 1 - (least & (POS - 1))] = True
    found = np.flatnonzero(picked)
    return found, np.searchsorted(end, found, side="right")


def piece_bounds(payload: bytes, window: int, width: int, instance: int = 0, piece: int | None = None) -> Iterator[np.ndarray]:
    """Boundaries of one payload in order, those of a piece at a time."""
    piece = PIECE if piece is None else piece
    if len(payload) <= piece:
        yield bounds_of(np.frombuffer(payload, np.uint8), np.array([len(payload)]), window, width, instance)[0]
        return
    for a in range(0, len(payload), piece):
        lead = min(a, window)
        data = np.frombuffer(payload[a - lead : a + piece + window + width], np.uint8)
        found = bounds_of(data, np.array([len(data)]), window, width, instance)[0] + a - lead
        yield found[(found >= a) & (found < a + piece)]


def payload_bounds(payload: bytes, window: int, width: int, instance: int = 0) -> np.ndarray:
    """Boundaries of one payload, piece by piece if it is long."""
    return np.concatenate(list(piece_bounds(payload, window, width, instance)))


def chunks(payloads: list[bytes | None], limit: int = 64 << 10) -> Iterator[tuple[int, int]]:
    """Ranges of payloads with about `limit` bytes, so that a chunk's arrays stay in a core's cache."""
    a, held = 0, 0
    for i, p in enumerate(payloads):
        held += len(p or b"")
        if held >= limit:
            yield a, i + 1
            a, held = i + 1, 0
    if a < len(payloads):
        yield a, len(payloads)


def winnow_places(payloads: list[bytes | None], window: int = WINDOW, overlap: int = OVERLAP, threshold: int = 0, keep_equal: bool = True, instance: int = 0) -> Iterator[tuple[bytes, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Kept blocks of a list of payloads, chunk by chunk: the chunk's bytes, start and end in them, row, number and start in the payload."""
    width = overlap + 1
    for a, b in chunks(payloads):
        own = [p or b"" for p in payloads[a:b]]
        if len(own) == 1:
            found = payload_bounds(own[0], window, width, instance)
            row, base, data = np.zeros(len(found), np.int64), np.zeros(1, np.int64), own[0]
        else:
            data = b"".join(own)
            lengths = np.array([len(p) for p in own], np.int64)
            found, row = bounds_of(np.frombuffer(data, np.uint8), lengths, window, width, instance)
            base = np.cumsum(lengths) - lengths
        same = row[1:] == row[:-1]
        at, to, own_row = found[:-1][same], found[1:][same] + width, row[:-1][same]
        size = to - at
        number = np.arange(len(own_row)) - np.searchsorted(own_row, own_row)
        if threshold:
            keep = size >= threshold if keep_equal else size > threshold
            at, to, own_row, number = at[keep], to[keep], own_row[keep], number[keep]
        yield data, at, to, own_row + a, number, at - base[own_row]


def winnow_batch(payloads: list[bytes | None], window: int = WINDOW, overlap: int = OVERLAP, threshold: int = 0, keep_equal: bool = True, instance: int = 0) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    """Row, number, start, size and bytes of all kept blocks of a list of payloads."""
    parts = [(row, number, start, to - at, [data[x:y] for x, y in zip(at.tolist(), to.tolist(), strict=True)]) for data, at, to, row, number, start in winnow_places(payloads, window, overlap, threshold, keep_equal, instance)]
    if not parts:
        empty = np.zeros(0, np.int64)
        return empty, empty, empty, empty, []
    return (*(np.concatenate([p[i] for p in parts]) for i in range(4)), [x for p in parts for x in p[4]])


def fixed_batch(payloads: list[bytes | None], size: int, stride: int | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, list[bytes]]:
    """Whole blocks of a fixed size, one after the other from the start."""
    row, number, start, out = [], [], [], []
    for i, p in enumerate(payloads):
        for n, a in enumerate(range(0, len(p or b"") - size + 1, stride or size)):
            row.append(i)
            number.append(n)
            start.append(a)
            out.append(p[a : a + size])
    return np.array(row, np.int64), np.array(number, np.int64), np.array(start, np.int64), np.full(len(row), size, np.int64), out


#: Bytes of payloads that are cut at a time where blocks become rows: a payload may have a block for each of its bytes.
CUT_BYTES = 256 << 10


def block_rows(trace: DataFrame, cut) -> DataFrame:
    """The rows of BLOCKS that cut(payloads) makes; row-local, no exchange."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            payloads = batch.column("payload").to_pylist()
            for first, end in chunks(payloads, CUT_BYTES):
                row, number, start, size, blocks = cut(payloads[first:end])
                for a in range(0, len(row), 50_000):
                    b = slice(a, a + 50_000)
                    at = pa.array(row[b] + first)
                    yield pa.RecordBatch.from_arrays(
                        [batch.column("interval_id").take(at), batch.column("flow_key").take(at), batch.column("seq").take(at), pa.array(number[b], pa.int32()), pa.array(start[b], pa.int32()), pa.array(size[b], pa.int32()), pa.array(blocks[b], pa.binary())],
                        ["interval_id", "flow_key", "seq", "block_no", "start", "size", "block"],
                    )

    return trace.select("interval_id", "flow_key", "seq", "payload").mapInArrow(kernel, BLOCKS)


def block_count(trace: DataFrame, cut) -> int:
    """How many blocks cut(payloads) makes; they don't become rows."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = 0
        for batch in batches:
            payloads = batch.column("payload").to_pylist()
            n += sum(len(cut(payloads[a:b])[0]) for a, b in chunks(payloads, CUT_BYTES))
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64())], ["n"])

    return int(trace.select("payload").mapInArrow(kernel, "n bigint").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])


def size_counts(payloads: Iterable[bytes | None], window: int = WINDOW, overlap: int = OVERLAP) -> np.ndarray:
    """How many winnowed blocks of each size payloads have. Short payloads are cut together, long ones in pieces: about CUT_BYTES at a time."""
    width = overlap + 1
    held = np.zeros(window + overlap + 2, np.int64)  # neighbours in the boundaries of full windows are at most a window apart
    own: list[bytes] = []
    waiting = 0

    def cut() -> None:
        for _, at, to, _, _, _ in winnow_places(own, window, overlap):
            held[:] += np.bincount(to - at, minlength=len(held))

    for p in payloads:
        if len(p or b"") > CUT_BYTES:
            last = np.zeros(0, np.int64)
            for found in piece_bounds(p, window, width, piece=CUT_BYTES):
                found = np.concatenate([last, found])
                held += np.bincount(np.diff(found) + width, minlength=len(held))
                last = found[-1:]
            continue
        own.append(p or b"")
        waiting += len(own[-1])
        if waiting > CUT_BYTES:
            cut()
            own, waiting = [], 0
    cut()
    return held


def block_sizes(trace: DataFrame, window: int = WINDOW, overlap: int = OVERLAP, made=None) -> DataFrame:
    """size, blocks of the winnowed blocks: counted in the tasks, where payloads with a block for each byte would be too many rows. made:
    turns a row's payload column into the payload itself, one at a time in the task, so that bytes which a number can say aren't sent."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = (x.as_py() for batch in batches for x in batch.column("payload"))
        held = size_counts(rows if made is None else map(made, rows), window, overlap)
        size = np.flatnonzero(held)
        yield pa.RecordBatch.from_arrays([pa.array(size.astype(np.int32)), pa.array(held[size])], ["size", "blocks"])

    return trace.select("payload").mapInArrow(kernel, "size int, blocks bigint").groupBy("size").agg(F.sum("blocks").alias("blocks"))


def winnow_blocks(trace: DataFrame, window: int = WINDOW, overlap: int = OVERLAP, threshold: int = 0, keep_equal: bool = True, instance: int = 0) -> DataFrame:
    return block_rows(trace, lambda payloads: winnow_batch(payloads, window, overlap, threshold, keep_equal, instance))


def fixed_blocks(trace: DataFrame, size: int = 32, stride: int | None = None) -> DataFrame:
    return block_rows(trace, lambda payloads: fixed_batch(payloads, size, stride))


def winnow_bounds_sql(trace: DataFrame, window: int = WINDOW, width: int = OVERLAP + 1, instance: int = 0) -> DataFrame:
    """flow_key, seq, pos of all boundaries by built-in functions: a row per byte, so for checks, not for scale."""
    n = F.octet_length("payload") - (width - 1)
    rows = trace.filter(F.octet_length("payload") >= window + width - 1).select("interval_id", "flow_key", "seq", n.alias("n"), "payload", F.explode(F.sequence(F.lit(0), n - 1)).alias("pos"))
    value = F.conv(F.hex(F.expr(f"substring(payload, pos + 1, {width})")), 16, 10).cast("bigint")
    keyed = rows.select("interval_id", "flow_key", "seq", "n", "pos", (boundary_hash_column(value, instance) * F.lit(POS) + (F.lit(POS - 1) - F.col("pos"))).alias("key"))
    frame = Window.partitionBy("interval_id", "flow_key", "seq").orderBy("pos").rowsBetween(0, window - 1)
    least = keyed.withColumn("least", F.min("key").over(frame)).filter(F.col("pos") <= F.col("n") - window)
    return least.select("interval_id", "flow_key", "seq", (F.lit(POS - 1) - F.pmod("least", F.lit(POS))).cast("int").alias("pos")).distinct()


def winnow_bounds(trace: DataFrame, window: int = WINDOW, width: int = OVERLAP + 1, instance: int = 0) -> DataFrame:
    """The same by the Arrow kernel."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, p in enumerate(batch.column("payload").to_pylist()):
                found = payload_bounds(p or b"", window, width, instance)
                at = pa.array(np.full(len(found), i))
                yield pa.RecordBatch.from_arrays([batch.column("interval_id").take(at), batch.column("flow_key").take(at), batch.column("seq").take(at), pa.array(found, pa.int32())], ["interval_id", "flow_key", "seq", "pos"])

    return trace.select("interval_id", "flow_key", "seq", "payload").mapInArrow(kernel, "interval_id int, flow_key string, seq bigint, pos int")
