"""The methods that the sectioned, indexed digest is compared with.

All are given as elements that are inserted in one filter and asked for by conjunction, so they run on the same filters
and the same evaluation. Internals of fixed_multifilter, double_winnow and hier_fixed are a reconstruction from their
parameters: the text at hand does not define them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import VECTOR_SPAN, md5, vector_hashes
from . import blocking

#: Cut functions give, for payloads: row, number, start, size, element bytes; the same function serves excerpts.


def shingled_winnow(window: int = 64, overlap: int = 4):
    """Baseline 1: winnowed blocks with overlap in a conventional filter."""
    return lambda payloads: blocking.winnow_batch(payloads, window, overlap)


def multi_winnow(t: int = 2, window: int = 64, overlap: int = 4):
    """Baseline 2: t instances with boundary hashes of their own, in one filter of the same size; all have to agree."""

    def cut(payloads):
        parts = []
        for i in range(t):
            row, number, start, size, blocks = blocking.winnow_batch(payloads, window, overlap, instance=i)
            parts.append((row, number * t + i, start, size, [b"%d:" % i + b for b in blocks]))
        order = np.argsort(np.concatenate([p[0] for p in parts]), kind="stable")
        blocks = [b for p in parts for b in p[4]]
        return (*(np.concatenate([p[i] for p in parts])[order] for i in range(4)), [blocks[i] for i in order.tolist()])

    return cut


def double_winnow(hash_window: int = 10, modulus: int = 8, window: int = 64):
    """Baseline 4: each block is stored twice, plain and tagged with its successor's digest; both are asked for."""

    def cut(payloads):
        row, number, start, size, blocks = blocking.winnow_batch(payloads, window, hash_window - 1)
        follows = np.flatnonzero((row[1:] == row[:-1]) & (number[1:] == number[:-1] + 1))
        tagged = [blocks[i] + b"~%d" % (int(md5(blocks[i + 1]).hexdigest()[:8], 16) % modulus) for i in follows.tolist()]
        order = np.argsort(np.concatenate([row, row[follows]]), kind="stable")
        every = [*blocks, *tagged]
        join = lambda x: np.concatenate([x, x[follows]])[order]
        return join(row), join(number), join(start), join(size), [every[i] for i in order.tolist()]

    return cut


def fixed_multifilter(hash_window: int = 8, aggregation: int = 3, modulus: int = 8):
    """Baseline 3: fixed blocks of hash_window·(aggregation + 1) bytes; the first bytes' digest chooses one of `modulus` filters."""
    size = hash_window * (aggregation + 1)
    return lambda payloads: blocking.fixed_batch(payloads, size), lambda block: int(md5(block[:hash_window]).hexdigest()[:8], 16) % modulus, size


def hier_fixed(block: int = 32, levels: int = 1):
    """Baseline 5: fixed blocks stored with their place; more levels also store runs of 2, 4, ... blocks."""

    def cut(payloads):
        row, number, start, size, out = [], [], [], [], []
        for i, p in enumerate(payloads):
            for level in range(levels):
                n = block << level
                for k, a in enumerate(range(0, len(p or b"") - n + 1, n)):
                    row.append(i)
                    number.append(k)
                    start.append(a)
                    size.append(n)
                    out.append(p[a : a + n] + b"@%d" % k)
        return np.array(row, np.int64), np.array(number, np.int64), np.array(start, np.int64), np.array(size, np.int64), out

    return cut


def hier_elements(excerpt: bytes, a: int, place: int, block: int = 32, levels: int = 1) -> list[bytes]:
    """What hier_fixed stores of the excerpt if its byte `a` begins the payload's block number `place`."""
    out = []
    for level in range(levels):
        run = 1 << level
        for i in range((len(excerpt) - a) // block - run + 1):
            if (place + i) % run == 0:
                out.append(excerpt[a + i * block : a + (i + run) * block] + b"@%d" % ((place + i) // run))
    return out


def packet_elements(trace: DataFrame) -> DataFrame:
    """Baseline 6: a whole payload is one element; only whole payloads can be asked for."""
    return trace.select("interval_id", "flow_key", F.col("payload").alias("block"))


#: Excerpt bytes that may be sent to every task at once.
SENT_BYTES = 64 << 20


def excerpt_bytes(excerpts: DataFrame) -> int:
    return int(excerpts.agg(F.coalesce(F.sum(F.octet_length("excerpt") + 16), F.lit(0))).first()[0])


def raw_archive(trace: DataFrame, excerpts: DataFrame, max_bytes: int = SENT_BYTES) -> DataFrame:
    """Baseline 7: keep everything and scan it. excerpt_id, flow_key; exact, quadratic: for truth on small inputs. Excerpts
    are sent to the payloads in parts of bounded size, a scan each."""
    parts = max(1, -(-excerpt_bytes(excerpts) // max_bytes))
    out = None
    for p in range(parts):
        part = excerpts.filter(F.pmod(F.xxhash64("excerpt_id"), F.lit(parts)) == p).select("excerpt_id", "excerpt")
        found = trace.select("flow_key", "payload").join(F.broadcast(part), F.contains("payload", "excerpt")).select("excerpt_id", "flow_key")
        out = found if out is None else out.unionByName(found)
    return out.distinct()


def exact_search(trace: DataFrame, excerpts: DataFrame, window: int = 64, overlap: int = 4, max_bytes: int = SENT_BYTES) -> DataFrame:
    """The same result for scale: an excerpt's largest block must be a block of every payload that contains it, so only
    payloads with that block are searched. Up to max_bytes of excerpts go to the payloads, in one row-local pass without
    an exchange of payloads or blocks; more excerpts meet them by an equi-join on blocks. Excerpts without a block are looked for in
    every payload."""
    if excerpt_bytes(excerpts) > max_bytes:
        return joined_search(trace, excerpts, window, overlap, max_bytes)
    rows = [(r["excerpt_id"], bytes(r["excerpt"])) for r in excerpts.select("excerpt_id", "excerpt").filter("excerpt is not null").collect()]
    row, _, _, size, blocks = blocking.winnow_batch([x for _, x in rows], window, overlap)
    best: dict[int, tuple[int, bytes]] = {}
    for r, n, b in zip(row.tolist(), size.tolist(), blocks, strict=True):
        best[r] = max(best.get(r, (0, b"")), (n, b))
    by_block: dict[bytes, list[tuple[int, bytes]]] = {}
    for r, (_, b) in best.items():
        by_block.setdefault(b, []).append(rows[r])
    plain = [rows[r] for r in range(len(rows)) if r not in best]
    held = trace.sparkSession.sparkContext.broadcast((by_block, plain))
    kind = excerpts.schema["excerpt_id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        anchors, everywhere = held.value
        for batch in batches:
            payloads, flows = batch.column("payload").to_pylist(), batch.column("flow_key").to_pylist()
            found = set()
            owner, _, _, _, own = blocking.winnow_batch(payloads, window, overlap)
            for r, b in zip(owner.tolist(), own, strict=True):
                if b in anchors:
                    found.update((i, flows[r]) for i, x in anchors[b] if x in payloads[r])
            for r, payload in enumerate(payloads):
                if payload is not None:
                    found.update((i, flows[r]) for i, x in everywhere if x in payload)
            found = sorted(found, key=str)
            yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in found], pa.string() if kind == "string" else pa.int64()), pa.array([f for _, f in found], pa.string())], ["excerpt_id", "flow_key"])

    return trace.select("flow_key", "payload").mapInArrow(kernel, f"excerpt_id {kind}, flow_key string").distinct()


def joined_search(trace: DataFrame, excerpts: DataFrame, window: int = 64, overlap: int = 4, max_bytes: int = SENT_BYTES) -> DataFrame:
    """Exact search for any number of excerpts."""
    own = excerpts.select(F.lit(0).alias("interval_id"), F.col("excerpt_id").cast("string").alias("flow_key"), F.lit(0).cast("bigint").alias("seq"), F.col("excerpt").alias("payload"))
    blocks = blocking.winnow_blocks(own, window, overlap)
    anchors = blocks.groupBy(F.col("flow_key").cast(excerpts.schema["excerpt_id"].dataType).alias("excerpt_id")).agg(F.max_by("block", F.struct("size", "block_no")).alias("block"))
    anchors = anchors.join(excerpts.select("excerpt_id", "excerpt"), "excerpt_id").select("excerpt_id", "excerpt", F.md5("block").alias("anchor"))
    placed = blocking.winnow_blocks(trace, window, overlap).select("interval_id", "flow_key", "seq", F.md5("block").alias("anchor")).distinct()
    met = placed.join(anchors, "anchor").join(trace.select("interval_id", "flow_key", "seq", "payload"), ["interval_id", "flow_key", "seq"])
    found = met.filter(F.contains("payload", "excerpt")).select("excerpt_id", "flow_key")
    rest = excerpts.join(anchors.select("excerpt_id"), "excerpt_id", "left_anti")
    return found.unionByName(raw_archive(trace, rest, max(1, max_bytes))).distinct()


#: Excerpts whose anchors (24 bytes each) may be sent to every task.
SENT_ANCHORS = 2_000_000


def excerpt_anchors(excerpts: DataFrame, window: int = 64, overlap: int = 4) -> DataFrame:
    """anchor, off, size, content: 64-bit hash and place of each different excerpt's largest block, the excerpt's bytes and 64-bit hash. Without a
    block, or beyond VECTOR_SPAN bytes, anchor is null."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = batch.column("excerpt").to_pylist()
            anchor, off, size = np.zeros(len(own), np.uint64), np.zeros(len(own), np.int32), np.array([len(x) for x in own], np.int32)
            best = np.zeros(len(own), np.int64)
            for data, at, to, row, _, start in blocking.winnow_places(own, window, overlap):
                order = np.argsort(to - at, kind="stable")  # the last of a row stays
                best[row[order]], off[row[order]], anchor[row[order]] = (to - at)[order], start[order], vector_hashes(np.frombuffer(data, np.uint8), at, to)[order]
            end = np.cumsum(size, dtype=np.int64)
            none = (best == 0) | (size > VECTOR_SPAN)
            content = np.zeros(len(own), np.uint64)
            some = np.flatnonzero(~none)
            content[some] = vector_hashes(np.frombuffer(b"".join(own), np.uint8), (end - size)[some], end[some])
            yield pa.RecordBatch.from_arrays([pa.array(anchor.view(np.int64), mask=none), pa.array(off), pa.array(size), pa.array(content.view(np.int64))], ["anchor", "off", "size", "content"])

    return excerpts.filter("excerpt is not null").select("excerpt").mapInArrow(kernel, "anchor bigint, off int, size int, content bigint").distinct()


def carried_once(trace: DataFrame, excerpts: DataFrame, window: int = 64, overlap: int = 4, most: int = SENT_ANCHORS) -> DataFrame:
    """excerpt_id, true_flow of the excerpts that exactly one flow contains. As exact_search, but the driver and the tasks get hashes of
    the excerpts, never their bytes, and a task hands on each excerpt's bytes with the first and last of its flows, so copies of a
    text don't become pairs. Bytes decide: the hashes only choose what is compared."""
    ends = [F.min("first").alias("first"), F.max("last").alias("last")]
    if excerpts.count() > most:
        found = joined_search(trace, excerpts, window, overlap).select("excerpt_id", F.col("flow_key").alias("first"), F.col("flow_key").alias("last"))
        return found.groupBy("excerpt_id").agg(*ends).filter("first = last").select("excerpt_id", F.col("first").alias("true_flow"))
    every = excerpt_anchors(excerpts, window, overlap).toArrow()
    sent = every.filter(every.column("anchor").is_valid())
    anchor, off, size, content = (sent.column(c).to_numpy() for c in ("anchor", "off", "size", "content"))
    contents = np.unique(content.view(np.uint64))
    # places of different excerpts around one block: at most as many as an excerpt is long
    order = np.lexsort((size, off, anchor.view(np.uint64)))
    places = [x[order] for x in (anchor.view(np.uint64), off.astype(np.int64), size.astype(np.int64))]
    new = np.ones(len(order), bool)
    new[1:] = np.logical_or.reduce([x[1:] != x[:-1] for x in places])
    held = trace.sparkSession.sparkContext.broadcast((*(x[new] for x in places), contents))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        anchors, offs, sizes, contents = held.value
        met: dict[bytes, tuple[str, str]] = {}
        held_bytes = 0

        def ready():
            return pa.RecordBatch.from_arrays([pa.array(list(met), pa.binary()), pa.array([x for x, _ in met.values()], pa.string()), pa.array([y for _, y in met.values()], pa.string())], ["excerpt", "first", "last"])

        for batch in batches:
            payloads, flows = batch.column("payload").to_pylist(), batch.column("flow_key").to_pylist()
            for data, at, to, row, _, start in blocking.winnow_places(payloads, window, overlap) if len(anchors) else ():
                if not len(row):
                    continue
                raw = np.frombuffer(data, np.uint8)
                own = vector_hashes(raw, at, to)
                low, high = np.searchsorted(anchors, own, "left"), np.searchsorted(anchors, own, "right")
                n = high - low
                block = np.repeat(np.arange(len(n)), n)
                which = np.arange(len(block)) - np.repeat(np.cumsum(n) - n, n) + low[block]
                a = at[block] - offs[which]
                b = a + sizes[which]
                base = at[block] - start[block]  # where the payload begins
                length = np.array([len(payloads[r] or b"") for r in range(int(row[0]), int(row[-1]) + 1)], np.int64)
                inside = np.flatnonzero((a >= base) & (b <= base + length[row[block] - row[0]]))
                inside = inside[np.argsort(a[inside], kind="stable")]
                if not len(inside):
                    continue
                a, b, who = a[inside], b[inside], row[block[inside]]
                own = vector_hashes(raw, a, b)
                hit = contents[np.minimum(np.searchsorted(contents, own), len(contents) - 1)] == own
                for x, y, r in zip(a[hit].tolist(), b[hit].tolist(), who[hit].tolist(), strict=True):
                    flow = flows[r]
                    if flow is None:
                        continue
                    key = data[x:y]
                    ends = met.get(key)
                    if ends is None:
                        met[key] = flow, flow
                        held_bytes += len(key) + 200
                    elif not ends[0] <= flow <= ends[1]:
                        met[key] = min(ends[0], flow), max(ends[1], flow)
            if held_bytes > 32 << 20:
                yield ready()
                met, held_bytes = {}, 0
        if met:
            yield ready()

    carried = trace.select("flow_key", "payload").mapInArrow(kernel, "excerpt binary, first string, last string").groupBy("excerpt").agg(*ends)
    found = excerpts.select("excerpt_id", "excerpt").join(carried, "excerpt").select("excerpt_id", "first", "last")
    if sent.num_rows < every.num_rows:
        rest = excerpts.filter(f"excerpt is not null and (octet_length(excerpt) > {VECTOR_SPAN} or octet_length(excerpt) < {2 * window + overlap})")
        more = exact_search(trace, rest, window, overlap).select("excerpt_id", F.col("flow_key").alias("first"), F.col("flow_key").alias("last"))
        found = found.unionByName(more)
    return found.groupBy("excerpt_id").agg(*ends).filter("first = last").select("excerpt_id", F.col("first").alias("true_flow"))
