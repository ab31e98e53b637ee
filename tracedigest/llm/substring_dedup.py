"""Substring deduplication with a count-min prefilter.

Words are runs of anything but ASCII white space. A window is `window` consecutive words of a document; every word covered
by a window that also starts in a document with a smaller id is removed (windows are judged on the input).

First pass: each task adds windows to a count-min sketch of saturating counters (none, one, more), kept as sorted
cells; the sketches of all tasks are merged block by block into one bitmap per row that says "more than one". A window is
counted by its anchor, the gram of half its words with the least hash: places of equal windows have equal anchors at
different places, so an anchor's count, and all the more its estimate, is no less than its window's, and neighbouring windows share
their anchor, which saves three updates of four. So a window that occurs twice always passes. Second pass: only windows that pass
are grouped exactly, by 96 bits of hash. A task first settles what it can on its own: for each window, its documents
beyond the smallest id that the batch, or the task's earlier batches, have shown are removed there and then (as runs), so a passage
that a third of all documents share reaches the exchange about once per task (where ids ascend, else whenever a smaller one comes).
The sketch has a fixed size (`cell_bits`, so rows·2^cell_bits/8 bytes are
broadcast); on inputs far beyond its capacity more windows pass and the exact stage groups them: dearer, never wrong.

Nulls: a null text has no words; a null id counts as larger than any other, so such rows lose what any identified
document has. Rows alike in id never remove each other's words. Texts shorter than a window keep all words. Empty
tables give no rows. Only the two named columns are read, so other columns cannot clash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import pieces, row_tag, shuffle_width

WINDOW = 13
CELL_BITS, BLOCK_BITS = 27, 20
#: Text bytes within which repeats are settled without an exchange.
SETTLE_BYTES = 8 << 20
#: Repeated windows that a task remembers from batch to batch.
REMEMBERED = 500_000
LOW = (1 << BLOCK_BITS) - 1
A, B, C = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0xD6E8FEB86659FD93))


class Memo(dict):
    """64 bits of each word's bytes; forgets all when large."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > 250_000:
            self.clear()
        out = self[word] = xxhash.xxh3_64_intdigest(word)
        return out


def split(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "replace").split()


def anchors(own: list[list[bytes]], memo: Memo, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of these documents: hashes of all words, of all grams, the least gram hash of each window (0: no window starts
    there), document number and place of each word. A gram is the longer half of a window."""
    gram = window // 2 + 1
    n = np.array([len(w) for w in own], np.int64)
    flat = np.fromiter((memo[w] for ws in own for w in ws), np.uint64, int(n.sum()))
    grams = np.zeros(max(0, len(flat) - gram + 1), np.uint64)
    for j in range(gram):
        grams = grams * A + flat[j : j + len(grams)]
    grams = (grams ^ (grams >> np.uint64(32))) * B | np.uint64(1)
    size = max(0, len(flat) - window + 1)
    least = grams[:size].copy()
    for j in range(1, window - gram + 1):
        np.minimum(least, grams[j : j + size], out=least)
    doc = np.repeat(np.arange(len(own)), n)
    first = np.arange(len(flat)) - np.repeat(np.cumsum(n) - n, n)
    least[doc[:size] != doc[window - 1 :][:size]] = 0
    return flat, grams, least, doc, first


def chosen(grams: np.ndarray, least: np.ndarray, window: int) -> np.ndarray:
    """The grams that are least in some window, each place once."""
    span = window - window // 2
    most = np.zeros(len(grams), np.uint64)
    for j in range(span):
        np.maximum(most[j : j + len(least)], least, out=most[j : j + len(least)])
    return grams[most == grams]


def digests(flat: np.ndarray, at: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Two hashes of each window that starts at a word of `at`."""
    h1, h2 = np.zeros(len(at), np.uint64), np.zeros(len(at), np.uint64)
    for j in range(window):
        word = flat[at + j]
        h1 = h1 * A + word
        h2 = h2 * B + (word ^ (word >> np.uint64(32))) * C
    return (h1 ^ (h1 >> np.uint64(32))) * B, (h2 ^ (h2 >> np.uint64(32))) * A


class Repeated:
    """Windows that a task has met several times, with the smallest rank of their documents; forgets older ones when full."""

    def __init__(self, most: int = REMEMBERED):
        self.most, self.h1, self.h2, self.rank = most, np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64)

    def find(self, h1: np.ndarray, h2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Place of each window, and whether it is there."""
        if not len(self.h1):
            return np.zeros(len(h1), np.int64), np.zeros(len(h1), bool)
        at = np.minimum(np.searchsorted(self.h1, h1), len(self.h1) - 1)
        return at, (self.h1[at] == h1) & (self.h2[at] == h2)

    def add(self, h1: np.ndarray, h2: np.ndarray, rank: np.ndarray) -> None:
        """Windows sorted by h1; a known one takes the new rank."""
        at, known = self.find(h1, h2)
        self.rank[at[known]] = rank[known]
        new = ~known
        if len(self.h1) + new.sum() > self.most:
            self.h1, self.h2, self.rank = h1, h2, rank
        elif new.any():
            at = np.searchsorted(self.h1, h1[new])
            self.h1, self.h2, self.rank = (np.insert(x, at, y[new]) for x, y in ((self.h1, h1), (self.h2, h2), (self.rank, rank)))


def cells(grams: np.ndarray, cell_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """The cells of a gram in the two rows of the sketch."""
    return (grams >> np.uint64(64 - cell_bits)).astype(np.int64), (grams * C >> np.uint64(64 - cell_bits)).astype(np.int64)


def packed_cells(own: np.ndarray) -> bytes:
    """Sorted different cells of a block: counts by high part, then low bytes."""
    return np.bincount(own >> 8, minlength=1 << (BLOCK_BITS - 8)).astype("<u2").tobytes() + (own & 255).astype(np.uint8).tobytes()


def unpacked_cells(raw: bytes) -> np.ndarray:
    high = np.frombuffer(raw, "<u2", 1 << (BLOCK_BITS - 8))
    return (np.repeat(np.arange(len(high), dtype=np.int64), high) << 8) | np.frombuffer(raw, np.uint8, offset=2 * len(high))


def sketch(docs: DataFrame, window: int, cell_bits: int) -> np.ndarray:
    """Bits, one row of bytes per hash: cells with a count over one. Fixed size."""
    blocks = 1 << (cell_bits - BLOCK_BITS)

    names = ["block", "ones", "more"]

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo, held, kept = Memo(), [], 0

        def flush():
            rows = []
            for r in range(2):
                own = np.sort(np.concatenate([x[r] for x in held]))
                new = np.diff(own, prepend=-1) != 0
                ones, more = own[new], np.unique(own[~new])
                edges = np.arange(blocks + 1, dtype=np.int64) << BLOCK_BITS
                a, b = np.searchsorted(ones, edges), np.searchsorted(more, edges)
                rows += [(r * blocks + i, packed_cells(ones[a[i] : a[i + 1]] & LOW), packed_cells(more[b[i] : b[i + 1]] & LOW) if b[i + 1] > b[i] else None) for i in range(blocks) if a[i + 1] > a[i]]
            for i in range(0, len(rows), 64):
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows[i : i + 64], strict=True), (pa.int32(), pa.binary(), pa.binary()), strict=True)], names)

        for batch in batches:
            for part in pieces(batch):
                _, grams, least, _, _ = anchors([split(t) for t in part.column("text").to_pylist()], memo, window)
                held.append(cells(chosen(grams, least, window), cell_bits))
                kept += len(held[-1][0])
                if kept > 3_000_000:
                    yield from flush()
                    held, kept = [], 0
        if kept:
            yield from flush()

    def merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come sorted by block; the counters of one block are held at a time."""
        now, ones, more = None, None, None

        def done():
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([np.packbits(more).tobytes()], pa.binary())], ["block", "bits"])

        for batch in batches:
            for block, one, two in zip(batch.column("block").to_pylist(), batch.column("ones"), batch.column("more"), strict=True):
                if block != now:
                    if now is not None:
                        yield done()
                    now, ones, more = block, np.zeros(1 << BLOCK_BITS, bool), np.zeros(1 << BLOCK_BITS, bool)
                own = unpacked_cells(one.as_py())
                more[own[ones[own]]] = True
                ones[own] = True
                if two.is_valid:
                    more[unpacked_cells(two.as_py())] = True
        if now is not None:
            yield done()

    found = docs.select("text").mapInArrow(partial, "block int, ones binary, more binary")
    found = found.repartition(shuffle_width(docs.sparkSession), "block").sortWithinPartitions("block").mapInArrow(merged, "block int, bits binary")
    out = np.zeros((2, 1 << (cell_bits - 3)), np.uint8)
    view = out.reshape(2 * blocks, -1)
    for block, bits in found.collect():  # at most the sketch's fixed size
        view[block] = np.frombuffer(bits, np.uint8)
    return out


def passes(bits: np.ndarray, least: np.ndarray, cell_bits: int) -> np.ndarray:
    """Windows of which the sketch holds more than one."""
    at = np.flatnonzero(least)
    for row, c in zip(bits, (0, 1), strict=True):
        own = cells(least[at], cell_bits)[c]
        at = at[(row[own >> 3] >> (7 - (own & 7)).astype(np.uint8) & 1).astype(bool)]
    return at


def repeats(docs: DataFrame, window: int, cell_bits: int) -> DataFrame:
    """doc_id, tag, spans: runs of removed windows (first window << 32 | windows) of each document that has some."""
    held = docs.sparkSession.sparkContext.broadcast(sketch(docs, window, cell_bits))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo, bits, repeated = Memo(), held.value, Repeated()
        for batch in (x for whole in batches for x in pieces(whole, limit=SETTLE_BYTES)):
            found, base = [], 0
            for part in pieces(batch):
                flat, _, least, doc, first = anchors([split(t) for t in part.column("text").to_pylist()], memo, window)
                at = passes(bits, least, cell_bits)
                h1, h2 = digests(flat, at, window)
                found.append((h1, h2 >> np.uint64(32), doc[at] + base, first[at]))
                base += part.num_rows
            if not found:
                continue
            h1, h2, doc, first = (np.concatenate([x[i] for x in found]) for i in range(4))
            ids, tags = batch.column("doc_id"), batch.column("tag").to_numpy(zero_copy_only=False)
            rank = np.where(np.asarray(ids.is_null()), np.iinfo(np.int64).max, np.asarray(ids.fill_null(0)))
            order = np.lexsort((rank[doc], h2, h1))
            h1, h2, doc, first = h1[order], h2[order], doc[order], first[order]
            head = np.ones(len(h1), bool)
            head[1:] = (h1[1:] != h1[:-1]) | (h2[1:] != h2[:-1])
            lead = np.flatnonzero(head)
            least = rank[doc][lead]
            at, known = repeated.find(h1[lead], h2[lead])
            least[known] = np.minimum(least[known], repeated.rank[at[known]])
            settled = rank[doc] > least[np.cumsum(head) - 1]
            if len(lead):
                busy = known | np.logical_or.reduceat(settled, lead)
                repeated.add(h1[lead][busy], h2[lead][busy], least[busy])
            ask = ~settled
            order = np.lexsort((first[settled], doc[settled]))
            sdoc, sfirst = doc[settled][order], first[settled][order]
            cut = np.flatnonzero(np.concatenate([[True], (np.diff(sdoc) != 0) | (np.diff(sfirst) != 1)])) if len(sdoc) else np.zeros(0, np.int64)
            length = np.diff(np.append(cut, len(sdoc)))
            sdoc, sfirst = sdoc[cut], sfirst[cut]
            order = np.lexsort((first[ask], doc[ask]))
            adoc, afirst, a1, a2 = (x[ask][order] for x in (doc, first, h1, h2))
            row = np.concatenate([adoc, sdoc])
            key = np.concatenate([a1, (sdoc.astype(np.uint64) + np.uint64(base)) * A + sfirst.astype(np.uint64) * B]).view(np.int64)
            place = np.concatenate([(a2 << np.uint64(32)).view(np.int64) | afirst, sfirst])
            tag = (tags[row] << 32) | np.concatenate([np.zeros(len(adoc), np.int64), length])
            yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(place), ids.take(pa.array(row)), pa.array(tag)], ["h", "place", "doc_id", "tag"])

    tagged = docs.select("doc_id", row_tag().bitwiseAND(F.lit(0x7FFFFFFF)).alias("tag"), "text")
    rows = tagged.mapInArrow(kernel, "h bigint, place bigint, doc_id bigint, tag bigint")
    rows = rows.repartition(max(8, shuffle_width(docs.sparkSession)), "h")
    run = F.col("tag").bitwiseAND(F.lit(0xFFFFFFFF))
    first = F.col("place").bitwiseAND(F.lit(0xFFFFFFFF))
    least = F.min("doc_id").over(Window.partitionBy("h", "h2", "settled"))
    judged = rows.withColumns({"h2": F.shiftright("place", 32), "settled": run > 0}).withColumn("least", least)
    gone = judged.filter(F.col("settled") | (F.col("least") < F.col("doc_id")) | (F.col("doc_id").isNull() & F.col("least").isNotNull()))
    gone = gone.select("doc_id", F.shiftright("tag", 32).alias("tag"), F.shiftleft(first, 32).bitwiseOR(F.greatest(run, F.lit(1))).alias("span"))
    return gone.groupBy("doc_id", "tag").agg(F.collect_list("span").alias("spans"))


def dedup(docs: DataFrame, window: int = WINDOW, cell_bits: int = CELL_BITS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_removed, kept (words left, joined by one space), of every document."""
    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    gone = repeats(own, window, cell_bits).select(F.col("doc_id").alias("g_id"), F.col("tag").alias("g_tag"), "spans")
    tag = row_tag().bitwiseAND(F.lit(0x7FFFFFFF))
    joined = own.withColumn("tag", tag).join(gone, F.col("doc_id").eqNullSafe(F.col("g_id")) & (F.col("tag") == F.col("g_tag")), "left").select("doc_id", "text", "spans")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch):
                n, removed, kept = [], [], []
                for text, spans in zip(part.column("text").to_pylist(), part.column("spans"), strict=True):
                    words = split(text)
                    n.append(len(words))
                    if spans.is_valid:
                        span = spans.values.to_numpy()
                        edge = np.zeros(len(words) + 1, np.int64)
                        first = span >> 32
                        np.add.at(edge, first, 1)
                        np.add.at(edge, first + (span & 0xFFFFFFFF) + window - 1, -1)
                        stay = np.cumsum(edge[:-1]) == 0
                        removed.append(len(words) - int(stay.sum()))
                        words = [words[i] for i in np.flatnonzero(stay).tolist()]
                    else:
                        removed.append(0)
                    kept.append(b" ".join(words).decode("utf-8"))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.string())], ["doc_id", "n_words", "n_removed", "kept"])

    return joined.mapInArrow(kernel, "doc_id bigint, n_words bigint, n_removed bigint, kept string")
