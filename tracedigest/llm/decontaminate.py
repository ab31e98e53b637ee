"""Benchmark decontamination: a broadcast hash set of normalised test n-grams, and one scan of the documents.

Words: A-Z lowered, then runs of ASCII letters, digits and anything beyond ASCII. An item's windows are its runs of
`window` words; a shorter item is one window. Every window of a document whose hash is in the set is verified byte by byte
against the item's normalised words, and its words are hit.

The set is arrays: sorted window hashes, the place of each window in one string of all normalised items, its item. Its bytes
are counted before it is sent: a benchmark whose set would be larger than `max_broadcast_bytes` is cut by item hash into
parts, and the documents stream through one kernel per part, each adding its hits. The scan is row-local: no
exchange, no state beyond one slice of text.

Nulls: a null text has no words and no hits; items with null text or no words give no window, items with a null id
are left out. Repeated items and ids count once. Empty tables give no rows, or no hits. Only named columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, pieces

#: Bytes to what normalisation makes of them: lower case, and a space for what is in no word.
NORMAL = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
MIX = np.uint64(0x9E3779B97F4A7C15)


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "replace").translate(NORMAL).split()


def rolling(hashes: np.ndarray, window: int) -> np.ndarray:
    """A hash of each run of `window` word hashes."""
    out = np.zeros(max(0, len(hashes) - window + 1), np.uint64)
    for j in range(window):
        out = out * MIX + hashes[j : j + len(out)]
    return out ^ (out >> np.uint64(29))


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 400_000:
            self.clear()
        out = self[word] = xxhash.xxh3_64_intdigest(word)
        return out


@dataclass(frozen=True)
class Grams:
    """The windows of one length: sorted hashes; first byte, end and item of each in `text`, where words are joined by one space."""

    hashes: np.ndarray
    first: np.ndarray
    end: np.ndarray
    item: np.ndarray


#: Bytes of the set for each word of an item beside its text, at most.
WORD_BYTES = 8 + 8 + 8 + 4 + 1
#: Parts scanned in one plan, each by Python workers of its own; then the rows are written and read again.
CHAINED = 4


def grams(items: list[tuple[str, str]], window: int) -> tuple[bytes, dict[int, Grams], list[str]]:
    """Normalised text of all items, windows by length (a window of one item once), item ids."""
    memo = WordHashes()
    names = sorted({i for i, _ in items})
    number = {x: i for i, x in enumerate(names)}
    text, found, at = [], {}, 0
    for item, raw in items:
        own = words(raw)
        if not own:
            continue
        n = min(window, len(own))
        size = np.array([len(w) for w in own], np.int64)
        end = np.cumsum(size + 1) - 1
        first = end - size
        h = rolling(np.fromiter((memo[w] for w in own), np.uint64, len(own)), n)
        found.setdefault(n, []).append((h, first[: len(h)] + at, end[n - 1 :] + at, np.full(len(h), number[item], np.int32)))
        text.append(b" ".join(own))
        at += int(end[-1]) + 1
    by_length = {}
    for n, parts in found.items():
        h, first, end, item = (np.concatenate([p[i] for p in parts]) for i in range(4))
        order = np.lexsort((item, h))
        h, first, end, item = h[order], first[order], end[order], item[order]
        # repeats within an item: the same hash and item once, unless the words differ
        same = (h[1:] == h[:-1]) & (item[1:] == item[:-1])
        whole = b" ".join(text)
        keep = np.ones(len(h), bool)
        for i in np.flatnonzero(same).tolist():
            keep[i + 1] = whole[first[i] : end[i]] != whole[first[i + 1] : end[i + 1]]
        by_length[n] = Grams(h[keep], first[keep], end[keep], item[keep])
    return b" ".join(text), by_length, names


def scan(docs: DataFrame, items: list[tuple[str, str]], window: int) -> DataFrame:
    """Adds the hits of these items to columns spans (word from, to) and items."""
    held = docs.sparkSession.sparkContext.broadcast(grams(items, window))
    names, schema = docs.columns, docs.schema

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        whole, by_length, item_ids = held.value
        memo = WordHashes()
        for batch in batches:
            for part in pieces(batch):
                spans, found = part.column("spans").to_pylist(), part.column("items").to_pylist()
                counts = []
                for row, text in enumerate(part.column("text").to_pylist()):
                    own = words(text)
                    counts.append(len(own))
                    if not own:
                        continue
                    hashes = np.fromiter((memo[w] for w in own), np.uint64, len(own))
                    hit, seen = [], set()
                    for n, g in by_length.items():
                        h = rolling(hashes, n)
                        at = np.flatnonzero(g.hashes[np.minimum(np.searchsorted(g.hashes, h), len(g.hashes) - 1)] == h)
                        for i, a, b in zip(at.tolist(), np.searchsorted(g.hashes, h[at]).tolist(), np.searchsorted(g.hashes, h[at], side="right").tolist(), strict=True):
                            mine = b" ".join(own[i : i + n])
                            which = [x for x in range(a, b) if whole[g.first[x] : g.end[x]] == mine]
                            if which:
                                hit.append({"a": i, "b": i + n})
                                seen.update(g.item[which].tolist())
                    if hit:
                        spans[row] = spans[row] + hit
                        found[row] = sorted({*found[row], *(item_ids[x] for x in seen)})
                columns = {c: part.column(c) for c in names}
                columns |= {
                    "spans": pa.array(spans, pa.list_(pa.struct([("a", pa.int32()), ("b", pa.int32())]))),
                    "items": pa.array(found, pa.list_(pa.string())),
                    "n_words": pa.array(counts, pa.int64()),
                }
                yield pa.RecordBatch.from_arrays([columns[c] for c in names], names)

    return docs.mapInArrow(kernel, schema)


def mark(docs: DataFrame, benchmark: DataFrame, window: int = 10, max_broadcast_bytes: int = 32 << 20, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, text, `keep` columns (renamed k0, k1, ...), n_words, spans, items of each document."""
    items = benchmark.select(F.col(item_col).cast("string").alias("item"), F.col(item_text_col).alias("text")).filter("item is not null and text is not null").distinct()
    # a word has a byte and a byte after it at least, and an item an id
    size = items.agg(F.sum(F.octet_length("text") + (F.octet_length("text") / 2 + 1) * WORD_BYTES + F.octet_length("item") + 64)).first()[0] or 0
    parts = max(1, -(-int(size) // max_broadcast_bytes))
    out = docs.select(
        F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), *[F.col(c).alias(f"k{i}") for i, c in enumerate(keep)],
        F.lit(0).cast("long").alias("n_words"), F.expr("cast(array() as array<struct<a:int,b:int>>)").alias("spans"), F.expr("cast(array() as array<string>)").alias("items"),
    )
    part = F.pmod(F.xxhash64("item", "text"), F.lit(parts))
    held = sorted(r[0] for r in items.select(part.alias("part")).distinct().collect()) if parts > 1 else [0]
    for i, p in enumerate(held or [0]):
        if i and i % CHAINED == 0:
            out = materialize(out, "decontaminated")
        out = scan(out, [tuple(r) for r in items.filter(part == p).collect()], window)
    return out


def hits(docs: DataFrame, benchmark: DataFrame, window: int = 10, **names) -> DataFrame:
    """doc_id, n_words, n_hit (words inside any hit window), items, contaminated."""
    marked = mark(docs, benchmark, window, **names)
    step = """aggregate(array_sort(spans), named_struct('n', 0, 'to', 0),
        (s, x) -> named_struct('n', s.n + greatest(x.b - greatest(x.a, s.to), 0), 'to', greatest(s.to, x.b)), s -> cast(s.n as bigint))"""
    return marked.select("doc_id", "n_words", F.expr(step).alias("n_hit"), "items").withColumn("contaminated", F.col("n_hit") > 0)


def clean(docs: DataFrame, benchmark: DataFrame, mode: str = "document", window: int = 10, text_col: str = "text", **names) -> DataFrame:
    """The documents' own columns without contaminated documents (mode "document"), or with the hit words cut from their texts
    (mode "span": the words left keep the white space before them)."""
    if mode not in ("document", "span"):
        raise ValueError(f"mode {mode!r}: document or span")
    columns = docs.columns
    marked = mark(docs, benchmark, window, text_col=text_col, keep=tuple(columns), **names)
    if mode == "document":
        return marked.filter(F.size("spans") == 0).select(*[F.col(f"k{i}").alias(c) for i, c in enumerate(columns)])

    @F.pandas_udf("string")
    def cut(texts, spans):
        import pandas as pd

        return pd.Series([remove_words(t, [(s["a"], s["b"]) for s in x]) for t, x in zip(texts, spans, strict=True)], dtype=object)

    k = f"k{columns.index(text_col)}"
    changed = F.when(F.size("spans") > 0, cut(F.col(k), F.col("spans"))).otherwise(F.col(k))
    return marked.select(*[(changed if c == text_col else F.col(f"k{i}")).alias(c) for i, c in enumerate(columns)])


def remove_words(text: str | None, spans: list[tuple[int, int]]) -> str | None:
    """The text without words a..b-1 of each span, and without what stands between two removed neighbours."""
    if text is None or not spans:
        return text
    raw = text.encode("utf-8", "replace")
    held = np.frombuffer(raw.translate(NORMAL), np.uint8) != 32
    edge = np.diff(np.concatenate([[False], held, [False]]).astype(np.int8))
    start, end = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    drop = np.zeros(len(start) + 1, bool)
    for a, b in spans:
        drop[a:b] = True
    out, at = [], 0
    run = np.flatnonzero(np.diff(np.concatenate([[False], drop])))
    for a, b in zip(run[::2].tolist(), run[1::2].tolist(), strict=True):
        out.append(raw[at : start[a]])
        at = int(end[b - 1])
    return b"".join([*out, raw[at:]]).decode("utf-8", "replace")
