"""Best-fit packing by minimum bin slack.

Per bin: the longest piece left, and beside it the combination of lengths left that fills the rest best, found by
subset-sum dynamic programming over bitsets (one Python integer has a bit for each sum that can be reached). A bin's combination
is then removed, as often as the counts allow, so the work depends on the number of different lengths (at most the bin
size), not on the number of pieces: the driver sees one histogram of lengths, bounded by the bin size.

Placing is distributed: pieces of one length are numbered within salted buckets, and each takes its place from the plan by
its number. Pieces that fill a bin alone need no number. Nothing is kept back: every piece lands in one bin.

Nulls: a null text is empty and is one piece with just the end token. Repeated rows are packed as often as they
occur. An empty table gives no rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, pieces

CAPACITY = 1024
END_ID = 2


def encoder(vocabulary: str = "byte_bpe_50k"):
    """text -> ids of the byte-level vocabulary, each task its own: the rank file gives the same ids as the tokenizer file
    (tests compare them) at several times the speed. A text that holds a special token's string goes to the tokenizer file."""
    import base64
    import json

    import public_tokenizers
    import tiktoken

    with open(public_tokenizers.path(f"{vocabulary}.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    with open(public_tokenizers.path(f"{vocabulary}.json"), encoding="utf-8") as f:
        special = [x["content"] for x in json.load(f)["added_tokens"]]
    plain = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
    whole: list = []

    def encode(text: str) -> list[int]:
        if not any(x in text for x in special):
            return plain(text)
        if not whole:
            from tokenizers import Tokenizer

            whole.append(Tokenizer.from_file(public_tokenizers.path(f"{vocabulary}.json")))
        return whole[0].encode(text, add_special_tokens=False).ids

    return encode


def tokenized(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary: str = "byte_bpe_50k", id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, and the ids if asked for. Of a document that is cut, the first
    piece is the one that may be shorter."""
    kind = docs.schema[id_col].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary)
        for batch in batches:
            for part in pieces(batch):
                row, piece, start, length, crc, values = [], [], [], [], [], []
                for i, text in enumerate(part.column("text").to_pylist()):
                    ids = np.array([*encode(text or ""), end_id], "<u4")
                    first = (len(ids) - 1) % capacity + 1
                    for k, b in enumerate(range(first, len(ids) + 1, capacity)):
                        a = max(0, b - capacity) if k else 0
                        row.append(i)
                        piece.append(k)
                        start.append(a)
                        length.append(b - a)
                        crc.append(zlib.crc32(ids[a:b].tobytes()))
                        if with_ids:
                            values.append(ids[a:b].astype(np.int32))
                columns = {
                    "doc_id": part.column("doc_id").take(pa.array(row, pa.int32())), "piece": pa.array(piece, pa.int32()), "start": pa.array(start, pa.int64()),
                    "length": pa.array(length, pa.int64()), "ids_crc32": pa.array(crc, pa.int64()),
                } | ({"ids": pa.array(values, pa.list_(pa.int32()))} if with_ids else {})
                yield pa.RecordBatch.from_arrays(list(columns.values()), list(columns))

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(
        kernel, f"doc_id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint" + ", ids array<int>" * with_ids
    )


def fullest(counts: np.ndarray, room: int) -> list[int]:
    """Lengths (with repetition, no more than counts[length] of each) whose sum is the largest possible up to room."""
    reach = 1
    mask = (1 << (room + 1)) - 1
    steps: list[tuple[int, int]] = []  # (length taken at once, what could be reached before)
    for n in range(min(room, len(counts) - 1), 0, -1):
        left, times = min(int(counts[n]), room // n), 1
        while left > 0:  # 1, 2, 4, ... copies: any number of them
            k = min(times, left)
            steps.append((n, k, reach))
            reach |= (reach << (n * k)) & mask
            left, times = left - k, times * 2
        if reach >> room & 1:
            break
    at = reach.bit_length() - 1
    out: list[int] = []
    for n, k, before in reversed(steps):
        if not before >> at & 1:
            out += [n] * k
            at -= n * k
    return out


def minimum_bin_slack(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, list[int]]]:
    """(number of bins, lengths in each) that hold histogram[length] pieces of every length."""
    counts = np.zeros(capacity + 1, np.int64)
    for n, k in histogram.items():
        counts[n] = k
    plan = []
    for n in range(capacity, 0, -1):
        while counts[n] > 0:
            counts[n] -= 1
            rest = fullest(counts[: min(n, capacity - n) + 1], capacity - n) if n < capacity else []
            counts[n] += 1
            need = np.bincount([n, *rest], minlength=capacity + 1)
            used = np.flatnonzero(need)
            times = int((counts[used] // need[used]).min())
            counts -= need * times
            plan.append((times, [n, *rest]))
    return plan


def plan_table(plan: list[tuple[int, list[int]]]) -> np.ndarray:
    """Rows (length, first number, copies in a bin, first bin, place in the bin) in the order of length and number."""
    taken: dict[int, int] = {}
    rows, bin_no = [], 0
    for times, lengths in plan:
        place = 0
        for n in sorted(set(lengths), reverse=True):
            k = lengths.count(n)
            rows.append((n, taken.get(n, 0), k, bin_no, place))
            taken[n] = taken.get(n, 0) + k * times
            place += n * k
        bin_no += times
    return np.array(sorted(rows), np.int64).reshape(-1, 5)


def packed(parts: DataFrame, capacity: int = CAPACITY, bucket_rows: int = 500) -> DataFrame:
    """Adds sequence_id and offset to rows that have a length of 1 to capacity. Full pieces take negative sequence ids of their own.
    A length has as many buckets as its rows take."""
    spark = parts.sparkSession
    counted = {r["length"]: r["count"] for r in parts.groupBy("length").count().collect()}
    table = plan_table(minimum_bin_slack({n: k for n, k in counted.items() if n < capacity}, capacity))
    names = parts.columns
    buckets = F.create_map(*[F.lit(x) for n, k in sorted(counted.items()) for x in (n, -(-k // bucket_rows))]) if counted else F.lit(None).cast("map<bigint,int>")
    salted = parts.filter(F.col("length") < capacity).withColumn("salt", F.pmod(F.xxhash64(*names), F.element_at(buckets, F.col("length"))).cast("int"))
    sizes = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("salt").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sizes.select(F.col("length").alias("o_length"), F.col("salt").alias("o_salt"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("o_before"))
    numbered = salted.withColumn("number", F.row_number().over(Window.partitionBy("length", "salt").orderBy(*[c for c in names if c != "length"])) - 1)
    numbered = numbered.join(offsets, (F.col("length") == F.col("o_length")) & (F.col("salt") == F.col("o_salt"))).select(*names, (F.col("number") + F.col("o_before")).cast("long").alias("number"))
    held = spark.sparkContext.broadcast(table)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = held.value
        order = (table[:, 0] << 44) | table[:, 1]
        for batch in batches:
            n, number = batch.column("length").to_numpy(zero_copy_only=False), batch.column("number").to_numpy(zero_copy_only=False)
            r = table[np.searchsorted(order, (n << 44) | number, side="right") - 1]
            nth = number - r[:, 1]
            columns = [*(batch.column(c) for c in names), pa.array(r[:, 3] + nth // np.maximum(1, r[:, 2])), pa.array(r[:, 4] + nth % np.maximum(1, r[:, 2]) * n)]
            yield pa.RecordBatch.from_arrays(columns, [*names, "sequence_id", "offset"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in parts.schema) + ", sequence_id bigint, offset bigint"
    full = parts.filter(F.col("length") == capacity).select(*names, (-1 - F.monotonically_increasing_id()).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    return numbered.mapInArrow(kernel, schema).unionByName(full)


def pack_documents(docs: DataFrame, capacity: int = CAPACITY, end_id: int = END_ID, vocabulary: str = "byte_bpe_50k", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece."""
    return packed(materialize(tokenized(docs, capacity, end_id, vocabulary, id_col, text_col), "pieces"), capacity)


def sequences(docs: DataFrame, packed_pieces: DataFrame, capacity: int = CAPACITY, **how) -> DataFrame:
    """sequence_id, ids: the packed sequences themselves, each at most `capacity` ids."""
    ids = tokenized(docs, capacity, with_ids=True, **how).dropDuplicates(["doc_id", "piece", "start", "ids_crc32"])
    joined = packed_pieces.alias("p").join(ids.alias("t"), F.expr("p.doc_id <=> t.doc_id and p.piece = t.piece and p.start = t.start and p.ids_crc32 = t.ids_crc32"))
    ordered = joined.select("p.sequence_id", F.struct("p.offset", "t.ids").alias("part"))
    return ordered.groupBy("sequence_id").agg(F.array_sort(F.collect_list("part")).alias("parts")).select("sequence_id", F.flatten("parts.ids").alias("ids"))
