"""Sharding by histogram sort: exact byte histograms over candidate key boundaries, refined until the
splitters meet the tolerance, then one exchange. DataFrame operations only.

Keys are 62-bit: 31 bits of the text's hash, then 31 bits of the id's, so equal texts are neighbours and yet a
text that holds a third of all rows can be cut anywhere. Each round counts the bytes below 256 probes inside
every interval that still holds a target, and replaces the interval by the probe cell that the target falls in.

Nulls: a null text has size 1 and no crc (0); a null id hashes to a constant. Rows alike in id and text share a key and so a
shard. An empty table gives no rows. Other columns are ignored; their names cannot clash, as columns are
selected and renamed first.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize

KEY_BITS, ROUND_BITS = 62, 8


def keyed(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, key of every row."""
    text = F.col(text_col)
    low = F.lit((1 << 31) - 1)
    return docs.select(
        F.col(id_col).alias("doc_id"),
        (F.coalesce(F.octet_length(text), F.lit(0)) + 1).cast("long").alias("size"),
        F.coalesce(F.crc32(text), F.lit(0)).cast("long").alias("text_crc32"),
        (F.shiftleft(F.xxhash64(text).bitwiseAND(low), 31) + F.xxhash64(F.lit(7), F.col(id_col)).bitwiseAND(low)).alias("key"),
    )


def splitters(rows: DataFrame, shards: int, tolerance: float = 1e-4) -> tuple[list[int], int, int]:
    """Boundaries b_1 < ... so that the bytes of keys below b_i are within tolerance·total/shards of i·total/shards,
    or as near as whole keys allow; also rounds taken and rows counted. The driver holds at most
    shards·256 counts a round."""
    total = rows.agg(F.sum("size"), F.count("*")).first()
    all_bytes, n = int(total[0] or 0), int(total[1])
    slack = tolerance * all_bytes / shards
    goals = {i: i * all_bytes / shards for i in range(1, shards)}
    open_at = dict.fromkeys(goals, (0, 0.0))  # target: (prefix that holds it, bytes below that prefix)
    found: dict[int, int] = {}
    width, rounds = KEY_BITS, 0
    while open_at and all_bytes:
        step = min(ROUND_BITS, width)
        prefixes = sorted({p for p, _ in open_at.values()})
        scan = rows if width == KEY_BITS else rows.filter(F.shiftright("key", width).isin(prefixes))
        cells: dict[int, list[tuple[int, int]]] = {}
        for cell, size in scan.groupBy(F.shiftright("key", width - step).alias("cell")).agg(F.sum("size")).collect():
            cells.setdefault(cell >> step, []).append((cell, int(size)))
        width, rounds = width - step, rounds + 1
        for i, (prefix, below) in list(open_at.items()):
            for cell, size in sorted(cells.get(prefix, [])):
                if below + size >= goals[i]:
                    under, over = goals[i] - below, below + size - goals[i]
                    if min(under, over) <= slack or width == 0:
                        found[i] = (cell if under <= over else cell + 1) << width
                        del open_at[i]
                    else:
                        open_at[i] = (cell, below)
                    break
                below += size
    return [found.get(i, 0) for i in range(1, shards)], rounds, n


def histogram_shards(docs: DataFrame, shards: int = 8, tolerance: float = 1e-4, rows_per_slot_bucket: int = 50_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard, key. Slots number each shard's rows without gaps: a
    shard's rows are dealt into buckets by id hash, counted, and numbered from the bucket's offset, so no task
    needs a whole shard."""
    slim = materialize(keyed(docs, id_col, text_col), "shard-keys")
    cuts, _, n = splitters(slim, shards, tolerance)
    shard = sum(((F.col("key") >= F.lit(c)).cast("int") for c in cuts), F.lit(0))
    buckets = max(8, -(-n // rows_per_slot_bucket) * 2)
    dealt = slim.withColumn("shard", shard.cast("int")).withColumn("bucket", F.pmod(F.xxhash64("doc_id", "key", "size"), F.lit(buckets)).cast("int"))
    offsets = dealt.groupBy("shard", "bucket").agg(F.count("*").alias("in_bucket"))
    before = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = offsets.select(F.col("shard").alias("o_shard"), F.col("bucket").alias("o_bucket"), F.coalesce(F.sum("in_bucket").over(before), F.lit(0)).alias("offset"))
    place = Window.partitionBy("shard", "bucket").orderBy("key", "doc_id", "text_crc32")
    numbered = dealt.withColumn("place", F.row_number().over(place))
    return numbered.join(offsets, (F.col("shard") == F.col("o_shard")) & (F.col("bucket") == F.col("o_bucket"))).select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard",
        (F.col("offset") + F.col("place") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "key",
    )


def write_shards(docs: DataFrame, path: str, shards: int = 8, id_col: str = "doc_id", text_col: str = "text", task_bytes: int = 128 << 20) -> None:
    """The rows themselves, exchanged once and written under path/shard=N, by a task for each `task_bytes` of a shard's text."""
    slim = materialize(keyed(docs, id_col, text_col), "shard-keys")
    cuts, _, _ = splitters(slim, shards)
    tasks_per_shard = max(1, -(-int(slim.agg(F.sum("size")).first()[0] or 0) // (shards * task_bytes)))
    low = F.lit((1 << 31) - 1)
    key = F.shiftleft(F.xxhash64(text_col).bitwiseAND(low), 31) + F.xxhash64(F.lit(7), F.col(id_col)).bitwiseAND(low)
    shard = sum(((key >= F.lit(c)).cast("int") for c in cuts), F.lit(0))
    name = "shard"
    while name in docs.columns:
        name += "_"
    docs.withColumn(name, shard).repartition(shards * tasks_per_shard, name, F.pmod(F.xxhash64(id_col), F.lit(tasks_per_shard))).write.partitionBy(name).parquet(path)
