"""Compressed bitmap tables, opened only for the intervals that a query hits."""

from __future__ import annotations

import lzma
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

FILTERS = [{"id": lzma.FILTER_LZMA2, "preset": 6}]
CODECS = {
    "lzma2": (lambda b: lzma.compress(b, format=lzma.FORMAT_RAW, filters=FILTERS), lambda b: lzma.decompress(b, format=lzma.FORMAT_RAW, filters=FILTERS)),
    "zlib": (lambda b: zlib.compress(b, 9), zlib.decompress),
    "none": (bytes, bytes),
}


#: Flows in one compressed table, about.
SHARD_FLOWS = 65_536


def pack_index(flowbits: DataFrame, codec: str = "lzma2", shards: int | None = None) -> DataFrame:
    """interval_id, shard, flows, width, raw_bytes, packed: one compressed table per interval and shard of flows. Without `shards` the
    interval with most flows decides their number, so that no table has many more than SHARD_FLOWS flows."""
    encode = CODECS[codec][0]
    if shards is None:
        most = flowbits.groupBy("interval_id").count().agg(F.max("count")).first()[0] or 0
        shards = -(-max(1, most) // SHARD_FLOWS)

    def pack(table: pa.Table) -> pa.Table:
        table = table.sort_by("flow_key")
        maps = table.column("bitmap").to_pylist()
        raw = b"".join(maps)
        return pa.table(
            {
                "interval_id": table.column("interval_id").slice(0, 1), "shard": table.column("shard").slice(0, 1), "flows": pa.array([table.column("flow_key").to_pylist()], pa.list_(pa.string())),
                "width": pa.array([len(maps[0])], pa.int32()), "raw_bytes": pa.array([len(raw)], pa.int64()), "packed": pa.array([encode(raw)], pa.binary()),
            }
        )

    sharded = flowbits.withColumn("shard", F.pmod(F.xxhash64("flow_key"), F.lit(shards)).cast("int"))
    return sharded.groupBy("interval_id", "shard").applyInArrow(pack, "interval_id int, shard int, flows array<string>, width int, raw_bytes bigint, packed binary")


def unpack_index(archive: DataFrame, hits: DataFrame | None = None, codec: str = "lzma2", opened=None) -> DataFrame:
    """flowbits again, of the intervals in `hits` only: nothing else is read or decompressed. opened: an accumulator that counts
    opened tables."""
    decode = CODECS[codec][1]
    wanted = archive if hits is None else archive.join(F.broadcast(hits.select("interval_id").distinct()), "interval_id", "left_semi")

    def unpack(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1).to_pylist()[0]
                raw, w, flows = decode(row["packed"]), row["width"], row["flows"]
                if opened is not None:
                    opened.add(1)
                maps = pa.Array.from_buffers(pa.binary(w), len(flows), [None, pa.py_buffer(raw)]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array([row["interval_id"]] * len(flows), pa.int32()), pa.array(flows, pa.string()), maps], ["interval_id", "flow_key", "bitmap"])

    return wanted.mapInArrow(unpack, "interval_id int, flow_key string, bitmap binary")


def pack_filter(packed_sections: DataFrame, codec: str = "zlib") -> DataFrame:
    """interval_id, raw_bytes, packed_bytes of filter bytes compressed as they are, some thousand rows together: high entropy, little
    to gain."""
    encode = CODECS[codec][0]

    def size(table: pa.Table) -> pa.Table:
        raw = b"".join(table.sort_by([("section", "ascending"), ("chunk", "ascending")]).column("bits").to_pylist())
        return pa.table({"interval_id": table.column("interval_id").slice(0, 1), "raw_bytes": pa.array([len(raw)], pa.int64()), "packed_bytes": pa.array([len(encode(raw))], pa.int64())})

    part = (F.col("section") / 1024).cast("int"), (F.col("chunk") / 1024).cast("int")
    each = packed_sections.withColumn("part", F.struct(*part)).groupBy("interval_id", "part").applyInArrow(size, "interval_id int, raw_bytes bigint, packed_bytes bigint")
    return each.groupBy("interval_id").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("packed_bytes").alias("packed_bytes"))
