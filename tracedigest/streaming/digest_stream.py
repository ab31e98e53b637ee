"""Digests of streams: interval filters and bitmaps by watermark, late packets, reassembly, standing queries.

Blocks are row-local (the Arrow function), so a stream carries block rows only to the partial aggregation in its own
task. OR may be repeated, so replays and restarts leave digests unchanged. Under a watermark the last open interval is never
emitted and late rows are dropped; both would be misses, so `patch` ORs them in afterwards.
"""

from __future__ import annotations

import pickle
from collections.abc import Callable, Iterator
from datetime import timedelta

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.hashing import block_digest, flow_digest, section_of
from ..operators import blocking, membership
from ..operators.digest import DigestConfig


def packets(events: DataFrame) -> DataFrame:
    """Trace columns of an event stream, its time as a real timestamp (watermarks reject the zoneless type)."""
    from ..operators import trace

    return trace.from_events(events)


def block_stream(trace: DataFrame, config: DigestConfig) -> DataFrame:
    """ts, flow_key, block of a batch or streaming trace; row-local."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            row, _, _, _, blocks = blocking.winnow_batch(batch.column("payload").to_pylist(), config.window, config.overlap, config.threshold, config.keep_equal)
            at = pa.array(row)
            yield pa.RecordBatch.from_arrays([batch.column("ts").take(at), batch.column("flow_key").take(at), pa.array(blocks, pa.binary())], ["ts", "flow_key", "block"])

    return trace.select("ts", "flow_key", "payload").mapInArrow(kernel, "ts timestamp, flow_key string, block binary")


def interval_of(window) -> F.Column:
    return F.floor(F.unix_seconds(window["start"]) / 86400).cast("int")


def filter_words(trace: DataFrame, config: DigestConfig, every: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """interval_id, section, word_ix, word of tumbling (or sliding) intervals. The same plan serves batch and stream."""
    blocks = block_stream(trace, config)
    if trace.isStreaming:
        blocks = blocks.withWatermark("ts", late)
    both = blocks.withColumn("digest", F.explode(F.array(block_digest(F.col("block"), config.salt), flow_digest(F.col("block"), F.col("flow_key"), config.salt))))
    rows = membership.probes(both.select("ts", "digest"), config.m_bits, config.sections, config.k)
    span = F.window("ts", every, slide) if slide else F.window("ts", every)
    words = rows.groupBy(span.alias("w"), "section", "word_ix").agg(F.bit_or("mask").alias("word"))
    return words.select(interval_of(F.col("w")).alias("interval_id"), "section", "word_ix", "word")


def flow_words(trace: DataFrame, config: DigestConfig, every: str = "1 day", late: str = "1 hour") -> DataFrame:
    """interval_id, flow_key, word_ix, word: the bitmap index of a stream."""
    blocks = block_stream(trace, config)
    if trace.isStreaming:
        blocks = blocks.withWatermark("ts", late)
    rows = blocks.withColumn("section", section_of(block_digest(F.col("block"), config.salt), config.sections))
    bit = F.expr("shiftleft(1L, section % 32)")
    words = rows.groupBy(F.window("ts", every).alias("w"), "flow_key", F.floor(F.col("section") / 32).cast("int").alias("word_ix")).agg(F.bit_or(bit).alias("word"))
    return words.select(interval_of(F.col("w")).alias("interval_id"), "flow_key", "word_ix", "word")


def sessions(trace: DataFrame, gap: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """flow_key, first_ts, packets, bytes of each flow's sessions."""
    own = trace.withWatermark("ts", late) if trace.isStreaming else trace
    out = own.groupBy("flow_key", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("packets"), F.sum(F.octet_length("payload")).alias("bytes"))
    return out.select("flow_key", F.col("w.start").alias("first_ts"), "packets", "bytes")


def patch(words: DataFrame, late: DataFrame) -> DataFrame:
    """Stored words with late (or last, or repeated) words ORed in."""
    return membership.merge(words, late)


def run_to_parquet(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> list[dict]:
    """All available input, to Parquet, to its end; the progress of its batches. Called again with the same checkpoint it goes on where
    it ended."""
    query = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()
    return list(query.recentProgress)


def dropped_rows(progress: list[dict]) -> int:
    """Rows that came later than the watermark allows, by a query's progress."""
    return sum(op["numRowsDroppedByWatermark"] for p in progress for op in p["stateOperators"])


def run_each(stream: DataFrame, checkpoint: str, sink: Callable[[DataFrame, int], None], mode: str = "update") -> None:
    """All available input through foreachBatch; with OR sinks a repeated batch does no harm."""
    query = stream.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    query.awaitTermination()


class Reassembler(StatefulProcessor):
    """Blocks across a flow's packets with bounded state: only the bytes after the last certain boundary are held, and a window
    before it. Emits flow_key, start, size, block as soon as they are certain: at any time all blocks that the bytes so far have,
    so a flow's end needs no mark or timer."""

    def __init__(self, window: int = 64, overlap: int = 4, ttl_ms: int | None = None):
        self.window, self.width, self.ttl_ms = window, overlap + 1, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.state = handle.getValueState("tail", "raw binary")

    def handleInputRows(self, key, rows, timer_values) -> Iterator[pd.DataFrame]:  # noqa: N802
        base, tail, done, until = pickle.loads(self.state.get()[0]) if self.state.exists() else (0, b"", -1, None)
        batch = pd.concat(list(rows)).sort_values("seq")
        if self.ttl_ms is not None:
            # rows come before a batch's expired timers
            if until is not None and until <= timer_values.getCurrentWatermarkInMs():
                base, tail, done = 0, b"", -1
            for old in list(self.handle.listTimers()):
                self.handle.deleteTimer(old)
            until = int(batch["ts"].max().timestamp() * 1000) + self.ttl_ms
            self.handle.registerTimer(until)
        data = tail + b"".join(bytes(p) for p in batch["payload"])
        found = blocking.payload_bounds(data, self.window, self.width)
        out, last = [], None
        # bounds come from complete windows only, and no later window picks a place before the last one: all of these are certain
        for a, b in zip(found[:-1].tolist(), found[1:].tolist(), strict=True):
            if base + a > done and not (base and a < self.window):
                out.append((key[0], base + a, b - a + self.width, data[a : b + self.width]))
                last = a
        if last is not None:
            done = base + last
        keep = max(0, min(len(data), (done - base if done >= base else 0)) - 2 * self.window)
        self.state.update((pickle.dumps((base + keep, data[keep:], done, until)),))
        yield pd.DataFrame(out, columns=["flow_key", "start", "size", "block"])

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        """A flow that has been silent is forgotten; all its blocks are out already."""
        self.state.clear()
        yield pd.DataFrame([], columns=["flow_key", "start", "size", "block"])

    def close(self) -> None:
        pass


#: Blocks of a watch list that are sent to every task.
WATCHED = 1_000_000
BLOCKS = "flow_key string, start bigint, size bigint, block binary"


#: Where state is kept: the one that stateful processors need.
STATE_STORE = ("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def reassembled_blocks(trace: DataFrame, window: int = 64, overlap: int = 4, ttl: timedelta | None = None, late: str = "1 hour") -> DataFrame:
    """Blocks of flows across packets, stateful. Packets of a flow must arrive in order of seq, over batches (within one they are
    put in order). With a ttl the trace needs times: a flow that is silent for so long (by the watermark, `late` behind the newest
    time) is forgotten, and what it sends later begins anew."""
    if ttl is None:
        own = trace.select("flow_key", "seq", "payload").groupBy("flow_key")
        return own.transformWithStateInPandas(Reassembler(window, overlap), outputStructType=BLOCKS, outputMode="append", timeMode="None")
    own = trace.withWatermark("ts", late).select("flow_key", "ts", "seq", "payload").groupBy("flow_key")
    return own.transformWithStateInPandas(Reassembler(window, overlap, int(ttl.total_seconds() * 1000)), outputStructType=BLOCKS, outputMode="append", timeMode="EventTime")


def watch(trace: DataFrame, excerpt_blocks: DataFrame, config: DigestConfig, late: str | None = None) -> DataFrame:
    """excerpt_id, flow_key, ts, block_no of blocks on a watch list (excerpt_id, block_no, block) as they pass by: a
    stream-static join. Lists of up to WATCHED blocks are broadcast. late: a block that a flow sends again within this time is told once."""
    listed = excerpt_blocks.select("excerpt_id", "block_no", block_digest(F.col("block"), config.salt).alias("digest"))
    seen = block_stream(trace, config).withColumn("digest", block_digest(F.col("block"), config.salt))
    out = seen.join(F.broadcast(listed) if listed.count() <= WATCHED else listed, "digest").select("excerpt_id", "flow_key", "ts", "block_no")
    if late is None:
        return out
    if not trace.isStreaming:
        return out.dropDuplicates(["excerpt_id", "flow_key", "block_no"])
    return out.withWatermark("ts", late).dropDuplicatesWithinWatermark(["excerpt_id", "flow_key", "block_no"])


def read_events(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
