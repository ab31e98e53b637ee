"""Streams over the given tables, run to the end of the input: equal to what batch plans give."""

from __future__ import annotations

from datetime import timedelta

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import attribution, trace
from ..operators.digest import DigestConfig
from ..streaming import digest_stream as ds
from . import oracle as o
from .queries import shared_folder
from .workloads import benchmark_items, table

#: Single events are short, so the window is small; the filter has a fixed size per day.
CONFIG = DigestConfig(m_bits=8192, sections=64, k=1, window=16)

EVENT = "hex(encode(concat_ws('|', event_id, epoch_us(ts), user_id, event_type, round(value * 10000)::bigint, props)))"
SETUP = f"""with trace(flow_key, seq, hx, day) as (select concat_ws('|', user_id, event_type), event_id, {EVENT}, floor(epoch_us(ts) / 86400000000)::int from events), {o.blocks(window=16)},
b as (select day, k.flow_key, block from blk k join trace t on k.flow_key = t.flow_key and k.seq = t.seq)"""
WORDS = f"""{SETUP}, e as (select day, {o.digest('block')} as d from b union all select day, {o.digest('block', 'flow_key')} from b)
select day as interval_id, ({o.number('d', '1', 8)} % 64)::int as section, (({o.number('d', '9', 12)} % 128) // 32)::int as word_ix, bit_or(1::bigint << ({o.number('d', '9', 12)} % 128 % 32)::int)::bigint as word from e group by all"""
BITS = f"{SETUP}, s as (select day, flow_key, {o.number(o.digest('block'), '1', 8)} % 64 as s from b) select day as interval_id, flow_key, (s // 32)::int as word_ix, bit_or(1::bigint << (s % 32)::int)::bigint as word from s group by all"


def stream_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table as a stream, be it one file or a folder of them. (As a pattern: a plain path of a stream has to be a folder.)"""
    return spark.readStream.schema(table(spark, sf_dir, name).schema).parquet(f"{sf_dir}/{name}.parque[t]")


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return trace.from_events(stream_of(spark, sf_dir, "events"))


def _written(spark: SparkSession, stream: DataFrame, mode: str = "append") -> DataFrame:
    folder = shared_folder(spark)
    schema = stream.schema
    ds.run_to_parquet(stream, f"{folder}/out", f"{folder}/checkpoint", mode)
    return spark.read.schema(schema).parquet(f"{folder}/out")


def stream_filter_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Filters of days from a stream, closed by a patch: the last open day is ORed in from the batch plan."""
    out = _written(spark, ds.filter_words(_events(spark, sf_dir), CONFIG))
    packets = trace.from_events(table(spark, sf_dir, "events"))
    last = packets.agg(F.max("interval_id")).first()[0]
    return ds.patch(out, ds.filter_words(packets.filter(F.col("interval_id") >= last), CONFIG))


def stream_bitmap(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = _written(spark, ds.flow_words(_events(spark, sf_dir), CONFIG))
    packets = trace.from_events(table(spark, sf_dir, "events"))
    last = packets.agg(F.max("interval_id")).first()[0]
    return ds.patch(out, ds.flow_words(packets.filter(F.col("interval_id") >= last), CONFIG))


def late_digest(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """Words of a stream that is stopped and goes on from its checkpoint, and how many late rows its watermark dropped: every
    fiftieth event comes with the second run, after its day was closed."""
    folder, events = shared_folder(spark), table(spark, sf_dir, "events")
    late = F.col("event_id") % 50 == 0
    schema = events.schema
    stream = lambda: ds.filter_words(trace.from_events(spark.readStream.schema(schema).option("recursiveFileLookup", True).parquet(f"{folder}/in")), CONFIG)
    events.filter(~late).write.parquet(f"{folder}/in/first")
    progress = ds.run_to_parquet(stream(), f"{folder}/out", f"{folder}/checkpoint")
    events.filter(late).write.parquet(f"{folder}/in/second")
    progress += ds.run_to_parquet(stream(), f"{folder}/out", f"{folder}/checkpoint")
    out = spark.read.schema("interval_id int, section int, word_ix int, word bigint").parquet(f"{folder}/out")
    return out, ds.dropped_rows(progress)


def stream_late_patch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Late packets are dropped by the watermark and ORed in afterwards, with the day that is still open; the digest is whole again. A
    part of the packets comes twice, which changes nothing."""
    out, _ = late_digest(spark, sf_dir)
    packets = trace.from_events(table(spark, sf_dir, "events"))
    last = packets.agg(F.max("interval_id")).first()[0]
    return ds.patch(out, ds.filter_words(packets.filter((F.col("seq") % 50 == 0) | (F.col("seq") % 10 == 0) | (F.col("interval_id") >= last)), CONFIG))


GAP, LATE = "6 hours", "1 hour"


def stream_sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sessions of a stream as the watermark closes them; those still open at the end of the input from the batch plan."""
    columns = ["flow_key", F.unix_micros("first_ts").alias("first_us"), "packets", F.col("bytes").cast("bigint").alias("bytes")]
    out = _written(spark, ds.sessions(_events(spark, sf_dir), GAP, LATE))
    packets = trace.from_events(table(spark, sf_dir, "events"))
    mark = packets.agg((F.unix_micros(F.max("ts")) - 3_600_000_000).alias("mark")).first()["mark"]
    # by the last packet, not by the window: a filter on a session window would be pushed below the merging of sessions
    own = packets.groupBy("flow_key", F.session_window("ts", GAP).alias("w")).agg(F.count("*").alias("packets"), F.sum(F.octet_length("payload")).alias("bytes"), F.max(F.unix_micros("ts")).alias("last"))
    open_ = F.floor((F.col("last") + 6 * 3_600_000_000) / 1000) > F.floor(F.lit(mark) / 1000)  # the stream's mark is in whole milliseconds
    still = own.filter(open_).select("flow_key", F.col("w.start").alias("first_ts"), "packets", "bytes")
    return out.select(*columns).unionByName(still.select(*columns))


def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Filters of two days that slide by one, each batch's changed words written as they come and ORed when read."""
    folder = shared_folder(spark)
    stream = ds.filter_words(_events(spark, sf_dir), CONFIG, "2 days", "1 day")
    ds.run_each(stream, f"{folder}/checkpoint", lambda df, n: df.write.mode("overwrite").parquet(f"{folder}/out/batch={n}"))
    kept = spark.read.schema("interval_id int, section int, word_ix int, word bigint").parquet(f"{folder}/out/*")
    return ds.patch(kept, kept.limit(0))


def stream_reassembled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks of conversations across their turns, held in state until a day of silence. (The table has no times: an hour each.)"""
    key, value = ds.STATE_STORE
    before = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        turns = trace.from_conversations(stream_of(spark, sf_dir, "conversations"))
        hour = F.timestamp_seconds(F.lit(1704067200) + F.col("flow_key").cast("long") % 24 * 3600)
        out = _written(spark, ds.reassembled_blocks(turns.withColumn("ts", hour), ttl=timedelta(days=1), late="1 day"))
    finally:
        spark.conf.set(key, before) if before is not None else spark.conf.unset(key)
    return out.select("flow_key", F.col("start").cast("int").alias("start"), F.col("size").cast("int").alias("size"), F.md5("block").alias("digest"))


def stream_watch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A watch list of known texts' blocks against documents as they pass by, each told once."""
    docs = trace.from_documents(stream_of(spark, sf_dir, "documents"))
    listed = attribution.excerpt_blocks(benchmark_items(spark, sf_dir), DigestConfig())
    out = _written(spark, ds.watch(docs.withColumn("ts", F.lit("2024-01-01").cast("timestamp")), listed, DigestConfig(), late=LATE))
    return out.select(F.col("excerpt_id").alias("item_id"), "flow_key", "block_no")


SESSIONS = f"""with t as (select concat_ws('|', user_id, event_type) as flow_key, epoch_us(ts) as us, len({EVENT}) // 2 as b from events),
g as (select *, case when us - lag(us) over w < 21600000000 then 0 else 1 end as new from t window w as (partition by flow_key order by us)),
s as (select *, sum(new) over (partition by flow_key order by us rows unbounded preceding) as s from g)
select flow_key, min(us) as first_us, count(*) as packets, sum(b)::bigint as bytes from s group by flow_key, s"""

SLIDING = WORDS.replace("select day as interval_id", "select day - back as interval_id").replace("from e group by all", "from e, range(2) g(back) group by all")
REASSEMBLED = f"with turns as (select conv_id, turn, hex(encode(coalesce(text, ''))) as h from conversations), trace(flow_key, seq, hx) as (select conv_id::varchar, 0::bigint, string_agg(h, '' order by turn) from turns group by conv_id), {o.blocks()} select flow_key, start, size, md5(block) as digest from blk"
WATCH = f"with {o.DOCS}, {o.blocks()}, xt(flow_key, seq, hx) as (select item_id::varchar, 0::bigint, hex(encode(text)) from benchmark where text <> ''), {o.blocks('xt', 'xblk')} select distinct x.flow_key::bigint as item_id, b.flow_key, x.block_no from xblk x join blk b on md5(x.block) = md5(b.block)"

QUERIES = {f.__name__: f for f in (stream_filter_words, stream_bitmap, stream_late_patch, stream_sessions, stream_sliding, stream_reassembled, stream_watch)}
ORACLE = {"stream_filter_words": WORDS, "stream_bitmap": BITS, "stream_late_patch": WORDS, "stream_sessions": SESSIONS, "stream_sliding": SLIDING, "stream_reassembled": REASSEMBLED, "stream_watch": WATCH}
