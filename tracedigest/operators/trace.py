"""Traces from tables: one row per packet, with flow, protocol, order and payload bytes."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _trace(df: DataFrame, flow: Column, src: Column, dst: Column, proto: Column, seq: Column, payload: Column, interval: Column | None = None, ts: Column | None = None) -> DataFrame:
    return df.select(
        (interval if interval is not None else F.lit(0)).cast("int").alias("interval_id"), (ts if ts is not None else F.lit(None)).cast("timestamp").alias("ts"), flow.cast("string").alias("flow_key"),
        src.cast("string").alias("src"), dst.cast("string").alias("dst"), proto.cast("string").alias("proto"), seq.cast("bigint").alias("seq"), payload.alias("payload"),
    )


def _bytes(c: str) -> Column:
    return F.encode(F.coalesce(F.col(c), F.lit("")), "UTF-8")


def from_documents(df: DataFrame, interval_docs: int | None = None, by: str = "doc_id") -> DataFrame:
    """One packet per document. by: "doc_id" (a flow each), "source" (source and language), or "skew" (every sixteenth id has a flow of its
    own, the others share their source's)."""
    shared = F.concat_ws("|", "source", "lang")
    flow = {"doc_id": F.col("doc_id"), "source": shared, "skew": F.when(F.col("doc_id") % 16 == 0, F.col("doc_id").cast("string")).otherwise(shared)}[by]
    interval = F.floor(F.col("doc_id") / interval_docs) if interval_docs else None
    return _trace(df, flow, F.col("source"), F.col("lang"), F.lit("doc"), F.lit(0) if by == "doc_id" else F.col("doc_id"), _bytes("text"), interval)


def from_conversations(df: DataFrame, interval_convs: int | None = None) -> DataFrame:
    """One packet per turn; the role is the protocol and the direction."""
    interval = F.floor(F.col("conv_id") / interval_convs) if interval_convs else None
    other = F.when(F.col("role") == "user", "assistant").otherwise("user")
    return _trace(df, F.col("conv_id"), F.col("role"), other, F.col("role"), F.col("turn"), _bytes("text"), interval)


def from_pages(df: DataFrame, by: str = "page_id") -> DataFrame:
    host, path = F.regexp_extract("url", "://([^/?#]*)", 1), F.regexp_extract("url", "://[^/?#]*([^?#]*)", 1)
    return _trace(df, host if by == "host" else F.col("page_id"), host, path, F.regexp_extract("url", "^([a-z]+)://", 1), F.lit(0) if by == "page_id" else F.col("page_id"), _bytes("html"))


def _cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("bigint")


def from_ledger(lineitem: DataFrame, orders: DataFrame, supplier: DataFrame, customer: DataFrame, yearly: bool = False) -> DataFrame:
    """One packet per line; flows are pairs of nations (supplier's, customer's). Numbers as integers, so the text is the same everywhere."""
    day = F.to_date("l_shipdate")
    text = F.concat_ws(
        "|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", _cents("l_quantity"), _cents("l_extendedprice"), _cents("l_discount"), _cents("l_tax"), "l_returnflag", "l_linestatus", F.datediff(day, F.lit("1970-01-01").cast("date"))
    )
    j = lineitem.join(orders.select("o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    j = j.join(supplier.select("s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    j = j.join(customer.select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    flow = F.concat_ws("|", "s_nationkey", "c_nationkey")
    seq = F.col("l_orderkey") * 16 + F.col("l_linenumber")
    return _trace(j, flow, F.col("s_nationkey"), F.col("c_nationkey"), F.col("l_returnflag"), seq, F.encode(text, "UTF-8"), F.year("l_shipdate") if yearly else None, F.col("l_shipdate").cast("timestamp"))


def from_events(df: DataFrame) -> DataFrame:
    """One packet per event; the interval is the day since 1970."""
    ts = F.col("ts").cast("timestamp")
    text = F.concat_ws("|", "event_id", F.unix_micros(ts), "user_id", "event_type", F.round(F.col("value") * 10000).cast("bigint"), "props")
    return _trace(df, F.concat_ws("|", "user_id", "event_type"), F.col("user_id"), F.col("event_type"), F.col("event_type"), F.col("event_id"), F.encode(text, "UTF-8"), F.floor(F.unix_seconds(ts) / 86400), ts)


def keep_protocols(df: DataFrame, protocols: list[str]) -> DataFrame:
    """What the capture filter records; the rest is dropped."""
    return df.filter(F.col("proto").isin(protocols))


def assign_interval(df: DataFrame, seconds: int | None = None, target_bytes: int | None = None, grain: int = 60) -> DataFrame:
    """Intervals of a fixed time, or of about a fixed number of bytes in the order of time: bytes are summed by grains of
    `grain` seconds, and the running sum over grains (never over packets) numbers the intervals. An interval holds whole grains, so it
    has target_bytes and less than a grain more. Packets without a time are interval 0."""
    if seconds:
        return df.withColumn("interval_id", F.floor(F.unix_seconds("ts") / seconds).cast("int"))
    own = df.drop("interval_id").withColumn("grain", F.coalesce(F.floor(F.unix_seconds("ts") / grain), F.lit(-1)))
    per = own.groupBy("grain").agg(F.sum(F.octet_length("payload")).alias("grain_bytes"))
    before = F.coalesce(F.sum("grain_bytes").over(Window.orderBy("grain").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    named = per.select("grain", F.floor(before / max(1, target_bytes)).cast("int").alias("interval_id"))
    return own.join(named, "grain").select(*df.columns) if "interval_id" in df.columns else own.join(named, "grain").drop("grain")


#: Bytes of a flow that may meet in one row.
FLOW_BYTES = 64 << 20


def _order(df: DataFrame) -> list[str]:
    """What orders a flow's packets: their number, and the fragment's where packets were cut."""
    return ["seq", "frag"] if "frag" in df.columns else ["seq"]


def reassemble(df: DataFrame, by: tuple[str, ...] = ("interval_id", "flow_key"), separator: bytes = b"", max_bytes: int = FLOW_BYTES) -> DataFrame:
    """One payload per flow: packets in order, joined without (or with) a separator. Excerpts that cross packets then have
    their blocks. A flow's bytes meet in one row: beyond max_bytes this fails, and flow_pieces does it in pieces."""
    hx = lambda c: F.hex(F.coalesce(c, F.lit(b"")))
    joined = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct(*_order(df), "payload"))), lambda x: hx(x["payload"])), separator.hex().upper())
    size = F.sum(F.octet_length("payload"))
    whole = F.when(size > max_bytes, F.raise_error(F.lit(f"a flow has more than {max_bytes} bytes in an interval: use flow_pieces"))).otherwise(F.unhex(joined))
    out = df.groupBy(*by).agg(F.min("ts").alias("ts"), F.min("src").alias("src"), F.min("dst").alias("dst"), F.min("proto").alias("proto"), F.lit(0).cast("bigint").alias("seq"), whole.alias("payload"))
    return out.select("interval_id", "ts", "flow_key", "src", "dst", "proto", "seq", "payload")


def flow_pieces(df: DataFrame, overlap: int, separator: bytes = b"", piece: int = 8 << 20) -> DataFrame:
    """interval_id, flow_key, seq, payload: each flow's bytes in order, in pieces of about `piece` bytes that share `overlap` bytes with
    the next, so every block of the flow is a block of a piece, and of no piece alone. Packets stream in order: a flow of any
    size takes one piece of memory."""
    keys = ["interval_id", "flow_key"]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held, size, number = None, [], 0, 0
        out: list[tuple] = []

        def ready():
            made = pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), (pa.int32(), pa.string(), pa.int64(), pa.binary()), strict=True)], [*keys, "seq", "payload"])
            out.clear()
            return made

        waiting = 0
        for batch in batches:
            for i, flow, payload in zip(*(batch.column(c).to_pylist() for c in keys), batch.column("payload"), strict=True):
                raw = payload.as_py() or b""
                if (i, flow) != now:
                    if now is not None:
                        out.append((*now, number, b"".join(held)))
                    now, held, size, number = (i, flow), [raw], len(raw), 0
                else:
                    held += [separator, raw] if separator else [raw]
                    size += len(separator) + len(raw)
                if size >= piece:
                    whole = b"".join(held)
                    out.append((*now, number, whole))
                    held, size, number = [whole[-overlap:]], min(overlap, len(whole)), number + 1
                waiting += len(raw)
                if waiting >= piece and out:
                    yield ready()
                    waiting = 0
        if now is not None:
            out.append((*now, number, b"".join(held)))
        if out:
            yield ready()

    order = [*keys, *_order(df)]
    rows = df.select(*order, "payload").repartition(*keys).sortWithinPartitions(*order, "payload")
    return rows.mapInArrow(kernel, "interval_id int, flow_key string, seq bigint, payload binary")


def fragment(df: DataFrame, size: int) -> DataFrame:
    """Payloads cut into packets of `size` bytes: what an evader does. A column frag numbers a packet's fragments."""
    n = F.greatest(F.ceil(F.octet_length("payload") / size), F.lit(1)).cast("int")
    cut = df.withColumn("frag", F.explode(F.sequence(F.lit(0), n - 1)))
    return cut.withColumn("payload", F.expr(f"substring(payload, frag * {size} + 1, {size})"))


def with_view(df: DataFrame, view: str, key: int = 5) -> DataFrame:
    """view "plain": as taken at the endpoints; "wire": as an enciphered link shows it. A substitution of half bytes by built-in
    functions stands in for the cipher."""
    if view == "plain":
        return df
    digits = "0123456789ABCDEF"
    return df.withColumn("payload", F.unhex(F.translate(F.hex("payload"), digits, "".join(digits[i ^ key] for i in range(16)))))
