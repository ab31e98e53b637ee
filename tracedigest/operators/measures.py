"""Accuracy, storage and cost measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def flow_fpr(verdict: DataFrame, truth: DataFrame, excerpts: DataFrame, flows: int, by: tuple[str, ...] = ()) -> DataFrame:
    """excerpts, reported, false_flows, fpr: false flows over flows of the trace, averaged over excerpts."""
    false = verdict.join(truth.select("excerpt_id", "flow_key").withColumn("true_", F.lit(True)), ["excerpt_id", "flow_key"], "left")
    n = excerpts.agg(F.count("*").alias("excerpts"))
    per = false.groupBy(*by).agg(F.count("*").alias("reported"), F.sum(F.when(F.col("true_").isNull(), 1).otherwise(0)).cast("bigint").alias("false_flows"))
    return per.crossJoin(F.broadcast(n)).withColumn("fpr", F.round(F.col("false_flows") / (F.col("excerpts") * F.lit(flows)), 6))


def appearance_fpr(present: DataFrame, absent: DataFrame) -> DataFrame:
    """Share of absent excerpts that are reported present."""
    hit = absent.select("excerpt_id").join(present.select("excerpt_id").distinct().withColumn("hit", F.lit(1)), "excerpt_id", "left")
    return hit.agg(F.count("*").alias("absent"), F.count("hit").alias("present"), F.round(F.avg(F.coalesce("hit", F.lit(0))), 6).alias("fpr"))


def false_negatives(truth: DataFrame, verdict: DataFrame) -> DataFrame:
    """True pairs that were not reported; there must be none."""
    return truth.select("excerpt_id", "flow_key").join(verdict.select("excerpt_id", "flow_key"), ["excerpt_id", "flow_key"], "left_anti")


def reduction(raw_bytes: float, filter_bytes: float) -> float:
    return raw_bytes / filter_bytes


def overall_reduction(raw_bytes: float, filter_bytes: float, index_bytes: float) -> float:
    """Raw bytes over filter and compressed index together."""
    return raw_bytes / (filter_bytes + index_bytes)


def index_bytes(flows: int, sections: int) -> float:
    return flows * sections / 8


def index_share(index: float, filter_bytes: float) -> float:
    return index / filter_bytes


def symbol_counts(flowbits: DataFrame, symbol_bytes: int) -> DataFrame:
    """symbol, n: fixed-size chunks of the table's bytes, row by row (rows are padded to whole symbols)."""
    hx = F.hex("bitmap")
    n = F.ceil(F.length(hx) / (2 * symbol_bytes)).cast("int")
    rows = flowbits.select(F.rpad(hx, n * 2 * symbol_bytes, "0").alias("hx"), F.explode(F.sequence(F.lit(0), n - 1)).alias("i"))
    return rows.groupBy(F.expr(f"substring(hx, i * {2 * symbol_bytes} + 1, {2 * symbol_bytes})").alias("symbol")).agg(F.count("*").alias("n"))


def symbol_entropy(flowbits: DataFrame, symbol_bytes: int) -> DataFrame:
    """symbol_bytes, symbols, different, entropy (bits), bound (bytes, with the codeword list), best_ratio."""
    counted = symbol_counts(flowbits, symbol_bytes)
    total = counted.agg(F.sum("n").alias("total"))
    p = F.col("n") / F.col("total")
    out = counted.crossJoin(F.broadcast(total)).agg(F.sum("n").alias("symbols"), F.count("*").alias("different"), F.sum(-p * F.log2(p)).alias("h"))
    bound = F.col("symbols") * F.col("h") / 8 + F.col("different") * symbol_bytes
    return out.select(F.lit(symbol_bytes).alias("symbol_bytes"), "symbols", "different", F.round("h", 6).alias("entropy"), F.round(bound, 3).alias("bound"), F.round(F.col("symbols") * symbol_bytes / bound, 6).alias("best_ratio"))


def entropy_bound(chunks: float, entropy: float, different: float, symbol_bytes: int) -> float:
    return chunks * entropy / 8 + different * symbol_bytes


def block_size_hist(blocks: DataFrame) -> DataFrame:
    return blocks.groupBy("size").agg(F.count("*").alias("blocks"))


def true_negative_by_size(probed: DataFrame) -> DataFrame:
    """size, blocks, negatives, rate, share of all negatives, from rows with size and present."""
    neg = F.sum(F.when(~F.col("present"), 1).otherwise(0)).cast("bigint")
    per = probed.groupBy("size").agg(F.count("*").alias("blocks"), neg.alias("negatives"))
    total = per.agg(F.sum("negatives").alias("all_negatives"))
    return per.crossJoin(F.broadcast(total)).select("size", "blocks", "negatives", F.round(F.col("negatives") / F.col("blocks"), 6).alias("rate"), F.round(F.col("negatives") / F.col("all_negatives"), 6).alias("share"))


def flow_cdf(flows: DataFrame, cuts: list[int]) -> DataFrame:
    """cut, flows_under, share: the distribution of flow sizes at the given cuts, by one aggregation (no global sort)."""
    grid = flows.sparkSession.createDataFrame([(c,) for c in cuts], "cut bigint")
    hist = flows.groupBy("bytes").agg(F.count("*").alias("n"))
    under = F.sum(F.when(F.col("bytes") < F.col("cut"), F.col("n")).otherwise(0)).cast("bigint")
    return hist.crossJoin(F.broadcast(grid)).groupBy("cut").agg(under.alias("flows_under"), F.sum("n").alias("flows")).select("cut", "flows_under", "flows", F.round(F.col("flows_under") / F.col("flows"), 6).alias("share"))


def block_reduction(blocks: DataFrame, threshold: int) -> DataFrame:
    return blocks.agg(F.count("*").alias("seen"), F.count(F.when(F.col("size") >= threshold, 1)).alias("kept")).withColumn("d", F.round(F.col("seen") / F.col("kept"), 6))


def model_fpr(k: int, n: float, m: float) -> float:
    """False-positive rate of a filter of m bits with n elements."""
    return (1 - math.exp(-k * n / m)) ** k


def model_flow_fpr(p: float, blocks_per_excerpt: DataFrame) -> DataFrame:
    """Mean over excerpts of p to the number of their blocks (column n)."""
    return blocks_per_excerpt.agg(F.round(F.avg(F.pow(F.lit(p), F.col("n"))), 6).alias("model_fpr"))


def model_ones(flow_bytes: float, sections: int, stride: float = 32.0, collisions: bool = False) -> float:
    """Share of ones that a flow of so many bytes sets."""
    n = flow_bytes / stride
    return 1 - (1 - 1 / sections) ** n if collisions else int(n) / sections


def candidate_stats(candidates: DataFrame, excerpts: DataFrame) -> DataFrame:
    return count_stats(candidates.groupBy("excerpt_id").agg(F.count("*").alias("c")), excerpts)


def count_stats(counts: DataFrame, excerpts: DataFrame) -> DataFrame:
    """excerpts, candidates, mean, most, from the number of candidates (c) of each excerpt."""
    per = excerpts.select("excerpt_id").join(counts, "excerpt_id", "left")
    c = F.coalesce("c", F.lit(0))
    return per.agg(F.count("*").alias("excerpts"), F.sum(c).cast("bigint").alias("candidates"), F.round(F.avg(c), 6).alias("mean"), F.max(c).cast("bigint").alias("most"))


def flow_probes(candidates: DataFrame, blocks: DataFrame) -> DataFrame:
    """Filter questions that determination asks: candidates times blocks, summed."""
    return count_probes(candidates.groupBy("excerpt_id").agg(F.count("*").alias("c")), blocks)


def count_probes(counts: DataFrame, blocks: DataFrame) -> DataFrame:
    n = blocks.groupBy("excerpt_id").agg(F.count("*").alias("n"))
    return counts.join(n, "excerpt_id").agg(F.coalesce(F.sum(F.col("c") * F.col("n")), F.lit(0)).cast("bigint").alias("probes"))


def timed(fn: Callable[[], DataFrame | None]) -> float:
    """Seconds of a plan run to its end without keeping its rows."""
    began = time.perf_counter()
    out = fn()
    if isinstance(out, DataFrame):
        out.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


#: The cost model's formulas, for payload length b, n blocks, t instances, k hashes, reduction d, index bytes i.
COSTS = (
    ("boundary_selection", lambda b, n, t, k, d, i: (2 * b, 2 * t * b, b, 2 * b, 2 * b)),
    ("blocks", lambda b, n, t, k, d, i: (n, t * n, n, 2 * n, n / d)),
    ("block_processing", lambda b, n, t, k, d, i: (k, k, k, k, k + 2)),
    ("storage_processing", lambda b, n, t, k, d, i: (0, 0, 0, 0, i)),
)


def cost_table(spark: SparkSession, b: float, n: float, t: int, d: float, k: int, index: float = 0.0) -> DataFrame:
    """index: bytes of bitmaps that compression goes over; only a digest with an index has that cost."""
    rows = [(name, *(float(x) for x in f(b, n, t, k, d, index))) for name, f in COSTS]
    return spark.createDataFrame(rows, "measure string, shingled_winnow double, multi_winnow double, fixed_multifilter double, double_winnow double, sectioned_indexed double")


def accesses_per_block(k: int, index: bool, content_only: bool = False) -> int:
    """Memory accesses of an inserted block: k bits, and with sections and an index the selector hash and the bitmap."""
    return k + 2 if index else k


def gain(baselines: list[float], ours: float) -> float:
    return sum(baselines) / len(baselines) / ours


def protocol_mix(trace: DataFrame) -> DataFrame:
    per = trace.groupBy("proto").agg(F.count("*").alias("packets"), F.sum(F.octet_length("payload")).cast("bigint").alias("bytes"))
    return per.withColumn("share", F.round(F.col("packets") / F.sum("packets").over(Window.partitionBy(F.lit(1))), 6))


def arrival_profile(trace: DataFrame) -> DataFrame:
    """Packets and bytes per interval, and the largest over the mean."""
    per = trace.groupBy("interval_id").agg(F.count("*").alias("packets"), F.sum(F.octet_length("payload")).cast("bigint").alias("bytes"))
    mean = per.agg(F.avg("bytes").alias("mean"))
    return per.crossJoin(F.broadcast(mean)).select("interval_id", "packets", "bytes", F.round(F.col("bytes") / F.col("mean"), 6).alias("to_mean"))


def storage_seconds(flowbits: DataFrame, codec: str = "lzma2") -> float:
    """Measured cost of storage processing: seconds to compress the bitmap table."""
    from . import compress

    return timed(lambda: compress.pack_index(flowbits, codec))


def lzma_size(flowbits: DataFrame, codec: str = "lzma2") -> DataFrame:
    from . import compress

    return compress.pack_index(flowbits, codec).groupBy("interval_id").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum(F.octet_length("packed")).cast("bigint").alias("packed_bytes"))


def numpy_blocks_rate(payloads: list[bytes], window: int = 64, overlap: int = 4) -> float:
    """MB/s of the block kernel on one core."""
    from . import blocking

    began = time.perf_counter()
    blocking.winnow_batch(payloads, window, overlap)
    return sum(map(len, payloads)) / 1e6 / (time.perf_counter() - began)


def digest_kernel_rate(payloads: list[bytes], config) -> float:
    """MB/s of everything a task does to make a digest's parts, on one core: blocks, both hashes, bits and bitmaps."""
    import pyarrow as pa

    from . import digest

    flows = [str(i) for i in range(len(payloads))]
    at = range(0, len(payloads), 2000)
    names = ["interval_id", "flow_key", "payload"]
    batches = [pa.RecordBatch.from_arrays([pa.array([0] * len(payloads[a : a + 2000]), pa.int32()), pa.array(flows[a : a + 2000]), pa.array(payloads[a : a + 2000], pa.binary())], names) for a in at]
    kernel = digest.partial_kernel(config)
    list(kernel(iter(batches[:1])))
    began = time.perf_counter()
    for _ in kernel(iter(batches)):
        pass
    return sum(map(len, payloads)) / 1e6 / (time.perf_counter() - began)
