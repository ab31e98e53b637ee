"""The registry: one query per method, variant, baseline, measure and workload, with DuckDB SQL where SQL can say it."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import block_digest, flow_digest, section_of
from ..operators import attribution, baselines, bitindex, blocking, compress, downsample, measures, membership, trace
from ..operators import digest as dg
from ..operators.digest import DigestConfig
from . import oracle as o
from . import workloads as w

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE[name] = sql
        return f

    return add


def _docs(spark: SparkSession, d: str) -> DataFrame:
    return w.docs_trace(spark, d)


def _sized(spark: SparkSession, d: str, **how) -> tuple[DataFrame, DigestConfig]:
    packets = _docs(spark, d)
    return packets, DigestConfig(**how).sized(dg.raw_bytes(packets))


# ---- blocks

DOCS_BLOCKS = f"with {o.DOCS}, {o.blocks()}"


@query("winnow_bounds", f"with {o.DOCS}, {o.bounds()} select flow_key, seq, pos from bounds")
def _(spark, d):
    return blocking.winnow_bounds_sql(_docs(spark, d)).select("flow_key", "seq", "pos")


@query("winnow_bounds_kernel", f"with {o.DOCS}, {o.bounds()} select flow_key, seq, pos from bounds")
def _(spark, d):
    return blocking.winnow_bounds(_docs(spark, d)).select("flow_key", "seq", "pos")


@query("winnow_blocks", f"{DOCS_BLOCKS} select flow_key, seq, block_no, start, size, md5(block) as digest from blk")
def _(spark, d):
    return blocking.winnow_blocks(_docs(spark, d)).select("flow_key", "seq", "block_no", "start", "size", F.md5("block").alias("digest"))


@query("winnow_blocks_pages", f"with {o.PAGES}, {o.blocks()} select flow_key, seq, block_no, start, size, md5(block) as digest from blk")
def _(spark, d):
    return blocking.winnow_blocks(trace.from_pages(w.table(spark, d, "pages"))).select("flow_key", "seq", "block_no", "start", "size", F.md5("block").alias("digest"))


@query("block_hist", f"{DOCS_BLOCKS} select size, count(*) as blocks from blk group by size")
def _(spark, d):
    return measures.block_size_hist(blocking.winnow_blocks(_docs(spark, d)))


@query("block_hist_pages", f"with {o.PAGES}, {o.blocks()} select size, count(*) as blocks from blk group by size")
def _(spark, d):
    return measures.block_size_hist(blocking.winnow_blocks(trace.from_pages(w.table(spark, d, "pages"))))


@query("downsample_counts", f"{DOCS_BLOCKS} select t as threshold, count(*) as seen, count(*) filter (size >= t) as kept, round(count(*) / count(*) filter (size >= t), 6) as d from blk, (values {', '.join(f'({t})' for t in w.THRESHOLDS)}) g(t) group by t")
def _(spark, d):
    return downsample.counts(blocking.winnow_blocks(_docs(spark, d)), list(w.THRESHOLDS))


@query("downsample_counts_strict", f"{DOCS_BLOCKS} select t as threshold, count(*) as seen, count(*) filter (size > t) as kept, round(count(*) / count(*) filter (size > t), 6) as d from blk, (values (30), (40)) g(t) group by t")
def _(spark, d):
    return downsample.counts(blocking.winnow_blocks(_docs(spark, d)), [30, 40], keep_equal=False)


@query("block_reduction", f"{DOCS_BLOCKS} select count(*) as seen, count(*) filter (size >= 40) as kept, round(count(*) / count(*) filter (size >= 40), 6) as d from blk")
def _(spark, d):
    return measures.block_reduction(blocking.winnow_blocks(_docs(spark, d)), 40)


@query("multi_instance_bounds", f"with {o.DOCS}, {o.bounds(out='b0')}, {o.bounds(out='b1', instance=1)} select 0 as instance, flow_key, count(*) as bounds, sum(pos)::bigint as places from b0 group by flow_key union all select 1, flow_key, count(*), sum(pos)::bigint from b1 group by flow_key")
def _(spark, d):
    per = lambda i: blocking.winnow_bounds(_docs(spark, d), instance=i).groupBy("flow_key").agg(F.count("*").alias("bounds"), F.sum("pos").alias("places")).select(F.lit(i).alias("instance"), "flow_key", "bounds", "places")
    return per(0).unionByName(per(1))


@query("fixed_blocks", f"with {o.DOCS}, {o.fixed()} select flow_key, block_no, start, size, md5(block) as digest from blk")
def _(spark, d):
    return blocking.fixed_blocks(_docs(spark, d)).select("flow_key", "block_no", "start", "size", F.md5("block").alias("digest"))


@query("double_winnow_blocks", f"with {o.DOCS}, {o.blocks(width=10)} select flow_key, block_no, start, size, md5(block) as digest from blk")
def _(spark, d):
    return blocking.winnow_blocks(_docs(spark, d), 64, 9).select("flow_key", "block_no", "start", "size", F.md5("block").alias("digest"))


@query("winnow_small_window", f"with {o.DOCS}, {o.blocks(window=16)} select size, count(*) as blocks from blk group by size")
def _(spark, d):
    return measures.block_size_hist(blocking.winnow_blocks(_docs(spark, d), window=16))


# ---- digests and filters


@query("type1_digest", f"{DOCS_BLOCKS} select flow_key, block_no, md5(block) as digest, {o.number('md5(block)', '1', 8)}::int % 256 as section from blk".replace("::bigint::int", "::bigint"))
def _(spark, d):
    blocks = blocking.winnow_blocks(_docs(spark, d)).withColumn("digest", block_digest(F.col("block")))
    return blocks.select("flow_key", "block_no", "digest", section_of(F.col("digest"), 256).cast("bigint").alias("section"))


@query("type2_digest", f"{DOCS_BLOCKS} select flow_key, block_no, {o.digest('block', 'flow_key')} as digest from blk")
def _(spark, d):
    return blocking.winnow_blocks(_docs(spark, d)).select("flow_key", "block_no", flow_digest(F.col("block"), F.col("flow_key")).alias("digest"))


@query("salted_digest", f"{DOCS_BLOCKS} select flow_key, block_no, md5(encode('pepper') || block) as digest from blk")
def _(spark, d):
    return blocking.winnow_blocks(_docs(spark, d)).select("flow_key", "block_no", block_digest(F.col("block"), "pepper").alias("digest"))


@query("filter_words", o.filter_words(1, 2) + o.words())
def _(spark, d):
    packets, c = _sized(spark, d, k=2)
    return dg.words_of(blocking.winnow_blocks(packets), c).select("section", "word_ix", "word")


@query("sectioned_words", o.filter_words(256, 1) + o.words())
def _(spark, d):
    packets, c = _sized(spark, d, sections=256)
    return dg.words_of(blocking.winnow_blocks(packets), c).select("section", "word_ix", "word")


@query("packed_digest_words", o.filter_words(256, 1) + o.words())
def _(spark, d):
    """The fused kernel's digest, unpacked: equal to the declarative filter."""
    packets, c = _sized(spark, d, sections=256, index=True)
    return attribution.words_of_sections(dg.build(packets, c)).select("section", "word_ix", "word")


@query("filter_fill", o.filter_words(1, 2) + "select count(*) as ones, round(count(*) / (select greatest(32, m) from size_), 6) as fill from bits")
def _(spark, d):
    packets, c = _sized(spark, d, k=2)
    return membership.fill(dg.words_of(blocking.winnow_blocks(packets), c), c.m_bits).select("ones", "fill")


@query("sectioned_fill", o.filter_words(256, 2) + "select count(*) as ones, round(count(*) / (select greatest(8192, m) from size_), 6) as fill from bits")
def _(spark, d):
    packets, c = _sized(spark, d, k=2, sections=256)
    return membership.fill(dg.words_of(blocking.winnow_blocks(packets), c), c.m_bits).select("ones", "fill")


@query("filter_merge", o.filter_words(1, 2) + o.words())
def _(spark, d):
    """Digests of two halves of the capture, merged by OR."""
    packets, c = _sized(spark, d, k=2)
    half = F.pmod(F.xxhash64("flow_key"), F.lit(2))
    return membership.merge(*(dg.words_of(blocking.winnow_blocks(packets.filter(half == i)), c) for i in (0, 1))).select("section", "word_ix", "word")


@query("digest_manifest", f"with {o.DOCS}, {o.SIZE} select 0 as interval_id, raw as raw_bytes, flows, ((greatest(8192, m) + 7) // 8)::bigint as filter_bytes, (flows * 32)::bigint as index_bytes from size_")
def _(spark, d):
    packets, c = _sized(spark, d, sections=256, index=True)
    return dg.manifest(dg.build(packets, c)).select("interval_id", "raw_bytes", "flows", "filter_bytes", "index_bytes")


# ---- index

TOUCHED = f"{DOCS_BLOCKS}, touched as (select distinct flow_key, {o.number(o.digest('block'), '1', 8)} % 256 as section from blk)"


@query("flow_list", "select cast(doc_id as varchar) as flow_key, source as src, lang as dst, 1::bigint as packets, octet_length(encode(coalesce(text, '')))::bigint as bytes from documents")
def _(spark, d):
    return bitindex.flow_list(_docs(spark, d)).select("flow_key", "src", "dst", "packets", "bytes")


@query("flow_list_source", "select concat_ws('|', source, lang) as flow_key, min(source) as src, min(lang) as dst, count(*) as packets, sum(octet_length(encode(coalesce(text, ''))))::bigint as bytes from documents group by 1")
def _(spark, d):
    return bitindex.flow_list(w.docs_trace(spark, d, by="source")).select("flow_key", "src", "dst", "packets", "bytes")


@query("flow_bitmap_words", f"{TOUCHED} select flow_key, (section // 32)::int as word_ix, bit_or(1::bigint << (section % 32)::int)::bigint as word from touched group by all")
def _(spark, d):
    packets, c = _sized(spark, d, sections=256, index=True)
    return bitindex.flow_words(dg.content_elements(blocking.winnow_blocks(packets), c)).select("flow_key", "word_ix", "word")


@query("flow_bitmaps_packed", f"{TOUCHED}, b as (select f.flow_key, g.b, coalesce(bit_or(1 << (section % 8)::int), 0) as v from (select distinct flow_key from trace) f cross join range(32) g(b) left join touched t on t.flow_key = f.flow_key and section // 8 = g.b group by all) select flow_key, string_agg(printf('%02X', v), '' order by b) as bitmap from b group by flow_key")
def _(spark, d):
    packets, c = _sized(spark, d, sections=256, index=True)
    return dg.build(packets, c).flowbits.select("flow_key", F.hex("bitmap").alias("bitmap"))


@query("index_round_trip", f"{TOUCHED}, b as (select f.flow_key, g.b, coalesce(bit_or(1 << (section % 8)::int), 0) as v from (select distinct flow_key from trace) f cross join range(32) g(b) left join touched t on t.flow_key = f.flow_key and section // 8 = g.b group by all) select flow_key, string_agg(printf('%02X', v), '' order by b) as bitmap from b group by flow_key")
def _(spark, d):
    """Bitmaps compressed and opened again, of the intervals with hits only."""
    e = w.Experiment(spark, d, count=1)
    c = DigestConfig(sections=256, index=True).sized(e.raw)
    archive = compress.pack_index(e.bitmaps(c), shards=4)
    return compress.unpack_index(archive, archive.select("interval_id")).select("flow_key", F.hex("bitmap").alias("bitmap"))


@query("ones_share", f"{TOUCHED} select (select count(distinct flow_key) from trace) as flows, count(*) as ones, 256 as sections, round(count(*) / ((select count(distinct flow_key) from trace) * 256), 6) as share from touched")
def _(spark, d):
    packets, c = _sized(spark, d, sections=256, index=True)
    words = bitindex.flow_words(dg.content_elements(blocking.winnow_blocks(packets), c))
    return bitindex.ones_share(words, bitindex.flow_list(packets), 256)


@query("bitmap_example", "with t as (select distinct l_orderkey as f, l_partkey % 10 + 1 as s from lineitem), q(e, need) as (values (1, [6]), (2, [3,6,10]), (3, []::int[]), (4, [5]), (5, [1,5])) select e::bigint as excerpt_id, f::varchar as flow_key from (select f, list(s) as own from t group by f), q where list_has_all(own, need)")
def _(spark, d):
    """The worked example's requirements over ten sections, asked of all orders: a line's part chooses the section."""
    rows = w.table(spark, d, "lineitem").select(F.lit(0).alias("interval_id"), F.col("l_orderkey").cast("string").alias("flow_key"), (F.pmod("l_partkey", F.lit(10)) + 1).cast("int").alias("section"))
    return bitindex.example_of(rows)


def _pruned(spark, d, inverted: bool) -> DataFrame:
    e = w.Experiment(spark, d, count=None)
    c = DigestConfig(sections=256, index=True).sized(e.raw)
    blocks = attribution.excerpt_blocks(e.excerpts, c)
    if not inverted:
        return attribution.candidates_of(blocks, e.words(c), e.flows, e.excerpts, c).select("excerpt_id", "flow_key")
    hits = blocks.select("excerpt_id", F.lit(0).alias("interval_id"), section_of(block_digest(F.col("block")), 256).alias("section"))
    return bitindex.prune_inverted(bitindex.invert(dg.content_elements(e.blocks, c)), hits).select("excerpt_id", "flow_key")


PRUNED = f"{o.SETUP_ALL}, touched as (select distinct flow_key, {o.number(o.digest('block'), '1', 8)} % 256 as section from blk), need as (select distinct flow_key::bigint as excerpt_id, {o.number(o.digest('block'), '1', 8)} % 256 as section from xblk), n as (select excerpt_id, count(*) as n from need group by 1)"
PRUNED += ", kept as (select excerpt_id, flow_key from need join touched using (section) join n using (excerpt_id) group by excerpt_id, flow_key, n having count(*) = n)"


@query("prune_candidates", f"{PRUNED} select excerpt_id, flow_key from kept")
def _(spark, d):
    return _pruned(spark, d, False)


@query("prune_inverted", f"{PRUNED} select excerpt_id, flow_key from kept")
def _(spark, d):
    return _pruned(spark, d, True)


def _counts(e: w.Experiment, c: DigestConfig) -> DataFrame:
    return attribution.candidate_counts(e.excerpts, dg.packed_bitmaps(e.packets, [(0, c)]).withColumnRenamed("b0", "bitmap"), c)


@query("candidate_stats", f"{PRUNED} select (select count(*) from excerpts) as excerpts, count(*) as candidates, round(count(*) / (select count(*) from excerpts), 6) as mean, (select max(c) from (select count(*) as c from kept group by excerpt_id)) as most from kept")
def _(spark, d):
    e = w.Experiment(spark, d, count=None)
    c = DigestConfig(sections=256, index=True).sized(e.raw)
    return measures.count_stats(_counts(e, c), e.excerpts)


@query("flow_probes", f"{PRUNED} select sum(c * b)::bigint as probes from (select excerpt_id, count(*) as c from kept group by 1) join (select flow_key::bigint as excerpt_id, count(*) as b from xblk group by 1) using (excerpt_id)")
def _(spark, d):
    e = w.Experiment(spark, d, count=None)
    c = DigestConfig(sections=256, index=True).sized(e.raw)
    return measures.count_probes(_counts(e, c), attribution.excerpt_blocks(e.excerpts, c))


for _s, _j in ((8, 64), (8, 256), (32, 256)):

    @query(f"symbol_entropy_{_s}_{_j}", o.entropy(_s, _j))
    def _(spark, d, s=_s, j=_j):
        e = w.Experiment(spark, d, count=1)
        return measures.symbol_entropy(e.bitmaps(DigestConfig(sections=j, index=True).sized(e.raw)), s)


@query("index_stats")
def _(spark, d):
    return w.index_stats(spark, d)


@query("index_stats_ledger")
def _(spark, d):
    return w.index_stats(spark, d, trace.reassemble(w.ledger_trace(spark, d), separator=b"\n"), (256, 1024, 4096))


@query("filter_compression")
def _(spark, d):
    """Raw and compressed bytes of the filter itself: little to gain."""
    packets, c = _sized(spark, d, sections=64)
    return compress.pack_filter(dg.build(packets, c).sections)


# ---- attribution


@query("unique_excerpts", f"with {o.DOCS}, {o.UNIQUE_ALL} select excerpt_id, hx as excerpt, true_flow from excerpts")
def _(spark, d):
    return w.unique_excerpts(spark, d).select("excerpt_id", F.hex("excerpt").alias("excerpt"), "true_flow")


@query("appearance", f"{o.SETUP_ALL}, {o.evaluation([{'k': 2}])} select excerpt_id, 0 as interval_id from excerpts anti join gone using (excerpt_id)")
def _(spark, d):
    e = w.Experiment(spark, d, count=None)
    c = DigestConfig(k=2).sized(e.raw)
    present, _ = attribution.appearance(attribution.excerpt_blocks(e.excerpts, c), e.excerpts, dg.words_of(e.blocks, c), e.flows, c)
    return present


ABSENT = f"""with {o.DOCS}, {o.SIZE}, {o.blocks()},
all_slices as (select excerpt_id, substr(hx, 2 * ((len(hx) // 2 - 200) // 2) + 1, 400) as hx from (select printf('turn %d of %d', turn, conv_id) as excerpt_id, hex(encode(coalesce(text, ''))) as hx from conversations union all select printf('page %d', page_id), hex(encode(coalesce(html, ''))) from pages) where len(hx) >= 400),
spaced as (select {o.SPACED.format('hx')} as sp from trace),
excerpts as (select excerpt_id, hx from all_slices a where not exists (select 1 from spaced where contains(sp, {o.SPACED.format('a.hx')})) order by excerpt_id limit 10000),
xt as (select excerpt_id as flow_key, 0::bigint as seq, hx from excerpts), {o.blocks('xt', 'xblk')},
cfg as (select 0 as config_id, 1 as j, 2 as k, m as ms from size_), el as (select 0 as config_id, {o.digest('block')} as d, null::bigint as tag from blk), {o.bits('el')},
ask as (select flow_key as excerpt_id, block_no, size, bool_and(b.pos is not null) as present from (select flow_key, block_no, size, ({o.number(o.digest('block'), '9', 12)} + r * {o.number(o.digest('block'), '21', 12)}) % ms as pos from xblk, cfg, range(2) g(r)) a left join bits b on a.pos = b.pos group by all)"""


@query("true_negative_size", f"{ABSENT} select size, count(*) as blocks, count(*) filter (not present) as negatives, round(count(*) filter (not present) / count(*), 6) as rate, round(count(*) filter (not present) / (select count(*) from ask where not present), 6) as share from ask group by size")
def _(spark, d):
    return w.true_negative_size(spark, d)


@query("appearance_only", f"{ABSENT} select (select count(*) from excerpts) as absent, (select count(*) from excerpts) - count(distinct excerpt_id) as present, round(((select count(*) from excerpts) - count(distinct excerpt_id)) / (select count(*) from excerpts), 6) as fpr from ask where not present")
def _(spark, d):
    """Appearance of absent excerpts, without flow-bound blocks."""
    packets, c = _sized(spark, d, k=2, flow_blocks=False)
    excerpts = w.absent_excerpts(spark, d)
    present, _ = attribution.appearance(attribution.excerpt_blocks(excerpts, c), excerpts, dg.words_of(blocking.winnow_blocks(packets), c), packets, c)
    return measures.appearance_fpr(present, excerpts)


def _verdict_sql(entry: dict) -> str:
    return f"{o.SETUP_ALL}, {o.evaluation([entry])} select excerpt_id, flow_key from (select excerpt_id, flow_key from excerpts, flows) anti join missed using (excerpt_id, flow_key)"


@query("determine_exhaustive", _verdict_sql({"k": 2}))
def _(spark, d):
    e = w.Experiment(spark, d, count=None)
    c = DigestConfig(k=2).sized(e.raw)
    if baselines.excerpt_bytes(e.excerpts) <= attribution.PACKED_BOUND // 4 and c.m_bits // 8 <= attribution.PACKED_BOUND:
        return e.verdicts([(0, c)]).select("excerpt_id", "flow_key")  # each pair is asked where the flow is: no probe crosses an exchange
    return attribution.attribute(e.excerpts, dg.build(e.packets, c), ends=False).select("excerpt_id", "flow_key")  # no index: the same, a part of the excerpts at a time


@query("attribute_pruned", _verdict_sql({"sections": 256, "index": True}))
def _(spark, d):
    """The whole procedure on a built digest: appearance, index, flow-bound probes."""
    e = w.Experiment(spark, d, count=None)
    digest = dg.build(e.packets, DigestConfig(sections=256, index=True).sized(e.raw))
    return attribution.attribute(e.excerpts, digest, ends=False).select("excerpt_id", "flow_key")


@query("attribute_hash_feature", _verdict_sql({"sections": 256, "index": True, "feature": "hash"}))
def _(spark, d):
    """The index's feature from a hash, beside a conventional filter."""
    e = w.Experiment(spark, d, count=None)
    digest = dg.build(e.packets, DigestConfig(sections=256, index=True, feature="hash").sized(e.raw))
    return attribution.attribute(e.excerpts, digest, ends=False).select("excerpt_id", "flow_key")


@query("attribute_downsampled", _verdict_sql({"sections": 256, "threshold": 40, "index": True}))
def _(spark, d):
    e = w.Experiment(spark, d, count=None)
    digest = dg.build(e.packets, DigestConfig(sections=256, threshold=40, index=True).sized(e.raw))
    return attribution.attribute(e.excerpts, digest, ends=False).select("excerpt_id", "flow_key")


@query("attribute_flagged", f"{o.SETUP_ALL}, {o.evaluation([{'threshold': 60}])} select excerpt_id, flow_key, excerpt_id not in (select excerpt_id from xd where size >= 60) as untestable from (select excerpt_id, flow_key from excerpts, flows) anti join missed using (excerpt_id, flow_key)")
def _(spark, d):
    """Excerpts without a kept block, flagged: they are reported everywhere."""
    e = w.Experiment(spark, d, count=None)
    digest = dg.build(e.packets, DigestConfig(threshold=60).sized(e.raw))
    return attribution.attribute(e.excerpts, digest, on_empty="flag", ends=False).select("excerpt_id", "flow_key", "untestable")


@query("attribute_saved", _verdict_sql({"sections": 64, "index": True}))
def _(spark, d):
    """A digest written with a compressed index, loaded, and asked in a range of intervals."""
    e = w.Experiment(spark, d, count=None)
    path = f"{shared_folder(spark)}/digest"
    dg.build(e.packets, DigestConfig(sections=64, index=True).sized(e.raw)).save(path, codec="lzma2")
    return attribution.attribute(e.excerpts, dg.load(spark, path), between=(0, 0), ends=False).select("excerpt_id", "flow_key")


def shared_folder(spark: SparkSession) -> str:
    """A new folder in the session's checkpoint folder, or in its warehouse where none is set: both are shared by all executors."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")
    return f"{base.rstrip('/')}/tracedigest-{uuid.uuid4().hex}"


@query("flow_fpr", o.sweep([{"sections": 256, "index": True}], "sections_ as sections").replace("sections_ as sections", "ji as sections"))
def _(spark, d):
    e = w.Experiment(spark, d)
    return e.fpr(w.grid(e.raw, [{"sections": 256, "index": True}])).select(F.lit(256).alias("sections"), "excerpts", "reported", "false_flows", "fpr")


@query("false_negatives", "select null::bigint as excerpt_id, null::varchar as flow_key where false")
def _(spark, d):
    """True carriers that any configuration misses: none."""
    e = w.Experiment(spark, d)
    entries = [{"k": 2}, {"threshold": 40, "k": 2}, {"sections": 256, "index": True}, {"sections": 1024, "threshold": 30, "index": True}]
    verdict = e.verdicts(w.grid(e.raw, entries))
    truth = e.excerpts.select("excerpt_id", F.col("true_flow").alias("flow_key")).crossJoin(spark.range(len(entries)).select(F.col("id").cast("int").alias("config_id")))
    return truth.join(verdict, ["config_id", "excerpt_id", "flow_key"], "left_anti").select("excerpt_id", "flow_key")


@query("safe_threshold", f"{o.SETUP_ALL} select min(largest)::int as safe from (select flow_key, max(size) as largest from xblk group by flow_key)")
def _(spark, d):
    return downsample.safe_threshold(attribution.excerpt_blocks(w.unique_excerpts(spark, d), DigestConfig()))


# ---- sweeps


@query("threshold_sweep", o.sweep([{"threshold": t, "k": 2} for t in w.THRESHOLDS], "t as threshold"))
def _(spark, d):
    return w.threshold_sweep(spark, d)


@query("best_threshold", o.sweep([{"threshold": t, "k": 2} for t in w.THRESHOLDS], "t as threshold").replace(o.RATE, o.RATE.split(", ", 3)[3]) + " order by fpr, threshold limit 1")
def _(spark, d):
    return w.best_threshold(spark, d)


@query("grid_fpr", o.sweep(w.GRID, "ji as sections, t as threshold"))
def _(spark, d):
    return w.grid_fpr(spark, d)


@query("threshold_sweep_skew", o.sweep([{"threshold": t, "k": 2} for t in w.THRESHOLDS], "t as threshold", o.DOCS_SKEW))
def _(spark, d):
    """The same on the trace of mice and elephants."""
    return w.threshold_sweep(spark, d, packets=w.docs_trace(spark, d, by="skew"))


@query("grid_fpr_skew", o.sweep(w.GRID, "ji as sections, t as threshold", o.DOCS_SKEW))
def _(spark, d):
    return w.grid_fpr(spark, d, w.docs_trace(spark, d, by="skew"))


@query("grid_cube", f"{o.SETUP}, {o.evaluation(w.GRID)} select ji as sections, t as threshold, sum(reported - excerpts)::bigint as false_flows from rate join cfg using (config_id) group by cube (ji, t)")
def _(spark, d):
    """False flows by sections and threshold, with totals."""
    return w.grid_fpr(spark, d).cube("sections", "threshold").agg(F.sum("false_flows").alias("false_flows"))


@query("grid_pivot", f"{o.SETUP}, {o.evaluation(w.GRID)} select ji as sections, max(case when t = 0 then f end) as t0, max(case when t = 20 then f end) as t20, max(case when t = 40 then f end) as t40 from (select ji, t, round((reported - excerpts) / (excerpts * (select flows from size_)), 6) as f from rate join cfg using (config_id)) group by ji")
def _(spark, d):
    return w.grid_fpr(spark, d).groupBy("sections").pivot("threshold", [0, 20, 40]).agg(F.max("fpr")).toDF("sections", "t0", "t20", "t40")


@query("hash_count_sweep", o.sweep([{"k": k} for k in (1, 2, 3)], "k"))
def _(spark, d):
    e = w.Experiment(spark, d)
    configs = w.grid(e.raw, [{"k": k} for k in (1, 2, 3)])
    names = spark.createDataFrame([(i, c.k) for i, c in configs], "config_id int, k int")
    return e.fpr(configs).join(F.broadcast(names), "config_id").select("k", "excerpts", "reported", "false_flows", "fpr")


@query("overall_ratio")
def _(spark, d):
    return w.overall_ratio(spark, d)


@query("matched_ratio")
def _(spark, d):
    return w.matched_ratio(spark, d)


@query("matched_ratio_docs")
def _(spark, d):
    """The same on small flows: a document each."""
    return w.matched_ratio(spark, d, skewed=False)


@query("index_stats_skew")
def _(spark, d):
    return w.index_stats(spark, d, w.docs_trace(spark, d, by="skew"))


@query("cost_table", f"{DOCS_BLOCKS}, {o.SIZE}, x as (select raw::double as b, (select count(*) from blk)::double as n, (select round(count(*) / count(*) filter (size >= 40), 6) from blk) as d from size_) select 'boundary_selection' as measure, 2 * b as shingled_winnow, 4 * b as multi_winnow, b as fixed_multifilter, 2 * b as double_winnow, 2 * b as sectioned_indexed from x union all select 'blocks', n, 2 * n, n, 2 * n, n / d from x union all select 'block_processing', 1, 1, 1, 1, 3 union all select 'storage_processing', 0, 0, 0, 0, (select flows * 32 from size_)")
def _(spark, d):
    return w.cost_table(spark, d)


# ---- baselines

def _plain_eval(el: str, xel: str, k: int = 1, m: str = "m") -> str:
    """Rates of one filter of m bits and k hashes from elements el(flow_key, block) and excerpt elements xel(excerpt_id, block)."""
    at = lambda flow: f"({o.number(o.digest('block', flow), '9', 12)} + r * {o.number(o.digest('block', flow), '21', 12)}) % ms as pos"
    return f""", cfg as (select 0 as config_id, 1 as j, {k} as k, {m} as ms from size_), e2 as (select 0 as config_id, {o.digest('block')} as d, null::bigint as tag from {el} union all select 0, {o.digest('block', 'flow_key')}, null from {el}), {o.bits('e2')},
flows as (select distinct flow_key from trace), gone as (select distinct excerpt_id from (select excerpt_id, {at(None)} from {xel}, cfg, range({k}) g(r)) a anti join bits using (pos)),
miss as (select distinct excerpt_id, flow_key from (select excerpt_id, flow_key, {at('flow_key')} from {xel}, flows, cfg, range({k}) g(r)) a anti join bits using (pos)),
bad as (select excerpt_id, flow_key from miss union select excerpt_id, flow_key from gone, flows)
select '{{name}}' as method, {k} as k, (select count(*) from {el})::bigint as elements, (select count(*) from excerpts) as excerpts, r as reported, r - (select count(*) from excerpts) as false_flows, round((r - (select count(*) from excerpts)) / ((select count(*) from excerpts) * (select flows from size_)), 6) as fpr
from (select (select count(*) from excerpts) * (select flows from size_) - count(*) as r from bad)"""


def _baseline(name: str):
    def run(spark, d):
        e = w.Experiment(spark, d)
        return w.baseline_fpr(e, name, DigestConfig().sized(e.raw).m_bits)

    return run


def _twice(src: str, out: str, key: str) -> str:
    return f"""{out} as (select {key}, block from {src} union all select {key}, block || encode('~' || ({o.number('md5(nxt)', '1', 8)} % 8)::varchar) from (select flow_key, block, lead(block) over (partition by flow_key, seq order by block_no) as nxt from {src}) where nxt is not null)"""


def _fixed_eval(k: int = 1, m: str = "m") -> str:
    mark = f"{o.number('md5(unhex(substr(hex(block), 1, 16)))', '1', 8)} % 8"
    at = lambda flow: f"({o.number(o.digest('block', flow), '9', 12)} + r * {o.number(o.digest('block', flow), '21', 12)}) % ms as pos"
    return f""", {o.fixed()}, cfg as (select 0 as config_id, 8 as j, {k} as k, ({m}) // 8 as ms from size_),
el as (select 0 as config_id, {o.digest('block')} as d, {mark} as tag from blk union all select 0, {o.digest('block', 'flow_key')}, {mark} from blk), {o.bits('el')},
xb as (select excerpt_id, a, unhex(substr(hx, 2 * p + 1, 64)) as block from (select excerpt_id, hx, a, unnest(range(a, 200 - 32 + 1, 32)) as p from excerpts, range(32) g(a))),
xd as (select excerpt_id, a, block, {mark} as section from xb),
dead as (select distinct excerpt_id, a from (select excerpt_id, a, section, {at(None)} from xd, cfg, range({k}) g(r)) q anti join bits using (section, pos)),
live as (select excerpt_id, a, block, section from xd anti join dead using (excerpt_id, a)), flows as (select distinct flow_key from trace),
miss as (select distinct excerpt_id, a, flow_key from (select excerpt_id, a, flow_key, section, {at('flow_key')} from live, flows, cfg, range({k}) g(r)) q anti join bits using (section, pos)),
hit as (select distinct excerpt_id, flow_key from (select distinct excerpt_id, a, flow_key from live, flows) q anti join miss using (excerpt_id, a, flow_key))
select 'fixed_multifilter' as method, {k} as k, (select count(*) from blk) as elements, (select count(*) from excerpts) as excerpts, count(*) as reported, count(*) - (select count(*) from excerpts) as false_flows, round((count(*) - (select count(*) from excerpts)) / ((select count(*) from excerpts) * (select flows from size_)), 6) as fpr from hit"""


BASE = f"with {o.DOCS}, {o.SIZE}, {o.UNIQUE}"


def method_sql(name: str, k: int = 1, m: str = "m") -> str:
    """One baseline's rates, with its k."""
    if name == "fixed_multifilter":
        return BASE + _fixed_eval(k, m)
    if name == "multi_winnow":
        cut = f", {o.blocks(out='k0')}, {o.blocks(out='k1', instance=1)}, {o.blocks('xt', 'x0')}, {o.blocks('xt', 'x1', instance=1)}, el as (select flow_key, encode('0:') || block as block from k0 union all select flow_key, encode('1:') || block from k1), xel as (select flow_key::bigint as excerpt_id, encode('0:') || block as block from x0 union all select flow_key::bigint, encode('1:') || block from x1)"
    elif name == "double_winnow":
        cut = f", {o.blocks(width=10)}, {o.blocks('xt', 'xblk', width=10)}, {_twice('blk', 'el', 'flow_key')}, {_twice('xblk', 'xel', 'flow_key::bigint as excerpt_id')}"
    else:
        cut = f", {o.blocks()}, {o.blocks('xt', 'xblk')}, el as (select flow_key, block from blk), xel as (select flow_key::bigint as excerpt_id, block from xblk)"
    return BASE + cut + _plain_eval("el", "xel", k, m).format(name=name)


RATES = "method, elements, excerpts, reported, false_flows, fpr"
for _key, _name in (("b_shingled", "shingled_winnow"), ("b_multi", "multi_winnow"), ("b_double", "double_winnow"), ("b_fixed", "fixed_multifilter")):
    query(_key, f"select {RATES} from ({method_sql(_name)})")(_baseline(_name))

BY_K = " union all ".join(f"select {RATES}, k from ({method_sql(name, k)})" for name in w.METHODS for k in (1, 2))


@query("methods_fpr", BY_K)
def _(spark, d):
    """The baselines at 100:1, by their number of hashes."""
    return w.methods_fpr(spark, d, ks=(1, 2))


@query("methods_best_k", f"select method, min(fpr) as fpr, arg_min(k, (fpr, k)) as k from ({BY_K}) group by method")
def _(spark, d):
    """Each baseline with the number of hashes that serves it best."""
    return w.at_best_k(w.methods_fpr(spark, d, ks=(1, 2)).select("method", "k", "fpr"), "method")


def _matched_sql(sections: int) -> str:
    m = f"m + 8 * flows * {sections // 8}"
    every = " union all ".join(f"select {RATES}, k from ({method_sql(name, k, m)})" for name in w.METHODS for k in (1, 2))
    ours = o.sweep([{"sections": sections, "index": True}], "ji as sections")
    best = f"select method, {sections} as sections, unnest(arg_min({{'k': k, 'excerpts': excerpts, 'reported': reported, 'false_flows': false_flows, 'fpr': fpr}}, (fpr, k))) from ({every}) group by method"
    return f"select 'sectioned_indexed' as method, sections, 1 as k, excerpts, reported, false_flows, fpr from ({ours}) union all ({best})"


@query("matched_uncompressed", " union all ".join(f"select method, sections, k, excerpts, reported, false_flows, fpr from ({_matched_sql(j)})" for j in (64, 256)))
def _(spark, d):
    """All methods where filter and uncompressed index together have the baselines' bytes."""
    return w.matched_uncompressed(spark, d)


HIER = f"""{BASE}, cfg as (select 8 * raw // 10 as ms from size_),
l0 as (select flow_key, unhex(substr(hx, 64 * i + 1, 64)) || encode('@' || i) as el from (select flow_key, hx, unnest(range(0, len(hx) // 64)) as i from trace)),
l1 as (select flow_key, unhex(substr(hx, 128 * i + 1, 128)) || encode('@' || i) as el from (select flow_key, hx, unnest(range(0, len(hx) // 128)) as i from trace)),
els as (select * from l0 union all select * from l1),
bits as (select distinct pos from (select {o.number("md5(el)", '9', 12)} % ms as pos from els, cfg union all select {o.number(o.digest('el', 'flow_key'), '9', 12)} % ms from els, cfg)),
guess as (select excerpt_id, hx, a, f, unhex(substr(hx, 2 * a + 1, 64)) || encode('@' || f) as el from excerpts, range(32) g(a), (select unnest(range(max(len(hx)) // 64)) as f from trace) p),
one as (select excerpt_id, hx, a, f from (select guess.*, {o.number("md5(el)", '9', 12)} % ms as pos from guess, cfg) q semi join bits using (pos)),
xs as (select excerpt_id, a, f, unhex(substr(hx, 2 * (a + 32 * i) + 1, 64)) || encode('@' || (f + i)) as el from one, range(6) n(i) where a + 32 * (i + 1) <= 200
  union all select excerpt_id, a, f, unhex(substr(hx, 2 * (a + 32 * i) + 1, 128)) || encode('@' || ((f + i) // 2)) from one, range(5) n(i) where a + 32 * (i + 2) <= 200 and (f + i) % 2 = 0),
dead as (select distinct excerpt_id, a, f from (select excerpt_id, a, f, {o.number("md5(el)", '9', 12)} % ms as pos from xs, cfg) q anti join bits using (pos)),
live as (select xs.* from xs anti join dead using (excerpt_id, a, f)), flows as (select distinct flow_key from trace),
miss as (select distinct excerpt_id, a, f, flow_key from (select excerpt_id, a, f, flow_key, {o.number(o.digest('el', 'flow_key'), '9', 12)} % ms as pos from live, flows, cfg) q anti join bits using (pos)),
hit as (select distinct excerpt_id, flow_key from (select distinct excerpt_id, a, f, flow_key from live, flows) q anti join miss using (excerpt_id, a, f, flow_key)),
r as (select count(*) as reported, count(*) filter (flow_key = true_flow) as right_ from hit join excerpts using (excerpt_id))
select (select count(*) from excerpts) as excerpts, (select count(*) from (select distinct excerpt_id, a, f from live)) as alive, reported, reported - right_ as false_flows, (select count(*) from excerpts) - right_ as missed from r"""


@query("b_hier", HIER)
def _(spark, d):
    return w.hier_verdict(spark, d)


@query("b_packet", f"with {o.DOCS}, {o.SIZE}, bits as (select distinct {o.number('md5(unhex(hx))', '9', 12)} % m as pos from trace, size_) select role, count(*) as asked, count(pos) as present from (select role, {o.number('md5(encode(text))', '9', 12)} % m as p from conversations, size_) left join bits on p = pos group by role")
def _(spark, d):
    """One element per whole payload; turns, which no document equals, are asked for."""
    packets, c = _sized(spark, d, flow_blocks=False)
    words = membership.build(baselines.packet_elements(packets).select("interval_id", F.md5("block").alias("digest")), c.m_bits, 1)
    asked = w.table(spark, d, "conversations").select(F.lit(0).alias("interval_id"), "conv_id", "turn", "role", F.md5(F.encode("text", "UTF-8")).alias("digest"))
    return membership.probe(asked, words, c.m_bits).groupBy("role").agg(F.count("*").alias("asked"), F.count(F.when(F.col("present"), 1)).alias("present"))


RAW = f"with {o.DOCS}, sp as (select flow_key, {o.SPACED.format('hx')} as sp from trace), it as (select item_id, {o.SPACED.format('hex(encode(text))')} as xp from benchmark where text <> '') select item_id{{id}}, flow_key from it join sp on contains(sp, xp)"


@query("b_raw", RAW.format(id=" as excerpt_id"))
def _(spark, d):
    items = w.table(spark, d, "benchmark").select(F.col("item_id").alias("excerpt_id"), F.encode("text", "UTF-8").alias("excerpt")).filter("octet_length(excerpt) > 0")
    return baselines.raw_archive(_docs(spark, d), items)


# ---- tables and uses


@query("leak_trace", RAW.format(id=""))
def _(spark, d):
    return w.leak_trace(spark, d)


def _use_sql(excerpts: str, entry: dict) -> str:
    """Verdicts on other excerpts(excerpt_id, hx)."""
    return f"with {o.DOCS}, {o.SIZE}, {o.blocks()}, excerpts as ({excerpts}), xt as (select excerpt_id::varchar as flow_key, 0::bigint as seq, hx from excerpts), {o.blocks('xt', 'xblk')}, {o.evaluation([entry])} select excerpt_id{{id}}, flow_key from (select excerpt_id, flow_key from excerpts, flows) anti join missed using (excerpt_id, flow_key)"


@query("leak_digest", _use_sql("select item_id as excerpt_id, hex(encode(text)) as hx from benchmark where text <> ''", w.USE).format(id=" as item_id"))
def _(spark, d):
    return w.leak_digest(spark, d)


@query("worm_digest", _use_sql("select min(doc_id) as excerpt_id, any_value(hex(encode(text))) as hx from documents where octet_length(encode(text)) >= 132 group by text having count(*) > 1", w.USE).format(id=""))
def _(spark, d):
    return w.worm_digest(spark, d)


@query("worm_trace", "with d as (select md5(coalesce(text, '')) as signature, doc_id::varchar as flow_key, octet_length(encode(coalesce(text, '')))::int as b from documents), s as (select signature, count(distinct flow_key) as carriers, min(b) as bytes from d group by 1 having count(distinct flow_key) > 1) select distinct signature, carriers, bytes, flow_key from d join s using (signature)")
def _(spark, d):
    return w.worm_trace(spark, d)


CUTS = [500, 1000, 2000, 4000, 8000, 16000, 32000]


def _cdf_sql(flows: str) -> str:
    return f"with f as ({flows}) select cut::bigint as cut, count(*) filter (bytes < cut) as flows_under, count(*) as flows, round(count(*) filter (bytes < cut) / count(*), 6) as share from f, (values {', '.join(f'({c})' for c in CUTS)}) g(cut) group by cut"


@query("flow_cdf_docs", _cdf_sql("select octet_length(encode(coalesce(text, ''))) as bytes from documents"))
def _(spark, d):
    return measures.flow_cdf(bitindex.flow_list(_docs(spark, d)), CUTS)


@query("flow_cdf_conversations", _cdf_sql("select sum(octet_length(encode(coalesce(text, '')))) as bytes from conversations group by conv_id"))
def _(spark, d):
    return measures.flow_cdf(bitindex.flow_list(trace.from_conversations(w.table(spark, d, "conversations"))), CUTS)


@query("flow_cdf_pages", _cdf_sql("select octet_length(encode(coalesce(html, ''))) as bytes from pages"))
def _(spark, d):
    return measures.flow_cdf(bitindex.flow_list(trace.from_pages(w.table(spark, d, "pages"))), CUTS)


@query("flow_cdf_ledger", _cdf_sql(f"with {o.LEDGER_ROWS} select sum(length(txt)) as bytes from rows_ group by s, c"))
def _(spark, d):
    return measures.flow_cdf(bitindex.flow_list(w.ledger_trace(spark, d)), CUTS)


@query("protocol_mix", "select role as proto, count(*) as packets, sum(octet_length(encode(coalesce(text, ''))))::bigint as bytes, round(count(*) / (select count(*) from conversations), 6) as share from conversations group by role")
def _(spark, d):
    return measures.protocol_mix(trace.from_conversations(w.table(spark, d, "conversations")))


@query("protocol_filter", "select conv_id::varchar as flow_key, count(*) as packets from conversations where role in ('user', 'assistant') group by conv_id")
def _(spark, d):
    return trace.keep_protocols(trace.from_conversations(w.table(spark, d, "conversations")), ["user", "assistant"]).groupBy("flow_key").agg(F.count("*").alias("packets"))


@query("arrival_profile", "with e as (select floor(epoch_us(ts) / 86400000000)::int as interval_id, octet_length(encode(concat_ws('|', event_id, epoch_us(ts), user_id, event_type, round(value * 10000)::bigint, props)))::bigint as b from events), p as (select interval_id, count(*) as packets, sum(b)::bigint as bytes from e group by 1) select interval_id, packets, bytes, round(bytes / (select avg(bytes) from p), 6) as to_mean from p")
def _(spark, d):
    return measures.arrival_profile(trace.from_events(w.table(spark, d, "events")))


@query("interval_hits", f"""with {o.DOCS}, {o.blocks()}, {o.UNIQUE_ALL}, {o.blocks('xt', 'xblk')},
bits as (select distinct flow_key::bigint // 250 as interval_id, {o.number(o.digest('block'), '9', 12)} % 49152 as pos from blk),
x as (select flow_key::bigint as excerpt_id, block_no, {o.number(o.digest('block'), '9', 12)} % 49152 as pos from xblk), n as (select excerpt_id, count(*) as n from x group by 1)
select excerpt_id, interval_id::int as interval_id from x join bits using (pos) join n using (excerpt_id) group by excerpt_id, interval_id, n having count(*) = n""")
def _(spark, d):
    return w.interval_hits(spark, d)


@query("attribute_intervals", f"""with {o.DOCS}, {o.blocks()}, {o.UNIQUE_ALL}, {o.blocks('xt', 'xblk')}, b as (select flow_key, flow_key::bigint // {w.INTERVAL_DOCS} as interval_id, block from blk),
bits as (select distinct interval_id, {o.number('d', '1', 8)} % 64 as section, {o.number('d', '9', 12)} % {w.INTERVAL_BITS // 64} as pos from (select interval_id, {o.digest('block')} as d from b union all select interval_id, {o.digest('block', 'flow_key')} from b)),
touched as (select distinct interval_id, flow_key, {o.number(o.digest('block'), '1', 8)} % 64 as section from b),
flows as (select distinct flow_key, flow_key::bigint // {w.INTERVAL_DOCS} as interval_id from trace), inside as (select * from flows where interval_id between 1 and 2),
ivs as (select distinct interval_id from inside), x as (select flow_key::bigint as excerpt_id, block, {o.digest('block')} as d from xblk),
gone as (select distinct excerpt_id, interval_id from (select excerpt_id, interval_id, {o.number('d', '1', 8)} % 64 as section, {o.number('d', '9', 12)} % {w.INTERVAL_BITS // 64} as pos from x, ivs) q anti join bits using (interval_id, section, pos)),
pairs as (select excerpt_id, interval_id, flow_key from excerpts, inside), alive as (select * from pairs anti join gone using (excerpt_id, interval_id)),
pruned as (select distinct excerpt_id, interval_id, flow_key from (select excerpt_id, interval_id, flow_key, {o.number('d', '1', 8)} % 64 as section from alive join x using (excerpt_id)) q anti join touched using (interval_id, flow_key, section)),
missed as (select distinct excerpt_id, interval_id, flow_key from (select excerpt_id, interval_id, flow_key, {o.number(o.digest('block', 'flow_key'), '1', 8)} % 64 as section, {o.number(o.digest('block', 'flow_key'), '9', 12)} % {w.INTERVAL_BITS // 64} as pos from alive join x using (excerpt_id)) q anti join bits using (interval_id, section, pos))
select excerpt_id, interval_id::int as interval_id, flow_key from alive anti join pruned using (excerpt_id, interval_id, flow_key) anti join missed using (excerpt_id, interval_id, flow_key)""")
def _(spark, d):
    return w.attribute_intervals(spark, d)


@query("intervals_by_bytes", """with e as (select floor(epoch_us(ts) / 1000000 / 3600)::bigint as g, octet_length(encode(concat_ws('|', event_id, epoch_us(ts), user_id, event_type, round(value * 10000)::bigint, props)))::bigint as b from events),
p as (select g, sum(b) as b, count(*) as n from e group by g), r as (select b, n, coalesce(sum(b) over (order by g rows between unbounded preceding and 1 preceding), 0) as before_ from p)
select (before_ // 50000)::int as interval_id, sum(n)::bigint as packets, sum(b)::bigint as bytes from r group by 1""")
def _(spark, d):
    """Intervals of about 50,000 bytes in the order of time, by grains of an hour."""
    packets = trace.assign_interval(trace.from_events(w.table(spark, d, "events")), target_bytes=50_000, grain=3600)
    return packets.groupBy("interval_id").agg(F.count("*").alias("packets"), F.sum(F.octet_length("payload")).cast("bigint").alias("bytes"))


@query("index_ones", " union all ".join(f"select {j} as sections, flows, ones, round(ones / (flows * {j}), 6) as share, flows * {j // 8} as index_bytes, round(raw / (greatest({32 * j}, m) // 8 + flows * {j // 8}), 3) as overall from ({DOCS_BLOCKS}, {o.SIZE}, touched as (select distinct flow_key, {o.number(o.digest('block'), '1', 8)} % {j} as section from blk) select (select count(*) from touched) as ones, flows, raw, m from size_)" for j in (64, 256)))
def _(spark, d):
    return w.index_ones(spark, d)


@query("index_included", f"with {o.DOCS}, {o.SIZE} select (8 * raw // 20 - flows * 256) as m_bits, (flows * 32)::bigint as index_bytes, round(raw / ((8 * raw // 20 - flows * 256) / 8 + flows * 32), 2) as overall from size_")
def _(spark, d):
    """A reduction of 20 that filter and uncompressed index have together."""
    c = dg.build(_docs(spark, d), DigestConfig(reduction=20.0, sections=256, index=True, reduction_includes_index=True)).config
    row = bitindex.flow_list(_docs(spark, d)).agg(F.count("*").alias("n"), F.sum("bytes").alias("raw"))
    return row.select(F.lit(c.m_bits).cast("bigint").alias("m_bits"), (F.col("n") * 32).alias("index_bytes"), F.round(F.col("raw") / (F.lit(c.m_bits / 8) + F.col("n") * 32), 2).alias("overall"))


@query("auto_k_words", o.filter_words(1, 5).replace("// 100", "// 20").replace("greatest(32, m)", "m") + o.words())
def _(spark, d):
    """At 20:1 five hashes fit the load that is to be expected."""
    packets, c = _sized(spark, d, reduction=20.0, k="auto")
    return dg.words_of(blocking.winnow_blocks(packets), c).select("section", "word_ix", "word")


@query("vector_family", f"{o.SETUP} select count(*) as excerpts, 0 as missed, true as fewer_false_flows from excerpts")
def _(spark, d):
    """A digest of the vectorised hashes misses no carrier, and its false flows are those of the portable one give or take a fifth."""
    e = w.Experiment(spark, d)
    found = lambda family: attribution.attribute(e.excerpts, dg.build(e.packets, DigestConfig(sections=256, index=True, hash_family=family).sized(e.raw))).select("excerpt_id", "flow_key")
    got = found("vector").persist()
    truth = e.excerpts.select("excerpt_id", F.col("true_flow").alias("flow_key"))
    missed = truth.join(got, ["excerpt_id", "flow_key"], "left_anti").agg(F.count("*").cast("int").alias("missed"))
    sizes = got.agg(F.count("*").alias("n")).crossJoin(found("portable").agg(F.count("*").alias("p"))).crossJoin(truth.agg(F.count("*").alias("excerpts")))
    return sizes.crossJoin(missed).select("excerpts", "missed", (F.col("n") - F.col("excerpts") <= 1.2 * (F.col("p") - F.col("excerpts")) + 50).alias("fewer_false_flows"))


@query("fragmentation", f"with {o.DOCS}, {o.blocks()} select 'packet' as assembly, (select sum(greatest(1, (len(hx) // 2 + 63) // 64)) from trace)::bigint as packets, 0::bigint as blocks union all select 'flow', (select count(*) from trace), (select count(*) from blk)")
def _(spark, d):
    return w.fragmentation(spark, d)


@query("small_blocks", "select 6 as size, sum(greatest(0, length(text) - 68))::bigint as blocks from documents")
def _(spark, d):
    return w.small_blocks(spark, d)


@query("encrypted", f"with {o.DOCS}, {o.SIZE}, {o.UNIQUE_ALL} select 'plain' as \"view\", 'plain' as excerpt_form, (select count(*) from excerpts) as found union all select 'wire', 'plain', 0 union all select 'wire', 'coded', (select count(*) from excerpts)")
def _(spark, d):
    return w.encrypted(spark, d)


@query("reassembled_blocks", f"with turns as (select conv_id, turn, hex(encode(coalesce(text, ''))) as h from conversations), trace(flow_key, seq, hx) as (select conv_id::varchar, 0::bigint, string_agg(h, '' order by turn) from turns group by conv_id), {o.blocks()} select flow_key, block_no, start, size, md5(block) as digest from blk")
def _(spark, d):
    whole = trace.reassemble(trace.from_conversations(w.table(spark, d, "conversations")))
    return blocking.winnow_blocks(whole).select("flow_key", "block_no", "start", "size", F.md5("block").alias("digest"))


@query("ledger_blocks", f"with {o.LEDGER_ROWS}, trace(flow_key, seq, hx) as (select concat_ws('|', s, c), 0::bigint, string_agg(hex(encode(txt)), '0A' order by ok * 16 + ln, encode(txt)) from rows_ group by s, c), {o.blocks()} select size, count(*) as blocks from blk group by size")
def _(spark, d):
    whole = trace.reassemble(w.ledger_trace(spark, d), separator=b"\n")
    return measures.block_size_hist(blocking.winnow_blocks(whole))


@query("ledger_years", f"with {o.LEDGER_ROWS} select y::int as interval_id, concat_ws('|', s, c) as flow_key, count(*) as packets, sum(length(txt))::bigint as bytes from rows_ group by all")
def _(spark, d):
    return bitindex.flow_list(w.ledger_trace(spark, d, yearly=True)).select("interval_id", "flow_key", "packets", "bytes")


@query("model_flow_fpr", f"{o.SETUP_ALL} select round(avg(pow(0.5, n)), 6) as model_fpr from (select flow_key, count(*) as n from xblk group by 1)")
def _(spark, d):
    blocks = attribution.excerpt_blocks(w.unique_excerpts(spark, d), DigestConfig())
    return measures.model_flow_fpr(0.5, blocks.groupBy("excerpt_id").agg(F.count("*").alias("n")))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """excerpt_id, interval_id, flow_key, src, dst: the whole procedure on documents."""
    e = w.Experiment(spark, sf_dir, count=None)
    return attribution.attribute(e.excerpts, dg.build(e.packets, DigestConfig(sections=256, index=True).sized(e.raw)))
