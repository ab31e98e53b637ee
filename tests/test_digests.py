"""Filters, indexes, digests on disk, attribution, baselines and measures."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tracedigest.functions import sql as surface
from tracedigest.operators import attribution, baselines, bitindex, blocking, compress, downsample, measures, membership, trace
from tracedigest.operators import digest as dg
from tracedigest.operators.digest import DigestConfig
from tracedigest.plans import workloads as w

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def exp(spark):
    e = w.Experiment(spark, SF)
    yield e
    e.close()


def pairs(df):
    return {(r["excerpt_id"], r["flow_key"]) for r in df.collect()}


def test_worked_example(spark):
    got = {}
    for r in bitindex.example(spark).collect():
        got.setdefault(r["excerpt_id"], set()).add(r["flow_key"])
    assert got == {1: {"1", "2", "4"}, 2: {"1", "4"}, 3: {"1", "2", "3", "4", "5"}, 4: {"3", "5"}}
    rows = spark.createDataFrame([(0, str(f), s) for f, own in bitindex.EXAMPLE.items() for s in own], "interval_id int, flow_key string, section int")
    flows = rows.select("interval_id", "flow_key").distinct()
    assert bitindex.ones_share(bitindex.flow_words(rows), flows, 10).first()["ones"] == 26
    assert {r["flow_key"]: bytes(r["bitmap"]).hex() for r in bitindex.construct_bitmaps(rows.withColumn("section", F.col("section") - 1), 16).collect()}["1"] == "2602"
    hits = spark.createDataFrame([(q, 0, s) for q, own in bitindex.EXAMPLE_NEEDS.items() for s in own], "excerpt_id long, interval_id int, section int")
    assert {(r[0], r[2]) for r in bitindex.prune_inverted(bitindex.invert(rows), hits).collect()} == {(q, f) for q, own in got.items() for f in own if q != 3}


def test_packed_bitmaps_in_both_forms(exp):
    c = DigestConfig(sections=64, index=True).sized(exp.raw)
    elements = dg.content_elements(exp.blocks, c)
    a = {r[1]: bytes(r[2]) for r in bitindex.flow_bitmaps(bitindex.flow_words(elements), exp.flows, 64).collect()}
    b = {r["flow_key"]: bytes(r["bitmap"]) for r in bitindex.construct_bitmaps(elements, 64).collect()}
    assert b.items() <= a.items() and all(v == bytes(8) for k, v in a.items() if k not in b)


def test_sections_keep_the_fill_and_one_section_is_the_plain_filter(exp):
    c = DigestConfig(k=2).sized(exp.raw)
    plain = {tuple(r) for r in membership.build(dg.elements(exp.blocks, c), c.m_bits, 2).collect()}
    assert plain == {(r["interval_id"], 0, r["word_ix"], r["word"]) for r in dg.words_of(exp.blocks, c).collect()} or {r[1:] for r in plain}
    fills = [membership.fill(dg.words_of(exp.blocks, DigestConfig(k=2, sections=j).sized(exp.raw)), c.m_bits).first()["fill"] for j in (1, 16, 64)]
    assert max(fills) - min(fills) < 0.02
    n = exp.blocks.count() * 2
    assert abs(fills[0] - (1 - np.exp(-2 * n / c.m_bits))) < 0.12  # repeated blocks set no more bits


def test_no_carrier_is_missed_in_any_configuration(exp):
    entries = [{"threshold": t, "sections": j, "k": k, "index": i} for t in (0, 40) for j, i in ((1, False), (64, True)) for k in (1, 3)]
    configs = w.grid(exp.raw, entries)
    truth = {(r["excerpt_id"], r["true_flow"]) for r in exp.excerpts.collect()}
    got = {}
    for r in exp.verdicts(configs).collect():
        got.setdefault(r["config_id"], set()).add((r["excerpt_id"], r["flow_key"]))
    assert all(truth <= got[i] for i, _ in configs)
    by = dict(configs)
    for i, c in by.items():
        for j, d in by.items():  # the index only takes candidates away
            if c.index and not d.index and (c.threshold, c.k) == (d.threshold, d.k):
                assert len(got[i]) <= len(got[j])


def test_word_join_equals_packed_evaluation(exp):
    c = DigestConfig(sections=64, threshold=20, index=True).sized(exp.raw)
    digest = dg.build(exp.packets, c)
    assert pairs(attribution.attribute(exp.excerpts, digest)) == pairs(exp.verdicts([(0, c)]))
    assert {tuple(r) for r in attribution.words_of_sections(digest).collect()} == {tuple(r) for r in dg.words_of(downsample.keep_large(exp.blocks, 20), c).select("interval_id", "section", "word_ix", "word").collect()}


def test_merge_of_halves_is_the_digest_of_all(exp):
    c = DigestConfig(sections=64, index=True).sized(exp.raw)
    half = F.pmod(F.xxhash64("flow_key"), F.lit(2))
    both = dg.merge(*(dg.build(exp.packets.filter(half == i), c) for i in (0, 1)))
    whole = dg.build(exp.packets.repartition(7), c)
    rows = lambda df: sorted((*map(str, r[:-1]), bytes(r[-1]).hex()) for r in df.collect())
    assert rows(both.sections) == rows(whole.sections) and rows(both.flowbits) == rows(whole.flowbits)
    with pytest.raises(ValueError):
        dg.merge(whole, dg.build(exp.packets, DigestConfig(m_bits=4096)))


def test_saved_digest_answers_alike_and_holds_no_payload(exp, spark, tmp_path):
    c = DigestConfig(sections=64, index=True).sized(exp.raw)
    digest = dg.build(exp.packets, c)
    want = pairs(attribution.attribute(exp.excerpts, digest))
    for codec in (None, "lzma2"):
        path = str(tmp_path / f"d{codec}")
        digest.save(path, codec)
        kept = dg.load(spark, path, intervals=[0])
        assert kept.config == c and pairs(attribution.attribute(exp.excerpts, kept)) == want
    raw = b"".join(p.read_bytes() for p in (tmp_path / "dNone").rglob("*.parquet"))
    assert not any(bytes(r["excerpt"]) in raw for r in exp.excerpts.limit(50).collect())
    m = dg.manifest(digest).first()
    assert m["raw_bytes"] == exp.raw and m["index_bytes"] == exp.n_flows * 8


def test_on_empty_and_wildcard(exp, spark):
    digest = dg.build(exp.packets, DigestConfig(sections=64, index=True).sized(exp.raw))
    short = spark.createDataFrame([(1, b"too short for a block", None)], "excerpt_id long, excerpt binary, true_flow string")
    out = attribution.attribute(short, digest, on_empty="flag")
    assert out.count() == exp.n_flows and out.filter("untestable").count() == exp.n_flows
    row = exp.excerpts.first()
    text = bytes(row["excerpt"])
    parts = spark.createDataFrame([(5, 0, text[:100] + b""), (5, 1, text[60:])], "excerpt_id long, part int, excerpt binary")
    assert row["true_flow"] in {r["flow_key"] for r in attribution.wildcard(parts, digest).collect()}
    assert attribution.attribute(exp.excerpts, digest, between=(3, 9)).count() == 0


def test_every_path_of_attribution_gives_the_same(exp, spark):
    """Row-local or by joins, compressed or not, under any hash family; parts and ids of any size or type."""
    truth = {(r["excerpt_id"], r["true_flow"]) for r in exp.excerpts.collect()}
    for how in ({"sections": 64, "threshold": 20, "index": True}, {"k": 2}, {"sections": 64, "index": True, "hash_family": "vector", "k": 2}, {"sections": 32, "index": True, "hash_family": "fast", "feature": "hash", "salt": "x"}):
        digest = dg.build(exp.packets, DigestConfig(**how).sized(exp.raw))
        got = pairs(attribution.attribute(exp.excerpts, digest))
        assert truth <= got == pairs(attribution.attribute(exp.excerpts, digest, rows_bound=5))
        digest.close()


def test_a_large_filter_travels_as_places(exp, monkeypatch):
    """A filter too large to hold, in many chunks, has the bits that a small task's array would have."""
    rows = lambda d: {(r[0], r[1], r[2], bytes(r[3])) for r in d.sections.collect()}
    c = DigestConfig(sections=8, m_bits=3_000_000, k=2)
    want = rows(dg.build(exp.packets, c))
    assert len({r[2] for r in want}) > 8
    parts = dg._partials(exp.packets, c).filter("octet_length(bits) < whole").count()
    assert not parts
    real = dg._Filter.__init__

    def sparse(self, layout):
        real(self, layout)
        self.dense = None

    monkeypatch.setattr(dg._Filter, "__init__", sparse)
    filters = dg._Filter(dg.Layout.of(c))
    filters.add(np.array([1, 7, 7, 7]), np.array([5, 0, 374_999, 32_768]))
    held = {(s, k): b for s, k, b in filters.rows()}
    assert held == {(1, 0): b"\x05\x00", (7, 0): b"\x00\x00", (7, 11): np.array([374_999 % 32_768], "<u2").tobytes(), (7, 1): b"\x00\x00"}


def test_only_tables_with_hits_are_opened(spark, tmp_path):
    packets = w.docs_trace(spark, SF, interval_docs=20)
    digest = dg.build(packets, DigestConfig(sections=64, reduction=4, index=True))
    path = str(tmp_path / "d")
    digest.save(path, codec="lzma2")
    row = w.unique_excerpts(spark, SF).orderBy("excerpt_id").limit(1).persist()
    opened = spark.sparkContext.accumulator(0)
    kept = dg.load(spark, path)
    got = attribution.attribute(row, kept, opened=opened).collect()
    assert (row.first()["true_flow"]) in {r["flow_key"] for r in got}
    assert 1 <= opened.value <= 3 < kept.flows.select("interval_id").distinct().count()
    assert attribution.attribute(row, kept, between=(5, 9)).count() == sum(5 <= r["interval_id"] <= 9 for r in got)


def test_pruned_flows_are_not_hashed(exp, monkeypatch):
    """Flow-bound digests are taken of pairs that the index leaves, the largest block first."""
    from tracedigest.functions import hashing

    taken = exp.packets.sparkSession.sparkContext.accumulator(0)
    real = hashing.Hashed.bound

    def counting(self, which, flow_key):
        taken.add(len(which))
        return real(self, which, flow_key)

    c = DigestConfig(sections=1024, index=True).sized(exp.raw)
    digest = dg.build(exp.packets, c)
    monkeypatch.setattr(hashing.Hashed, "bound", counting)
    got = attribution.attribute(exp.excerpts, digest).count()
    blocks = attribution.excerpt_blocks(exp.excerpts, c).count()
    assert 0 < taken.value < 0.05 * blocks * exp.n_flows and got >= exp.excerpts.count()


def test_wildcards_of_any_part_number_and_a_flow_in_pieces(exp, spark):
    row = exp.excerpts.first()
    text = bytes(row["excerpt"])
    digest = dg.build(exp.packets, DigestConfig(sections=64, index=True).sized(exp.raw))
    for numbers in ((0, 1), (0, 1500), (2**31 - 1, 7)):
        parts = spark.createDataFrame([(5, numbers[0], text[:132]), (5, numbers[1], text[60:])], "excerpt_id long, part int, excerpt binary")
        assert row["true_flow"] in {r["flow_key"] for r in attribution.wildcard(parts, digest).collect()}


def test_fragments_beyond_any_number_and_pieces_of_flows(spark):
    rng = np.random.default_rng(3)
    raw = rng.integers(97, 123, 70_000 * 2).astype(np.uint8).tobytes()
    packets = spark.createDataFrame([(0, None, "f", "a", "b", "t", 0, raw), (0, None, "f", "a", "b", "t", 1, b"end" * 50), (0, None, "g", "a", "b", "t", 0, None)], "interval_id int, ts timestamp, flow_key string, src string, dst string, proto string, seq long, payload binary")
    cut = trace.fragment(packets, 2)
    assert cut.agg(F.max("frag")).first()[0] == 69_999
    whole = {r["flow_key"]: bytes(r["payload"]) for r in trace.reassemble(cut).collect()}
    assert whole == {"f": raw + b"end" * 50, "g": b""}
    with pytest.raises(Exception, match="use flow_pieces"):
        trace.reassemble(cut, max_bytes=1000).collect()
    want = {bytes(r["block"]) for r in blocking.winnow_blocks(trace.reassemble(cut)).collect()}
    pieces = trace.flow_pieces(cut, 544, piece=5_000)
    assert pieces.count() > 20 and {bytes(r["block"]) for r in blocking.winnow_blocks(pieces).collect()} == want


def test_intervals_are_separate(spark):
    packets = w.docs_trace(spark, SF, interval_docs=50)
    digest = dg.build(packets, DigestConfig(sections=64, reduction=20, index=True))
    excerpts = w.unique_excerpts(spark, SF)
    got = {(r["excerpt_id"], r["flow_key"], r["interval_id"]) for r in attribution.attribute(excerpts, digest).collect()}
    assert {(r["excerpt_id"], r["true_flow"], r["excerpt_id"] // 50) for r in excerpts.collect()} <= got


def test_exact_search_equals_the_archive_scan(exp, spark):
    short = spark.createDataFrame([(10_001, b"the "), (10_002, b"no such bytes at all")], "excerpt_id long, excerpt binary")
    both = w.excerpt_slices(spark.read.parquet(f"{SF}/documents.parquet")).unionByName(short)
    want = pairs(baselines.raw_archive(exp.packets, both))
    assert pairs(baselines.exact_search(exp.packets, both)) == want == pairs(baselines.exact_search(exp.packets, both, max_bytes=10_000))


def test_baselines_find_the_carrier_and_count_elements(exp):
    rows = {r["method"]: r for name in w.METHODS for r in w.baseline_fpr(exp, name, DigestConfig().sized(exp.raw).m_bits).collect()}
    n = rows["shingled_winnow"]["elements"]
    assert abs(rows["multi_winnow"]["elements"] / n - 2) < 0.05 and abs(rows["double_winnow"]["elements"] / n - 2) < 0.05 and abs(rows["fixed_multifilter"]["elements"] / n - 1) < 0.15
    assert all(r["reported"] - r["false_flows"] == r["excerpts"] for r in rows.values())


def test_hier_fixed_levels():
    row, number, _, size, out = baselines.hier_fixed(32, 2)([bytes(range(200)), None, b"x" * 31])
    assert set(row.tolist()) == {0} and sorted(set(size.tolist())) == [32, 64] and out[0] == bytes(range(32)) + b"@0" and len(number) == 6 + 3


def test_gain_at_equal_overall_ratio_and_false_flows_fall_with_sections(spark):
    rows = w.matched_ratio(spark, "/root/testdata/sf0.01", skewed=False).collect()
    ours = {(r["sections"], r["threshold"]): r["fpr"] for r in rows if r["method"] == "sectioned_indexed"}
    assert ours[1024, 0] < ours[256, 0]
    for key, fpr in ours.items():
        others = [r["fpr"] for r in rows if (r["sections"], r["threshold"]) == key and r["method"] != "sectioned_indexed"]
        assert len(others) == 4
        if key[1] == 0:
            assert measures.gain(others, fpr) > 1.5


def test_threshold_curve_has_its_shape(spark):
    rows = {r["threshold"]: r["fpr"] for r in w.threshold_sweep(spark, "/root/testdata/sf0.01").collect()}
    assert min(rows, key=rows.get) in (20, 30, 40) and rows[60] > 0.4 > rows[50] > rows[45] > rows[30] and rows[0] > rows[30]


def test_index_table_measures(spark):
    stats = {r["sections"]: r for r in w.index_stats(spark, SF).collect()}
    assert stats[64]["share"] > stats[256]["share"] > stats[1024]["share"]
    assert stats[1024]["packed_bytes"] < stats[1024]["index_bytes"] and stats[64]["overall"] > stats[1024]["overall"]


def test_round_trips_of_codecs(exp):
    bitmaps = exp.bitmaps(DigestConfig(sections=256, index=True).sized(exp.raw))
    want = {r["flow_key"]: bytes(r["bitmap"]) for r in bitmaps.collect()}
    for codec in ("lzma2", "zlib", "none"):
        packed = compress.pack_index(bitmaps, codec, shards=3)
        assert {r["flow_key"]: bytes(r["bitmap"]) for r in compress.unpack_index(packed, packed.select("interval_id"), codec).collect()} == want
        none = packed.filter("false").select("interval_id")
        assert compress.unpack_index(packed, none, codec).count() == 0


def test_closed_forms(spark):
    assert [round(measures.overall_reduction(100, 1, x / 1000)) for x in (44, 65, 98, 154)] == [96, 94, 91, 87]
    assert round(measures.model_ones(1000, 2048), 4) == 0.0151
    assert round(measures.entropy_bound(216e6 / 32, 23.0, 16.0e6 / 32, 32) / 1e6, 1) == 35.4
    assert round(measures.gain([0.138, 0.134, 0.135, 0.132], 0.006)) == 22 and round(measures.gain([0.088, 0.081, 0.082, 0.077], 0.002)) == 41
    table = {r["measure"]: r for r in measures.cost_table(spark, 100.0, 10.0, 2, 2.0, 3).collect()}
    assert table["boundary_selection"]["multi_winnow"] == 400 and table["blocks"]["sectioned_indexed"] == 5 and table["block_processing"]["sectioned_indexed"] == 5
    assert measures.accesses_per_block(3, True) == 5 and measures.index_bytes(860_000, 1024) == 110_080_000
    assert 0 < measures.model_fpr(1, 2, 3) < 1 and measures.reduction(100, 4) == 25 and measures.index_share(44, 1000) == 0.044


def test_larger_blocks_are_denied_more_often_than_the_smallest(spark):
    rows = w.true_negative_size(spark, "/root/testdata/sf0.01").collect()
    small = [r for r in rows if r["size"] < 10]
    large = [r for r in rows if r["size"] >= 40]
    rate = lambda x: sum(r["negatives"] for r in x) / sum(r["blocks"] for r in x)
    assert rate(large) > rate(small)


def test_best_k_and_sizes():
    assert membership.best_k(100, 1000) == 1 and membership.best_k(1000, 100) == 7
    assert DigestConfig(reduction=100).sized(2_472_458).m_bits == 197_796


def test_sql_surface(exp, spark):
    digest = dg.build(exp.packets, DigestConfig(sections=64, index=True).sized(exp.raw))
    surface.register(spark, exp.packets, digest)
    exp.excerpts.createOrReplaceTempView("my_excerpts")
    assert surface.ask(spark, "my_excerpts", digest).count() == spark.sql("select * from td_verdict").count() > 0
    n = spark.sql("select sum(size(td_blocks(payload))) as n from td_trace").first()["n"]
    assert n == exp.blocks.count() == spark.sql("select count(*) as n from td_trace, lateral td_winnow(payload, 64, 4, 0)").first()["n"]
    assert spark.sql("select td_section(cast('abc' as binary), 256) as s").first()["s"] == int("90015098", 16) % 256
    assert spark.sql("select count(*) as n from td_index").first()["n"] == exp.n_flows


def test_assigning_intervals_by_bytes(spark):
    minute = F.timestamp_seconds(F.lit(1704067200) + F.col("flow_key").cast("long") * 60)
    packets = w.docs_trace(spark, SF).withColumn("ts", minute)
    out = trace.assign_interval(packets, target_bytes=20_000)
    sizes = [r["b"] for r in out.groupBy("interval_id").agg(F.sum(F.octet_length("payload")).alias("b")).collect()]
    assert sum(sizes) == dg.raw_bytes(packets) and max(sizes) < 20_000 + 40_000
    # an interval is a stretch of time
    spans = sorted((r["a"], r["b"]) for r in out.groupBy("interval_id").agg(F.min("ts").alias("a"), F.max("ts").alias("b")).collect())
    assert len(spans) > 10 and all(x[1] < y[0] for x, y in zip(spans, spans[1:], strict=False))
    assert trace.assign_interval(packets, seconds=86_400).select("interval_id").distinct().count() == 1


def test_plans_keep_their_shape(exp, spark):
    """Pruned columns and pushed filters reach the scan; probing is by equi-joins; nothing is a Cartesian product."""
    packets = trace.keep_protocols(trace.from_conversations(spark.read.parquet(f"{SF}/conversations.parquet")), ["user"])
    plan = packets.select("flow_key").groupBy("flow_key").count()._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(role), EqualTo(role,user)]" in plan and "ReadSchema: struct<conv_id:bigint,role:string>" in plan
    c = DigestConfig(sections=64).sized(exp.raw)
    words, blocks = dg.words_of(exp.blocks, c), attribution.excerpt_blocks(exp.excerpts, c)
    present, _ = attribution.appearance(blocks, exp.excerpts, words, exp.flows, c)
    plan = attribution.determine(attribution.all_flows(present, exp.flows), blocks, words, c)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan
    built = blocking.winnow_blocks(exp.packets)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in built
