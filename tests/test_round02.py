"""What the second round's findings were about: filters, blocks and streams at size."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from tracedigest.operators import attribution, baselines, blocking, downsample
from tracedigest.operators import digest as dg
from tracedigest.operators.digest import DigestConfig
from tracedigest.plans import workloads as w

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def exp(spark):
    e = w.Experiment(spark, SF)
    yield e
    e.close()


def of_words(words, config):
    out = np.zeros((config.filter_sections, -(-max(1, config.m_bits // config.filter_sections) // 32)), np.uint32)
    for r in words.collect():
        out[r["section"], r["word_ix"]] = r["word"]
    return out


def test_filters_come_as_packed_chunks_and_equal_the_words(exp, monkeypatch):
    """Not as a row per word: a filter of 100 MB has 26 million words, and 26 thousand chunks."""
    configs = w.grid(exp.raw, [{"threshold": t, "k": 2} for t in (0, 40)] + [{"sections": 64, "threshold": 20, "keep_equal": False}]) + [(3, DigestConfig(m_bits=3_000_000, sections=8))]
    want = {i: of_words(dg.words_of(downsample.keep_large(exp.blocks, c.threshold, c.keep_equal), c), c) for i, c in configs}
    monkeypatch.setattr(dg, "MANY_PLACES", 5_000)
    monkeypatch.setattr("pyspark.sql.DataFrame.toPandas", None, raising=False)
    assert dg.packed_filters(exp.packets, configs).count() <= sum(dg.Layout.of(c).sections * dg.Layout.of(c).chunks for _, c in configs)
    got = exp.filters(configs)
    assert got.keys() == want.keys() and all(np.array_equal(got[i], want[i]) for i in want)


def test_configurations_go_in_passes_of_bounded_bytes(exp, monkeypatch):
    configs = w.grid(exp.raw, [{"k": 1}, {"k": 2}, {"sections": 64, "index": True}])
    size = configs[0][1].m_bits // 8
    assert [[i for i, _ in p] for p in w.in_passes(configs, 2 * size + 2)] == [[0, 1], [2]]
    want = {tuple(r) for r in exp.verdicts(configs).select("config_id", "flow_key", "excerpt_id").collect()}
    monkeypatch.setattr(w, "in_passes", lambda c, most=0, f=w.in_passes: f(c, 2 * size + 2))
    assert {tuple(r) for r in exp.verdicts(configs).select("config_id", "flow_key", "excerpt_id").collect()} == want
    monkeypatch.setattr(w, "PASS_BYTES", 1)  # a filter that fits in no pass: by joins
    monkeypatch.setattr(w, "in_passes", lambda c, most=0, f=w.in_passes: f(c, 1))
    monkeypatch.setattr(attribution, "evaluate", None)
    monkeypatch.setattr(attribution.attribute, "__defaults__", ("positive", None, 0, 0, None))
    assert {tuple(r) for r in exp.verdicts(configs[2:]).select("config_id", "flow_key", "excerpt_id").collect()} == {r for r in want if r[0] == 2}


def test_sizes_of_a_baseline_share_one_pass(exp):
    m = DigestConfig().sized(exp.raw).m_bits
    for name in ("double_winnow", "fixed_multifilter"):
        both = {r["config_id"]: r for r in w.baseline_rates(exp, name, [(m, 1), (2 * m, 2)]).collect()}
        assert both[1].asDict() == w.baseline_rates(exp, name, [(2 * m, 2)]).withColumn("config_id", F.lit(1)).first().asDict()
        assert both[0]["reported"] == w.baseline_fpr(exp, name, m).first()["reported"]


def test_payloads_with_a_block_for_each_byte_are_cut_in_parts(spark, monkeypatch):
    rows = spark.createDataFrame([(0, str(i), 0, b"a" * 3000) for i in range(100)], "interval_id int, flow_key string, seq long, payload binary").coalesce(1)
    limit = spark.sparkContext.accumulator(0)

    def cut(payloads):
        if sum(map(len, payloads)) > blocking.CUT_BYTES + 3000:
            limit.add(1)
        return blocking.winnow_batch(payloads)

    assert blocking.block_rows(rows, cut).groupBy("flow_key").count().filter("count <> 2932").count() == 0
    assert limit.value == 0
    assert [tuple(r) for r in blocking.block_sizes(rows).collect()] == [(6, 293_200)]
    assert blocking.block_count(rows, cut) == 293_200
    docs = w.docs_trace(spark, SF)
    assert {tuple(r) for r in blocking.block_sizes(docs).collect()} == {tuple(r) for r in blocking.winnow_blocks(docs).groupBy("size").count().collect()}


def test_streams_read_tables_that_are_folders(spark, tmp_path):
    """A table may be a file or a folder of files with names of their own."""
    from tracedigest.plans import stream_queries as sq

    for name in ("conversations", "documents", "events"):
        spark.read.parquet(f"{SF}/{name}.parquet").repartition(3).write.parquet(f"{tmp_path}/{name}.parquet")
    spark.read.parquet(f"{SF}/benchmark.parquet").write.parquet(f"{tmp_path}/benchmark.parquet")
    for f in (sq.stream_reassembled, sq.stream_watch, sq.stream_filter_words):
        rows = lambda d, f=f: sorted(map(tuple, f(spark, d).collect()))
        assert rows(str(tmp_path)) == rows(SF) != []


def test_candidates_are_counted_without_their_pairs(exp, spark):
    c = DigestConfig(sections=64, threshold=40, index=True).sized(exp.raw)
    short = spark.createDataFrame([(10**6, b"no block")], "excerpt_id long, excerpt binary")
    excerpts = exp.excerpts.select("excerpt_id", "excerpt").unionByName(short)
    pairs = attribution.candidates_of(attribution.excerpt_blocks(excerpts, c), exp.words(c), exp.flows, excerpts, c)
    want = {r["excerpt_id"]: r["count"] for r in pairs.groupBy("excerpt_id").count().collect()}
    maps = dg.packed_bitmaps(exp.packets, [(0, c)]).withColumnRenamed("b0", "bitmap")
    assert {r["flow_key"]: bytes(r["bitmap"]) for r in maps.collect()} == {r["flow_key"]: bytes(r["bitmap"]) for r in exp.bitmaps(c).collect()}
    for part in (500_000, 50):
        got = {r["excerpt_id"]: r["c"] for r in attribution.candidate_counts(excerpts, maps, c, part).collect()}
        assert {i: n for i, n in got.items() if n} == want and want[10**6] == exp.n_flows


def test_the_local_pass_is_spread_over_tasks(exp, spark):
    """The flows' bitmaps are a few MB, which one task would read; each flow is asked about every excerpt."""
    digest = dg.build(exp.packets.coalesce(1), DigestConfig(sections=64, index=True).sized(exp.raw))
    hit = [(r["excerpt_id"], 0) for r in exp.excerpts.collect()]
    rows = spark.createDataFrame(hit, "excerpt_id long, interval_id int").collect()
    found = attribution._local(exp.excerpts.select("excerpt_id", "excerpt"), digest, digest.flows, rows, [0], None)
    assert found.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism


def test_the_worked_example_over_a_table(spark):
    from tracedigest.operators import bitindex
    from tracedigest.plans import queries as q

    found = q.QUERIES["bitmap_example"](spark, SF)
    assert any("lineitem" in f for f in found.inputFiles())
    lines = {}
    for r in spark.read.parquet(f"{SF}/lineitem.parquet").select("l_orderkey", "l_partkey").collect():
        lines.setdefault(str(r[0]), set()).add(r[1] % 10 + 1)
    assert {tuple(r) for r in found.collect()} == {(i, f) for f, own in lines.items() for i, need in bitindex.EXAMPLE_NEEDS.items() if own >= set(need)}


def test_unique_excerpts_are_found_without_their_pairs_or_bytes_in_the_driver(spark, monkeypatch):
    """Copies of a text don't become pairs, and no excerpt is collected."""
    docs = w.table(spark, SF, "documents").select(F.col("doc_id"), F.encode(F.coalesce("text", F.lit("")), "UTF-8").alias("data"))
    short = docs.select(F.col("doc_id").alias("excerpt_id"), F.expr("substring(data, 20, 30 + cast(doc_id % 200 as int))").alias("excerpt"))
    for excerpts, by in ((w.excerpt_slices(w.table(spark, SF, "documents")), "skew"), (short, "doc_id")):
        packets = w.docs_trace(spark, SF, by=by)
        found = baselines.exact_search(packets, excerpts).groupBy("excerpt_id").agg(F.count("*").alias("n"), F.min("flow_key").alias("f")).filter("n = 1")
        want = {(r["excerpt_id"], r["f"]) for r in found.collect()}
        assert {tuple(r) for r in baselines.carried_once(packets, excerpts).collect()} == want != set()
        assert {tuple(r) for r in baselines.carried_once(packets, excerpts, most=5).collect()} == want
    text = b"".join(b"line %d of the copied text, " % i for i in range(100))
    copies = spark.createDataFrame([(0, str(i), 0, text if i else text[:600] + b"only here " * 30) for i in range(300)], "interval_id int, flow_key string, seq long, payload binary").coalesce(2)
    slices = spark.createDataFrame([(i, text[i : i + 200]) for i in range(300)] + [(300, b"only here " * 20), (301, None)], "excerpt_id long, excerpt binary")
    monkeypatch.setattr(baselines, "exact_search", None)
    found = baselines.carried_once(copies, slices)
    assert [tuple(r) for r in found.collect()] == [(300, "0")]


def test_alignments_of_fixed_blocks_are_asked_in_parts(exp, monkeypatch):
    m = DigestConfig().sized(exp.raw).m_bits
    rows = lambda: {tuple(r) for r in w.fixed_verdicts(exp, [(m, 1), (m, 2)]).collect()}
    want = rows()
    most = []
    monkeypatch.setattr(w, "ALIGNED", 7)
    monkeypatch.setattr(w, "content_alive", lambda r, *a, f=w.content_alive: (most.append(len(r)), f(r, *a))[1])
    assert rows() == want != set()
    assert max(most) <= 7 * 200


def test_every_pair_is_asked_without_an_exchange_of_probes(spark, monkeypatch):
    from tracedigest.plans import queries as q

    run = lambda: q.QUERIES["determine_exhaustive"](spark, SF)
    with monkeypatch.context() as m:
        m.setattr(baselines, "excerpt_bytes", lambda x: 1 << 40)  # too many for one pass: by joins
        want = sorted(map(tuple, run().collect()))
    monkeypatch.setattr(attribution, "determine", None)
    assert sorted(map(tuple, run().collect())) == want != []


def test_md5_of_short_blocks_is_the_interpreters_own():
    import hashlib

    from tracedigest.functions import hashing

    assert hashing.digests([b"", b"a" * 69], b"|7", salt="s") == b"".join(hashlib.md5(b"s" + x + b"|7").digest() for x in (b"", b"a" * 69))
    assert hashing.md5 is not hashlib.md5


def test_sizes_are_counted_a_piece_of_a_payload_at_a_time(spark, monkeypatch):
    """A payload of any length is cut in bounded parts, and payloads of one character are made in the tasks, not sent to them."""
    from tracedigest.plans import queries as q

    text = np.random.default_rng(5).integers(0, 4, 200_000, np.uint8).tobytes()
    payloads = [b"a" * 100_000, None, text, b"", text[:500], b"a" * 69, *[text[i : i + 300] for i in range(0, 9_000, 300)], b"a" * 68, text[:7_000]]
    size = blocking.winnow_batch(payloads)[3]
    most = []
    monkeypatch.setattr(blocking, "CUT_BYTES", 5_000)
    monkeypatch.setattr(blocking, "bounds_of", lambda data, *a, f=blocking.bounds_of: (most.append(len(data)), f(data, *a))[1])
    assert np.array_equal(blocking.size_counts(payloads), np.bincount(size, minlength=70))
    assert max(most) <= 2 * 5_000 + 2 * 64
    found = q.QUERIES["small_blocks"](spark, SF)
    assert "repeat(" not in found._jdf.queryExecution().toString()
    assert [tuple(r) for r in found.collect()] == [(6, w.table(spark, SF, "documents").selectExpr("sum(greatest(0, length(text) - 68))").first()[0])]


def test_pairs_cross_no_exchange_where_excerpts_go_in_parts(exp, spark, monkeypatch):
    """More hits than one pass takes are asked in several; the verdicts of a large table would fill the disk in an exchange."""
    short = spark.createDataFrame([(10**6, b"no block")], "excerpt_id long, excerpt binary")
    excerpts = exp.excerpts.select("excerpt_id", "excerpt").unionByName(short).coalesce(1).persist()
    n = excerpts.count()
    digest = dg.build(exp.packets, DigestConfig(sections=256, threshold=40, index=True).sized(exp.raw))
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    want = rows(attribution.attribute(excerpts, digest, rows_bound=0, packed_bound=0))  # by joins
    assert sum(r[0] == 10**6 for r in want) == exp.n_flows
    parts = []
    monkeypatch.setattr(attribution, "_joined", None)
    monkeypatch.setattr(attribution, "_asked", lambda own, blocks, hits, *a, f=attribution._asked: (parts.append(len(hits)), f(own, blocks, hits, *a))[1])
    assert rows(attribution.attribute(excerpts, digest, rows_bound=n - 1)) == want
    assert len(parts) == 3 and sum(parts) == n
    for found in (attribution.attribute(excerpts, digest, ends=False), attribution.attribute(excerpts, digest, rows_bound=n - 1, ends=False)):
        assert found.columns == ["excerpt_id", "interval_id", "flow_key"]
        assert not {"Join", "Aggregate", "Repartition"} & set(re.findall(r"[A-Z]\w+", found._jdf.queryExecution().optimizedPlan().toString().split("MapInArrow")[0]))
    assert rows(attribution.attribute(excerpts, digest, ends=False)) == [r[:3] for r in want]
    digest.close()
    excerpts.unpersist()
