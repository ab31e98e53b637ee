"""What the third round's findings were about."""

import re

import numpy as np

from tracedigest.functions.hashing import Hashed, digests, flow_suffix, md5_parts
from tracedigest.operators import attribution, baselines
from tracedigest.operators import digest as dg
from tracedigest.operators.digest import DigestConfig
from tracedigest.plans import workloads as w
from tracedigest.plans.queries import QUERIES

SF = "/root/testdata/sf0.001"


def test_a_task_hands_on_filters_in_which_it_set_nothing(spark):
    """As after its last full hand-over, of payloads without blocks, or for a configuration that keeps none of them."""
    configs = [(0, DigestConfig(m_bits=4096)), (1, DigestConfig(m_bits=4096, sections=4, threshold=99))]
    assert list(dg._Filter(dg.Layout.of(configs[0][1]), 0).rows()) == []
    short = spark.createDataFrame([(0, "a", 0, b"short"), (0, "b", 0, None)], "interval_id int, flow_key string, seq long, payload binary")
    assert dg.packed_filters(short, configs).count() == 0
    long = short.unionByName(spark.createDataFrame([(0, "c", 0, bytes(np.random.default_rng(3).integers(0, 256, 3000, np.uint8)))], short.schema))
    assert {r["config_id"] for r in dg.packed_filters(long, configs).collect()} == {0}


def test_pairs_of_block_and_flow_are_hashed_as_one_by_one():
    rng = np.random.default_rng(5)
    blocks = [bytes(rng.integers(0, 256, n, np.uint8)) for n in range(200)]
    flows = ["", "7", "51281", "é|en", *["x" * n for n in range(40, 90)]]
    for salt in ("", "salt"):
        hashed = Hashed(blocks, "portable", salt)
        which, of = (x.ravel() for x in np.meshgrid(np.arange(len(blocks)), np.arange(len(flows))))
        want = md5_parts(digests([blocks[b] + flow_suffix(flows[f]) for b, f in zip(which, of, strict=True)], b"", "portable", salt))
        got = hashed.bound(which, hashed.binding(flows), of)
        assert all(np.array_equal(x, y) for x, y in zip(got, want, strict=True))
        assert all(len(x) == 0 for x in hashed.bound(which[:0], hashed.binding([]), of[:0]))


def test_pairs_are_asked_many_at_a_time(spark, monkeypatch):
    """Not flow by flow; and in parts of any size with the same verdicts."""
    e = w.Experiment(spark, SF)
    entries = [{"k": 2}, {"threshold": 40}, {"sections": 64, "index": True}, {"sections": 64, "index": True, "threshold": 60}]
    configs = w.grid(e.raw, entries)
    rows, ids = e.excerpt_rows()
    flows = dg.packed_bitmaps(e.packets, [x for x in configs if x[1].index]).drop("interval_id").coalesce(1)
    found = attribution.evaluate(flows, rows, ids, configs, e.filters(configs)).toArrow().to_pylist()
    want = {tuple(r.values()) for r in found}
    assert len(found) == len(want)
    monkeypatch.setattr(attribution, "HELD_PAIRS", 50)
    monkeypatch.setattr(attribution, "HELD_CELLS", 1)
    assert {tuple(r.values()) for r in attribution.evaluate(flows, rows, ids, configs, e.filters(configs)).toArrow().to_pylist()} == want
    e.close()


def test_flagged_verdicts_meet_no_excerpt_again(spark):
    """The pairs of a large table would fill the disk in a join with the excerpts that were tested."""
    e = w.Experiment(spark, SF)
    digest = dg.build(e.packets, DigestConfig(threshold=60).sized(e.raw))
    rows = lambda df: sorted(map(tuple, df.collect()))
    want = rows(attribution.attribute(e.excerpts, digest, "flag", None, 0, 0, ends=False))  # by joins
    assert {r[-1] for r in want} == {True, False}
    for bound in (attribution.ROWS_BOUND, e.excerpts.count() - 1):
        found = attribution.attribute(e.excerpts, digest, "flag", None, bound, ends=False)
        assert "Join" not in found._jdf.queryExecution().optimizedPlan().toString().split("MapInArrow")[0]
        assert rows(found) == want
    e.close()


def test_pairs_of_too_many_excerpts_for_one_pass_cross_no_exchange(spark, monkeypatch):
    run = lambda: QUERIES["determine_exhaustive"](spark, SF)
    want = sorted(map(tuple, run().collect()))
    monkeypatch.setattr(baselines, "excerpt_bytes", lambda x: 1 << 40)
    monkeypatch.setattr(attribution, "determine", None)
    monkeypatch.setattr(attribution, "_joined", None)
    monkeypatch.setattr(attribution.attribute, "__defaults__", ("positive", None, 50, attribution.PACKED_BOUND, None))  # 50 hits a pass
    found = run()
    assert not {"Join", "Aggregate", "Repartition"} & set(re.findall(r"[A-Z]\w+", found._jdf.queryExecution().optimizedPlan().toString().split("MapInArrow")[0]))
    assert sorted(map(tuple, found.collect())) == want != []


def test_an_excerpt_is_looked_for_at_every_place_of_a_payload(spark):
    """Not at the first 64 blocks alone: then those that start further on are missed."""
    found = QUERIES["b_hier"](spark, SF).first()
    assert w.table(spark, SF, "documents").selectExpr("max(octet_length(text))").first()[0] > 2 * 2048
    assert found["missed"] == 0 and found["alive"] >= found["excerpts"]


def test_places_of_a_large_filter_are_sorted_and_not_hashed(monkeypatch):
    layout = dg.Layout.of(DigestConfig(m_bits=3_000_000, sections=8))
    rng = np.random.default_rng(7)
    section, pos = rng.integers(0, 8, 50_000), rng.integers(0, layout.m_sub, 50_000)
    packed, placed = dg._Filter(layout), dg._Filter(layout, 0)
    for f in (packed, placed):
        f.add(section, pos)
        f.add(section[:100], pos[:100])
    monkeypatch.setattr(np, "unique", None)

    def dense(section, chunk, bits):
        if len(bits) == layout.chunk_bytes(chunk):
            return section, chunk, bits
        own = np.zeros(8 * layout.chunk_bytes(chunk), bool)
        own[np.frombuffer(bits, "<u2")] = True
        return section, chunk, np.packbits(own, bitorder="little").tobytes()

    assert [dense(*r) for r in placed.rows()] == list(packed.rows())
