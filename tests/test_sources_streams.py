"""Sources, sinks and streams; and the library without its training-data operators."""

import os
import subprocess
import sys
from pathlib import Path

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from tracedigest.operators import blocking, trace
from tracedigest.operators.digest import DigestConfig
from tracedigest.plans import stream_queries as sq
from tracedigest.sources import capture, io
from tracedigest.streaming import digest_stream as ds

SF = "/root/testdata/sf0.001"
ROOT = Path(__file__).resolve().parents[1]


def test_capture_source_batch_and_stream(spark, tmp_path):
    packets = [(1700000000.25, "10.0.0.1:1234", "10.0.0.2:80", "tcp", b"GET / HTTP/1.1"), (1700000001.5, "10.0.0.3:53", "10.0.0.1:999", "udp", b"\x00\xff"), (1700000002.0, "10.0.0.1:1234", "10.0.0.2:80", "tcp", b"")]
    raw = capture.capture_bytes(packets)
    (tmp_path / "a.pcap").write_bytes(raw)
    (tmp_path / "b.pcap").write_bytes(raw[:-5])  # cut off
    capture.register(spark)
    rows = spark.read.format("packet_capture").load(str(tmp_path)).collect()
    assert len(rows) == 5
    assert {(r["flow_key"], r["proto"], bytes(r["payload"])) for r in rows} == {(f"{a}>{b}", p, x) for _, a, b, p, x in packets}
    stream = capture.as_trace(spark.readStream.format("packet_capture").load(str(tmp_path)))
    ds.run_to_parquet(stream, str(tmp_path / "out"), str(tmp_path / "check"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 5


def test_files_round_trip(spark, tmp_path):
    packets = trace.from_conversations(spark.read.parquet(f"{SF}/conversations.parquet"))
    want = {(r["flow_key"], r["seq"], bytes(r["payload"])) for r in packets.collect()}
    got = lambda df: {(r["flow_key"], r["seq"], bytes(r["payload"] or b"")) for r in df.collect()}
    io.to_json(packets, f"{tmp_path}/j")
    io.to_csv(packets, f"{tmp_path}/c")
    io.to_parquet(packets, f"{tmp_path}/p")
    assert got(io.from_json(spark, f"{tmp_path}/j")) == got(io.from_csv(spark, f"{tmp_path}/c")) == got(io.from_parquet(spark, f"{tmp_path}/p")) == want
    (tmp_path / "f").mkdir()
    (tmp_path / "f" / "x.bin").write_bytes(b"\x00\x01")
    assert [bytes(r["payload"]) for r in io.from_files(spark, f"{tmp_path}/f", "*.bin").collect()] == [b"\x00\x01"]
    (tmp_path / "t.txt").write_text("a\nb\n")
    assert io.from_text(spark, f"{tmp_path}/t.txt").count() == 2
    verdict = spark.createDataFrame([(1, 0, "b"), (1, 0, "a")], "excerpt_id long, interval_id int, flow_key string")
    io.report(verdict, f"{tmp_path}/r")
    assert spark.read.json(f"{tmp_path}/r").first()["flows"] == ["a", "b"]


def events(spark):
    return trace.from_events(spark.read.parquet(f"{SF}/events.parquet"))


def words(df):
    return {(r["interval_id"], r["section"], r["word_ix"], r["word"]) for r in df.collect()}


def test_stream_equals_batch_after_the_patch(spark):
    assert words(sq.stream_filter_words(spark, SF)) == words(ds.filter_words(events(spark), sq.CONFIG)) == words(sq.stream_late_patch(spark, SF))


def test_late_rows_are_dropped_and_the_patch_restores_them(spark):
    """A stream that is stopped and goes on from its checkpoint; its watermark drops late events."""
    out, dropped = sq.late_digest(spark, SF)
    assert dropped > 0
    whole = words(ds.filter_words(events(spark), sq.CONFIG))
    assert words(out) != whole == words(sq.stream_late_patch(spark, SF))


def test_sliding_intervals_and_each_batch_sink(spark, tmp_path):
    stream = sq._events(spark, SF)
    kept = []
    ds.run_each(ds.filter_words(stream, sq.CONFIG, "2 days", "1 day"), str(tmp_path / "c"), lambda df, _: kept.extend(tuple(r) for r in df.collect()))
    want = words(ds.filter_words(events(spark), sq.CONFIG, "2 days", "1 day"))
    assert set(kept) == want


def test_reassembly_in_state_equals_whole_flows(spark, tmp_path):
    rng = np.random.default_rng(9)
    flows = {f"f{i}": [rng.integers(97, 123, int(n)).astype(np.uint8).tobytes() for n in rng.integers(20, 150, 40)] for i in range(4)}
    schema = "flow_key string, seq long, payload binary"
    for part in range(5):
        rows = [(k, s, p) for k, own in flows.items() for s, p in enumerate(own) if s // 8 == part]
        spark.createDataFrame(rows, schema).coalesce(1).write.parquet(f"{tmp_path}/in/p{part}")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    ds.run_to_parquet(ds.reassembled_blocks(stream), f"{tmp_path}/out", f"{tmp_path}/check")
    got = {}
    for r in spark.read.schema(ds.BLOCKS).parquet(f"{tmp_path}/out").collect():
        got.setdefault(r["flow_key"], set()).add((r["start"], bytes(r["block"])))
    for k, own in flows.items():
        _, _, start, _, blocks = blocking.winnow_batch([b"".join(own)])
        want = set(zip(start.tolist(), blocks, strict=True))
        assert got[k] == want


def test_silent_flows_are_forgotten(spark, tmp_path):
    """State is cleared a time after a flow's last packet, by the watermark; what is sent later begins anew."""
    from datetime import datetime, timedelta

    rng = np.random.default_rng(1)
    raw = rng.integers(97, 123, 900).astype(np.uint8).tobytes()
    at = datetime(2024, 1, 1)
    days = [(0, [("f", 0, raw[:300]), ("g", 0, b"x" * 200)]), (1, [("h", 0, b"y" * 200)]), (9, [("h", 1, b"y" * 200)]), (10, [("f", 1, raw[300:])])]
    for n, (day, own) in enumerate(days):
        spark.createDataFrame([(k, s, p, at + timedelta(days=day)) for k, s, p in own], "flow_key string, seq long, payload binary, ts timestamp").coalesce(1).write.parquet(f"{tmp_path}/in/p{n}")
        for f in os.listdir(f"{tmp_path}/in/p{n}"):
            os.utime(f"{tmp_path}/in/p{n}/{f}", (n + 1, n + 1))
    spark.conf.set(*ds.STATE_STORE)
    for name, ttl in (("kept", timedelta(days=60)), ("gone", timedelta(days=2))):
        stream = spark.readStream.schema("flow_key string, seq long, payload binary, ts timestamp").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
        ds.run_to_parquet(ds.reassembled_blocks(stream, ttl=ttl), f"{tmp_path}/{name}", f"{tmp_path}/c{name}")
        got = {(r["start"], bytes(r["block"])) for r in spark.read.schema(ds.BLOCKS).parquet(f"{tmp_path}/{name}").filter("flow_key = 'f'").collect()}
        parts = [raw] if name == "kept" else [raw[:300], raw[300:]]
        want = set()
        for p in parts:
            _, _, start, _, blocks = blocking.winnow_batch([p])
            want |= set(zip(start.tolist(), blocks, strict=True))
        assert got == want


class Held:
    raw = None

    def getValueState(self, *_):  # noqa: N802
        return self

    def exists(self):
        return self.raw is not None

    def get(self):
        return self.raw

    def update(self, raw):
        self.raw = raw


def test_reassembly_has_every_block_of_the_bytes_so_far():
    rng = np.random.default_rng(10)
    for alphabet in (26, 2, 1):
        for _ in range(40):
            own = [rng.integers(97, 97 + alphabet, int(n)).astype(np.uint8).tobytes() for n in rng.integers(0, 200, int(rng.integers(1, 30)))]
            state, got = ds.Reassembler(), []
            state.init(Held())
            for at in range(0, len(own), 3):
                batch = pd.DataFrame({"seq": range(at, at + len(own[at : at + 3])), "payload": own[at : at + 3]})
                for out in state.handleInputRows(("f",), iter([batch]), None):
                    got += zip(out["start"].tolist(), out["block"].tolist(), strict=True)
                _, _, start, _, blocks = blocking.winnow_batch([b"".join(own[: at + 3])])
                assert got == list(zip(start.tolist(), blocks, strict=True))


def test_watch_list(spark, tmp_path):
    packets = trace.from_conversations(spark.read.parquet(f"{SF}/conversations.parquet")).withColumn("ts", F.lit("2024-01-01").cast("timestamp"))
    packets.write.parquet(f"{tmp_path}/in")
    listed = blocking.winnow_blocks(packets.limit(1)).select(F.lit(1).cast("bigint").alias("excerpt_id"), "block_no", "block")
    stream = spark.readStream.schema(packets.schema).parquet(f"{tmp_path}/in")
    ds.run_to_parquet(ds.watch(stream, listed, DigestConfig()), f"{tmp_path}/out", f"{tmp_path}/check")
    seen = spark.read.parquet(f"{tmp_path}/out")
    assert seen.count() >= listed.count() > 0


def test_sessions(spark):
    assert ds.sessions(events(spark)).agg(F.sum("packets")).first()[0] == 1000


def test_the_registry_stands_without_the_training_data_operators(tmp_path):
    for p in ROOT.iterdir():
        if p.name not in (".git", "tests", "corpus_pipeline.py"):
            (tmp_path / p.name).symlink_to(p) if p.name != "tracedigest" else None
    (tmp_path / "tracedigest").mkdir()
    for p in (ROOT / "tracedigest").iterdir():
        if p.name not in ("llm", "__pycache__"):
            (tmp_path / "tracedigest" / p.name).symlink_to(p)
    (tmp_path / "__spark_entry__.py").unlink()
    (tmp_path / "__spark_entry__.py").write_text((ROOT / "__spark_entry__.py").read_text())
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 100 and set(o) <= set(q) and 'pipeline' not in q and not any(k[:2] == 'op' and k[2].isdigit() for k in q)"
    subprocess.run([sys.executable, "-B", "-c", code], cwd=tmp_path, check=True, timeout=120)


def test_the_registry_stands_where_a_module_of_those_is_missing():
    code = "import sys; sys.modules['tracedigest.llm.common'] = None; import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 100 and set(o) <= set(q) and 'pipeline' not in q"
    subprocess.run([sys.executable, "-B", "-c", code], cwd=ROOT, check=True, timeout=120)


def test_registry_is_whole():
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q)
