"""Boundaries and blocks: kernel against brute force and the SQL twin, and the invariants that keep true carriers."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from tracedigest.functions import hashing
from tracedigest.operators import blocking, downsample, trace


def slow_hash(b: bytes, instance: int = 0) -> int:
    p = hashing.PRIME
    x = (int.from_bytes(b, "big") % p * hashing.STEP_A + hashing.STEP_B + hashing.STEP_I * instance) % p
    x = (x * x + x) % p
    return (x * hashing.STEP_C + hashing.STEP_D) % p


def slow_bounds(data: bytes, window: int = 64, width: int = 5, instance: int = 0) -> list[int]:
    h = [slow_hash(data[i : i + width], instance) for i in range(len(data) - width + 1)]
    out = set()
    for a in range(len(h) - window + 1):
        own = h[a : a + window]
        least = min(own)
        out.add(a + max(i for i, x in enumerate(own) if x == least))
    return sorted(out)


def blocks_of(data: bytes, **how) -> list[tuple[int, bytes]]:
    _, _, start, _, blocks = blocking.winnow_batch([data], **how)
    return list(zip(start.tolist(), blocks, strict=True))


@pytest.mark.parametrize(("window", "width", "instance"), [(64, 5, 0), (16, 5, 1), (64, 10, 0), (8, 3, 2)])
def test_bounds_equal_brute_force(window, width, instance):
    rng = np.random.default_rng(window + width)
    for n in (0, 5, window + width - 2, window + width - 1, window + width, 700, 3000):
        for data in (rng.integers(0, 256, n).astype(np.uint8).tobytes(), rng.integers(97, 99, n).astype(np.uint8).tobytes(), bytes(n)):
            assert blocking.payload_bounds(data, window, width, instance).tolist() == slow_bounds(data, window, width, instance)


def test_block_sizes_and_overlap():
    data = np.random.default_rng(1).integers(0, 256, 200_000).astype(np.uint8).tobytes()
    found = blocks_of(data)
    sizes = np.array([len(b) for _, b in found])
    assert sizes.min() == 6 and sizes.max() == 69 and 37 < sizes.mean() < 38.2
    for (a, x), (b, y) in zip(found, found[1:], strict=False):
        assert data[a : a + len(x)] == x and a + len(x) == b + 5 and x[-5:] == y[:5]


def test_repeated_bytes_give_the_smallest_blocks():
    assert {len(b) for _, b in blocks_of(bytes(500))} == {6}


def test_payloads_too_short_have_no_block_and_132_bytes_always_have_one():
    rng = np.random.default_rng(2)
    for n in range(0, 69):
        assert blocks_of(rng.integers(0, 256, n).astype(np.uint8).tobytes()) == []
    for _ in range(200):
        assert blocks_of(rng.integers(97, 123, 132).astype(np.uint8).tobytes())


def test_long_payloads_in_pieces(monkeypatch):
    data = np.random.default_rng(3).integers(97, 123, 20_000).astype(np.uint8).tobytes() + b"a" * 3000 + bytes(5000)
    want = blocking.payload_bounds(data, 64, 5)
    monkeypatch.setattr(blocking, "PIECE", 1000)
    assert (blocking.payload_bounds(data, 64, 5) == want).all()


@settings(max_examples=60, deadline=None)
@given(st.binary(min_size=0, max_size=400), st.binary(min_size=0, max_size=400), st.binary(min_size=69, max_size=300), st.integers(0, 60))
def test_blocks_of_an_excerpt_are_blocks_of_what_contains_it(head, tail, excerpt, threshold):
    inside = {(a - len(head), b) for a, b in blocks_of(head + excerpt + tail, threshold=threshold)}
    assert set(blocks_of(excerpt, threshold=threshold)) <= inside


def test_batches_equal_single_payloads():
    rng = np.random.default_rng(4)
    payloads = [rng.integers(97, 110, n).astype(np.uint8).tobytes() for n in (0, 10, 500, 3, 900, 68, 69, 70, 4000)] + [None]
    row, number, start, size, blocks = blocking.winnow_batch(payloads)
    got = sorted(zip(row.tolist(), number.tolist(), start.tolist(), blocks, strict=True))
    want = []
    for i, p in enumerate(payloads):
        want += [(i, k, a, b) for k, (a, b) in enumerate(blocks_of(p or b""))]
    assert got == sorted(want) and size.tolist() == [len(b) for b in blocks]


def test_kernel_equals_sql_twin(spark):
    packets = trace.from_documents(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    a = {tuple(r) for r in blocking.winnow_bounds(packets).collect()}
    assert a == {tuple(r) for r in blocking.winnow_bounds_sql(packets).collect()} and len(a) > 10_000


def test_downsampling_nests(spark):
    packets = trace.from_documents(spark.read.parquet("/root/testdata/sf0.001/documents.parquet"))
    blocks = blocking.winnow_blocks(packets)
    one, two = ({tuple(r) for r in downsample.keep_large(blocks, t).select("flow_key", "start").collect()} for t in (20, 40))
    assert two < one
    fused = {tuple(r) for r in blocking.winnow_blocks(packets, threshold=40).select("flow_key", "start").collect()}
    assert fused == two


def test_digest_constants():
    assert hashing.digests([bytes.fromhex("61C3A9")]).hex() == "128fda53c8c07c8c66f2a4812187d92f"
    assert hashing.digests([bytes.fromhex("61C3A9")], hashing.flow_suffix("7")).hex() == "b12bee6829ed4c2485ad6d1d27b70c43"
    assert hashing.md5_parts(hashing.digests([b"abc"]))[1][0] == 66873977788054
    assert len(hashing.digests([b"a", b"b"], family="fast", salt="s")) == 32
