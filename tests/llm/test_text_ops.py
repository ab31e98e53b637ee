"""Operators on texts against brute force, and rows that break naive code."""

import hashlib
import re
import zlib

import duckdb
import numpy as np
import pytest

from tracedigest.llm import bin_packing, decontaminate, histogram_shard, queries, substring_dedup, url_filter

SF = "/root/testdata/sf0.001"
AWKWARD = [
    (1, None, "x"), (2, "", "x"), (3, "   \n", "x"), (4, "one", "x"), (4, "one", "x"), (None, "a b c d e f g h i j k l m n o", "x"), (5, "a b c d e f g h i j k l m n o", "x"),
    (6, "z a b c d e f g h i j k l m n o q", "x"), (7, "ab " * 60_000, "x"), (8, "\u00a0n\u0085b \u2003 w", "x"), (9, "w" * 200_000, "x"), (10, "ab " * 30, "x"),
]


def rows(name, sf=SF):
    return duckdb.sql(f"select * from '{sf}/{name}.parquet'").fetchall()


def awkward(spark):
    return spark.createDataFrame(AWKWARD, "doc_id long, text string, tag string")


def brute_dedup(docs, window=13):
    words = [(i, re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t in docs]
    least = {}
    for i, w in words:
        for k in range(len(w) - window + 1):
            key = tuple(w[k : k + window])
            if i is not None:
                least[key] = min(least.get(key, i), i)
    out = []
    for i, w in words:
        drop = set()
        for k in range(len(w) - window + 1):
            j = least.get(tuple(w[k : k + window]))
            if j is not None and (i is None or j < i):
                drop.update(range(k, k + window))
        kept = " ".join(x for k, x in enumerate(w) if k not in drop)
        out.append((i, len(w), len(drop), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=str)


def test_substring_dedup_equals_brute_force(spark):
    got = [tuple(r)[:4] for r in queries.op1_substring_dedup(spark, SF).collect()]
    assert sorted(got, key=str) == brute_dedup([r[:2] for r in rows("documents")])
    assert any(r[2] for r in got)


def test_substring_dedup_awkward_rows_and_a_saturated_sketch(spark):
    want = brute_dedup([r[:2] for r in AWKWARD])
    for bits in (20, 22):
        got = substring_dedup.dedup(awkward(spark), cell_bits=bits).collect()
        assert sorted(((r[0], r[1], r[2], hashlib.sha256(r[3].encode()).hexdigest()) for r in got), key=str) == want
    assert substring_dedup.dedup(awkward(spark).limit(0), cell_bits=20).collect() == []


def test_substring_dedup_settles_repeats_over_many_batches(spark):
    """A passage in every text, ids in no order, many small batches a task: little of it is left to the exchange."""
    passage = " ".join(f"p{i}" for i in range(30))
    docs = [(i * 7919 % 2003 if i % 50 else None, f"own{i} {passage} " + " ".join(f"x{i % 400}y{j}" for j in range(15))) for i in range(2000)]
    table = spark.createDataFrame(docs, "doc_id long, text string").repartition(3)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "16")
    try:
        got = substring_dedup.dedup(table, cell_bits=20).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert sorted(((r[0], r[1], r[2], hashlib.sha256(r[3].encode()).hexdigest()) for r in got), key=str) == brute_dedup(docs)


def test_remembered_windows_forget_when_full():
    seen = substring_dedup.Repeated(most=4)
    of = lambda *x: np.array(x, np.uint64)
    seen.add(of(3, 5, 9), of(1, 1, 1), np.array([7, 8, 9]))
    seen.add(of(4, 5), of(1, 1), np.array([2, 6]))
    at, known = seen.find(of(3, 4, 5, 9, 5), of(1, 1, 1, 1, 2))
    assert known.tolist() == [True, True, True, True, False] and seen.rank[at[:4]].tolist() == [7, 2, 6, 9]
    seen.add(of(6), of(1), np.array([1]))
    assert seen.find(of(3, 6), of(1, 1))[1].tolist() == [False, True]


def brute_url(url):
    host, path = "", ""
    if url is not None and "://" in url:
        rest = url.split("://", 1)[1]
        host = re.split(r"[/?#]", rest, maxsplit=1)[0]
        path = re.split(r"[?#]", rest[len(host) :], maxsplit=1)[0]
        host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    best = None
    for verdict, rule in url_filter.GIVEN_RULES:
        h, _, p = rule.partition("/")
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p) and (best is None or len(rule) > len(best[1])):
            best = verdict, rule
    if best is None:
        own = any(re.search(rf"(^|[.-]){w}($|[.-])", host) for w in url_filter.HOST_WORDS) or any(re.search(rf"(^|[/._-]){w}($|[/._-])", path) for w in url_filter.PATH_WORDS)
        best = ("block" if own else "allow"), None
    return host, path, best[1], best[0]


URLS = ["http://free-bets.org/" + "x/" * 50_000, "http://free-bets.org/" + "x/" * 50_000, "http://" + "a." * 20_000 + "net/es/", "a://x.org/go/casino", "a://x.org/casinos/", "a://m.casino-win.org", "a://casinowin.org", "a://x.org/y.porn", "a://cheap-pills", "a://pills.org/cheap", "http://WWW.Example.com/en/1", "https://example.com/en", "https://example.com/en/", "x.net/es/1", None, "", "a://b.net/es/?q", "a://net/fr/", "a://xnet/fr/", "http://spam-farm.org", "http://casino.example.org/x", "http://a.com", "http://a.com/?x://b.net/es/", "://com/", "http://e\u00e9.NET/es/\n#x", "http://com/En/"]


def test_url_filter_equals_brute_force(spark):
    got = {r[0]: tuple(r)[1:5] for r in queries.op2_url_filter(spark, SF).collect()}
    assert got == {i: brute_url(u) for i, u, _ in rows("pages")}
    made = spark.createDataFrame(list(enumerate(URLS)), "page_id long, url string")
    want = {i: brute_url(u) for i, u in enumerate(URLS)}
    one, other = (sorted(map(tuple, url_filter.judge(made, closure_bytes=b).collect())) for b in (1 << 20, 0))
    assert one == other and {r[0]: r[1:5] for r in one} == want
    assert url_filter.judge(made.limit(0), closure_bytes=0).collect() == []
    assert url_filter.judge(made.limit(0)).collect() == []


def test_url_index_runs_only_candidates(spark):
    rules = [url_filter.host_word_rule(f"site{i}") for i in range(500)]
    made = spark.createDataFrame([(1, "http://site7.example.com/a"), (2, "http://other.example.com/")], "page_id long, url string")
    got = {r["page_id"]: (r["verdict"], r["tried"]) for r in url_filter.judge(made, rules).collect()}
    assert got == {1: ("block", 1), 2: ("allow", 0)}


def brute_hits(docs, items, window=10):
    norm = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
    grams = {}
    for i, t in items:
        w = norm(t)
        n = min(window, len(w))
        for k in range(len(w) - n + 1 if w else 0):
            grams.setdefault(tuple(w[k : k + n]), set()).add(str(i))
    sizes = {len(g) for g in grams}
    out = []
    for i, t in docs:
        w, hit, found = norm(t), set(), set()
        for n in sizes:
            for k in range(len(w) - n + 1):
                if (g := grams.get(tuple(w[k : k + n]))) is not None:
                    hit.update(range(k, k + n))
                    found |= g
        out.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit)))
    return sorted(out, key=str)


def test_decontamination_equals_brute_force(spark):
    got = sorted((tuple(r) for r in queries.op5_decontaminate(spark, SF).collect()), key=str)
    assert got == brute_hits([r[:2] for r in rows("documents")], rows("benchmark"))
    assert any(r[5] for r in got)


def test_decontamination_awkward_rows_parts_and_removal(spark):
    items = [(1, "One"), (2, None), (3, ""), (4, "c D e f g h i j k l m"), (5, "ab ab ab"), (5, "ab ab ab"), (11, "a-b, c")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = brute_hits([r[:2] for r in AWKWARD], items)
    for bound in (1 << 20, 8):
        got = decontaminate.hits(awkward(spark), bench, max_broadcast_bytes=bound).collect()
        assert sorted(((r[0], r[1], r[2], len(r[3]), hashlib.sha256(",".join(r[3]).encode()).hexdigest(), r[4]) for r in got), key=str) == want
    left = {r[0] for r in decontaminate.clean(awkward(spark), bench).collect()}
    assert left == {r[0] for r in want if not r[5]}
    cut = {r["doc_id"]: r["text"] for r in decontaminate.clean(awkward(spark), bench, mode="span").collect()}
    assert cut[6].split() == ["z", "n", "o", "q"] and cut[1] is None
    assert decontaminate.hits(awkward(spark).limit(0), bench).collect() == []
    assert not any(r["contaminated"] for r in decontaminate.hits(awkward(spark), bench.limit(0)).collect())


def test_packing_covers_every_token_once(spark):
    from tokenizers import Tokenizer

    import numpy as np
    import public_tokenizers

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    docs = [r[:2] for r in rows("documents")]
    got = queries.op7_best_fit_packing(spark, SF).collect()
    by_doc, bins = {}, {}
    for r in got:
        by_doc.setdefault(r["doc_id"], []).append(r)
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    total = 0
    for i, t in docs:
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        total += len(ids)
        own = sorted(by_doc.pop(i), key=lambda r: r["piece"])
        assert [r["piece"] for r in own] == list(range(len(own))) and sum(r["length"] for r in own) == len(ids)
        for r in own:
            assert zlib.crc32(ids[r["start"] : r["start"] + r["length"]].tobytes()) == r["ids_crc32"]
            assert r["length"] == 1024 or r["piece"] == 0
        assert len(own) == -(-len(ids) // 1024)
    assert not by_doc
    for placed in bins.values():
        at = 0
        for a, n in sorted(placed):
            assert a == at
            at += n
        assert at <= 1024
    assert len(bins) <= -(-total // 1024) * 1.01 + 1


def test_packing_of_special_strings_and_a_hot_length(spark):
    """Strings of special tokens have their id, as the tokenizer file says; a length of many rows has many buckets."""
    from tokenizers import Tokenizer

    import public_tokenizers

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = ["a<|endoftext|>b", "<|endoftext|>", " <|endoftext|> x<|endoftext", "plain"]
    encode = bin_packing.encoder()
    assert [encode(t) for t in texts] == [tok.encode(t, add_special_tokens=False).ids for t in texts] and encode(texts[0]) == [64, 50256, 65]
    docs = spark.createDataFrame([(i, "one") for i in range(3000)] + [(9000, "a<|endoftext|>b")], "doc_id long, text string")
    got = bin_packing.pack_documents(docs).collect()
    bins = {}
    for r in got:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert len(got) == 3001 and len(bins) == 6
    for placed in bins.values():
        placed.sort()
        assert all(a + n == b for (a, n), (b, _) in zip(placed, placed[1:], strict=False)) and placed[0][0] == 0


def test_packing_awkward_rows_and_sequences(spark):
    docs = awkward(spark)
    got = bin_packing.pack_documents(docs)
    out = bin_packing.sequences(docs, got).collect()
    assert sum(len(r["ids"]) for r in out) == sum(r["length"] for r in got.collect())
    assert all(len(r["ids"]) <= 1024 for r in out)
    assert bin_packing.pack_documents(docs.limit(0)).collect() == []


@pytest.mark.parametrize("room", [1, 7, 30])
def test_fullest_is_the_best_sum(room):
    import itertools

    import numpy as np

    rng = np.random.default_rng(room)
    for _ in range(50):
        counts = np.zeros(room + 1, int)
        counts[1:] = rng.integers(0, 3, room) * (rng.random(room) < 0.4)
        pool = [n for n in range(1, room + 1) for _ in range(counts[n])][:12]
        counts = np.bincount(pool, minlength=room + 1) if pool else np.zeros(room + 1, int)
        best = max((sum(c) for k in range(len(pool) + 1) for c in itertools.combinations(pool, k) if sum(c) <= room), default=0)
        got = bin_packing.fullest(counts, room)
        assert sum(got) == best and all(got.count(n) <= counts[n] for n in got)


def check_shards(got, docs):
    assert sorted((r["doc_id"], r["size"], r["text_crc32"]) for r in got if r["doc_id"] is not None) == sorted((i, len((t or "").encode()) + 1, zlib.crc32((t or "").encode())) for i, t in docs if i is not None)
    slots = {}
    for r in got:
        assert r["law"] == "bytes" and 0 <= r["shard"] < 8 and r["grown_shard"] is None
        slots.setdefault(r["shard"], []).append(r["slot"])
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_shards_are_even_in_bytes(spark):
    docs = [r[:2] for r in rows("documents")]
    got = queries.op8_histogram_shards(spark, SF).collect()
    check_shards(got, docs)
    held = [sum(r["size"] for r in got if r["shard"] == s) for s in range(8)]
    assert max(held) - min(held) <= 2 * max(r["size"] for r in got)
    check_shards(histogram_shard.histogram_shards(awkward(spark)).collect(), [r[:2] for r in AWKWARD])
    assert histogram_shard.histogram_shards(awkward(spark).limit(0)).collect() == []


def test_written_shards_hold_all_rows(spark, tmp_path):
    docs = awkward(spark)
    histogram_shard.write_shards(docs, str(tmp_path / "out"), shards=4, task_bytes=100_000)
    assert spark.read.parquet(str(tmp_path / "out")).count() == docs.count()
