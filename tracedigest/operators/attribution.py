"""Attribution: in which intervals does an excerpt appear, and which flows carried it.

Verdicts are conjunctions over an excerpt's blocks. An excerpt without a kept block can't be tested and is present everywhere (or
flagged): no true carrier is ever missed. `attribute` goes from the cheap to the dear and reads only what is still in question:

1. appearance: content places meet the packed chunks that hold them by equi-join, and the bits are tested as they are;
2. only intervals with hits are read on, and only their tables are opened;
3. bitmaps rule flows out, on packed bytes, before any flow-bound digest is taken;
4. the largest block of each (flow, excerpt) left is bound to the flow and probed, the others only for the survivors.

Up to ROWS_BOUND hits and PACKED_BOUND bytes of excerpts and of filters with hits, steps 3 and 4 are one row-local pass over
the flows; more excerpts go in parts, up to MOST_PASSES passes. No pair crosses an exchange there. Beyond, the places of survivors meet
chunks by equi-join too, so any number of excerpts and intervals will do.
`appearance` and `determine` say the same on word rows. `evaluate` is the row-local pass for many configurations at once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import Hashed, block_digest, flow_digest, section_of
from . import bitindex, blocking, membership
from .digest import CHUNK_BITS, CHUNK_BYTES, Digest, DigestConfig, Layout

#: Bytes of filters and of excerpts that the row-local pass may send to every task.
PACKED_BOUND = 64 << 20
#: Hits (excerpt, interval) that it may send.
ROWS_BOUND = 200_000
#: Pairs (excerpt, flow) that a task asks together in the row-local pass, and cells whose bits it holds.
HELD_PAIRS, HELD_CELLS = 1 << 19, 256 << 20
#: Passes over the flows, each with a part of the excerpts, before joins take over.
MOST_PASSES = 64


def id_type(excerpts: DataFrame) -> str:
    return excerpts.schema["excerpt_id"].dataType.simpleString()


def excerpt_blocks(excerpts: DataFrame, config: DigestConfig) -> DataFrame:
    """excerpt_id, block_no, size, block, under the digest's own window, overlap and threshold."""
    rows = excerpts.select(F.lit(0).alias("interval_id"), F.col("excerpt_id").cast("string").alias("flow_key"), F.lit(0).cast("bigint").alias("seq"), F.col("excerpt").alias("payload"))
    out = blocking.winnow_blocks(rows, config.window, config.overlap, config.threshold, config.keep_equal)
    return out.select(F.col("flow_key").cast(id_type(excerpts)).alias("excerpt_id"), "block_no", "size", "block")


def appearance(blocks: DataFrame, excerpts: DataFrame, words: DataFrame, intervals: DataFrame, config: DigestConfig) -> tuple[DataFrame, DataFrame]:
    """(excerpt_id, interval_id) whose content blocks are all present, and their (excerpt_id, interval_id, section) hits."""
    asked = blocks.select("excerpt_id", "block_no", block_digest(F.col("block"), config.salt).alias("digest")).withColumn("feature", section_of(F.col("digest"), config.sections))
    rows = membership.probes(asked, config.m_bits, config.filter_sections, config.k)
    need = rows.groupBy("excerpt_id").agg(F.count("*").alias("need"))
    hits = words.join(rows, ["section", "word_ix"]).filter(F.col("word").bitwiseAND(F.col("mask")) != 0)
    found = hits.groupBy("excerpt_id", "interval_id").agg(F.count("*").alias("met"), F.collect_set("feature").alias("sections")).join(need, "excerpt_id").filter("met = need")
    free = excerpts.select("excerpt_id").join(need, "excerpt_id", "left_anti").join(intervals.select("interval_id").distinct())
    present = found.select("excerpt_id", "interval_id").unionByName(free.select("excerpt_id", "interval_id"))
    return present, found.select("excerpt_id", "interval_id", F.explode("sections").alias("section"))


def determine(candidates: DataFrame, blocks: DataFrame, words: DataFrame, config: DigestConfig, first_only: bool = True) -> DataFrame:
    """Candidates (excerpt_id, interval_id, flow_key) whose flow-bound blocks are all present. Two rounds: the largest
    block of each excerpt first, the others for the survivors."""
    order = F.row_number().over(Window.partitionBy("excerpt_id").orderBy(F.desc("size"), "block_no"))
    ranked = blocks.withColumn("turn", order)

    def survivors(who: DataFrame, own: DataFrame) -> DataFrame:
        asked = who.join(own.select("excerpt_id", "block_no", "block"), "excerpt_id", "left")  # without a block left: stays
        asked = asked.select("excerpt_id", "interval_id", "flow_key", flow_digest(F.col("block"), F.col("flow_key"), config.salt).alias("digest"))
        rows = membership.probes(asked, config.m_bits, config.filter_sections, config.k)
        hit = F.col("digest").isNull() | (F.coalesce("word", F.lit(0)).bitwiseAND(F.col("mask")) != 0)
        met = rows.join(words, ["interval_id", "section", "word_ix"], "left").select("excerpt_id", "interval_id", "flow_key", hit.alias("hit"))
        return met.groupBy("excerpt_id", "interval_id", "flow_key").agg(F.bool_and("hit").alias("hit")).filter("hit").drop("hit")

    if not first_only:
        return survivors(candidates, ranked)
    return survivors(survivors(candidates, ranked.filter("turn = 1")), ranked.filter("turn > 1"))


def all_flows(present: DataFrame, flows: DataFrame) -> DataFrame:
    """Exhaustive candidates: every flow of each interval that has the excerpt."""
    return present.join(flows.select("interval_id", "flow_key"), "interval_id").select("excerpt_id", "interval_id", "flow_key")


def words_of_sections(digest: Digest) -> DataFrame:
    """Word rows of a packed digest, for SQL and for checks; attribution does not need them."""
    hx = F.hex(F.col("bits"))
    four = digest.sections.select("interval_id", "section", "chunk", hx.alias("hx"), F.explode(F.expr("sequence(0, cast(octet_length(bits) div 4 as int) - 1)")).alias("i"))
    at = lambda i: F.expr(f"substring(hx, i * 8 + {i}, 2)")
    word = F.conv(F.concat(at(7), at(5), at(3), at(1)), 16, 10).cast("bigint")
    return four.select("interval_id", "section", (F.col("chunk") * (CHUNK_BYTES // 4) + F.col("i")).cast("int").alias("word_ix"), word.alias("word")).filter("word <> 0")


def _placed(layout: Layout, k: int, parts) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Section, chunk and bit in it of k places each, hash by hash."""
    found = list(layout.places(parts, k))
    section, pos = np.concatenate([x for x, _ in found]), np.concatenate([x for _, x in found])
    return section.astype(np.int32), (pos // CHUNK_BITS).astype(np.int32), (pos % CHUNK_BITS).astype(np.int32)


def content_places(blocks: DataFrame, config: DigestConfig) -> DataFrame:
    """excerpt_id, block_no, feature, section, chunk, bit: the k places of each content block."""
    layout, k = Layout.of(config), config.k

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parts = Hashed(batch.column("block").to_pylist(), config.hash_family, config.salt).content()
            at = pa.array(np.tile(np.arange(batch.num_rows), k))
            feature = np.tile(parts[0] % config.sections, k).astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column("excerpt_id").take(at), batch.column("block_no").take(at), pa.array(feature), *map(pa.array, _placed(layout, k, parts))], ["excerpt_id", "block_no", "feature", "section", "chunk", "bit"])

    return blocks.select("excerpt_id", "block_no", "block").mapInArrow(kernel, f"excerpt_id {id_type(blocks)}, block_no int, feature int, section int, chunk int, bit int")


def bit_set(bits: str = "bits", bit: str = "bit"):
    """Whether a place of packed bits is one; one byte of the row is looked at."""
    byte = f"conv(hex(substring({bits}, {bit} div 8 + 1, 1)), 16, 10)"
    return F.expr(f"(shiftright(cast({byte} as int), cast({bit} % 8 as int)) & 1) = 1")


def present_in(places: DataFrame, sections: DataFrame) -> DataFrame:
    """excerpt_id, interval_id of excerpts whose content places are all ones. Only chunks that are asked for meet them."""
    need = places.groupBy("excerpt_id").agg(F.count("*").alias("need"))
    hits = sections.join(places, ["section", "chunk"]).filter(bit_set())
    return hits.groupBy("excerpt_id", "interval_id").agg(F.count("*").alias("met")).join(need, "excerpt_id").filter("met = need").select("excerpt_id", "interval_id")


def attribute(excerpts: DataFrame, digest: Digest, on_empty: str = "positive", between: tuple[int, int] | None = None, rows_bound: int = ROWS_BOUND, packed_bound: int = PACKED_BOUND, opened=None, *, ends: bool = True) -> DataFrame:
    """excerpt_id, interval_id, flow_key, src, dst (and untestable with on_empty="flag"): the whole procedure. between restricts the
    intervals; ends=False leaves src and dst out; opened counts the compressed tables that are opened. Ids may have any type; rows of one id are one excerpt.
    Appearance runs when this is called, the rest with the result."""
    config, flows, sections = digest.config, digest.flows, digest.sections
    if between is not None:
        flows, sections = (df.filter(F.col("interval_id").between(*between)) for df in (flows, sections))
    excerpts = excerpts.filter("excerpt_id is not null").select("excerpt_id", "excerpt")
    blocks = excerpt_blocks(excerpts, config)
    places = content_places(blocks, config)
    size = _size(excerpts)
    near = F.broadcast(places) if size <= packed_bound // 4 else places  # then filters are only scanned
    asked = [r["section"] for r in places.select("section").distinct().collect()] if config.filter_sections > 1 else [0]  # at most the sections of the filter
    found = present_in(near, sections.filter(F.col("section").isin(asked)) if len(asked) < config.filter_sections else sections)
    free = excerpts.select("excerpt_id").distinct().join(blocks.select("excerpt_id").distinct(), "excerpt_id", "left_anti")
    every = flows.select("interval_id").distinct()
    present = found.unionByName(free.join(F.broadcast(every), how="cross").select("excerpt_id", "interval_id"))
    flag = on_empty == "flag"
    rows = present.limit(rows_bound + 1).collect()
    hit = sorted({r["interval_id"] for r in rows})
    layout = Layout.of(config)
    small = len(rows) <= rows_bound and len(hit) * layout.sections * layout.section_bytes <= packed_bound and size <= packed_bound
    if small:
        out = _local(excerpts, digest, flows, rows, hit, opened, ends, flag)
    else:
        present, few = _kept(present), len(rows) <= rows_bound
        del rows
        hit, passes = _passes(present, excerpts, blocks, config, rows_bound, packed_bound)
        if passes:
            out = _in_passes(present, blocks, _kept(_asked_flows(digest, flows, hit, opened, ends, passes)), filter_arrays(digest, hit), passes, config, ends, flag)
        else:
            if few:
                flows, sections, maps = (df if df is None else df.filter(F.col("interval_id").isin(hit)) for df in (flows, sections, digest.bitmaps(hit, opened)))
            else:
                maps = digest.bitmaps(None, opened)
                maps = maps if maps is None or between is None else maps.filter(F.col("interval_id").between(*between))
            out = _joined(present, blocks, places, sections, flows, maps, config)
            out = out.join(flows.select("interval_id", "flow_key", "src", "dst"), ["interval_id", "flow_key"]) if ends else out
            if flag:
                tested = blocks.select("excerpt_id").distinct().withColumn("t", F.lit(True))
                out = out.join(tested, "excerpt_id", "left").withColumn("untestable", F.col("t").isNull())
    return out.select("excerpt_id", "interval_id", "flow_key", *(["src", "dst"] if ends else []), *(["untestable"] if flag else []))


def _kept(df: DataFrame) -> DataFrame:
    """df, computed once: in the session's checkpoint folder, or in memory where none is set."""
    if df.sparkSession.sparkContext._jsc.sc().getCheckpointDir().isDefined() or df.sparkSession.conf.get("spark.checkpoint.dir", None):
        return df.checkpoint()
    return df.persist(StorageLevel.MEMORY_AND_DISK)


def _size(excerpts: DataFrame) -> int:
    return int(excerpts.agg(F.coalesce(F.sum(F.coalesce(F.octet_length("excerpt"), F.lit(0)) + 64), F.lit(0))).first()[0])


def filter_arrays(digest: Digest, intervals: list[int]) -> dict[int, np.ndarray]:
    """[section, word] arrays of the given intervals, in the driver: the caller bounds their bytes, which the configuration gives."""
    layout = Layout.of(digest.config)
    out = {i: np.zeros((layout.sections, layout.section_bytes), np.uint8) for i in intervals}
    for r in digest.sections.filter(F.col("interval_id").isin(intervals)).collect() if intervals else []:
        raw = np.frombuffer(r["bits"], np.uint8)
        out[r["interval_id"]][r["section"], r["chunk"] * CHUNK_BYTES : r["chunk"] * CHUNK_BYTES + len(raw)] = raw
    return {i: f.view("<u4") for i, f in out.items()}


def _asked_flows(digest: Digest, flows: DataFrame, hit: list[int], opened, ends: bool, passes: int = 1) -> DataFrame:
    """The flows of the intervals with hits: bitmaps as b0 where there is an index, src and dst where they are asked for."""
    keys, more = ["interval_id", "flow_key"], ["src", "dst"] if ends else []
    own = flows.filter(F.col("interval_id").isin(hit)).select(*keys, *more)
    if digest.config.index:
        maps = digest.bitmaps(hit, opened).withColumnRenamed("bitmap", "b0")
        own = maps.join(own, keys) if ends else maps
    tasks = own.sparkSession.sparkContext.defaultParallelism * (4 if passes == 1 else 8)
    return own.repartition(-(-tasks // passes))  # few bytes, but a row is asked about every excerpt; the passes run side by side


def _local(excerpts: DataFrame, digest: Digest, flows: DataFrame, rows: list, hit: list[int], opened, ends: bool = True, flag: bool = False) -> DataFrame:
    """Steps 3 and 4 in one pass over the flows of the intervals with hits."""
    config = digest.config
    held = [(r["excerpt_id"], bytes(r["excerpt"] or b"")) for r in excerpts.collect()] if rows else []
    row, number, _, size, blocks = blocking.winnow_batch([x for _, x in held], config.window, config.overlap, config.threshold, config.keep_equal)
    block_rows = [(held[i][0], int(n), int(s), b) for i, n, s, b in zip(row.tolist(), number, size, blocks, strict=True)]
    return _asked(_asked_flows(digest, flows, hit, opened, ends), block_rows, rows, {i for i, _ in held}, filter_arrays(digest, hit), config, id_type(excerpts), ends, flag)


def _asked(own: DataFrame, block_rows: list, rows: list, ids: set, arrays: dict[int, np.ndarray], config: DigestConfig, kind: str, ends: bool, flag: bool = False) -> DataFrame:
    present: dict[int, list] = {}
    for r in rows:
        present.setdefault(r["interval_id"], []).append(r["excerpt_id"])
    tables = {(i, 0): f for i, f in arrays.items()}
    return evaluate(own, block_rows, sorted(ids), [(0, config)], tables, present=present, kind=kind, carry=("src", "dst") if ends else (), flag=flag)


def _passes(present: DataFrame, excerpts: DataFrame, blocks: DataFrame, config: DigestConfig, rows_bound: int, packed_bound: int) -> tuple[list[int], int]:
    """Intervals with hits, and the parts of the excerpts in which row-local passes take all hits. 0 parts: the filters, an excerpt or the
    number of passes are too large."""
    layout, room = Layout.of(config), packed_bound // 4
    most = packed_bound // (layout.sections * layout.section_bytes)
    hit = [r["interval_id"] for r in present.select("interval_id").distinct().collect()]
    sent = blocks.groupBy("excerpt_id").agg(F.sum(F.col("size") + 64).alias("b")).agg(F.coalesce(F.sum("b"), F.lit(0)).alias("all"), F.coalesce(F.max("b"), F.lit(0)).alias("most")).first()
    if len(hit) > most or sent["most"] > room:
        return sorted(hit), 0
    n = max(1, -(-2 * present.count() // max(1, rows_bound)), -(-sent["all"] // room))
    return sorted(hit), n if n <= MOST_PASSES else 0


def _in_passes(present: DataFrame, blocks: DataFrame, own: DataFrame, arrays: dict[int, np.ndarray], passes: int, config: DigestConfig, ends: bool, flag: bool = False) -> DataFrame:
    """Steps 3 and 4 in several passes over the flows. The driver holds the blocks of one part of the excerpts at a time."""
    part, out = F.pmod(F.xxhash64("excerpt_id"), F.lit(passes)), None
    for p in range(passes):
        rows = present.filter(part == p).collect()
        ids = {r["excerpt_id"] for r in rows}
        own_blocks = blocks.filter(part == p).select("excerpt_id", "block_no", "size", "block").toArrow()
        block_rows = [r for r in zip(*(c.to_pylist() for c in own_blocks.columns), strict=True) if r[0] in ids]
        found = _asked(own, block_rows, rows, ids, arrays, config, id_type(blocks), ends, flag)
        out = found if out is None else out.unionByName(found)
    return out


def _bound_places(asked: DataFrame, config: DigestConfig) -> DataFrame:
    """Rows (excerpt_id, interval_id, flow_key, block) as the k places of the flow-bound block."""
    layout, k, keys = Layout.of(config), config.k, ["excerpt_id", "interval_id", "flow_key"]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            hashed, flows = Hashed(batch.column("block").to_pylist(), config.hash_family, config.salt), batch.column("flow_key").to_pylist()
            each = np.arange(batch.num_rows)
            parts = hashed.bound(each, hashed.binding(flows), each)
            at = pa.array(np.tile(np.arange(batch.num_rows), k))
            yield pa.RecordBatch.from_arrays([*(batch.column(c).take(at) for c in keys), *map(pa.array, _placed(layout, k, parts))], [*keys, "section", "chunk", "bit"])

    return asked.select(*keys, "block").mapInArrow(kernel, f"excerpt_id {id_type(asked)}, interval_id int, flow_key string, section int, chunk int, bit int")


def _joined(present: DataFrame, blocks: DataFrame, places: DataFrame, sections: DataFrame, flows: DataFrame, maps: DataFrame | None, config: DigestConfig) -> DataFrame:
    """Steps 3 and 4 by equi-joins, for any number of hits."""
    keys = ["excerpt_id", "interval_id", "flow_key"]
    ranked = blocks.withColumn("turn", F.row_number().over(Window.partitionBy("excerpt_id").orderBy(F.desc("size"), "block_no")))
    if maps is not None:
        needed = _kept(present.join(places.select("excerpt_id", F.col("feature").alias("section")).distinct(), "excerpt_id"))
        # only bitmaps of intervals with hits, and of them only sections that some excerpt asks for
        candidates = bitindex.prune_inverted(_asked_ones(maps, needed), needed)
        free = present.join(places.select("excerpt_id").distinct(), "excerpt_id", "left_anti")
        candidates = candidates.unionByName(all_flows(free, flows))
    else:
        candidates = all_flows(present, flows)

    def survivors(who: DataFrame, some: DataFrame) -> DataFrame:
        asked = who.join(some.select("excerpt_id", "block"), "excerpt_id")
        probes = _bound_places(asked, config)
        met = probes.join(sections.select("interval_id", "section", "chunk", "bits"), ["interval_id", "section", "chunk"], "left")
        missed = met.filter(F.col("bits").isNull() | ~bit_set()).select(*keys).distinct()
        return who.join(missed, keys, "left_anti")

    return survivors(survivors(candidates, ranked.filter("turn = 1")), ranked.filter("turn > 1"))


def _asked_ones(maps: DataFrame, needed: DataFrame) -> DataFrame:
    """interval_id, flow_key, section: ones of packed bitmaps among the sections that some excerpt of the interval asks for."""
    per = needed.groupBy("interval_id").agg(F.collect_set("section").alias("asked"))
    rows = maps.join(per, "interval_id").select("interval_id", "flow_key", "bitmap", F.explode("asked").alias("section"))
    return rows.filter(bit_set("bitmap", "section")).select("interval_id", "flow_key", "section")


def bitmap_words(flowbits: DataFrame, sections: int) -> DataFrame:
    """Word rows of packed bitmaps."""
    n = -(-sections // 32)
    hx = F.rpad(F.hex("bitmap"), n * 8, "0")
    rows = flowbits.select("interval_id", "flow_key", hx.alias("hx"), F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("word_ix"))
    at = lambda i: F.expr(f"substring(hx, word_ix * 8 + {i}, 2)")
    return rows.select("interval_id", "flow_key", F.col("word_ix").cast("int"), F.conv(F.concat(at(7), at(5), at(3), at(1)), 16, 10).cast("bigint").alias("word")).filter("word <> 0")


def bitmap_sections(flowbits: DataFrame, sections: int) -> DataFrame:
    """interval_id, flow_key, section: a row per one-bit of packed bitmaps."""
    words = bitmap_words(flowbits, sections)
    ones = F.filter(F.sequence(F.lit(0), F.lit(31)), lambda i: F.call_function("shiftright", F.col("word"), i).bitwiseAND(F.lit(1)) == 1)
    return words.select("interval_id", "flow_key", "word_ix", F.explode(ones).alias("i")).select("interval_id", "flow_key", (F.col("word_ix") * 32 + F.col("i")).alias("section"))


def evaluate(flows: DataFrame, excerpt_rows: list[tuple], every_excerpt: list, configs: list[tuple[int, DigestConfig]], filters: dict, tags: list[int] | None = None, present: dict[int, list] | None = None, kind: str = "bigint", packed_bound: int = 2 * PACKED_BOUND, carry: tuple[str, ...] = (), flag: bool = False) -> DataFrame:
    """config_id, interval_id, flow_key, excerpt_id for all configurations in one row-local pass over the flows.

    flows has flow_key, interval_id where there are several, and, for configurations with an index, a column b<config_id> of
    section bitmaps. excerpt_rows are (excerpt_id, block_no, size, block); a block under a configuration's threshold counts as
    present. filters are [section, word] arrays by (interval, config_id), or by config_id for the one interval. present: the excerpts that
    appear in each interval; without it appearance is decided here. tags: the section of each row, where something else than
    the digest chooses it. carry: more columns of the flows that the result keeps. flag: a column untestable, of excerpts without a kept
    block, so that no verdict has to meet its excerpt again.

    Bitmaps are tested for a batch of flows at a time. Of the pairs left by any configuration the largest block is bound to the
    flow, once for all configurations; then the others of the pairs that are still left."""
    size = sum(f.nbytes for f in filters.values()) + sum(len(b) + 64 for *_, b in excerpt_rows)
    if size > packed_bound:
        raise ValueError(f"{size} bytes of filters and excerpts: use the joins")
    if any(c.hash_family != configs[0][1].hash_family or c.salt != configs[0][1].salt for _, c in configs):
        raise ValueError("configurations of one pass share their hashes")
    filters = {k if isinstance(k, tuple) else (0, k): v for k, v in filters.items()}
    number = {e: i for i, e in enumerate(every_excerpt)}
    asked_for = [any(r[2] >= c.threshold if c.keep_equal else r[2] > c.threshold for _, c in configs) for r in excerpt_rows]
    rows = sorted((i for i, a in enumerate(asked_for) if a), key=lambda i: (number[excerpt_rows[i][0]], -excerpt_rows[i][2], excerpt_rows[i][1]))
    owner = np.array([number[excerpt_rows[i][0]] for i in rows], np.int64)
    sizes = np.array([excerpt_rows[i][2] for i in rows], np.int64)
    blocks = [excerpt_rows[i][3] for i in rows]
    tag = None if tags is None else np.array([tags[i] for i in rows], np.int64)
    listed = None if present is None else {i: np.array(sorted(number[e] for e in own), np.int64) for i, own in present.items()}
    held = flows.sparkSession.sparkContext.broadcast((owner, sizes, blocks, filters, tag, listed, every_excerpt))
    one_interval = "interval_id" not in flows.columns
    family, salt = configs[0][1].hash_family, configs[0][1].salt
    arrow_id = pa.string() if kind == "string" else pa.int64() if kind == "bigint" else None

    def tested(parts, c: DigestConfig, table: np.ndarray, tag: np.ndarray | None, some, known: dict) -> np.ndarray:
        """Whether the places of some of the hashes are ones. known: sections and places that configurations share, by what decides them."""
        layout = Layout.of(c)
        sel, g1, g2 = parts
        if tag is None and ("s", c.filter_sections) not in known:
            known["s", c.filter_sections] = sel % c.filter_sections
        section = (known["s", c.filter_sections] if tag is None else tag)[some]
        hit = np.ones(len(section), bool)
        for r in range(c.k):
            if (layout.m_sub, r) not in known:
                known[layout.m_sub, r] = (g1 + r * g2) % layout.m_sub
            pos = known[layout.m_sub, r][some]
            hit &= (table[section, pos >> 5] >> (pos & 31).astype(np.uint32) & 1).astype(bool)
        return hit

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        owner, sizes, blocks, tables, tag, listed, every = held.value
        hashed = Hashed(blocks, family, salt)
        content = hashed.content() if blocks else (np.zeros(0, np.int64),) * 3
        begin, end = (np.searchsorted(owner, np.arange(len(every)), side) for side in ("left", "right"))
        ids = pa.array(every, arrow_id)
        step = min(4096, max(64, (HELD_CELLS // len(configs)) // max(1, len(every)) // 8 * 8))
        kept = {cid: sizes >= c.threshold if c.keep_equal else sizes > c.threshold for cid, c in configs}
        blind = {cid: np.bincount(owner[k], minlength=len(every)) == 0 for cid, k in kept.items()} if flag else {}
        alive_at: dict[tuple[int, int], np.ndarray] = {}
        shared: dict = {}

        def appears(i: int, cid: int, c: DigestConfig) -> np.ndarray:
            if (i, cid) not in alive_at:
                out = np.ones(len(every), bool)
                if listed is not None:
                    out = np.isin(np.arange(len(every)), listed.get(i, []))
                elif (i, cid) in tables:
                    out[owner[kept[cid] & ~tested(content, c, tables[i, cid], tag, slice(None), shared)]] = False
                alive_at[i, cid] = out
            return alive_at[i, cid]

        def left_by_index(c: DigestConfig, cid: int, alive: np.ndarray, bitmaps: np.ndarray, ok: np.ndarray) -> None:
            """[excerpt, flow], packed: all sections of the excerpt's kept blocks are ones. A section's flows are a row of bits, and an excerpt's
            rows are taken together."""
            flows = np.packbits(np.unpackbits(bitmaps, axis=1, bitorder="little").T, axis=1, bitorder="little")
            some = np.flatnonzero(kept[cid] & alive[owner])
            section = content[0][some] % c.sections
            first = np.flatnonzero(np.concatenate([[True], owner[some][1:] != owner[some][:-1]])) if len(some) else some
            for a in range(0, len(first), 8192):
                own = first[a : a + 8192]
                last = first[a + 8192] if a + 8192 < len(first) else len(some)
                ok[owner[some[own]]] = np.bitwise_and.reduceat(flows[section[own[0] : last]], own - own[0], axis=0)

        def slabs(ok: dict[int, np.ndarray]) -> Iterator[tuple[int, int]]:
            """Excerpts a to b that have about HELD_PAIRS pairs in any configuration, and a bounded number of cells."""
            pairs = np.cumsum(np.maximum.reduce([np.bitwise_count(x).sum(axis=1, dtype=np.int64) for x in ok.values()]))
            a, most = 0, max(1, HELD_PAIRS * 32 // len(ok) // max(1, 8 * next(iter(ok.values())).shape[1]))
            while a < len(pairs):
                b = int(np.searchsorted(pairs, (pairs[a - 1] if a else 0) + HELD_PAIRS, "right"))
                yield a, (b := min(max(b, a + 1), a + most))
                a = b

        def asked(left: np.ndarray, excerpt: np.ndarray, turn: int) -> tuple[np.ndarray, np.ndarray]:
            """Of the pairs that are left the largest block, then the second, then all others; and the pair of each."""
            pairs = np.flatnonzero(left & (end > begin + turn)[excerpt])
            first = begin[excerpt[pairs]] + turn
            if turn < 2:
                return first, pairs
            n = end[excerpt[pairs]] - first
            return np.repeat(first - np.cumsum(n) + n, n) + np.arange(n.sum()), np.repeat(pairs, n)

        for whole in batches:
            for a in range(0, whole.num_rows, step):
                batch = whole.slice(a, step)
                interval = np.zeros(batch.num_rows, np.int64) if one_interval else batch.column("interval_id").to_numpy(zero_copy_only=False)
                keys = batch.column("flow_key")
                for i in np.unique(interval).tolist():
                    at = np.flatnonzero(interval == i)
                    taken = pa.array(at)
                    bind, ok = hashed.binding(keys.take(taken).to_pylist()), {}
                    for cid, c in configs:
                        alive = appears(i, cid, c)
                        ok[cid] = np.repeat(np.where(alive, np.uint8(255), np.uint8(0))[:, None], -(-len(at) // 8), axis=1)
                        if c.index:
                            maps = np.frombuffer(b"".join(batch.column(f"b{cid}").take(taken).to_pylist()), np.uint8).reshape(len(at), -1)
                            left_by_index(c, cid, alive, maps, ok[cid])
                    for x, y in slabs(ok):
                        cells = {cid: np.unpackbits(rows[x:y], axis=1, count=len(at), bitorder="little").view(bool).ravel() for cid, rows in ok.items()}
                        flat = np.flatnonzero(np.logical_or.reduce(list(cells.values())) if len(cells) > 1 else cells[configs[0][0]])
                        own = {cid: cell[flat] for cid, cell in cells.items()}
                        excerpt = flat // len(at)
                        of = flat - excerpt * len(at)
                        excerpt += x
                        del cells, flat
                        for turn in range(3):
                            which, pair = asked(np.logical_or.reduce(list(own.values())) if len(own) > 1 else own[configs[0][0]], excerpt, turn)
                            if not len(which):
                                continue
                            parts, known = hashed.bound(which, bind, of[pair]), {}
                            for cid, c in configs:
                                some = np.flatnonzero(own[cid][pair] & kept[cid][which])
                                own[cid][pair[some[~tested(parts, c, tables[i, cid], None if tag is None else tag[which], some, known)]]] = False
                        for cid, still in own.items():
                            found = np.flatnonzero(still)
                            if len(found):
                                n, flow, who = len(found), pa.array(at[of[found]]), excerpt[found]
                                columns = [pa.array(np.full(n, cid, np.int32)), pa.array(np.full(n, i, np.int32)), keys.take(flow), ids.take(pa.array(who)), *(batch.column(c).take(flow) for c in carry)]
                                yield pa.RecordBatch.from_arrays([*columns, *([pa.array(blind[cid][who])] if flag else [])], names)

    names = ["config_id", "interval_id", "flow_key", "excerpt_id", *carry, *(["untestable"] if flag else [])]
    columns = ["flow_key", *(["interval_id"] if not one_interval else []), *[f"b{cid}" for cid, c in configs if c.index], *carry]
    more = "".join(f", {c} {flows.schema[c].dataType.simpleString()}" for c in carry)
    return flows.select(*columns).mapInArrow(kernel, f"config_id int, interval_id int, flow_key string, excerpt_id {kind}{more}{', untestable boolean' if flag else ''}")


def candidates_of(blocks: DataFrame, flow_words: DataFrame, flows: DataFrame, excerpts: DataFrame, config: DigestConfig) -> DataFrame:
    """Flows that the index leaves for each excerpt in interval 0, by content sections alone."""
    hits = blocks.select("excerpt_id", F.lit(0).alias("interval_id"), section_of(block_digest(F.col("block"), config.salt), config.sections).alias("section")).distinct()
    asked = excerpts.select("excerpt_id", F.lit(0).alias("interval_id"))
    return bitindex.prune(flow_words, bitindex.required_words(hits), flows, asked)


def candidate_counts(excerpts: DataFrame, maps: DataFrame, config: DigestConfig, part: int = 500_000) -> DataFrame:
    """excerpt_id, c: how many flows the index leaves for each excerpt in interval 0; the pairs themselves are not made. maps has a
    bitmap for each flow. A section's flows are a row of bits; an excerpt's rows are taken together and counted. Excerpts go in parts of
    about `part`, a pass over the bitmaps each."""
    section = section_of(block_digest(F.col("block"), config.salt), config.sections)
    need = excerpt_blocks(excerpts, config).groupBy("excerpt_id").agg(F.collect_set(section).alias("need"))
    need = excerpts.select("excerpt_id").join(need, "excerpt_id", "left").select("excerpt_id", F.coalesce("need", F.array().cast("array<int>")).alias("need"))
    need = need.persist(StorageLevel.MEMORY_AND_DISK)
    parts = max(1, -(-need.count() // part))
    spark, kind = excerpts.sparkSession, id_type(excerpts)
    spread = maps.select("bitmap").repartition(spark.sparkContext.defaultParallelism * 2)

    def counted(p: int) -> DataFrame:
        held = need.filter(F.pmod(F.xxhash64("excerpt_id"), F.lit(parts)) == p).toArrow().combine_chunks()
        ids, lists = (held.column(c).chunk(0) if held.column(c).num_chunks else pa.array([], held.schema.field(c).type) for c in ("excerpt_id", "need"))
        of = np.diff(lists.offsets.to_numpy())
        sent = spark.sparkContext.broadcast((ids, lists.flatten().to_numpy(zero_copy_only=False), lists.offsets.to_numpy(), of))

        def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            ids, sections, start, of = sent.value
            total = np.zeros(len(ids), np.int64)
            for whole in batches:
                n = whole.num_rows
                if not n:
                    continue
                raw = np.frombuffer(b"".join(whole.column("bitmap").to_pylist()), np.uint8).reshape(n, -1)
                bits = np.packbits(np.unpackbits(raw, axis=1, bitorder="little").T, axis=1, bitorder="little")
                bits = np.ascontiguousarray(np.pad(bits, ((0, 0), (0, -bits.shape[1] % 8)))).view(np.uint64)
                for k in np.unique(of).tolist():
                    same = np.flatnonzero(of == k)
                    if k == 0:
                        total[same] += n
                    for a in range(0, len(same) if k else 0, 1024):
                        own = same[a : a + 1024]
                        left = bits[sections[start[own]]]
                        for j in range(1, k):
                            left &= bits[sections[start[own] + j]]
                        total[own] += np.bitwise_count(left).sum(axis=1, dtype=np.int64)
            yield pa.RecordBatch.from_arrays([ids, pa.array(total)], ["excerpt_id", "c"])

        return spread.mapInArrow(kernel, f"excerpt_id {kind}, c bigint")

    out = counted(0)
    for p in range(1, parts):
        out = out.unionByName(counted(p))
    return out.groupBy("excerpt_id").agg(F.sum("c").alias("c"))


def wildcard(parts: DataFrame, digest: Digest, **how) -> DataFrame:
    """Excerpts with gaps: rows (excerpt_id, part, excerpt); a flow is reported if it carries every literal part, whatever the parts'
    numbers are."""
    key = F.concat_ws(":", F.col("excerpt_id").cast("string"), F.col("part").cast("string"))
    keyed = parts.filter("excerpt_id is not null and part is not null").select(key.alias("excerpt_id"), "excerpt")
    own = parts.select(key.alias("key"), F.col("excerpt_id").alias("whole")).distinct()
    found = attribute(keyed, digest, **how).join(own, F.col("excerpt_id") == F.col("key")).select(F.col("whole").alias("excerpt_id"), "interval_id", "flow_key", "key")
    need = parts.groupBy("excerpt_id").agg(F.countDistinct("part").alias("n"))
    return found.groupBy("excerpt_id", "interval_id", "flow_key").agg(F.countDistinct("key").alias("met")).join(need, "excerpt_id").filter("met = n").select("excerpt_id", "interval_id", "flow_key")
