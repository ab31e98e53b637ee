"""The experiments, on traces from the given tables.

One interval, excerpts of 200 bytes that occur in one flow. Filters of all configurations are built in one plan, and every flow-bound
digest is computed once for all of them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import Heads, Tails, block_digest, digests, flow_digest, md5_parts, section_of
from ..operators import attribution, baselines, bitindex, blocking, downsample, measures, membership, trace
from ..operators.digest import CHUNK_BYTES, DigestConfig, Layout, build, content_elements, packed_bitmaps, packed_filters, raw_bytes, words_of

#: The experiments' size: this many excerpts (the smallest ids), of this many bytes.
EXCERPTS, LENGTH = 1_000, 200
THRESHOLDS = (0, 10, 20, 30, 40, 45, 50, 60)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def docs_trace(spark: SparkSession, sf_dir: str, **how) -> DataFrame:
    return trace.from_documents(table(spark, sf_dir, "documents"), **how)


def ledger_trace(spark: SparkSession, sf_dir: str, yearly: bool = False) -> DataFrame:
    return trace.from_ledger(*(table(spark, sf_dir, t) for t in ("lineitem", "orders", "supplier", "customer")), yearly=yearly)


def excerpt_slices(documents: DataFrame, length: int = LENGTH) -> DataFrame:
    """excerpt_id, excerpt, own: a slice of each document of 400 bytes or more, at a place that its id decides."""
    data = F.encode(F.coalesce("text", F.lit("")), "UTF-8")
    rows = documents.select(F.col("doc_id").alias("excerpt_id"), data.alias("data")).filter(F.octet_length("data") >= 400)
    at = F.lit(50) + F.pmod(F.col("excerpt_id") * 7919, F.octet_length("data") - 300)
    return rows.withColumn("at", at.cast("int")).select("excerpt_id", F.expr(f"substring(data, at + 1, {length})").alias("excerpt"))


def unique_excerpts(spark: SparkSession, sf_dir: str, packets: DataFrame | None = None, count: int | None = None) -> DataFrame:
    """excerpt_id, excerpt, true_flow: slices that exactly one flow of the trace contains; an experiment takes `count`."""
    packets = docs_trace(spark, sf_dir) if packets is None else packets
    slices = excerpt_slices(table(spark, sf_dir, "documents"))
    found = slices.join(baselines.carried_once(packets, slices), "excerpt_id")
    return found if count is None else found.orderBy("excerpt_id").limit(count)


def absent_excerpts(spark: SparkSession, sf_dir: str, count: int = 10_000) -> DataFrame:
    """excerpt_id, excerpt: slices of turns and pages that no document contains."""
    turn = F.encode(F.coalesce("text", F.lit("")), "UTF-8")
    turns = table(spark, sf_dir, "conversations").select(F.format_string("turn %d of %d", "turn", "conv_id").alias("excerpt_id"), turn.alias("data"))
    pages = table(spark, sf_dir, "pages").select(F.format_string("page %d", "page_id").alias("excerpt_id"), F.encode(F.coalesce("html", F.lit("")), "UTF-8").alias("data"))
    slices = turns.unionByName(pages).filter(F.octet_length("data") >= LENGTH).select("excerpt_id", F.expr(f"substring(data, (octet_length(data) - {LENGTH}) div 2 + 1, {LENGTH})").alias("excerpt"))
    found = baselines.exact_search(docs_trace(spark, sf_dir), slices)
    return slices.join(found.select("excerpt_id").distinct(), "excerpt_id", "left_anti").orderBy("excerpt_id").limit(count)


def grid(raw: int, entries: list[dict]) -> list[tuple[int, DigestConfig]]:
    """Numbered configurations, sized for the trace's bytes."""
    return [(i, DigestConfig(**e).sized(raw)) for i, e in enumerate(entries)]


#: Bytes of filters in one pass over the flows, where no index or excerpt needs the room.
PASS_BYTES = 112 << 20


def in_passes(configs: list[tuple[int, DigestConfig]], most: int = PASS_BYTES) -> list[list[tuple[int, DigestConfig]]]:
    """Configurations in groups whose filters have at most so many bytes; a larger one is a group by itself."""
    out: list[list] = []
    room = 0
    for i, c in configs:
        size = -(-c.m_bits // 8)
        if not out or size > room:
            out.append([])
            room = most
        out[-1].append((i, c))
        room -= size
    return out


class Experiment:
    """A trace, its blocks (kept), and unique excerpts (kept); made once for all configurations. A new experiment lets the last
    one's kept rows go; plans that still use them compute them again."""

    last: Experiment | None = None

    def __init__(self, spark: SparkSession, sf_dir: str, packets: DataFrame | None = None, count: int | None = EXCERPTS):
        if Experiment.last is not None and Experiment.last.spark is spark:
            Experiment.last.close()
        Experiment.last = self
        self.spark = spark
        self.packets = docs_trace(spark, sf_dir) if packets is None else packets
        self.raw = raw_bytes(self.packets)
        self.flows = bitindex.flow_list(self.packets)
        self.n_flows = self.flows.count()
        self.blocks = blocking.winnow_blocks(self.packets).persist(StorageLevel.MEMORY_AND_DISK)
        self.excerpts = unique_excerpts(spark, sf_dir, self.packets, count).persist(StorageLevel.MEMORY_AND_DISK)

    def close(self) -> None:
        self.blocks.unpersist()
        self.excerpts.unpersist()

    def excerpt_rows(self, cut=None) -> tuple[list, list[int]]:
        """Block rows of the excerpts and all excerpt ids; refused where the excerpts are too large to be sent to every task."""
        if baselines.excerpt_bytes(self.excerpts) > attribution.PACKED_BOUND:
            raise ValueError("too many excerpts for one pass: use attribution.attribute")
        held = [(r["excerpt_id"], bytes(r["excerpt"])) for r in self.excerpts.select("excerpt_id", "excerpt").collect()]
        row, number, _, size, blocks = (cut or blocking.winnow_batch)([e for _, e in held])
        return [(held[i][0], int(n), int(s), b) for i, n, s, b in zip(row.tolist(), number, size, blocks, strict=True)], sorted(i for i, _ in held)

    def filters(self, configs: list[tuple[int, DigestConfig]], cut=None, tag=None) -> dict[int, np.ndarray]:
        """[section, word] arrays of all configurations, from one plan that hands on packed chunks, which come to the driver one
        partition after the other."""
        if sum(c.m_bits for _, c in configs) > 16 * attribution.PACKED_BOUND:
            raise ValueError("filters too large for one pass: use attribution.attribute")
        layouts = {i: Layout.of(c) for i, c in configs}
        out = {i: np.zeros((x.sections, x.section_bytes), np.uint8) for i, x in layouts.items()}
        for r in packed_filters(self.packets, configs, cut, tag).toLocalIterator():
            raw = np.frombuffer(r["bits"], np.uint8)
            out[r["config_id"]][r["section"], r["chunk"] * CHUNK_BYTES : r["chunk"] * CHUNK_BYTES + len(raw)] = raw
        return {i: f.view("<u4") for i, f in out.items()}

    def words(self, config: DigestConfig) -> DataFrame:
        """Index words of a configuration."""
        return bitindex.flow_words(content_elements(downsample.keep_large(self.blocks, config.threshold, config.keep_equal), config))

    def bitmaps(self, config: DigestConfig) -> DataFrame:
        return bitindex.flow_bitmaps(self.words(config), self.flows, config.sections)

    def verdicts(self, configs: list[tuple[int, DigestConfig]]) -> DataFrame:
        """config_id, interval_id, flow_key, excerpt_id. Configurations whose filters fit in one pass share it; a filter that fits in none is
        asked by joins."""
        parts = in_passes(configs)
        if len(parts) > 1:
            return union([self.verdicts(p) for p in parts])
        rows, ids = self.excerpt_rows()
        flows, parallel = self.flows.select("flow_key"), self.spark.sparkContext.defaultParallelism
        if len(configs) == 1:  # one configuration: the digest itself
            i, c = configs[0]
            digest = build(self.packets, c)
            if c.m_bits > 8 * PASS_BYTES:
                return attribution.attribute(self.excerpts, digest).select(F.lit(i).alias("config_id"), "interval_id", "flow_key", "excerpt_id")
            if c.index:
                flows = digest.flowbits.select("flow_key", F.col("bitmap").alias(f"b{i}"))
            return attribution.evaluate(flows.repartition(parallel), rows, ids, configs, {i: attribution.filter_arrays(digest, [0])[0]})
        if indexed := [(i, c) for i, c in configs if c.index]:
            flows = packed_bitmaps(self.packets, indexed).drop("interval_id")
        return attribution.evaluate(flows.repartition(parallel), rows, ids, configs, self.filters(configs))

    def fpr(self, configs: list[tuple[int, DigestConfig]]) -> DataFrame:
        """config_id, excerpts, reported, false_flows, fpr."""
        truth = self.excerpts.select("excerpt_id", F.col("true_flow").alias("flow_key"))
        return measures.flow_fpr(self.verdicts(configs), truth, self.excerpts, self.n_flows, ("config_id",))


def threshold_sweep(spark: SparkSession, sf_dir: str, k: int = 2, packets: DataFrame | None = None) -> DataFrame:
    """threshold, excerpts, reported, false_flows, fpr: downsampling alone."""
    e = Experiment(spark, sf_dir, packets)
    configs = grid(e.raw, [{"threshold": t, "k": k} for t in THRESHOLDS])
    names = spark.createDataFrame([(i, c.threshold) for i, c in configs], "config_id int, threshold int")
    return e.fpr(configs).join(F.broadcast(names), "config_id").select("threshold", "excerpts", "reported", "false_flows", "fpr")


def best_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    """threshold, fpr at the least of the measured curve."""
    return threshold_sweep(spark, sf_dir).select("threshold", "fpr").orderBy("fpr", "threshold").limit(1)


GRID = [{"sections": j, "threshold": t, "index": True} for j in (64, 256, 1024) for t in (0, 20, 40)]


def grid_fpr(spark: SparkSession, sf_dir: str, packets: DataFrame | None = None) -> DataFrame:
    """sections, threshold, ...: index and downsampling together."""
    e = Experiment(spark, sf_dir, packets)
    configs = grid(e.raw, GRID)
    names = spark.createDataFrame([(i, c.sections, c.threshold) for i, c in configs], "config_id int, sections int, threshold int")
    return e.fpr(configs).join(F.broadcast(names), "config_id").select("sections", "threshold", "excerpts", "reported", "false_flows", "fpr")


def cut_of(name: str):
    """How a baseline cuts payloads and excerpts."""
    return {"shingled_winnow": baselines.shingled_winnow, "multi_winnow": baselines.multi_winnow, "double_winnow": baselines.double_winnow, "fixed_multifilter": lambda: baselines.fixed_multifilter()[0]}[name]()


def baseline_verdicts(e: Experiment, name: str, sizes: list[tuple[int, int]]) -> DataFrame:
    """config_id, flow_key, excerpt_id that a baseline reports in filters of (m_bits, k); config_id is the number of the size. All sizes
    share cuts and hashes."""
    if name == "fixed_multifilter":
        return fixed_verdicts(e, sizes)
    cut = cut_of(name)
    rows, ids = e.excerpt_rows(cut)
    flows = e.flows.select("flow_key").repartition(e.spark.sparkContext.defaultParallelism)
    configs = [(i, DigestConfig(m_bits=m, k=k)) for i, (m, k) in enumerate(sizes)]
    return union([attribution.evaluate(flows, rows, ids, p, e.filters(p, cut)) for p in in_passes(configs)]).select("config_id", "flow_key", "excerpt_id")


def baseline_verdict(e: Experiment, name: str, m_bits: int, k: int = 1) -> tuple[DataFrame, DataFrame]:
    """flow_key, excerpt_id that a baseline reports, and its elements."""
    return baseline_verdicts(e, name, [(m_bits, k)]).select("flow_key", "excerpt_id"), blocking.block_rows(e.packets, cut_of(name))


def baseline_rates(e: Experiment, name: str, sizes: list[tuple[int, int]]) -> DataFrame:
    """config_id, method, k, elements, excerpts, reported, false_flows, fpr of a baseline in filters of (m_bits, k)."""
    truth = e.excerpts.select("excerpt_id", F.col("true_flow").alias("flow_key"))
    one = len(sizes) == 1  # then there is a row even where nothing is reported
    found = measures.flow_fpr(baseline_verdicts(e, name, sizes), truth, e.excerpts, e.n_flows, () if one else ("config_id",))
    found = found.withColumn("config_id", F.lit(0)) if one else found
    n = blocking.block_count(e.packets, cut_of(name))
    k = F.element_at(F.array(*[F.lit(k) for _, k in sizes]), F.col("config_id") + 1)
    return found.select("config_id", F.lit(name).alias("method"), k.alias("k"), F.lit(n).cast("bigint").alias("elements"), "excerpts", "reported", "false_flows", "fpr")


def baseline_fpr(e: Experiment, name: str, m_bits: int, k: int = 1) -> DataFrame:
    """method, elements, excerpts, reported, false_flows, fpr of a baseline in a filter of m_bits."""
    return baseline_rates(e, name, [(m_bits, k)]).drop("config_id", "k")


def fixed_verdicts(e: Experiment, sizes: list[tuple[int, int]], modulus: int = 8) -> DataFrame:
    """Baseline 3: alignments are asked one by one; flows only under alignments whose content is all present."""
    cut, tag, size = baselines.fixed_multifilter(modulus=modulus)
    if baselines.excerpt_bytes(e.excerpts) * size > 16 * attribution.PACKED_BOUND:
        raise ValueError("too many excerpts for one pass")
    held = [(r["excerpt_id"], bytes(r["excerpt"])) for r in e.excerpts.select("excerpt_id", "excerpt").collect()]
    flows = e.flows.select("flow_key").repartition(e.spark.sparkContext.defaultParallelism)
    found = []
    for part in in_passes([(i, DigestConfig(m_bits=m, k=k, sections=modulus)) for i, (m, k) in enumerate(sizes)]):
        filters = e.filters(part, cut, tag)
        rows, tags = [], []
        for a in range(0, len(held), ALIGNED):
            # alignments whose content is absent everywhere fall out here, before any flow is asked
            some, own = aligned_rows(held[a : a + ALIGNED], size, tag)
            alive = set().union(*(content_alive(some, own, filters[i], c) for i, c in part)) if some else set()
            kept = [n for n, r in enumerate(some) if r[0] in alive]
            rows += [some[n] for n in kept]
            tags += [own[n] for n in kept]
        found.append(attribution.evaluate(flows, rows, sorted({r[0] for r in rows}), part, filters, tags, kind="string"))
    return union(found).select("config_id", "flow_key", F.substring_index("excerpt_id", ":", 1).cast("bigint").alias("excerpt_id")).distinct()


#: Excerpts whose alignments are in the driver at a time.
ALIGNED = 64


def aligned_rows(held: list[tuple[int, bytes]], size: int, tag) -> tuple[list, list[int]]:
    """Block rows of each alignment of each excerpt, and their tags."""
    rows = [(f"{i}:{a}", n, size, x[at : at + size]) for i, x in held for a in range(size) for n, at in enumerate(range(a, len(x) - size + 1, size))]
    return rows, [tag(r[3]) for r in rows]


def content_alive(rows: list, tags: list[int], array: np.ndarray, config: DigestConfig) -> set[int]:
    """Ids of row groups whose content digests are all present."""
    _, g1, g2 = md5_parts(digests([r[3] for r in rows]))
    tag, m_sub = np.array(tags), config.m_bits // config.sections
    hit = np.ones(len(rows), bool)
    for r in range(config.k):
        pos = (g1 + r * g2) % m_sub
        hit &= (array[tag, pos >> 5] >> (pos & 31).astype(np.uint32) & 1).astype(bool)
    gone = {r[0] for r, h in zip(rows, hit.tolist(), strict=True) if not h}
    return {r[0] for r in rows} - gone


METHODS = ("shingled_winnow", "multi_winnow", "fixed_multifilter", "double_winnow")


def methods_fpr(spark: SparkSession, sf_dir: str, reduction: float = 100.0, ks: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """method, k, elements, ...: the four baselines at one reduction ratio, for each number of hashes."""
    e = Experiment(spark, sf_dir)
    m = DigestConfig(reduction=reduction).sized(e.raw).m_bits
    return union([baseline_rates(e, name, [(m, k) for k in ks]).drop("config_id") for name in METHODS])


def union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def at_best_k(rows: DataFrame, *keys: str) -> DataFrame:
    """Each method with the number of hashes that serves it best (the smaller of equals)."""
    rest = [c for c in rows.columns if c not in keys]
    best = rows.groupBy(*keys).agg(F.min(F.struct("fpr", "k", *[c for c in rest if c not in ("fpr", "k")])).alias("b"))
    return best.select(*keys, *[F.col(f"b.{c}").alias(c) for c in rest])


def matched_uncompressed(spark: SparkSession, sf_dir: str, sections: tuple[int, ...] = (64, 256), ks: tuple[int, ...] = (1, 2)) -> DataFrame:
    """method, sections, k, fpr ...: all methods at equal overall ratios with the index as it is: the baselines' filters have the bytes of
    our filter and bitmaps, and each its best number of hashes."""
    e = Experiment(spark, sf_dir)
    configs = grid(e.raw, [{"sections": j, "index": True} for j in sections])
    names = spark.createDataFrame([(i, c.sections) for i, c in configs], "config_id int, sections int")
    ours = e.fpr(configs).join(F.broadcast(names), "config_id").select(F.lit("sectioned_indexed").alias("method"), "sections", F.lit(1).alias("k"), "excerpts", "reported", "false_flows", "fpr")
    sizes = [(c.sections, c.m_bits + 8 * e.n_flows * (-(-c.sections // 8)), k) for _, c in configs for k in ks]
    j = F.element_at(F.array(*[F.lit(j) for j, _, _ in sizes]), F.col("config_id") + 1)
    others = [baseline_rates(e, name, [(m, k) for _, m, k in sizes]).select("method", j.alias("sections"), "k", "excerpts", "reported", "false_flows", "fpr") for name in METHODS]
    return ours.unionByName(at_best_k(union(others), "method", "sections"))


#: The ratio of the hierarchical digest, and how many lengths its runs of blocks have.
HIER_RATIO, HIER_LEVELS = 10.0, 2


def hier_verdict(spark: SparkSession, sf_dir: str, block: int = 32) -> DataFrame:
    """excerpts, alive (guesses of alignment and place that content leaves), reported, false_flows, missed: fixed blocks stored with
    their place, and runs of two. An excerpt is asked for at each place that a payload of the trace has."""
    e = Experiment(spark, sf_dir)
    config = DigestConfig(reduction=HIER_RATIO).sized(e.raw)
    cut = baselines.hier_fixed(block, HIER_LEVELS)
    filters = e.filters([(0, config)], cut)
    held = spark.sparkContext.broadcast(filters[0])
    places = int(e.packets.agg(F.coalesce(F.max(F.octet_length("payload")), F.lit(0))).first()[0]) // block
    m = config.m_bits

    def guesses(batches):
        table = held.value[0]
        at_place = Tails([b"@%d" % f for f in range(places + LENGTH // block)])

        def present(parts) -> np.ndarray:
            pos = parts[1] % m
            return (table[pos >> 5] >> (pos & 31).astype(np.uint32) & 1).astype(bool)

        def left(x: bytes) -> Iterator[tuple[int, int]]:
            """Alignments and places at which all that hier_fixed stores of the excerpt is present: block by block, then runs."""
            starts = range(min(block, len(x) - block + 1))
            a, f = np.repeat(np.arange(len(starts)), places), np.tile(np.arange(places), len(starts))
            for level in range(HIER_LEVELS):
                run, size = 1 << level, block << level
                heads = Heads([x[i : i + size] for i in range(max(0, len(x) - size + 1))])
                for i in range(len(x) // block):
                    inside = a + i * block + size <= len(x)
                    asked = np.flatnonzero(inside & ((f + i) % run == 0))
                    ok = np.ones(len(a), bool)
                    ok[asked] = present(heads.parts(a[asked] + i * block, at_place, (f[asked] + i) // run))
                    a, f = a[ok], f[ok]
            return zip(a.tolist(), f.tolist(), strict=True)

        for batch in batches:
            out = []
            for i, x in zip(batch.column("excerpt_id").to_pylist(), batch.column("excerpt").to_pylist(), strict=True):
                out += [(i, a, f, n, len(b), b) for a, f in left(x) for n, b in enumerate(baselines.hier_elements(x, a, f, block, HIER_LEVELS))]
            yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in out], t) for j, t in enumerate((pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary()))], ["excerpt_id", "a", "f", "n", "size", "element"])

    alive = e.excerpts.select("excerpt_id", "excerpt").repartition(4 * spark.sparkContext.defaultParallelism).mapInArrow(guesses, "excerpt_id bigint, a int, f int, n int, size int, element binary")
    rows = [(f"{r['excerpt_id']}:{r['a']}:{r['f']}", r["n"], r["size"], bytes(r["element"])) for r in alive.collect()]
    ids = sorted({r[0] for r in rows})
    verdict = attribution.evaluate(e.flows.select("flow_key").repartition(spark.sparkContext.defaultParallelism), rows, ids, [(0, config)], filters, kind="string")
    found = verdict.select(F.substring_index("excerpt_id", ":", 1).cast("bigint").alias("excerpt_id"), "flow_key").distinct()
    truth = e.excerpts.select("excerpt_id", F.col("true_flow").alias("flow_key"), F.lit(1).alias("own"))
    counted = found.join(truth, ["excerpt_id", "flow_key"], "left").agg(F.count("*").alias("reported"), F.count("own").alias("right"))  # flows are asked once
    out = counted.crossJoin(e.excerpts.agg(F.count("*").alias("excerpts")))
    return out.select("excerpts", F.lit(len(ids)).cast("bigint").alias("alive"), "reported", (F.col("reported") - F.col("right")).alias("false_flows"), (F.col("excerpts") - F.col("right")).alias("missed"))


def index_sizes(e: Experiment, entries: list[dict], codec: str = "lzma2") -> DataFrame:
    """sections, threshold, raw_bytes, filter_bytes, index_bytes, packed_bytes, reduction, overall."""
    parts = None
    for _, c in grid(e.raw, entries):
        size = measures.lzma_size(e.bitmaps(c), codec)
        row = size.select(
            F.lit(c.sections).alias("sections"), F.lit(c.threshold).alias("threshold"), F.lit(e.raw).cast("bigint").alias("raw_bytes"), F.lit(c.m_bits // 8).cast("bigint").alias("filter_bytes"),
            F.col("raw_bytes").alias("index_bytes"), "packed_bytes",
        )
        parts = row if parts is None else parts.unionByName(row)
    return parts.withColumns({"reduction": F.round(F.col("raw_bytes") / F.col("filter_bytes"), 3), "overall": F.round(F.col("raw_bytes") / (F.col("filter_bytes") + F.col("packed_bytes")), 3)})


def overall_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    return index_sizes(Experiment(spark, sf_dir, count=1), GRID)


def index_stats(spark: SparkSession, sf_dir: str, packets: DataFrame | None = None, sections: tuple[int, ...] = (64, 256, 1024)) -> DataFrame:
    """sections, ones share, raw and compressed size, overall ratio, best entropy bound over symbol sizes, threshold 0."""
    e = Experiment(spark, sf_dir, packets, count=1)
    out = None
    for j in sections:
        c = DigestConfig(sections=j, index=True).sized(e.raw)
        share = measures_ones(e, c)
        sizes = index_sizes(e, [{"sections": j, "index": True}]).select("index_bytes", "packed_bytes", "overall")
        bitmaps = e.bitmaps(c)
        bounds = None
        for s in (8, 16, 32, 64):
            if s * 8 <= j:
                b = measures.symbol_entropy(bitmaps, s)
                bounds = b if bounds is None else bounds.unionByName(b)
        best = bounds.agg(F.min_by(F.struct("symbol_bytes", "entropy", "bound", "best_ratio"), "bound").alias("b")).select("b.*")
        row = share.crossJoin(sizes).crossJoin(best)
        out = row if out is None else out.unionByName(row)
    return out


def measures_ones(e: Experiment, c: DigestConfig) -> DataFrame:
    return bitindex.ones_share(e.words(c), e.flows, c.sections)


def matched_ratio(spark: SparkSession, sf_dir: str, skewed: bool = True) -> DataFrame:
    """All methods at equal overall ratios: our configurations decide the ratios, the baselines get filters of that size, each with
    its best number of hashes. On the
    trace of mice and elephants, or on small flows."""
    packets = docs_trace(spark, sf_dir, by="skew") if skewed else None
    e = Experiment(spark, sf_dir, packets)
    entries = [{"sections": j, "threshold": t, "index": True} for j in (256, 1024) for t in (0, 30)]
    configs = grid(e.raw, entries)
    ratios = {(r["sections"], r["threshold"]): r["overall"] for r in index_sizes(e, entries).collect()}
    names = spark.createDataFrame([(i, c.sections, c.threshold, float(ratios[c.sections, c.threshold])) for i, c in configs], "config_id int, sections int, threshold int, overall double")
    out = e.fpr(configs).join(F.broadcast(names), "config_id").select(F.lit("sectioned_indexed").alias("method"), "sections", "threshold", "overall", "excerpts", "false_flows", "fpr")
    sizes = [(c, ratios[c.sections, c.threshold], k) for _, c in configs for k in (1, 2)]
    mine = spark.createDataFrame([(n, c.sections, c.threshold, float(x)) for n, (c, x, _) in enumerate(sizes)], "config_id int, sections int, threshold int, overall double")
    for name in METHODS:
        rates = baseline_rates(e, name, [(DigestConfig(reduction=x).sized(e.raw).m_bits, k) for _, x, k in sizes]).join(F.broadcast(mine), "config_id")
        out = out.unionByName(at_best_k(rates.drop("config_id"), "method", "sections", "threshold", "overall").select("method", "sections", "threshold", "overall", "excerpts", "false_flows", "fpr"))
    return out


def true_negative_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks of absent excerpts by size: how many the conventional filter denies."""
    packets = docs_trace(spark, sf_dir)
    c = DigestConfig(k=2, flow_blocks=False).sized(raw_bytes(packets))
    words = words_of(blocking.winnow_blocks(packets), c)
    blocks = attribution.excerpt_blocks(absent_excerpts(spark, sf_dir), c)
    asked = blocks.select(F.lit(0).alias("interval_id"), "excerpt_id", "block_no", "size", block_digest(F.col("block")).alias("digest"))
    return measures.true_negative_by_size(membership.probe(asked, words, c.m_bits, 1, c.k))


def cost_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The analytic costs with the measured payload length, blocks and reduction of the trace."""
    packets = docs_trace(spark, sf_dir)
    d = measures.block_reduction(blocking.winnow_blocks(packets), 40).first()
    index = packets.select("flow_key").distinct().count() * 256 / 8
    return measures.cost_table(spark, raw_bytes(packets), d["seen"], 2, d["d"], 1, index)


def fragmentation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """assembly, packets, blocks: 64-byte fragments have no block until a flow is put together again."""
    cut = trace.fragment(docs_trace(spark, sf_dir), 64)
    whole = trace.reassemble(cut)
    row = lambda name, t: t.agg(F.count("*").alias("packets")).crossJoin(blocking.winnow_blocks(t).agg(F.count("*").alias("blocks"))).select(F.lit(name).alias("assembly"), "packets", "blocks")
    return row("packet", cut).unionByName(row("flow", whole))


def encrypted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """view, excerpt form, found: plain excerpts miss on the enciphered link; the stored form is found."""
    packets = docs_trace(spark, sf_dir)
    wire = trace.with_view(packets, "wire")
    plain = unique_excerpts(spark, sf_dir)
    coded = trace.with_view(plain.withColumnRenamed("excerpt", "payload"), "wire").withColumnRenamed("payload", "excerpt")
    found = lambda t, x: baselines.exact_search(t, x).agg(F.countDistinct("excerpt_id").alias("found"))
    rows = [("plain", "plain", packets, plain), ("wire", "plain", wire, plain), ("wire", "coded", wire, coded)]
    out = None
    for view, form, t, x in rows:
        row = found(t, x).select(F.lit(view).alias("view"), F.lit(form).alias("excerpt_form"), "found")
        out = row if out is None else out.unionByName(row)
    return out


def benchmark_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """excerpt_id, excerpt: known texts whose leaks are looked for."""
    return table(spark, sf_dir, "benchmark").select(F.col("item_id").alias("excerpt_id"), F.encode("text", "UTF-8").alias("excerpt")).filter("octet_length(excerpt) > 0")


def leak_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item_id, flow_key: which documents carry a known text whole, by exact search."""
    return baselines.exact_search(docs_trace(spark, sf_dir), benchmark_items(spark, sf_dir)).select(F.col("excerpt_id").alias("item_id"), "flow_key")


#: The digest that uses ask: sections, index, 100:1.
USE = {"sections": 256, "index": True}


def leak_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item_id, flow_key: which flows carried a known text, as the digest says without the payloads: all carriers, and false ones."""
    packets = docs_trace(spark, sf_dir)
    found = attribution.attribute(benchmark_items(spark, sf_dir), build(packets, DigestConfig(**USE).sized(raw_bytes(packets))))
    return found.select(F.col("excerpt_id").alias("item_id"), "flow_key")


def worm_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """signature, carriers, bytes, flow_key: payloads that several flows carried, a row for each of their flows."""
    packets = docs_trace(spark, sf_dir).withColumn("signature", F.md5("payload"))
    several = packets.groupBy("signature").agg(F.countDistinct("flow_key").alias("carriers"), F.min(F.octet_length("payload")).alias("bytes")).filter("carriers > 1")
    return packets.select("signature", "flow_key").distinct().join(several, "signature").select("signature", "carriers", "bytes", "flow_key")


def worms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """excerpt_id, excerpt: each payload of 132 bytes or more that several documents carry, once."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.encode(F.coalesce("text", F.lit("")), "UTF-8").alias("excerpt")).filter("octet_length(excerpt) >= 132")
    first = docs.groupBy(F.md5("excerpt").alias("s")).agg(F.min("doc_id").alias("excerpt_id"), F.count("*").alias("n")).filter("n > 1")
    return docs.join(first, F.col("doc_id") == F.col("excerpt_id"), "left_semi").select(F.col("doc_id").alias("excerpt_id"), "excerpt")


def worm_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """excerpt_id, flow_key: the flows that carried a repeated payload, as the digest says."""
    packets = docs_trace(spark, sf_dir)
    return attribution.attribute(worms(spark, sf_dir), build(packets, DigestConfig(**USE).sized(raw_bytes(packets)))).select("excerpt_id", "flow_key")


#: Documents in an interval, and the filter bits of one, where several intervals are asked.
INTERVAL_DOCS, INTERVAL_BITS = 250, 49_152


def attribute_intervals(spark: SparkSession, sf_dir: str, between: tuple[int, int] = (1, 2)) -> DataFrame:
    """excerpt_id, interval_id, flow_key: the whole procedure over several intervals, asked within a range of them."""
    digest = build(docs_trace(spark, sf_dir, interval_docs=INTERVAL_DOCS), DigestConfig(m_bits=INTERVAL_BITS, sections=64, index=True))
    return attribution.attribute(unique_excerpts(spark, sf_dir), digest, between=between).select("excerpt_id", "interval_id", "flow_key")


def index_ones(spark: SparkSession, sf_dir: str, sections: tuple[int, ...] = (64, 256)) -> DataFrame:
    """sections, flows, ones, share, index_bytes, reduction with the index as it is: the index table without its compressed size."""
    e = Experiment(spark, sf_dir, count=1)
    out = []
    for _, c in grid(e.raw, [{"sections": j, "index": True} for j in sections]):
        size = F.lit(c.m_bits // 8) + F.col("flows") * (c.sections // 8)
        out.append(measures_ones(e, c).select("sections", "flows", "ones", "share", (F.col("flows") * (c.sections // 8)).alias("index_bytes"), F.round(F.lit(e.raw) / size, 3).alias("overall")))
    return union(out)


def interval_hits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """excerpt_id, interval_id: in which intervals of 250 documents an excerpt appears, from a digest with one filter each."""
    packets = docs_trace(spark, sf_dir, interval_docs=250)
    c = DigestConfig(m_bits=49_152, k=1, flow_blocks=False)
    words = words_of(blocking.winnow_blocks(packets), c)
    excerpts = unique_excerpts(spark, sf_dir)
    present, _ = attribution.appearance(attribution.excerpt_blocks(excerpts, c), excerpts, words, packets, c)
    return present


def small_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """size, blocks: payloads of one repeated character give only the smallest blocks, which downsampling then drops. Spark hands on
    their lengths; each payload is made where it is cut."""
    rows = table(spark, sf_dir, "documents").select(F.coalesce(F.length("text"), F.lit(0)).alias("payload"))
    return blocking.block_sizes(rows, made=lambda n: b"a" * n)
