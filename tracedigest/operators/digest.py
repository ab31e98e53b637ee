"""Digests: configuration, building, keeping on disk, merging.

`build` is one row-local kernel over payloads (blocks, digests, bits) that hands on partial chunks of sections and partial
flow bitmaps, never a row per block; one exchange merges both by OR. A section's bits are rows of CHUNK_BYTES, so an interval's
filter of any size is many keys; what a task sets in a large filter travels as places, not as zeros.
`words_of` is the declarative form of the same filter.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import asdict, dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import block_digest, bound_hashes, digests, flow_digest, flow_number, flow_suffix, hash_parts, md5_parts, section_of, vector_hashes
from . import bitindex, blocking, compress, membership, trace


@dataclass(frozen=True)
class DigestConfig:
    """reduction: raw bytes over filter bytes; m_bits overrides it (bits per interval). sections 1 is the conventional filter; index
    keeps flow bitmaps, of the sections or (feature "hash") of as many hash values beside a conventional filter; threshold discards smaller
    blocks; k may be "auto"; assembly "flow" joins a flow's packets before blocking. hash_family: "portable" (SQL can say it), "fast" or "vector"."""

    reduction: float = 100.0
    m_bits: int | None = None
    k: int | str = 1
    sections: int = 1
    window: int = 64
    overlap: int = 4
    threshold: int = 0
    keep_equal: bool = True
    index: bool = False
    assembly: str = "packet"
    hash_family: str = "portable"
    salt: str = ""
    flow_blocks: bool = True
    feature: str = "section"
    reduction_includes_index: bool = False

    @property
    def filter_sections(self) -> int:
        """Sections of the filter itself: the index's feature may also be a plain hash beside a conventional filter."""
        return 1 if self.feature == "hash" else self.sections

    def sized(self, raw_bytes: int, flows: int = 0) -> DigestConfig:
        """With m_bits and k as numbers, for an interval of so many bytes (and flows, if the reduction is that of filter and
        uncompressed index together). k "auto" fits the load that is to be expected."""
        own = self
        if not own.m_bits:
            index_bits = flows * self.sections if self.reduction_includes_index and self.index else 0
            own = replace(own, m_bits=max(32 * self.filter_sections, int(8 * raw_bytes / self.reduction) - index_bits))
        if own.k == "auto":
            kept = max(0, min(self.window, self.window + self.overlap + 1 - self.threshold)) / self.window
            blocks = raw_bytes / ((self.window + 1) / 2) * kept
            own = replace(own, k=membership.best_k(own.m_bits, int(blocks * (2 if self.flow_blocks else 1))))
        return own


#: Bytes of a section's bits in one row.
CHUNK_BYTES = 4096
CHUNK_BITS = 8 * CHUNK_BYTES


@dataclass(frozen=True)
class Layout:
    """Where bits are: a section's bits are padded to whole words and cut in chunks."""

    m_sub: int
    sections: int

    @staticmethod
    def of(config: DigestConfig) -> Layout:
        return Layout(max(1, config.m_bits // config.filter_sections), config.filter_sections)

    @property
    def section_bytes(self) -> int:
        return -(-self.m_sub // 32) * 4

    @property
    def chunks(self) -> int:
        return -(-self.section_bytes // CHUNK_BYTES)

    def chunk_bytes(self, chunk: int) -> int:
        return min(CHUNK_BYTES, self.section_bytes - chunk * CHUNK_BYTES)

    def places(self, parts: tuple[np.ndarray, np.ndarray, np.ndarray], k: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Section and bit in it of each of the k hashes."""
        sel, g1, g2 = parts
        section = sel % self.sections
        for r in range(k):
            yield section, (g1 + r * g2) % self.m_sub


@dataclass(frozen=True)
class Digest:
    """sections: (interval_id, section, chunk, bits); flows: (interval_id, flow_key, src, dst, packets, bytes); flowbits: (interval_id,
    flow_key, bitmap) or None; config has m_bits. archive: the compressed bitmap table (with its codec) that flowbits are opened from."""

    config: DigestConfig
    sections: DataFrame
    flows: DataFrame
    flowbits: DataFrame | None
    archive: DataFrame | None = None
    codec: str = ""
    kept: tuple[DataFrame, ...] = ()

    def save(self, path: str, codec: str | None = None) -> None:
        """Parquet partitioned by interval, sorted by section, so a query reads the sections it needs of the intervals it
        needs; an interval is written by as many tasks as its rows take. codec compresses the bitmap table, shard by shard."""
        spark = self.sections.sparkSession
        ordered = self.sections.repartitionByRange("interval_id", "section", "chunk").sortWithinPartitions("interval_id", "section", "chunk")
        ordered.write.partitionBy("interval_id").parquet(f"{path}/sections")
        self.flows.write.partitionBy("interval_id").parquet(f"{path}/flows")
        if self.flowbits is not None:
            kept = compress.pack_index(self.flowbits, codec) if codec else self.flowbits
            kept.write.partitionBy("interval_id").parquet(f"{path}/index")
        spark.createDataFrame([asdict(self.config) | {"reduction": float(self.config.reduction), "codec": codec or ""}], ", ".join(f"{k} {t}" for k, t in CONFIG_TYPES.items())).coalesce(1).write.json(f"{path}/config")

    def bitmaps(self, intervals: list[int] | None = None, opened=None) -> DataFrame | None:
        """The flow bitmaps of the given intervals; of a compressed table no other shard is read or opened. opened: an accumulator
        that counts the opened shards."""
        some = (lambda df: df) if intervals is None else (lambda df: df.filter(F.col("interval_id").isin(intervals)))
        if self.archive is not None:
            return compress.unpack_index(some(self.archive), None, self.codec, opened)
        return None if self.flowbits is None else some(self.flowbits)

    def close(self) -> None:
        """Lets go of what building kept in memory; plans that still use it compute it again."""
        for df in self.kept:
            df.unpersist()


CONFIG_TYPES = {
    "reduction": "double", "m_bits": "bigint", "k": "int", "sections": "int", "window": "int", "overlap": "int", "threshold": "int", "keep_equal": "boolean", "index": "boolean", "assembly": "string",
    "hash_family": "string", "salt": "string", "flow_blocks": "boolean", "feature": "string", "reduction_includes_index": "boolean", "codec": "string",
}


def load(spark: SparkSession, path: str, intervals: list[int] | None = None) -> Digest:
    """A kept digest; `intervals` prunes partitions."""
    row = spark.read.schema(", ".join(f"{k} {t}" for k, t in CONFIG_TYPES.items())).json(f"{path}/config").first().asDict()
    codec = row.pop("codec")
    config = DigestConfig(**row)
    some = (lambda df: df.filter(F.col("interval_id").isin(intervals))) if intervals is not None else (lambda df: df)
    sections = some(spark.read.schema("section int, chunk int, bits binary, interval_id int").parquet(f"{path}/sections")).select("interval_id", "section", "chunk", "bits")
    flows = some(spark.read.schema("flow_key string, src string, dst string, packets bigint, bytes bigint, interval_id int").parquet(f"{path}/flows"))
    flowbits = archive = None
    if config.index:
        if codec:
            archive = some(spark.read.schema("shard int, flows array<string>, width int, raw_bytes bigint, packed binary, interval_id int").parquet(f"{path}/index"))
            flowbits = compress.unpack_index(archive, None, codec)
        else:
            flowbits = some(spark.read.schema("flow_key string, bitmap binary, interval_id int").parquet(f"{path}/index"))
    return Digest(config, sections, flows, flowbits, archive, codec)


def prepared(packets: DataFrame, config: DigestConfig) -> DataFrame:
    """Packets, or their flows' bytes in overlapping pieces: the same set of blocks as whole flows have."""
    return trace.flow_pieces(packets, overlap=8 * (config.window + config.overlap)) if config.assembly == "flow" else packets


def raw_bytes(packets: DataFrame) -> int:
    return int(packets.agg(F.coalesce(F.sum(F.octet_length("payload")), F.lit(0))).first()[0])


def largest_interval(packets: DataFrame, flows: bool = False) -> tuple[int, int]:
    """Bytes (and flows, if asked for) of the interval with most bytes."""
    per = packets.groupBy("interval_id").agg(F.coalesce(F.sum(F.octet_length("payload")), F.lit(0)).alias("b"))
    found = per.orderBy(F.desc("b"), "interval_id").first()
    if found is None:
        return 0, 0
    n = packets.filter(F.col("interval_id") == found["interval_id"]).select("flow_key").distinct().count() if flows else 0
    return int(found["b"]), n


def blocks_of(packets: DataFrame, config: DigestConfig) -> DataFrame:
    return blocking.winnow_blocks(prepared(packets, config), config.window, config.overlap, config.threshold, config.keep_equal)


def content_elements(blocks: DataFrame, config: DigestConfig) -> DataFrame:
    """Blocks with their content digest and its section."""
    out = blocks.withColumn("digest", block_digest(F.col("block"), config.salt))
    return out.withColumn("section", section_of(F.col("digest"), config.sections))


def elements(blocks: DataFrame, config: DigestConfig) -> DataFrame:
    """interval_id, digest of everything that is inserted: content blocks, and flow-bound ones."""
    content = blocks.select("interval_id", block_digest(F.col("block"), config.salt).alias("digest"))
    if not config.flow_blocks:
        return content
    return content.unionByName(blocks.select("interval_id", flow_digest(F.col("block"), F.col("flow_key"), config.salt).alias("digest")))


def words_of(blocks: DataFrame, config: DigestConfig) -> DataFrame:
    return membership.build_sectioned(elements(blocks, config), config.m_bits, config.filter_sections, config.k)


#: Up to so many bits of filters a task holds as they are; larger filters as sorted places.
DENSE_BITS = 1 << 26
#: Places that a task holds before it hands them on.
HELD_PLACES = 4_000_000


class _Filter:
    """What one task sets in one interval's filter. dense_bits: up to so many bits are held as they are."""

    def __init__(self, layout: Layout, dense_bits: int = DENSE_BITS):
        self.layout, self.width = layout, layout.section_bytes * 8
        self.dense = np.zeros(layout.sections * self.width, bool) if layout.sections * self.width <= dense_bits else None
        self.places: list[np.ndarray] = []
        self.held = 0

    def add(self, section: np.ndarray, pos: np.ndarray) -> None:
        at = section * self.width + pos
        if self.dense is not None:
            self.dense[at] = True
        else:
            self.places.append(at)
            self.held += len(at)

    def rows(self) -> Iterator[tuple[int, int, bytes]]:
        """section, chunk, bits of what is set: all bytes of the chunk, or fewer bytes with the places (16 bits each)."""
        layout = self.layout
        if self.dense is not None:
            packed = np.packbits(self.dense, bitorder="little").reshape(layout.sections, -1)
            for section in np.flatnonzero(packed.any(axis=1)).tolist():
                raw = packed[section].tobytes()
                for chunk in range(layout.chunks):
                    bits = raw[chunk * CHUNK_BYTES : (chunk + 1) * CHUNK_BYTES]
                    if any(bits):
                        yield section, chunk, bits
            return
        if not self.held:
            return
        every = np.sort(np.concatenate(self.places))  # np.unique of numpy 2.3 hashes them, at ninety times the cost
        every = every[np.concatenate([[True], every[1:] != every[:-1]])]
        section, pos = every // self.width, every % self.width
        key = section * layout.chunks + pos // CHUNK_BITS
        low = (pos % CHUNK_BITS).astype("<u2")
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        for a, b in zip(first.tolist(), [*first[1:].tolist(), len(key)], strict=True):
            whole = layout.chunk_bytes(int(key[a]) % layout.chunks)
            if 2 * (b - a) < whole:
                bits = low[a:b].tobytes()
            else:
                own = np.zeros(whole * 8, bool)
                own[low[a:b]] = True
                bits = np.packbits(own, bitorder="little").tobytes()
            yield int(key[a]) // layout.chunks, int(key[a]) % layout.chunks, bits


def cut_places(cut):
    """A baseline's elements in the form of winnowed places."""

    def places(payloads: list[bytes | None]):
        for a, b in blocking.chunks(payloads):
            row, number, start, _, blocks = cut(payloads[a:b])
            end = np.cumsum(np.fromiter(map(len, blocks), np.int64, len(blocks)))
            yield b"".join(blocks), np.concatenate([[0], end[:-1]]) if len(end) else end, end, np.asarray(row, np.int64) + a, number, start

    return places


def binding(flows: list[str], config: DigestConfig):
    """What binds the hashes of each of these flows' blocks."""
    if config.hash_family == "vector":
        return np.array([flow_number(f) for f in flows], np.uint64)
    return [flow_suffix(f) for f in flows]


def block_parts(data: bytes, at: np.ndarray, to: np.ndarray, row: np.ndarray, bind, config: DigestConfig, bound: bool = True):
    """Hash parts of the blocks data[at:to], and of the same bound to their flows (or None)."""
    if config.hash_family == "vector":
        hashes = vector_hashes(np.frombuffer(data, np.uint8), at, to, config.salt)
        return hash_parts(hashes), hash_parts(bound_hashes(hashes, bind[row])) if bound else None
    blocks = [data[x:y] for x, y in zip(at.tolist(), to.tolist(), strict=True)]
    content = md5_parts(digests(blocks, b"", config.hash_family, config.salt))
    return content, md5_parts(digests([b + bind[r] for b, r in zip(blocks, row.tolist(), strict=True)], b"", config.hash_family, config.salt)) if bound else None


def partial_kernel(config: DigestConfig, budget: int = 64 << 20, cut=None):
    """What a task does with batches of interval_id, flow_key and payload. Gives interval_id, flow_key ("\\0": filter), section and chunk (0 for flows), whole (bytes that the bits have when unpacked), bits: what
    each task has gathered, at most about `budget` bytes at a time."""
    layout, width = Layout.of(config), -(-config.sections // 8)
    places = cut_places(cut) if cut is not None else lambda payloads: blocking.winnow_places(payloads, config.window, config.overlap, config.threshold, config.keep_equal)
    names, types = ["interval_id", "flow_key", "section", "chunk", "whole", "bits"], (pa.int32(), pa.string(), pa.int32(), pa.int32(), pa.int32(), pa.binary())

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filters: dict[int, _Filter] = {}
        maps: dict[tuple[int, str], np.ndarray] = {}

        def ready(rows):
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)], names)

        def flush():
            rows = []
            for i, f in filters.items():
                for section, chunk, bits in f.rows():
                    rows.append((i, "\0", section, chunk, layout.chunk_bytes(chunk), bits))
                    if len(rows) == 4096:
                        yield ready(rows)
                        rows = []
            for (i, key), bits in maps.items():
                rows.append((i, key, 0, 0, width, bits.tobytes()))
                if len(rows) == 4096:
                    yield ready(rows)
                    rows = []
            filters.clear()
            maps.clear()
            if rows:
                yield ready(rows)

        for batch in batches:
            interval, flows = batch.column("interval_id").to_numpy(zero_copy_only=False), batch.column("flow_key").to_pylist()
            bind = binding(flows, config)
            one = len(np.unique(interval)) == 1
            touched: list[tuple[np.ndarray, np.ndarray]] = []
            for data, at, to, row, _, _ in places(batch.column("payload").to_pylist()):
                if not len(row):
                    continue
                content, bound = block_parts(data, at, to, row, bind, config, config.flow_blocks)
                own = interval[row]
                for i in [int(own[0])] if one else np.unique(own).tolist():
                    some = slice(None) if one else own == i
                    if i not in filters:
                        filters[i] = _Filter(layout)
                    for parts in (content, bound):
                        if parts is not None:
                            for section, pos in layout.places(parts, config.k):
                                filters[i].add(section[some], pos[some])
                if config.index:
                    touched.append((row, content[0] % config.sections))
            if touched:
                row, section = (np.concatenate([x[i] for x in touched]) for i in range(2))
                who, nth = np.unique(row, return_inverse=True)
                for a in range(0, len(who), 4096):
                    held = np.zeros((min(4096, len(who) - a), width * 8), bool)
                    near = (nth >= a) & (nth < a + 4096) if len(who) > 4096 else slice(None)
                    held[nth[near] - a, section[near]] = True
                    for r, bits in zip(who[a : a + 4096].tolist(), np.packbits(held, axis=1, bitorder="little"), strict=True):
                        key = (int(interval[r]), flows[r])
                        maps[key] = maps[key] | bits if key in maps else bits
            dense = sum(f.dense is not None for f in filters.values()) * layout.sections * layout.section_bytes * 8
            if dense + len(maps) * (width + 100) > budget or sum(f.held for f in filters.values()) > HELD_PLACES:
                yield from flush()
        yield from flush()

    return kernel


def _partials(packets: DataFrame, config: DigestConfig, cut=None) -> DataFrame:
    return packets.select("interval_id", "flow_key", "payload").mapInArrow(partial_kernel(config, cut=cut), "interval_id int, flow_key string, section int, chunk int, whole int, bits binary")


def or_merged(parts: DataFrame, keys: list[str]) -> DataFrame:
    """Bits of equal keys merged by OR. Rows stream in key order, so a key of any number of parts needs one buffer. A column `whole`
    gives the bytes of the result; rows with fewer hold places."""
    from pyspark.sql import types as T

    schema = T.StructType([parts.schema[k] for k in keys] + [T.StructField("bits", T.BinaryType())])
    if "whole" not in parts.columns:
        parts = parts.withColumn("whole", F.octet_length("bits"))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, bits, out, types = None, None, [], None

        def ready(rows):
            return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate(types)], [*keys, "bits"])

        for batch in batches:
            types = [batch.schema.field(k).type for k in [*keys, "bits"]]
            columns = [batch.column(k).to_pylist() for k in keys]
            for *key, whole, raw in zip(*columns, batch.column("whole").to_pylist(), batch.column("bits").to_pylist(), strict=True):
                if len(raw) < whole:
                    own = np.zeros(whole * 8, bool)
                    own[np.frombuffer(raw, "<u2")] = True
                    own = np.packbits(own, bitorder="little")
                else:
                    own = np.frombuffer(raw, np.uint8)
                if key == now:
                    bits = bits | own
                else:
                    if now is not None:
                        out.append((*now, bits.tobytes()))
                    now, bits = key, own
                if len(out) >= 1024:
                    yield ready(out)
                    out = []
        if now is not None:
            yield ready([*out, (*now, bits.tobytes())])

    return parts.select(*keys, "whole", "bits").repartition(*keys).sortWithinPartitions(*keys).mapInArrow(kernel, schema)


#: Places of all filters that a task of `packed_filters` holds before it hands them on.
MANY_PLACES = 8_000_000


def packed_filters(packets: DataFrame, configs: list[tuple[int, DigestConfig]], cut=None, tag=None) -> DataFrame:
    """config_id, section, chunk, bits: one filter for each configuration over all intervals, from one pass that cuts and hashes each
    block once. Rows are chunks of packed bits, never words. cut: a baseline's elements; tag: the section of a block, where something
    else than the digest chooses it."""
    base = configs[0][1]
    if any((c.window, c.overlap, c.hash_family, c.salt, c.assembly) != (base.window, base.overlap, base.hash_family, base.salt, "packet") for _, c in configs):
        raise ValueError("configurations of one pass share their packets' blocks and their hashes")
    places = cut_places(cut) if cut is not None else lambda payloads: blocking.winnow_places(payloads, base.window, base.overlap)
    names, types = ["config_id", "section", "chunk", "whole", "bits"], (pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary())
    layouts, bound_too = {i: Layout.of(c) for i, c in configs}, any(c.flow_blocks for _, c in configs)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filters = {i: _Filter(layout, 0) for i, layout in layouts.items()}

        def ready(rows):
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)], names)

        def flush():
            rows = []
            for i, f in filters.items():
                for section, chunk, bits in f.rows():
                    rows.append((i, section, chunk, layouts[i].chunk_bytes(chunk), bits))
                    if len(rows) == 4096:
                        yield ready(rows)
                        rows = []
                filters[i] = _Filter(layouts[i], 0)
            if rows:
                yield ready(rows)

        for batch in batches:
            bind = binding(batch.column("flow_key").to_pylist(), base)
            for data, at, to, row, _, _ in places(batch.column("payload").to_pylist()):
                if not len(row):
                    continue
                content, bound = block_parts(data, at, to, row, bind, base, bound_too)
                tags = None if tag is None else np.array([tag(data[x:y]) for x, y in zip(at.tolist(), to.tolist(), strict=True)], np.int64)
                for i, c in configs:
                    kept = slice(None) if not c.threshold else to - at >= c.threshold if c.keep_equal else to - at > c.threshold
                    for parts in (content, bound if c.flow_blocks else None):
                        if parts is not None:
                            for section, pos in layouts[i].places(parts, c.k):
                                filters[i].add((section if tags is None else tags)[kept], pos[kept])
                if sum(f.held for f in filters.values()) > MANY_PLACES:
                    yield from flush()
        yield from flush()

    parts = packets.select("flow_key", "payload").mapInArrow(kernel, "config_id int, section int, chunk int, whole int, bits binary")
    return or_merged(parts, ["config_id", "section", "chunk"])


def packed_bitmaps(packets: DataFrame, configs: list[tuple[int, DigestConfig]]) -> DataFrame:
    """interval_id, flow_key and a bitmap b<config_id> for each configuration, from one pass that cuts and hashes each block once. Flows
    without blocks have zeros."""
    base = configs[0][1]
    if any((c.window, c.overlap, c.hash_family, c.salt, c.assembly) != (base.window, base.overlap, base.hash_family, base.salt, "packet") for _, c in configs):
        raise ValueError("configurations of one pass share their packets' blocks and their hashes")
    width = [-(-c.sections // 8) for _, c in configs]
    first = np.cumsum([0, *width]).tolist()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for a in range(0, whole.num_rows, 4096):
                batch = whole.slice(a, 4096)
                held = np.zeros((batch.num_rows, 8 * first[-1]), bool)
                for data, at, to, row, _, _ in blocking.winnow_places(batch.column("payload").to_pylist(), base.window, base.overlap):
                    if not len(row):
                        continue
                    content, _ = block_parts(data, at, to, row, None, base, False)
                    for (_, c), f in zip(configs, first, strict=False):
                        kept = slice(None) if not c.threshold else to - at >= c.threshold if c.keep_equal else to - at > c.threshold
                        held[row[kept], 8 * f + content[0][kept] % c.sections] = True
                bits = np.packbits(held, axis=1, bitorder="little")
                yield pa.RecordBatch.from_arrays([batch.column("interval_id"), batch.column("flow_key"), pa.array([b.tobytes() for b in bits], pa.binary())], ["interval_id", "flow_key", "bits"])

    parts = packets.select("interval_id", "flow_key", "payload").mapInArrow(kernel, "interval_id int, flow_key string, bits binary")
    merged = or_merged(parts, ["interval_id", "flow_key"])
    return merged.select("interval_id", "flow_key", *[F.substring("bits", f + 1, n).alias(f"b{i}") for (i, _), f, n in zip(configs, first, width, strict=False)])


def build(packets: DataFrame, config: DigestConfig, cut=None) -> Digest:
    """A digest of the packets. Without m_bits the largest interval's bytes decide it (one cheap aggregate before). cut: a
    baseline's elements instead of winnowed blocks."""
    config = config if config.m_bits and config.k != "auto" else config.sized(*largest_interval(packets, config.reduction_includes_index))
    own = prepared(packets, config)
    flows = bitindex.flow_list(packets)
    merged = or_merged(_partials(own, config, cut=cut), ["interval_id", "flow_key", "section", "chunk"])
    if not config.index:
        return Digest(config, merged.drop("flow_key"), flows, None)
    merged = merged.persist(StorageLevel.MEMORY_AND_DISK)  # read twice below, until close()
    sections = merged.filter(F.col("flow_key") == "\0").drop("flow_key")
    some = merged.filter(F.col("flow_key") != "\0").select("interval_id", "flow_key", F.col("bits").alias("bitmap"))
    zero = F.lit(bytes(-(-config.sections // 8)))
    flowbits = flows.select("interval_id", "flow_key").join(some, ["interval_id", "flow_key"], "left").withColumn("bitmap", F.coalesce("bitmap", zero))
    return Digest(config, sections, flows, flowbits, kept=(merged,))


def merge(a: Digest, b: Digest) -> Digest:
    """Digests of two places as one; refused unless they were taken alike."""
    if a.config != b.config:
        raise ValueError("digests of different configurations can't be merged")
    sections = or_merged(a.sections.unionByName(b.sections), ["interval_id", "section", "chunk"])
    flows = a.flows.unionByName(b.flows).groupBy("interval_id", "flow_key").agg(F.min("src").alias("src"), F.min("dst").alias("dst"), F.sum("packets").alias("packets"), F.sum("bytes").alias("bytes"))
    flowbits = None
    if a.flowbits is not None and b.flowbits is not None:
        both = a.flowbits.unionByName(b.flowbits).withColumnRenamed("bitmap", "bits")
        flowbits = or_merged(both, ["interval_id", "flow_key"]).withColumnRenamed("bits", "bitmap")
    return Digest(a.config, sections, flows, flowbits)


def manifest(digest: Digest) -> DataFrame:
    """interval_id, raw_bytes, flows, filter_bytes, index_bytes (before compression), and the configuration."""
    c = digest.config
    per = digest.flows.groupBy("interval_id").agg(F.sum("bytes").alias("raw_bytes"), F.count("*").alias("flows"))
    filter_bytes = F.lit(-(-c.m_bits // 8)).cast("bigint").alias("filter_bytes")
    index_bytes = (F.col("flows") * (-(-c.sections // 8) if c.index else 0)).cast("bigint").alias("index_bytes")
    return per.select("interval_id", "raw_bytes", "flows", filter_bytes, index_bytes, *[F.lit(v).alias(k) for k, v in asdict(c).items()])
