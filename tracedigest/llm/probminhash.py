"""Near-duplicate classes by ProbMinHash signatures, banding and verification.

A document's weighted set is its `shingle`-word shingles, weighted 1 + ln(count), so that a line repeated a few times more moves the
similarity little, as it doesn't move the verified one (words: ASCII lower case, split at ASCII white
space; fewer words than a shingle make one shingle). Each shingle is a Poisson process with its weight as rate; its
arrivals fall on random registers, a register keeps its earliest arrival, and a shingle stops as soon as its next arrival
is later than every register's: two documents agree in a register with the probability Jaccard similarity.

1. Signatures of `bands`·`rows` registers and band hashes, row-local: of the weighted set, and of the same shingles with unit
   weights, whose similarity is the verified one however often a line is repeated. Without repeated shingles both are the same
   bands. Rows with one word sequence are one exact class, and from here on one member.
2. In each band bucket every member is paired with one leader (a star, never all pairs): the one that meets most others in its
   buckets, as the original of many copies does. Pairs whose unit-weight signatures agree too
   little for the threshold (five standard deviations) are dropped; the others are verified by the exact Jaccard similarity
   of their shingle sets, from their whole texts. Verified pairs are links, links make components.
3. Stars can miss a link between members of a bucket that both miss the leader. So in each bucket that still holds several
   components the members of different components are compared too, large buckets in blocks, and the components are made
   again. A bucket of near copies is by then one component and a few strays, so this costs the strays times the bucket.

Nulls and empty texts: no shingles; all of them form no class with others (each row is its own class). A null id is kept
as a row of its own with a null class. Repeated ids with one text are one member. Nothing is sampled or
capped, links and components stay in tables.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize, pieces, shuffle_width

SHINGLE, THRESHOLD, BANDS, ROWS = 5, 0.8, 32, 5
K1, K2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)


class Memo(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 400_000:
            self.clear()
        out = self[word] = xxhash.xxh3_64_intdigest(word)
        return out


def step(n: int) -> np.uint64:
    return np.uint64(n * int(K1) & (1 << 64) - 1)


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * K2
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "replace").lower().split()


def shingle_hashes(own: list[list[bytes]], memo: Memo, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Hash and document number of every shingle, in order."""
    n = np.array([len(w) for w in own], np.int64)
    m = np.where(n == 0, 0, np.maximum(n, k))  # short documents are padded to one shingle
    flat = np.zeros(int(m.sum()), np.uint64)
    start = np.cumsum(m) - m
    at = np.repeat(start, n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
    flat[at] = np.fromiter((memo[w] for ws in own for w in ws), np.uint64, int(n.sum()))
    size = max(0, len(flat) - k + 1)
    h = np.zeros(size, np.uint64)
    for j in range(k):
        h = h * K1 + flat[j : j + size]
    doc = np.repeat(np.arange(len(own)), m)
    whole = doc[:size] == doc[k - 1 :][:size] if size else np.zeros(0, bool)
    return mix(h[whole]), doc[:size][whole]


def weighted(h: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Different shingles of each document with their weights, 1 + ln(count)."""
    order = np.lexsort((h, doc))
    h, doc = h[order], doc[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    at = np.flatnonzero(new)
    return h[at], doc[at], 1.0 + np.log(np.diff(np.append(at, len(h))))


def signatures(h: np.ndarray, doc: np.ndarray, weight: np.ndarray, docs: int, registers: int) -> np.ndarray:
    """The shingle whose arrival is first in each register; documents without shingles have zeros."""
    first = np.full((docs, registers), np.inf)
    who = np.zeros((docs, registers), np.uint64)
    last = np.full(docs, np.inf)
    seed, when = h, np.zeros(len(h))
    rate = 1.0 / weight
    turn = 0
    while len(seed):
        turn += 1
        r = mix(seed + step(2 * turn))
        when = when - np.log(((r >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) * rate
        alive = when < last[doc]
        seed, when, rate, doc = seed[alive], when[alive], rate[alive], doc[alive]
        register = (mix(seed + step(2 * turn + 1)) >> np.uint64(32)).astype(np.int64) * registers >> 32
        flat = doc * registers + register
        better = when < first.ravel()[flat]
        at, w = flat[better], when[better]
        np.minimum.at(first.ravel(), at, w)
        won = first.ravel()[at] == w
        who.ravel()[at[won]] = seed[better][won]
        touched = np.unique(doc[better])
        last[touched] = first[touched].max(axis=1)
    return who


def band_hashes(who: np.ndarray, bands: int, rows: int) -> np.ndarray:
    out = np.zeros((len(who), bands), np.uint64)
    for j in range(rows):
        out = out * K1 + who[:, j::rows]
    return mix(out + np.arange(1, bands + 1, dtype=np.uint64) * K2)


def all_bands(h: np.ndarray, doc: np.ndarray, docs: int, bands: int, rows: int) -> tuple[np.ndarray, list[np.ndarray]]:
    """Unit-weight signatures, and each document's band hashes: `bands` of them, or twice as many (unit weights, then weighted) where
    a shingle is repeated."""
    h, doc, weight = weighted(h, doc)
    unit = signatures(h, doc, np.ones(len(h)), docs, bands * rows)
    keys = list(band_hashes(unit, bands, rows).view(np.int64))
    again = np.unique(doc[weight > 1.0])
    if len(again):
        some = np.isin(doc, again)
        more = signatures(h[some], np.searchsorted(again, doc[some]), weight[some], len(again), bands * rows)
        for i, own in zip(again.tolist(), band_hashes(more, bands, rows).view(np.int64), strict=True):
            keys[i] = np.concatenate([keys[i], own])
    return unit, keys


def signed(docs: DataFrame, bands: int, rows: int) -> DataFrame:
    """doc_id, s1, s2 (hash of the word sequence; null without words), sig (a byte per register, unit weights), keys (band hashes) of
    every row of (doc_id, text). Row-local."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo = Memo()
        for batch in batches:
            for part in pieces(batch):
                own = [words(t) for t in part.column("text").to_pylist()]
                same = [xxhash.xxh3_128_digest(b" ".join(w)) if w else None for w in own]
                who, keys = all_bands(*shingle_hashes(own, memo), len(own), bands, rows)
                sig = (who >> np.uint64(24)).astype(np.uint8)
                s1, s2 = ([x and int.from_bytes(x[i : i + 8], "little", signed=True) for x in same] for i in (0, 8))
                some = [w is not None for w in same]
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(s1, pa.int64()), pa.array(s2, pa.int64()), pa.array([s.tobytes() if k else None for s, k in zip(sig, some, strict=True)], pa.binary()), pa.array([s if k else None for s, k in zip(keys, some, strict=True)], pa.list_(pa.int64()))],
                    ["doc_id", "s1", "s2", "sig", "keys"],
                )

    return docs.mapInArrow(kernel, "doc_id bigint, s1 bigint, s2 bigint, sig binary, keys array<bigint>")


def agreement(registers: int, threshold: float) -> float:
    """Registers that agree at least, but for a chance of one in millions, in a pair at the threshold."""
    return registers * (threshold - 5 * (threshold * (1 - threshold) / registers) ** 0.5)


def agreeing(pairs: DataFrame, registers: int, threshold: float) -> DataFrame:
    """Pairs whose signatures (sa, sb) agree as often as the threshold asks for, less five standard deviations."""
    least = agreement(registers, threshold)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8).reshape(-1, registers) for c in ("sa", "sb"))
            keep = pa.array((a == b).sum(axis=1) >= least) if batch.num_rows else pa.array([], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column("a").filter(keep), batch.column("b").filter(keep)], ["a", "b"])

    return pairs.mapInArrow(kernel, "a bigint, b bigint")


def verified(pairs: DataFrame, texts: DataFrame, threshold: float) -> DataFrame:
    """Pairs (a, b) with the Jaccard similarity of their shingle sets, from whole texts, at or over the threshold."""
    left = texts.select(F.col("rep").alias("a"), F.col("text").alias("ta"))
    right = texts.select(F.col("rep").alias("b"), F.col("text").alias("tb"))
    both = pairs.join(left, "a").join(right, "b").select("a", "b", "ta", "tb")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        memo, sets = Memo(), {}

        def of(i: int, text: str) -> np.ndarray:
            if i not in sets:
                if len(sets) > 64:
                    sets.clear()
                sets[i] = np.unique(shingle_hashes([words(text)], memo)[0])
            return sets[i]

        for batch in batches:
            out = []
            for a, b, ta, tb in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), batch.column("ta"), batch.column("tb"), strict=True):
                x, y = of(a, ta.as_py() if a not in sets else ""), of(b, tb.as_py() if b not in sets else "")
                both = len(np.intersect1d(x, y, assume_unique=True))
                out.append(both / max(1, len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(out, pa.float64())], ["a", "b", "jaccard"])

    return both.mapInArrow(kernel, "a bigint, b bigint, jaccard double").filter(F.col("jaccard") >= threshold - 1e-12)


def components(links: DataFrame, nodes: DataFrame) -> DataFrame:
    """node, root: the smallest id of each node's component. Least-label steps with pointer jumping, each written and
    reread; stars end in two or three."""
    edges = links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    labels = nodes.select("node", F.col("node").alias("root"))
    while True:
        heard = edges.join(labels.withColumnsRenamed({"node": "b", "root": "heard"}), "b").groupBy("a").agg(F.min("heard").alias("heard"))
        near = labels.join(heard, labels["node"] == heard["a"], "left").select("node", F.least("root", F.coalesce("heard", "root")).alias("root"), F.col("root").alias("was"))
        jump = near.select(F.col("node").alias("j_node"), F.col("root").alias("j_root"))
        moved = materialize(near.join(jump, near["root"] == jump["j_node"]).select("node", F.least("root", "j_root").alias("root"), "was"), "labels")
        labels = moved.select("node", "root")
        if moved.filter("root <> was").isEmpty():
            return labels


def dedup(docs: DataFrame, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, s1, s2 (hash of the word sequence), class_id (smallest id of the class; its own id for a row without words, null for
    a null id) of every row."""
    own = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    every = materialize(signed(own, bands, rows), "signatures")
    exact = every.filter("s1 is not null and doc_id is not null").groupBy("s1", "s2").agg(F.min("doc_id").alias("rep"))
    sigs = every.alias("k").join(exact.alias("e"), F.expr("k.s1 = e.s1 and k.s2 = e.s2 and k.doc_id = e.rep")).select("e.rep", "k.s1", "k.s2", "k.sig", "k.keys").dropDuplicates(["rep", "s1", "s2"])
    # an id may stand for several texts: the class's number is its word sequence's hash
    sigs = materialize(sigs.select(F.col("s1").alias("rep"), "sig", "keys"), "representatives")

    band = sigs.select("rep", F.explode(F.array_distinct("keys")).alias("key"))
    sizes = band.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    shared = materialize(band.join(sizes, "key").select("key", "rep", "n"), "shared-bands")
    known = shared.groupBy("rep").agg(F.sum("n").alias("known"))
    leaders = shared.join(known, "rep").groupBy("key").agg(F.max(F.struct("known", "rep")).alias("x")).select("key", F.col("x.rep").alias("leader"))
    buckets = materialize(shared.join(leaders, "key").select("key", "rep", "leader", "n"), "buckets")
    nodes = materialize(buckets.select(F.col("rep").alias("node")).distinct(), "nodes")
    texts = node_texts(own, every, nodes)
    registers = bands * rows
    pairs = buckets.filter("rep <> leader").select(F.least("leader", "rep").alias("a"), F.greatest("leader", "rep").alias("b")).distinct()
    links = compare(pairs, sigs, texts, registers, threshold)
    labels = components(links, nodes)
    few, many = crossing(buckets, sigs, texts, labels, registers, threshold)
    more = materialize(compare(few, sigs, texts, registers, threshold).unionByName(many).distinct(), "more-links")
    if not more.isEmpty():
        labels = components(links.unionByName(more), nodes)

    named = exact.join(labels, exact["s1"] == labels["node"], "left").select("s1", "s2", "rep", F.coalesce("root", "s1").alias("root"))
    least = named.groupBy("root").agg(F.min("rep").alias("class_id"))
    classes = named.join(least, "root").select("s1", "s2", "class_id")
    slim = every.select("doc_id", "s1", "s2")
    found = slim.alias("m").join(classes.alias("c"), F.expr("m.s1 = c.s1 and m.s2 = c.s2 and m.doc_id is not null"), "left")
    return found.select("m.doc_id", "m.s1", "m.s2", F.coalesce("class_id", "doc_id").alias("class_id"))


def node_texts(own: DataFrame, every: DataFrame, nodes: DataFrame, most: int = 2_000_000) -> DataFrame:
    """(rep, text) of the nodes. One row's id stands for each; the ids meet the texts by broadcast up to `most` of them."""
    ids = every.filter("doc_id is not null").join(nodes, every["s1"] == nodes["node"]).groupBy("node").agg(F.min(F.struct("doc_id", "s2")).alias("x")).select(F.col("x.doc_id").alias("doc_id"), "node")
    ids = materialize(ids, "node-ids")
    side = F.broadcast(ids) if ids.count() <= most else ids
    rows = own.join(side, "doc_id").select("node", "text")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Only the text whose hash it is: an id may have several."""
        for batch in batches:
            keep = []
            for node, text in zip(batch.column("node").to_pylist(), batch.column("text").to_pylist(), strict=True):
                own = words(text)
                keep.append(bool(own) and int.from_bytes(xxhash.xxh3_128_digest(b" ".join(own))[:8], "little", signed=True) == node)
            yield batch.filter(pa.array(keep, pa.bool_()))

    return materialize(rows.mapInArrow(kernel, "node bigint, text string").dropDuplicates(["node"]).select(F.col("node").alias("rep"), "text"), "node-texts")


def compare(pairs: DataFrame, sigs: DataFrame, texts: DataFrame, registers: int, threshold: float) -> DataFrame:
    """Links among the pairs, written out: signatures first, then whole texts."""
    sa = sigs.select(F.col("rep").alias("a"), F.col("sig").alias("sa"))
    sb = sigs.select(F.col("rep").alias("b"), F.col("sig").alias("sb"))
    likely = materialize(agreeing(pairs.join(sa, "a").join(sb, "b").select("a", "b", "sa", "sb"), registers, threshold), "likely")
    return materialize(verified(likely, texts, threshold).select("a", "b"), "links")


def crossing(buckets: DataFrame, sigs: DataFrame, texts: DataFrame, labels: DataFrame, registers: int, threshold: float, small: int = 32, block: int = 256) -> tuple[DataFrame, DataFrame]:
    """What the stars left open: pairs of one bucket and different components. Members outside the bucket's largest component meet
    all others, so a bucket that is one component and a few strays costs its size times the strays.

    Pairs to compare of buckets with up to `small` members, and links of larger ones. There, blocks of strays meet blocks
    of members in a kernel with their texts, which emits links only; a pair is looked at just in the first band that it shares."""
    held = buckets.join(labels, buckets["rep"] == labels["node"]).select("key", "rep", "root", "leader")
    parts = held.groupBy("key", "root").agg(F.count("*").alias("k"))
    several = parts.groupBy("key").agg(F.count("*").alias("roots"), F.max_by("root", "k").alias("main"), F.sum("k").alias("m"), F.max("k").alias("most")).filter("roots > 1 and m > 2")
    open_ = materialize(held.join(several.select("key", "main", "m", (F.col("m") - F.col("most")).alias("s")), "key"), "open-buckets")

    few = open_.filter(F.col("m") <= small).groupBy("key").agg(F.first("leader").alias("leader"), F.collect_list(F.struct("rep", "root")).alias("x"))
    pairs = few.select("leader", F.explode("x").alias("p"), "x").select("leader", "p", F.explode("x").alias("q")).filter("p.rep < q.rep and p.root <> q.root and p.rep <> leader and q.rep <> leader")
    pairs = pairs.select(F.col("p.rep").alias("a"), F.col("q.rep").alias("b")).distinct()

    many = open_.filter(F.col("m") > small).withColumns({"mb": F.ceil(F.col("m") / block).cast("int"), "sb": F.ceil(F.col("s") / block).cast("int")})
    own = many.join(sigs.select("rep", "sig", "keys"), "rep").join(texts, "rep")
    columns = ["key", "i", "j", "rep", "root", "stray", "sig", "keys", "text"]
    left = own.filter("root <> main").withColumns({"i": F.pmod(F.xxhash64("rep"), F.col("sb")).cast("int"), "stray": F.lit(True)}).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("mb") - 1)))
    right = own.withColumns({"j": F.pmod(F.xxhash64("rep"), F.col("mb")).cast("int"), "stray": F.lit(False)}).withColumn("i", F.explode(F.sequence(F.lit(0), F.col("sb") - 1)))
    least = agreement(registers, threshold)

    def block_links(table: pa.Table) -> pa.Table:
        key, stray = table.column("key")[0].as_py(), np.asarray(table.column("stray"))
        rep, root = (np.asarray(table.column(c)) for c in ("rep", "root"))
        sig = np.frombuffer(b"".join(table.column("sig").to_pylist()), np.uint8).reshape(-1, registers)
        keys = table.column("keys").to_pylist()
        widest = max(map(len, keys))
        keys = np.array([k * (widest // len(k)) for k in keys], np.int64)  # without repeats, weighted bands are those of unit weights
        memo, texts = Memo(), table.column("text")
        members, sets = np.flatnonzero(~stray), {}

        def of(i: int) -> np.ndarray:
            if i not in sets:
                sets[i] = np.unique(shingle_hashes([words(texts[i].as_py())], memo)[0])
            return sets[i]

        out: list[tuple[int, int]] = []
        for i in np.flatnonzero(stray).tolist():
            near = members[((sig[members] == sig[i]).sum(axis=1) >= least) & (root[members] != root[i])]
            same = keys[near] == keys[i]
            # a pair may also meet by a weighted band of one and a unit band of the other
            near = near[(keys[near, same.argmax(axis=1)] == key) | ~same.any(axis=1)] if len(near) else near
            if not len(near):
                continue
            x, each = of(i), [of(j) for j in near.tolist()]
            size = np.array([len(y) for y in each])
            flat = np.concatenate(each)
            hit = x[np.minimum(np.searchsorted(x, flat), len(x) - 1)] == flat
            both = np.add.reduceat(hit, np.cumsum(size) - size)
            fine = near[both / (len(x) + size - both) >= threshold - 1e-12]
            out += [(min(int(rep[i]), r), max(int(rep[i]), r)) for r in rep[fine].tolist()]
        found = np.array(sorted(set(out)), np.int64).reshape(-1, 2)
        return pa.table({"a": found[:, 0], "b": found[:, 1]})

    links = left.select(*columns).unionByName(right.select(*columns)).groupBy("key", "i", "j").applyInArrow(block_links, "a bigint, b bigint")
    return pairs, links


def keep_one(docs: DataFrame, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The documents' own columns, one row of each class: the one with the smallest id (of rows alike in id and words, any
    one). Rows without words or with a null id stay."""
    found = dedup(docs, threshold, id_col=id_col, text_col=text_col).filter("s1 is not null and doc_id is not null")
    gone = found.filter("doc_id <> class_id").select("doc_id").distinct()
    again = found.filter("doc_id = class_id").groupBy("doc_id").agg(F.count("*").alias("n")).filter("n > 1").select("doc_id")
    check = materialize(gone.withColumn("again", F.lit(False)).unionByName(again.withColumn("again", F.lit(True))).groupBy("doc_id").agg(F.max("again").alias("again")), "dropped-ids")
    columns = docs.columns
    rows = docs.select(F.struct(*[F.col(c) for c in columns]).alias("row"), F.col(id_col).cast("long").alias("d"))
    out = rows.join(check, rows["d"] == check["doc_id"], "left_anti").select("row.*")
    if check.filter("again").isEmpty():
        return out
    # ids that more than one row carries: decided by their words, one row for each class
    kept = found.filter("doc_id = class_id").join(check.filter("again"), "doc_id").select("doc_id", "s1", "s2").distinct()
    twice = materialize(rows.join(check.filter("again"), rows["d"] == check["doc_id"]).select("row", "d", F.col(f"row.`{text_col}`").alias("text")), "repeated-ids")
    keyed = twice.withColumn("n", F.monotonically_increasing_id())
    keyed = materialize(keyed, "repeated-rows")
    hashes = signed(keyed.select(F.col("n").alias("doc_id"), "text"), 1, 1).select(F.col("doc_id").alias("n"), "s1", "s2")
    named = keyed.join(hashes, "n").join(kept, (F.col("d") == kept["doc_id"]) & (hashes["s1"] == kept["s1"]) & (hashes["s2"] == kept["s2"]), "left").select("n", "d", hashes["s1"], hashes["s2"], kept["doc_id"].isNotNull().alias("stays"))
    first = named.filter("stays").groupBy("d").agg(F.min("n").alias("n")).select("n").union(named.filter("s1 is null").select("n"))
    return out.unionByName(keyed.join(first, "n").select("row.*"))
