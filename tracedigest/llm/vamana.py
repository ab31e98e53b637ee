"""Approximate nearest neighbours on robust-pruned directed graphs.

Equal vectors are one node, which keeps its smallest ids (one more than the answers asked for: no other id of that vector can be
an answer; repeated rows count once). Nodes are dealt into shards of bounded size by vector hash. Each shard's graph is grown in batches: greedy
searches from the medoid propose neighbours, relaxed distance pruning keeps the diverse ones (a candidate goes if a
kept neighbour is nearer to it by the factor `alpha` than the node itself), reverse edges are added and pruned
alike. A second pass uses the relaxed factor. Queries, in blocks, search every shard by beam; distances of what a
beam ends with are taken again in double precision, and the best of all shards are ranked.

The index is one written row per shard. A few shards meet a set of queries in one kernel call, which loads each once, searches in blocks
and hands on the best of them all. Vectors that are null, zero, of another length than most, or hold null or non-finite
components take no part; nor do rows with a null id. An id with several vectors is as near as its nearest one, as a
neighbour and as a query. An empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialize

SHARD_NODES, DEGREE, BEAM, ALPHA, BLOCK = 4_000, 32, 64, 1.2, 512
#: Queries and shards that meet in one kernel call.
CALL_QUERIES, CALL_SHARDS = 8_192, 8


def usable(rows: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    v = F.transform(F.col(vector_col), lambda x: x.cast("double"))
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    own = rows.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).filter("vec_id is not null and v is not null and size(v) > 0").filter(fine)
    return own.filter(F.exists("v", lambda x: x != 0.0))


def main_length(own: DataFrame) -> tuple[int, int]:
    """The most frequent vector length, and its rows."""
    found = own.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    return (found["d"], found["count"]) if found else (0, 0)


def squared(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a * a).sum(-1)[:, None] + (b * b).sum(-1)[None, :] - 2.0 * (a @ b.T), 0.0)


def beam_search(x: np.ndarray, graph: np.ndarray, start: int, queries: np.ndarray, beam: int, with_seen: bool = False):
    """Ids and squared distances of the beam of every query, nearest first; also whether each was expanded. graph has -1 where a
    node has fewer edges. All queries step together."""
    nq, n = len(queries), len(x)
    norms = (x * x).sum(1)
    own = (queries * queries).sum(1)
    ids = np.full((nq, beam), -1, np.int64)
    dist = np.full((nq, beam), np.inf, np.float32)
    done = np.ones((nq, beam), bool)
    seen = np.zeros((nq, n), bool)
    ids[:, 0], done[:, 0] = start, False
    dist[:, 0] = norms[start] + own - 2 * queries @ x[start]
    seen[:, start] = True
    live = np.arange(nq)
    while len(live):
        open_ = np.where(done[live], np.inf, dist[live])
        best = np.argmin(open_, axis=1)
        some = np.isfinite(open_[np.arange(len(live)), best])
        live, best = live[some], best[some]
        if not len(live):
            break
        done[live, best] = True
        near = graph[ids[live, best]]
        fresh = (near >= 0) & ~seen[live[:, None], near]
        safe = np.where(near < 0, 0, near)
        r, c = np.nonzero(fresh)
        seen[live[r], safe[r, c]] = True
        d = np.full(near.shape, np.inf, np.float32)
        d[r, c] = norms[safe[r, c]] + own[live[r]] - 2 * np.einsum("ij,ij->i", x[safe[r, c]], queries[live[r]])
        all_d = np.concatenate([dist[live], d], axis=1)
        all_i = np.concatenate([ids[live], np.where(fresh, safe, -1)], axis=1)
        all_o = np.concatenate([done[live], np.zeros_like(fresh)], axis=1)
        order = np.argsort(all_d, axis=1, kind="stable")[:, :beam]
        take = np.arange(len(live))[:, None]
        dist[live], ids[live], done[live] = all_d[take, order], all_i[take, order], all_o[take, order]
        done[live] |= ids[live] < 0
    return ids, dist


def robust_prune(x: np.ndarray, node: int, candidates: np.ndarray, alpha: float, degree: int) -> np.ndarray:
    candidates = np.unique(candidates[(candidates >= 0) & (candidates != node)])
    if not len(candidates):
        return candidates
    own = x[candidates]
    to_node = ((own - x[node]) ** 2).sum(1)
    order = np.argsort(to_node, kind="stable")
    candidates, own, to_node = candidates[order], own[order], to_node[order]
    between = squared(own, own) * (alpha * alpha)
    alive = np.ones(len(candidates), bool)
    kept = []
    for i in range(len(candidates)):
        if alive[i]:
            kept.append(i)
            if len(kept) == degree:
                break
            alive &= between[i] > to_node
    return candidates[kept]


def build(x: np.ndarray, degree: int = DEGREE, beam: int = BEAM, alpha: float = ALPHA, seed: int = 7) -> tuple[np.ndarray, int]:
    """Graph ([node, degree], -1 where there is no edge) and start node."""
    n = len(x)
    rng = np.random.default_rng(seed)
    start = int(np.argmin(((x - x.mean(0)) ** 2).sum(1)))
    graph = np.full((n, degree), -1, np.int64)
    if n > 1:
        graph[:, : min(degree, 8)] = rng.integers(0, n, (n, min(degree, 8)))
        graph[graph == np.arange(n)[:, None]] = -1
    for factor in (1.0, alpha):
        order = rng.permutation(n)
        for a in range(0, n, 256):
            batch = order[a : a + 256]
            found, _ = beam_search(x, graph, start, x[batch], beam)
            back: dict[int, list[int]] = {}
            for node, near in zip(batch.tolist(), found, strict=True):
                kept = robust_prune(x, node, np.concatenate([near, graph[node]]), factor, degree)
                graph[node] = -1
                graph[node, : len(kept)] = kept
                for k in kept.tolist():
                    back.setdefault(k, []).append(node)
            for node, more in back.items():
                own = graph[node][graph[node] >= 0]
                more = np.setdiff1d(np.array(more), own)
                if len(own) + len(more) <= degree:
                    graph[node, len(own) : len(own) + len(more)] = more
                else:
                    kept = robust_prune(x, node, np.concatenate([own, more]), factor, degree)
                    graph[node] = -1
                    graph[node, : len(kept)] = kept
    return graph, start


def distinct_vectors(own: DataFrame, dim: int, keep: int, shards: int) -> DataFrame:
    """shard, vector (bytes), ids (the smallest `keep` of them). Repeats meet within a batch first, then by vector hash."""

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            held: dict[bytes, set[int]] = {}
            values = batch.column("v").flatten().to_numpy(zero_copy_only=False).reshape(-1, dim) if batch.num_rows else np.zeros((0, dim))
            for i, v in zip(batch.column("vec_id").to_pylist(), values, strict=True):
                held.setdefault(v.tobytes(), set()).add(i)
            yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array([sorted(x)[:keep] for x in held.values()], pa.list_(pa.int64()))], ["vector", "ids"])

    merge = F.slice(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))), 1, keep)
    rows = own.mapInArrow(local, "vector binary, ids array<bigint>")
    salted = rows.groupBy("vector", F.pmod(F.element_at("ids", 1), F.lit(64)).alias("salt")).agg(merge.alias("ids"))
    return salted.groupBy("vector").agg(merge.alias("ids")).withColumn("shard", F.pmod(F.xxhash64("vector"), F.lit(shards)).cast("int"))


def index(nodes: DataFrame, dim: int, degree: int, beam: int, alpha: float) -> DataFrame:
    """One row per shard: vectors, ids, graph and start, as bytes."""

    def kernel(table: pa.Table) -> pa.Table:
        x = np.frombuffer(b"".join(table.column("vector").to_pylist()), np.float64).reshape(-1, dim)
        graph, start = build(x.astype(np.float32), degree, beam, alpha)
        ids = table.column("ids").to_pylist()
        return pa.table(
            {
                "shard": pa.array([table.column("shard")[0].as_py()], pa.int32()), "vectors": pa.array([x.tobytes()], pa.binary()), "graph": pa.array([graph.astype(np.int32).tobytes()], pa.binary()),
                "start": pa.array([start], pa.int32()), "ids": pa.array([ids], pa.list_(pa.list_(pa.int64()))),
            }
        )

    return nodes.groupBy("shard").applyInArrow(kernel, "shard int, vectors binary, graph binary, start int, ids array<array<bigint>>")


def search(shards: DataFrame, queries: DataFrame, dim: int, k: int, degree: int, beam: int, n_shards: int, call_queries: int = CALL_QUERIES, call_shards: int = CALL_SHARDS) -> DataFrame:
    """query_id, vec_id, score of the k best of each query and few shards."""
    sets, groups = -(-max(1, queries.count()) // call_queries), -(-n_shards // call_shards)
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    asked = queries.select("vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.lit(sets)).cast("int").alias("part")).withColumn("some", every(groups))
    held = shards.withColumn("some", F.floor(F.col("shard") / call_shards).cast("int")).withColumn("part", every(sets))

    def kernel(own: pa.Table, asked: pa.Table) -> pa.Table:
        ids = asked.column("vec_id").to_numpy()
        q = asked.column("v").combine_chunks().flatten().to_numpy().reshape(-1, dim) if asked.num_rows else np.zeros((0, dim))
        best: list[dict[int, float]] = [{} for _ in ids]
        for n in range(own.num_rows if len(ids) else 0):
            one = own.slice(n, 1)
            x = np.frombuffer(one.column("vectors")[0].as_py(), np.float64).reshape(-1, dim)
            graph = np.frombuffer(one.column("graph")[0].as_py(), np.int32).reshape(len(x), degree).astype(np.int64)
            names, start, small = one.column("ids")[0].as_py(), one.column("start")[0].as_py(), x.astype(np.float32)
            for a in range(0, len(ids), BLOCK):
                found, _ = beam_search(small, graph, start, q[a : a + BLOCK].astype(np.float32), max(beam, 2 * k))
                for i, near in enumerate(found, a):
                    near = near[near >= 0]
                    mine = best[i]
                    for s, node in zip(np.sqrt(((x[near] - q[i]) ** 2).sum(1)).tolist(), near.tolist(), strict=True):
                        for v in names[node]:
                            if v != ids[i]:
                                mine[v] = min(s, mine.get(v, s))
                    best[i] = {v: s for s, v in sorted((s, v) for v, s in mine.items())[:k]}
        rows = [(i, v, s) for i, own in zip(ids.tolist(), best, strict=True) for v, s in own.items()]
        return pa.table({"query_id": pa.array([r[0] for r in rows], pa.int64()), "vec_id": pa.array([r[1] for r in rows], pa.int64()), "score": pa.array([r[2] for r in rows], pa.float64())})

    return held.groupBy("part", "some").cogroup(asked.groupBy("part", "some")).applyInArrow(kernel, "query_id bigint, vec_id bigint, score double")


def nearest(rows: DataFrame, k: int = 10, query_step: int = 100, shard_nodes: int = SHARD_NODES, degree: int = DEGREE, beam: int = BEAM, alpha: float = ALPHA, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest other rows found of each row whose id is divisible by query_step."""
    own = usable(rows, id_col, vector_col)
    dim, n = main_length(own)
    if not n:
        return rows.sparkSession.createDataFrame([], "query_id bigint, rank int, vec_id bigint, score double")
    own = own.filter(F.size("v") == dim)
    n_shards = -(-n // shard_nodes)
    shards = materialize(index(distinct_vectors(own, dim, k + 1, n_shards), dim, degree, beam, alpha), "graph-shards")
    found = search(shards, own.filter(F.col("vec_id") % query_step == 0), dim, k, degree, beam, n_shards)
    best = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return found.groupBy("query_id", "vec_id").agg(F.min("score").alias("score")).withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
