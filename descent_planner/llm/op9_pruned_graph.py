"""Nearest neighbours by inner product over robust-pruned directed graphs, one a shard.

Equal vectors are one node with its smallest ids. Nodes are dealt into shards by a hash.
Largest inner product becomes least distance by one more coordinate that gives all nodes of a shard the same
length; graphs are built in double precision. A shard's graph grows in batches that double: a beam search over the graph so far proposes neighbours of
each new node; robust pruning keeps the nearest candidate and drops those that are nearer to it, by the factor
``RELAX``, than to the node, up to ``DEGREE`` times; edges are answered by reverse edges, and nodes of too many are
pruned again. Searches of a batch run side by side as array operations.

Queries are gathered in blocks of ``BLOCK``, and every block meets the index of every shard by an equi-join, so that an
index moves once for that many queries; each shard is beam-searched, scores are taken anew in double precision from
the original vectors, and the best of all shards are the answer.

Vectors that are null, zero, or hold null or non-finite components take no part; vectors of other lengths are
indexed apart. Repeated ids are one row each. Ties go to the smaller id.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .shared import over_batches, saved

#: Nodes of a shard at least, while there are ``SHARDS`` at most; then shards grow until one's vectors hold
#: ``SHARD_BYTES``, and only then there are more: a search costs little more in a larger shard, but once for each shard.
SHARD_NODES, SHARDS, SHARD_BYTES = 4_000, 64, 32 << 20
DEGREE = 32
BEAM = 64
QUERY_BEAM = 160
RELAX = 1.2
#: Queries that travel together, and that one search handles side by side.
BLOCK, SIDE_BY_SIDE = 1_024, 256
#: Neighbour lists that one step of a search opens.
OPEN = 4


def beam_search(v: np.ndarray, half: np.ndarray, graph: np.ndarray, entries: np.ndarray, q: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
    """The nearest nodes found for each query (-1 fills up), nearest first, and their half[i] - v[i].q.

    Each step opens a query's nearest unopened nodes and merges their neighbours into its beam.
    """
    b, n, e = len(q), len(v), len(entries)
    ids = np.full((b, beam), -1, dtype=np.int64)
    dist = np.full((b, beam), np.inf, dtype=v.dtype)
    opened = np.zeros((b, beam), dtype=bool)
    seen = np.zeros((b, n + 1), dtype=bool)
    seen[:, n] = True  # stands for no node
    first = np.argsort(d := half[entries] - q @ v[entries].T, axis=1, kind="stable")[:, :beam]
    ids[:, : min(e, beam)] = entries[first]
    dist[:, : min(e, beam)] = np.take_along_axis(d, first, axis=1)
    seen[:, entries] = True
    live = np.arange(b)
    while len(live):
        shut = ~opened[live] & (ids[live] >= 0)
        some = shut.any(axis=1)
        live, shut = live[some], shut[some]
        if not len(live):
            break
        rank = np.cumsum(shut, axis=1)
        take = shut & (rank <= OPEN)
        opened[live] |= take
        row, col = np.nonzero(take)
        near = np.full((len(live), OPEN, graph.shape[1]), n, dtype=np.int64)
        near[row, rank[row, col] - 1] = graph[ids[live[row], col]]
        near = near.reshape(len(live), -1)
        near[near < 0] = n
        near[seen[live[:, None], near]] = n
        near.sort(axis=1)
        near[:, 1:][near[:, 1:] == near[:, :-1]] = n
        row, col = np.nonzero(near < n)
        node = near[row, col]
        seen[live[row], node] = True
        d = np.full(near.shape, np.inf, dtype=v.dtype)
        d[row, col] = half[node] - np.einsum("ij,ij->i", v[node], q[live[row]])
        near[near == n] = -1
        all_d = np.concatenate([dist[live], d], axis=1)
        best = np.argsort(all_d, axis=1, kind="stable")[:, :beam]
        ids[live] = np.take_along_axis(np.concatenate([ids[live], near], axis=1), best, axis=1)
        dist[live] = np.take_along_axis(all_d, best, axis=1)
        opened[live] = np.take_along_axis(np.concatenate([opened[live], np.zeros(near.shape, dtype=bool)], axis=1), best, axis=1)
    return ids, dist


def robust_prune(v: np.ndarray, nodes: np.ndarray, candidates: np.ndarray, degree: int, relax: float) -> np.ndarray:
    """Diverse neighbours of each node among its row of candidates (-1 fills up)."""
    out = np.full((len(nodes), degree), -1, dtype=np.int64)
    for at in range(0, len(nodes), 128):
        own, cand = nodes[at : at + 128], np.sort(candidates[at : at + 128], axis=1)
        cand[:, 1:][cand[:, 1:] == cand[:, :-1]] = -1
        cand[cand == own[:, None]] = -1
        alive = cand >= 0
        x = v[np.maximum(cand, 0)]
        d = ((x - v[own][:, None]) ** 2).sum(axis=2)
        sq = (x * x).sum(axis=2)
        rows = np.arange(len(own))
        for k in range(degree):
            best = np.where(alive, d, np.inf).argmin(axis=1)
            ok = alive[rows, best]
            if not ok.any():
                break
            out[at + rows[ok], k] = cand[rows[ok], best[ok]]
            chosen = x[rows, best]
            between = sq + sq[rows, best][:, None] - 2 * np.einsum("ijk,ik->ij", x, chosen)
            alive &= ~(ok[:, None] & (relax * relax * between <= d))
            alive[rows, best] = False
    return out


def build_graph(vectors: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(neighbours of each node, entry nodes) over vectors whose inner product is to be large."""
    n = len(vectors)
    sq = (vectors.astype(np.float64) ** 2).sum(axis=1)
    # the further coordinate is measured from that of the shortest vector, which leaves distances as they are: one
    # long vector then doesn't swamp the products of the short ones
    further = np.sqrt(np.maximum(sq.max() - sq, 0))
    lift = (sq - sq.min()) / np.maximum(further + further.max(), np.finfo(np.float64).tiny)
    v = np.concatenate([vectors.astype(np.float64), lift[:, None]], axis=1)
    half = (v * v).sum(axis=1) / 2
    graph = np.full((n, DEGREE), -1, dtype=np.int64)
    # in hashed order, so that the input's order doesn't shape the graph; the first few are all entries
    order = np.argsort((np.arange(n, dtype=np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15), kind="stable")
    entries = np.sort(order[: min(n, 8)])
    done = min(n, 64)
    start = order[:done]
    graph[start] = robust_prune(v, start, np.broadcast_to(start, (done, done)).copy(), DEGREE, RELAX)
    while done < n:
        size = min(n - done, max(64, done // 2))
        new = order[done : done + size]
        found = np.full((size, BEAM), -1, dtype=np.int64)
        for at in range(0, size, SIDE_BY_SIDE):
            found[at : at + SIDE_BY_SIDE], _ = beam_search(v, half, graph, entries, v[new[at : at + SIDE_BY_SIDE]], BEAM)
        graph[new] = robust_prune(v, new, found, DEGREE, RELAX)
        # reverse edges
        src = np.repeat(new, DEGREE)
        dst = graph[new].reshape(-1)
        src, dst = src[dst >= 0], dst[dst >= 0]
        by = np.argsort(dst, kind="stable")
        src, dst = src[by], dst[by]
        touched, at, count = np.unique(dst, return_index=True, return_counts=True)
        wide = np.full((len(touched), DEGREE + int(count.max())), -1, dtype=np.int64)
        wide[:, :DEGREE] = graph[touched]
        row = np.repeat(np.arange(len(touched)), count)
        wide[row, DEGREE + np.arange(len(dst)) - np.repeat(at, count)] = src
        graph[touched] = robust_prune(v, touched, wide, DEGREE, RELAX)
        done += size
    return graph, entries


def usable(rows: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, v) of the rows that take part; v is array<double>."""
    v = F.col(vector_col).cast("array<double>")
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists("v", lambda x: x != 0)
    return rows.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & F.col("v").isNotNull()).where(fine)


def build_index(rows: DataFrame, k: int, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """A row a shard: (dim, shard, vectors, graph, entries, ids, id_ends); a node keeps its k + 1 smallest ids."""
    mine = usable(rows, id_col, vector_col)
    first = Window.partitionBy("v").orderBy("vec_id")
    nodes = mine.withColumn("n", F.row_number().over(first)).where(F.col("n") <= k + 1).groupBy("v").agg(F.sort_array(F.collect_list("vec_id")).alias("ids"))
    nodes = saved(nodes, "graph-nodes")
    count, width = nodes.agg(F.count("*"), F.coalesce(F.max(F.size("v")), F.lit(1))).first()
    shards = max(1, min(round(count / SHARD_NODES), SHARDS), -(-count // max(1, SHARD_BYTES // (8 * width))))
    dealt = nodes.select(F.size("v").alias("dim"), F.pmod(F.xxhash64("v"), F.lit(shards)).cast("int").alias("shard"), "v", "ids").repartition("dim", "shard").sortWithinPartitions("dim", "shard", F.element_at("ids", 1))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        key = None

        def flush() -> pa.RecordBatch:
            vectors = np.array([x for x, _ in held], dtype=np.float64)
            graph, entries = build_graph(vectors)
            ids = np.array([i for _, own in held for i in own], dtype=np.int64)
            ends = np.cumsum([len(own) for _, own in held])
            packed = [x.tobytes() for x in (vectors, graph.astype(np.int32), entries.astype(np.int64), ids, ends.astype(np.int64))]
            return pa.RecordBatch.from_arrays([pa.array([key[0]], pa.int32()), pa.array([key[1]], pa.int32()), *(pa.array([x], pa.binary()) for x in packed)], ["dim", "shard", "vectors", "graph", "entries", "ids", "id_ends"])

        for b in batches:
            for dim, shard, v, ids in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                if (dim, shard) != key and held:
                    yield flush()
                    held.clear()
                key = (dim, shard)
                held.append((v, ids))
        if held:
            yield flush()

    return saved(dealt.mapInArrow(run, "dim int, shard int, vectors binary, graph binary, entries binary, ids binary, id_ends binary"), "graph-index")


@lru_cache(maxsize=1)
def _unpacked(dim: int, vectors: bytes, graph: bytes, entries: bytes, ids: bytes, ends: bytes) -> tuple:
    x = np.frombuffer(vectors, dtype=np.float64).reshape(-1, dim)
    return x, x.astype(np.float32), np.zeros(len(x), dtype=np.float32), np.frombuffer(graph, dtype=np.int32).reshape(len(x), -1).astype(np.int64), np.frombuffer(entries, dtype=np.int64), np.frombuffer(ids, dtype=np.int64), np.frombuffer(ends, dtype=np.int64)


def search_shard(index: tuple, query_ids: np.ndarray, q: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query, vec_id, score) of the k best of a shard for each query, its own id left out."""
    x, narrow, zero, graph, entries, ids, ends = index
    small = q.astype(np.float32)
    found = np.concatenate([beam_search(narrow, zero, graph, entries, small[at : at + SIDE_BY_SIDE], max(QUERY_BEAM, 2 * k))[0] for at in range(0, len(q), SIDE_BY_SIDE)])
    row, col = np.nonzero(found >= 0)
    node = found[row, col]
    score = np.einsum("ij,ij->i", x[node], q[row])
    size = ends - np.concatenate([[0], ends[:-1]])
    own = size[node]
    at = np.repeat(ends[node] - own, own) + np.arange(int(own.sum())) - np.repeat(np.cumsum(own) - own, own)
    row, score, vec = np.repeat(row, own), np.repeat(score, own), ids[at]
    other = vec != query_ids[row]
    row, score, vec = row[other], score[other], vec[other]
    order = np.lexsort((vec, -score, row))
    row, score, vec = row[order], score[order], vec[order]
    place = np.arange(len(row)) - np.searchsorted(row, row)
    best = place < k
    return query_ids[row[best]], vec[best], score[best]


def search(index: DataFrame, queries: DataFrame, k: int, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score) of the k nearest of each query."""

    def block(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list] = {}
        for b in batches:
            for i, v in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                own = held.setdefault(len(v), [])
                own.append((i, v))
                if len(own) == BLOCK:
                    yield _block(own)
                    own.clear()
        for own in held.values():
            if own:
                yield _block(own)

    asked = usable(queries, id_col, vector_col)
    # tasks of a block each, whatever the files: part-filled blocks would send the indexes more often
    blocks = asked.repartition(max(1, -(-asked.count() // BLOCK)), "vec_id").mapInArrow(block, "dim int, query_ids binary, q binary")
    # every block goes to each shard of its dimension; shards is a row a shard, without the index itself
    shards = index.groupBy("dim").agg(F.collect_set("shard").alias("shards"))
    sent = blocks.join(F.broadcast(shards), "dim").select("dim", F.explode("shards").alias("shard"), "query_ids", "q")

    def make():
        def each(b: pa.RecordBatch) -> pa.RecordBatch | None:
            out = []
            for i in range(b.num_rows):
                dim, query_ids, q, *packed = (b.column(j)[i].as_py() for j in range(b.num_columns))
                q = np.frombuffer(q, dtype=np.float64).reshape(-1, dim)
                out.append(search_shard(_unpacked(dim, *packed), np.frombuffer(query_ids, dtype=np.int64), q, k))
            return pa.RecordBatch.from_arrays([pa.array(np.concatenate([x[j] for x in out])) for j in range(3)], ["query_id", "vec_id", "score"])

        return each

    met = sent.join(index.hint("merge"), ["dim", "shard"]).select("dim", "query_ids", "q", "vectors", "graph", "entries", "ids", "id_ends")
    found = over_batches(met, make, "query_id long, vec_id long, score double")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def _block(own: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([len(own[0][1])], pa.int32()), pa.array([np.array([i for i, _ in own], dtype=np.int64).tobytes()], pa.binary()), pa.array([np.array([v for _, v in own], dtype=np.float64).tobytes()], pa.binary())], ["dim", "query_ids", "q"])


def op9_pruned_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return search(build_index(rows, 20), rows.where(F.col("vec_id") % 20 == 0), 20)


QUERIES = {"op9_pruned_graph": op9_pruned_graph}
ORACLES: dict[str, str] = {}
