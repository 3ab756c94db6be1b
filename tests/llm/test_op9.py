import numpy as np
import pytest
from pyspark.sql import Row

from descent_planner.llm import op9_pruned_graph as op9


def exact(ids, x, k=20):
    """Brute force, as the contract says."""
    out = {}
    for i, v in zip(ids, x, strict=True):
        if i % 20 == 0:
            s = x @ v
            order = [j for j in np.lexsort((ids, -s)) if ids[j] != i][:k]
            out[i] = [(int(ids[j]), s[j]) for j in order]
    return out


def recall(rows, want):
    got = {}
    for r in rows:
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    hits = total = 0
    for q, best in want.items():
        own = sorted(got.get(q, []))
        assert [r for r, _, _ in own] == list(range(1, len(best) + 1))
        assert all(a[2] >= b[2] for a, b in zip(own, own[1:]))
        hits += len({v for _, v, _ in own} & {v for v, _ in best})
        total += len(best)
    return hits / total


def test_recall_on_the_table(spark):
    sf = "/root/testdata/sf0.1"
    rows = spark.read.parquet(f"{sf}/embeddings.parquet").orderBy("vec_id").collect()
    ids, x = np.array([r.vec_id for r in rows]), np.array([r.embedding for r in rows], dtype=np.float64)
    assert recall(op9.op9_pruned_graph(spark, sf).collect(), exact(ids, x)) >= 0.95


@pytest.mark.parametrize("scaled", [False, True])
def test_recall_over_shards_of_random_vectors(spark, tmp_path, monkeypatch, scaled):
    rng = np.random.default_rng(5)
    x = rng.normal(size=(3000, 24)).astype(np.float32)
    if scaled:
        x *= rng.uniform(0.2, 3, size=(3000, 1)).astype(np.float32)
    ids = np.arange(3000)
    spark.createDataFrame([(int(i), v.tolist(), 0) for i, v in zip(ids, x, strict=True)], "vec_id long, embedding array<float>, score int").write.parquet(f"{tmp_path}/embeddings.parquet")
    monkeypatch.setattr(op9, "SHARD_NODES", 1000)
    assert recall(op9.op9_pruned_graph(spark, str(tmp_path)).collect(), exact(ids, x.astype(np.float64))) >= 0.94


@pytest.mark.parametrize("norm", [1e4, 1e7])
def test_one_long_vector_spoils_no_shard(norm):
    rng = np.random.default_rng(7)
    x = rng.normal(size=(2000, 32))
    x /= np.linalg.norm(x, axis=1)[:, None]
    x[777] *= norm
    graph, entries = op9.build_graph(x)
    ids = np.arange(len(x))
    index = (x, x.astype(np.float32), np.zeros(len(x), dtype=np.float32), graph, entries, ids, ids + 1)
    q, vec, score = op9.search_shard(index, ids[::20], x[::20], 20)
    rows = [Row(query_id=i, rank=k % 20 + 1, vec_id=v, score=s) for k, (i, v, s) in enumerate(zip(q.tolist(), vec.tolist(), score.tolist(), strict=True))]
    assert recall(rows, exact(ids, x)) >= 0.95
    # the others keep as many neighbours as they have without it
    rest = np.delete(ids, 777)
    other, _ = op9.build_graph(x[rest])
    assert abs((graph[rest] >= 0).sum(axis=1).mean() - (other >= 0).sum(axis=1).mean()) < 2


def test_edges(spark, tmp_path):
    bad = [None, [], [0.0, 0.0], [1.0, None], [float("nan"), 1.0], [float("inf"), 1.0], [1.0, 2.0, 3.0]]
    rows = [(i, v) for i, v in enumerate(bad)] + [(i, [1.0, 1.0]) for i in range(20, 70)] + [(80, [2.0, 0.0]), (81, [0.0, 1.0])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {}
    for r in op9.op9_pruned_graph(spark, str(tmp_path)).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    assert set(got) == {20, 40, 60, 80}
    # all score 2: ties go to the smaller ids
    assert got[20] == [(i, 2.0) for i in range(21, 41)]
    assert got[60] == [(i, 2.0) for i in range(20, 40)]
    assert got[80] == [(i, 2.0) for i in range(20, 40)]
    spark.createDataFrame([], "vec_id long, embedding array<float>").write.parquet(f"{tmp_path}/e/embeddings.parquet")
    assert op9.op9_pruned_graph(spark, f"{tmp_path}/e").count() == 0
