import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from descent_planner.llm import op7_near_duplicates as op7

from . import edge


def sets_of(text, size):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if len(words) < size:
        return frozenset([tuple(words)]) if words else frozenset()
    return frozenset(tuple(words[i : i + size]) for i in range(len(words) - size + 1))


def brute(rows, p):
    """Every pair compared."""
    sets = {i: sets_of(t, p.shingle) for i, t in rows}
    parent = {i: i for i in sets}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and min(len(x), len(y)) * p.den >= p.num * max(len(x), len(y)):
                n = len(x & y)
                if p.den * n >= p.num * (len(x) + len(y) - n):
                    ra, rb = sorted((root(a), root(b)))
                    parent[rb] = ra
    return sorted((i, len(sets[i]), root(i), root(i) == i) for i in ids)


def families(seed, n=60):
    """Chains of small edits, so that ends of a family are linked only through others."""
    rng = random.Random(seed)
    rows = []
    for f in range(n // 10):
        words = [f"w{rng.randint(0, 400)}" for _ in range(rng.choice([2, 8, 60, 150]))]
        for _ in range(10):
            words = list(words)
            if rng.random() < 0.7:
                words[rng.randrange(len(words))] = f"x{rng.randint(0, 9)}"
            rows.append((rng.randrange(10**6), " ".join(words)))
    return list(dict(rows).items())


@pytest.mark.parametrize("case", ["edges", "families", "table"])
def test_op7_equals_all_pairs(spark, sf, tmp_path, case):
    if case == "table":
        folder = sf
    else:
        folder = edge.tables(spark, tmp_path)
        if case == "families":
            spark.createDataFrame(families(1), "doc_id long, text string").write.mode("overwrite").parquet(f"{folder}/documents.parquet")
    rows = spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text").collect()
    assert sorted(map(tuple, op7.op7_near_duplicates(spark, folder).collect())) == brute(rows, op7.CONTRACT)


def test_rows_of_one_id_are_one_document(spark):
    rows = [(5, "a b c d"), (3, "x y z w"), (5, "x y z w"), (None, "x y z w"), (None, "lonely words"), (9, "a b c d"), (7, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r.doc_id or -1, r.component_id or -1, r.kept) for r in op7.near_duplicates(docs, op7.CONTRACT).collect())
    assert got == [(-1, -1, True), (-1, 3, True), (3, 3, True), (5, 3, False), (5, 3, False), (7, 7, True), (9, 3, False)]
    left = sorted((r.doc_id or -1, r.text or "") for r in op7.drop_near_duplicates(docs, op7.CONTRACT).collect())
    assert left == [(-1, "lonely words"), (-1, "x y z w"), (3, "x y z w"), (7, "")]


def test_many_short_and_one_very_long_text(spark):
    short = spark.range(100_000).select("id", F.concat(F.lit("w"), F.col("id") % 90_000, F.lit(" x y z")).alias("text"))
    long = spark.range(2).select((F.col("id") + 200_000).alias("id"), F.array_join(F.transform(F.sequence(F.lit(1), F.lit(2_800_000)), lambda i: F.concat(F.lit("w"), (i.cast("long") * 7919) % 1000003)), " ").alias("text"))
    docs = short.union(long).select(F.col("id").alias("doc_id"), "text")
    got = op7.near_duplicates(docs, op7.CONTRACT).groupBy((F.col("doc_id") >= 200_000).alias("long")).agg(F.count("*").alias("n"), F.sum(F.col("kept").cast("int")).alias("kept"), F.max("n_shingles").alias("most"))
    assert {(r.long, r.n, r.kept) for r in got.collect()} == {(False, 100_000, 90_000), (True, 2, 1)}


@pytest.mark.parametrize("size", [1, 3, 5])
def test_windows_give_the_same_set(size, monkeypatch):
    rng = random.Random(size)
    text = " ".join("Ab" * rng.randint(1, 9) for _ in range(3000)) + "\n\t  end " + "z" * 700
    want = op7.shingle_sets([text], size)
    monkeypatch.setattr(op7, "PIECE_BYTES", 500)
    for texts in ([text], [None, text, "a b"]):
        elements, n = op7.shingle_sets(texts, size)
        at = 0 if len(texts) == 1 else int(n[0])
        own = elements[at : at + n[texts.index(text)]]
        assert (own == want[0]).all() and len(own) == want[1][0] == len(sets_of(text, size))


def test_op7_empty(spark, tmp_path):
    assert op7.op7_near_duplicates(spark, edge.tables(spark, tmp_path, [])).count() == 0


def test_shuffled_candidates_give_the_same(spark, monkeypatch):
    docs = spark.createDataFrame(families(2), "doc_id long, text string")
    want = sorted(map(tuple, op7.near_duplicates(docs, op7.CORPUS).collect()))
    assert want == brute(families(2), op7.CORPUS)
    monkeypatch.setattr(op7, "BROADCAST_ROWS", -1)
    assert sorted(map(tuple, op7.near_duplicates(docs, op7.CORPUS).collect())) == want
    kept = {r.doc_id for r in op7.drop_near_duplicates(docs).collect()}
    assert kept == {i for i, _, _, k in want if k}


@pytest.mark.parametrize("size", [1, 3, 40, 3000])
def test_sketches_estimate_similarity(size):
    rng = np.random.default_rng(size)
    t = 256
    both = rng.integers(0, 1 << 63, 2 * size).astype(np.uint64)
    for share in (0.5, 0.9):
        cut = int(size * (1 - share) / (1 + share))
        a, b = both[:size], np.concatenate([both[cut:size], both[size : size + cut]])
        true = len(set(a.tolist()) & set(b.tolist())) / len(set(a.tolist()) | set(b.tolist()))
        s = op7.sketches(np.concatenate([np.sort(a), np.sort(b)]), np.array([len(a), len(b)]), t)
        assert (s != np.uint64(0xFFFFFFFFFFFFFFFF)).all()
        assert abs((s[0] == s[1]).mean() - true) < 0.16


def test_counts_travel_in_blocks():
    total = np.zeros(1 << 16, dtype=np.int32)
    total[[0, 4095, 4096, 65535]] = 3, 2**31 - 1, 1, 7
    back = np.zeros_like(total)
    rows = [r for b in op7._block_rows((at, total[at << op7.BLOCK_BITS : (at + 1) << op7.BLOCK_BITS]) for at in range(16)) for r in b.to_pylist()]
    for r in rows:
        back[(r["block"] << op7.BLOCK_BITS) + np.frombuffer(r["slots"], dtype="<u2")] = np.frombuffer(r["n"], dtype="<i4")
    assert len(rows) == 3 and (back == total).all()


def test_the_shingle_table_comes_in_one_job(spark, monkeypatch):
    """A row a block, not a row a slot and a job a partition."""
    docs = spark.createDataFrame([(i, f"common words open this text then {i} and {i + 1} follow") for i in range(40)], "doc_id long, text string")
    members = docs.select(F.col("doc_id").alias("id"), F.col("doc_id").alias("comp"), F.lit(9).alias("n_shingles"))
    monkeypatch.setattr(type(docs), "toLocalIterator", None)
    heads = op7._prefixes(docs, members, op7.CONTRACT).where("place = 0").collect()
    # the rarest shingle stands first, and that none shares
    assert len(heads) == 40 and len({r.element for r in heads}) == 40
