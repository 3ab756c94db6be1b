import hashlib
import zlib

import numpy as np
import public_tokenizers as P
import pytest
from tokenizers import Tokenizer

from descent_planner.llm import op1_chunk_store as op1
from descent_planner.llm import op6_bpe_codec as op6

from . import edge

LIB = Tokenizer.from_file(P.path("byte_bpe_50k.json"))


def ids_of(text):
    return LIB.encode(text or "", add_special_tokens=False).ids


@pytest.mark.parametrize("edges", [True, False])
def test_op1_equals_plain_encoding(spark, sf, tmp_path, edges):
    folder = edge.tables(spark, tmp_path) if edges else sf
    rows = sorted(spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text").collect())
    want, at = [], 0
    for doc, text in rows:
        ids = [*ids_of(text), 0]
        want.append((doc, at, len(ids), zlib.crc32(np.array(ids, dtype="<u4").tobytes())))
        at += len(ids)
    assert sorted(map(tuple, op1.op1_chunk_store(spark, folder).collect())) == want


def test_op1_empty_and_repeated(spark, tmp_path):
    assert op1.op1_chunk_store(spark, edge.tables(spark, tmp_path / "a", [])).collect() == []
    docs = spark.createDataFrame([(1, "b c")] * 3, "doc_id long, text string")
    root = op1.write_store(docs, f"{tmp_path}/s", P.path("byte_bpe_50k.json"))
    assert sorted(r.start for r in op1.read_store(spark, f"{tmp_path}/s", root).collect()) == [0, 3, 6]
    assert spark.read.parquet(f"{tmp_path}/s/chunks").count() == 1


def test_op1_finds_damage(spark, tmp_path):
    docs = spark.createDataFrame([(1, "b c"), (2, "d")], "doc_id long, text string")
    root = op1.write_store(docs, f"{tmp_path}/s", P.path("byte_bpe_50k.json"))
    with pytest.raises(ValueError):
        op1.read_store(spark, f"{tmp_path}/s", "00" + root[2:])


def test_chunks_resume_after_an_edit():
    rng = np.random.default_rng(3)
    a = rng.integers(0, 50_000, 60_000)
    b = np.insert(a, 30_000, [1, 2, 3])
    chunks = [{a[s:e].tobytes() for s, e in zip([0, *c], c)} for a, c in ((x, op1.cut_points(x, np.array([len(x)]))[0].tolist()) for x in (a, b))]
    assert len(chunks[0] - chunks[1]) <= 3 and all(len(c) <= op1.MOST * 8 for c in chunks[0])


def test_shifted_checksums_join():
    a, b = b"some bytes", b"that follow it"
    crc = op1.shift_crc(np.array([zlib.crc32(a)]), np.array([len(b)]))[0] ^ zlib.crc32(b)
    assert crc == zlib.crc32(a + b)


def test_merkle_of_a_stream_is_merkle_of_the_list():
    for n in range(20):
        nodes = [bytes([i]) * 16 for i in range(n)]
        s = op1.MerkleStack()
        for x in nodes:
            s.add(x)
        assert s.root() == op1.merkle(nodes)


@pytest.mark.parametrize("edges", [True, False])
def test_op6_equals_the_library(spark, sf, tmp_path, edges):
    folder = edge.tables(spark, tmp_path) if edges else sf
    want = []
    for doc, text in spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text").collect():
        ids = ids_of(text)
        back = LIB.decode(ids, skip_special_tokens=False)
        want.append((doc, len(ids), hashlib.sha256(np.array(ids, dtype="<u4").tobytes()).hexdigest(), hashlib.sha256(back.encode()).hexdigest()))
    assert sorted(map(tuple, op6.op6_bpe_codec(spark, folder).collect())) == sorted(want)


def test_op6_round_trip(spark):
    docs = edge.documents(spark)
    path = P.path("byte_bpe_50k.json")
    back = {r.doc_id: r.text for r in op6.decode(op6.encode(docs, path), path).collect()}
    assert back == {i: t or "" for i, t in enumerate(edge.TEXTS)}
