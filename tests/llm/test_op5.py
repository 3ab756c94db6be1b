import numpy as np

from descent_planner.llm import op5_language_spans as op5

from . import edge

ROWS = [("the cat and the dog were in the house with that man " * 5, "en"), ("der Hund und die Katze sind nicht in dem Haus mit " * 5, "de"), ("привет как дела это мой дом и собака " * 5, "ru")]


def brute(scores, penalty):
    n, k = scores.shape
    best = [(scores[0, j], [j]) for j in range(k)]
    for i in range(1, n):
        best = [max(((v - penalty * (p[-1] != j) + scores[i, j], [*p, j]) for v, p in best), key=lambda x: x[0]) for j in range(k)]
    return max(best, key=lambda x: x[0])


def test_viterbi_is_optimal():
    rng = np.random.default_rng(1)
    counts = np.array([5, 0, 9, 1, 5])
    scores = rng.normal(size=(20, 3))
    labels = op5.viterbi(scores, counts, 1.0)
    at = 0
    for n in counts:
        if n:
            own = scores[at : at + n]
            value, _ = brute(own, 1.0)
            path = labels[at : at + n]
            assert abs(sum(own[i, j] for i, j in enumerate(path)) - (np.diff(path) != 0).sum() - value) < 1e-9
        at += n


def test_mixed_text_has_spans(spark):
    model = op5.Model.fit(ROWS)
    texts = ["the dog and the man in the house und die Katze sind nicht in dem Haus", "это собака", "12 34 !", None, "日本語"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in op5.identify(docs, model, spans=True).collect()}
    assert got[0].spans == "en:8,de:8" and got[0].n_spans == 2
    assert got[1].lang_pred == "ru" and got[1].score == 1.0
    assert got[2].lang_pred == got[3].lang_pred == "und" and got[3].score == 0.0
    assert got[4].lang_pred in ("de", "en", "ru")


def test_edges(spark, tmp_path):
    rows = op5.op5_language_spans(spark, edge.tables(spark, tmp_path / "a")).collect()
    assert len(rows) == len(edge.TEXTS) and all(0 <= r.score <= 1 for r in rows)
    assert {r.doc_id for r in rows if r.lang_pred == "und"} >= {0, 1, 2}
    assert op5.op5_language_spans(spark, edge.tables(spark, tmp_path / "b", [])).count() == 0
    docs = edge.documents(spark)
    kept = op5.keep_identified(docs, op5.Model.fit(ROWS))
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()}.isdisjoint({0, 1, 2})


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    truth = {r.doc_id: r.lang for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = op5.op5_language_spans(spark, sf).collect()
    assert all(r.held_out == op5.python_held_out(r.doc_id) for r in rows)
    own = [r for r in rows if r.held_out and truth[r.doc_id]]
    assert sum(r.lang_pred == truth[r.doc_id] for r in own) >= 0.98 * len(own)


def test_batches_of_long_texts_are_bounded(spark):
    """Batches of 10,000 long texts took an executor of the pipeline over its memory."""
    import pyarrow as pa

    from descent_planner.llm.shared import BATCH_BYTES, over_batches

    docs = spark.range(0, 400, 1, 1).selectExpr("id AS doc_id", "repeat('lorem ', 20000) AS text")

    def make():
        return lambda b: pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], ["n", "size"])

    found = over_batches(docs, make, "n long, size long").collect()
    assert sum(r.n for r in found) == 400 and max(r.size for r in found) < 1.1 * BATCH_BYTES


def test_decodes_in_little_memory():
    import tracemalloc

    import pyarrow as pa

    text = " ".join(t for t, _ in ROWS) * 10
    batch = pa.RecordBatch.from_pydict({"text": [text] * (4_000_000 // len(text.encode()))})
    model = op5.Model.fit(ROWS)
    tracemalloc.start()
    for _ in op5._decoded(batch, 0, model):
        pass
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 64e6, most  # before: 75 MB


def test_a_worker_forgets_what_other_work_kept(monkeypatch):
    from descent_planner.llm import bpe, hashing, shared
    from descent_planner.llm.op6_bpe_codec import _tokenizer_path

    monkeypatch.setattr(shared, "_entered", None)
    shared.enter("packing")
    encoder = bpe.tree_encoder(_tokenizer_path())
    ids = encoder(["one two"])[0]
    shared.enter("packing")
    assert bpe.tree_encoder(_tokenizer_path()) is encoder and hashing._made
    shared.enter("language")
    assert bpe.tree_encoder.cache_info().currsize == 0 and not hashing._made
    assert (bpe.tree_encoder(_tokenizer_path())(["one two"])[0] == ids).all()
