from collections import defaultdict

import corpus_pipeline as pipeline
from descent_planner.llm import op3_pii_spans as op3
from descent_planner.llm import op4_conflict_packing as op4
from descent_planner.llm import op7_near_duplicates as op7

from . import edge
from .test_op7 import brute


def stages(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for name, stage in pipeline.STAGES:
        before = docs
        docs = stage(spark, docs, folder)
        docs.cache()
        yield name, before, docs


def test_stages_on_the_table(spark, sf):
    for name, before, after in stages(spark, sf):
        old = {r.doc_id: r for r in before.collect()}
        rows = after.collect()
        if name != "packing":
            assert after.columns == before.columns and len({r.doc_id for r in rows}) == len(rows)
        if name == "language":
            assert len(rows) >= 0.98 * len(old) and all(r.text == old[r.doc_id].text for r in rows)
        if name == "lines":
            assert len(rows) == len(old)
            assert all(set(r.text.split("\n")) <= set(old[r.doc_id].text.split("\n")) | {""} for r in rows)
        if name == "near_duplicates":
            want = brute([(i, r.text) for i, r in old.items()], op7.CORPUS)
            assert sorted(r.doc_id for r in rows) == [i for i, _, _, kept in want if kept]
        if name == "personal_data":
            assert {r.doc_id: r.text for r in rows} == {i: op3.redacted(r.text) for i, r in old.items()}
            assert all(not op3.base_spans(r.text) for r in rows) and all(r.n_chars == len(r.text) for r in rows)
        if name == "packing":
            tokens = defaultdict(int)
            for r in rows:
                tokens[r.doc_id] += r.n_tokens
            assert dict(tokens) == {i: len(r.text.lower().split()) for i, r in old.items()}
            assert op4.PACKED.count(",") == len(after.columns) - 1


def test_edges_and_empty(spark, tmp_path):
    folder = edge.tables(spark, tmp_path / "a")
    for name, before, after in stages(spark, folder):
        after.collect()
        if name not in ("packing",):
            assert after.columns == before.columns
    assert pipeline.run(spark, edge.tables(spark, tmp_path / "b", [])).count() == 0


def test_registered():
    import __spark_entry__ as entry

    found = entry.queries()
    assert "pipeline" in found and all(any(k.startswith(f"op{n}_") for k in found) for n in range(1, 11))
