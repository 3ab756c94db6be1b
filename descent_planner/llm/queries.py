"""The queries of the training-data operators."""

from __future__ import annotations

import importlib

QUERIES: dict = {}
ORACLES: dict = {}
for _name in (
    "op1_chunk_store",
    "op2_media_archives",
    "op3_pii_spans",
    "op4_conflict_packing",
    "op5_language_spans",
    "op6_bpe_codec",
    "op7_near_duplicates",
    "op8_site_lines",
    "op9_pruned_graph",
    "op10_toxicity_chain",
):
    _module = importlib.import_module(f".{_name}", __package__)
    QUERIES |= _module.QUERIES
    ORACLES |= _module.ORACLES

_pipeline = importlib.import_module("corpus_pipeline")
QUERIES["pipeline"] = _pipeline.run
if _pipeline.ORACLE_SQL:
    ORACLES["pipeline"] = _pipeline.ORACLE_SQL
