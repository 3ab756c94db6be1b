"""The corpus pipeline: documents in, packed training sequences out.

Each stage takes (spark, docs, sf_dir) and returns the columns of documents, but for the last, which returns the
packing. ``run`` writes each stage's rows as Parquet in the shared folder and rereads them for the next one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from descent_planner.llm import op3_pii_spans, op4_conflict_packing, op5_language_spans, op7_near_duplicates, op8_site_lines
from descent_planner.llm.shared import saved


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents with a letter of which half the letters or more are in one language, and sets ``lang`` to it.

    The model learns from the stage's own labelled rows, its held-out quarter left out.
    """
    model = op5_language_spans.train(docs, ~op5_language_spans.held_out(docs.doc_id))
    return op5_language_spans.keep_identified(docs, model)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops lines that a quarter of a source's documents hold; no document goes."""
    return _measured(op8_site_lines.drop_site_lines(docs))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document of the smallest id of each group at 0.8 over 5-word shingles; rows of one id stay or go together, rows without an id stay."""
    return op7_near_duplicates.drop_near_duplicates(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data by its kind; no document goes."""
    return _measured(op3_pii_spans.redact(docs))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs all documents into bins in which no source and no cluster of near copies comes twice.

    Clusters are looked for anew, since the redaction may have made near copies. Every row is packed, repeated ids too.
    """
    items, n = op4_conflict_packing.clustered(docs)
    return op4_conflict_packing.pack(items, n_rows=n)


def _measured(docs: DataFrame) -> DataFrame:
    """``n_chars`` anew from the text."""
    from pyspark.sql import functions as F

    if "n_chars" not in docs.columns:
        return docs
    return docs.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))


STAGES = [("language", language), ("lines", lines), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("packing", packing)]

#: The learned model, sketches' classes and best-fit order have no SQL form; tests hold the rows against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = saved(stage(spark, docs, sf_dir), f"stage-{name}")
    return docs
