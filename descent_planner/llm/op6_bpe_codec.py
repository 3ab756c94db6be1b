"""BPE encoding and decoding of a table of texts by segment-tree merges (see ``bpe``).

Null and empty texts give no ids. Rows stay one for one, repeated ids and rows included; other columns of the
input are left out, so that none can clash. Memory: a batch of texts is cut to ``PIECE_BYTES``, a longer text
stands alone.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import tree_encoder, vocabulary
from .shared import over_batches, pieces

PIECE_BYTES = 1 << 19


def _tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def encode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """Ids of each text (``ids array<int>``), or with ``digest`` their hash and that of the text decoded from them."""

    def make():
        encoder, vocab = tree_encoder(path), vocabulary(path)

        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            keys, counts, made = batch.column(0), [], []
            for part in pieces(batch, "text", PIECE_BYTES):
                ids, n = encoder(part.column(1).to_pylist())
                counts.append(n)
                ends = np.cumsum(n)
                for a, b in zip((ends - n).tolist(), ends.tolist(), strict=True):
                    own = ids[a:b]
                    if digest:
                        made.append((hashlib.sha256(own.astype("<u4").tobytes()).hexdigest(), hashlib.sha256(vocab.decode(own)).hexdigest()))
                    else:
                        made.append(own.astype(np.int32))
            count = pa.array(np.concatenate(counts))
            if digest:
                return pa.RecordBatch.from_arrays([keys, count, pa.array([x for x, _ in made]), pa.array([x for _, x in made])], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
            return pa.RecordBatch.from_arrays([keys, count, pa.array(made, pa.list_(pa.int32()))], ["doc_id", "n_tokens", "ids"])

        return each

    schema = "doc_id long, n_tokens long, " + ("ids_sha256 string, decoded_sha256 string" if digest else "ids array<int>")
    return over_batches(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), make, schema)


def decode(encoded: DataFrame, path: str) -> DataFrame:
    """Texts of ``ids``; null ids give an empty text."""

    def make():
        vocab = vocabulary(path)

        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = [vocab.decode(np.array(x or [], dtype=np.int64)).decode() for x in batch.column(1).to_pylist()]
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

        return each

    return over_batches(encoded.select("doc_id", "ids"), make, "doc_id long, text string")


def op6_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(spark.read.parquet(f"{sf_dir}/documents.parquet"), _tokenizer_path(), digest=True)


QUERIES = {"op6_bpe_codec": op6_bpe_codec}
ORACLES: dict[str, str] = {}
