"""A content-addressed store of token ids.

``write_store`` cuts each document's ids where a rolling hash of the last 32 ids says so, keeps every different
chunk once, and writes three tables:

* ``chunks(chunk, n, ids)``: ``chunk`` is the BLAKE2b-128 of the ids, ``ids`` their little-endian bytes, two a
  token where the vocabulary allows it, else four;
* ``recipes(part, doc_id, seq, start_in_part, n_tokens, chunks, sizes)``: in ascending doc_id order, in files of
  consecutive ranges ``part``; ``seq`` counts the documents of a part;
* ``manifest(part, base, n_tokens, n_docs, leaf)``: ``base`` is the number of ids before the part, ``leaf`` the
  Merkle node over the part's recipes; ``root`` hashes the leaves in order.

``read_store`` reads the stored bytes, hashes each chunk anew, rebuilds leaf and root, and raises if any differs.
A document's checksum comes from its chunks' checksums, which CRC algebra joins, so that no ids move again.

A chunk that many documents share is met once a task before the shuffle. Null and empty texts hold the end id
alone. Repeated rows are stored as rows of their own, after one another. An empty table gives empty tables.
Other columns of the input are left out. A task that runs again writes the same rows.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import library_encoder
from .hashing import mix
from .op6_bpe_codec import PIECE_BYTES, _tokenizer_path
from .shared import discard, give_back, new_path, over_batches, pieces

#: Mean, least and most ids of a chunk.
MEAN, LEAST, MOST = 1024, 128, 8192
#: The rolling hash covers so many ids.
WINDOW = 32


def cut_points(ids: np.ndarray, ends: np.ndarray) -> list[np.ndarray]:
    """For each document, given by its end in ``ids``, where its chunks end.

    The hash of a place is the sum of 32 table values, the j-th last shifted by j bits; doubling makes it for all
    places at once. It may look back into the document before: the first LEAST ids of a document have no cut.
    """
    gear = mix(ids.astype(np.uint64) + np.uint64(0x51ED27)).astype(np.uint32)
    h = gear.copy()
    span = 1
    while span < WINDOW:
        h[span:] = h[span:] + (h[:-span] << np.uint32(span))
        span *= 2
    marked = np.flatnonzero(h >> np.uint32(32 - MEAN.bit_length() + 1) == 0) + 1
    out = []
    start = 0
    for end in ends.tolist():
        own = marked[np.searchsorted(marked, start + LEAST) : np.searchsorted(marked, end)]
        cuts, last = [], start
        for c in own.tolist():
            while c - last > MOST:
                last += MOST
                cuts.append(last)
            if c - last >= LEAST:
                cuts.append(c)
                last = c
        while end - last > MOST:
            last += MOST
            cuts.append(last)
        if end > start:
            cuts.append(end)
        out.append(np.array(cuts, dtype=np.int64))
        start = end
    return out


def _digest(raw: bytes) -> bytes:
    return hashlib.blake2b(raw, digest_size=16).digest()


_STAGED = "is_chunk boolean, spread binary, doc_id long, n_tokens long, chunks binary, sizes array<int>, chunk binary, n int, ids binary"


def _stage(docs: DataFrame, tokenizer: str, end_id: int) -> DataFrame:
    """A row for each document, and one for each chunk that its task hasn't sent yet."""
    fields = pa.schema([("is_chunk", pa.bool_()), ("spread", pa.binary()), ("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("chunks", pa.binary()), ("sizes", pa.list_(pa.int32())), ("chunk", pa.binary()), ("n", pa.int32()), ("ids", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = library_encoder(tokenizer)
        sent: set[bytes] = set()
        for batch in batches:
            for part in pieces(batch, "text", PIECE_BYTES) if batch.num_rows else ():
                ids, n = encoder(part.column(1).to_pylist())
                ids = np.insert(ids, np.cumsum(n), end_id)
                n = n + 1
                ends = np.cumsum(n)
                doc_rows, chunk_rows = [], []
                start = 0
                for doc, count, cuts in zip(part.column(0).to_pylist(), n.tolist(), cut_points(ids, ends), strict=True):
                    keys, sizes = [], []
                    for c in cuts.tolist():
                        raw = ids[start:c].astype("<u2" if encoder.narrow else "<u4").tobytes()
                        key = _digest(raw)
                        keys.append(key)
                        sizes.append(c - start)
                        if key not in sent:
                            sent.add(key)
                            chunk_rows.append((key, c - start, raw))
                        start = c
                    doc_rows.append((doc, count, b"".join(keys), sizes, _digest(str(doc).encode() + keys[0])))
                if len(sent) > 1_000_000:
                    sent.clear()
                d, c = len(doc_rows), len(chunk_rows)
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array([False] * d + [True] * c),
                        pa.array([x[4] for x in doc_rows] + [x[0] for x in chunk_rows], pa.binary()),
                        pa.array([x[0] for x in doc_rows] + [None] * c, pa.int64()),
                        pa.array([x[1] for x in doc_rows] + [None] * c, pa.int64()),
                        pa.array([x[2] for x in doc_rows] + [None] * c, pa.binary()),
                        pa.array([x[3] for x in doc_rows] + [None] * c, pa.list_(pa.int32())),
                        pa.array([None] * d + [x[0] for x in chunk_rows], pa.binary()),
                        pa.array([None] * d + [x[1] for x in chunk_rows], pa.int32()),
                        pa.array([None] * d + [x[2] for x in chunk_rows], pa.binary()),
                    ],
                    schema=fields,
                )
        sent.clear()
        give_back()

    return docs.mapInArrow(run, _STAGED)


def _once(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Leaves the first row of each chunk; all rows of a chunk are in this partition."""
    seen: set[bytes] = set()
    for batch in batches:
        keep = []
        for key in batch.column("chunk").to_pylist():
            keep.append(key is None or key not in seen)
            if key is not None:
                seen.add(key)
        yield batch.filter(pa.array(keep, pa.bool_()))


def _recipe_leaf(doc_id: int, n_tokens: int, chunks: bytes) -> bytes:
    return _digest(f"{doc_id}:{n_tokens}:".encode() + chunks)


def merkle(nodes: list[bytes]) -> bytes:
    """The root over nodes in order: pairs are hashed level by level, an odd last one rises as it is."""
    while len(nodes) > 1:
        nodes = [_digest(b"".join(nodes[i : i + 2])) if i + 1 < len(nodes) else nodes[i] for i in range(0, len(nodes), 2)]
    return nodes[0] if nodes else _digest(b"")


class MerkleStack:
    """The root of a stream of nodes, with one held node a level."""

    def __init__(self):
        self.levels: list[bytes | None] = []

    def add(self, node: bytes) -> None:
        for i, held in enumerate(self.levels):
            if held is None:
                self.levels[i] = node
                return
            node, self.levels[i] = _digest(held + node), None
        self.levels.append(node)

    def root(self) -> bytes:
        node = None
        for held in self.levels:
            if held is not None:
                node = held if node is None else _digest(held + node)
        return node if node is not None else _digest(b"")


def write_store(docs: DataFrame, path: str, tokenizer: str, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> str:
    """Writes the store under ``path`` and returns the manifest's root in hex."""
    spark = docs.sparkSession
    staged_path = new_path(spark, "chunk-stage")
    staged = _stage(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), tokenizer, end_id)
    # one shuffle deals out chunks by their key and documents by their own; the key makes the rows of a chunk meet
    staged.repartition("spread").mapInArrow(_once, _STAGED).drop("spread").write.partitionBy("is_chunk").option("compression", "zstd").parquet(staged_path)
    staged = spark.read.schema(_STAGED.replace("is_chunk boolean, spread binary, ", "") + ", is_chunk boolean").parquet(staged_path)

    ordered = staged.where(~F.col("is_chunk")).select("doc_id", "n_tokens", "chunks", "sizes").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "n_tokens", "chunks")

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, seq, start = TaskContext.get().partitionId(), 0, 0
        for b in batches:
            n = b.column(1).to_numpy().astype(np.int64)
            at = start + np.cumsum(n) - n
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(n), part, dtype=np.int32)), b.column(0), pa.array(np.arange(seq, seq + len(n))), pa.array(at), b.column(1), b.column(2), b.column(3)], ["part", "doc_id", "seq", "start_in_part", "n_tokens", "chunks", "sizes"])
            seq, start = seq + len(n), start + int(n.sum())

    ordered.mapInArrow(number, "part int, doc_id long, seq long, start_in_part long, n_tokens long, chunks binary, sizes array<int>").write.option("compression", "zstd").parquet(f"{path}/recipes")

    # a few numbers for each part, of which there are as many as tasks
    parts = sorted(_leaves(spark.read.parquet(f"{path}/recipes")).collect())
    base, rows = 0, []
    for part, n_docs, n_tokens, leaf in parts:
        rows.append((part, base, n_tokens, n_docs, bytes(leaf)))
        base += n_tokens
    spark.createDataFrame(rows, "part int, base long, n_tokens long, n_docs long, leaf binary").coalesce(1).write.parquet(f"{path}/manifest")
    fs_move(spark, f"{staged_path}/is_chunk=true", f"{path}/chunks")
    discard(spark, staged_path)
    return merkle([x[4] for x in rows]).hex()


def fs_move(spark: SparkSession, old: str, new: str) -> None:
    """Rename a folder of the shared store; a missing one (no rows) leaves an empty folder."""
    jvm = spark._jvm.org.apache.hadoop.fs
    a, b = jvm.Path(old), jvm.Path(new)
    fs = a.getFileSystem(spark._jsc.hadoopConfiguration())
    if not fs.exists(a):
        fs.mkdirs(b)
    elif not fs.rename(a, b):
        raise OSError(f"couldn't move {old} to {new}")


def _leaves(recipes: DataFrame) -> DataFrame:
    """(part, n_docs, n_tokens, leaf) from recipes as stored; a part is one file in order, which one task reads in order or in a few splits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        stacks: dict[int, list] = {}
        for b in batches:
            for part, seq, doc, n, chunks in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                s = stacks.setdefault(part, [MerkleStack(), 0, 0])
                if seq != s[1]:
                    raise ValueError(f"part {part} of the recipes is out of order at {seq}")
                s[0].add(_recipe_leaf(doc, n, chunks))
                s[1] += 1
                s[2] += n
        yield pa.RecordBatch.from_arrays([pa.array(list(stacks), pa.int32()), pa.array([s[1] for s in stacks.values()], pa.int64()), pa.array([s[2] for s in stacks.values()], pa.int64()), pa.array([s[0].root() for s in stacks.values()], pa.binary())], ["part", "n_docs", "n_tokens", "leaf"])

    one_file = recipes.select("part", "seq", "doc_id", "n_tokens", "chunks").repartition("part").sortWithinPartitions("part", "seq")
    return one_file.mapInArrow(run, "part int, n_docs long, n_tokens long, leaf binary")


#: The reversed CRC-32 polynomial.
POLY = 0xEDB88320


def _times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products modulo the CRC-32 polynomial, bits reversed: bit 31 is 1."""
    a, b, out = a.astype(np.uint32).copy(), b.astype(np.uint32).copy(), np.zeros(len(a), dtype=np.uint32)
    for _ in range(32):
        out ^= np.where(a & np.uint32(0x80000000), b, np.uint32(0))
        a <<= np.uint32(1)
        b = (b >> np.uint32(1)) ^ np.where(b & np.uint32(1), np.uint32(POLY), np.uint32(0))
    return out


def shift_crc(crc: np.ndarray, n_bytes: np.ndarray) -> np.ndarray:
    """What ``crc`` adds to the checksum of a text in which n_bytes follow: crc times x^(8 n_bytes)."""
    out, n = crc.astype(np.uint32), n_bytes.astype(np.int64) * 8
    power = np.array([0x40000000], dtype=np.uint32)  # x
    while n.any():
        odd = (n & 1).astype(bool)
        if odd.any():
            out[odd] = _times(out[odd], np.broadcast_to(power, (int(odd.sum()),)))
        power = _times(power, power)
        n >>= 1
    return out


def read_store(spark: SparkSession, path: str, root: str | None = None) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) from the stored files; raises where bytes, recipes or root differ."""
    manifest = spark.read.parquet(f"{path}/manifest")
    recipes = spark.read.parquet(f"{path}/recipes")
    wanted = {r.part: (r.n_docs, r.n_tokens, bytes(r.leaf)) for r in manifest.collect()}
    found = {part: (n_docs, n_tokens, bytes(leaf)) for part, n_docs, n_tokens, leaf in _leaves(recipes).collect()}
    if wanted != found or root not in (None, merkle([wanted[p][2] for p in sorted(wanted)]).hex()):
        raise ValueError(f"the store at {path} doesn't match its manifest")

    def make():
        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            crc = []
            for key, n, raw in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                if _digest(raw) != key:
                    raise ValueError(f"chunk {key.hex()} is damaged")
                crc.append(zlib.crc32(raw if len(raw) == 4 * n else np.frombuffer(raw, dtype="<u2").astype("<u4").tobytes()))
            return pa.RecordBatch.from_arrays([b.column(0), pa.array(crc, pa.int64())], ["chunk", "crc"])

        return each

    chunks = over_batches(spark.read.schema("chunk binary, n int, ids binary").parquet(f"{path}/chunks").select("chunk", "n", "ids"), make, "chunk binary, crc long")

    def refer(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A row for each chunk of a document, with the bytes that follow it."""
        for b in batches:
            part, doc, seq, keys = b.column(0), b.column(1), b.column(2), b.column(3).to_pylist()
            sizes = b.column(4)
            per = np.array([len(k) // 16 for k in keys], dtype=np.int64)
            n = sizes.flatten().to_numpy().astype(np.int64)
            last = np.cumsum(per)
            total = np.cumsum(n)
            rest = np.repeat(total[last - 1], per) - total
            row = np.repeat(np.arange(b.num_rows), per)
            yield pa.RecordBatch.from_arrays([part.take(pa.array(row)), doc.take(pa.array(row)), seq.take(pa.array(row)), pa.array([k[i : i + 16] for k in keys for i in range(0, len(k), 16)], pa.binary()), pa.array(rest * 4)], ["part", "doc_id", "seq", "chunk", "after"])

    def shifted(b: pa.RecordBatch) -> pa.RecordBatch:
        crc = shift_crc(b.column(3).to_numpy().astype(np.uint32), b.column(4).to_numpy())
        return pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(crc.astype(np.int64))], ["part", "doc_id", "seq", "crc"])

    used = recipes.select("part", "doc_id", "seq", "chunks", "sizes").mapInArrow(refer, "part int, doc_id long, seq long, chunk binary, after long")
    # a left join, so that a chunk that is missing raises
    joined = used.join(chunks.hint("merge"), "chunk", "left").select("part", "doc_id", "seq", F.coalesce("crc", F.raise_error(F.lit("a chunk is missing")).cast("long")).alias("crc"), "after")
    sums = over_batches(joined, lambda: shifted, "part int, doc_id long, seq long, crc long").groupBy("part", "seq").agg(F.expr("bit_xor(crc)").alias("ids_crc32"))
    starts = recipes.join(F.broadcast(manifest.select("part", "base")), "part").select("part", "seq", "doc_id", (F.col("base") + F.col("start_in_part")).alias("start"), "n_tokens")
    return starts.join(sums, ["part", "seq"]).select("doc_id", "start", "n_tokens", "ids_crc32")


def op1_chunk_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = new_path(spark, "chunk-store")
    root = write_store(spark.read.parquet(f"{sf_dir}/documents.parquet"), path, _tokenizer_path())
    return read_store(spark, path, root)


QUERIES = {"op1_chunk_store": op1_chunk_store}
ORACLES: dict[str, str] = {}
