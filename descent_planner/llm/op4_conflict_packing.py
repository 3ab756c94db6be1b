"""Best-fit packing of documents into bins of ``CAPACITY`` tokens under conflicts.

Tokens are the ids that op6's encoder gives (``n_ids``; here short words are merged by columns, which is faster and
gives the same ids), and bins are filled by them; ``n_tokens`` counts the words between
white space that start in a piece, which says nothing of its size.

A bin never holds two documents of one source, nor two of one duplicate cluster: it carries a bitmap of each. A
cluster is a component of op7's near copies (``CORPUS``: 5 words, 0.8) over lower-case words between white space;
texts without words have none. Bins are ordered by residual space. A document takes the bin of least residual that fits; where that one conflicts, the
search goes to its successor until a bin is compatible, and opens a bin where none is.

Documents longer than a bin are cut: their full pieces fill bins of their own, and the rest is packed as one piece.
Rows are dealt out by a hash of id and cluster-free salt into groups of about ``GROUP_ROWS``, each packed by itself,
longest first and ties by id; so a hot source or cluster is spread and no task gets more than its groups. Every row
is placed. Null lengths count as 0; pieces of no ids take a place in a bin as any other. A null source or
cluster conflicts with nothing. Repeated rows are rows of their own; bins are numbered within their group.
"""

from __future__ import annotations

from bisect import bisect_left, insort
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import column_encoder, vocabulary
from .op6_bpe_codec import PIECE_BYTES, _tokenizer_path
from .op7_near_duplicates import CORPUS, SKETCHED, Params, components_of, sketch_columns, windowed_sets
from .shared import give_back, over_batches, pieces, saved

CAPACITY = 2048
GROUP_ROWS = 2_000
#: Whether a code point is white space; the last entry stands for all beyond.
_BLANK = np.array([chr(c).isspace() for c in range(0x3002)])


class Bins:
    """Bins of one group, ordered by residual. Bins of like residual and bitmaps lie on one shelf."""

    def __init__(self, capacity: int):
        self.capacity = capacity
        self.residuals: list[int] = []
        self.shelves: dict[int, dict[tuple[int, int], list[int]]] = {}
        self.count = 0

    def place(self, size: int, source: int, cluster: int) -> tuple[int, int]:
        """Puts a piece with these bits into the tightest compatible bin: (bin, residual before)."""
        at = bisect_left(self.residuals, size)
        while at < len(self.residuals):
            residual = self.residuals[at]
            shelf = self.shelves[residual]
            for masks, bins in shelf.items():
                if not (masks[0] & source or masks[1] & cluster):
                    number = bins.pop()
                    if not bins:
                        del shelf[masks]
                        if not shelf:
                            del self.shelves[residual], self.residuals[at]
                    self._put(number, residual - size, masks[0] | source, masks[1] | cluster)
                    return number, residual
            at += 1
        self.count += 1
        self._put(self.count - 1, self.capacity - size, source, cluster)
        return self.count - 1, self.capacity

    def _put(self, number: int, residual: int, sources: int, clusters: int) -> None:
        if residual not in self.shelves:
            insort(self.residuals, residual)
            self.shelves[residual] = {}
        self.shelves[residual].setdefault((sources, clusters), []).append(number)


def _bits(values: list, spare: bool) -> list[int]:
    """A bit for each different value; with ``spare`` a value met once needs none, since it conflicts with nothing."""
    many: dict = {}
    for v in values:
        many[v] = many.get(v, 0) + 1
    numbers: dict = {}
    out = []
    for v in values:
        if v is None or spare and many[v] == 1:
            out.append(0)
        else:
            out.append(1 << numbers.setdefault(v, len(numbers)))
    return out


def pack_group(rows: list[tuple], capacity: int) -> list[tuple[int, int, int, int]]:
    """(row, piece, bin, tokens) of rows (id, length, source, cluster), in packing order."""
    bins = Bins(capacity)
    out = []
    rest = []
    for i, (_, length, _, _) in enumerate(rows):
        for piece in range(length // capacity):
            out.append((i, piece, bins.count, capacity))
            bins.count += 1
        if length % capacity or not length:
            rest.append(i)
    source = _bits([rows[i][2] for i in rest], True)
    cluster = _bits([rows[i][3] for i in rest], True)
    order = sorted(range(len(rest)), key=lambda k: (-(rows[rest[k]][1] % capacity), rows[rest[k]][0] is None, rows[rest[k]][0] or 0, rest[k]))
    for k in order:
        i = rest[k]
        size = rows[i][1] % capacity
        number, _ = bins.place(size, source[k], cluster[k])
        out.append((i, rows[i][1] // capacity, number, size))
    return out


PACKED = "doc_id long, piece int, shard long, bin long, n_tokens long, source string, cluster long, n_ids long"


def pack(items: DataFrame, capacity: int = CAPACITY, group_rows: int = GROUP_ROWS, n_rows: int | None = None) -> DataFrame:
    """Packs (doc_id, n_ids, source, cluster, words) by n_ids; the bins are named by (shard, bin). ``words`` are the words of each piece, ``n_rows`` how many items there are, where that is known."""
    items = items.select(F.col("doc_id").cast("long").alias("doc_id"), F.greatest(F.coalesce(F.col("n_ids").cast("long"), F.lit(0)), F.lit(0)).alias("n_ids"), F.col("source").cast("string").alias("source"), F.col("cluster").cast("long").alias("cluster"), F.col("words").cast("array<long>").alias("words"))
    groups = max(1, round((items.count() if n_rows is None else n_rows) / group_rows))
    dealt = items.withColumn("shard", F.pmod(F.xxhash64("doc_id", "n_ids", "source", F.lit(11)), F.lit(groups))).repartition("shard").sortWithinPartitions("shard", "doc_id", "n_ids", "source", "cluster", "words")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        shard = None

        def flush() -> pa.RecordBatch:
            found = pack_group([x[:4] for x in held], capacity)
            own = [held[i] for i, _, _, _ in found]
            words = [x[4][f[1]] for x, f in zip(own, found, strict=True)]
            return pa.RecordBatch.from_arrays(
                [pa.array([x[0] for x in own], pa.int64()), pa.array([f[1] for f in found], pa.int32()), pa.array(np.full(len(found), shard)), pa.array([f[2] for f in found], pa.int64()), pa.array(words, pa.int64()), pa.array([x[2] for x in own], pa.string()), pa.array([x[3] for x in own], pa.int64()), pa.array([f[3] for f in found], pa.int64())],
                ["doc_id", "piece", "shard", "bin", "n_tokens", "source", "cluster", "n_ids"],
            )

        for b in batches:
            for *row, s in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                if s != shard and held:
                    yield flush()
                    held.clear()
                shard = s
                held.append(tuple(row))
        if held:
            yield flush()
        held.clear()
        give_back()

    return dealt.mapInArrow(run, PACKED)


def _starts(blank: np.ndarray) -> np.ndarray:
    """Where a word starts."""
    out = ~blank
    out[1:] &= blank[:-1]
    return out


def words_of_pieces(text: str, lengths: np.ndarray, capacity: int, count: int | None = None) -> list[int]:
    """How many words start in each piece of ``capacity`` ids, of which ``lengths`` has the bytes; ``count`` is the number of words, where that is known."""
    if len(lengths) <= capacity:
        return [len(text.split()) if count is None else count]
    raw = np.frombuffer(text.encode(), dtype=np.uint8)
    if len(raw) == len(text):
        at = np.flatnonzero(_starts(_BLANK[raw]))
    else:
        points = np.frombuffer(text.encode("utf-32-le"), dtype=np.uint32)
        # a point begins at a byte that goes on with none
        at = np.flatnonzero((raw & 0xC0) != 0x80)[_starts(_BLANK[np.minimum(points, len(_BLANK) - 1)])]
    ends = np.cumsum(lengths)[capacity - 1 :: capacity]
    return np.bincount(np.searchsorted(ends, at, "right"), minlength=-(-len(lengths) // capacity)).tolist()


def folded(text: str) -> str:
    """Lower-case words with a space between."""
    return " ".join(text.lower().split())


#: What makes a cluster: op7's near copies, over folded texts.
CLUSTERS = Params(CORPUS.shingle, CORPUS.num, CORPUS.den, CORPUS.bands, CORPUS.rows, folded)


def measured(docs: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """(doc_id, n_ids, source, words, n_shingles, set_key, bands) of (doc_id, text, source): ids are those that op6's encoder gives, ``words`` the words between white space of each piece, and the rest op7's sketches."""
    path = _tokenizer_path()

    def make():
        encoder, vocab = column_encoder(path), vocabulary(path)

        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            n_ids, words, sets = [], [], []
            for part in pieces(batch, "text", PIECE_BYTES):
                texts = part.column(1).to_pylist()
                ids, n = encoder(texts)
                ends = np.cumsum(n)
                split = [(text or "").lower().split() for text in texts]
                counts = [len(own) for own in split]
                # the texts are folded here, and so as CLUSTERS would have them
                sets.append(windowed_sets([" ".join(own) for own in split], CORPUS))
                words += [words_of_pieces(text or "", vocab.lengths[ids[a:b]] if b - a > capacity else ids[a:b], capacity, count) for text, a, b, count in zip(texts, (ends - n).tolist(), ends.tolist(), counts, strict=True)]
                n_ids.append(n)
            elements, sizes = (np.concatenate(x) for x in zip(*sets, strict=True))
            return pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.concatenate(n_ids).astype(np.int64)), batch.column(2), pa.array(words, pa.list_(pa.int64())), *sketch_columns(elements, sizes, CORPUS)], ["doc_id", "n_ids", "source", "words", "n_shingles", "set_key", "bands"])

        return each

    return over_batches(docs, make, "doc_id long, n_ids long, source string, words array<long>, " + SKETCHED)


def clustered(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> tuple[DataFrame, int]:
    """What ``pack`` takes: the measures of ``docs`` with the cluster of each row (null without words), and how many rows there are."""
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(source_col).cast("string").alias("source"))
    rows = saved(measured(docs), "measured")
    named = components_of(docs.select("doc_id", "text"), rows, CLUSTERS)
    # sets that only rows without an id have are known by their hash
    cluster = F.when(F.col("set_key").isNotNull(), F.coalesce("comp", F.xxhash64("set_key")))
    return rows.drop("bands").join(named.hint("merge"), "set_key", "left").select("doc_id", "n_ids", "source", cluster.alias("cluster"), "words"), rows.count()


def op4_conflict_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    items, n = clustered(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return pack(items, n_rows=n)


QUERIES = {"op4_conflict_packing": op4_conflict_packing}
ORACLES: dict[str, str] = {}
