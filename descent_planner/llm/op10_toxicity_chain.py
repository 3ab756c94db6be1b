"""Toxicity by a classifier chain of linear models over hashed word features.

The chain predicts the categories of ``labels`` one after the other. Each category's logistic model sees the words
of a text and the log odds of the categories before it. Those log odds come, for training, from models that didn't
see the row (out-of-fold predictions over ``FOLDS`` folds of the id's hash), so that later models learn what earlier
predictions are worth on new texts.

Features of a text: whether it holds a word, a word's start of four to eight letters, and a few shapes (share of
capitals and marks, length of words, number of words). For each category the ``KEEP`` features of the largest
absolute z score between its classes are used.

Fitted on at most ``SAMPLE_ROWS`` labelled rows: up to half of them are of the last category, the rest not, each
taken by the hash of their ids and weighted back to their share of the labels; of an id's rows the one of least hash
of its text. So the model is the same in every run. All texts are scored whole. Null
texts and texts without a letter have probability 0 in every category, and are of none. Where no label was learned, or only one
class, every probability is that class's share (0 for none). Rows stay one for one.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import LETTER, _classes
from .hashing import mix, run_hashes
from .shared import over_batches, pieces

SAMPLE_ROWS = 8_000
BITS = 20
FOLDS = 3
KEEP = 8_000
PIECE_BYTES = 1_000_000


def features(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, slot) of every feature, without repeats in a text, and which texts have a letter."""
    joined = "\n".join(texts) + "\n"
    points = np.frombuffer(joined.encode("utf-32-le"), dtype=np.uint32)
    ends = np.cumsum([len(t) + 1 for t in texts]) - 1
    letter = _classes()[points] == LETTER
    upper = (points >= 65) & (points <= 90)
    lower = joined.lower()
    # a lower case of another length would shift offsets: such texts are folded letter by letter where that's one to one
    if len(lower) != len(joined):
        lower = "".join(y if len(y := x.lower()) == 1 else x for x in joined)
    low = np.frombuffer(lower.encode("utf-32-le"), dtype=np.uint32)
    edge = np.flatnonzero(np.diff(np.concatenate([[False], letter, [False]]).astype(np.int8)))
    starts, stops = edge[::2], edge[1::2]
    owner = np.searchsorted(ends, starts)
    sizes = stops - starts
    shift = np.uint64(64 - BITS)
    found_text, found_slot = [owner], [(run_hashes(low, starts, stops, 3) >> shift).astype(np.int64)] if len(starts) else [np.empty(0, dtype=np.int64)]
    for n in range(4, 9):
        some = sizes > n
        if some.any():
            found_text.append(owner[some])
            found_slot.append((run_hashes(low, starts[some], starts[some] + n, 4) >> shift).astype(np.int64))
    count = len(texts)
    words = np.bincount(owner, minlength=count)
    letters = np.bincount(owner, weights=sizes, minlength=count)
    text_of = np.repeat(np.arange(count), np.diff(np.concatenate([[-1], ends])))
    capitals = np.bincount(text_of, weights=upper, minlength=count)
    space = np.isin(points, [9, 10, 13, 32])
    marks = np.bincount(text_of, weights=~letter & ~space, minlength=count)
    for i, shape in enumerate((8 * capitals / np.maximum(letters, 1), 8 * marks / np.maximum(letters, 1), 2 * letters / np.maximum(words, 1), np.log2(words + 1))):
        found_text.append(np.arange(count))
        level = np.minimum(shape, 40).astype(np.uint64)
        found_slot.append((mix(level + np.uint64(1000 * (i + 1))) >> shift).astype(np.int64))
    key = np.unique((np.concatenate(found_text) << BITS) | np.concatenate(found_slot))
    return key >> BITS, key & ((1 << BITS) - 1), words > 0


def _fit_linear(text: np.ndarray, column: np.ndarray, n_columns: int, extra: np.ndarray, y: np.ndarray, weight: np.ndarray, steps: int = 150) -> np.ndarray:
    """Weights (columns, extras, intercept) of a ridge-penalised logistic model, by adaptive gradient steps."""
    n, e = len(y), extra.shape[1]
    w, seen = np.zeros(n_columns + e + 1), np.full(n_columns + e + 1, 1e-8)
    weight = weight * (n / weight.sum())
    ones = (weight * y).sum()
    w[-1] = np.log((ones + 0.5) / (n - ones + 0.5))
    for _ in range(steps):
        z = np.bincount(text, weights=w[column], minlength=n) + extra @ w[n_columns : n_columns + e] + w[-1]
        r = weight * (1 / (1 + np.exp(-np.clip(z, -40, 40))) - y)
        g = np.concatenate([np.bincount(column, weights=r[text], minlength=n_columns), extra.T @ r, [r.sum()]]) / n
        g[:-1] += 1e-4 * w[:-1]
        seen += g * g
        w -= 0.3 * g / np.sqrt(seen)
    return w


def _best_cut(odds: np.ndarray, y: np.ndarray, weight: np.ndarray) -> float:
    """The probability at which F1 is best, halfway to the next lower prediction; 0.5 where there is one class."""
    if not len(y) or y.min() == y.max():
        return 0.5
    order = np.argsort(-odds, kind="stable")
    hit, taken = np.cumsum((weight * y)[order]), np.cumsum(weight[order])
    f1 = 2 * hit / (taken + (weight * y).sum())
    last = np.append(odds[order][1:] < odds[order][:-1], True)  # cuts lie between different predictions
    at = int(np.argmax(np.where(last, f1, -1)))
    below = odds[order][at + 1] if at + 1 < len(order) else odds[order][at] - 1
    return float(1 / (1 + np.exp(-(odds[order][at] + below) / 2)))


class Chain:
    """The fitted models, in order: (category, slots, weights, or a constant where there was one class)."""

    def __init__(self, categories: Sequence[str]):
        self.categories = list(categories)
        self.models: list[tuple] = []
        #: From this probability on a text is of the category: where out-of-fold predictions have the best F1.
        self.thresholds: list[float] = []

    @staticmethod
    def _fit_one(text, slot, rows, extra, y, weight):
        """A model from the rows marked in ``rows``."""
        use = rows[text]
        number = np.cumsum(rows) - 1
        text, slot, own_y, own_extra, weight = number[text[use]], slot[use], y[rows], extra[rows], weight[rows]
        n = len(own_y)
        if not n or own_y.min() == own_y.max():
            return None, float(own_y[0]) if n else 0.0
        here = np.bincount(slot, minlength=1 << BITS).astype(np.float64)
        with_y = np.bincount(slot, weights=own_y[text], minlength=1 << BITS)
        share = own_y.mean()
        z = np.abs(with_y - here * share) / np.sqrt(np.maximum(here * share * (1 - share), 1e-9))
        z[here < 3] = 0
        chosen = np.sort(np.argsort(-z, kind="stable")[:KEEP])
        chosen = chosen[z[chosen] > 0]
        column = np.full(1 << BITS, -1, dtype=np.int64)
        column[chosen] = np.arange(len(chosen))
        kept = column[slot] >= 0
        return chosen, _fit_linear(text[kept], column[slot[kept]], len(chosen), own_extra, own_y, weight)

    @staticmethod
    def _odds(model, text, slot, extra, n):
        chosen, w = model
        if chosen is None:
            p = min(max(w, 1e-6), 1 - 1e-6)
            return np.full(n, np.log(p / (1 - p)))
        column = np.full(1 << BITS, -1, dtype=np.int64)
        column[chosen] = np.arange(len(chosen))
        at = column[slot]
        kept = at >= 0
        return np.bincount(text[kept], weights=w[at[kept]], minlength=n) + extra @ w[len(chosen) : -1] + w[-1]

    @staticmethod
    def fit(categories: Sequence[str], text: np.ndarray, slot: np.ndarray, y: np.ndarray, fold: np.ndarray, weight: np.ndarray) -> Chain:
        """From features of texts, their labels (texts x categories), folds and weights."""
        chain = Chain(categories)
        n = len(y)
        extra = np.zeros((n, 0))
        for k in range(len(categories)):
            odds = np.zeros(n)
            for f in range(FOLDS):
                inside = text[fold[text] == f], slot[fold[text] == f]
                model = Chain._fit_one(text, slot, fold != f, extra, y[:, k], weight)
                odds = np.where(fold == f, Chain._odds(model, *inside, extra, n), odds)
            chain.thresholds.append(_best_cut(odds, y[:, k], weight))
            chain.models.append(Chain._fit_one(text, slot, np.ones(n, dtype=bool), extra, y[:, k], weight))
            extra = np.column_stack([extra, np.clip(odds, -15, 15)])
        return chain

    def predict(self, texts: list[str]) -> np.ndarray:
        """Probabilities, texts x categories."""
        text, slot, lettered = features(texts)
        n = len(texts)
        extra = np.zeros((n, 0))
        for model in self.models:
            extra = np.column_stack([extra, np.clip(self._odds(model, text, slot, extra, n), -15, 15)])
        p = 1 / (1 + np.exp(-extra))
        for k, (chosen, w) in enumerate(self.models):
            if chosen is None:
                p[:, k] = w
        p[~lettered] = 0
        return p


def train(docs: DataFrame, labels: DataFrame, categories: Sequence[str], sample_rows: int = SAMPLE_ROWS) -> Chain:
    """Fits on labelled documents; rows with a null label are left out, and an id's labels are the largest of its rows."""
    names = [f"y{i}" for i in range(len(categories))]
    labelled = labels.select(F.col("doc_id").cast("long").alias("doc_id"), *(F.col(c).cast("double").alias(y) for c, y in zip(categories, names, strict=True))).na.drop()
    labelled = labelled.groupBy("doc_id").agg(*(F.max(y).alias(y) for y in names))
    sides = [labelled.where(F.col(names[-1]) > 0), labelled.where(F.col(names[-1]) <= 0)]
    sizes = {r.positive: r.n for r in labelled.groupBy((F.col(names[-1]) > 0).alias("positive")).agg(F.count("*").alias("n")).collect()}
    positive = min(sizes.get(True, 0), sample_rows // 2)
    parts = [(sides[0], positive, sizes.get(True, 0)), (sides[1], sample_rows - positive, sizes.get(False, 0))]
    picked = [side.orderBy(F.xxhash64("doc_id"), "doc_id").limit(n).withColumn("weight", F.lit(max(1.0, whole / max(n, 1)))) for side, n, whole in parts]
    chosen = picked[0].union(picked[1])
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).where(F.col("text").isNotNull())

    def make():
        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            slots = []
            for part in pieces(b, "text", PIECE_BYTES):
                text, slot, _ = features(part.column(1).to_pylist())
                slots += [x.astype("<i4").tobytes() for x in np.split(slot, np.searchsorted(text, np.arange(1, part.num_rows)))]
            return pa.RecordBatch.from_arrays([b.column(0), *b.columns[2:], pa.array(slots, pa.binary())], ["doc_id", *names, "weight", "slots"])

        return each

    # the chosen ids are bounded by sample_rows
    rows = texts.join(F.broadcast(chosen), "doc_id")
    # one row an id: partial minima, so an id of many rows is no hot key
    rows = rows.groupBy("doc_id", *names, "weight").agg(F.min(F.struct(F.xxhash64("text").alias("h"), "text")).alias("r")).select("doc_id", F.col("r.text").alias("text"), *names, "weight")
    rows = over_batches(rows, make, "doc_id long, " + ", ".join(f"{y} double" for y in names) + ", weight double, slots binary")
    found = sorted((r.doc_id, bytes(r.slots), [r[y] for y in names], r.weight) for r in rows.toLocalIterator())
    slots = [np.frombuffer(s, dtype="<i4") for _, s, _, _ in found]
    ids = np.array([d for d, _, _, _ in found], dtype=np.int64).astype(np.uint64)
    text = np.repeat(np.arange(len(found)), [len(s) for s in slots]).astype(np.int64)
    y = np.array([y for _, _, y, _ in found], dtype=np.float64).reshape(len(found), len(names))
    return Chain.fit(categories, text, np.concatenate([np.empty(0, dtype="<i4"), *slots]), y, (mix(ids) % np.uint64(FOLDS)).astype(np.int64), np.array([w for _, _, _, w in found]))


def score(docs: DataFrame, chain: Chain, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, p_<category> for each)."""
    known = docs.sparkSession.sparkContext.broadcast(chain)
    names = [f"p_{c}" for c in chain.categories]

    def make():
        chain = known.value

        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            p = np.concatenate([chain.predict([t or "" for t in part.column(1).to_pylist()]) for part in pieces(b, "text", PIECE_BYTES)])
            return pa.RecordBatch.from_arrays([b.column(0), *(pa.array(np.ascontiguousarray(p[:, k])) for k in range(len(names)))], ["doc_id", *names])

        return each

    return over_batches(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), make, "doc_id long, " + ", ".join(f"{n} double" for n in names))


def op10_toxicity_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").withColumn("low_quality", 1 - F.col("quality"))
    chain = train(docs, labels, ("low_quality", "toxic"))
    return score(docs, chain).select("doc_id", "p_low_quality", "p_toxic", (F.col("p_toxic") >= chain.thresholds[-1]).alias("toxic"))


QUERIES = {"op10_toxicity_chain": op10_toxicity_chain}
ORACLES: dict[str, str] = {}
