"""Language identification of mixed-language texts.

A word is a run of letters. Its scripts, by ranges of code points, narrow the languages to those whose training
words used that script. Within them, every place of the word adds learned log scores of the letter groups that end
there (two to five letters, word edges included). Viterbi decoding with a penalty for each switch labels the words
of a text; equal labels in a row are a span. The text's language is the one with the most letters.

The model is fitted on a bounded sample of labelled rows, ``SAMPLE_ROWS`` at most, taken by the hash of their ids, of
an id's rows the one of least hash of text and language; so it is the same in every run. Their whole texts go to the
driver, as many as those. The model has ``2^BITS`` entries a language. Every text is scored whole.

Null texts and texts without a letter are ``und`` with score 0. Where no language was learned (an empty table, no
labels) every text is ``und``. The score is the share of the text's letters in the predicted language. Ties go to
the language that sorts first. Rows stay one for one.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import LETTER, _classes
from .hashing import mix
from .shared import over_batches, pieces

#: Most labelled rows that the model is fitted on.
SAMPLE_ROWS = 4_000
BITS = 18
GROUPS = (2, 3, 4, 5)
SWITCH = 6.0
#: Most letters a batch holds, but for single longer texts.
PIECE_BYTES = 100_000
#: Most bytes of text that are decoded side by side, but for single longer texts: steps cost by the longest text of those.
DECODE_BYTES = 8_000_000

# First code points of blocks of letters, and the script each begins.
SCRIPTS = (
    (0x0000, "latin"), (0x0370, "greek"), (0x0400, "cyrillic"), (0x0530, "armenian"), (0x0590, "hebrew"), (0x0600, "arabic"),
    (0x0780, "other"), (0x0900, "indic"), (0x0E00, "thai"), (0x0E80, "other"), (0x10A0, "georgian"), (0x1100, "hangul"),
    (0x1200, "other"), (0x1C80, "cyrillic"), (0x1C90, "other"), (0x1D00, "latin"), (0x1F00, "greek"), (0x2000, "latin"),
    (0x2C80, "other"), (0x3040, "kana"), (0x3100, "han"), (0x3130, "hangul"), (0x3190, "han"), (0xA4D0, "other"),
    (0xAC00, "hangul"), (0xD800, "other"), (0xF900, "han"), (0xFB00, "latin"), (0xFB13, "other"), (0xFF21, "latin"),
    (0xFF65, "kana"), (0xFFA0, "hangul"), (0xFFE0, "other"), (0x20000, "han"), (0x323B0, "other"),
)
SCRIPT_NAMES = sorted({name for _, name in SCRIPTS})


@lru_cache(maxsize=1)
def _script_of() -> np.ndarray:
    first = np.array([x for x, _ in SCRIPTS])
    return np.array([SCRIPT_NAMES.index(n) for _, n in SCRIPTS], dtype=np.uint8)[np.searchsorted(first, np.arange(0x110000), "right") - 1]


class Letters:
    """The words of some texts as arrays: hashed letter groups of each place, word edges and scripts."""

    def __init__(self, texts: list[str]):
        joined = "\n".join(texts).lower() + "\n"
        points = np.frombuffer(joined.encode("utf-32-le"), dtype=np.uint32)
        # lower() may lengthen a text: the ends are those of its lower-case form
        self.ends = np.cumsum([len(t.lower()) + 1 for t in texts]) - 1
        letter = _classes()[points] == LETTER
        edge = np.flatnonzero(np.diff(np.concatenate([[False], letter, [False]]).astype(np.int8)))
        self.starts, stops = edge[::2], edge[1::2]
        self.sizes = stops - self.starts
        self.word_count = np.diff(np.concatenate([[0], np.searchsorted(self.starts, self.ends)]))
        # letters of all words, each word between two edge marks
        total = self.sizes + 2
        self.first = np.cumsum(total) - total
        n = int(total.sum())
        symbols = np.full(n, 0x20, dtype=np.uint64)
        inner = np.ones(n, dtype=bool)
        inner[self.first] = False
        inner[self.first + total - 1] = False
        symbols[inner] = points[letter]
        self.scripts = np.zeros(len(self.starts), dtype=np.uint32)
        if n:
            bits = np.zeros(n, dtype=np.uint32)
            bits[inner] = np.uint32(1) << _script_of()[points[letter]].astype(np.uint32)
            self.scripts = np.bitwise_or.reduceat(bits, self.first)
        within = np.arange(n) - np.repeat(self.first, total)
        self.slots = []
        symbols = mix(symbols + np.uint64(77))
        h = symbols
        for size in range(2, max(GROUPS) + 1):
            h = h.copy()
            h[1:] = symbols[1:] + h[:-1] * np.uint64(0x9FB21C651E98DF25)
            if size in GROUPS:
                slot = (mix(h + np.uint64(size)) >> np.uint64(64 - BITS)).astype(np.int64)
                self.slots.append((np.flatnonzero(within >= size - 1), slot))


class Model:
    """Log scores of letter groups for each language, and which scripts each language uses."""

    def __init__(self, languages: list[str], scores: np.ndarray, scripts: np.ndarray):
        self.languages, self.scores, self.scripts = languages, scores, scripts

    @staticmethod
    def fit(rows: list[tuple[str, str]]) -> Model:
        languages = sorted({lang for _, lang in rows})
        counts = np.zeros((1 << BITS, len(languages)), dtype=np.float64)
        scripts = np.zeros(len(languages), dtype=np.uint32)
        for k, lang in enumerate(languages):
            texts = [t for t, own in rows if own == lang and t]
            for at in range(0, len(texts), 64):
                found = Letters(texts[at : at + 64])
                for where, slot in found.slots:
                    counts[:, k] += np.bincount(slot[where], minlength=1 << BITS)
                share = np.bincount(found.scripts, minlength=1)
                for s in np.flatnonzero(share):
                    scripts[k] |= np.uint32(s)
        total = counts.sum(axis=0)
        # groups that no text had say nothing; others are smoothed towards the mean of all languages
        mean = (counts.sum(axis=1, keepdims=True) + 0.5) / (total.sum() + 0.5)
        scores = np.log((counts + 5 * mean * len(languages)) / (total + 5 * len(languages)) / mean)
        scores[counts.sum(axis=1) == 0] = 0
        return Model(languages, np.clip(scores, -4, 4).astype(np.float32), scripts)

    def words(self, found: Letters) -> np.ndarray:
        """A score of each word for each language; languages without the word's scripts are out, unless all are."""
        n = len(found.starts)
        k = len(self.languages)
        if not n:
            return np.zeros((0, k), dtype=np.float32)
        total = int(found.first[-1] + found.sizes[-1] + 2)
        place = np.zeros((total, k), dtype=np.float32)
        for where, slot in found.slots:
            place[where] += self.scores[slot[where]]
        out = np.add.reduceat(place, found.first, axis=0) / len(GROUPS)
        fits = (found.scripts[:, None] & ~self.scripts[None, :]) == 0
        out[~fits & fits.any(axis=1)[:, None]] -= 1e3
        return out


def viterbi(scores: np.ndarray, counts: np.ndarray, penalty: float) -> np.ndarray:
    """The best labels of the words of each text; the texts are decoded side by side, word by word.

    With one penalty for all switches, a label's best past is its own or the best one's less the penalty.
    """
    n, k = scores.shape
    labels = np.zeros(n, dtype=np.int8)
    order = np.argsort(-counts, kind="stable")
    size = counts[order]
    first = (np.cumsum(counts) - counts)[order]
    longest = int(size[0]) if len(size) else 0
    # texts that still have a word at each step, longest first
    active = np.searchsorted(-size, -np.arange(1, longest + 1), "right")
    base = np.concatenate([[0], np.cumsum(active)])
    came = np.zeros((int(base[-1]), k), dtype=np.int8)
    value = np.zeros((len(size), k), dtype=np.float64)
    final = np.zeros(len(size), dtype=np.int64)
    for step in range(longest):
        m = active[step]
        v = value[:m]
        best = v.argmax(axis=1)
        switched = v[np.arange(m), best][:, None] - penalty
        stay = v >= switched
        came[base[step] : base[step] + m] = np.where(stay, np.arange(k), best[:, None])
        value[:m] = np.where(stay, v, switched) + scores[first[:m] + step]
    final = value.argmax(axis=1) if len(size) else final
    for step in range(longest - 1, -1, -1):
        m = active[step]
        labels[first[:m] + step] = final[:m]
        final[:m] = came[base[step] : base[step] + m][np.arange(m), final[:m]]
    return labels


def _decoded(batch: pa.RecordBatch, column: int, model: Model) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray, np.ndarray]]:
    """Parts of a batch with the text and the label of each word, and each text's letters by language."""
    k = max(1, len(model.languages))
    for part in pieces(batch, "text", DECODE_BYTES):
        scores, counts, sizes = [], [], []
        for small in pieces(part, "text", PIECE_BYTES):
            found = Letters([t or "" for t in small.column(column).to_pylist()])
            scores.append(model.words(found))
            counts.append(found.word_count)
            sizes.append(found.sizes.astype(np.int32))
        del found
        count, size = np.concatenate(counts), np.concatenate(sizes)
        # all words' scores are the most that is held here: the lists they came in go before they are decoded
        score = np.concatenate(scores)
        scores.clear(), sizes.clear()
        label = viterbi(score, count, SWITCH) if model.languages else np.zeros(len(size), dtype=np.int8)
        del score
        text = np.repeat(np.arange(part.num_rows), count)
        yield part, text, label, np.bincount(text * k + label, weights=size, minlength=part.num_rows * k).reshape(-1, k)


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string")) % 4 == 2


def train(docs: DataFrame, where: Column | None = None, sample_rows: int = SAMPLE_ROWS, id_col: str = "doc_id") -> Model:
    """Fits on labelled rows that meet ``where``: the ``sample_rows`` of lowest hashed id, with their whole texts."""
    rows = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    if where is not None:
        rows = rows.where(where)
    chosen = rows.select(F.xxhash64(id_col).alias("h"), F.col(id_col).alias("id")).distinct().orderBy("h", "id").limit(sample_rows).select(F.col("id").alias("_id"))
    texts = rows.select(F.col(id_col).alias("id"), "text", "lang").join(F.broadcast(chosen), F.expr("id <=> _id")).drop("_id")
    # one row an id: partial minima, so an id of many rows is no hot key
    texts = texts.groupBy("id").agg(F.min(F.struct(F.xxhash64("text", "lang").alias("h"), "text", "lang")).alias("r"))
    return Model.fit(sorted((r.r.text, r.r.lang) for r in texts.toLocalIterator()))


def identify(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", spans: bool = False) -> DataFrame:
    """(doc_id, lang_pred, score, n_spans), and with ``spans`` the labelled runs as ``language:words``."""

    def make():
        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            langs, shares, counts, shown = [], [], [], []
            for part, text, label, letters in _decoded(batch, 1, model):
                total = letters.sum(axis=1)
                best = letters.argmax(axis=1)
                none = (total == 0) | (not model.languages)
                langs += ["und" if z else model.languages[b] for z, b in zip(none.tolist(), best.tolist(), strict=True)]
                shares.append(np.where(none, 0.0, letters.max(axis=1) / np.maximum(total, 1)))
                turn = np.ones(len(label), dtype=bool)
                turn[1:] = (label[1:] != label[:-1]) | (text[1:] != text[:-1])
                counts.append(np.where(none, 0, np.bincount(text[turn], minlength=part.num_rows)))
                if spans:
                    at = np.flatnonzero(turn)
                    runs: list[list[str]] = [[] for _ in range(part.num_rows)]
                    for i, n in zip(at.tolist(), np.diff(np.append(at, len(label))).tolist(), strict=True):
                        runs[text[i]].append(f"{model.languages[label[i]] if model.languages else 'und'}:{n}")
                    shown += [",".join(x) for x in runs]
            cols = [batch.column(0), pa.array(langs), pa.array(np.concatenate(shares)), pa.array(np.concatenate(counts).astype(np.int64))]
            names = ["doc_id", "lang_pred", "score", "n_spans"]
            return pa.RecordBatch.from_arrays(cols + [pa.array(shown)] * spans, names + ["spans"] * spans)

        return each

    schema = "doc_id long, lang_pred string, score double, n_spans long" + ", spans string" * spans
    return over_batches(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), make, schema)


def keep_identified(docs: DataFrame, model: Model, least: float = 0.5) -> DataFrame:
    """The rows of ``docs`` whose language is told with at least that score, with ``lang`` set to it."""
    at, lang_at = docs.columns.index("text"), docs.columns.index("lang")

    def make():
        def each(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for part, _, _, letters in _decoded(batch, at, model) if model.languages else ():
                total = letters.sum(axis=1)
                ok = (total > 0) & (letters.max(axis=1) >= least * total)
                names = pa.array([model.languages[b] for b in letters.argmax(axis=1).tolist()], pa.string())
                yield part.set_column(lang_at, part.schema.field(lang_at), names.cast(part.schema.field(lang_at).type)).filter(pa.array(ok))

        return each

    return over_batches(docs, make, docs.schema)


def op5_language_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = train(docs, ~held_out(F.col("doc_id")))
    return identify(docs, model).select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "lang_pred", "score", "n_spans")


def python_held_out(doc_id: int) -> bool:
    return zlib.crc32(str(doc_id).encode()) % 4 == 2


QUERIES = {"op5_language_spans": op5_language_spans}
ORACLES: dict[str, str] = {}
