"""Near duplicates by fast similarity sketching, banding and exact verification.

A document's set holds its distinct word shingles, as 64-bit hashes. The sketch has ``bands * rows`` coordinates.
In round i every element of the set is thrown into one bin with the value i plus a hash in [0, 1), and each bin keeps
its least value. The first t rounds choose bins at random; round t + i puts every element into bin i, so that after
2t rounds no coordinate is empty. A document stops after the first round that leaves none empty. Coordinates agree
with the probability of the Jaccard similarity, as those of min-wise hashing, and estimates concentrate as if bins
were drawn without replacement.

Documents of equal sets are one class. A set too small to reach the threshold with any other set (one of fewer than
num / (den - num) elements) links by equality alone and needs no sketch. Classes that agree on a band are
candidates. At similarity s a pair shares no band with probability (1 - s^rows)^bands; the defaults make that under
1e-8 at the threshold. No bucket is capped and no pair is listed twice:

1. Star rounds: every bucket names a centre, and each class is compared with the centre it shares most bands with.
   In the first round a bucket's centre is the member that meets most others over all its buckets, most likely the
   text that near copies were made from; later rounds take centres by hash. Confirmed links make components.
2. What remains: classes that share a bucket with another component. Any linked pair of them shares one of the rare
   shingles at the head of both sets (see ``_prefixes``), so pairs come from those, and only pairs of different
   components that haven't been compared: neither a group of near copies nor the texts that quote one passage are
   listed pair by pair. This step loses nothing.

Links are confirmed on the full sets: the sets of candidates are made again from their texts, sent to their partners
by a sort-merge join, and intersected. Components come from minimum labels with pointer jumping, in tables.

Texts without words (null, empty, white space) have an empty set and no link. Rows of one id are one document: all
of them get one component, which joins those of their sets. Rows without an id join no component of others' by an
id; they are named by the least id of their set's component, null where there is none, and are always kept. Nothing
is collected but counts; ids of candidates are broadcast while there are ``BROADCAST_ROWS`` at most, else they are
joined by shuffling. Tables that no later job reads are removed. Texts are hashed in windows of ``PIECE_BYTES``, so
one very long text takes 8 bytes a word, not more.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bpe import ragged
from .hashing import mix, run_hashes
from .shared import Scratch, over_batches, pieces, saved

#: Bytes of text hashed at once, and elements and rows sketched at once.
PIECE_BYTES, SKETCH_ELEMENTS, SKETCH_ROWS = 250_000, 200_000, 2_000
#: Two or three longs each: 24 MB at most.
BROADCAST_ROWS = 1_000_000
STAR_ROUNDS = 2
_SPACES = np.isin(np.arange(256), [0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D])
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def _words(data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Where each word starts and ends, and its hash."""
    word = ~_SPACES[data]
    edge = np.flatnonzero(np.diff(np.concatenate([[False], word, [False]]).astype(np.int8)))
    starts, stops = edge[::2], edge[1::2]
    return starts, stops, run_hashes(data, starts, stops, 5) if len(starts) else np.empty(0, dtype=np.uint64)


def _windows(h: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    """Hashes of the ``size`` words from each place."""
    out = np.full(len(at), size, dtype=np.uint64)
    for k in range(size):
        out += h[at + k] * np.uint64((2 * k + 1) * 0x9E3779B97F4A7C15 % (1 << 64))
    return mix(out)


def _unique(values: np.ndarray) -> np.ndarray:
    values.sort()
    keep = np.ones(len(values), dtype=bool)
    np.not_equal(values[1:], values[:-1], out=keep[1:])
    return values[keep]


def _long_set(raw: bytes, size: int) -> np.ndarray:
    """The set of one text, hashed in windows that end between words; only the words' hashes are held."""
    held = []
    at = 0
    while at < len(raw):
        end = at + PIECE_BYTES
        # a window ends at white space, however far that is
        while end < len(raw) and raw[end] not in b"\x20\x09\x0a\x0b\x0c\x0d":
            end += 1
        held.append(_words(_LOWER[np.frombuffer(raw[at:end], dtype=np.uint8)])[2])
        at = end
    h = np.concatenate(held)
    size = min(size, len(h))
    return _unique(_windows(h, np.arange(len(h) - size + 1), size)) if size else h


def shingle_sets(texts: list[str | None], size: int) -> tuple[np.ndarray, np.ndarray]:
    """All sets in a row, each sorted, and how many elements each has."""
    raw = [(t or "").encode() for t in texts]
    if any(len(r) > PIECE_BYTES for r in raw) and len(raw) > 1:
        apart = [shingle_sets([t], size) for t in texts]
        return np.concatenate([x for x, _ in apart]), np.concatenate([n for _, n in apart])
    if raw and len(raw[0]) > PIECE_BYTES:
        own = _long_set(raw[0], size)
        return own, np.array([len(own)])
    data = _LOWER[np.frombuffer(b" ".join(raw) + b" ", dtype=np.uint8)]
    ends = np.cumsum([len(r) + 1 for r in raw])
    starts, _, h = _words(data)
    count = np.diff(np.concatenate([[0], np.searchsorted(starts, ends)]))
    first = np.cumsum(count) - count
    # one shingle for each word that has size - 1 after it; a shorter text's words make a single one
    n = np.where(count >= size, count - size + 1, np.minimum(count, 1))
    full = np.repeat(count >= size, n)
    at = ragged(first, n)
    out = np.empty(len(at), dtype=np.uint64)
    out[full] = _windows(h, at[full], size)
    for k in range(1, size):
        short = np.repeat(count == k, n)
        out[short] = _windows(h, at[short], k)
    stop = np.cumsum(n)
    for a, b in zip((stop - n).tolist(), stop.tolist(), strict=True):
        out[a:b].sort()
    owner = np.repeat(np.arange(len(texts)), n)
    keep = np.ones(len(out), dtype=bool)
    keep[1:] = (out[1:] != out[:-1]) | (owner[1:] != owner[:-1])
    return out[keep], np.bincount(owner[keep], minlength=len(texts))


def set_keys(elements: np.ndarray, sizes: np.ndarray) -> list[bytes | None]:
    """A hash of each set; None for an empty one."""
    data = elements.tobytes()
    return [hashlib.blake2b(data[8 * (e - k) : 8 * e], digest_size=16).digest() if k else None for e, k in zip(np.cumsum(sizes).tolist(), sizes.tolist(), strict=True)]


def _throw(out: np.ndarray, e: np.ndarray, row, i: int, t: int) -> None:
    """Round i for elements ``e`` of the sketches that start at ``row`` in ``out``."""
    h = mix(e + np.uint64((i + 1) * 0x9E3779B97F4A7C15 % (1 << 64)))
    if i < t:
        # the bin comes from bits apart from the value's
        at = (((h & np.uint64(0xFFFFFFFF)) * np.uint64(t)) >> np.uint64(32)).astype(np.int64) + row
        if i:
            # a coordinate that an earlier round filled stays
            open_ = np.flatnonzero(out[at] >= np.uint64(i) << np.uint64(48))
            at, h = at[open_], h[open_]
        h = mix(h)
    else:
        at = row + (i - t)
    h >>= np.uint64(16)
    h |= np.uint64(i) << np.uint64(48)
    np.minimum.at(out, at, h)


def sketches(elements: np.ndarray, sizes: np.ndarray, t: int) -> np.ndarray:
    """A row of t coordinates for each set; rows of empty sets are all ones."""
    n = len(sizes)
    full = np.uint64(0xFFFFFFFFFFFFFFFF)
    out = np.full(n * t, full, dtype=np.uint64)
    first = np.cumsum(sizes) - sizes
    large = sizes > SKETCH_ELEMENTS
    for k in np.flatnonzero(large).tolist():
        own, mine = elements[first[k] : first[k] + sizes[k]], out[k * t : (k + 1) * t]
        for i in range(2 * t):
            for at in range(0, len(own), SKETCH_ELEMENTS):
                _throw(mine, own[at : at + SKETCH_ELEMENTS], 0, i, t)
            if (mine != full).all():
                break
    live = np.flatnonzero((sizes > 0) & ~large)
    for i in range(2 * t):
        if not len(live):
            break
        own = sizes[live]
        _throw(out, elements[ragged(first[live], own)], np.repeat(live * t, own), i, t)
        if i < t or (i + 1) % 8 == 0:
            live = live[(out.reshape(n, t)[live] == full).any(axis=1)]
    return out.reshape(n, t)


def band_keys(sketch: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """A 64-bit key of each band, that differs between bands."""
    parts = sketch.reshape(len(sketch), bands, rows)
    key = np.broadcast_to(np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0xA24BAED4963EE407), parts.shape[:2])
    for r in range(rows):
        key = mix(key + parts[:, :, r])
    return key.view(np.int64) if key.flags.c_contiguous else np.ascontiguousarray(key).view(np.int64)


class Params:
    def __init__(self, shingle: int, num: int, den: int, bands: int, rows: int, fold=None):
        """Link where den * intersection >= num * union. ``fold`` rewrites a text before it is read."""
        self.shingle, self.num, self.den, self.bands, self.rows, self.fold = shingle, num, den, bands, rows, fold

    def sets(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        return shingle_sets(texts if self.fold is None else [t and self.fold(t) for t in texts], self.shingle)


#: 3-word shingles at 0.85: a link is missed with probability 1e-8 at most.
CONTRACT = Params(3, 85, 100, 25, 4)
#: 5-word shingles at 0.8: 6e-9.
CORPUS = Params(5, 80, 100, 36, 4)


def bands_of(elements: np.ndarray, sizes: np.ndarray, p: Params) -> tuple[np.ndarray, np.ndarray]:
    """The band keys of all sets in a row, and how many each has: all, or none where a set can only link to its equals."""
    can = sizes * (p.den - p.num) >= p.num
    total = np.cumsum(sizes)
    which = np.flatnonzero(can)
    made, at = [np.empty(0, dtype=np.int64)], 0
    while at < len(which):
        base = total[which[at]] - sizes[which[at]]
        end = max(at + 1, min(at + SKETCH_ROWS, int(np.searchsorted(total[which], base + SKETCH_ELEMENTS, "right"))))
        some = which[at:end]
        own = elements[ragged(total[some] - sizes[some], sizes[some])]
        made.append(band_keys(sketches(own, sizes[some], p.bands * p.rows), p.bands, p.rows).reshape(-1))
        at = end
    return np.concatenate(made), np.where(can, p.bands, 0)


def windowed_sets(texts: list[str | None], p: Params) -> tuple[np.ndarray, np.ndarray]:
    """``p.sets`` of some texts, ``PIECE_BYTES`` at a time."""
    elements, n = [], []
    size = np.array([len(t or "") for t in texts], dtype=np.int64)
    total, at = np.cumsum(size), 0
    while at < len(texts):
        end = max(at + 1, int(np.searchsorted(total, total[at] - size[at] + PIECE_BYTES, "right")))
        e, k = p.sets(texts[at:end])
        elements.append(e)
        n.append(k)
        at = end
    return np.concatenate(elements), np.concatenate(n)


def sketch_columns(e: np.ndarray, k: np.ndarray, p: Params) -> list[pa.Array]:
    """n_shingles, set_key and bands of some texts by their sets. Each round of a sketch has a price of its own, so many sets go together."""
    flat, many = bands_of(e, k, p)
    return [pa.array(k.astype(np.int64)), pa.array(set_keys(e, k), pa.binary()), pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(many)]).astype(np.int32)), pa.array(flat))]


SKETCHED = "n_shingles long, set_key binary, bands array<long>"


def sketched(docs: DataFrame, p: Params) -> DataFrame:
    """(doc_id, n_shingles, set_key, bands) for each row."""

    def make():
        def each(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for part in pieces(b, "text", 4 * PIECE_BYTES):
                yield pa.RecordBatch.from_arrays([part.column(0), *sketch_columns(*windowed_sets(part.column(1).to_pylist(), p), p)], ["doc_id", "n_shingles", "set_key", "bands"])

        return each

    return over_batches(docs.select("doc_id", "text"), make, "doc_id long, " + SKETCHED)


def confirmed(docs: DataFrame, pairs: DataFrame, p: Params) -> DataFrame:
    """Those of ``pairs`` (a, b) that are linked, by their texts' full sets."""
    num, den, sets_of = p.num, p.den, p.sets

    def make_sets():
        def each(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for part in pieces(b, "text", PIECE_BYTES):
                elements, n = sets_of(part.column(2).to_pylist())
                data, ends = elements.tobytes(), np.cumsum(n)
                sets = [data[8 * (e - k) : 8 * e] for e, k in zip(ends.tolist(), n.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(sets, pa.binary())], ["id", "to", "elements"])

        return each

    # the set of a goes to b; that of b stays under its own id
    sends = pairs.select(F.col("a").alias("id"), F.col("b").alias("to"))
    stays = pairs.select(F.col("b").alias("id"), F.lit(None).cast("long").alias("to")).distinct()
    wanted = sends.union(stays)
    text = docs.select(F.col("doc_id").alias("id"), "text")
    small = pairs.count() * 2 <= BROADCAST_ROWS
    found = (text.join(F.broadcast(wanted), "id") if small else text.join(wanted.hint("merge"), "id")).select("id", "to", "text")
    sets = over_batches(found, make_sets, "id long, to long, elements binary")
    left = sets.where(F.col("to").isNotNull()).select(F.col("id").alias("a"), F.col("to").alias("b"), F.col("elements").alias("x"))
    right = sets.where(F.col("to").isNull()).select(F.col("id").alias("b"), F.col("elements").alias("y"))

    def make_test():
        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            ok = []
            # views of the batch; a copy of all its sets would double it
            for x, y in zip(b.column(2), b.column(3), strict=True):
                both = np.concatenate([np.frombuffer(v.as_buffer(), dtype=np.uint64) for v in (x, y)])
                both.sort()
                inter = int((both[1:] == both[:-1]).sum())
                ok.append(den * inter >= num * (len(both) - inter))
            return b.select([0, 1]).filter(pa.array(ok))

        return each

    return over_batches(left.join(right.hint("merge"), "b").select("a", "b", "x", "y"), make_test, "a long, b long")


#: The table of shingle frequencies has 2^16 to 2^22 slots (16 MB) of 32 bits by how many shingles are counted; beyond
#: that rare and common shingles are told apart less well, which costs time and loses no link.
LEAST_BITS, MOST_BITS = 16, 22
#: The table travels in blocks of 2^12 slots, each a row.
BLOCK_BITS = 12


_BLOCKS = "block long, slots binary, n binary"


def _block_rows(blocks: Iterator[tuple[int, np.ndarray]]) -> Iterator[pa.RecordBatch]:
    """A row for each block that has counts: its number, the places of those that aren't 0, and what they are."""
    for block, own in blocks:
        slot = np.flatnonzero(own)
        if len(slot):
            yield pa.RecordBatch.from_arrays([pa.array([block]), pa.array([slot.astype("<u2").tobytes()], pa.binary()), pa.array([own[slot].astype("<i4").tobytes()], pa.binary())], ["block", "slots", "n"])


def _prefixes(docs: DataFrame, members: DataFrame, p: Params) -> DataFrame:
    """(element, place, id, n, comp): the rarest shingles of each member, as many as make sure that linked sets share one.

    Two sets that share at least ceil(t n) of n elements, put in one order, agree somewhere in their first
    n - ceil(t n) + 1. The order takes shingles that few members have first, by counts in a table of fixed size;
    what all texts of a group share comes last, so that a passage doesn't bring its texts together.
    """
    num, den, sets_of = p.num, p.den, p.sets
    text = docs.select(F.col("doc_id").alias("id"), "text")
    many, shingles = members.agg(F.count("*"), F.coalesce(F.sum("n_shingles"), F.lit(0))).first()
    bits = min(MOST_BITS, max(LEAST_BITS, int(shingles).bit_length()))
    members = members.select("id", "comp").distinct()
    found = text.join(F.broadcast(members) if many <= BROADCAST_ROWS else members.hint("merge"), "id").select("id", "comp", "text")
    low = np.uint64(64 - bits)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << bits, dtype=np.int32)
        for b in batches:
            for part in pieces(b, "text", PIECE_BYTES):
                elements, _ = sets_of(part.column(2).to_pylist())
                np.add.at(total, (elements >> low).astype(np.int64), 1)
        yield from _block_rows((at, total[at << BLOCK_BITS : (at + 1) << BLOCK_BITS]) for at in range(1 << (bits - BLOCK_BITS)))

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for b in batches:
            for block, slots, n in zip(*(b.column(i).to_pylist() for i in range(3)), strict=True):
                if block not in sums:
                    sums[block] = np.zeros(1 << BLOCK_BITS, dtype=np.int64)
                sums[block][np.frombuffer(slots, dtype="<u2")] += np.frombuffer(n, dtype="<i4")
        yield from _block_rows((block, np.minimum(own, 2**31 - 1)) for block, own in sums.items())

    counts = np.zeros(1 << bits, dtype=np.int32)
    for r in found.mapInArrow(count, _BLOCKS).repartition("block").mapInArrow(add, _BLOCKS).collect():
        counts[r.block << BLOCK_BITS : (r.block + 1) << BLOCK_BITS][np.frombuffer(r.slots, dtype="<u2")] = np.frombuffer(r.n, dtype="<i4")
    known = docs.sparkSession.sparkContext.broadcast(counts)

    def make_heads():
        counts = known.value

        def each(b: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for part in pieces(b, "text", PIECE_BYTES):
                elements, n = sets_of(part.column(2).to_pylist())
                owner = np.repeat(np.arange(part.num_rows), n)
                order = np.lexsort((elements, counts[(elements >> low).astype(np.int64)], owner))
                first = np.cumsum(n) - n
                # of n elements at least the share num / den is common
                take = np.where(n > 0, n - -(-num * n // den) + 1, 0)
                out = elements[order][ragged(first, take)].view(np.int64)
                place = np.arange(len(out)) - np.repeat(np.cumsum(take) - take, take)
                row = pa.array(np.repeat(np.arange(part.num_rows), take))
                yield pa.RecordBatch.from_arrays([pa.array(out), pa.array(place), part.column(0).take(row), pa.array(np.repeat(n, take).astype(np.int64)), part.column(1).take(row)], ["element", "place", "id", "n", "comp"])

        return each

    return over_batches(found, make_heads, "element long, place long, id long, n long, comp long")


def components(edges: DataFrame, name: str, scratch: Scratch) -> DataFrame:
    """(id, comp) of every id in ``edges`` (a, b): the smallest id reachable.

    Each round gives an id the least label around it, then that label's own label; ids that nobody names keep theirs.
    """
    own = Scratch(edges.sparkSession)
    both = own.saved(edges.union(edges.select("b", "a")).distinct(), f"{name}-edges")
    labels = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("comp"))
    labels = own.saved(labels, f"{name}-labels")
    while True:
        near = both.join(labels.select(F.col("id").alias("b"), "comp").hint("merge"), "b").groupBy(F.col("a").alias("id")).agg(F.min("comp").alias("near"))
        new = labels.join(near, "id").select("id", F.col("comp").alias("old"), F.least("comp", "near").alias("comp"))
        jump = labels.select(F.col("id").alias("comp"), F.col("comp").alias("further"))
        round_of = Scratch(edges.sparkSession)
        new = round_of.saved(new.join(jump.hint("merge"), "comp").select("id", "old", F.least("comp", "further").alias("comp")), f"{name}-labels")
        if new.where("old <> comp").isEmpty():
            own.drop()
            scratch.take(round_of)
            return new.select("id", "comp")
        own.take(round_of)
        labels = new.select("id", "comp")


def one_document(rows: DataFrame, classes: DataFrame) -> DataFrame:
    """(a, b): the classes that meet in one id, by their ids; rows of an id mostly have one set, and then there are none."""
    more = rows.where("doc_id is not null and set_key is not null").groupBy("doc_id").agg(F.min(F.xxhash64("set_key")).alias("low"), F.max(F.xxhash64("set_key")).alias("high")).where("low <> high").select("doc_id")
    ids = rows.join(more.hint("merge"), "doc_id").join(classes.hint("merge"), "set_key").select("doc_id", "rep").distinct()
    # an id of several sets stands for itself, so that classes of one representative meet too
    return ids.select(F.col("doc_id").alias("a"), F.col("rep").alias("b")).where("a <> b")


def set_components(docs: DataFrame, p: Params, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """(doc_id, n_shingles, set_key) of each row, and (set_key, comp) of each different set."""
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    rows = saved(sketched(docs, p), "near-sketches")
    return rows.select("doc_id", "n_shingles", "set_key"), components_of(docs, rows, p)


def components_of(docs: DataFrame, rows: DataFrame, p: Params) -> DataFrame:
    """(set_key, comp) of each different set of the saved sketches ``rows`` of ``docs`` (doc_id, text)."""
    scratch = Scratch(docs.sparkSession)
    classes = scratch.saved(rows.where("set_key is not null").groupBy("set_key").agg(F.min("doc_id").alias("rep")), "near-classes")
    reps = rows.join(classes.hint("merge"), (rows.set_key == classes.set_key) & (rows.doc_id == classes.rep)).select("rep", "n_shingles", "bands")
    buckets = reps.select(F.explode("bands").alias("key"), "rep", "n_shingles")
    shared = buckets.groupBy("key").agg(F.min("rep").alias("low"), F.max("rep").alias("high"), F.count("*").alias("members")).where("low <> high").select("key", "members")
    buckets = scratch.saved(buckets.join(shared.hint("merge"), "key"), "near-shared")
    # a class that meets many others is likely the text that its near copies were made from
    meets = buckets.groupBy("rep").agg(F.sum("members").alias("meets"))
    buckets = scratch.saved(buckets.join(meets.hint("merge"), "rep").select("key", "rep", "n_shingles", "meets"), "near-buckets")

    links = scratch.saved(one_document(rows, classes), "near-links")
    tested = comps = None
    for turn in range(STAR_ROUNDS):
        first = -F.col("meets") if turn == 0 else F.xxhash64("rep", F.lit(turn))
        order = F.struct(first.alias("o"), "rep", "n_shingles")
        centres = buckets.groupBy("key").agg(F.min(order).alias("c"))
        near = buckets.join(centres.hint("merge"), "key").where("rep <> c.rep").select(F.col("rep").alias("a"), F.col("c.rep").alias("b"), F.col("n_shingles").alias("na"), F.col("c.n_shingles").alias("nb"))
        near = near.where(F.greatest("na", "nb") * p.num <= F.least("na", "nb") * p.den)
        stars = near.groupBy("a", "b").agg(F.count("*").alias("n"))
        if comps is not None:
            stars = _apart(stars, comps)
        stars = stars.groupBy("a").agg(F.max(F.struct("n", "b")).alias("m")).select("a", F.col("m.b").alias("b"))
        stars = scratch.saved(stars.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "near-stars")
        if tested is not None:
            stars = stars.join(tested, ["a", "b"], "left_anti")
        tested = stars if tested is None else tested.union(stars)
        links = links.union(scratch.saved(confirmed(docs, stars, p), "near-links"))
        comps = components(links, "near", scratch)

    # pairs of one bucket whose components differ
    labelled = buckets.join(comps.withColumnRenamed("id", "rep").hint("merge"), "rep", "left").select("key", "rep", "n_shingles", F.coalesce("comp", "rep").alias("comp"))
    labelled = scratch.saved(labelled, "near-labelled")
    open_keys = labelled.groupBy("key").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low <> high").select("key")
    left = labelled.join(open_keys.hint("merge"), "key")
    members = scratch.saved(left.select(F.col("rep").alias("id"), "comp", "n_shingles").distinct(), "near-members")
    heads = scratch.saved(_prefixes(docs, members, p), "near-heads")
    meet = heads.groupBy("element").agg(F.min("comp").alias("low"), F.max("comp").alias("high")).where("low <> high").select("element")
    heads = heads.join(meet.hint("merge"), "element")
    x = heads.select("element", F.col("id").alias("a"), F.col("comp").alias("ca"), F.col("n").alias("na"), F.col("place").alias("ia"))
    y = heads.select("element", F.col("id").alias("b"), F.col("comp").alias("cb"), F.col("n").alias("nb"), F.col("place").alias("ib"))
    # where the first shared element stands bounds how many can follow it
    room = F.least(F.col("na") - F.col("ia"), F.col("nb") - F.col("ib")) * (p.den + p.num) >= p.num * (F.col("na") + F.col("nb"))
    rest = x.join(y.hint("merge"), "element").where((F.col("a") < F.col("b")) & (F.col("ca") != F.col("cb")) & room)
    rest = scratch.saved(rest.select("a", "b").distinct().join(tested, ["a", "b"], "left_anti"), "near-rest")
    if not rest.isEmpty():
        links = links.union(scratch.saved(confirmed(docs, rest, p), "near-links"))
        comps = components(links, "near", scratch)

    named = saved(classes.join(comps.withColumnRenamed("id", "rep").hint("merge"), "rep", "left").select("set_key", F.coalesce("comp", "rep").alias("comp")), "near-named")
    scratch.drop()
    return named


def near_duplicates(docs: DataFrame, p: Params, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, kept)."""
    rows, named = set_components(docs, p, id_col, text_col)
    out = rows.join(named.hint("merge"), "set_key", "left")
    return out.select("doc_id", "n_shingles", F.coalesce("comp", "doc_id").alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def _apart(stars: DataFrame, comps: DataFrame) -> DataFrame:
    """Those (a, b, n) whose ends aren't in one component yet."""
    a = comps.select(F.col("id").alias("a"), F.col("comp").alias("ca"))
    b = comps.select(F.col("id").alias("b"), F.col("comp").alias("cb"))
    joined = stars.join(a.hint("merge"), "a", "left").join(b.hint("merge"), "b", "left")
    return joined.where(F.coalesce("ca", "a") != F.coalesce("cb", "b")).select("a", "b", "n")


def drop_near_duplicates(docs: DataFrame, p: Params = CORPUS) -> DataFrame:
    """The rows of ``docs`` without all but the smallest id of each group; rows of a repeated id stay together, and so do null ids."""
    kept = near_duplicates(docs, p).where(~F.col("kept")).select(F.col("doc_id").alias("_gone"))
    gone = saved(kept.distinct(), "near-gone")
    ids = F.col("doc_id").cast("long")
    if gone.count() <= BROADCAST_ROWS:
        return docs.join(F.broadcast(gone), ids == F.col("_gone"), "left_anti")
    return docs.join(gone.hint("merge"), ids == F.col("_gone"), "left_anti")


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"), CONTRACT)


QUERIES = {"op7_near_duplicates": op7_near_duplicates}
ORACLES: dict[str, str] = {}
