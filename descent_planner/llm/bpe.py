"""Byte-level BPE over whole batches of texts.

``tree_encoder`` cuts texts into words by the vocabulary's pattern with array operations over code points. Each word's
ids come from a bounded direct-mapped cache; words it lacks go to ``TreeMerger``: a segment tree over the ranks of
adjacent pairs. The root names the lowest rank, leftmost on ties; a merge changes three leaves and the paths above
them. Words of like size share one array of trees. ``library_encoder`` gives whole texts to the tokenizers library.

Defined results: null and empty texts have no ids; the text of an added token is that token, as in the library.
"""

from __future__ import annotations

import json
import re
from functools import lru_cache

import numpy as np

from .hashing import run_hashes
from .shared import on_other_work

SPACE, LETTER, NUMBER, OTHER, EDGE = 0, 1, 2, 3, 4
#: A long word is merged alone, so that no array of trees is wide.
WIDE = 64


@lru_cache(maxsize=1)
def _classes() -> np.ndarray:
    """The class of every code point: the pattern's space, letter and number, and the rest."""
    import regex

    every = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    table = np.full(0x110000, OTHER, dtype=np.uint8)
    for kind, pattern in ((LETTER, r"\p{L}+"), (NUMBER, r"\p{N}+"), (SPACE, r"\p{White_Space}+")):
        for m in regex.finditer(pattern, every):
            a, b = ord(m[0][0]), ord(m[0][-1]) + 1
            table[a:b] = kind
    return table


def word_starts(points: np.ndarray, edges: np.ndarray) -> np.ndarray:
    """True where a word starts. ``edges``: positions of single separators between texts, each a word of its own."""
    c = _classes()[points]
    c[edges] = EDGE
    n = len(c)
    start = np.ones(n, dtype=bool)
    start[1:] = (c[1:] != c[:-1]) | (c[1:] == EDGE)
    # a run after white space takes a plain space before it, and other white space stands alone
    after = np.flatnonzero(start[1:] & (c[1:] != SPACE) & (c[1:] != EDGE) & (c[:-1] == SPACE)) + 1
    joined = after[points[after - 1] == 0x20]
    start[after - 1] = True
    start[joined] = False
    # an apostrophe at a word's start takes these letters
    mark = np.flatnonzero((points[:-1] == 0x27) & start[:-1] & (c[1:] == LETTER))
    if len(mark):
        one = points[mark + 1]
        two = np.where(mark + 2 < n, points[np.minimum(mark + 2, n - 1)], 0)
        short = np.isin(one, [ord(x) for x in "stmd"])
        pair = [(ord(a), ord(b)) for a, b in ("re", "ve", "ll")]
        long = np.zeros(len(mark), dtype=bool)
        for a, b in pair:
            long |= (one == a) & (two == b)
        for hit, size in ((short, 1), (long & ~short, 2)):
            at = mark[hit]
            start[at + 1] = False
            end = at + 1 + size
            start[end[end < n]] = True
    return start


class Vocabulary:
    """What a byte-level BPE file of the tokenizers library holds."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        vocab: dict[str, int] = model["vocab"]
        self.added = {x["content"]: x["id"] for x in spec.get("added_tokens", [])}
        shown = _shown_bytes()
        back = {v: k for k, v in shown.items()}
        size = max([*vocab.values(), *self.added.values()]) + 1
        self.bytes_of: list[bytes] = [b""] * size
        for word, i in vocab.items():
            self.bytes_of[i] = bytes(back[x] for x in word) if all(x in back for x in word) else word.encode()
        for word, i in self.added.items():
            self.bytes_of[i] = word.encode()
        self.of_byte = np.array([vocab[shown[b]] for b in range(256)], dtype=np.int64)
        pairs = [x.split(" ") if isinstance(x, str) else x for x in model["merges"]]
        key = np.array([(vocab[a] << 20) | vocab[b] for a, b in pairs], dtype=np.int64)
        order = np.argsort(key)
        self.pair_keys, self.pair_ranks = key[order], order.astype(np.int64)
        self.merged = np.array([vocab[a + b] for a, b in pairs], dtype=np.int64)
        self.rank_of = dict(zip(key.tolist(), range(len(pairs)), strict=True))
        joined = b"".join(self.bytes_of)
        self.flat = np.frombuffer(joined, dtype=np.uint8)
        self.lengths = np.array([len(x) for x in self.bytes_of], dtype=np.int64)
        self.offsets = np.concatenate([[0], np.cumsum(self.lengths)])[:-1]

    def decode(self, ids: np.ndarray) -> bytes:
        """UTF-8 of the text that the ids stand for; bytes that aren't UTF-8 become replacement characters."""
        if not len(ids):
            return b""
        size = self.lengths[ids]
        out = self.flat[ragged(self.offsets[ids], size)].tobytes()
        try:
            out.decode("utf-8")
        except UnicodeDecodeError:
            out = out.decode("utf-8", "replace").encode()
        return out


def _shown_bytes() -> dict[int, str]:
    """The printable stand-in of each byte: itself where it prints, else the next free code point from 256 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return {b: chr(b) if b in plain else chr(next(spare)) for b in range(256)}


def ragged(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The indices starts[i], starts[i]+1, ... of sizes[i] items, one run after the other."""
    total = int(sizes.sum())
    ends = np.cumsum(sizes)
    out = np.arange(total, dtype=np.int64)
    return out + np.repeat(starts - (ends - sizes), sizes)


class TreeMerger:
    """Merges words with segment trees over the ranks of adjacent pairs."""

    NONE = np.iinfo(np.int64).max
    #: Leaves of the trees that are merged side by side.
    LEAVES = 320_000
    #: Most bytes of the words that are merged side by side.
    WIDTHS = (2, 4, 8, 16, 32, WIDE)

    def __init__(self, vocabulary: Vocabulary):
        self.v = vocabulary
        # leaves hold rank * width + place
        self.kind = np.int32 if (len(vocabulary.merged) + 1) * WIDE < np.iinfo(np.int32).max else np.int64
        byte = vocabulary.of_byte
        #: The rank of each pair of bytes.
        self.first_ranks = self._ranks(np.repeat(byte, 256), np.tile(byte, 256))

    def __call__(self, words: list[str]) -> list[np.ndarray]:
        raw = [w.encode() for w in words]
        ids, sizes = self.merge(b"".join(raw), np.array([len(w) for w in raw], dtype=np.int64))
        return np.split(ids, np.cumsum(sizes)[:-1]) if raw else []

    def merge(self, data: bytes, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Words of these lengths in bytes, one after the other: all ids in a row, and how many each word has."""
        flat = np.frombuffer(data, dtype=np.uint8)
        first = np.cumsum(length) - length
        sizes = np.zeros(len(length), dtype=np.int64)
        made: list[tuple[np.ndarray, np.ndarray]] = []
        for i in np.flatnonzero(length > WIDE).tolist():
            ids = self._alone(data[first[i] : first[i] + length[i]])
            sizes[i] = len(ids)
            made.append((np.array([i]), ids))
        low = 0
        for width in self.WIDTHS:
            which = np.flatnonzero((length > low) & (length <= width))
            step = self.LEAVES // width
            for at in range(0, len(which), step):
                part = which[at : at + step]
                ids, sizes[part] = self._together(flat, first[part], length[part], width)
                made.append((part, ids))
            low = width
        starts = np.cumsum(sizes) - sizes
        out = np.empty(int(sizes.sum()), dtype=np.int64)
        for part, ids in made:
            out[ragged(starts[part], sizes[part])] = ids
        return out, sizes

    def _ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of each pair, NONE where it can't merge."""
        key = (a << 20) | b
        at = np.minimum(np.searchsorted(self.v.pair_keys, key), len(self.v.pair_keys) - 1)
        return np.where(self.v.pair_keys[at] == key, self.v.pair_ranks[at], self.NONE)

    def _together(self, flat: np.ndarray, first: np.ndarray, length: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Ids, and how many each word has, of words of at most n bytes; places and nodes are numbered through all words."""
        count = len(first)
        none = np.iinfo(self.kind).max
        place = np.arange(n)
        inside = place < length[:, None]
        byte = np.zeros(count * n, dtype=np.int64)
        byte[inside.ravel()] = flat[ragged(first, length)]
        symbol = np.where(inside.ravel(), self.v.of_byte[byte], -1)
        linked = place + 1 < length[:, None]
        after = np.where(linked, place + 1, -1).ravel()
        before = np.tile(np.arange(-1, n - 1), count)
        pair = np.flatnonzero(linked.ravel())
        rank = self.first_ranks[(byte[pair] << 8) | byte[pair + 1]]
        ok = rank != self.NONE
        grid = np.full((count, 2 * n), none, dtype=self.kind)
        tree = grid.reshape(-1)
        tree[(pair[ok] // n) * (2 * n) + n + pair[ok] % n] = rank[ok] * n + pair[ok] % n
        low = n
        while low > 1:
            half = low // 2
            np.minimum(grid[:, low : 2 * low : 2], grid[:, low + 1 : 2 * low : 2], out=grid[:, half:low])
            low = half

        def value(a: np.ndarray, b: np.ndarray, left: np.ndarray) -> np.ndarray:
            r = self._ranks(symbol[a], symbol[b])
            return np.where(r == self.NONE, none, np.where(r == self.NONE, 0, r) * n + left)

        live = np.flatnonzero(grid[:, 1] != none)
        while len(live):
            root = tree[live * (2 * n) + 1].astype(np.int64)
            left, rank = root % n, root // n
            word = live * n
            right = after[word + left]
            beyond = after[word + right]
            symbol[word + left] = self.v.merged[rank]
            symbol[word + right] = -1
            after[word + left] = beyond
            more, prior = beyond >= 0, before[word + left]
            before[(word + beyond)[more]] = left[more]
            own = np.full(len(live), none, dtype=np.int64)
            own[more] = value((word + left)[more], (word + beyond)[more], left[more])
            some = prior >= 0
            w, p = word[some], prior[some]
            # three leaves change, and the minima above them
            base = np.concatenate([live, live, live[some]]) * (2 * n)
            node = np.concatenate([n + right, n + left, n + p])
            tree[base + node] = np.concatenate([np.full(len(live), none, dtype=np.int64), own, value(w + p, w + left[some], p)])
            for _ in range(n.bit_length() - 1):
                node >>= 1
                two = base + 2 * node
                tree[base + node] = np.minimum(tree[two], tree[two + 1])
            live = live[tree[live * (2 * n) + 1] != none]
        kept = symbol >= 0
        return symbol[kept], kept.reshape(count, n).sum(axis=1)

    def _alone(self, word: bytes) -> np.ndarray:
        """One long word, with lists."""
        rank_of, merged = self.v.rank_of, self.v.merged
        symbol = self.v.of_byte[np.frombuffer(word, dtype=np.uint8)].tolist()
        m = len(symbol)
        n = 1 << (m - 1).bit_length()
        none = 1 << 62
        tree = [none] * (2 * n)
        for i in range(m - 1):
            rank = rank_of.get((symbol[i] << 20) | symbol[i + 1])
            if rank is not None:
                tree[n + i] = rank * n + i
        for k in range(n - 1, 0, -1):
            tree[k] = min(tree[2 * k], tree[2 * k + 1])
        after, before = [*range(1, m), -1], [*range(-1, m - 1)]

        def put(i: int, value: int) -> None:
            k = n + i
            tree[k] = value
            k >>= 1
            while k:
                a, b = tree[2 * k], tree[2 * k + 1]
                value = a if a < b else b
                if tree[k] == value:
                    return
                tree[k] = value
                k >>= 1

        def pair(i: int, j: int) -> int:
            rank = rank_of.get((symbol[i] << 20) | symbol[j])
            return none if rank is None else rank * n + i

        while tree[1] != none:
            rank, left = divmod(tree[1], n)
            right = after[left]
            symbol[left] = int(merged[rank])
            symbol[right] = -1
            beyond = after[left] = after[right]
            put(right, none)
            if beyond >= 0:
                before[beyond] = left
                put(left, pair(left, beyond))
            else:
                put(left, none)
            if before[left] >= 0:
                put(before[left], pair(before[left], left))
        return np.array([x for x in symbol if x >= 0], dtype=np.int64)


class ColumnMerger(TreeMerger):
    """Merges short words without trees: row i holds the i-th symbol of all words and row i of the ranks its pair with
    the next, and what follows a merged pair moves up by a row. Longer words take the trees."""

    WIDTHS = (8, 16, 32, WIDE)
    #: Bits of a place.
    BITS = 5
    NO_PAIR = 1 << 30

    def __init__(self, vocabulary: Vocabulary):
        super().__init__(vocabulary)
        key = self.v.pair_keys
        self.shift = np.uint64(64 - max(8, (4 * len(key)).bit_length()))
        self.held = np.full((1 << int(64 - self.shift)) + 64, -1, dtype=np.int64)
        self.rank = np.full(len(self.held), -1, dtype=np.int32)
        rest, at = np.arange(len(key)), self._slot(key)
        while len(rest):
            if at[rest].max() >= len(self.held):
                self.held, self.rank = (np.concatenate([x, np.full(len(x), -1, dtype=x.dtype)]) for x in (self.held, self.rank))
            # of those that want an empty slot one gets it, and the others go on to the next
            free = rest[self.held[at[rest]] < 0]
            self.held[at[free]] = key[free]
            rest = rest[self.held[at[rest]] != key[rest]]
            at[rest] += 1
        placed = self.held >= 0
        self.rank[placed] = self.v.pair_ranks[np.searchsorted(key, self.held[placed])]

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def _found(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of each pair, -1 where it can't merge."""
        key = (a.astype(np.int64) << 20) | b
        at = self._slot(key)
        held = self.held[at]
        out = self.rank[at]
        more = np.flatnonzero(held != key)
        out[more] = -1
        more = more[held[more] >= 0]
        while len(more):
            at[more] += 1
            held = self.held[at[more]]
            hit = held == key[more]
            out[more[hit]] = self.rank[at[more[hit]]]
            more = more[~hit & (held >= 0)]
        return out

    def _together(self, flat: np.ndarray, first: np.ndarray, length: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
        bits = self.BITS
        if n > 1 << bits or (len(self.v.merged) + 1) << bits >= self.NO_PAIR // 2:
            return super()._together(flat, first, length, n)
        count = len(first)
        byte = np.zeros((n, count), dtype=np.uint8)
        place = ragged(np.zeros(count, dtype=np.int64), length)
        byte[place, np.repeat(np.arange(count), length)] = flat[ragged(first, length)]
        row = np.arange(n, dtype=np.int32)[:, None]
        symbol = np.where(row < length, self.v.of_byte.astype(np.int32)[byte], np.int32(-1))
        ranks = np.where(self.first_ranks == self.NONE, self.NO_PAIR, np.minimum(self.first_ranks, self.NO_PAIR >> bits) << bits).astype(np.int32)
        # rank * n + place; the last row has no pair
        pair = np.full((n, count), self.NO_PAIR, dtype=np.int32)
        pair[:-1] = np.where(row[1:] < length, ranks[(byte[:-1].astype(np.uint16) << 8) | byte[1:]] + row[:-1], np.int32(self.NO_PAIR))
        merged = self.v.merged.astype(np.int32)
        ended = np.empty((count, n), dtype=np.int32)
        word = np.arange(count)
        while True:
            low = pair.min(axis=0)
            # a pair that can't merge loses a place when it moves up
            goes = low < self.NO_PAIR // 2
            live = np.flatnonzero(goes)
            if len(live) < 0.8 * len(word):
                over = np.flatnonzero(~goes)
                ended[word[over]] = symbol.take(over, axis=1).T
                word, symbol, pair, low = word[live], symbol.take(live, axis=1), pair.take(live, axis=1), low[live]
                live = np.arange(len(word))
            if not len(live):
                break
            root = low[live]
            left = root & np.int32((1 << bits) - 1)
            symbol[left, live] = merged[root >> bits]
            last = np.full(len(word), n, dtype=np.int32)
            last[live] = left
            moves = row[1 : n - 1] > last
            np.copyto(symbol[1 : n - 1], symbol[2:], where=moves)
            np.copyto(pair[1 : n - 1], pair[2:] - 1, where=moves)
            symbol[n - 1, live] = -1
            after = symbol[left + 1, live]
            own = np.full(len(live), self.NO_PAIR, dtype=np.int32)
            some = np.flatnonzero(after >= 0)
            back = np.flatnonzero(left > 0)
            fresh = symbol[left, live]
            found = self._found(np.concatenate([fresh[some], symbol[left[back] - 1, live[back]]]), np.concatenate([after[some], fresh[back]]))
            key = np.where(found >= 0, (found << bits) | np.concatenate([left[some], left[back] - 1]), np.int32(self.NO_PAIR))
            own[some] = key[: len(some)]
            pair[left, live] = own
            pair[left[back] - 1, live[back]] = key[len(some) :]
        kept = ended >= 0
        return ended[kept].astype(np.int64), kept.sum(axis=1)


class WholeTexts:
    """Encodes whole texts with the tokenizers library; truncation and padding stay off.

    A text beyond ``LONG`` characters goes in parts, cut between a letter and a space before a letter: there a word of
    the vocabulary's pattern ends, whatever stands around, and no added token holds that.
    """

    LONG = 1_000_000
    _CUT = re.compile(r"(?<=[^\W\d_]) (?=[^\W\d_])")

    def __init__(self, path: str):
        import os

        # a task has one core
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.t = Tokenizer.from_file(path)
        self.t.no_truncation()
        self.t.no_padding()
        self.narrow = self.t.get_vocab_size() <= 1 << 16

    def _cut(self, text: str) -> list[str]:
        out, at = [], 0
        while len(text) - at > self.LONG:
            m = self._CUT.search(text, at + self.LONG)
            if m is None:
                break
            out.append(text[at : m.start()])
            at = m.start()
        return [*out, text[at:]]

    def __call__(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """All ids in a row, and how many each text has."""
        if any(len(t or "") > self.LONG for t in texts):
            ids, n = [], []
            for text in texts:
                own = [self._ids([part])[0] for part in self._cut(text or "")]
                ids += own
                n.append(sum(map(len, own)))
            return np.concatenate(ids), np.array(n, dtype=np.int64)
        ids = self._ids([t or "" for t in texts])
        return np.concatenate([np.empty(0, dtype=np.uint32), *ids]), np.array([len(x) for x in ids], dtype=np.int64)

    def _ids(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, dtype=np.uint32) for e in self.t.encode_batch_fast(texts, add_special_tokens=False)]


class BatchEncoder:
    """Ids of many texts, through a cache of fixed size whose entries are told apart by 128 bits of hash."""

    SLOTS = 20
    POOL = 8_000_000

    def __init__(self, words, added: dict[str, int], size: int):
        self.words, self.added = words, added
        #: Whether ids fit 16 bits.
        self.narrow = size <= 1 << 16
        self._clear()

    def _clear(self) -> None:
        n = 1 << self.SLOTS
        # two hashes, and at << 32 | size + 1: one row a slot, so that a look-up meets one place of memory
        self.table = np.zeros((n, 3), dtype=np.uint64)
        self.pool, self.used = np.zeros(self.POOL, dtype=np.uint32), 0

    def __call__(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """All ids in a row, and how many each text has."""
        parts: list[str] = []
        owner: list[int] = []
        marks: list[tuple[int, int]] = []  # a part that ends in an added token, and its id
        for i, text in enumerate(texts):
            rest = [(text or "", None)]
            for token, number in self.added.items():
                if text and token in text:
                    rest = [y for part, end in rest for y in self._cut(part, end, token, number)]
            for part, end in rest:
                if end is not None:
                    marks.append((len(parts), end))
                parts.append(part)
                owner.append(i)
        ids, sizes = self._parts(parts)
        if marks:
            ends = np.cumsum(sizes)
            ids = np.insert(ids, [ends[k] for k, _ in marks], [x for _, x in marks])
            for k, _ in marks:
                sizes[k] += 1
        counts = np.bincount(np.array(owner, dtype=np.int64), weights=sizes, minlength=len(texts)).astype(np.int64)
        return ids, counts

    def _encoded(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        raw = [w.encode() for w in words]
        return self.words.merge(b"".join(raw), np.array([len(w) for w in raw], dtype=np.int64))

    @staticmethod
    def _cut(part: str, end: int | None, token: str, number: int) -> list[tuple[str, int | None]]:
        cut = part.split(token)
        return [(x, number) for x in cut[:-1]] + [(cut[-1], end)]

    def _parts(self, parts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        joined = "\n".join(parts) + "\n"
        points = np.frombuffer(joined.encode("utf-32-le"), dtype=np.uint32)
        edges = np.cumsum([len(p) + 1 for p in parts]) - 1
        starts = np.flatnonzero(word_starts(points, edges))
        ends = np.append(starts[1:], len(points))
        edge_words = np.searchsorted(starts, edges)
        word = np.ones(len(starts), dtype=bool)
        word[edge_words] = False
        per_part = np.diff(np.concatenate([[-1], edge_words])) - 1
        starts, ends = starts[word], ends[word]
        if not len(starts):
            return np.empty(0, dtype=np.uint32), np.zeros(len(parts), dtype=np.int64)
        h1, h2 = run_hashes(points, starts, ends, 1), run_hashes(points, starts, ends, 2)
        if self.used > self.POOL // 2:
            self._clear()
        slot = (h1 >> np.uint64(64 - self.SLOTS)).astype(np.int64)
        held = self.table.take(slot, axis=0)
        hit = (held[:, 0] == h1) & (held[:, 1] == h2) & (held[:, 2] > 0)
        at, size = (held[:, 2] >> np.uint64(32)).astype(np.int64), (held[:, 2] & np.uint64(0xFFFFFFFF)).astype(np.int64) - 1
        miss = np.flatnonzero(~hit)
        if len(miss):
            _, one, inverse = np.unique(h1[miss], return_index=True, return_inverse=True)
            new = miss[one]
            # two words of one first hash: the second hash tells, and such words are encoded one by one
            if (h2[new][inverse] != h2[miss]).any():
                new, inverse = miss, np.arange(len(miss))
            ids, sizes = self._encoded([joined[a:b] for a, b in zip(starts[new].tolist(), ends[new].tolist(), strict=True)])
            total = int(sizes.sum())
            if self.used + total > len(self.pool):
                self.pool = np.concatenate([self.pool, np.zeros(self.used + total - len(self.pool) + self.POOL, dtype=np.uint32)])
            where = self.used + np.cumsum(sizes) - sizes
            self.pool[self.used : self.used + total] = ids
            self.used += total
            at[miss], size[miss] = where[inverse], sizes[inverse]
            self.table[slot[new]] = np.stack([h1[new], h2[new], ((where << 32) | (sizes + 1)).astype(np.uint64)], axis=1)
        out = self.pool[ragged(at, size)]
        ends_of = np.cumsum(per_part)
        total = np.concatenate([[0], np.cumsum(size)])
        return out, total[ends_of] - total[ends_of - per_part]


@lru_cache(maxsize=2)
def vocabulary(path: str) -> Vocabulary:
    return Vocabulary(path)


@lru_cache(maxsize=2)
def tree_encoder(path: str) -> BatchEncoder:
    """The encoder of this Python worker; it lasts over tasks."""
    v = vocabulary(path)
    return BatchEncoder(TreeMerger(v), v.added, len(v.lengths))


@lru_cache(maxsize=2)
def column_encoder(path: str) -> BatchEncoder:
    """As ``tree_encoder``, for those who want the ids alone."""
    v = vocabulary(path)
    return BatchEncoder(ColumnMerger(v), v.added, len(v.lengths))


@lru_cache(maxsize=2)
def library_encoder(path: str) -> WholeTexts:
    return WholeTexts(path)


def _forget() -> None:
    for made in (vocabulary, tree_encoder, column_encoder, library_encoder):
        made.cache_clear()


on_other_work(_forget)
