"""Personal data in texts, with disguises undone and spans kept in source offsets.

Base patterns find plain emails, IPv4 addresses, card and phone numbers. A chain of transducers then rewrites the
text (look-alike letters, spelled digits, at/dot disguises), each keeping for every character of its output the
source range it came from. What the same patterns find in the rewritten text, over a range that a transducer
changed, is mapped back and added; base spans stay.

Null and empty texts have no spans. Rows stay one for one, repeated ones too. Offsets are code points, ends exclusive.
The work on a text is linear in its length: no pattern can split a run in two ways, and a spelled host has labels of
``LABEL`` characters and ``LABELS`` of them at most, as in the names of hosts.
"""

from __future__ import annotations

import hashlib
import re
import unicodedata
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .op6_bpe_codec import PIECE_BYTES
from .shared import over_batches, pieces

KINDS = ("email", "ip", "card", "phone")

# Letters of other scripts that look like Latin ones.
LOOKALIKES = dict(
    zip(
        "аеіоорсухѕјһԁѵкмнтвАВЕКМНОРСТХУІЅЈαεοριυνκΑΒΕΖΗΙΚΜΝΟΡΤΥΧ",
        "aeioopcyxsjhdvkmhtbABEKMHOPCTXYISJaeopiuvkABEZHIKMNOPTYX",
        strict=True,
    )
)

# Names of the digits in four languages.
DIGIT_NAMES = (
    "zero oh null zéro cero",
    "one eins un uno",
    "two zwei deux dos",
    "three drei trois tres",
    "four vier quatre cuatro",
    "five fünf cinq cinco",
    "six sechs seis",
    "seven sieben sept siete",
    "eight acht huit ocho",
    "nine neun neuf nueve",
)
DIGIT_OF = {name: str(d) for d, names in enumerate(DIGIT_NAMES) for name in names.split()}

# Words that stand before a dot in plain speech ("at the dot in"), so that they are no host.
NO_HOST = "the a an this that these those each every any one no my your his her its our their which what last first next"

#: The longest label of a host's name, and the most labels of one.
LABEL, LABELS = 63, 16

# The @ with its local part is looked up from the @ on, so that long runs of its letters cost one pass.
_DOMAIN = re.compile(r"@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]+)++")
# A run of digits is tried from its first one: from any other it would go on alike.
_DIGIT = re.compile("[0-9]")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"(?<![0-9])[0-9](?:[ -]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        v = ord(d) - 48
        if i % 2:
            v = 2 * v - 9 if v > 4 else 2 * v
        total += v
    return total % 10 == 0


def _emails(text: str) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    last, at = 0, text.find("@")
    while at >= 0:
        # backwards over the local part: at most to the end of the match or of the run before
        start = at
        while start > last and _is_local(text[start - 1]):
            start -= 1
        found = _DOMAIN.match(text, at) if start < at else None
        if found:
            out.append((start, found.end()))
            last = found.end()
            at = text.find("@", last)
        else:
            last = at + 1
            at = text.find("@", at + 1)
    return out


def _is_local(c: str) -> bool:
    return c in "._%+-" or ("0" <= c <= "9") or ("a" <= c <= "z") or ("A" <= c <= "Z")


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of plain identifiers, leftmost and without overlap in each kind."""
    out = []
    if "@" in text:
        out += [(a, 0, b) for a, b in _emails(text)]
    digit = _DIGIT.search(text)
    if digit is None:
        return sorted(out)
    for m in _IP.finditer(text, digit.start()):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or "0") <= 255 for p in m[0].split(".")):
            out.append((m.start(), 1, m.end()))
    for m in _CARD.finditer(text, digit.start()):
        digits = m[0].replace(" ", "").replace("-", "")
        if 12 <= len(digits) <= 19 and luhn(digits):
            out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 9 <= sum("0" <= c <= "9" for c in m[0]) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


@lru_cache(maxsize=1)
def _letters() -> dict[int, str]:
    """Each look-alike's plain character: the fixed letters, other scripts' digits, and compatibility forms of ASCII."""
    table = {ord(k): v for k, v in LOOKALIKES.items()}
    for lo, hi in ((0x0660, 0x0A00), (0xFF01, 0xFF5F), (0x1D400, 0x1D800), (0x2460, 0x2500)):
        for cp in range(lo, hi):
            plain = unicodedata.normalize("NFKC", chr(cp))
            if len(plain) == 1 and plain.isascii() and plain.isprintable() and plain != " ":
                table[cp] = plain
            elif (digit := unicodedata.digit(chr(cp), None)) is not None and unicodedata.category(chr(cp)) == "Nd":
                table[cp] = str(digit)
    return table


#: Characters without width, which may stand inside an identifier.
_HIDDEN = "​‌‍⁠﻿­"


@lru_cache(maxsize=1)
def _is_odd() -> np.ndarray:
    """Of each code point, whether the first transducer changes it."""
    table = np.zeros(0x110000, dtype=bool)
    table[[*_letters(), *map(ord, _HIDDEN)]] = True
    return table


def _holds_odd(text: str) -> bool:
    """Whether a text has a character that the first transducer changes. A search by pattern tries most of a thousand
    characters at each place, as those beyond the basic plane are no part of a class's bit map."""
    return bool(_is_odd()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)].any())


def _odd_class() -> str:
    """A class of those characters, made of ranges, which are tried faster than as many single ones."""
    edge = np.flatnonzero(np.diff(_is_odd().astype(np.int8), prepend=0, append=0)).tolist()
    return "[" + "".join(f"{re.escape(chr(a))}-{re.escape(chr(b - 1))}" for a, b in zip(edge[::2], edge[1::2], strict=True)) + "]"


class Rewritten:
    """A text with the source range of each of its characters, and which characters a transducer made."""

    def __init__(self, text: str):
        self.text = text
        self.starts = range(len(text))
        self.ends = range(1, len(text) + 1)
        self.changed = bytes(len(text))

    def apply(self, pattern: re.Pattern, to) -> None:
        """Replace each match for which ``to`` gives a text; the new characters share the match's source range."""
        parts, starts, ends, changed, last = [], [], [], [], 0
        for m in pattern.finditer(self.text):
            new = to(m)
            if new is None:
                continue
            a, b = m.span()
            parts += [self.text[last:a], new]
            starts += [*self.starts[last:a], *[self.starts[a]] * len(new)]
            ends += [*self.ends[last:a], *[self.ends[b - 1]] * len(new)]
            changed += [self.changed[last:a], b"\1" * len(new)]
            last = b
        if parts:
            self.text = "".join([*parts, self.text[last:]])
            self.starts = [*starts, *self.starts[last:]]
            self.ends = [*ends, *self.ends[last:]]
            self.changed = b"".join([*changed, self.changed[last:]])

    def source(self, a: int, b: int) -> tuple[int, int]:
        return self.starts[a], self.ends[b - 1]


@lru_cache(maxsize=1)
def _rules() -> tuple:
    letters = _letters()
    odd = re.compile(_odd_class())
    names = "|".join(sorted(DIGIT_OF, key=len, reverse=True))
    between = r"(?:[ ,.-]{1,3})"
    point = r"(?:dot|point|punkt|punto)"
    # four names or more in a row; single digits and the word "plus" may stand among them
    spelled = re.compile(rf"(?<!\w)(?:plus{between})?(?:(?:{names}|[0-9]){between}(?:{point}{between})?){{3,}}(?:{names}|[0-9])(?!\w)", re.I)
    token = re.compile(r"\w+|[^\w]+")
    box_at = re.compile(r"(?<!\s)\s*[(\[{<]\s*(?:at|@)\s*[)\]}>]\s*", re.I)
    box_dot = re.compile(r"(?<!\s)\s*[(\[{<]\s*(?:dot|point|punkt|punto|\.)\s*[)\]}>]\s*", re.I)
    # any digit groups and names in a row, of which one adjoins the other
    sep = r"(?:[ ,.()-]{1,3})"
    item = rf"(?:{names}|[0-9]++)(?!\w)"
    wide = re.compile(rf"(?<!\w)(?:plus{sep})?{item}(?:{sep}(?:{point}{sep})?{item})++", re.I)
    # bare words count only in the whole shape: name at host dot ending, whatever the ending; a label stops at a spelled dot
    dot = r"(?:\s++|_|-)dot(?:\s++|_|-)"
    label = rf"(?:[A-Za-z0-9]|-(?!dot(?:\s|_|-))){{1,{LABEL}}}+"
    bare = re.compile(rf"(?<=[A-Za-z0-9])(?:\s+|_|-)at(?:\s+|_|-)(?!(?:{'|'.join(NO_HOST.split())})\b)(?={label}(?:{dot}{label}){{0,{LABELS - 2}}}{dot}[A-Za-z]{{2,{LABEL}}}\b)", re.I)
    mixed = re.compile(r"(?<=[A-Za-z0-9])(?:\s+|_|-)dot(?:\s+|_|-)(?=[A-Za-z0-9])", re.I)

    def digits(m: re.Match) -> str | None:
        words = token.findall(m[0].lower())
        if sum(w in DIGIT_OF for w in words) < 4:
            return None
        # separators vanish, but a spelled point is one
        return "".join(DIGIT_OF.get(w, w if w.isdigit() else {"plus": "+"}.get(w, "." if w in ("dot", "point", "punkt", "punto") else "")) for w in words if w[0].isalnum())

    def group(dots: bool):
        def to(m: re.Match) -> str | None:
            words = token.findall(m[0].lower())
            if not any(w in DIGIT_OF for w in words):
                return None
            # with ``dots`` a single point between two groups stays, as in an address
            return "".join(DIGIT_OF.get(w, w if w[0].isdigit() else {"plus": "+", "dot": ".", "point": ".", "punkt": ".", "punto": "."}.get(w, "." if dots and w == "." else "")) for w in words)

        return to

    return odd, lambda m: letters.get(ord(m[0]), ""), ((spelled, digits), (wide, group(False)), (wide, group(True))), box_at, box_dot, bare, mixed


#: Quick signs that a transducer has anything to do.
_SIGN = re.compile(r"[(\[{<]\s*(?:at|@|dot|point|punkt|punto|\.)\s*[)\]}>]|[\s_-]dot[\s_-]", re.I)


@lru_cache(maxsize=1)
def _spelled_sign() -> re.Pattern:
    names = "|".join(sorted(DIGIT_OF, key=len, reverse=True))
    return re.compile(rf"(?<!\w)(?:{names})[ ,.-]{{1,3}}(?:(?:point|dot|punkt|punto)[ ,.-]{{1,3}})?(?:{names}|[0-9])[ ,.-]", re.I)


def _names_in(low: str) -> int:
    """How many words of a lower-case text name a digit; cheaper than the pattern, which only a few texts then see."""
    words = low.replace(",", " ").replace(".", " ").replace("-", " ").split()
    return sum(map(DIGIT_OF.__contains__, words))


#: A group of digits, from which a name of a digit is looked for on both sides.
_GROUP = re.compile("[0-9]+")


@lru_cache(maxsize=1)
def _beside() -> tuple[re.Pattern, re.Pattern]:
    names = "|".join(sorted(DIGIT_OF, key=len, reverse=True))
    sep = "[ ,.()-]{1,3}"
    point = rf"(?:(?:dot|point|punkt|punto){sep})?"
    return re.compile(rf"{sep}{point}(?:{names})(?!\w)", re.I), re.compile(rf"(?<!\w)(?:{names}){sep}{point}\Z", re.I)


def _adjoins(text: str) -> bool:
    """Whether a name of a digit stands beside a group of digits."""
    after, before = _beside()
    return any(after.match(text, m.end()) or before.search(text[max(0, m.start() - 24) : m.start()]) for m in _GROUP.finditer(text))


def added_spans(text: str, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Spans of disguised identifiers, in source offsets."""
    odd, letter, runs, box_at, box_dot, bare, mixed = _rules()
    has_odd = not text.isascii() and _holds_odd(text)
    low = text.lower()
    has_sign = ("dot" in low or any(c in text for c in "([{<")) and _SIGN.search(text) is not None
    # names of look-alike letters show only after the first transducer
    named = _names_in(low.replace("(", " ").replace(")", " "))
    has_spelled = has_odd or named >= 2 and _spelled_sign().search(text) is not None or named >= 1 and _adjoins(text)
    if not (has_odd or has_sign or has_spelled):
        return []
    known = {(a, k, b) for a, k, b in base}
    out = set()
    # each way of reading runs of digits stands for itself, and what any of them shows counts
    for run in runs if has_spelled else (None,):
        r = Rewritten(text)
        sign = has_sign
        if has_odd:
            r.apply(odd, letter)
            sign = sign or _SIGN.search(r.text) is not None
        if run:
            before = r.text
            r.apply(*run)
            if run is not runs[0] and r.text == before:
                continue
        if sign:
            r.apply(box_at, lambda m: "@")
            r.apply(bare, lambda m: "@")
            r.apply(box_dot, lambda m: ".")
            # a bare dot counts within what follows an @
            r.apply(re.compile(rf"(?<=@)[A-Za-z0-9-]+(?:(?:{mixed.pattern})[A-Za-z0-9-]+)+", re.I), lambda m: mixed.sub(".", m[0]))
        for a, kind, b in base_spans(r.text):
            s, e = r.source(a, b)
            # a changed character, or hidden ones that left
            if (r.changed.find(b"\1", a, b) >= 0 or e - s != b - a) and (s, kind, e) not in known:
                out.add((s, kind, e))
    return sorted(out)


def show(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def redacted(text: str) -> str:
    """The text with every span replaced by its kind; spans that overlap become one, named by the first."""
    base = base_spans(text)
    spans = sorted(base + added_spans(text, base))
    if not spans:
        return text
    out, last = [], 0
    merged: list[list[int]] = []
    for a, k, b in spans:
        if merged and a < merged[-1][2]:
            merged[-1][2] = max(merged[-1][2], b)
        else:
            merged.append([a, k, b])
    for a, k, b in merged:
        out += [text[last:a], f"<{KINDS[k].upper()}>"]
        last = b
    return "".join([*out, text[last:]])


def find_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Counts of base spans, the hash of their list, all spans as text, and how many were added."""

    def make():
        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            counts, hashes, shown, more = [], [], [], []
            for part in pieces(batch, "text", 8 * PIECE_BYTES):
                for text in part.column(1).to_pylist():
                    base = base_spans(text) if text else []
                    extra = added_spans(text, base) if text else []
                    counts.append([sum(k == i for _, k, _ in base) for i in range(4)])
                    hashes.append(hashlib.sha256(show(base).encode()).hexdigest())
                    shown.append(show(base + extra))
                    more.append(len(extra))
            cols = [pa.array([c[i] for c in counts], pa.int64()) for i in range(4)]
            return pa.RecordBatch.from_arrays([batch.column(0), *cols, pa.array(hashes), pa.array(shown), pa.array(more, pa.int64())], ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans", "n_added"])

        return each

    schema = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"
    return over_batches(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), make, schema)


def redact(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The same columns, with identifiers in ``text_col`` replaced by their kinds; null texts stay null."""
    index = docs.columns.index(text_col)

    def make():
        def each(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            for part in pieces(batch, text_col, 8 * PIECE_BYTES):
                texts = pa.array([t if t is None else redacted(t) for t in part.column(index).to_pylist()], part.schema.field(index).type)
                yield part.set_column(index, part.schema.field(index), texts)

        return each

    return over_batches(docs, make, docs.schema)


def op3_pii_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_spans(spark.read.parquet(f"{sf_dir}/documents.parquet"))


QUERIES = {"op3_pii_spans": op3_pii_spans}
ORACLES: dict[str, str] = {}
