import hashlib
import re
import time

from hypothesis import given, settings
from hypothesis import strategies as st

from descent_planner.llm import op3_pii_spans as op3

from . import edge

PATTERNS = [
    r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    r"[0-9]([\x20-]?[0-9])+",
    r"\+[0-9][\x20().0-9-]+[0-9]",
]


def plain(text):
    """The contract's patterns as they stand."""
    out = []
    for k, p in enumerate(PATTERNS):
        for m in re.finditer(p, text):
            d = re.sub("[^0-9]", "", m[0])
            ok = [True, k == 1 and all(int(x) <= 255 for x in m[0].split(".")), 12 <= len(d) <= 19 and op3.luhn(d), 9 <= len(d) <= 15][k]
            if ok:
                out.append((m.start(), k, m.end()))
    return sorted(out)


@settings(max_examples=400, deadline=None)
@given(st.text(alphabet="a.@-+ %0123456789()é", max_size=60))
def test_base_equals_the_patterns(text):
    assert op3.base_spans(text) == plain(text)


def found(text):
    base = op3.base_spans(text)
    return [(op3.KINDS[k], text[a:b]) for a, k, b in op3.added_spans(text, base)]


def test_disguises():
    for text, kind, span in [
        ("mail jane.doe (at) example (dot) com now", "email", "jane.doe (at) example (dot) com"),
        ("mail jane at example dot co dot uk", "email", "jane at example dot co dot uk"),
        ("j[at]mail.example.org!", "email", "j[at]mail.example.org"),
        ("write jаne@example.com", "email", "jаne@example.com"),  # a Cyrillic letter
        ("call plus four nine one two three four five six seven eight today", "phone", "plus four nine one two three four five six seven eight"),
        ("card ４１１１１１１１１１１１１１１１ ok", "card", "４１１１１１１１１１１１１１１１"),
        ("ip one nine two dot one six eight dot one dot two x", "ip", "one nine two dot one six eight dot one dot two"),
        ("+٤٩ ١٢٣٤٥٦٧٨٩", "phone", "+٤٩ ١٢٣٤٥٦٧٨٩"),
        ("a​b@ex​ample.com", "email", "a​b@ex​ample.com"),
    ]:
        assert (kind, span) in found(text), text


def test_partly_disguised():
    for text, kind, span in [
        ("call +1 four one five 555 0123 now", "phone", "+1 four one five 555 0123"),
        ("call +1 (four one five) 555 0123 now", "phone", "+1 (four one five) 555 0123"),
        ("host 192.168.one.two is up", "ip", "192.168.one.two"),
        ("host 192 dot 168 dot 1 dot two is up", "ip", "192 dot 168 dot 1 dot two"),
        ("card 4111 1111 1111 111 one ok", "card", "4111 1111 1111 111 one"),
        ("mail jane at firma dot cz today", "email", "jane at firma dot cz"),
        ("mail jane at mail dot firma dot photography", "email", "jane at mail dot firma dot photography"),
    ]:
        assert (kind, span) in found(text), text
    for text in ["room 12, one door", "chapter 3 one page, 2 two", "it looked at the dot matrix", "in 2019 one of 4 won", "we met at example.com"]:
        assert found(text) == [], text
    assert op3.redacted("at 192.168.one.two or +1 four one five 555 0123.") == "at <IP> or <PHONE>."
    for text in ["1 one " * 50_000, "1.one." * 50_000, "one(" * 50_000, "1 " * 150_000 + "one"]:
        op3.added_spans(text, [])


def test_clean_texts_stay():
    for text in ["meet me at the dot in one two three steps", "look at example com, one dot two", "Привет, это обычный текст 12", "array[at] (dot) product", "un deux trois, partez"]:
        assert found(text) == [] and op3.redacted(text) == text


def test_redaction():
    assert op3.redacted("to a@b.co or x (at) y.org, 10.0.0.1") == "to <EMAIL> or <EMAIL>, <IP>"


def test_long_runs_are_linear():
    for text in ["1" * 300_000, "a" * 300_000 + "@", "1 " * 150_000, "+1" + " " * 100_000, "x@" * 100_000, "one " * 20_000, "1.1." * 50_000]:
        base = op3.base_spans(text)
        op3.added_spans(text, base)


def test_op3(spark, sf, tmp_path):
    for folder in (sf, edge.tables(spark, tmp_path)):
        texts = dict(spark.read.parquet(f"{folder}/documents.parquet").select("doc_id", "text").collect())
        rows = op3.op3_pii_spans(spark, folder).collect()
        assert len(rows) == len(texts)
        for r in rows:
            want = plain(texts[r.doc_id] or "")
            assert r.base_sha256 == hashlib.sha256(op3.show(want).encode()).hexdigest()
            assert [r.n_email, r.n_ip, r.n_card, r.n_phone] == [sum(k == i for _, k, _ in want) for i in range(4)]
    assert op3.redact(edge.documents(spark)).columns == edge.documents(spark).columns


def test_hostile_texts_take_linear_time():
    for text in ["x at " + "bb-dot-" * 150_000 + "zzzz9", "x at " + "bb dot " * 140_000, "x-at-bb-dot-" * 80_000, "bb-at-" * 160_000 + "b-dot-cz", "one " * 250_000 + "onex", "1 one " * 160_000 + "onex", "(" * 1_000_000, "( " * 500_000, "a" + " " * 1_000_000 + "(at", "+1" * 500_000]:
        began = time.monotonic()
        op3.added_spans(text, op3.base_spans(text))
        assert time.monotonic() - began < 6, text[:20]
    assert found("x at " + "bb-dot-" * 12 + "com now")[0][0] == "email"


def test_looks_for_odd_characters_in_few_steps():
    odd = op3._rules()[0]
    characters = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    expected = [c for c in characters if ord(c) in op3._letters() or c in op3._HIDDEN]
    assert odd.findall(characters) == expected == [c for c in characters if op3._is_odd()[ord(c)]]
    assert op3._holds_odd("é 𝐚") and not op3._holds_odd("é日a")
    text = "straße müde " * 100_000
    began = time.process_time()
    assert op3.added_spans(text, []) == []
    assert time.process_time() - began < 1  # before: above 2 s
