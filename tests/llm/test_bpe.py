import numpy as np
import public_tokenizers as P
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from descent_planner.llm import bpe

PATH = P.path("byte_bpe_50k.json")
LIB = Tokenizer.from_file(PATH)
CASES = ["", " ", "  \n x", "it's we're I'll 'tis ''s 'store x's's", "a  b　c", "日本語 テスト１２３", "<|endoftext|>", "a<|endoftext|> b<|endoftext|>", "x" * 3000, "ab" * 700 + " " * 300, "\r\n\t  1234567890 $%^ é́", "'ſ 'S 'RE"]


def both(texts):
    for e in (bpe.tree_encoder(PATH), bpe.library_encoder(PATH)):
        ids, n = e(texts)
        yield [x.tolist() for x in np.split(ids, np.cumsum(n)[:-1])]


def test_cases_equal_the_library():
    want = [e.ids for e in LIB.encode_batch(CASES, add_special_tokens=False)]
    for _ in range(2):  # with an empty and a filled cache
        for got in both(CASES):
            assert got == want
    v = bpe.vocabulary(PATH)
    for ids in want:
        assert v.decode(np.array(ids, dtype=np.int64)).decode() == LIB.decode(ids, skip_special_tokens=False)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.text(alphabet=st.one_of(st.sampled_from(" '\n\tstrevemld.,1"), st.characters(exclude_categories=["Cs", "Cn"]))), min_size=1, max_size=4))
def test_any_text(texts):
    want = [e.ids for e in LIB.encode_batch(texts, add_special_tokens=False)]
    for got in both(texts):
        assert got == want


def test_decode_of_cut_characters():
    ids = LIB.encode("😀é", add_special_tokens=False).ids[:1]
    assert bpe.vocabulary(PATH).decode(np.array(ids)).decode() == LIB.decode(ids, skip_special_tokens=False)


@pytest.mark.parametrize("word", ["aaaaaaaaaaaaaaaaaaaa", "abcabcabc" * 30])
def test_ties_go_left(word):
    assert bpe.TreeMerger(bpe.vocabulary(PATH))([word])[0].tolist() == LIB.encode(word, add_special_tokens=False).ids


def test_columns_equal_trees():
    rng = np.random.default_rng(5)
    words = ["".join(rng.choice(list("aeinrsth o'é漢€\n"), size=n)) for n in [*range(1, 80), *rng.integers(1, 40, 4000)]]
    raw = [w.encode() for w in words]
    flat, length = b"".join(raw), np.array([len(x) for x in raw])
    v = bpe.vocabulary(PATH)
    columns = bpe.ColumnMerger(v)
    for got, want in zip(columns.merge(flat, length), bpe.TreeMerger(v).merge(flat, length), strict=True):
        assert got.tolist() == want.tolist()
    # every pair is found in the table, and no other
    a, b = v.pair_keys >> 20, v.pair_keys & 0xFFFFF
    assert (columns._found(a, b) == v.pair_ranks).all()
    assert (columns._found(b, a + 1) == np.where(columns._ranks(b, a + 1) == columns.NONE, -1, columns._ranks(b, a + 1))).all()
    want = [e.ids for e in LIB.encode_batch(CASES, add_special_tokens=False)]
    for _ in range(2):
        ids, n = bpe.column_encoder(PATH)(CASES)
        assert [x.tolist() for x in np.split(ids, np.cumsum(n)[:-1])] == want
