import random
import re
import time
from collections import defaultdict

import duckdb
import numpy as np
import pytest

from descent_planner.llm import op4_conflict_packing as op4
from descent_planner.llm import op6_bpe_codec as op6
from descent_planner.llm import op8_site_lines as op8

from . import edge


def tightest(rows, capacity):
    """Best fit by looking at every bin."""
    bins = []
    for i in sorted(range(len(rows)), key=lambda i: (-rows[i][1], rows[i][0])):
        _, size, source, cluster = rows[i]
        fits = [(b["left"], k) for k, b in enumerate(bins) if b["left"] >= size and (source is None or source not in b["s"]) and (cluster is None or cluster not in b["c"])]
        if fits:
            b = bins[min(fits)[1]]
        else:
            bins.append(b := {"left": capacity, "s": set(), "c": set(), "n": []})
        b["left"] -= size
        b["s"].add(source)
        b["c"].add(cluster)
        b["n"].append(size)
    return sorted(sorted(b["n"]) for b in bins)


@pytest.mark.parametrize("seed", range(8))
def test_tightest_compatible_bin(seed):
    """The residual chosen is always the least that is compatible."""
    rng = random.Random(seed)
    rows = [(i, rng.randint(1, 60), rng.choice([None, *"abcde"]), rng.choice([None, 1, 2, 3])) for i in range(300)]
    placed = op4.pack_group(rows, 64)
    bins = defaultdict(lambda: [64, set(), set()])
    for i, _, number, size in placed:
        _, _, s, c = rows[i]
        ok = [b[0] for b in bins.values() if b[0] >= size and (s is None or s not in b[1]) and (c is None or c not in b[2])]
        before = bins[number][0] if number in bins else 64
        assert before == (min(ok) if ok else 64)
        b = bins[number]
        b[0] -= size
        assert b[0] >= 0 and (s is None or s not in b[1]) and (c is None or c not in b[2])
        b[1].add(s)
        b[2].add(c)
    assert len(placed) == len(rows)


def test_long_documents_are_cut():
    placed = op4.pack_group([(1, 150, "a", 1), (2, 64, "a", 1), (3, 0, None, None)], 64)
    sizes = defaultdict(int)
    for i, _, _, n in placed:
        sizes[i] += n
    assert dict(sizes) == {0: 150, 1: 64, 2: 0}


@pytest.mark.parametrize("edges", [True, False])
def test_op4(spark, sf, tmp_path, edges):
    folder = edge.tables(spark, tmp_path) if edges else sf
    texts = {r.doc_id: r for r in spark.read.parquet(f"{folder}/documents.parquet").collect()}
    rows = op4.op4_conflict_packing(spark, folder).collect()
    tokens, bins, seen = defaultdict(int), defaultdict(int), set()
    for r in rows:
        tokens[r.doc_id] += r.n_tokens
        bins[r.shard, r.bin] += r.n_tokens
        for what in ("source", "cluster"):
            if r[what] is not None and r.n_tokens < op4.CAPACITY:
                key = (r.shard, r.bin, what, r[what])
                assert key not in seen
                seen.add(key)
    assert dict(tokens) == {k: len((r.text or "").lower().split()) for k, r in texts.items()}
    assert max(bins.values()) <= op4.CAPACITY


def test_op4_sizes_are_the_encoders(spark, tmp_path):
    """Texts without spaces are cut and fill bins by their ids; words are counted once over the pieces."""
    texts = ["漢字仮名交じり文" * 3000, "QUJDREVGR0hJSktMTU5PUFFSU1RVVldYWVo=" * 400, "wörd two  three\n" * 3000, "one 日本", "a", None, " "]
    folder = edge.tables(spark, tmp_path, texts)
    want = {r.doc_id: r.n_tokens for r in op6.op6_bpe_codec(spark, folder).collect()}
    ids, words, bins, pieces = defaultdict(int), defaultdict(int), defaultdict(int), defaultdict(list)
    for r in op4.op4_conflict_packing(spark, folder).collect():
        ids[r.doc_id] += r.n_ids
        words[r.doc_id] += r.n_tokens
        bins[r.shard, r.bin] += r.n_ids
        pieces[r.doc_id].append(r.piece)
    assert dict(ids) == want and max(bins.values()) <= op4.CAPACITY
    assert dict(words) == {i: len((t or "").split()) for i, t in enumerate(texts)}
    for i, n in want.items():
        assert sorted(pieces[i]) == list(range(max(1, -(-n // op4.CAPACITY))))
    assert all(want[i] > op4.CAPACITY for i in range(3))


def test_op4_near_copies_conflict(spark, tmp_path):
    """Near copies of different or no sources are one cluster and never share a bin; so are copies but for case and spaces."""
    rng = random.Random(3)
    texts = []
    for _ in range(5):
        words = [f"w{rng.randrange(10**6)}" for _ in range(80)]
        for k in range(6):
            own = words.copy()
            own[k * 13] = "edited"
            texts.append(" ".join(own))
    texts += ["ÄRGER im Büro", "ärger\u3000im büro", "ärger im\xa0BÜRO"]
    rows = [(i, t, None if i % 3 == 0 else f"s{i}") for i, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    clusters, bins = defaultdict(set), defaultdict(list)
    for r in op4.op4_conflict_packing(spark, str(tmp_path)).collect():
        clusters[min(r.doc_id // 6, 5)].add(r.cluster)
        bins[r.shard, r.bin].append(r.cluster)
    assert [clusters[k] for k in range(6)] == [{6 * k} for k in range(6)]
    assert all(len(set(b)) == len(b) for b in bins.values())


def test_op4_empty(spark, tmp_path):
    assert op4.op4_conflict_packing(spark, edge.tables(spark, tmp_path, [])).count() == 0


def by_sql(folder):
    con = duckdb.connect()
    con.sql(f"create view pages as from '{folder}/pages.parquet{'/*.parquet' if '/testdata' not in folder else ''}'")
    return sorted(con.sql(op8.ORACLES["op8_site_lines"]).fetchall())


# no line of the smaller tables is on enough pages of a host to go
@pytest.mark.parametrize(("sf_dir", "drops"), [("/root/testdata/sf0.001", False), ("/root/testdata/sf0.01", False), ("/root/testdata/sf0.1", True)])
def test_op8_equals_sql(spark, sf_dir, drops):
    got = sorted(map(tuple, op8.op8_site_lines(spark, sf_dir).collect()))
    assert got == by_sql(sf_dir) and (sum(r[3] for r in got) > 0 or not drops)


def test_op8_planted_boilerplate(spark, tmp_path):
    """Menus of two hosts go, also where a page is there six times; other hosts' and rare lines stay."""
    rows = [(i, f"https://a.b/{i}", f"<p>menu</p><p>own {i}</p><script>x</script>foot") for i in range(12)]
    rows += [(100, "https://c.d/x", "<p>menu</p><b>once")] * 6 + [(101 + i, "https://c.d/y", f"<p>page {i}</p>") for i in range(8)]
    rows += [(200 + i, f"https://e.f/{i}", f"<p>menu</p>text {i}<!-- open") for i in range(3)]
    spark.createDataFrame(rows, "page_id long, url string, html string").coalesce(1).write.parquet(f"{tmp_path}/pages.parquet")
    got = sorted(map(tuple, op8.op8_site_lines(spark, str(tmp_path)).collect()))
    assert got == by_sql(str(tmp_path))
    dropped = {r[0]: r[3] for r in got}
    assert [dropped[i] for i in (0, 100, 101, 200)] == [2, 2, 0, 0] and len(got) == len(rows)


def test_op8_open_tags_take_one_pass():
    for text in ["<script " * 130_000, "<style" * 170_000, "<!--" * 250_000, "<" * 1_000_000, "<script>a</script>" * 20_000 + "<script " * 50_000, "a<b " * 100 + "<!-->" * 100 + "x"]:
        began = time.monotonic()
        got = op8.html_lines(text)
        assert time.monotonic() - began < 2
        if len(text) < 100_000:
            assert got == [y for x in op8._HTML.split(text) if (y := x.strip())]
    rng = random.Random(5)
    for _ in range(3000):
        text = "".join(rng.choices(["<script", "</script>", "<style", "</style>", "<!--", "-->", "<", ">", "\n", "a", " ", "--"], k=rng.randint(0, 14)))
        want = [x.strip(" \t\n\r\f") for x in op8._HTML.split(text)]
        assert [x for x in map(lambda y: y.strip(" \t\n\r\f"), op8._split(text)) if x] == [x for x in want if x] == op8.html_lines(text)


def site(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, source string, host string")


def test_site_lines_by_both_ways(spark, monkeypatch):
    rows = [(i, f"menu\nown {i}\n\nfoot", "a", "clash") for i in range(8)] + [(9, "menu\nother", "b", None), (10, None, "a", None), (11, "", None, None)]
    want = {i: f"own {i}\n" for i in range(8)} | {9: "menu\nother", 10: None, 11: ""}
    for limit in (op8.BROADCAST_LINES, -1):
        monkeypatch.setattr(op8, "BROADCAST_LINES", limit)
        got = op8.drop_site_lines(site(spark, rows))
        assert got.columns == ["doc_id", "text", "source", "host"]
        assert {r.doc_id: r.text for r in got.collect()} == want
        assert op8.drop_site_lines(site(spark, [])).count() == 0


def test_op8_edges(spark, tmp_path):
    spark.createDataFrame([(1, None, None, "x"), (2, "nonsense", "", "x"), (3, "http://a.b/c", "<p>t</p>", "x")], "page_id long, url string, html string, host string").write.parquet(f"{tmp_path}/pages.parquet")
    got = {r.page_id: (r.host, r.n_lines, r.n_dropped) for r in op8.op8_site_lines(spark, str(tmp_path)).collect()}
    assert got == {1: ("", 0, 0), 2: ("", 0, 0), 3: ("a.b", 1, 0)}


def test_words_of_pieces_by_any_white_space():
    rng = random.Random(4)
    blank = "".join(chr(c) for c in range(0x110000) if chr(c).isspace())
    assert all(op4._BLANK[ord(c)] for c in blank) and op4._BLANK.sum() == len(blank)
    for alphabet in ("ab \t\n\x1c\x85", "aé漢😀 　 \x1f"):
        for _ in range(20):
            text = "".join(rng.choices(alphabet, k=rng.randint(40, 300)))
            ends, left = [], len(text.encode())
            while left:
                ends.append(min(left, rng.randint(1, 5)))
                left -= ends[-1]
            got = op4.words_of_pieces(text, np.array(ends), 8)
            at = [len(text[: m.start()].encode()) for m in re.finditer(r"\S+", text)]
            bounds = np.cumsum(ends)
            want = [sum(1 for x in at if (bounds[k * 8 - 1] if k else 0) <= x < bounds[min(len(ends), k * 8 + 8) - 1]) for k in range(-(-len(ends) // 8))]
            assert got == want
