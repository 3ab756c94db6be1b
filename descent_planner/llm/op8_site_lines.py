"""Line removal by how common a line is within its site.

For each host, the pages that hold a line are divided by the host's pages; a line above ``RATIO`` that stands on
``LEAST_PAGES`` pages or more is boilerplate there, and leaves every page of the host.

A page counts once for each different line. Lines travel as 128-bit hashes of host and line; they are counted with
partial sums before the shuffle, so a hot host or line is spread. What is boilerplate is broadcast while it has
``BROADCAST_LINES`` keys at most, else texts and keys meet by a sort-merge join on the page.

Null texts have no lines and stay null in ``drop_site_lines``; rows without a host form a site of their own. Every
row is a page, repeated rows and ids too. Rows stay one for one; a page that loses every line keeps an empty text.
A script, style, comment or tag without an end is text, and takes one look for its end, however many there are.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import over_batches, saved

RATIO = 0.25
LEAST_PAGES = 5
#: 16 bytes each: 16 MB at most.
BROADCAST_LINES = 1_000_000

#: Where a line of a web page ends: at a script, a style, a comment, any other tag, or a line feed.
HTML_LINE_END = r"(?s:<script.*?</script>|<style.*?</style>|<!--.*?-->|<[^>]*>|\n)"
_HOST = r"^[a-z]+://([^/:?#]+)"


_HTML = re.compile(HTML_LINE_END)
# What begins a part that is no text, and what ends it.
_ENDS = {"<script": "</script>", "<style": "</style>", "<!--": "-->"}
_BEGIN = re.compile(r"<script|<style|<!--|<|\n")


def html_lines(html: str) -> list[str]:
    open_ended = any(html.rfind(a) + len(a) > html.rfind(b) for a, b in _ENDS.items() if a in html) or html.rfind("<") > html.rfind(">")
    return [y for x in (_split(html) if open_ended else _HTML.split(html)) if (y := x.strip(" \t\n\r\f"))]


def _split(html: str) -> list[str]:
    """As ``_HTML.split``, in one pass: where no end follows any more, none is looked for."""
    last = {a: html.rfind(b) for a, b in _ENDS.items()} | {"<": html.rfind(">")}
    out, start, at = [], 0, 0
    while m := _BEGIN.search(html, at):
        kind, at = m[0], m.end()
        end = at if kind == "\n" else 0
        if kind in _ENDS and at <= last[kind]:
            end = html.find(_ENDS[kind], at) + len(_ENDS[kind])
        elif kind != "\n" and m.start() < last["<"]:
            end = html.find(">", m.start()) + 1
        if end:
            out.append(html[start : m.start()])
            start = at = end
        else:
            at = m.start() + 1
    return [*out, html[start:]]


def text_lines(text: str) -> list[str]:
    """Lines as they are; an empty one is kept in the text but never counted."""
    return text.split("\n")


def _key(host: str | None, line: str) -> bytes:
    return hashlib.blake2b(line.encode(), digest_size=16, key=hashlib.blake2b((host or "").encode(), digest_size=16).digest()).digest()


def boilerplate(docs: DataFrame, text_col: str, host_col: str, lines, ratio: float = RATIO, least: int = LEAST_PAGES) -> DataFrame:
    """The keys of boilerplate lines: (host, key, pages, host_pages)."""
    named = docs.select(F.coalesce(F.col(host_col).cast("string"), F.lit("")).alias("host"), F.col(text_col).cast("string").alias("text"))

    def make():
        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            hosts, keys = [], []
            for host, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                own = {_key(host, x) for x in lines(text) if x} if text else ()
                hosts += [host] * len(own)
                keys += own
            return pa.RecordBatch.from_arrays([pa.array(hosts, pa.string()), pa.array(keys, pa.binary())], ["host", "key"])

        return each

    counts = over_batches(named, make, "host string, key binary").groupBy("host", "key").agg(F.count("*").alias("pages")).where(F.col("pages") >= least)
    totals = named.groupBy("host").agg(F.count("*").alias("host_pages"))
    return counts.join(totals, "host").where(F.col("pages") > ratio * F.col("host_pages"))


def _flagged(docs: DataFrame, keys: DataFrame, text_col: str, host_col: str, lines, finish, schema) -> DataFrame:
    """Maps (row, lines kept, number of lines) by ``finish`` with boilerplate left out."""
    bad = saved(keys.select("host", "key"), "site-lines")
    names = docs.columns
    text_at, host_at = names.index(text_col), names.index(host_col)
    spark = docs.sparkSession
    if bad.count() <= BROADCAST_LINES:
        known = spark.sparkContext.broadcast(frozenset(bytes(r.key) for r in bad.select("key").toLocalIterator()))

        def make():
            drop = known.value

            def each(batch: pa.RecordBatch) -> pa.RecordBatch:
                kept = []
                for host, text in zip(batch.column(host_at).to_pylist(), batch.column(text_at).to_pylist(), strict=True):
                    own = lines(text) if text is not None else None
                    kept.append(None if own is None else (len(own), own if not drop else [x for x in own if not x or _key(host, x) not in drop]))
                return finish(batch, kept)

            return each

        return over_batches(docs, make, schema)
    return _flagged_by_join(docs, bad, text_at, host_at, lines, finish, schema)


def _flagged_by_join(docs: DataFrame, bad: DataFrame, text_at: int, host_at: int, lines, finish, schema) -> DataFrame:
    """The same without a broadcast: each row's keys are joined with the boilerplate's, and what they hit comes back to it."""
    names = docs.columns
    numbered = saved(docs.withColumn("_row", F.monotonically_increasing_id()), "site-rows")

    def make_keys():
        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            rows, keys = [], []
            for row, host, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                own = {_key(host, x) for x in lines(text) if x} if text else ()
                rows += [row] * len(own)
                keys += own
            return pa.RecordBatch.from_arrays([pa.array(rows, pa.int64()), pa.array(keys, pa.binary())], ["_row", "key"])

        return each

    own = over_batches(numbered.select("_row", F.col(names[host_at]).cast("string"), F.col(names[text_at]).cast("string")), make_keys, "_row long, key binary")
    hits = own.join(bad.select("key"), "key").groupBy("_row").agg(F.collect_set("key").alias("_hits"))
    joined = numbered.join(hits, "_row", "left").select(*names, "_hits")

    def make():
        def each(batch: pa.RecordBatch) -> pa.RecordBatch:
            kept = []
            for host, text, hit in zip(batch.column(host_at).to_pylist(), batch.column(text_at).to_pylist(), batch.column(len(names)).to_pylist(), strict=True):
                drop = set(hit or ())
                found = lines(text) if text is not None else None
                kept.append(None if found is None else (len(found), [x for x in found if not x or _key(host, x) not in drop]))
            return finish(batch.select(list(range(len(names)))), kept)

        return each

    return over_batches(joined, make, schema)


def drop_site_lines(docs: DataFrame, text_col: str = "text", host_col: str = "source", lines=text_lines, ratio: float = RATIO, least: int = LEAST_PAGES) -> DataFrame:
    """The same rows and columns with boilerplate lines gone from ``text_col``."""
    at = docs.columns.index(text_col)

    def finish(batch: pa.RecordBatch, kept: list) -> pa.RecordBatch:
        texts = pa.array([None if k is None else "\n".join(k[1]) for k in kept], batch.schema.field(at).type)
        return batch.set_column(at, batch.schema.field(at), texts)

    return _flagged(docs, boilerplate(docs, text_col, host_col, lines, ratio, least), text_col, host_col, lines, finish, docs.schema)


def op8_site_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    pages = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce(F.regexp_extract("url", _HOST, 1), F.lit("")).alias("host"), F.col("html").cast("string").alias("html"))

    def finish(batch: pa.RecordBatch, kept: list) -> pa.RecordBatch:
        n = [0 if k is None else k[0] for k in kept]
        left = [[] if k is None else k[1] for k in kept]
        digest = [hashlib.sha256("\n".join(x).encode()).hexdigest() for x in left]
        return pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array([a - len(b) for a, b in zip(n, left, strict=True)], pa.int64()), pa.array(digest)], ["page_id", "host", "n_lines", "n_dropped", "kept_sha256"])

    schema = "page_id long, host string, n_lines long, n_dropped long, kept_sha256 string"
    return _flagged(pages, boilerplate(pages, "html", "host", html_lines), "html", "host", html_lines, finish, schema)


QUERIES = {"op8_site_lines": op8_site_lines}
ORACLES = {
    "op8_site_lines": rf"""
WITH p AS (
  SELECT row_number() OVER () AS page, page_id, coalesce(regexp_extract(url, '{_HOST}', 1), '') AS host,
         string_split_regex(coalesce(html, ''), '{HTML_LINE_END}') AS parts
  FROM pages),
l AS (
  SELECT page, host, pos, regexp_replace(part, '^[ \t\n\r\f]+|[ \t\n\r\f]+$', '', 'g') AS line
  FROM (SELECT page, host, unnest(parts) AS part, generate_subscripts(parts, 1) AS pos FROM p)),
f AS (SELECT * FROM l WHERE line <> ''),
t AS (SELECT host, count(*) AS host_pages FROM p GROUP BY host),
b AS (
  SELECT host, line FROM f JOIN t USING (host)
  GROUP BY host, line, host_pages
  HAVING count(DISTINCT page) >= {LEAST_PAGES} AND count(DISTINCT page) > {RATIO} * host_pages),
k AS (SELECT f.*, b.line IS NOT NULL AS bad FROM f LEFT JOIN b ON f.host = b.host AND f.line = b.line),
s AS (
  SELECT page, count(*) AS n_lines, count(*) FILTER (bad) AS n_dropped,
         coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT bad), '') AS kept
  FROM k GROUP BY page)
SELECT p.page_id, p.host, coalesce(n_lines, 0)::BIGINT AS n_lines, coalesce(n_dropped, 0)::BIGINT AS n_dropped,
       sha256(coalesce(kept, '')) AS kept_sha256
FROM p LEFT JOIN s USING (page)"""
}
