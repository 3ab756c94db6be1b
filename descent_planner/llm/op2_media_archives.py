"""Media in archives, read by a Spark data source that plans byte ranges.

``write_archives`` lays members end to end in files of the shared folder: each member is a header (magic, id, sizes)
and a PNG of 8-bit grey samples, 576 a row. A member without an id has a magic of its own. Every task writes files of its own name, and the list of files comes
from the tasks that ended well; what a lost task left behind is on no list.

The data source ``media_archives`` plans partitions of ``range_bytes`` over the listed files. A partition holds
one open file and reads the members that start in its range, found by the file's directory at its end, in runs of
``BATCH_BYTES`` a read; it yields Arrow batches of about that size. A member that fails is read again by its offset
from a file opened anew, ``ATTEMPTS`` times in all, without another member being read twice; if it still fails its
row holds the error and no samples. So a range costs one request for each run, not one for each document.

Null texts count as empty; every text fills at least one row of 576. Repeated rows are members of their own.
Files are opened by ``pyarrow.fs``, which serves local, HDFS and object stores.
"""

from __future__ import annotations

import hashlib
import json
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .shared import new_path, over_batches

ROW = 576
FILE_BYTES = 256 << 20
RANGE_BYTES = 16 << 20
BATCH_BYTES = 4 << 20
ATTEMPTS = 3
_HEAD = struct.Struct("<4sqqq")  # magic, id, bytes before padding, bytes of the medium
_TAIL = struct.Struct("<qq4s")  # offset and number of the directory's entries, magic
_MAGIC = b"mda1"
_NO_ID = b"mda0"
# The PNG signature.
_PNG = b"\x89PNG\r\n\x1a\n"


def _chunk(kind: bytes, data: bytes) -> bytes:
    return struct.pack(">I", len(data)) + kind + data + struct.pack(">I", zlib.crc32(kind + data))


def png(samples: bytes, width: int = ROW) -> bytes:
    """Grey samples, whole rows of them, as a PNG without row filters."""
    rows = np.frombuffer(samples, dtype=np.uint8).reshape(-1, width)
    raw = np.zeros((len(rows), width + 1), dtype=np.uint8)
    raw[:, 1:] = rows
    return _PNG + _chunk(b"IHDR", struct.pack(">IIBBBBB", width, len(rows), 8, 0, 0, 0, 0)) + _chunk(b"IDAT", zlib.compress(raw.tobytes(), 4)) + _chunk(b"IEND", b"")


def samples(medium: bytes) -> bytes:
    """The samples of such a PNG; raises ValueError where anything doesn't fit."""
    if medium[:8] != _PNG:
        raise ValueError("not a PNG")
    at, size, data = 8, None, []
    while at + 12 <= len(medium):
        n, kind = struct.unpack_from(">I4s", medium, at)
        body = medium[at + 8 : at + 8 + n]
        if len(medium) < at + 12 + n or zlib.crc32(kind + body) != struct.unpack_from(">I", medium, at + 8 + n)[0]:
            raise ValueError(f"damaged chunk at {at}")
        if kind == b"IHDR":
            size = struct.unpack(">IIBBBBB", body)
        elif kind == b"IDAT":
            data.append(body)
        at += 12 + n
        if kind == b"IEND":
            break
    else:
        raise ValueError("no end")
    if size is None or size[2:] != (8, 0, 0, 0, 0):
        raise ValueError("not 8-bit grey")
    try:
        raw = np.frombuffer(zlib.decompress(b"".join(data)), dtype=np.uint8).reshape(size[1], size[0] + 1)
    except zlib.error as e:
        raise ValueError(str(e)) from e
    if raw[:, 0].any():
        raise ValueError("row filters aren't written here")
    return raw[:, 1:].tobytes()


def payload(text: str | None) -> tuple[bytes, int]:
    """UTF-8 padded with 255 to a positive multiple of ROW, and its length before that."""
    raw = (text or "").encode()
    return raw + b"\xff" * (max(1, -(-len(raw) // ROW)) * ROW - len(raw)), len(raw)


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_archives(docs: DataFrame, folder: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Writes the texts' media under ``folder`` and saves and returns the list of files (file, bytes, members)."""
    listed = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _write_files(batches, folder)

    spark = docs.sparkSession
    listed.mapInArrow(run, "file string, bytes long, members long").write.parquet(f"{folder}/list")
    return spark.read.parquet(f"{folder}/list")


def _write_files(batches: Iterator[pa.RecordBatch], folder: str) -> Iterator[pa.RecordBatch]:
    """The files of one task; yields their list."""
    files, out, entries, at, name = [], None, [], 0, ""

    def close() -> None:
        nonlocal out, at
        body = np.array(entries, dtype="<i8").tobytes()
        out.write(body)
        out.write(_TAIL.pack(at, len(entries), _MAGIC))
        out.close()
        files.append((name, at + len(body) + _TAIL.size, len(entries)))
        out, at = None, 0
        entries.clear()

    for batch in batches:
        for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if out is None:
                name = f"{uuid.uuid4().hex}.mda"
                system, path = _open(folder)
                system.create_dir(path, recursive=True)
                out = system.open_output_stream(f"{path}/{name}")
            body, n = payload(text)
            medium = png(body)
            out.write(_HEAD.pack(_NO_ID if doc is None else _MAGIC, doc or 0, n, len(medium)))
            out.write(medium)
            entries.append(at)
            at += _HEAD.size + len(medium)
            if at >= FILE_BYTES:
                close()
    if out is not None:
        close()
    yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in files], pa.string()), pa.array([x[1] for x in files], pa.int64()), pa.array([x[2] for x in files], pa.int64())], ["file", "bytes", "members"])


class _Range(InputPartition):
    def __init__(self, file: str, low: int, high: int, size: int):
        self.file, self.low, self.high, self.size = file, low, high, size


SCHEMA = "doc_id long, file string, offset long, n_bytes long, medium binary, payload binary, error string"


class MediaArchives(DataSource):
    """``spark.read.format("media_archives").option("files", json of [file, bytes]).load(folder)``."""

    @classmethod
    def name(cls) -> str:
        return "media_archives"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> ArchiveReader:
        return ArchiveReader(self.options)


class ArchiveReader(DataSourceReader):
    def __init__(self, options):
        self.folder = options["path"]
        self.files = json.loads(options.get("files", "[]"))
        self.range_bytes = int(options.get("range_bytes", RANGE_BYTES))

    def partitions(self) -> list[_Range]:
        """Byte ranges; a member belongs to the one it starts in."""
        found = [_Range(f, low, low + self.range_bytes, size) for f, size in self.files for low in range(0, max(size, 1), self.range_bytes)]
        return found or [_Range("", 0, 0, 0)]

    def read(self, part: _Range) -> Iterator[pa.RecordBatch]:
        if not part.file:
            return
        system, path = _open(self.folder)
        path = f"{path}/{part.file}"
        with system.open_input_file(path) as f:
            f.seek(part.size - _TAIL.size)
            start, n, magic = _TAIL.unpack(f.read(_TAIL.size))
            if magic != _MAGIC:
                raise ValueError(f"{part.file} has no directory")
            f.seek(start)
            offsets = np.frombuffer(f.read(8 * n), dtype="<i8")
            ends = np.append(offsets[1:], start)
            mine = (offsets >= part.low) & (offsets < part.high)
            lows, highs = offsets[mine], ends[mine]
            rows, held, at = [], 0, 0
            while at < len(lows):
                # members lie end to end: as many as a read may hold, one at least
                stop = max(at + 1, int(np.searchsorted(highs, lows[at] + BATCH_BYTES, "right")))
                try:
                    f.seek(int(lows[at]))
                    run = f.read(int(highs[stop - 1] - lows[at]))
                except OSError:
                    run = b""
                for low, high in zip(lows[at:stop].tolist(), highs[at:stop].tolist(), strict=True):
                    try:
                        own = _parsed(run[low - int(lows[at]) : high - int(lows[at])])
                    except (ValueError, struct.error) as e:
                        own = self._member(system, path, low, high, ATTEMPTS - 1, f"{type(e).__name__}: {e}")
                    rows.append((*own, part.file, low))
                    held += high - low + len(own[3] or b"")
                    if held >= BATCH_BYTES:
                        yield _batch(rows)
                        rows, held = [], 0
                at = stop
        if rows:
            yield _batch(rows)

    @staticmethod
    def _member(system, path: str, low: int, high: int, attempts: int = ATTEMPTS, why: str = "") -> tuple:
        """(id, bytes, medium, samples, error) of the member at an offset, from a file opened anew at each attempt."""
        for _ in range(attempts):
            try:
                with system.open_input_file(path) as f:
                    f.seek(low)
                    return _parsed(f.read(high - low))
            except (OSError, ValueError, struct.error) as e:
                why = f"{type(e).__name__}: {e}"
        return None, None, None, None, why


def _parsed(raw: bytes) -> tuple:
    magic, doc, n, size = _HEAD.unpack_from(raw)
    medium = raw[_HEAD.size : _HEAD.size + size]
    if magic not in (_MAGIC, _NO_ID) or len(medium) != size:
        raise ValueError("damaged header")
    return None if magic == _NO_ID else doc, n, medium, samples(medium), None


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (("doc_id", pa.int64(), 0), ("file", pa.string(), 5), ("offset", pa.int64(), 6), ("n_bytes", pa.int64(), 1), ("medium", pa.binary(), 2), ("payload", pa.binary(), 3), ("error", pa.string(), 4))
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], kind) for _, kind, i in kinds], [name for name, _, _ in kinds])


def read_archives(spark: SparkSession, folder: str, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """The members of the listed files. The list has a row a file, of which there are as many as writing tasks or more."""
    spark.dataSource.register(MediaArchives)
    files = sorted((r.file, r.bytes) for r in spark.read.schema("file string, bytes long").parquet(f"{folder}/list").collect())
    return spark.read.format("media_archives").option("files", json.dumps(files)).option("range_bytes", str(range_bytes)).load(folder)


def feature(body: bytes) -> str:
    """Mean, deviation and entropy of the samples, and the share of each quarter of their range."""
    x = np.frombuffer(body, dtype=np.uint8)
    counts = np.bincount(x, minlength=256)
    p = counts[counts > 0] / len(x)
    quarters = counts.reshape(4, 64).sum(axis=1) / len(x)
    return f"mean={x.mean():.4f};sd={x.std():.4f};entropy={-(p * np.log2(p)).sum():.4f};quarters=" + "/".join(f"{q:.4f}" for q in quarters)


def op2_media_archives(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = new_path(spark, "media")
    write_archives(spark.read.parquet(f"{sf_dir}/documents.parquet"), folder)

    def make():
        def each(b: pa.RecordBatch) -> pa.RecordBatch:
            ids, sizes, media, bodies, errors = (b.column(i).to_pylist() for i in range(5))
            if bad := [e for e in errors if e]:
                raise ValueError(f"a member couldn't be read: {bad[0]}")
            sha = lambda x: hashlib.sha256(x).hexdigest()
            cols = [pa.array(ids, pa.int64()), pa.array(sizes, pa.int64()), pa.array([len(x) for x in bodies], pa.int64()), pa.array([sha(x) for x in bodies]), pa.array([zlib.crc32(x[-32:]) for x in bodies], pa.int64()), pa.array([len(x) for x in media], pa.int64()), pa.array([sha(x) for x in media]), pa.array([feature(x) for x in bodies])]
            return pa.RecordBatch.from_arrays(cols, ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

        return each

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return over_batches(read_archives(spark, folder).select("doc_id", "n_bytes", "medium", "payload", "error"), make, schema)


QUERIES = {"op2_media_archives": op2_media_archives}
ORACLES: dict[str, str] = {}
