"""Where operators keep tables between jobs, and small helpers they share."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``. Where it is unset a local run (tests) has one of its own,
    and a cluster an error, since its machines share no local folder."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        folder = getattr(spark, "_own_shared_folder", None)
        if folder is None:
            folder = "file://" + tempfile.mkdtemp(prefix="shared-")
            spark._own_shared_folder = folder
    return folder.rstrip("/") if "://" in folder else "file://" + folder.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def saved(df: DataFrame, name: str) -> DataFrame:
    """Write and reread: cuts the lineage with files that outlive an executor."""
    return Scratch(df.sparkSession).saved(df, name)


def discard(spark: SparkSession, path: str) -> None:
    """Remove a table that no later job reads."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


class Scratch:
    """Saved tables that go together once nothing reads them."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def saved(self, df: DataFrame, name: str) -> DataFrame:
        path = new_path(self.spark, name)
        df.write.option("compression", "zstd").parquet(path)
        self.paths.append(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def take(self, other: Scratch) -> None:
        """Tables of ``other`` go with these."""
        self.paths += other.paths

    def drop(self) -> None:
        for path in self.paths:
            discard(self.spark, path)
        self.paths = []


def over_batches(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch | Iterator[pa.RecordBatch]]], schema: str) -> DataFrame:
    """mapInArrow where ``make`` sets up once a task and its result maps each batch, to one or to several. Batches hold
    ``BATCH_BYTES`` or one longer row at most, by a setting of the session, which stays for the later run of the plan."""
    _bound_batches(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enter(f"{make.__module__}.{make.__qualname__}")
        each = make()
        batch = out = made = None
        for batch in batches:
            if batch.num_rows:
                out = each(batch)
                for made in [out] if isinstance(out, pa.RecordBatch) else out:
                    if made.num_rows:
                        yield made
            if batch.nbytes > LARGE_BATCH:
                batch = out = made = None
                give_back()
        del batch, out, made
        give_back()

    return df.mapInArrow(run, schema)


#: What empties this Python worker's caches, and the work that filled them.
_releases: list[Callable[[], None]] = []
_entered: str | None = None


def on_other_work(release: Callable[[], None]) -> None:
    """Has ``release`` called in a Python worker before it begins a task of other work than its last one's. A worker lives
    as long as the executor and serves all stages, so what one keeps for its next task would stand beside all later ones."""
    _releases.append(release)


def enter(work: str) -> None:
    """Names the work of the task that begins in this worker."""
    global _entered
    if _entered not in (None, work):
        for release in _releases:
            release()
        give_back()
    _entered = work


#: Most bytes of an Arrow batch: the JVM and its Python worker hold several copies of one side by side.
BATCH_BYTES = 4 << 20
_BATCH_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def _bound_batches(spark: SparkSession) -> None:
    """Lowers the session's bound, and leaves a lower one."""
    now = spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(_BATCH_SETTING))
    if now > BATCH_BYTES:
        spark.conf.set(_BATCH_SETTING, f"{BATCH_BYTES}b")


#: Freed memory is given back after batches beyond so many bytes, and at the end of each task.
LARGE_BATCH = 2 << 20


def give_back() -> None:
    """Hands freed memory of this Python worker to the system. A worker outlives its task, and would else stay as large
    as its largest batch made it, beside the next task's memory."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # other C libraries have none
    if trim is not None:
        trim(0)


def pieces(batch: pa.RecordBatch, column: str, limit: int) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that no piece holds more than ``limit`` bytes of a text column, but for single longer rows."""
    import numpy as np
    import pyarrow.compute as pc

    size = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    total = np.cumsum(size)
    at = 0
    while at < batch.num_rows:
        base = total[at] - size[at]
        end = max(at + 1, int(np.searchsorted(total, base + limit, "right")))
        yield batch.slice(at, end - at)
        at = end
