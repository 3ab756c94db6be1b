"""Samples of an iteration: Bernoulli, random partition and shuffled partition, by a hash of (seed, draw, unit).

The hash makes a draw the same wherever and however often a task runs, and lets a SQL oracle repeat it. Units are laid
out by ``part_id``: ``lay_out`` writes a file a partition and their catalogue, from which the partition samplers open
the files of the chosen partitions and nothing else. Without a layout ``part_id`` is a column of the units and every
draw scans them all.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SPAN = 1 << 32
#: Units of a partition that the driver holds at most: a longer one is read slice by slice of its shuffled order.
SLICE_UNITS = 200_000
#: Numbers that those units hold at most: a slice of wide units has fewer units.
SLICE_NUMBERS = 4_000_000
#: Equal parts of the hashes' range in which mixed partitions' units are counted, so that a slice reads its own parts.
CELLS = 4096


def here(spark, rows: list, schema) -> DataFrame:
    """Rows of the driver as a table that needs no Python worker and, for expressions alone, no job; in their order."""
    from pyspark.sql.conversion import LocalDataToArrowConversion
    from pyspark.sql.types import _parse_datatype_string

    schema = _parse_datatype_string(schema) if isinstance(schema, str) else schema
    return spark.createDataFrame(LocalDataToArrowConversion.convert(rows, schema, False), schema)


def slice_of(numbers: float) -> int:
    """Units of a slice, by how many numbers one holds."""
    return max(1, min(SLICE_UNITS, int(SLICE_NUMBERS / max(1.0, numbers))))


def _digest(seed: int, draw, unit: Column) -> Column:
    draw = F.lit(draw) if isinstance(draw, int) else draw
    return F.md5(F.concat_ws(":", F.lit(seed).cast("string"), draw.cast("string"), unit.cast("string")))


def rank_key(seed: int, draw, unit: Column) -> Column:
    """A hash in [0, 2^32)."""
    return F.conv(F.substring(_digest(seed, draw, unit), 1, 8), 16, 10).cast("long")


def rank_below(seed: int, draw, unit: Column, limit: float) -> Column:
    """``rank_key(...) < limit``: digits of equal length are in order of their numbers, so that none is made of them."""
    least = max(0, math.ceil(limit))
    return F.lit(True) if least >= SPAN else _digest(seed, draw, unit) < f"{least:08x}"


def rank_sql(seed, draw, unit) -> str:
    return f"('0x'||substr(md5(concat_ws(':',{seed},{draw},{unit})),1,8))::BIGINT"


def py_rank(seed: int, draw: int, unit) -> int:
    import hashlib

    return int(hashlib.md5(f"{seed}:{draw}:{unit}".encode()).hexdigest()[:8], 16)


def ranks(seed: int, draw: int, ids: np.ndarray | list) -> np.ndarray:
    """``py_rank`` of many ids."""
    from hashlib import md5

    head = f"{seed}:{draw}:"
    return np.frombuffer(b"".join([md5(f"{head}{k}".encode()).digest()[:4] for k in (ids.tolist() if isinstance(ids, np.ndarray) else ids)]), ">u4").astype(np.int64)


def with_parts(units: DataFrame, parts: int, by: str = "hash") -> DataFrame:
    """Units with the partition they belong to: by id modulo, by ranges of the id, or by the file they come from."""
    if by == "hash":
        return units.withColumn("part_id", F.pmod("unit_id", F.lit(parts)).cast("int"))
    if by == "range":
        edges = units.select(F.percentile_approx("unit_id", [j / parts for j in range(1, parts)], 10000)).first()[0] or []
        return units.withColumn("part_id", sum((F.when(F.col("unit_id") > e, 1).otherwise(0) for e in edges), F.lit(0)))
    if by == "file":
        return units.withColumn("part_id", F.pmod(F.xxhash64(F.input_file_name()), F.lit(parts)).cast("int"))
    raise ValueError(f"unknown layout {by}")


def layout_partitions(units: DataFrame, path: str, parts: int, by: str = "hash") -> DataFrame:
    """Writes units partitioned by part_id and returns the table; a filter on part_id then prunes the scan."""
    with_parts(units, parts, by).repartition("part_id").write.partitionBy("part_id").parquet(path)
    return units.sparkSession.read.parquet(path)


def partition_catalog(units: DataFrame) -> DataFrame:
    """(part_id, n_units) of a layout."""
    return units.groupBy("part_id").agg(F.count("*").alias("n_units"))


def layout_files(units: DataFrame, path: str, parts: int) -> DataFrame:
    """Writes one file a partition, in order of the units' ids and with their ``offset``, and returns the files'
    catalogue (part_id, file, bytes, n_units).

    Folders of partitions cost a listing each; with a catalogue a draw opens the files it names and lists nothing.
    """
    from pyspark.sql.window import Window

    # the window deals out and sorts by part_id, which is what the writer needs too: one shuffle
    laid = with_parts(units, parts).withColumn("offset", F.row_number().over(Window.partitionBy("part_id").orderBy("unit_id")) - 1)
    laid.write.partitionBy("part_id").parquet(path)
    rows = units.sparkSession.read.schema(laid.schema).parquet(path)
    return rows.groupBy("part_id", F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_size").alias("bytes")).agg(F.count("*").alias("n_units"))


def catalog_reader(path: str, catalog: DataFrame):
    """A reader of chosen partitions by the files that a catalogue names, for ``ShuffledPartition(read=...)``.

    The catalogue has a row for each file; it is a table, from which a draw takes the rows of its partitions.
    """
    spark = catalog.sparkSession
    schema = spark.read.parquet(path).schema

    # later draws of the same partitions look nothing up and list nothing
    @lru_cache(maxsize=64)
    def opened(parts: tuple) -> DataFrame:
        files = [r.file for r in catalog.where(F.col("part_id").isin(list(parts))).select("file").collect()]
        return spark.read.schema(schema).option("basePath", path).parquet(*files)

    return lambda parts: opened(tuple(parts))


@dataclass
class Layout:
    """Units in files of their partitions. The driver holds two numbers a partition, of which there are bytes / 128 MB."""

    rows: DataFrame
    read: object
    sizes: dict[int, int]
    bytes: dict[int, int]


def lay_out(units: DataFrame, folder: str, parts: int) -> Layout:
    """Writes units and catalogue under ``folder``."""
    spark, path = units.sparkSession, f"{folder}/units"
    layout_files(units, path, parts).write.parquet(f"{folder}/catalog")
    catalog = spark.read.parquet(f"{folder}/catalog").persist()
    found = catalog.groupBy("part_id").agg(F.sum("n_units").alias("n"), F.sum("bytes").alias("b")).collect()
    return Layout(spark.read.parquet(path), catalog_reader(path, catalog), {r.part_id: r.n for r in found}, {r.part_id: r.b for r in found})


@dataclass
class Bernoulli:
    """Scans all units and keeps each with probability ``fraction``; an empty draw is drawn again with another sub-seed."""

    fraction: float
    seed: int = 7
    boost: float = 1.0
    name: str = "bernoulli"

    def condition(self, draw: int, unit: Column) -> Column:
        return rank_below(self.seed, draw, unit, min(1.0, self.fraction * self.boost) * SPAN)

    def draw(self, units: DataFrame, i: int) -> DataFrame:
        return units.where(self.condition(i, F.col("unit_id")))


def boosted_fraction(n: int, miss: float = 1e-3) -> float:
    """The least fraction at which a draw over n units is empty with probability ``miss`` at most."""
    return 1 - miss ** (1 / n)


@dataclass
class RandomPartition:
    """For each unit wanted, a partition in proportion to its size (or uniformly), then a unit of it, with replacement."""

    sizes: dict[int, int]
    size: int
    seed: int = 7
    weights: str = "size"
    name: str = "random"
    read: object = None

    def picks(self, i: int) -> list[tuple[int, int]]:
        """(part, offset) of each draw."""
        parts = sorted(self.sizes)
        n = np.array([self.sizes[p] for p in parts], dtype=float)
        share = np.cumsum(n / n.sum() if self.weights == "size" else np.ones(len(n)) / len(n))
        u = ranks(self.seed, i, [f"p{k}" for k in range(self.size)]) / SPAN
        at = np.minimum(np.searchsorted(share, u, "right"), len(parts) - 1)
        within = ranks(self.seed, i, [f"u{k}" for k in range(self.size)])
        return [(parts[a], r * self.sizes[parts[a]] // SPAN) for a, r in zip(at.tolist(), within.tolist(), strict=True)]

    def draw(self, units: DataFrame, i: int) -> DataFrame:
        """Reads the chosen partitions; a unit drawn twice comes twice. Offsets are in order of the unit's id: a layout
        holds them, and then the scan takes the row groups between the least and the greatest offset."""
        from pyspark.sql.window import Window

        picks = self.picks(i)
        chosen = sorted({p for p, _ in picks})
        if self.read:
            offsets, rows = sorted({o for _, o in picks}), self.read(chosen)
            # a scan takes no more than this from a long list, whose literals cost a call each
            pruned = rows.where(F.col("offset").isin(offsets) if len(offsets) <= 10 else F.col("offset").between(offsets[0], offsets[-1]))
        else:
            pruned = units.where(F.col("part_id").isin(chosen)).withColumn("offset", F.row_number().over(Window.partitionBy("part_id").orderBy("unit_id")) - 1)
        wanted = here(units.sparkSession, picks, "part_id int, offset int")
        return pruned.join(F.broadcast(wanted), ["part_id", "offset"])


@dataclass
class ShuffledPartition:
    """One partition, shuffled once by hash, is used up in order; then the next one in the order of its own hash.

    What is left of a partition is discarded when it is less than a batch, or with ``carry`` filled up from the next
    partition. After all partitions a new epoch begins with a new shuffle.

    ``mix`` partitions are read and used up together, each in proportion to its size, where partitions are skewed (a
    layout that follows the label). What is read together and holds more than ``slice_units`` is read in slices, one
    after the other, which gives the same order: a single partition in slices of its hashes' range, mixed ones in
    slices of the places in them. ``prefetch`` reads the next load in the background; then two are held, of half the
    length. ``read`` gives the rows of partitions by other means than a filter on part_id; ``source`` gives
    (part, row) in order for (parts, epoch, least hash, hash after the last), where units are on the driver.
    """

    sizes: dict[int, int]
    size: int
    seed: int = 7
    carry: bool = False
    name: str = "shuffle"
    epoch: int = 0
    at: int = 0
    offset: int = 0
    held: list = field(default_factory=list)
    reads: int = 0
    mix: int = 1
    prefetch: bool = False
    read: object = None
    source: object = None
    slice_units: int = SLICE_UNITS
    #: How often each partition was read.
    opened: dict = field(default_factory=dict)

    def order(self, epoch: int) -> list[int]:
        return sorted(self.sizes, key=lambda p: (py_rank(self.seed, epoch, f"part{p}"), p))

    def __post_init__(self):
        if not self.sizes or sum(self.sizes.values()) == 0:
            raise ValueError("no units to sample")
        if all(n < self.size for n in self.sizes.values()):
            self.carry = True
        self._short = min(self.size, sum(self.sizes.values()))
        self._pool, self._next, self._gone = None, None, 0
        self._counted: tuple = (None, {})
        self._start(0, 0)

    def _start(self, epoch: int, at: int) -> None:
        self._loads = self._all_loads(epoch, at)
        self._ahead = next(self._loads)

    def _all_loads(self, epoch: int, at: int):
        """What is read from a place on, for ever: (epoch, place, partitions, least hash, hash after the last); of mixed
        partitions the last two are places, as shares of SPAN."""
        limit = max(1, self.slice_units // (2 if self.prefetch else 1))
        while True:
            order = self.order(epoch)
            while at < len(order):
                parts = order[at : at + self.mix]
                slices = max(1, -(-sum(self.sizes[p] for p in parts) // limit)) if len(parts) == 1 or not self.source else 1
                for j in range(slices):
                    yield epoch, at, parts, j * SPAN // slices, (j + 1) * SPAN // slices
                at += self.mix
            epoch, at = epoch + 1, 0

    def _fetch(self, units: DataFrame, load: tuple) -> list:
        """A load's rows, shuffled; several partitions are dealt by their shares."""
        from pyspark.sql.window import Window

        epoch, _, parts, low, high = load
        if self.source:
            return self.source(parts, epoch, low, high)
        rows = self.read(parts) if self.read else units.where(F.col("part_id").isin(parts))
        rows = rows.withColumn("_r", rank_key(self.seed, epoch, F.col("unit_id")))
        sliced = high - low < SPAN
        if len(parts) > 1:
            of = lambda values: F.element_at(F.create_map(*(F.lit(v) for p in parts for v in (p, values[p]))), F.col("part_id"))
            before = F.lit(0)
            if sliced:
                least, end, known = self._cells(rows, load)
                rows, before = rows.where((F.col("_r") >= of(least)) & (F.col("_r") < of(end))), of(known)
            place = (F.row_number().over(Window.partitionBy("part_id").orderBy("_r", "unit_id")) + before - 0.5) / of(self.sizes)
            rows = rows.withColumn("_p", place)
            if sliced:
                rows = rows.where((F.col("_p") * SPAN >= low) & (F.col("_p") * SPAN < high))
            rows = rows.repartition(1).sortWithinPartitions("_p", "part_id").drop("_p")
        else:
            if sliced:
                rows = rows.where((F.col("_r") >= low) & (F.col("_r") < high))
            # a slice is bounded, so one task sorts it: a sort of the whole reads and hashes its input twice, once to sample it
            rows = rows.repartition(1).sortWithinPartitions("_r", "unit_id")
        return [(r.part_id, r) for r in rows.drop("_r").collect()]

    def _cells(self, rows: DataFrame, load: tuple) -> tuple[dict, dict, dict]:
        """By partition: between which hashes the units of a slice of places lie, and how many units have lesser ones.
        Hashes are counted once for the slices of the same partitions."""
        epoch, _, parts, low, high = load
        width = SPAN // CELLS
        if self._counted[0] != (epoch, parts):
            below = {p: np.zeros(CELLS + 1, dtype=np.int64) for p in parts}
            for r in rows.groupBy("part_id", F.floor(F.col("_r") / width).cast("int").alias("cell")).agg(F.count("*").alias("n")).collect():
                below[r.part_id][r.cell + 1] = r.n
            self._counted = ((epoch, parts), {p: np.cumsum(n) for p, n in below.items()})
        least, end, known = {}, {}, {}
        for p, below in self._counted[1].items():
            # a unit more on either side: a place is half a unit off its rank
            first, last = max(0, low * self.sizes[p] // SPAN - 1), high * self.sizes[p] // SPAN + 1
            at = int(np.searchsorted(below, first, "right")) - 1
            least[p], end[p], known[p] = at * width, min(CELLS, int(np.searchsorted(below, last))) * width, int(below[at])
        return least, end, known

    def cursor(self) -> tuple[int, int, int]:
        """(epoch, place after the partitions held, offset in them): where a later run goes on."""
        return self.epoch, self.at, self._gone + self.offset

    def seek(self, units: DataFrame, cursor: tuple[int, int, int], draws: int) -> None:
        """Goes on at a cursor. What is carried over came from partitions before, so with ``carry`` draws are repeated."""
        if self.carry:
            for _ in range(draws):
                self.draw_rows(units)
            return
        self.epoch, self.at, left = cursor
        if self.at:
            start = (self.at - 1) // self.mix * self.mix
            self._start(self.epoch, start)
            self.held, self._gone = self._load(units), 0
            while left > len(self.held) and self._ahead[3] > 0:
                left, self._gone = left - len(self.held), self._gone + len(self.held)
                self.held = self._load(units)
            self.offset = left

    def _load(self, units: DataFrame) -> list:
        """The next load; the scan reads its partitions alone."""
        load, self._ahead = self._ahead, next(self._loads)
        rows = self._next.result() if self._next else self._fetch(units, load)
        self.epoch, self.at = load[0], load[1] + len(load[2])
        self.reads += len(load[2]) * (load[3] == 0)
        for p in load[2]:
            self.opened[p] = self.opened.get(p, 0) + 1
        if self.prefetch:
            from concurrent.futures import ThreadPoolExecutor

            self._pool = self._pool or ThreadPoolExecutor(1)
            self._next = self._pool.submit(self._fetch, units, self._ahead)
        return rows

    def close(self) -> None:
        """Waits for a read in the background and drops it."""
        if self._pool:
            self._pool.shutdown(wait=True)
            self._pool = self._next = None

    def draw_rows(self, units: DataFrame) -> list:
        """The next batch as (part, row); a load and a batch are the most that is held."""
        while len(self.held) - self.offset < self._short:
            same = self._ahead[3] > 0  # a later slice of the same partition
            rest = self.held[self.offset :] if self.carry or same else []
            self._gone = self._gone + self.offset if same else 0
            self.held, self.offset = rest + self._load(units), 0
        batch = self.held[self.offset : self.offset + self._short]
        self.offset += self._short
        return batch


#: Users' samplers by name: (factory, cost). ``factory(sizes, batch, seed)`` gives an object whose ``draw(units, i)`` is a
#: DataFrame of about a batch; ``cost(data, m, env)`` gives a draw's seconds, or is None.
CUSTOM: dict[str, tuple] = {}


def register_sampler(name: str, factory, cost=None) -> None:
    """Adds a user's sampler to the space of plans, eager and lazy."""
    from ..plans.space import SAMPLERS

    CUSTOM[name] = (factory, cost)
    if name not in SAMPLERS:
        SAMPLERS.append(name)


def unregister_sampler(name: str) -> None:
    from ..plans.space import SAMPLERS

    CUSTOM.pop(name, None)
    if name in SAMPLERS:
        SAMPLERS.remove(name)


def draw_once(units: DataFrame, n: int, seed: int = 7) -> DataFrame:
    """The n units of lowest hash."""
    return units.orderBy(rank_key(seed, 0, F.col("unit_id")), "unit_id").limit(n)
