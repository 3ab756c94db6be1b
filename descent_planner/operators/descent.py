"""The seven operators and the algorithms made of them.

Stage sets the state on the driver, Transform is the expressions of ``sources.tasks``, Compute sums gradients over
units on the cluster (or in NumPy where a batch is on the driver), Update and Converge act on one vector, Loop stops.
Every iteration starts from the same plan of units: lineage doesn't grow. Weights travel as one array literal, so
that no iteration compiles anew.

Special cases: no units raise EmptyDataset; labels other than -1 and 1 raise for gradients that need signs; weights
that aren't finite end a run as DIVERGED; a batch of at least all units is all units.
"""

from __future__ import annotations

import time
from contextlib import contextmanager, nullcontext
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.gradients import GRADIENTS, Gradient, penalty, regulariser
from ..functions.steps import NORMS, STEPS, LoopRule
from .samplers import CUSTOM, SPAN, Bernoulli, Layout, RandomPartition, ShuffledPartition, here, partition_catalog, ranks, slice_of, with_parts

#: Up to this many features gradients are SQL sums; beyond it NumPy sums of Arrow batches.
SQL_FEATURES = 16
#: Most bytes of partial sums that a job returns to the driver; beyond it they are added by tree.
PARTIAL_BYTES = 256 << 20


class EmptyDataset(ValueError):
    """No unit to learn from."""


@dataclass
class Config:
    step: str = "inv_sqrt"
    beta: float = 1.0
    tolerance: float = 1e-3
    max_iter: int = 1000
    time_budget: float | None = None
    norm: str = "l1"
    reduce: str = "mean"
    reg: str = "none"
    lam: float = 0.0
    patience: int = 1
    weights: object = "zeros"
    seed: int = 7
    aggregation: str = "auto"
    on_empty: str = "redraw"

    def loop(self) -> LoopRule:
        return LoopRule(self.tolerance, self.max_iter, self.time_budget, self.patience)

    def alpha(self, i: int) -> float:
        return float(STEPS[self.step](self.beta, i))


@dataclass
class FitResult:
    weights: np.ndarray
    trace: list[dict]
    status: str
    config: Config
    seconds: float = 0.0
    touched: dict = field(default_factory=dict)

    @property
    def iterations(self) -> int:
        return len(self.trace)

    def trace_frame(self, spark: SparkSession) -> DataFrame:
        rows = [(r["iter"], r["delta"], r["n_used"], r["step"], bool(r["zero_step"]), r["millis"], [float(x) for x in r["w"]]) for r in self.trace]
        return spark.createDataFrame(rows, "iter int, delta double, n_used long, step double, zero_step boolean, millis double, w array<double>")


@dataclass
class Partial:
    """The sum of computed units: how many, loss and gradient."""

    n: int
    loss: float
    grad: np.ndarray


def stage(dim: int, cfg: Config, units: DataFrame | None = None) -> np.ndarray:
    """Initial weights: zeros, given ones, or the mean of a few units' features."""
    if isinstance(cfg.weights, str):
        if cfg.weights == "sample" and units is not None:
            rows = units.orderBy("unit_id").limit(10).select("features").collect()
            return np.mean([r.features for r in rows], axis=0)
        return np.zeros(dim)
    return np.array(cfg.weights, dtype=float)


def stage_stats(raw: DataFrame, columns: list[str]) -> dict:
    """Count, mean, deviation and range of columns in one job, which keeps lazy transformation legal."""
    aggs = [f(c).alias(f"{n}_{c}") for c in columns for n, f in (("mean", F.avg), ("std", F.stddev_pop), ("min", F.min), ("max", F.max))]
    return raw.agg(F.count("*").alias("n"), *aggs).first().asDict()


def standardised(columns: list[str], stats: dict) -> list[Column]:
    return [(F.col(c) - stats[f"mean_{c}"]) / (stats[f"std_{c}"] or 1.0) for c in columns]


def dimension(units: DataFrame) -> int:
    first = units.select(F.size("features").alias("d")).first()
    if first is None:
        raise EmptyDataset("the table has no units")
    return first.d


def vector(w: np.ndarray) -> Column:
    """A vector as one constant: one call to the JVM whatever its length, and folded into a literal by the optimiser."""
    return F.split(F.lit(",".join(repr(float(x)) for x in w)), ",").cast("array<double>")


def margin(w: np.ndarray) -> Column:
    """w.x with the weights as one literal, for units with ``features``."""
    if len(w) <= SQL_FEATURES:
        # an index that names a column (and is j): else each weight would be folded into a number of its own, which stands in the
        # generated code, so that every iteration compiled anew. One expression is one call to the JVM
        known = f"cast(split('{','.join(repr(float(x)) for x in w)}', ',') AS array<double>)"
        return F.expr(" + ".join(["0.0D", *(f"element_at(features, {j}) * element_at({known}, greatest({j}, least(size(features), 0)))" for j in range(1, len(w) + 1))]))
    return F.aggregate(F.zip_with("features", vector(w), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)


def compute(units: DataFrame, w: np.ndarray, gradient: Gradient, how: str = "auto") -> Partial:
    """The sum of the units' gradients and losses."""
    d = len(w)
    if how == "auto":
        how = "sql" if d <= SQL_FEATURES else "partials"
    if how == "sql":
        z = margin(w)
        c = gradient.coefficient(z, F.col("label"))
        row = units.select("features", c.alias("c"), gradient.loss(z, F.col("label")).alias("l")).agg(F.count("*"), F.sum("l"), *(F.expr(f"sum(c * element_at(features, {j + 1}))") for j in range(d))).first()
        return Partial(row[0], row[1] or 0.0, np.array([x or 0.0 for x in row[2:]]))
    if how == "keyed":
        z = margin(w)
        c = gradient.coefficient(z, F.col("label"))
        # count and loss ride along as the keys d and d + 1: one scan, one shuffle
        cells = units.select("features", c.alias("c"), gradient.loss(z, F.col("label")).alias("l")).select(F.posexplode(F.concat(F.transform("features", lambda x: F.col("c") * x), F.array(F.lit(1.0), F.col("l")))).alias("j", "x"))
        return _keyed(cells.groupBy("j").agg(F.sum("x").alias("g")).collect(), d)
    weights = np.asarray(w, dtype=float)
    coefficient, loss = gradient.np_coefficient, gradient.np_loss

    def sums(batches):
        n, total, grad = 0, 0.0, np.zeros(len(weights))
        for b in batches:
            if b.num_rows:
                x = b.column(1).flatten().to_numpy().reshape(b.num_rows, -1)
                y = b.column(0).to_numpy()
                z = x @ weights
                grad += x.T @ coefficient(z, y)
                total += float(loss(z, y).sum())
                n += b.num_rows
        yield pa.RecordBatch.from_arrays([pa.array([[*grad.tolist(), float(n), total]], pa.list_(pa.float64()))], ["sums"])

    parts = units.select("label", "features").mapInArrow(sums, "sums array<double>")
    if how == "tree" or _tasks(units) * d * 8 > PARTIAL_BYTES:
        return _keyed(parts.select(F.posexplode("sums").alias("j", "x")).groupBy("j").agg(F.sum("x").alias("g")).collect(), d)
    rows = parts.collect()
    total = np.sum([r.sums for r in rows], axis=0) if rows else np.zeros(d + 2)
    return Partial(int(total[d]), float(total[d + 1]), total[:d])


def _keyed(rows: list, d: int) -> Partial:
    """Sums by feature, with the count and the loss after the last one."""
    total = np.zeros(d + 2)
    for r in rows:
        total[r.j] = r.g or 0.0
    return Partial(int(total[d]), float(total[d + 1]), total[:d])


def _tasks(units: DataFrame) -> int:
    """How many tasks read ``units``; asked once a table, since the answer may run its shuffles."""
    known = units.__dict__.get("_task_count")
    if known is None:
        known = units.__dict__["_task_count"] = units.rdd.getNumPartitions()
    return known


def compute_local(x: np.ndarray, y: np.ndarray, w: np.ndarray, gradient: Gradient, loss: bool = True) -> Partial:
    """Compute on the driver; without ``loss`` where no one asks for it."""
    z = x @ w
    return Partial(len(y), float(gradient.np_loss(z, y).sum()) if loss else 0.0, x.T @ gradient.np_coefficient(z, y))


def update(p: Partial, w: np.ndarray, alpha: float, cfg: Config) -> np.ndarray:
    g = p.grad / p.n if cfg.reduce == "mean" and p.n else p.grad
    return w - alpha * (g + regulariser(cfg.reg, cfg.lam, w))


def check_labels(units: DataFrame, gradient: Gradient) -> None:
    if gradient.needs_signs and not units.where((F.col("label") != 1.0) & (F.col("label") != -1.0) | F.col("label").isNull()).isEmpty():
        raise ValueError(f"labels for {gradient.name} must be -1 or 1: map them in Transform")


def clean(units: DataFrame, on_bad: str = "fail") -> DataFrame:
    """Units with nulls or non-finite numbers: ``drop`` them, set the numbers to ``zero``, or ``fail`` with their count."""
    finite = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))
    good = finite(F.col("label")) & F.col("features").isNotNull() & F.forall("features", finite)
    if on_bad == "zero":
        return units.select("unit_id", F.when(finite(F.col("label")), F.col("label")).otherwise(0.0).alias("label"), F.transform("features", lambda x: F.when(finite(x), x).otherwise(0.0)).alias("features"))
    if on_bad == "fail":
        bad = units.where(~F.coalesce(good, F.lit(False))).count()
        if bad:
            raise ValueError(f"{bad} units hold nulls or numbers that aren't finite")
        return units
    return units.where(F.coalesce(good, F.lit(False)))


@dataclass
class RunLog:
    """Weights of every ``every``-th iteration as small tables under ``path``; a run over the same path goes on from the last.

    Bernoulli and random-partition draws depend on the iteration alone and shuffled partitions on their cursor, so that
    a run that is broken off and taken up ends with the weights of one that isn't.
    """

    spark: SparkSession
    path: str
    every: int = 10
    schema = "iter int, w array<double>, delta double, cursor array<int>"

    def last(self):
        p = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/*/_SUCCESS")
        done = p.getFileSystem(self.spark._jsc.hadoopConfiguration()).globStatus(p)
        if not done:
            return None
        i = max(int(s.getPath().getParent().getName()) for s in done)
        return self.spark.read.schema(self.schema).parquet(f"{self.path}/{i}").first()

    def save(self, i: int, w: np.ndarray, delta: float | None, cursor: tuple) -> None:
        row = (i, [float(x) for x in w], delta, [int(c) for c in cursor])
        self.spark.createDataFrame([row], self.schema).coalesce(1).write.mode("overwrite").parquet(f"{self.path}/{i}")


def _run(w: np.ndarray, cfg: Config, one, log: RunLog | None = None, seek=None, cursor=None) -> FitResult:
    """The loop: ``one(i, w)`` gives (new weights, units used, step). The trace of a run taken up holds its own iterations."""
    rule, trace, delta, i, began = cfg.loop(), [], None, 0, time.monotonic()
    saved = log.last() if log else None
    if saved:
        i, w, delta = saved.iter, np.array(saved.w), saved.delta
        if seek:
            seek(tuple(saved.cursor), i)
    while rule.should_continue(delta, i):
        i += 1
        t = time.monotonic()
        new, n_used, alpha = one(i, w)
        if new is None:  # an empty draw that is skipped: the iteration counts, the delta isn't tested
            trace.append({"iter": i, "delta": None, "n_used": 0, "step": alpha, "zero_step": True, "millis": 1e3 * (time.monotonic() - t), "w": w})
            delta = None
            continue
        delta = NORMS[cfg.norm](new - w)
        trace.append({"iter": i, "delta": delta, "n_used": n_used, "step": alpha, "zero_step": delta == 0, "millis": 1e3 * (time.monotonic() - t), "w": new})
        if np.isfinite(new).all():
            w = new
        else:
            rule.status = "DIVERGED"
            break
        if log and i % log.every == 0:
            log.save(i, w, delta, cursor() if cursor else ())
    return FitResult(w, trace, rule.status, cfg, time.monotonic() - began)


def _computed(units: DataFrame, cfg: Config) -> DataFrame:
    """What batch descent reads of units: without ids, which may cost a hash a row and take room in the cache."""
    return units if isinstance(cfg.weights, str) and cfg.weights == "sample" else units.select("label", "features")


@contextmanager
def kept(units: DataFrame, source: DataFrame | None = None):
    """Units in the cache while they are used. What a caller keeps there, them or the source they are taken from, is
    neither held twice nor dropped: a caller's next run would read and transform its table anew in each iteration."""
    level = (units if source is None else source).storageLevel
    if level.useMemory or level.useDisk:
        yield units
        return
    units = units.persist()
    try:
        yield units
    finally:
        units.unpersist()


def bgd(units: DataFrame, gradient: str = "linear", cfg: Config | None = None, cache: bool = True, log: RunLog | None = None) -> FitResult:
    """Batch descent: one aggregate of all units an iteration."""
    cfg, g = cfg or Config(), GRADIENTS[gradient]
    own = _computed(units, cfg)
    with kept(own, units) if cache else nullcontext(own) as rows:

        def one(i, w):
            p = compute(rows, w, g, cfg.aggregation)
            return update(p, w, cfg.alpha(i), cfg), p.n, cfg.alpha(i)

        return _run(stage(dimension(rows), cfg, rows), cfg, one, log)


def mgd(units: DataFrame, gradient: str = "linear", cfg: Config | None = None, batch: int = 1000, sampler: str = "bernoulli", transform=None, fraction: float | None = None, log: RunLog | None = None, layout: Layout | None = None, **sampler_options) -> FitResult:
    """Mini-batch descent. ``units`` hold part_id for the partition samplers, unless they are laid out in files: then a
    draw opens the files of its partitions alone.

    With ``transform`` the units are raw rows and are transformed after each draw (lazy); else they are transformed
    already (eager). Both draw by the units' ids, so that weights agree to the bit. The result's ``touched`` counts
    units, partitions and, with a layout, bytes that draws read.
    """
    cfg, g = cfg or Config(), GRADIENTS[gradient]
    units = layout.rows if layout else units
    lazily = transform or (lambda df: df)
    sample = lazily(units.limit(1))
    d = dimension(sample)
    touched = {"units": 0, "partitions": 0, "bytes": 0}
    seek = cursor = None

    def opened(parts) -> None:
        touched["partitions"] += len(parts)
        if layout:
            touched["bytes"] += sum(layout.bytes[p] for p in parts)

    if sampler == "bernoulli":
        n = sum(layout.sizes.values()) if layout else units.count()
        chooser = Bernoulli(fraction if fraction is not None else min(1.0, batch / n), cfg.seed, **sampler_options)

        def one(i, w):
            for again in range(10):
                p = compute(lazily(chooser.draw(units, i + again * 1_000_003)), w, g, cfg.aggregation)
                touched["units"] += n
                if layout:
                    opened(layout.sizes)
                if p.n or cfg.on_empty == "skip":
                    break
            return (update(p, w, cfg.alpha(i), cfg) if p.n else None), p.n, cfg.alpha(i)

    else:
        sizes = layout.sizes if layout else {r.part_id: r.n_units for r in partition_catalog(units).collect()}
        read = {"read": layout.read} if layout else {}
        if sampler == "random":
            chooser = RandomPartition(sizes, min(batch, sum(sizes.values())), cfg.seed, **read, **sampler_options)

            def one(i, w):
                opened({p for p, _ in chooser.picks(i)})
                x, y = local(lazily(chooser.draw(units, i)))
                touched["units"] += len(y)
                return update(compute_local(x, y, w, g, False), w, cfg.alpha(i), cfg), len(y), cfg.alpha(i)

        elif sampler in CUSTOM:
            chooser = CUSTOM[sampler][0](sizes, batch, cfg.seed, **sampler_options)

            def one(i, w):
                p = compute(lazily(chooser.draw(units, i)), w, g, cfg.aggregation)
                touched["units"] += p.n
                return (update(p, w, cfg.alpha(i), cfg) if p.n else None), p.n, cfg.alpha(i)

        else:
            chooser = ShuffledPartition(sizes, batch, cfg.seed, **({"slice_units": slice_of(d)} | read | sampler_options))
            made: dict = {}
            seek, cursor = (lambda at, draws: chooser.seek(units, at, draws)), chooser.cursor

            def one(i, w):
                rows = [r for _, r in chooser.draw_rows(units)]
                touched["partitions"] = chooser.reads
                if layout:
                    touched["bytes"] = sum(layout.bytes[p] * k for p, k in chooser.opened.items())
                touched["units"] += len(rows)
                if transform is None:
                    x, y = np.array([r.features for r in rows], dtype=float), np.array([r.label for r in rows], dtype=float)
                else:
                    made["schema"] = made.get("schema") or units.schema
                    # the batch's order stays that of the draw, so that sums are those of the eager plan
                    x, y = _in_order(lazily(here(units.sparkSession, rows, made["schema"])))
                return update(compute_local(x, y, w, g, False), w, cfg.alpha(i), cfg), len(y), cfg.alpha(i)

    try:
        out = _run(stage(d, cfg, units if transform is None else sample), cfg, one, log, seek, cursor)
    finally:
        if isinstance(chooser, ShuffledPartition):
            chooser.close()
    out.touched = touched
    return out


def _in_order(units: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of rows as they come."""
    rows = units.select("label", "features").collect()
    return np.array([r.features for r in rows], dtype=float), np.array([r.label for r in rows], dtype=float)


def on_driver(ids: np.ndarray, x: np.ndarray, y: np.ndarray, gradient: str, cfg: Config, algorithm: str, batch: int = 1000, sampler: str = "shuffle", parts: int = 8, fraction: float | None = None) -> FitResult:
    """An algorithm over units that one partition holds, without a job: draws are those of the samplers on the cluster,
    by the same hashes of the same ids, so that the weights are those of the cluster's run."""
    g, n = GRADIENTS[gradient], len(y)
    if not n:
        raise EmptyDataset("no unit to learn from")
    order = np.lexsort((y, ids))
    ids, x, y = ids[order], x[order], y[order]
    part = ids % parts
    of = {int(p): np.flatnonzero(part == p) for p in np.unique(part)}
    sizes = {p: len(rows) for p, rows in of.items()}
    touched = {"units": 0, "partitions": 0, "bytes": 0}
    m = 1 if algorithm == "sgd" else batch

    def source(chosen, epoch, low, high):
        rows = np.concatenate([of[p] for p in chosen])
        r = ranks(cfg.seed, epoch, ids[rows])
        rows, r = rows[(r >= low) & (r < high)], r[(r >= low) & (r < high)]
        rows = rows[np.lexsort((rows, part[rows], ids[rows], r))]
        return list(zip(part[rows].tolist(), rows.tolist(), strict=True))

    if algorithm == "bgd":
        draw = lambda i: slice(None)
    elif sampler == "bernoulli":
        limit = min(1.0, fraction if fraction is not None else m / n) * SPAN

        def draw(i):
            for again in range(10):
                touched["units"] += n
                rows = np.flatnonzero(ranks(cfg.seed, i + again * 1_000_003, ids) < limit)
                if len(rows) or cfg.on_empty == "skip":
                    break
            return rows

    elif sampler == "random":
        chooser = RandomPartition(sizes, min(m, n), cfg.seed)

        def draw(i):
            picks = chooser.picks(i)
            touched["partitions"] += len({p for p, _ in picks})
            return np.sort([of[p][o] for p, o in picks])

    else:
        chooser = ShuffledPartition(sizes, m, cfg.seed, source=source)

        def draw(i):
            rows = np.array([k for _, k in chooser.draw_rows(None)])
            touched["partitions"] = chooser.reads
            return rows

    def one(i, w):
        rows = draw(i)
        p = compute_local(x[rows], y[rows], w, g, False)
        touched["units"] += p.n * (sampler != "bernoulli" or algorithm == "bgd")
        return (update(p, w, cfg.alpha(i), cfg) if p.n else None), p.n, cfg.alpha(i)

    out = _run(stage(x.shape[1], cfg), cfg, one)
    out.touched = touched
    return out


def arrays(units: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Ids, features and labels as they come, by Arrow: no object a number on the driver."""
    t = units.select("unit_id", F.col("label").cast("double"), F.col("features").cast("array<double>")).toArrow()
    flat = t.column(2).combine_chunks().flatten().to_numpy(zero_copy_only=False)
    return t.column(0).to_numpy(), flat.reshape(t.num_rows, -1) if t.num_rows else flat, t.column(1).to_numpy()


def local(units: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Features and labels of a bounded draw, in order of the ids."""
    ids, x, y = arrays(units)
    # repeated ids are in order of their labels and features
    order = np.lexsort((*x.T[::-1], y, ids)) if len(np.unique(ids)) < len(ids) else np.argsort(ids)
    return x[order], y[order]


def sgd(units: DataFrame, gradient: str = "linear", cfg: Config | None = None, sampler: str = "shuffle", **options) -> FitResult:
    """A batch of one."""
    return mgd(units, gradient, cfg, batch=1, sampler=sampler, **options)


def svrg(units: DataFrame, gradient: str, cfg: Config, every: int) -> FitResult:
    """Variance reduction: a full mean gradient at an anchor every ``every`` iterations, single units between.

    An iteration i is an anchor's when (i - 1) mod every is 0; the anchor is the weights before it, and the step of that
    iteration is the full gradient's, so that every = 1 is batch descent.
    """
    g = GRADIENTS[gradient]
    sizes = {r.part_id: r.n_units for r in partition_catalog(units).collect()}
    chooser = ShuffledPartition(sizes, 1, cfg.seed)
    d = dimension(units)
    at: dict = {}

    def one(i, w):
        if (i - 1) % every == 0:
            p = compute(units, w, g, cfg.aggregation)
            at["w"], at["mu"] = w, p.grad / p.n
            return w - cfg.alpha(i) * (at["mu"] + regulariser(cfg.reg, cfg.lam, w)), p.n, cfg.alpha(i)
        r = chooser.draw_rows(units)[0][1]
        x, y = np.array([r.features], dtype=float), np.array([r.label])
        v = compute_local(x, y, w, g).grad - compute_local(x, y, at["w"], g).grad + at["mu"]
        return w - cfg.alpha(i) * (v + regulariser(cfg.reg, cfg.lam, w)), 1, cfg.alpha(i)

    return _run(stage(d, cfg, units), cfg, one)


def losses_along(units: DataFrame, w: np.ndarray, direction: np.ndarray, alphas: list[float], gradient: Gradient) -> list[float]:
    """Mean losses at w - alpha * direction for every alpha, in one scan."""
    z0, z1 = margin(w), margin(direction)
    row = units.select(z0.alias("z0"), z1.alias("z1"), "label").agg(*(F.avg(gradient.loss(F.col("z0") - F.lit(float(a)) * F.col("z1"), F.col("label"))) for a in alphas)).first()
    return list(row)


def bgd_line_search(units: DataFrame, gradient: str, cfg: Config, shrink: float = 0.5, rule: str = "armijo", trials: int = 12, sigma: float = 1e-4, serial: bool = False) -> FitResult:
    """Batch descent whose step shrinks until a decrease test holds.

    ``armijo`` takes the first step whose decrease is at least sigma * alpha * |g|^2. ``printed`` shrinks while the
    decrease is at least alpha * i, as the source text says it, up to ``trials``. Steps of a trial series are evaluated
    in one scan, or one by one with ``serial``; both give the same step.
    """
    g = GRADIENTS[gradient]
    units = _computed(units, cfg).persist()
    d = dimension(units)
    grid = [cfg.beta * shrink**k for k in range(trials)]

    def one(i, w):
        p = compute(units, w, g, cfg.aggregation)
        grad, f0 = p.grad / p.n + regulariser(cfg.reg, cfg.lam, w), p.loss / p.n + penalty(cfg.reg, cfg.lam, w)
        losses = (lambda k: losses_along(units, w, grad, [grid[k]], g)[0]) if serial else losses_along(units, w, grad, grid, g).__getitem__
        values = lambda k: losses(k) + penalty(cfg.reg, cfg.lam, w - grid[k] * grad)
        for k, a in enumerate(grid):
            drop = f0 - values(k)
            if rule == "armijo" and drop >= sigma * a * float(grad @ grad) or rule == "printed" and drop < a * i:
                break
        if rule == "armijo" and drop < 0:
            return w, p.n, 0.0
        return w - a * grad, p.n, a

    try:
        return _run(stage(d, cfg, units), cfg, one)
    finally:
        units.unpersist()


def bgd_bb(units: DataFrame, gradient: str, cfg: Config, kind: int = 1) -> FitResult:
    """Batch descent with the step from the last two weights and gradients; the first step is the configured one."""
    g = GRADIENTS[gradient]
    units = _computed(units, cfg).persist()
    last: dict = {}

    def one(i, w):
        p = compute(units, w, g, cfg.aggregation)
        grad = p.grad / p.n + regulariser(cfg.reg, cfg.lam, w)
        alpha = cfg.alpha(i)
        if last:
            s, y = w - last["w"], grad - last["g"]
            top, low = (s @ s, s @ y) if kind == 1 else (s @ y, y @ y)
            if low > 0 and top > 0:
                alpha = float(top / low)
        last.update(w=w, g=grad)
        return w - alpha * grad, p.n, alpha

    try:
        return _run(stage(dimension(units), cfg, units), cfg, one)
    finally:
        units.unpersist()


def objective(units: DataFrame, w: np.ndarray, gradient: str, reg: str = "none", lam: float = 0.0) -> float:
    p = compute(units, w, GRADIENTS[gradient])
    return p.loss / p.n + penalty(reg, lam, np.asarray(w))


#: Algorithms by name; a user's enlarges the plan space.
ALGORITHMS = {"bgd": bgd, "mgd": mgd, "sgd": sgd}


def register_algorithm(name: str, run, samples: bool = False, scans: float = 1.0) -> None:
    """Adds ``run(units, gradient, cfg)`` to the space of plans. Its units hold part_id; it gives a FitResult.

    Its iterations are estimated by running it over the speculation's sample. An iteration costs ``scans`` scans of all
    units, or with ``samples`` what a sampled batch does; then it takes samplers and laziness as MGD does.
    """
    from ..plans.space import SAMPLED, SCANS

    ALGORITHMS[name] = run
    SAMPLED[name] = samples
    SCANS[name] = scans


def unregister_algorithm(name: str) -> None:
    from ..plans.space import SAMPLED, SCANS

    for known in (ALGORITHMS, SAMPLED, SCANS):
        known.pop(name, None)


#: Most bytes of weights that every task holds; beyond them weights are a table.
WEIGHT_BYTES = 256 << 20


def sparse_margins(sparse: DataFrame, weights: DataFrame) -> DataFrame:
    """(unit_id, label, z, cells) by joining features with a table of weights (j, w): for dimensions that no task can
    hold. A hot feature is one row of the weights' side, so a skewed join splits the features' side."""
    pairs = sparse.select("unit_id", "label", F.explode(F.arrays_zip("idx", "val")).alias("p")).select("unit_id", "label", F.col("p.idx").alias("j"), F.col("p.val").alias("x"))
    met = pairs.join(weights, "j", "left")
    return met.groupBy("unit_id", "label").agg(F.sum(F.col("x") * F.coalesce("w", F.lit(0.0))).alias("z"), F.collect_list(F.struct("j", "x")).alias("cells"))


def sparse_gradient(margins: DataFrame, gradient: Gradient) -> DataFrame:
    """(j, g): the sum of gradients keyed by feature; the margins hold the units' features, so none is read again."""
    c = margins.select(gradient.coefficient(F.col("z"), F.col("label")).alias("c"), F.explode("cells").alias("p"))
    return c.groupBy(F.col("p.j").alias("j")).agg(F.sum(F.col("c") * F.col("p.x")).alias("g"))


def sparse_partials(sparse: DataFrame, w: np.ndarray, gradient: Gradient) -> DataFrame:
    """(j, g) with the weights in every task: each adds its units by Arrow batches, so that a task sends a row for each
    feature that it met, and features meet in one shuffle. Weights beyond ``WEIGHT_BYTES`` raise."""
    if w.nbytes > WEIGHT_BYTES:
        raise ValueError(f"{w.nbytes} bytes of weights: use sparse_margins with a table of them")
    known = sparse.sparkSession.sparkContext.broadcast(np.asarray(w, dtype=float))
    coefficient = gradient.np_coefficient

    def sums(batches):
        weights = known.value
        grad, met = np.zeros(len(weights)), np.zeros(len(weights), dtype=bool)
        for b in batches:
            if b.num_rows:
                n = np.diff(b.column(1).offsets.to_numpy())
                j, x = b.column(1).flatten().to_numpy(), b.column(2).flatten().to_numpy()
                row = np.repeat(np.arange(b.num_rows), n)
                inside = j < len(weights)
                j, x, row = j[inside], x[inside], row[inside]
                z = np.bincount(row, weights=weights[j] * x, minlength=b.num_rows)
                np.add.at(grad, j, coefficient(z, b.column(0).to_numpy())[row] * x)
                met[j] = True
        at = np.flatnonzero(met)
        for k in range(0, len(at), 10_000):
            own = at[k : k + 10_000]
            yield pa.RecordBatch.from_arrays([pa.array(own.astype(np.int32)), pa.array(grad[own])], ["j", "g"])

    return sparse.select("label", "idx", "val").mapInArrow(sums, "j int, g double").groupBy("j").agg(F.sum("g").alias("g"))


def bgd_sparse(sparse: DataFrame, gradient: str, cfg: Config, dim: int) -> FitResult:
    """Batch descent over sparse units, with partial sums by task."""
    g = GRADIENTS[gradient]
    with kept(sparse) as rows:
        n = rows.count()

        def one(i, w):
            grad = np.zeros(dim)
            found = sparse_partials(rows, w, g).toArrow()
            grad[found.column(0).to_numpy()] = found.column(1).to_numpy()
            return update(Partial(n, 0.0, grad), w, cfg.alpha(i), cfg), n, cfg.alpha(i)

        return _run(stage(dim, cfg), cfg, one)


def sgd_sparse(sparse: DataFrame, gradient: str, cfg: Config, dim: int, parts: int = 8) -> FitResult:
    """SGD over sparse units of shuffled partitions: an iteration changes the weights of one unit's features."""
    g = GRADIENTS[gradient]
    units = with_parts(sparse, parts)
    found = units.groupBy("part_id").agg(F.count("*").alias("n"), F.sum(F.size("idx")).alias("cells")).collect()
    # a cell is two numbers
    longest = max((2 * r.cells / r.n for r in found), default=0)
    chooser = ShuffledPartition({r.part_id: r.n for r in found}, 1, cfg.seed, slice_units=slice_of(longest))

    def one(i, w):
        r = chooser.draw_rows(units)[0][1]
        j, x = np.array(r.idx, dtype=np.int64), np.array(r.val, dtype=float)
        new = w.copy()
        new[j] -= cfg.alpha(i) * float(g.np_coefficient(np.array([w[j] @ x]), np.array([r.label]))[0]) * x
        return new, 1, cfg.alpha(i)

    return _run(stage(dim, cfg), cfg, one)


def with_tolerance(cfg: Config, **changes) -> Config:
    return replace(cfg, **changes)
