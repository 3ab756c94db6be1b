"""Baselines. Stand-ins for systems that aren't here are our own re-creations, and say so in their names."""

from __future__ import annotations

import time
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.gradients import GRADIENTS
from .descent import SQL_FEATURES, Config, FitResult, Partial, _keyed, _run, compute, compute_local, dimension, kept, margin, stage, update
from .samplers import SPAN, Bernoulli, py_rank, rank_below, rank_key, ranks


def vector_cells(values: str, idx: str | None = None, dim: int | None = None) -> Column:
    """An array as the library's vectors are stored: dense, or sparse with its indices and dimension."""
    kind, size = F.lit(1 if idx is None else 0).cast("tinyint"), F.lit(dim).cast("int")
    return F.struct(kind.alias("type"), size.alias("size"), (F.lit(None) if idx is None else F.col(idx)).cast("array<int>").alias("indices"), F.col(values).cast("array<double>").alias("values"))


def labeled_points(units: DataFrame, label: Column, cells: Column):
    """The library's points of units, in the units' order and partitions, made where units are: none passes Python."""
    spark = units.sparkSession
    jvm, gateway = spark._jvm, spark.sparkContext._gateway
    of, encoders = jvm.java.lang.Class.forName, "org.apache.spark.sql.catalyst.encoders.AgnosticEncoders$"
    single = lambda name: of(f"{name}$").getField("MODULE$").get(None)

    def made(name, *options):
        given = gateway.new_array(jvm.java.lang.Object, len(options))
        for k, v in enumerate(options):
            given[k] = v
        return of(encoders + name).getConstructors()[0].newInstance(given)

    types, vectors, none = jvm.org.apache.spark.sql.types, jvm.org.apache.spark.mllib.linalg.VectorUDT(), single("scala.None")
    rows = units.select(F.coalesce(label.cast("double"), F.lit(float("nan"))).alias("label"), cells.alias("features"))
    schema = types.StructType().add("label", types.DataTypes.DoubleType, False).add("features", vectors, False)
    typed = spark._jsparkSession.internalCreateDataFrame(rows._jdf.queryExecution().toRdd(), schema, False)
    kinds = (("label", single(encoders + "PrimitiveDoubleEncoder")), ("features", made("UDTEncoder", vectors, vectors.getClass())))
    fields = [made("EncoderField", name, kind, False, types.Metadata.empty(), none, none) for name, kind in kinds]
    point = single("scala.reflect.ClassTag").apply(of("org.apache.spark.mllib.regression.LabeledPoint"))
    product = made("ProductEncoder", point, jvm.PythonUtils.toSeq(fields).toList(), none)
    return getattr(typed, "as")(jvm.org.apache.spark.sql.catalyst.encoders.ExpressionEncoder.apply(product)).toJavaRDD()


def _train(kind: str, points, cfg: Config, step: float, fraction: float, d: int, reg_type: str | None, tolerance: float) -> np.ndarray:
    """The library's training over points of its own; it keeps them in memory or on disk while it runs."""
    from pyspark.mllib.common import callMLlibFunc
    from pyspark.mllib.linalg import Vectors

    first, rate = Vectors.dense(np.zeros(d)), (float(fraction), float(cfg.lam))
    # the library's own order of options differs by model
    name, (a, b, c) = {
        "linear": ("trainLinearRegressionModelWithSGD", (rate[0], first, rate[1])),
        "logistic": ("trainLogisticRegressionModelWithSGD", (rate[0], first, rate[1])),
        "hinge": ("trainSVMModelWithSGD", (rate[1], rate[0], first)),
    }[kind]
    model = callMLlibFunc(name, points, int(cfg.max_iter), float(step), a, b, c, reg_type, False, True, float(tolerance))
    return np.array(model[0].toArray())


def library_sgd(units: DataFrame, gradient: str, cfg: Config, fraction: float = 1.0) -> FitResult:
    """Spark's own RDD library: Bernoulli samples each iteration and a tree of partial sums; fraction 1 is batch descent.

    Its step rule is beta / sqrt(i), its labels are 0 and 1, and its tolerance is relative.
    """
    began = time.monotonic()
    signs = GRADIENTS[gradient].needs_signs
    d = dimension(units)
    points = labeled_points(units, (F.col("label") + 1) / 2 if signs else F.col("label"), vector_cells("features"))
    # the library's squared loss is half of ours
    step = cfg.beta * (2 if gradient == "linear" else 1)
    w = _train(gradient, points, cfg, step, fraction, d, None if cfg.reg == "none" else cfg.reg, cfg.tolerance)
    return FitResult(w, [], "DONE", cfg, time.monotonic() - began)


def library_sparse(sparse: DataFrame, cfg: Config, dim: int, fraction: float = 1.0) -> FitResult:
    """The library's logistic regression over sparse vectors."""
    began = time.monotonic()
    points = labeled_points(sparse, (F.col("label") + 1) / 2, vector_cells("val", "idx", dim))
    w = _train("logistic", points, replace(cfg, lam=0.0), cfg.beta, fraction, dim, None, 0.0)
    return FitResult(w, [], "DONE", cfg, time.monotonic() - began)


def bernoulli_tree(units: DataFrame, gradient: str, cfg: Config, fraction: float = 1.0) -> FitResult:
    """The library's way on DataFrames: a Bernoulli sample of the whole table each iteration, partial sums added by tree."""
    g = GRADIENTS[gradient]
    with kept(units) as rows:

        def one(i, w):
            p = compute(rows if fraction >= 1 else rows.sample(fraction=fraction, seed=cfg.seed + i), w, g, "tree")
            return (update(p, w, cfg.alpha(i), cfg) if p.n else None), p.n, cfg.alpha(i)

        return _run(stage(dimension(rows), cfg), cfg, one)


def drawn(ids: np.ndarray, seed: int, i: int, fraction: float) -> np.ndarray:
    """Which ids the Bernoulli sampler keeps in draw i."""
    return ranks(seed, i, ids) < min(1.0, fraction) * SPAN


def _blocks(units: DataFrame, block_rows: int = 4096) -> DataFrame:
    """(n, y, x, ids) of (label, features, id): rows as binary blocks; without an id its block is null."""

    def to_blocks(batches):
        for b in batches:
            for at in range(0, b.num_rows, block_rows):
                part = b.slice(at, block_rows)
                x = part.column(1).flatten().to_numpy().astype("<f8")
                ids = part.column(2).to_numpy().astype("<i8").tobytes() if part.num_columns > 2 else None
                yield pa.RecordBatch.from_arrays([pa.array([part.num_rows]), pa.array([part.column(0).to_numpy().astype("<f8").tobytes()], pa.binary()), pa.array([x.tobytes()], pa.binary()), pa.array([ids], pa.binary())], ["n", "y", "x", "ids"])

    return units.mapInArrow(to_blocks, "n long, y binary, x binary, ids binary")


def matrix_blocks_standin(units: DataFrame, gradient: str, cfg: Config, block_rows: int = 4096, fraction: float = 1.0) -> tuple[FitResult, float]:
    """Stand-in for a declarative matrix system: rows are converted to binary blocks first (its seconds apart), then
    each iteration is a block-wise product; one block runs on the driver. With a ``fraction`` each block multiplies a
    selection of its rows (MGD, SGD), for which it is read whole; an iteration whose selection is empty changes nothing."""
    g = GRADIENTS[gradient]
    began = time.monotonic()
    d = dimension(units)

    blocks = _blocks(units.select("label", "features", F.col("unit_id").cast("long")), block_rows).persist()
    many = blocks.count() > 1
    conversion = time.monotonic() - began
    coefficient, loss, seed = g.np_coefficient, g.np_loss, cfg.seed
    if not many:
        one_block = blocks.first()
        x, y, ids = (np.frombuffer(b, kind) for b, kind in zip((one_block.x, one_block.y, one_block.ids) if one_block else (b"", b"", b""), ("<f8", "<f8", "<i8"), strict=True))
        x = x.reshape(len(y), -1)

    def one(i, w):
        if not many:
            rows = drawn(ids, seed, i, fraction) if fraction < 1 else slice(None)
            p = compute_local(x[rows], y[rows], w, g)
        else:

            def products(batches, w=w):
                for b in batches:
                    for n, y, x, ids in zip(*(b.column(k).to_pylist() for k in range(4)), strict=True):
                        m, t = np.frombuffer(x, "<f8").reshape(n, -1), np.frombuffer(y, "<f8")
                        if fraction < 1:
                            rows = drawn(np.frombuffer(ids, "<i8"), seed, i, fraction)
                            m, t = m[rows], t[rows]
                        z = m @ w
                        yield pa.RecordBatch.from_arrays([pa.array([[*(m.T @ coefficient(z, t)).tolist(), float(len(t)), float(loss(z, t).sum())]], pa.list_(pa.float64()))], ["sums"])

            sums = blocks.mapInArrow(products, "sums array<double>").select(F.posexplode("sums").alias("j", "x")).groupBy("j").agg(F.sum("x").alias("g")).collect()
            p = _keyed(sums, d)
        return (update(p, w, cfg.alpha(i), cfg) if p.n else None), p.n, cfg.alpha(i)

    try:
        return _run(np.zeros(d), cfg, one), conversion
    finally:
        blocks.unpersist()


def fused_standin(units: DataFrame, gradient: str, cfg: Config, max_bytes: int | None = None, fraction: float = 1.0) -> FitResult:
    """Stand-in for an abstraction that fuses Compute and Update: all units of an iteration pass one task, which holds an
    Arrow batch of them at a time. With ``max_bytes``, a capacity, reports FAILED_CAPACITY where those units hold more.
    Reading and Transform are parallel. All units pass as binary blocks, in the order they are read in; with a
    ``fraction`` the sample is drawn in parallel and goes to the one task in order of its ids (MGD, SGD)."""
    g = GRADIENTS[gradient]
    d = dimension(units)
    if max_bytes is not None and units.count() * min(1.0, fraction) * d * 8 > max_bytes:
        return FitResult(np.zeros(d), [], "FAILED_CAPACITY", cfg)
    whole = fraction >= 1
    own = _blocks(units.select("label", "features")).drop("ids") if whole else units.select("unit_id", "label", "features")
    coefficient, sampler = g.np_coefficient, Bernoulli(fraction, cfg.seed)

    def one(i, w):
        def serial(batches, w=w):
            grad, n = np.zeros(d), 0
            for b in batches:
                if not b.num_rows:
                    continue
                if whole:
                    own = ((np.frombuffer(x.as_py(), "<f8").reshape(-1, d), np.frombuffer(y.as_py(), "<f8")) for y, x in zip(b.column(1), b.column(2), strict=True))
                else:
                    own = [(b.column(2).flatten().to_numpy().reshape(b.num_rows, -1), b.column(1).to_numpy())]
                for x, y in own:
                    grad += x.T @ coefficient(x @ w, y)
                    n += len(y)
            yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([grad.tolist()], pa.list_(pa.float64()))], ["n", "grad"])

        batch = mine.coalesce(1) if whole else sampler.draw(mine, i).repartition(1).sortWithinPartitions("unit_id")
        r = batch.mapInArrow(serial, "n long, grad array<double>").first()
        return (update(Partial(r.n, 0.0, np.array(r.grad)), w, cfg.alpha(i), cfg) if r and r.n else None), r.n if r else 0, cfg.alpha(i)

    with kept(own) if whole else kept(own, units) as mine:
        if whole:
            # filled by as many tasks as read the table; the one task of an iteration would else read it alone
            mine.count()
        return _run(np.zeros(d), cfg, one)


def handcoded_bgd(units: DataFrame, gradient: str, iterations: int, beta: float = 1.0, fraction: float = 1.0, seed: int = 7) -> np.ndarray:
    """The same plan as a straight loop without operators; with a ``fraction`` over a Bernoulli sample (MGD, SGD)."""
    with kept(units) as rows:
        return _straight(rows, gradient, iterations, beta, fraction, seed)


def _straight(units: DataFrame, gradient: str, iterations: int, beta: float, fraction: float, seed: int) -> np.ndarray:
    g = GRADIENTS[gradient]
    w = np.zeros(dimension(units))
    coefficient = g.np_coefficient
    for i in range(1, iterations + 1):
        rows = units if fraction >= 1 else units.where(rank_below(seed, i, F.col("unit_id"), fraction * SPAN))
        if len(w) <= SQL_FEATURES:
            # numbers of their own in the code would have it compiled anew each time
            c = g.coefficient(margin(w), F.col("label"))
            mean = rows.select("features", c.alias("c")).agg(*(F.expr(f"avg(c * element_at(features, {j + 1}))") for j in range(len(w)))).first()
            mean = None if mean[0] is None else np.array(mean)
        else:

            def sums(batches, w=w):
                total = np.zeros(len(w) + 1)
                for b in batches:
                    if b.num_rows:
                        x = b.column(1).flatten().to_numpy().reshape(b.num_rows, -1)
                        total[:-1] += x.T @ coefficient(x @ w, b.column(0).to_numpy())
                        total[-1] += b.num_rows
                yield pa.RecordBatch.from_arrays([pa.array([total.tolist()], pa.list_(pa.float64()))], ["t"])

            total = np.sum([r.t for r in rows.select("label", "features").mapInArrow(sums, "t array<double>").collect()], axis=0)
            mean = total[:-1] / total[-1] if total[-1] else None
        if mean is not None:
            w = w - beta / np.sqrt(i) * mean
    return w


def handcoded_shuffled(units: DataFrame, gradient: str, iterations: int, batch: int = 1, beta: float = 1.0, seed: int = 7) -> np.ndarray:
    """MGD or SGD over shuffled partitions as a straight loop: one partition after the other, in order of its hashes."""
    g = GRADIENTS[gradient]
    sizes = {r.part_id: r.n for r in units.groupBy("part_id").agg(F.count("*").alias("n")).collect()}
    w, i, epoch = np.zeros(dimension(units)), 0, 0
    while i < iterations:
        before = i
        for p in sorted(sizes, key=lambda p: (py_rank(seed, epoch, f"part{p}"), p)):
            if i == iterations:
                break
            rows = units.where(F.col("part_id") == p).orderBy(rank_key(seed, epoch, F.col("unit_id")), "unit_id").select("label", "features").collect()
            for at in range(0, len(rows) - batch + 1, batch):
                if i == iterations:
                    break
                i += 1
                x, y = np.array([r.features for r in rows[at : at + batch]], dtype=float), np.array([r.label for r in rows[at : at + batch]], dtype=float)
                w = w - beta / np.sqrt(i) * (x.T @ g.np_coefficient(x @ w, y)) / batch
        epoch += 1
        if i == before:
            raise ValueError("no partition holds a batch")
    return w


def ols_exact(units: DataFrame) -> np.ndarray:
    """Normal equations from one aggregate of the Gram matrix, for few features."""
    d = dimension(units)
    x = [F.element_at("features", j + 1) for j in range(d)]
    row = units.agg(*(F.sum(x[a] * x[b]) for a in range(d) for b in range(d)), *(F.sum(x[a] * F.col("label")) for a in range(d))).first()
    return np.linalg.lstsq(np.array(row[: d * d]).reshape(d, d), np.array(row[d * d :]), rcond=None)[0]
