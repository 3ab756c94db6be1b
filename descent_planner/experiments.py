"""The experiments, each a query of measured rows over the given tables.

Seconds differ from run to run, so these have no oracle; tests hold what must not differ. Runs go to the survey's
tolerances or 1,000 iterations, with batches of 1,000. Plans are placed as ``execute`` places them: over a set that
one partition holds they run on the driver, over a larger one on the cluster. A job an iteration of a system that has
no placement (library, stand-ins) costs a fixed time whatever the set, so those run ``SYSTEM_ITERATIONS`` iterations
and their seconds are compared by iteration; README names this and every other reduction. A run over ``BUDGET_S``
seconds ends with status TIME, and then no error is computed from it.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import baselines, descent, metrics, samplers
from .operators.descent import Config
from .plans import cost, estimate, optimizer
from .plans.optimizer import Request
from .sources import tasks
from .sources.folders import new_folder
from .sources.tasks import W1, W2, W2_SVM, W6

QUERIES: dict = {}
#: No oracle: measured seconds.
ORACLES: dict[str, str] = {}

#: The largest dimension at which hashed texts are taken as dense units.
TEXT_DIM = 128
CAP = 1000


def language(spark: SparkSession, sf: str, dim: int = TEXT_DIM) -> DataFrame:
    return tasks.densify(tasks.doc_language(spark, sf, dim))


#: Iterations of systems that run a job each, and seconds after which a run ends.
SYSTEM_ITERATIONS, BUDGET_S = 10, 6.0

#: name: (units, gradient, step's beta, tolerance of the total-time experiment)
SETS = {
    "big_charge": (W2.units, "logistic", 1.0, 1e-3),
    "halfspace": (tasks.halfspace, "hinge", 1.0, 1e-3),
    "doc_language": (language, "logistic", 1.0, 1e-2),
    "charge_regression": (W1.units, "linear", 0.3, 1e-1),
}


def raw_set(spark: SparkSession, sf: str, name: str):
    """(raw rows with unit_id, Transform) of a set, so that lazy plans have something to put off."""
    if name in ("big_charge", "charge_regression"):
        task = tasks.TASKS[name]
        return tasks.table(spark, sf, task.table).selectExpr("*", f"{task.unit_id} AS unit_id"), lambda df: tasks.transform_columns(df, "unit_id", task.label, task.features)
    if name == "halfspace":
        return tasks.table(spark, sf, "embeddings").withColumn("unit_id", F.col("vec_id")), tasks.side_of_plane
    # hashing needs the words of a whole text, and the label: sparse rows are raw, spreading them out is Transform
    return tasks.doc_language(spark, sf, TEXT_DIM), tasks.densify
ALGORITHMS = ("bgd", "mgd", "sgd")


def dealt(spark: SparkSession, sf: str, name: str) -> DataFrame:
    """A set's units over all cores: a small table is read by a few tasks, which would bound every scan of its units."""
    if name in tasks.TASKS:
        task = tasks.TASKS[name]
        return task.over(tasks.spread(tasks.table(spark, sf, task.table)))
    return tasks.spread(SETS[name][0](spark, sf))


def experiment(name: str, schema: str):
    def add(f):
        QUERIES[name] = lambda spark, sf: spark.createDataFrame([tuple(r) for r in f(spark, sf)], schema)
        return f

    return add


def timed(f):
    began = time.monotonic()
    out = f()
    return out, time.monotonic() - began


def first_at(pairs: list[tuple[float, int]], tolerance: float) -> int | None:
    """The iteration at which a run came to a tolerance first."""
    return next((i for e, i in pairs if e <= tolerance), None)


@experiment("x1_no_algorithm_always_wins", "task string, tolerance double, algorithm string, seconds double, iterations int, status string, fastest boolean")
def x1(spark, sf):
    """Seconds of the three algorithms to one tolerance, over three tasks."""
    for name, make, gradient, tolerance in (("big_charge_svm", W2_SVM.units, "hinge", 0.01), ("halfspace", tasks.halfspace, "hinge", 0.01), ("doc_language", language, "logistic", 1e-4)):
        units = make(spark, sf).persist()
        data = optimizer.collect_stats(units)
        runs = {a: optimizer.run_placed(units, a, gradient, Config(tolerance=tolerance, max_iter=CAP, time_budget=BUDGET_S), data=data) for a in ALGORITHMS}
        best = min(runs, key=lambda a: (runs[a]["status"] != "CONVERGED", runs[a]["seconds"]))
        yield from ((name, tolerance, a, r["seconds"], r["iterations"], r["status"], a == best) for a, r in runs.items())
        units.unpersist()


@experiment("x2_iterations_estimated", "task string, algorithm string, tolerance double, estimated long, actual int, ratio double, same_order boolean, order_kept boolean, tau double")
def x2(spark, sf):
    """Estimates from speculation against runs; one run gives the first iteration at each tolerance. Null: not reached."""
    for name in ("big_charge", "halfspace", "doc_language"):
        make, gradient, beta, _ = SETS[name]
        units = make(spark, sf).persist()
        data = optimizer.collect_stats(units)
        cfg = Config(beta=beta, norm="l2", tolerance=1e-3, max_iter=10 * CAP, time_budget=8)
        found = estimate.speculate(units, gradient, cfg, **estimate.PRESETS["experiment"])
        runs = {a: optimizer.run_placed(units, a, gradient, cfg, data=data)["pairs"] for a in ALGORITHMS}
        for tolerance in (0.1, 0.01, 0.001):
            guess = {a: estimate.estimate_iterations(found[a].pairs, tolerance)[0] for a in ALGORITHMS}
            actual = {a: first_at(runs[a], tolerance) for a in ALGORITHMS}
            known = {a: t for a, t in actual.items() if t}
            kept, tau = metrics.same_ordering(guess, known) if len(known) > 1 else (None, None)
            for a in ALGORITHMS:
                error = metrics.iteration_error(guess[a], actual[a]) if actual[a] else {"ratio": None, "same_order": None}
                yield name, a, tolerance, guess[a], actual[a], error["ratio"], error["same_order"], kept, tau
        units.unpersist()


@experiment("x3_cost_per_iteration", "task string, iterations int, estimated_s double, actual_s double, error double")
def x3(spark, sf):
    """A fixed number of BGD iterations on the cluster against the calibrated cost model."""
    for name, (make, gradient, beta, _) in SETS.items():
        units = make(spark, sf).persist()
        raw, transform = raw_set(spark, sf, name)
        data, env = optimizer.collect_stats(units), cost.calibrate(units, gradient, raw=raw, transform=transform)
        # on the cluster whatever its size: a partition is a little less than what a task reads
        env.partition_bytes = max(1.0, 0.999 * data.bytes / max(1, units.rdd.getNumPartitions()))
        r, seconds = timed(lambda: descent.bgd(units, gradient, Config(beta=beta, tolerance=0.0, max_iter=X3_ITERATIONS), cache=False))  # noqa: B023
        done = r.iterations
        guess = cost.plan_cost(cost.PlanSpec("bgd"), data, 1000, done, env)["iter_cost"]
        yield name, done, guess, seconds / done, metrics.relative_error(guess, seconds / done)
        units.unpersist()


X3_ITERATIONS = 50


@experiment("x4_total_time", "task string, tolerance double, plan string, estimated_s double, actual_s double, iterations_est long, iterations int, status string, error double")
def x4(spark, sf):
    """The chosen plan's total cost, estimated, and its run to the tolerance. Null error: the run didn't come to it."""
    for name, (make, gradient, beta, tolerance) in SETS.items():
        raw, transform = raw_set(spark, sf, name)
        units = make(spark, sf).persist()
        env = cost.calibrate(units, gradient, raw=raw, transform=transform)
        report = optimizer.optimise(units, Request(gradient, tolerance, step=beta), env)
        row = next(r for r in report.rows if r["plan"] == report.chosen.key)
        cfg = Config(beta=beta, tolerance=tolerance, max_iter=10 * CAP, time_budget=BUDGET_S)
        run, seconds = timed(lambda: optimizer.execute(report.chosen, raw, transform, Request(gradient), None, cfg, report.data, env))  # noqa: B023
        error = metrics.relative_error(row["total_cost"], seconds) if run.status == "CONVERGED" else None
        yield name, tolerance, report.chosen.key, row["total_cost"], seconds, row["iters"], run.iterations, run.status, error
        units.unpersist()


def event_rows(spark, sf):
    return tasks.table(spark, sf, "events").withColumn("unit_id", F.col("event_id")), lambda df: tasks.transform_columns(df, "unit_id", W6.label, W6.features)


def plan_runs(spark, sf, name: str, algorithms=None, data=None, keep=None) -> list[dict]:
    """Each plan, or each for which ``keep`` holds, over a set to tolerance 0.001 or 1,000 iterations with batches of 1,000, placed by its size."""
    raw, transform = raw_set(spark, sf, name)
    _, gradient, beta, _ = SETS[name]
    if name == "doc_language":
        # hashing the words is no part of a plan: the raw rows of all of them are made once
        raw = raw.persist()
    try:
        data = data or optimizer.collect_stats(transform(raw))
        cfg = Config(beta=beta, tolerance=1e-3, max_iter=CAP, time_budget=BUDGET_S)
        return optimizer.run_all_plans(raw, transform, Request(gradient, step=beta), 8, cfg, data, algorithms, keep)
    finally:
        raw.unpersist()


def cluster_runs(spark, sf, algorithms, iterations: int = 20, keep=None) -> list[dict]:
    """Each plan over the events on the cluster, laid out in files, long enough to use up a shuffled partition."""
    raw, transform = event_rows(spark, sf)
    return optimizer.run_all_plans(raw, transform, Request("hinge", batch=max(1, raw.count() // 80)), 8, Config(tolerance=0.0, max_iter=iterations), None, algorithms, keep)


@experiment("x5_choice_against_all_plans", "task string, plan string, seconds double, status string, iterations int, chosen boolean, optimise_s double, sample_s double, regret double, rank int, spread double, always_sgd double, always_bgd double, rule_based double")
def x5(spark, sf):
    """All eleven plans run, the optimiser's choice among them, what choosing cost, and the seconds over the best of
    fixed beliefs and of the rules."""
    for name, (make, gradient, beta, _) in SETS.items():
        raw, transform = raw_set(spark, sf, name)
        units = make(spark, sf).persist()
        report = optimizer.optimise(units, Request(gradient, 1e-3, max_iter=CAP, step=beta), cost.calibrate(units, gradient, raw=raw, transform=transform))
        runs = plan_runs(spark, sf, name, data=report.data)
        # a plan that doesn't converge isn't better for having been ended: they rank after those that do
        late = max(r["seconds"] for r in runs)
        judged = [r | {"seconds": r["seconds"] + late * (r["status"] != "CONVERGED")} for r in runs]
        found = optimizer.plan_regret(judged, report.chosen.key, report.seconds)
        rules = optimizer.rule_based_choice(max(1, int(report.data.bytes // cost.Env().partition_bytes)), report.chosen.algorithm, max(r["iters"] for r in report.rows), int(report.data.n))
        others = [optimizer.plan_regret(judged, p)["regret"] for p in (optimizer.fixed_choice("sgd", report.rows)["plan"], optimizer.fixed_choice("bgd", report.rows)["plan"], rules.key)]
        for r in runs:
            yield name, r["plan"], r["seconds"], r["status"], r["iterations"], r["plan"] == report.chosen.key, report.seconds, report.sample_seconds, found["regret"], found["rank"], found["spread"], *others
        units.unpersist()


@experiment("x6_systems", "task string, system string, algorithm string, iterations int, seconds_per_iteration double, conversion_s double, slower_than_ours double, status string")
def x6(spark, sf):
    """Ours against the library, its re-creation on DataFrames and the stand-ins, all on the cluster, for the same number
    of iterations: BGD, MGD of 1,000 and SGD over three sets."""
    for name in ("big_charge", "halfspace", "doc_language"):
        _, gradient, beta, _ = SETS[name]
        units = samplers.with_parts(dealt(spark, sf, name), 8).persist()
        rows, n = max(units.count(), 1), SYSTEM_ITERATIONS
        cfg = Config(beta=beta, tolerance=0.0, max_iter=n)
        # from the cached units: their table isn't read, nor its texts hashed, a second time
        layout = samplers.lay_out(units.drop("part_id"), new_folder(spark, "layout"), 8)
        for algorithm, m in (("bgd", rows), ("mgd", 1000), ("sgd", 1)):
            # one unit wanted: a fraction at which draws are seldom empty
            share = min(1.0, samplers.boosted_fraction(rows) if algorithm == "sgd" else m / rows)
            ours = (lambda: descent.bgd(units, gradient, cfg, cache=False)) if algorithm == "bgd" else (lambda: descent.mgd(None, gradient, cfg, m, "shuffle", layout=layout))  # noqa: B023
            r, base = timed(ours)
            yield name, "ours", algorithm, n, base / n, 0.0, 1.0, r.status
            for system, run in (
                ("library", lambda: (baselines.library_sgd(units, gradient, cfg, share), 0.0)),  # noqa: B023
                ("bernoulli_tree", lambda: (baselines.bernoulli_tree(units, gradient, cfg, share), 0.0)),  # noqa: B023
                ("matrix_blocks_standin", lambda: baselines.matrix_blocks_standin(units, gradient, cfg, fraction=share)),  # noqa: B023
                ("fused_standin", lambda: (baselines.fused_standin(units, gradient, cfg, fraction=share), 0.0)),  # noqa: B023
            ):
                (r, conversion), s = timed(run)
                yield name, system, algorithm, n, (s - conversion) / n, conversion, (s - conversion) / base, r.status
        units.unpersist()


@experiment("x7_scale_points", "system string, copies int, units long, seconds_per_iteration double, layout_s double, slope double")
def x7(spark, sf):
    """SGD over 1, 4, 16 and 64 copies of the events: two of our plans over laid-out files and the library."""
    raw, transform = event_rows(spark, sf)
    n, iterations, found, wrote = raw.count(), 10, {}, {}
    cfg = Config(tolerance=0.0, max_iter=iterations)
    for k in (1, 4, 16, 64):
        # each row k times by a generator, so that no join is needed
        many = tasks.spread(raw).withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(k - 1)))).withColumn("unit_id", F.col("unit_id") * k + F.col("copy"))
        for plan in (optimizer.PlanSpec("sgd", "eager", "random"), optimizer.PlanSpec("sgd", "lazy", "shuffle")):
            layout, wrote[plan.key, k] = timed(lambda: optimizer.prepare(plan, many, transform, 8))  # noqa: B023
            found[plan.key, k] = timed(lambda: optimizer.execute(plan, many, transform, Request("hinge"), 8, cfg, layout=layout))[1]  # noqa: B023
        units = transform(many).persist()
        units.count()
        found["library", k] = timed(lambda: baselines.library_sgd(units, "hinge", cfg, samplers.boosted_fraction(n * k)))[1]  # noqa: B023
        units.unpersist()
    for (system, k), seconds in found.items():
        yield system, k, n * k, seconds / iterations, wrote.get((system, k), 0.0), metrics.scaling_slope([(n * c, s) for (x, c), s in found.items() if x == system])


@experiment("x8_scale_features", "system string, dim int, seconds_per_iteration double, slope double")
def x8(spark, sf):
    """Sparse texts as their dimension grows: batch descent with partial sums, the library (BGD and SGD) over sparse
    vectors, and SGD over the sparse units of a shuffled partition."""
    # words are hashed once for all dimensions
    found, hashes = {}, tasks.doc_hashes(spark, sf).persist()
    for dim in (1024, 4096, 16384, 65536, 262144):
        sparse = tasks.doc_language(spark, sf, dim, hashes).persist()
        n = sparse.count()
        cfg = Config(tolerance=0.0, max_iter=3)
        r, _ = timed(lambda: descent.bgd_sparse(sparse, "logistic", cfg, dim))  # noqa: B023
        # the first iteration compiles
        found["ours_bgd", dim] = float(np.mean([t["millis"] for t in r.trace[1:]])) / 1e3
        found["ours_sgd_shuffle", dim] = timed(lambda: descent.sgd_sparse(sparse, "logistic", descent.with_tolerance(cfg, max_iter=10), dim))[1] / 10  # noqa: B023
        found["library_bgd", dim] = timed(lambda: baselines.library_sparse(sparse, cfg, dim))[1] / 3  # noqa: B023
        found["library_sgd", dim] = timed(lambda: baselines.library_sparse(sparse, cfg, dim, samplers.boosted_fraction(n)))[1] / 3  # noqa: B023
        sparse.unpersist()
    hashes.unpersist()
    for (system, dim), s in found.items():
        yield system, dim, s, metrics.scaling_slope([(d, t) for (x, d), t in found.items() if x == system])


@experiment("x9_abstraction", "task string, algorithm string, ours_s double, handcoded_s double, overhead double, fused_s double, fused_status string")
def x9(spark, sf):
    """Our operators against a straight loop of the same plan and against the fused stand-in: SGD, MGD of 1,000 and of
    10,000 and BGD over three sets. The stand-in's capacity is a fixed 64 MB for what one task gets."""
    n = 10
    cfg = Config(tolerance=0.0, max_iter=n)
    for name in ("big_charge", "halfspace", "doc_language"):
        gradient = SETS[name][1]
        units = dealt(spark, sf, name).persist()
        rows = units.count()
        for algorithm, m in (("sgd", 1), ("mgd_1000", 1000), ("mgd_10000", 10_000), ("bgd", rows)):
            share = min(1.0, samplers.boosted_fraction(rows) if m == 1 else m / rows)
            ours = (lambda k: descent.bgd(units, gradient, descent.with_tolerance(cfg, max_iter=k), cache=False)) if share >= 1 else (lambda k: descent.mgd(units, gradient, descent.with_tolerance(cfg, max_iter=k), fraction=share))  # noqa: B023
            straight = lambda k: baselines.handcoded_bgd(units, gradient, k, fraction=share)  # noqa: B023, E731
            # each once before it is timed, all over the units that are read once
            ours(1)
            s = timed(lambda: ours(n))[1]  # noqa: B023
            straight(1)
            h = timed(lambda: straight(n))[1]  # noqa: B023
            fused, f = timed(lambda: baselines.fused_standin(units, gradient, cfg, 64 << 20, share))  # noqa: B023
            yield name, algorithm, s, h, s / h, f, fused.status
        units.unpersist()


@experiment("x10_testing_error", "task string, system string, algorithm string, mse_pm1 double, error_rate double, distance_to_ours double")
def x10(spark, sf):
    """Errors on the held-out fifth by system over an even and a skewed layout (partitions that follow the label), where
    shuffled partitions see one class at a time; batch descent gives one model everywhere."""
    for name, by_label in (("event_heavy", False), ("event_heavy_by_label", True)):
        train, test = metrics.split_80_20(W6.units(spark, sf))
        parts = F.pmod("unit_id", F.lit(4)).cast("int") + F.when(F.col("label") > 0, 4).otherwise(0)
        train = (train.withColumn("part_id", parts) if by_label else samplers.with_parts(train, 8)).persist()
        test = test.persist()
        share = min(1.0, 100 / train.count())
        cfg = Config(tolerance=0.0, max_iter=20)
        ours = None
        for system, algorithm, run in (
            ("ours", "bgd", lambda: descent.bgd(train, "hinge", cfg, cache=False)),  # noqa: B023
            ("library", "bgd", lambda: baselines.library_sgd(train, "hinge", cfg)),  # noqa: B023
            ("matrix_blocks_standin", "bgd", lambda: baselines.matrix_blocks_standin(train, "hinge", cfg)[0]),  # noqa: B023
            ("ours", "mgd", lambda: descent.mgd(train, "hinge", cfg, 100, "shuffle")),  # noqa: B023
            ("ours_mixed", "mgd", lambda: descent.mgd(train, "hinge", cfg, 100, "shuffle", mix=8)),  # noqa: B023
            ("library", "mgd", lambda: baselines.library_sgd(train, "hinge", cfg, share)),  # noqa: B023
            ("matrix_blocks_standin", "mgd", lambda: baselines.matrix_blocks_standin(train, "hinge", cfg, fraction=share)[0]),  # noqa: B023
            ("ours", "sgd", lambda: descent.sgd(train, "hinge", cfg, "shuffle")),  # noqa: B023
            ("ours_mixed", "sgd", lambda: descent.sgd(train, "hinge", cfg, "shuffle", mix=8)),  # noqa: B023
            ("library", "sgd", lambda: baselines.library_sgd(train, "hinge", cfg, share / 10)),  # noqa: B023
        ):
            w = run().weights
            ours = w if system == "ours" else ours
            e = metrics.testing_error(optimizer.predictions(test, w, "hinge")).first()
            yield name, system, algorithm, e.mse_pm1, e.error_rate, float(np.abs(w - ours).max())
        train.unpersist()
        test.unpersist()


def _effects(name: str, algorithms: tuple, keep=None) -> None:
    @experiment(name, "task string, plan string, algorithm string, transform string, sampler string, place string, seconds double, layout_s double, iterations int, status string, units long, partitions long, bytes long")
    def _(spark, sf):
        """W1 to W4 to tolerance 0.001 or 1,000 iterations, placed by size; and the events on the cluster, from files."""
        for task, runs in [*((t, lambda t=t: plan_runs(spark, sf, t, algorithms, keep=keep)) for t in SETS), ("events_in_files", lambda: cluster_runs(spark, sf, algorithms, keep=keep))]:
            for r in runs():
                yield task, r["plan"], r["algorithm"], r["transform"], r["sampler"], r["place"], r["seconds"], r["layout_s"], r["iterations"], r["status"], r["units"], r["partitions"], r["bytes"]


_effects("x11_samplers_mgd", ("mgd",))
_effects("x12_transform_shuffle", ("mgd", "sgd"), lambda p: p.sampler == "shuffle")
_effects("x13_samplers_sgd", ("sgd",))
_effects("x14_transform_random", ("mgd", "sgd"), lambda p: p.sampler == "random")


@experiment("x15_curve_fits", "task string, step string, actual int, pairs int, inverse long, step_aware long, power long, rmse double, error double, status string")
def x15(spark, sf):
    """Predicted and needed iterations by step rule, and the fitted curve's residual over speculation's pairs. The whole of
    a set is run to 0.001, on the driver where it fits a partition, else on the cluster. Null error: it didn't come to it."""
    for name, (make, gradient, _, _) in SETS.items():
        units = make(spark, sf).persist()
        large = optimizer.collect_stats(units).bytes > cost.Env().partition_bytes
        for r in estimate.curve_study(units, gradient, 1e-3, budget_s=BUDGET_S, cluster=large):
            error = metrics.relative_error(r["inverse"], r["actual"]) if r["status"] == "CONVERGED" else None
            yield name, r["step"], r["actual"], r["pairs"], r["inverse"], r["step_aware"], r["power"], r["rmse"], error, r["status"]
        units.unpersist()


@experiment("x16_chosen_plans", "task string, algorithm string, plan string, iterations_est long, total_cost double, chosen boolean")
def x16(spark, sf):
    """The cheapest plan of each algorithm over each set."""
    for name, (make, gradient, beta, tolerance) in SETS.items():
        units = make(spark, sf).persist()
        report = optimizer.optimise(units, Request(gradient, tolerance, step=beta), cost.calibrate(units, gradient))
        for a in ALGORITHMS:
            best = min((r for r in report.rows if r["algorithm"] == a), key=lambda r: r["total_cost"])
            yield name, a, best["plan"], best["iters"], best["total_cost"], best["plan"] == report.chosen.key
        units.unpersist()


@experiment("x17_choice_with_given_iterations", "plans int, seconds double, under_100_ms boolean")
def x17(spark, sf):
    data = cost.Data(1e8, 1.6e11, 100)
    report, s = timed(lambda: optimizer.optimise(None, Request(max_iter=1000, fixed_iterations=True), cost.Env(), data))
    yield len(report.rows), s, s < 0.1


@experiment("x18_aggregations", "how string, seconds double, distance double")
def x18(spark, sf):
    units, first = tasks.halfspace(spark, sf).persist(), None
    units.count()
    for how in ("partials", "tree", "keyed", "sql"):
        r, s = timed(lambda: descent.bgd(units, "hinge", Config(tolerance=0.0, max_iter=5, aggregation=how), cache=False))  # noqa: B023
        first = r.weights if first is None else first
        yield how, s, float(np.abs(r.weights - first).max())
    units.unpersist()


@experiment("x19_variants", "variant string, iterations int, objective double")
def x19(spark, sf):
    """Objectives that variance reduction, line search and secant steps come to in as many iterations as BGD and SGD."""
    units, n = samplers.with_parts(W6.units(spark, sf), 8).persist(), 12
    cfg = Config(tolerance=0.0, max_iter=n)
    for name, run in (
        ("bgd", lambda: descent.bgd(units, "logistic", cfg, cache=False)),
        ("sgd", lambda: descent.sgd(units, "logistic", cfg, "shuffle")),
        ("svrg", lambda: descent.svrg(units, "logistic", cfg, 4)),
        ("line_search", lambda: descent.bgd_line_search(units, "logistic", descent.with_tolerance(cfg, beta=8.0))),
        ("secant", lambda: descent.bgd_bb(units, "logistic", cfg)),
    ):
        w = run().weights
        yield name, n, descent.objective(units, w, "logistic")
    units.unpersist()


# --- around the samplers and runs ------------------------------------------------------------------------------------


@experiment("speculation_per_sampler", "plan string, pairs int, iterations long, stopped_by string")
def _speculation(spark, sf):
    found = estimate.speculate_samplers(W6.units(spark, sf), "hinge", Config(), **estimate.PRESETS["experiment"])
    return [(k, len(s.pairs), estimate.estimate_iterations(s.pairs, 0.01, CAP)[0], s.stopped_by) for k, s in found.items()]


@experiment("mixed_partitions_on_skew", "mix int, objective double")
def _skew(spark, sf):
    """A layout that follows the label: batches of one partition see one class, mixed ones see both."""
    raw = W6.units(spark, sf)
    units = raw.withColumn("part_id", F.pmod("unit_id", F.lit(2)).cast("int") + F.when(F.col("label") > 0, 2).otherwise(0)).persist()
    for mix in (1, 4):
        r = descent.mgd(units, "logistic", Config(tolerance=0.0, max_iter=8), 20, "shuffle", mix=mix)
        yield mix, descent.objective(units, r.weights, "logistic")
    units.unpersist()
