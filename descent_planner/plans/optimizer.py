"""Chooses the plan of least estimated total cost, checks constraints, and runs it."""

from __future__ import annotations

import math
import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.descent import ALGORITHMS, Config, FitResult, arrays, bgd, dimension, local, mgd, on_driver
from ..operators.samplers import Layout, lay_out, with_parts
from ..sources.folders import new_folder
from .cost import Data, Env, place_operators, plan_cost
from .estimate import PRESETS, estimate_iterations, run_local, speculate, speculate_registered, speculate_samplers
from .space import SAMPLED, PlanSpec, enumerate_plans


@dataclass
class Request:
    """What is asked for: tolerance, constraints and hints that narrow the space."""

    gradient: str = "linear"
    epsilon: float = 1e-3
    max_iter: int | None = None
    time_s: float | None = None
    algorithm: str | None = None
    sampler: str | None = None
    transform: str | None = None
    step: float = 1.0
    step_rule: str = "inv_sqrt"
    norm: str = "l1"
    batch: int = 1000
    fixed_iterations: bool = False
    mode: str = "corrected"
    preset: str = "experiment"
    epsilon_given: bool = False
    per_sampler: bool = False
    #: Whether Transform may move below Sample (see ``space.commutes``); without, no lazy plan is made.
    commute: bool = True


@dataclass
class Report:
    rows: list[dict]
    chosen: PlanSpec
    seconds: float
    sample_seconds: float
    data: Data
    speculation: dict = field(default_factory=dict)

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(r["plan"], r["algorithm"], r["transform"], r["sampler"], r["iters"], r["prep_cost"], r["iter_cost"], r["total_cost"], r["plan"] == self.chosen.key, not r["violated"], ",".join(r["violated"])) for r in self.rows]
        return spark.createDataFrame(rows, "plan string, algorithm string, transform string, sampler string, iters_est long, prep_cost double, iter_cost double, total_cost double, chosen boolean, feasible boolean, violated string")


def collect_stats(units: DataFrame) -> Data:
    """Size by one aggregate; ``nnz`` is the mean number of features that aren't zero, by which the model scales a unit's
    work where units are sparse."""
    d = dimension(units)
    row = units.agg(F.count("*"), F.avg(F.size(F.filter("features", lambda x: x != 0)))).first()
    return Data(row[0], row[0] * (8.0 * d + 16), d, float(row[1]) if row[1] is not None and row[1] < 0.5 * d else None)


def check_constraints(row: dict, req: Request, iters_needed: int) -> list[str]:
    """Names of the constraints that a plan can't meet."""
    out = []
    if req.time_s is not None and row["total_cost"] > req.time_s:
        out.append("TIME")
    if req.max_iter is not None and not req.fixed_iterations and iters_needed > req.max_iter and req.epsilon_given:
        out += ["EPSILON", "MAX_ITER"]
    return out


def choose(req: Request, data: Data, env: Env, iterations: dict[str, int]) -> tuple[PlanSpec, list[dict]]:
    """Costs every plan the hints allow; feasible plans first, then least total, then the fixed order."""
    plans = [p for p in enumerate_plans(commute=req.commute) if (req.algorithm in (None, p.algorithm)) and (req.sampler in (None, p.sampler)) and (req.transform in (None, p.transform))]
    if not plans:
        raise ValueError(f"no plan has algorithm={req.algorithm}, sampler={req.sampler}, transform={req.transform}")
    rows = []
    for p in plans:
        # an algorithm without an estimate is taken to need what its like does
        need = iterations.get(f"{p.algorithm}-{p.sampler}") or iterations.get(p.algorithm) or iterations.get("mgd" if SAMPLED[p.algorithm] else "bgd") or req.max_iter or 1000
        t = min(need, req.max_iter) if req.max_iter else need
        row = plan_cost(p, data, req.batch, t, env, req.mode)
        row["violated"] = check_constraints(row, req, need)
        rows.append(row)
    best = min(range(len(plans)), key=lambda k: (bool(rows[k]["violated"]), rows[k]["total_cost"], k))
    return plans[best], rows


def optimise(units: DataFrame, req: Request, env: Env | None = None, data: Data | None = None) -> Report:
    """Speculates unless iterations are given, then chooses."""
    began = time.monotonic()
    env = env or Env()
    data = data or collect_stats(units)
    sampled, found = 0.0, {}
    if req.fixed_iterations and req.max_iter:
        iterations = dict.fromkeys(ALGORITHMS, req.max_iter)
    else:
        t = time.monotonic()
        cfg = Config(step=req.step_rule, beta=req.step, norm=req.norm)
        found = (speculate_samplers if req.per_sampler else speculate)(units, req.gradient, cfg, batch=req.batch, **PRESETS[req.preset])
        found |= {a: speculate_registered(units, a, req.gradient, cfg, **PRESETS[req.preset]) for a in ALGORITHMS if a not in ("bgd", "mgd", "sgd") and req.algorithm in (None, a)}
        sampled = time.monotonic() - t
        iterations = {a: estimate_iterations(s.pairs, req.epsilon, None)[0] for a, s in found.items()}
    chosen, rows = choose(req, data, env, iterations)
    return Report(rows, chosen, time.monotonic() - began, sampled, data, found)


def rule_based_choice(n_partitions: int, algorithm: str, t: int, n: int) -> PlanSpec:
    """The patterns seen in experiments: one partition wants Bernoulli; few iterations of SGD want laziness; else shuffle eagerly."""
    if algorithm == "bgd":
        return PlanSpec("bgd")
    if n_partitions <= 1:
        return PlanSpec(algorithm, "eager", "bernoulli")
    if algorithm == "sgd" and t < n / 10:
        return PlanSpec("sgd", "lazy", "shuffle")
    return PlanSpec(algorithm, "eager", "shuffle")


def fixed_choice(algorithm: str, rows: list[dict]) -> dict:
    """Always one algorithm, by its cheapest plan: what a belief in it would run."""
    return min((r for r in rows if r["algorithm"] == algorithm), key=lambda r: r["total_cost"])


def prepare(plan: PlanSpec, raw: DataFrame, transform, parts: int, folder: str | None = None) -> Layout:
    """The layout of a plan with a partition sampler: of units (eager) or of raw rows (lazy), written once."""
    return lay_out(raw if plan.transform == "lazy" else transform(raw), folder or new_folder(raw.sparkSession, "layout"), parts)


def belongs_on_driver(plan: PlanSpec, data: Data | None, batch: int, env: Env) -> bool:
    """Whether a built-in plan's data, where they are known, fit one partition."""
    built_in = plan.algorithm in ("bgd", "mgd", "sgd") and plan.sampler in ("none", "bernoulli", "random", "shuffle")
    return bool(built_in and data and place_operators(data, batch, env, SAMPLED[plan.algorithm])["transform"] == "driver")


def execute(plan: PlanSpec, raw: DataFrame, transform, req: Request, parts: int | None = None, cfg: Config | None = None, data: Data | None = None, env: Env | None = None, layout: Layout | None = None, held: tuple | None = None) -> FitResult:
    """Runs a plan over raw rows (with unit_id) and their Transform.

    With ``data`` known, operators are placed: units that fit one partition are collected once (``held`` are their arrays,
    where they are there already), and the plan runs on the driver with the draws of the cluster's samplers. Else,
    partition samplers read a layout in files: ``layout``, or one that is written first, of ``parts`` partitions (by bytes
    where that is None and data are known).
    """
    cfg = cfg or Config(step=req.step_rule, beta=req.step, tolerance=req.epsilon, max_iter=req.max_iter or 1000, norm=req.norm, time_budget=req.time_s)
    env = env or Env()
    built_in = plan.algorithm in ("bgd", "mgd", "sgd")
    batch = 1 if plan.algorithm == "sgd" else req.batch
    if parts is None:
        parts = max(1, math.ceil(data.bytes / env.partition_bytes)) if data else 8
    if belongs_on_driver(plan, data, batch, env):
        began = time.monotonic()
        fit = on_driver(*(held or arrays(transform(raw))), req.gradient, cfg, plan.algorithm, batch, plan.sampler, parts)
        fit.seconds = time.monotonic() - began
        fit.touched |= {"bytes": int(data.bytes), "place": "driver"}
        return fit
    if plan.algorithm == "bgd":
        return bgd(transform(raw), req.gradient, cfg)
    if not SAMPLED[plan.algorithm]:
        return ALGORITHMS[plan.algorithm](with_parts(transform(raw), parts), req.gradient, cfg)
    run = mgd if built_in else ALGORITHMS[plan.algorithm]
    lazily = {"transform": transform} if plan.transform == "lazy" else {}
    if plan.sampler in ("random", "shuffle"):
        layout = layout or prepare(plan, raw, transform, parts)
        return run(layout.rows, req.gradient, cfg, batch, plan.sampler, layout=layout, **lazily)
    if lazily:
        return run(with_parts(raw, parts), req.gradient, cfg, batch, plan.sampler, **lazily)
    units = with_parts(transform(raw), parts).persist()
    try:
        return run(units, req.gradient, cfg, batch, plan.sampler)
    finally:
        units.unpersist()


def run_placed(units: DataFrame, algorithm: str, gradient: str, cfg: Config, batch: int = 1000, data: Data | None = None, env: Env | None = None, parts: int = 8) -> dict:
    """Runs an algorithm where its data belong: on the driver when they fit one partition, else on the cluster.

    Gives the errors (delta, iteration), iterations, status, seconds and the place.
    """
    data, env, began = data or collect_stats(units), env or Env(), time.monotonic()
    if place_operators(data, batch, env, algorithm != "bgd")["transform"] == "driver":
        s = run_local(algorithm, *local(units), gradient, cfg, cfg.tolerance, cfg.time_budget or 60.0, batch, max_iter=cfg.max_iter)
        return {"pairs": s.pairs, "iterations": s.iterations, "status": {"tolerance": "CONVERGED", "cap": "MAX_ITER", "budget": "TIME"}.get(s.stopped_by, "DIVERGED"), "seconds": time.monotonic() - began, "place": "driver"}
    r = bgd(units, gradient, cfg) if algorithm == "bgd" else mgd(with_parts(units, parts), gradient, cfg, 1 if algorithm == "sgd" else batch, "shuffle")
    return {"pairs": [(t["delta"], t["iter"]) for t in r.trace if t["delta"]], "iterations": r.iterations, "status": r.status, "seconds": time.monotonic() - began, "place": "cluster"}


def run_all_plans(raw: DataFrame, transform, req: Request, parts: int | None = 8, cfg: Config | None = None, data: Data | None = None, algorithms=None, keep=None) -> list[dict]:
    """Every plan run, or those for which ``keep`` holds, for the best and the worst of them. Plans of one transformation
    share a layout, whose seconds are given apart: it is written once, whatever runs over it. Plans on the driver share
    the units that are read once. Where ``data`` are known, the seconds of what is shared count in each plan."""
    out, layouts, wrote, held, read = [], {}, {}, None, 0.0
    for p in enumerate_plans(algorithms, commute=req.commute):
        if keep and not keep(p):
            continue
        layout, here = None, belongs_on_driver(p, data, 1 if p.algorithm == "sgd" else req.batch, Env())
        if here and held is None:
            t = time.monotonic()
            held = arrays(transform(raw))
            read = time.monotonic() - t
        if p.sampler in ("random", "shuffle") and not here:
            if p.transform not in layouts:
                t = time.monotonic()
                layouts[p.transform] = prepare(p, raw, transform, parts or 8)
                wrote[p.transform] = time.monotonic() - t
            layout = layouts[p.transform]
        t = time.monotonic()
        r = execute(p, raw, transform, req, parts, cfg, data, layout=layout, held=held if here else None)
        # where data are known and so plans placed, what a plan reads or lays out counts in its seconds
        seconds = time.monotonic() - t + (read if here else wrote[p.transform] if layout and data else 0.0)
        out.append({"plan": p.key, "algorithm": p.algorithm, "transform": p.transform, "sampler": p.sampler, "seconds": seconds, "layout_s": wrote[p.transform] if layout and not data else 0.0, "iterations": r.iterations, "status": r.status, "place": r.touched.get("place", "cluster"), "units": r.touched.get("units", 0), "partitions": r.touched.get("partitions", 0), "bytes": r.touched.get("bytes", 0)})
    return out


def plan_regret(runs: list[dict], chosen: str, overhead: float = 0.0) -> dict:
    seconds = {r["plan"]: r["seconds"] for r in runs}
    best = min(seconds.values())
    return {"regret": (seconds[chosen] + overhead) / best, "rank": 1 + sum(s < seconds[chosen] for s in seconds.values()), "spread": max(seconds.values()) / best}


def placements(data: Data, m: int, env: Env) -> dict:
    return {True: place_operators(data, m, env, True), False: place_operators(data, m, env, False)}


def predictions(units: DataFrame, w: np.ndarray, gradient: str) -> DataFrame:
    """(unit_id, label, z, prediction): the margin itself for regression, else its sign."""
    from ..operators.descent import margin

    z = margin(np.asarray(w, dtype=float))
    return units.select("unit_id", "label", z.alias("z")).withColumn("prediction", F.col("z") if gradient == "linear" else F.when(F.col("z") >= 0, 1.0).otherwise(-1.0))
