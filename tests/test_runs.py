import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from descent_planner import experiments, queries, relational
from descent_planner.operators import descent, samplers
from descent_planner.operators.descent import Config, RunLog
from descent_planner.plans import estimate, optimizer
from descent_planner.sources import tasks
from descent_planner.sources.tasks import TABLES, W6


@pytest.mark.parametrize("name", ["sample_mixed_partition_slices", "stream_late_data", "stream_stream_interval_join"])
def test_equals_oracle(spark, name):
    # the batches need the larger table
    sf = "/root/testdata/sf0.01"
    df = (queries.QUERIES | relational.QUERIES)[name](spark, sf)
    cols = sorted(df.columns)
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as from '{sf}/{t}.parquet'")
    want = con.sql(f"select {','.join(cols)} from ({(queries.ORACLES | relational.ORACLES)[name]})").fetchall()
    got = [tuple(r) for r in df.select(*cols).collect()]
    assert want and sorted(got) == sorted(want)


@pytest.mark.parametrize("sampler", ["bernoulli", "random", "shuffle"])
def test_broken_run_goes_on(spark, sf, tmp_path, sampler):
    """Weights of a run taken up equal those of one that wasn't broken off."""
    units = samplers.with_parts(W6.units(spark, sf), 4).persist()
    run = lambda n, log=None: descent.mgd(units, "hinge", Config(tolerance=0.0, max_iter=n), 100, sampler, log=log)
    log = RunLog(spark, f"file://{tmp_path}/run", every=2)
    run(5, log)
    again = run(8, log)
    assert [t["iter"] for t in again.trace] == [5, 6, 7, 8]
    assert np.array_equal(again.weights, run(8).weights)
    units.unpersist()


def test_files_of_a_catalogue(spark, sf, tmp_path):
    path = f"file://{tmp_path}/files"
    catalog = samplers.layout_files(W6.units(spark, sf), path, 4).persist()
    assert {r.part_id for r in catalog.collect()} == {0, 1, 2, 3}
    sizes = {r.part_id: r.n_units for r in catalog.groupBy("part_id").sum("n_units").withColumnRenamed("sum(n_units)", "n_units").collect()}
    units = samplers.with_parts(W6.units(spark, sf), 4)
    a = samplers.ShuffledPartition(sizes, 50, read=samplers.catalog_reader(path, catalog))
    b = samplers.ShuffledPartition(sizes, 50)
    for _ in range(7):
        assert [(p, r.unit_id) for p, r in a.draw_rows(units)] == [(p, r.unit_id) for p, r in b.draw_rows(units)]


def test_wide_vectors_are_one_constant(spark):
    w = np.random.default_rng(1).normal(size=20_000)
    assert spark.range(1).select(descent.vector(w)).first()[0] == w.tolist()


def test_per_sampler_speculation_and_choice(spark, sf):
    found = estimate.speculate_samplers(W6.units(spark, sf), "hinge", Config(), eps_s=0.1, budget_s=5)
    assert set(found) == {"bgd", *(f"{a}-{s}" for a in ("mgd", "sgd") for s in ("bernoulli", "random", "shuffle"))}
    its = {k: 10 for k in found} | {"sgd-shuffle": 2}
    _, rows = optimizer.choose(optimizer.Request(), optimizer.Data(1e6, 1e9, 10), optimizer.Env(), its)
    assert {r["plan"]: r["iters"] for r in rows}["sgd-lazy-shuffle"] == 2


def test_placed_runs(spark, sf):
    r = optimizer.run_placed(W6.units(spark, sf), "bgd", "hinge", Config(tolerance=0.0, max_iter=4))
    assert (r["place"], r["iterations"]) == ("driver", 4)
    far = optimizer.run_placed(W6.units(spark, sf), "bgd", "hinge", Config(tolerance=0.0, max_iter=4), env=optimizer.Env(partition_bytes=1))
    assert far["place"] == "cluster"
    assert np.allclose([e for e, _ in r["pairs"]], [e for e, _ in far["pairs"]])


def test_experiments_that_dont_depend_on_the_clock(spark, sf):
    agg = experiments.QUERIES["x18_aggregations"](spark, sf).collect()
    assert all(r.distance < 1e-9 for r in agg)
    assert len(experiments.QUERIES) == 21
    assert tasks.TASKS


def test_curve_study_runs_the_whole_set_on_the_cluster(spark, sf):
    from descent_planner.plans import estimate
    from descent_planner.sources.tasks import W2

    units = W2.units(spark, sf)
    here, there = (estimate.curve_study(units, "logistic", 0.1, steps=("inv",), budget_s=20, cluster=c) for c in (False, True))
    assert here == there and here[0]["status"] == "CONVERGED" and here[0]["actual"] > 0


@pytest.mark.parametrize("plan", [p.key for p in optimizer.enumerate_plans()])
def test_a_plan_on_the_driver_is_the_plan_on_the_cluster(spark, sf, plan):
    """Placement changes where a plan runs, not what it draws."""
    raw = tasks.table(spark, sf, "events").selectExpr("*", "event_id AS unit_id")
    transform = lambda df: tasks.transform_columns(df, "unit_id", W6.label, W6.features)
    spec = next(p for p in optimizer.enumerate_plans() if p.key == plan)
    req, cfg = optimizer.Request("hinge", batch=60), Config(tolerance=0.0, max_iter=4)
    here = optimizer.execute(spec, raw, transform, req, 4, cfg, data=optimizer.collect_stats(transform(raw)))
    there = optimizer.execute(spec, raw, transform, req, 4, cfg)
    assert here.touched["place"] == "driver" and "place" not in there.touched
    assert np.allclose(here.weights, there.weights, atol=1e-12)


def test_partition_samplers_open_the_files_of_their_partitions(spark, sf, tmp_path):
    units = W6.units(spark, sf)
    layout = samplers.lay_out(units, f"file://{tmp_path}/l", 8)
    one = layout.read([3])
    assert {r.part_id for r in one.select("part_id").distinct().collect()} == {3} and len(one.inputFiles()) == 1
    r = descent.mgd(None, "hinge", Config(tolerance=0.0, max_iter=3), 30, "shuffle", layout=layout)
    assert r.touched["partitions"] == 1 and r.touched["bytes"] in layout.bytes.values()
    r = descent.mgd(None, "hinge", Config(tolerance=0.0, max_iter=5), 1, "random", layout=layout)
    assert r.touched["partitions"] == 5 and r.touched["bytes"] < sum(layout.bytes.values())
    r = descent.mgd(None, "hinge", Config(tolerance=0.0, max_iter=2), 30, "bernoulli", layout=layout)
    assert r.touched["bytes"] == 2 * sum(layout.bytes.values())


def test_slices_of_a_partition_give_the_same_batches(spark, sf):
    units = samplers.with_parts(W6.units(spark, sf), 4).persist()
    sizes = {r.part_id: r.n_units for r in samplers.partition_catalog(units).collect()}
    whole, sliced = samplers.ShuffledPartition(sizes, 60), samplers.ShuffledPartition(sizes, 60, slice_units=80, prefetch=True)
    for _ in range(11):
        assert [r.unit_id for _, r in whole.draw_rows(units)] == [r.unit_id for _, r in sliced.draw_rows(units)]
        assert len(sliced.held) < 80 + 60 + 60
    again = samplers.ShuffledPartition(sizes, 60, slice_units=80)
    again.seek(units, sliced.cursor(), 11)
    sliced.close()
    assert [r.unit_id for _, r in again.draw_rows(units)] == [r.unit_id for _, r in whole.draw_rows(units)]
    units.unpersist()


def test_users_samplers_and_algorithms_are_planned(spark, sf):
    class FirstOnes:
        def __init__(self, sizes, batch, seed):
            self.batch = batch

        def draw(self, units, i):
            return units.orderBy("unit_id").limit(self.batch)

    samplers.register_sampler("first_ones", FirstOnes, cost=lambda data, m, env: 1e-9)
    descent.register_algorithm("svrg", lambda units, gradient, cfg: descent.svrg(units, gradient, cfg, 5), scans=0.2)
    try:
        plans = [p.key for p in optimizer.enumerate_plans()]
        assert len(plans) == 16 and "svrg" in plans and "mgd-lazy-first_ones" in plans
        units = samplers.with_parts(W6.units(spark, sf), 4)
        report = optimizer.optimise(units, optimizer.Request("logistic", 0.05, sampler="none"))
        assert {r["plan"] for r in report.rows} == {"bgd", "svrg"} and report.speculation["svrg"].pairs
        req = optimizer.Request("hinge", batch=50, sampler="first_ones", max_iter=3, fixed_iterations=True)
        report = optimizer.optimise(units, req)
        assert len(report.rows) == 4 and "first_ones" in report.chosen.key
        fit = optimizer.execute(report.chosen, units, lambda df: df, req, cfg=Config(tolerance=0.0, max_iter=3))
        assert all(t["n_used"] in (1, 50) for t in fit.trace) and fit.iterations == 3
        w = optimizer.execute(next(p for p in optimizer.enumerate_plans() if p.key == "svrg"), W6.units(spark, sf), lambda df: df, optimizer.Request("logistic"), 4, Config(tolerance=0.0, max_iter=3)).weights
        assert np.isfinite(w).all()
    finally:
        samplers.unregister_sampler("first_ones")
        descent.unregister_algorithm("svrg")
    assert len(optimizer.enumerate_plans()) == 11
    assert len(optimizer.enumerate_plans(commute=False)) == 7


def test_equal_lines_are_units_of_their_own(spark, tmp_path):
    (tmp_path / "a.csv").write_text("1,2\n1,2\n3,4\n")
    (tmp_path / "b.libsvm").write_text("1 1:2\n1 1:2\n")
    for units, n in ((tasks.read_csv_units(spark, str(tmp_path / "a.csv")), 3), (tasks.read_libsvm_units(spark, str(tmp_path / "b.libsvm")), 2)):
        assert units.select("unit_id").distinct().count() == n
    for task in ("big_charge", "return_flag"):
        ids = tasks.TASKS[task].units(spark, "/root/testdata/sf0.01").select("unit_id")
        assert ids.distinct().count() == ids.count()


def test_the_variants_keep_the_regulariser(spark, sf):
    units = samplers.with_parts(W6.units(spark, sf), 4).persist()
    for run in (lambda c: descent.svrg(units, "logistic", c, 1), lambda c: descent.bgd_line_search(units, "logistic", c), lambda c: descent.bgd_bb(units, "logistic", c)):
        plain, bound = run(Config(tolerance=0.0, max_iter=4)), run(Config(tolerance=0.0, max_iter=4, reg="l2", lam=1.0))
        assert np.abs(bound.weights).sum() < np.abs(plain.weights).sum()
    want = descent.bgd(units, "logistic", Config(tolerance=0.0, max_iter=4, reg="l1", lam=0.1)).weights
    assert np.allclose(descent.svrg(units, "logistic", Config(tolerance=0.0, max_iter=4, reg="l1", lam=0.1), 1).weights, want)


def test_fused_standin_without_a_capacity_takes_every_unit(spark, sf, monkeypatch):
    """sets beyond a gibibyte came back as zero weights."""
    from descent_planner.operators import baselines

    units, cfg = W6.units(spark, sf), Config(tolerance=0.0, max_iter=3)
    want = descent.bgd(units, "logistic", cfg).weights
    monkeypatch.setattr(type(units), "count", lambda self: 1 << 40)
    got = baselines.fused_standin(units, "logistic", cfg)
    assert got.status == "MAX_ITER" and np.allclose(got.weights, want, atol=1e-12)
    assert baselines.fused_standin(units, "logistic", cfg, 64 << 20).status == "FAILED_CAPACITY"


@pytest.mark.parametrize("prefetch", [False, True])
def test_slices_of_mixed_partitions_give_the_same_batches(spark, sf, prefetch):
    """F2 to F4: what was mixed came to the driver whole."""
    units = samplers.with_parts(W6.units(spark, sf), 4).withColumn("part_id", F.when(F.col("unit_id") % 3 == 0, 0).otherwise(F.col("part_id"))).persist()
    sizes = {r.part_id: r.n_units for r in samplers.partition_catalog(units).collect()}
    whole, sliced = samplers.ShuffledPartition(sizes, 60, mix=3), samplers.ShuffledPartition(sizes, 60, mix=3, slice_units=100, prefetch=prefetch)
    for _ in range(2 * sum(sizes.values()) // 60):
        assert [(p, r.unit_id) for p, r in whole.draw_rows(units)] == [(p, r.unit_id) for p, r in sliced.draw_rows(units)]
        assert len(sliced.held) <= 100 + 60
    again = samplers.ShuffledPartition(sizes, 60, mix=3, slice_units=130)
    again.seek(units, sliced.cursor(), 0)
    assert [r.unit_id for _, r in again.draw_rows(units)] == [r.unit_id for _, r in whole.draw_rows(units)]
    sliced.close()
    units.unpersist()


def test_slices_of_wide_units_hold_fewer(spark, sf, monkeypatch):
    """a partition of sparse texts came to the driver whole, whatever its texts held."""
    sparse, cfg, held = tasks.doc_language(spark, sf, 256).persist(), Config(tolerance=0.0, max_iter=4), []
    want = descent.sgd_sparse(sparse, "logistic", cfg, 256, parts=2).weights
    draw = samplers.ShuffledPartition.draw_rows
    monkeypatch.setattr(samplers, "SLICE_NUMBERS", 2_000)
    monkeypatch.setattr(samplers.ShuffledPartition, "draw_rows", lambda self, units: (draw(self, units), held.append(len(self.held)))[0])
    assert np.array_equal(descent.sgd_sparse(sparse, "logistic", cfg, 256, parts=2).weights, want)
    assert max(held) < sparse.count() / 4
    sparse.unpersist()


def test_only_the_plans_asked_for_run_and_read_the_units_once(spark, sf, monkeypatch):
    raw, transform = experiments.raw_set(spark, sf, "big_charge")
    reads, ran = [], []
    known, execute = optimizer.arrays, optimizer.execute
    monkeypatch.setattr(optimizer, "arrays", lambda units: reads.append(1) or known(units))
    monkeypatch.setattr(optimizer, "execute", lambda plan, *a, **k: ran.append(plan.key) or execute(plan, *a, **k))
    runs = optimizer.run_all_plans(raw, transform, optimizer.Request("logistic"), 8, Config(tolerance=0.0, max_iter=3), optimizer.collect_stats(transform(raw)), ("mgd", "sgd"), lambda p: p.sampler == "shuffle")
    assert len(reads) == 1
    assert ran == [r["plan"] for r in runs] == [f"{a}-{t}-shuffle" for a in ("mgd", "sgd") for t in ("eager", "lazy")]
    assert {r["place"] for r in runs} == {"driver"} and {r["iterations"] for r in runs} == {3}


def test_ranks_of_many_ids_are_those_of_one():
    ids = np.array([0, 7, -3, 2**60], dtype=np.int64)
    assert samplers.ranks(7, 3, ids).tolist() == [samplers.py_rank(7, 3, k) for k in ids.tolist()]


def test_rows_of_the_driver_need_no_job(spark, sf):
    events = tasks.table(spark, sf, "events").withColumn("unit_id", F.col("event_id"))
    rows = events.orderBy(F.desc("value"), "event_id").limit(50).collect()
    frame = samplers.here(spark, rows, events.schema)
    assert frame.schema == events.schema and frame.collect() == rows
    assert "LocalTableScan" in frame._jdf.queryExecution().executedPlan().toString()


def test_spreading_out_makes_no_map_for_each_component(spark):
    sparse = spark.createDataFrame([(1, 1.0, 5, [0, 3], [0.25, 0.5]), (2, -1.0, 5, [], []), (3, 1.0, 5, [4], [None])], "unit_id long, label double, dim int, idx array<int>, val array<double>")
    dense = tasks.densify(sparse)
    assert [r.features for r in dense.orderBy("unit_id").collect()] == [[0.25, 0.0, 0.0, 0.5, 0.0], [0.0] * 5, [0.0] * 5]
    assert "map_from_arrays" not in dense._jdf.queryExecution().optimizedPlan().toString()


def test_one_row_group_is_spread_over_the_cores(spark, sf):
    """A small table is read by one task; its words are hashed by as many as there are cores."""
    cores = spark.sparkContext.defaultParallelism
    rows = tasks.table(spark, sf, "documents")
    assert tasks.spread(rows).rdd.getNumPartitions() == cores and tasks.spread(rows).count() == rows.count()
    many = rows.repartition(cores + 1)
    assert tasks.spread(many) is many
    assert "REPARTITION_BY_NUM" in tasks.doc_words(spark, sf)._jdf.queryExecution().executedPlan().toString()


def test_random_draws_of_the_same_partitions_open_them_once(spark, sf, tmp_path, monkeypatch):
    layout = samplers.lay_out(W6.units(spark, sf), f"file://{tmp_path}/laid", 4)
    assert layout.read([0, 2]) is layout.read([0, 2])
    chooser = samplers.RandomPartition(layout.sizes, 40, read=layout.read)
    drawn = sorted(r.unit_id for r in chooser.draw(layout.rows, 1).collect())
    parts = {p: sorted(r.unit_id for r in layout.read([p]).collect()) for p in layout.sizes}
    assert drawn == sorted(parts[p][o] for p, o in chooser.picks(1))


def test_placed_plans_on_the_cluster_share_a_layout(spark, sf, monkeypatch):
    raw, transform = experiments.event_rows(spark, sf)
    wrote, prepare = [], optimizer.prepare
    monkeypatch.setattr(optimizer, "belongs_on_driver", lambda *_: False)
    monkeypatch.setattr(optimizer, "prepare", lambda plan, *a: wrote.append(plan.transform) or prepare(plan, *a))
    runs = optimizer.run_all_plans(raw, transform, optimizer.Request("hinge", batch=20), 2, Config(tolerance=0.0, max_iter=2), optimizer.collect_stats(transform(raw)), ("sgd",), lambda p: p.sampler != "bernoulli")
    assert wrote == ["eager", "lazy"] and len(runs) == 4
    assert {r["layout_s"] for r in runs} == {0.0} and {r["iterations"] for r in runs} == {2}


def test_systems_lay_out_the_cached_units(spark, sf, monkeypatch):
    """x6 reads a set's table and hashes its texts once, for the units and their layout."""

    class Stop(Exception):
        pass

    def stop(units, folder, parts):
        plan = units._jdf.queryExecution().optimizedPlan().toString()
        assert "InMemoryRelation" in plan and "part_id" not in units.columns
        raise Stop

    monkeypatch.setattr(samplers, "lay_out", stop)
    with pytest.raises(Stop):
        list(experiments.x6(spark, sf))
