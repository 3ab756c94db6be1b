"""What keeps the systems of the experiments comparable: caches, draws, compiled code and the library's points."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from descent_planner.functions.gradients import GRADIENTS
from descent_planner.operators import baselines, descent, samplers
from descent_planner.operators.descent import Config
from descent_planner.sources.tasks import W2, doc_language, halfspace


def in_cache(df) -> bool:
    return df.storageLevel.useMemory or df.storageLevel.useDisk


@pytest.mark.parametrize("run", [
    lambda u, c: baselines.fused_standin(u, "hinge", c, fraction=0.5),
    lambda u, c: baselines.fused_standin(u, "hinge", c),
    lambda u, c: baselines.bernoulli_tree(u, "hinge", c, 0.5),
    lambda u, c: baselines.handcoded_bgd(u, "hinge", 2, fraction=0.5),
    lambda u, c: baselines.library_sgd(u, "hinge", c),
    lambda u, c: descent.bgd(u.select("label", "features"), "hinge", c),
])
def test_a_run_leaves_its_callers_units_in_the_cache(spark, sf, run):
    units = halfspace(spark, sf).persist()
    units.count()
    try:
        run(units, Config(tolerance=0.0, max_iter=2))
        assert in_cache(units)
    finally:
        units.unpersist()
    run(units, Config(tolerance=0.0, max_iter=2))
    assert not in_cache(units)


def test_sparse_batch_descent_leaves_its_callers_units_in_the_cache(spark, sf):
    sparse = doc_language(spark, sf, 64).persist()
    n = sparse.count()
    try:
        assert n and descent.bgd_sparse(sparse, "logistic", Config(tolerance=0.0, max_iter=2), 64).iterations == 2
        assert in_cache(sparse)
    finally:
        sparse.unpersist()


def test_rank_below_is_the_comparison_of_ranks(spark):
    rows = spark.range(3000).union(spark.sql("SELECT CAST(NULL AS BIGINT)"))
    rank = samplers.rank_key(7, 3, F.col("id"))
    for limit in (-5, 0, 1, 0.37 * samplers.SPAN, samplers.SPAN / 3 + 0.5, samplers.SPAN - 1, samplers.SPAN, 2.0 * samplers.SPAN):
        below = samplers.rank_below(7, 3, F.col("id"), limit)
        assert rows.where(below != (rank < F.lit(float(limit)))).count() == 0


def test_new_weights_compile_nothing_anew(spark, sf):
    units, g = W2.units(spark, sf).persist(), GRADIENTS["logistic"]
    count = spark._jvm.org.apache.spark.metrics.source.CodegenMetrics.METRIC_COMPILATION_TIME().getCount
    descent.compute(units, np.array([0.5, 0.25, -1.0, 3.0]), g)
    before = count()
    x, y = descent.local(units)
    after = count()
    for w in ([0.1, 0.2, 0.3, 0.4], [-1e-300, 2.5, float("1e17"), 0.0]):
        found, ours = descent.compute(units, np.array(w), g), descent.compute_local(x, y, np.array(w), g)
        assert found.n == ours.n
        np.testing.assert_allclose(found.grad, ours.grad, rtol=1e-9)
    assert count() == after >= before
    units.unpersist()


def test_library_over_points_of_the_jvm_equals_its_python_interface(spark, sf):
    from pyspark.mllib.classification import LogisticRegressionWithSGD
    from pyspark.mllib.linalg import SparseVector
    from pyspark.mllib.regression import LabeledPoint

    options = {"iterations": 3, "step": 1.0, "miniBatchFraction": 0.3, "regParam": 0.0, "regType": None, "intercept": False, "convergenceTol": 0.0}
    cfg = Config(tolerance=0.0, max_iter=3)
    units = W2.units(spark, sf)
    points = units.rdd.map(lambda r: LabeledPoint((r.label + 1) / 2, r.features))
    theirs = LogisticRegressionWithSGD.train(points, initialWeights=[0.0] * 4, **options).weights.toArray()
    assert (baselines.library_sgd(units, "logistic", cfg, 0.3).weights == theirs).all() and theirs.any()
    sparse = doc_language(spark, sf, 64).orderBy("unit_id").persist()
    points = sparse.rdd.map(lambda r: LabeledPoint((r.label + 1) / 2, SparseVector(64, r.idx, r.val)))
    theirs = LogisticRegressionWithSGD.train(points, initialWeights=[0.0] * 64, **options).weights.toArray()
    assert (baselines.library_sparse(sparse, cfg, 64, 0.3).weights == theirs).all() and theirs.any()
    sparse.unpersist()


def test_texts_hashed_by_row_have_the_buckets_of_their_words(spark, sf, tmp_path):
    from descent_planner.sources import tasks

    docs = tasks.table(spark, sf, "documents").select("doc_id", "text", "lang")
    odd = spark.createDataFrame([(-1, None, "en"), (-2, "", "en"), (-3, " \n", "de"), (-4, "a A  b", "en"), (-4, "c\tb", "en")], docs.schema)
    docs.union(odd).write.parquet(f"{tmp_path}/documents.parquet")
    hashes = tasks.doc_hashes(spark, str(tmp_path))
    for dim in (3, 1024):
        words = tasks.doc_words(spark, str(tmp_path), dim).groupBy("unit_id").agg(F.array_sort(F.collect_list("bucket")).alias("idx"))
        theirs = {r.unit_id: r.idx for r in words.collect()}
        assert theirs == {r.unit_id: r.idx for r in tasks.doc_language(spark, str(tmp_path), dim, hashes).collect()} and -4 in theirs and -1 not in theirs
    assert "Generate" not in tasks.doc_language(spark, sf)._jdf.queryExecution().optimizedPlan().toString()


def test_a_slice_is_sorted_without_a_sample_of_its_input(spark, sf):
    units = samplers.with_parts(W2.units(spark, sf), 4).persist()
    sizes = {r.part_id: r.n_units for r in samplers.partition_catalog(units).collect()}
    chooser = samplers.ShuffledPartition(sizes, 5)
    tracker, group = spark.sparkContext.statusTracker(), "one load"
    spark.sparkContext.setJobGroup(group, group)
    rows = [r for _, r in chooser.draw_rows(units)]
    jobs = [tracker.getJobInfo(j) for j in tracker.getJobIdsForGroup(group)]
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    first = chooser.order(0)[0]
    theirs = sorted(((samplers.py_rank(7, 0, r.unit_id), r.unit_id) for r in units.where(F.col("part_id") == first).collect()))[:5]
    assert [r.unit_id for r in rows] == [u for _, u in theirs]
    assert len(jobs) <= 2
    units.unpersist()


def test_sets_are_dealt_over_all_cores(spark, sf):
    from descent_planner import experiments

    for name in ("big_charge", "halfspace"):
        units, plain = experiments.dealt(spark, sf, name), experiments.SETS[name][0](spark, sf)
        assert units.rdd.getNumPartitions() >= spark.sparkContext.defaultParallelism
        assert units.count() == plain.count() and units.exceptAll(plain).isEmpty()
