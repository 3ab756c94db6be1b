"""Cost and accuracy measures."""

from __future__ import annotations

import math
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .samplers import SPAN, rank_key


def split_80_20(units: DataFrame, seed: int = 7, share: float = 0.2) -> tuple[DataFrame, DataFrame]:
    """(training, test) by the hash of the id."""
    test = rank_key(seed, 0, F.col("unit_id")) < int(share * SPAN)
    return units.where(~test), units.where(test)


def testing_error(pred: DataFrame) -> DataFrame:
    """Mean squared errors of labels and the error rate; labels of classes are -1 and 1."""
    miss = F.avg(F.when(F.col("prediction") != F.col("label"), 1.0).otherwise(0.0))
    return pred.agg(F.avg((F.col("prediction") - F.col("label")) ** 2).alias("mse_pm1"), miss.alias("mse_01"), miss.alias("error_rate"), F.sqrt(F.avg((F.col("prediction") - F.col("label")) ** 2)).alias("rmse"))


def r2(pred: DataFrame) -> DataFrame:
    return pred.agg((1 - F.sum((F.col("prediction") - F.col("label")) ** 2) / (F.var_pop("label") * F.count("*"))).alias("r2"))


def classification_report(pred: DataFrame) -> DataFrame:
    n = lambda p, y: F.sum(F.when((F.col("prediction") == p) & (F.col("label") == y), 1).otherwise(0))
    c = pred.agg(n(1.0, 1.0).alias("tp"), n(1.0, -1.0).alias("fp"), n(-1.0, 1.0).alias("fn"), n(-1.0, -1.0).alias("tn"))
    p, r = F.try_divide(F.col("tp"), F.col("tp") + F.col("fp")), F.try_divide(F.col("tp"), F.col("tp") + F.col("fn"))
    return c.withColumns({"precision": p, "recall": r, "f1": F.try_divide(2.0 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn"))})


def auc(pred: DataFrame, buckets: int = 256) -> DataFrame:
    """Area under the curve of z by counts a distinct value: partial sums first, so that a hot value is one row.

    Values are dealt into ``buckets`` ranges of z by approximate quantiles; a running sum within a range is added to the
    sum of the ranges before, so that no task sorts all of them.
    """
    from pyspark.sql.window import Window

    by = pred.groupBy("z").agg(F.sum(F.when(F.col("label") > 0, 1).otherwise(0)).alias("p"), F.sum(F.when(F.col("label") > 0, 0).otherwise(1)).alias("n"))
    edges = sorted(set(pred.select(F.percentile_approx("z", [k / buckets for k in range(1, buckets)], 10_000)).first()[0] or []))
    by = by.withColumn("b", F.size(F.filter(F.array(*(F.lit(float(e)) for e in edges)), lambda e: e < F.col("z"))) if edges else F.lit(0))
    before = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    totals = by.groupBy("b").agg(F.sum("n").alias("own")).select("b", F.coalesce(F.sum("own").over(before), F.lit(0)).alias("base"))
    below = F.coalesce(F.sum("n").over(Window.partitionBy("b").orderBy("z").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = by.withColumn("within", below).join(F.broadcast(totals), "b").withColumn("below", F.col("within") + F.col("base"))
    return ranked.agg((F.sum(F.col("p") * (F.col("below") + F.col("n") / 2)) / (F.sum("p") * F.sum("n"))).alias("auc"))


def iteration_error(estimated: int, actual: int) -> dict:
    ratio = estimated / actual
    return {"ratio": ratio, "same_order": abs(math.log10(ratio)) < 1}


def same_ordering(estimated: dict, actual: dict) -> tuple[bool, float]:
    """Whether both put the algorithms in one order, and Kendall's tau."""
    signs = [(estimated[a] - estimated[b]) * (actual[a] - actual[b]) for a, b in combinations(sorted(actual), 2)]
    tau = sum((s > 0) - (s < 0) for s in signs) / max(1, len(signs))
    return all(s >= 0 for s in signs), tau


def relative_error(estimated: float, actual: float) -> float:
    return abs(estimated - actual) / actual


def scaling_slope(points: list[tuple[float, float]]) -> float:
    """Slope of log time over log size."""
    x, y = [math.log(a) for a, _ in points], [math.log(b) for _, b in points]
    mx, my = sum(x) / len(x), sum(y) / len(y)
    return sum((a - mx) * (b - my) for a, b in zip(x, y, strict=True)) / sum((a - mx) ** 2 for a in x)
