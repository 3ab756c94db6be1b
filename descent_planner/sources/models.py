"""Models as one-row Parquet tables."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

SCHEMA = "task string, gradient string, dim int, weights array<double>, plan string, tolerance double, norm string, iters int, status string"


def model_frame(spark: SparkSession, m: dict) -> DataFrame:
    w = [float(x) for x in m["weights"]]
    return spark.createDataFrame([(m["task"], m["gradient"], len(w), w, m["plan"], float(m["tolerance"]), m["norm"], int(m["iters"]), m["status"])], SCHEMA)


def save_model(spark: SparkSession, m: dict, path: str) -> None:
    model_frame(spark, m).coalesce(1).write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> dict:
    r = spark.read.schema(SCHEMA).parquet(path).first()
    return r.asDict() | {"weights": np.array(r.weights)}
