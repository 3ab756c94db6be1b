"""Learning and measuring over streams of events."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.gradients import GRADIENTS
from ..operators.descent import Config, compute, update


def stream_fit(stream: DataFrame, dim: int, gradient: str, cfg: Config, checkpoint: str, model_path: str) -> np.ndarray:
    """One Update a micro-batch. Each batch writes the model of its number, made of the model before it: a batch that
    runs again after a failure writes the same model again."""
    spark = stream.sparkSession
    g = GRADIENTS[gradient]
    schema = "w array<double>"

    def one(batch: DataFrame, number: int) -> None:
        w = np.zeros(dim) if number == 0 else np.array(spark.read.schema(schema).parquet(f"{model_path}/{number - 1}").first().w)
        p = compute(batch, w, g)
        if p.n:
            w = update(p, w, cfg.alpha(number + 1), cfg)
        spark.createDataFrame([([float(x) for x in w],)], schema).coalesce(1).write.mode("overwrite").parquet(f"{model_path}/{number}")
        one.last = w

    one.last = np.zeros(dim)
    stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return one.last


def windowed(events: DataFrame, kind: str) -> DataFrame:
    """Mean value and count by tumbling, sliding or session windows; the same over batch and stream."""
    w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "1 day", "6 hours")}.get(kind)
    if kind == "session":
        return events.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("total")).select("user_id", F.col("w.start").alias("start"), "n", "total")
    return events.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.avg("value").alias("mean_value")).select(F.col("w.start").alias("start"), "n", "mean_value")


def replay(spark: SparkSession, sf_dir: str, make, folder: str, watermark: str = "10 days", mode: str = "complete") -> DataFrame:
    """Runs ``make`` over events as a stream to its end and returns the sink's rows."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    src = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(path if _is_folder(spark, path) else sf_dir + "/event*.parquet")
    src = src.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)
    out, rows = f"{folder}/rows", make(src)

    def keep(batch: DataFrame, number: int) -> None:
        # a batch that runs again writes its folder again; a complete result replaces the one before
        batch.write.mode("overwrite").parquet(f"{out}/{0 if mode == 'complete' else number}")

    rows.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(rows.schema).parquet(f"{out}/*")


def late_counts(spark: SparkSession, on_time: DataFrame, late: DataFrame, folder: str, watermark: str = "1 hour") -> DataFrame:
    """(start, n) of the days that the watermark closes, where ``late`` rows arrive after all ``on_time`` ones.

    The query stops between the two arrivals and is started again over the same checkpoint, so that the second one meets
    the watermark of the first: what belongs to a closed day is dropped.
    """
    source, sink = f"{folder}/in", f"{folder}/out"
    schema = on_time.select("event_id", "ts").schema
    for rows in (on_time, late):
        rows.select("event_id", "ts").write.mode("append").parquet(source)
        days = spark.readStream.schema(schema).parquet(source).withWatermark("ts", watermark).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n"))
        q = days.select(F.col("w.start").alias("start"), "n").writeStream.format("parquet").outputMode("append").option("checkpointLocation", f"{folder}/ckpt").trigger(availableNow=True).start(sink)
        q.awaitTermination()
    return spark.read.parquet(sink)


def followed_within(events: DataFrame, span: str = "1 hour") -> DataFrame:
    """(first, second): a user's events and those that follow them within ``span``; the watermarks bound the state."""
    a = events.select(F.col("event_id").alias("first"), "user_id", F.col("ts").alias("at"))
    b = events.select(F.col("event_id").alias("second"), F.col("user_id").alias("who"), F.col("ts").alias("then"))
    near = (F.col("user_id") == F.col("who")) & (F.col("then") > F.col("at")) & (F.col("then") <= F.col("at") + F.expr(f"INTERVAL {span}"))
    return a.join(b, near).select("first", "second")


def _is_folder(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def per_user_models(events: DataFrame, gradient: str, cfg: Config) -> DataFrame:
    """A model of each user, updated batch by batch in a keyed state."""
    import pandas as pd

    g = GRADIENTS[gradient]

    def step(key, frames, state):
        w, n = (np.array(state.get[0]), state.get[1]) if state.exists else (np.zeros(2), 0)
        for f in frames:
            x = np.column_stack([np.ones(len(f)), f["value"] / 100])
            y = np.where(f["value"] > 50, 1.0, -1.0)
            n += 1
            w = w - cfg.alpha(n) * (x.T @ g.np_coefficient(x @ w, y)) / len(f)
        state.update((w.tolist(), n))
        yield pd.DataFrame({"user_id": [key[0]], "w0": [w[0]], "w1": [w[1]], "batches": [n]})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, w0 double, w1 double, batches int", "w array<double>, n int", "update", "NoTimeout")
