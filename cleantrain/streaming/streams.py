"""Streams over file sources, for triggers that run until the input is used up as well as for endless ones."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.losses import Loss
from ..operators.sampling import estimate
from ..plans.loop import combine, update


def event_stream(spark: SparkSession, path: str, schema, files: int = 10, delay: str = "1 hour") -> DataFrame:
    """Parquet files as they arrive; ts is cast to an instant, which watermarks need."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def detect_stream(rows: DataFrame, predicate) -> DataFrame:
    return rows.withColumn("is_dirty", predicate)


def error_rates(rows: DataFrame, length: str, slide: str | None = None) -> DataFrame:
    """Counts of rows and dirty rows for each tumbling or sliding window; groups end with the watermark."""
    return rows.groupBy(F.window("ts", length, slide)).agg(F.count(F.lit(1)).alias("n"), F.count_if("is_dirty").alias("dirty")).select(F.col("window.start").alias("start"), "n", "dirty")


def sessions(rows: DataFrame, key: str, gap: str) -> DataFrame:
    return rows.groupBy(F.session_window("ts", gap), key).agg(F.count(F.lit(1)).alias("n")).select(key, F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def once_each(rows: DataFrame, key: str) -> DataFrame:
    """Drops a repeated event within the watermark's delay."""
    return rows.dropDuplicatesWithinWatermark([key])


def with_static(rows: DataFrame, static: DataFrame, key: str) -> DataFrame:
    return rows.join(static, key, "left")


def joined_within(left: DataFrame, right: DataFrame, key: str, seconds: int) -> DataFrame:
    """Two streams with watermarks on ts and ts2: rows of equal key at most so many seconds apart; state is dropped by time."""
    near = (F.col("ts2") >= F.col("ts")) & (F.col("ts2") <= F.col("ts") + F.expr(f"interval {seconds} seconds"))
    return left.join(right.withColumnRenamed(key, f"{key}2"), (F.col(key) == F.col(f"{key}2")) & near)


def running_means(rows: DataFrame, key: str, value: str) -> DataFrame:
    """The mean as a loss, one exact step a row (step 1 / (2 n)), with its state kept for each key: key, n, theta after every batch."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(k: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, theta = state.get if state.exists else (0, 0.0)
        for part in parts:
            for v in part[value]:
                n += 1
                theta -= 2 * (theta - float(v)) / (2 * n)
        state.update((n, theta))
        yield pd.DataFrame({key: [k[0]], "n": [n], "theta": [theta]})

    kind = f"{key} {rows.schema[key].dataType.simpleString()}, n long, theta double"
    return rows.groupBy(key).applyInPandasWithState(step, kind, "n long, theta double", "update", GroupStateTimeout.NoTimeout)


class StreamUpdater:
    """One progressive step for each micro-batch of cleaned rows (x_c, y_c, p, n_dirty, draw_order).

    A batch that Spark replays after a failure is recognised by its number and not counted twice; theta and the number
    of the last batch are saved together by `save`.
    """

    def __init__(self, loss: Loss, theta: np.ndarray, clean_gradient: Callable[[np.ndarray], tuple[float, np.ndarray]], step, save: Callable[[int, np.ndarray], None] | None = None, last: int = -1):
        self.loss, self.theta, self.clean_gradient, self.step, self.save, self.last = loss, theta, clean_gradient, step, save, last

    def __call__(self, batch: DataFrame, number: int) -> None:
        if number <= self.last:
            return
        rows = batch.orderBy("draw_order").collect()  # a batch of repairs is bounded by who repairs
        if rows:
            g = self.loss.np_gradients(np.array([r.x_c for r in rows]), np.array([r.y_c for r in rows], dtype=float), self.theta)
            n, total = self.clean_gradient(self.theta)
            g_s = estimate(g, np.array([r.p for r in rows]), rows[0].n_dirty)
            self.theta = update(self.theta, combine(total / max(n, 1), n, g_s, rows[0].n_dirty), self.step(number + 1, len(rows)))
        self.last = number
        if self.save:
            self.save(number, self.theta)


def run_to_memory(spark: SparkSession, rows: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Runs a stream over what there is and returns its result table; for small results."""
    query = rows.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return spark.table(name)
