"""Measures of models, detectors and runs. A history has run_id, method, seed, iteration, cleaned, theta and errors."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .train import Model


def model_error(theta, clean) -> float:
    return float(np.linalg.norm(np.asarray(theta) - np.asarray(clean)))


def relative_model_error(theta, clean) -> float:
    return model_error(theta, clean) / max(float(np.linalg.norm(clean)), 1e-300)


def relative_error_rows(history: DataFrame, clean) -> DataFrame:
    """The history with model_error and rel_model_error from its theta arrays."""
    t = F.array(*[F.lit(float(v)) for v in np.asarray(clean)])
    size = float(np.linalg.norm(clean)) or 1.0
    square = F.aggregate(F.zip_with("theta", t, lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, v: s + v)
    return history.withColumn("model_error", F.sqrt(square)).withColumn("rel_model_error", F.sqrt(square) / size)


def accuracy(rows: DataFrame, prediction: Column, label: str = "y") -> DataFrame:
    return rows.agg(F.avg((prediction == F.col(label)).cast("double")).alias("accuracy"))


def mean_squared_error(rows: DataFrame, model: Model, x: str = "x", y: str = "y") -> DataFrame:
    e = model.score(x) - F.col(y)
    return rows.agg(F.avg(e * e).alias("mse"))


def confusion(rows: DataFrame, truth: Column, flagged: Column) -> DataFrame:
    """tpr (the detection rate), fpr, precision and accuracy of a boolean detector; null where undefined."""
    n = lambda c: F.count_if(c)
    ratio = lambda a, b: F.try_divide(a.cast("double"), b.cast("double"))
    return rows.agg(ratio(n(truth & flagged), n(truth)).alias("tpr"), ratio(n(~truth & flagged), n(~truth)).alias("fpr"), ratio(n(truth & flagged), n(flagged)).alias("precision"), ratio(n(truth == flagged), F.count(F.lit(1))).alias("accuracy"))


def confusion_by(rows: DataFrame, truth: str, predicted: str, *keys: str) -> DataFrame:
    return rows.groupBy(*keys, truth, predicted).agg(F.count(F.lit(1)).alias("n"))


def cleaned_to_reach(history: DataFrame, error: str, target: float, staying: bool = False) -> DataFrame:
    """run_id and the least number of cleaned rows with the error at or below the target (and there to stay); null if never."""
    ok = F.col(error) <= target
    if staying:
        after = Window.partitionBy("run_id").orderBy("cleaned").rowsBetween(Window.currentRow, Window.unboundedFollowing)
        history = history.withColumn("_worst", F.max(error).over(after))
        ok = F.col("_worst") <= target
    return history.groupBy("run_id").agg(F.min(F.when(ok, F.col("cleaned"))).alias("cleaned"))


def ratio_at(history: DataFrame, cleaned: int, base: str, error: str = "rel_model_error") -> DataFrame:
    """Each method's mean error over that of the base method, at one budget."""
    at = history.where(F.col("cleaned") == cleaned).groupBy("method").agg(F.avg(error).alias("e"))
    b = at.where(F.col("method") == base).select(F.col("e").alias("_b"))
    return at.crossJoin(F.broadcast(b)).select("method", F.try_divide(F.col("e"), F.col("_b")).alias("ratio"))


def error_reduction(history: DataFrame, better: str, worse: str, error: str = "rel_model_error") -> DataFrame:
    """1 - error of one method over that of the other, for each number of cleaned rows."""
    wide = history.where(F.col("method").isin(better, worse)).groupBy("cleaned").pivot("method", [better, worse]).agg(F.avg(error))
    return wide.select("cleaned", (1 - F.try_divide(F.col(better), F.col(worse))).alias("reduction"))


def call_counts(ledger: DataFrame) -> DataFrame:
    """Cleaner calls, batches and mean batch size of each run."""
    return ledger.groupBy("run_id").agg(F.count(F.lit(1)).alias("calls"), F.count_distinct("iteration").alias("batches"))


def crossover(history: DataFrame, a: str, b: str, parameter: str, measure: str) -> DataFrame:
    """The least parameter at which method b is no worse than a; null if none."""
    wide = history.groupBy(parameter).pivot("method", [a, b]).agg(F.avg(measure))
    return wide.agg(F.min(F.when(F.col(b) <= F.col(a), F.col(parameter))).alias("crossover"))


def reliability(history: DataFrame, error: str = "rel_model_error") -> DataFrame:
    """Mean and spread of the error over seeds, and whether the mean fell since the last point."""
    out = history.groupBy("method", "cleaned").agg(F.avg(error).alias("mean_error"), F.stddev_samp(error).alias("sd"), F.max(error).alias("worst"))
    before = F.lag("mean_error").over(Window.partitionBy("method").orderBy("cleaned"))
    return out.withColumn("falling", F.col("mean_error") <= before)
