"""Sampling weights, distributions and designs with the estimators that are right for them.

Random numbers are hashes of (seed, iteration, row id): a retried task draws the same rows.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.losses import Loss
from ..functions.portable import uniform, uniform_number
from ..functions.vectors import add_all, dot, masked

FLOOR = 0.1
BUCKETS = 1024


class Weight:
    """Columns of unnormalised sampling weights."""

    @staticmethod
    def uniform() -> Column:
        return F.lit(1.0)

    @staticmethod
    def dirty_gradient(loss: Loss, theta, x: str = "x", y: str = "y", norm: str | None = None) -> Column:
        return loss.gradient_norm(F.col(x), F.col(y), theta, None if norm is None else F.col(norm))

    @staticmethod
    def oracle(loss: Loss, theta, x: str = "x_c", y: str = "y_c") -> Column:
        """The norm of the clean gradient, which only an experiment can know."""
        return loss.gradient_norm(F.col(x), F.col(y), theta)

    @staticmethod
    def taylor(loss: Loss, theta, delta, delta_y: float = 0.0, features: str = "err_features", labels: str | None = None, x: str = "x", y: str = "y") -> Column:
        """The expected clean gradient's norm to first order, with the mean change of the features flagged on the row."""
        dy = F.lit(float(delta_y)) if labels is None else F.when(F.size(labels) > 0, float(delta_y)).otherwise(0.0)
        return loss.corrected_norm(F.col(x), F.col(y), theta, masked(delta, F.col(features)), dy)

    @staticmethod
    def taylor_by_class(loss: Loss, theta, deltas: dict[int, tuple], class_id: str = "class_id", x: str = "x", y: str = "y") -> Column:
        """The same with one mean change for each class of error; unknown classes and class 0 keep the dirty gradient."""
        if not deltas:
            return Weight.dirty_gradient(loss, theta, x, y)

        def of(part) -> Column:
            """A number for each class; without a change the norm is the dirty gradient's."""
            out = F.lit(0.0)
            for c, (delta, delta_y) in sorted(deltas.items()):
                out = F.when(F.col(class_id) == c, part(np.asarray(delta, dtype=float), float(delta_y))).otherwise(out)
            return out

        # The norm is written once, not once a class: planning and compiling it took longer than its pass.
        s, square, dy = of(lambda v, _: F.lit(float(v @ theta))), of(lambda v, _: F.lit(float(v @ v))), of(lambda _, v: F.lit(v))
        return loss.norm_of_parts(F.col(x), F.col(y), theta, s, of(lambda v, _: dot(F.col(x), v)), square, dy)

    @staticmethod
    def feature_change(loss: Loss, theta, delta, features: str = "err_features", x: str = "x", y: str = "y") -> Column:
        """The gradient's norm at the row moved by the mean change: no linearisation."""
        moved = F.zip_with(F.col(x), masked(delta, F.col(features)), lambda a, b: a + b)
        return loss.gradient_norm(moved, F.col(y), theta)

    @staticmethod
    def average_gradient(loss: Loss, theta, change, x: str = "x", y: str = "y") -> Column:
        """The dirty gradient plus the mean change of gradients seen so far."""
        s = loss.slope(dot(F.col(x), theta), F.col(y))
        return F.sqrt(add_all([(s * F.get(x, F.lit(i)) + float(c)) * (s * F.get(x, F.lit(i)) + float(c)) for i, c in enumerate(change)]))

    @staticmethod
    def gradient_regression(loss: Loss, theta, b: np.ndarray, x: str = "x", y: str = "y") -> Column:
        """A linear prediction of the clean gradient from the dirty one: b is d x (d + 1), its last column the intercept."""
        s = loss.slope(dot(F.col(x), theta), F.col(y))
        g = [s * F.get(x, F.lit(i)) for i in range(len(theta))]
        parts = [add_all([g[j] * float(row[j]) for j in range(len(g))]) + float(row[-1]) for row in b]
        return F.sqrt(add_all([p * p for p in parts]))

    @staticmethod
    def uncertainty(theta, x: str = "x", threshold: float = 0.0) -> Column:
        """The inverse distance to the decision boundary."""
        size = float(np.linalg.norm(theta)) or 1.0
        return 1.0 / (F.abs(dot(F.col(x), theta) - threshold) / size + 1e-3)


def floored(weight: Column, total: Column, n: Column, floor: float = FLOOR) -> Column:
    """(1 - floor) w / sum w + floor / n; even where all weights are zero. No row is left without a chance."""
    return F.when(total > 0, (1 - floor) * weight / total + floor / n).otherwise(1.0 / n)


def distribution(rows: DataFrame, weight: Column, floor: float = FLOOR) -> DataFrame:
    """The rows with w and p; the totals are one row, joined by broadcast."""
    rows = rows.withColumn("w", F.coalesce(weight, F.lit(0.0)))
    totals = rows.agg(F.coalesce(F.sum("w"), F.lit(0.0)).alias("_total"), F.count(F.lit(1)).alias("_n"))
    return rows.crossJoin(F.broadcast(totals)).withColumn("p", floored(F.col("w"), F.col("_total"), F.col("_n"), floor)).withColumn("n_dirty", F.col("_n")).drop("_total", "_n")


def draw_key(p: Column, seed: object, iteration: object, row_id: str = "row_id") -> Column:
    """Exponential arrival of rate p: the b earliest, in order, are a successive draw without replacement."""
    return -F.log(uniform(row_id, seed, iteration)) / p


def draw_ordered(rows: DataFrame, b: int, seed: object, iteration: object) -> DataFrame:
    """The b smallest keys with draw_order 1..b: a heap of b in each task, no sort, no shuffle of rows."""
    top = rows.withColumn("key", draw_key(F.col("p"), seed, iteration)).orderBy("key", "row_id").limit(b)
    return top.withColumn("draw_order", F.row_number().over(Window.partitionBy(F.lit(1)).orderBy("key", "row_id")))  # b rows


def draw_poisson(rows: DataFrame, b: int, seed: object, iteration: object) -> DataFrame:
    """Every row on its own with pi = min(1, b p): a filter, of random size."""
    return rows.withColumn("pi", F.least(F.lit(1.0), b * F.col("p"))).where(uniform("row_id", seed, iteration) < F.col("pi"))


def draw_bottom_k(rows: DataFrame, b: int, seed: object, iteration: object) -> DataFrame:
    """The b smallest keys with pi, the chance of a key below the next one, tau; pi is 1 where the pool has no next one."""
    top = rows.withColumn("key", draw_key(F.col("p"), seed, iteration)).orderBy("key", "row_id").limit(b + 1)
    every = Window.partitionBy(F.lit(1))  # b + 1 rows
    top = top.withColumn("draw_order", F.row_number().over(every.orderBy("key", "row_id"))).withColumn("_k", F.count(F.lit(1)).over(every)).withColumn("tau", F.max("key").over(every))
    pi = F.when(F.col("_k") > b, 1 - F.exp(-F.col("p") * F.col("tau"))).otherwise(1.0)
    return top.where(F.col("draw_order") <= b).withColumn("pi", pi).drop("_k", "tau")


def draw_with_replacement(rows: DataFrame, b: int, seed: int, iteration: int) -> DataFrame:
    """b independent draws: row_id, p, times; p needs no normaliser. Points are hashes of (seed, iteration, number); they fall into buckets of rows by their totals, then into a row by a running sum.

    The totals are BUCKETS numbers on the driver; running sums are needed only in buckets that got a point.
    """
    rows = rows.withColumn("_bucket", F.pmod("row_id", F.lit(BUCKETS)))
    sums = {r["_bucket"]: r.s for r in rows.groupBy("_bucket").agg(F.sum("p").alias("s")).collect()}
    names = sorted(sums)
    edges = np.cumsum([sums[k] for k in names])
    if not names:
        return rows.select("row_id", "p", F.lit(0).cast("long").alias("times"))
    points = np.array([uniform_number(k, seed, iteration, "point") for k in range(1, b + 1)]) * edges[-1]
    at = np.minimum(np.searchsorted(edges, points, side="right"), len(names) - 1)
    inside = points - np.concatenate([[0.0], edges[:-1]])[at]
    spark = rows.sparkSession
    asked = spark.createDataFrame([(int(names[k]), float(v)) for k, v in zip(at, inside, strict=True)], "_bucket long, point double")
    ordered = Window.partitionBy("_bucket").orderBy("row_id")
    held = rows.join(F.broadcast(asked.select("_bucket").distinct()), "_bucket", "left_semi")
    held = held.withColumn("_to", F.sum("p").over(ordered)).withColumn("_from", F.col("_to") - F.col("p")).withColumn("_last", F.lead("row_id").over(ordered).isNull())
    hit = held.join(F.broadcast(asked), "_bucket").where((F.col("point") >= F.col("_from")) & ((F.col("point") < F.col("_to")) | F.col("_last")))
    return hit.groupBy("row_id").agg(F.first("p").alias("p"), F.count(F.lit(1)).alias("times"))


def estimate(gradients: np.ndarray, p: np.ndarray, n: float, design: str = "ordered", times: np.ndarray | None = None, pi: np.ndarray | None = None, tau: float | None = None, b: int | None = None) -> np.ndarray:
    """The mean gradient of the pool from a batch, by the estimator of the design. Rows are in draw order."""
    k = len(p)
    if not k:
        return np.zeros(gradients.shape[1])
    if design == "ordered":
        # Of each draw: what came before, plus its own inverse-probability term for what was left.
        before = np.cumsum(gradients, axis=0) - gradients
        left = 1 - (np.cumsum(p) - p)
        return (before + gradients * (left / p)[:, None]).sum(0) / (k * n)
    if design == "with_replacement":
        times = np.ones(k) if times is None else times
        return (gradients * (times / p)[:, None]).sum(0) / (times.sum() * n)
    if design == "poisson":
        return (gradients / pi[:, None]).sum(0) / n
    if design == "bottom_k":
        return (gradients / (1 - np.exp(-p * tau))[:, None]).sum(0) / n
    if design == "naive":
        return (gradients / ((b or k) * p)[:, None]).sum(0) / n
    if design == "literal":
        return (gradients / p[:, None]).sum(0) / k  # the printed form, which estimates the sum of the pool
    raise ValueError(design)


def estimate_part(gradients: np.ndarray, p: np.ndarray, n: float, start: int) -> np.ndarray:
    """The pool's mean gradient from the draws from `start` on, given all draws up to the last of them: each draw's own term is unbiased."""
    before = np.cumsum(gradients, axis=0) - gradients
    left = 1 - (np.cumsum(p) - p)
    return (before + gradients * (left / p)[:, None])[start:].mean(0) / n


def design_variance(rows: DataFrame, p: str, size: str, k: int = 1) -> DataFrame:
    """variance of the mean of k independent draws: (sum a^2/p / n^2 - mean^2) / k, least where p follows |a|."""
    out = rows.agg(F.sum(F.col(size) * F.col(size) / F.col(p)).alias("s"), F.avg(size).alias("m"), F.count(F.lit(1)).alias("n"))
    return out.select(((F.col("s") / (F.col("n") * F.col("n")) - F.col("m") * F.col("m")) / k).alias("variance"))
