"""Sums of gradients by partial aggregation, and sufficient statistics that replace them for squared losses."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.losses import Loss
from ..functions.vectors import dot

#: Above so many features a row's arithmetic goes to an Arrow kernel instead of one generated expression for each position.
WIDE = 40


def gradient_sums(loss: Loss, theta, x: str = "x", y: str = "y", weight: Column | None = None) -> Column:
    """One array-valued aggregate: the sum over rows of weight * gradient."""
    slope = loss.slope(dot(F.col(x), theta), F.col(y))
    slope = slope if weight is None else slope * weight
    return F.array(*[F.sum(slope * F.get(x, F.lit(i))) for i in range(len(theta))])


def total_gradient(rows: DataFrame, loss: Loss, theta, x: str = "x", y: str = "y", weight: str | None = None) -> tuple[np.ndarray, int]:
    """The sum of gradients and the number of rows, on the driver; rows with a null in x or y are left out by the caller."""
    theta = np.asarray(theta, dtype=float)
    if len(theta) <= WIDE:
        found = rows.agg(gradient_sums(loss, theta, x, y, None if weight is None else F.col(weight)).alias("g"), F.count(F.lit(1)).alias("n")).first()
        return (np.array(found.g) if found.n else np.zeros(len(theta))), found.n

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(len(theta)), 0
        for batch in batches:
            part = np.stack(batch.column(0).to_numpy(zero_copy_only=False)) if batch.num_rows else np.zeros((0, len(theta)))
            slope = loss.np_slope(part @ theta, batch.column(1).to_numpy(zero_copy_only=False))
            slope = slope * batch.column(2).to_numpy(zero_copy_only=False)
            total, n = total + slope @ part, n + len(part)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(theta)), pa.int32()), pa.array(total), pa.array([n] * len(theta), pa.int64())], ["feature", "g", "n"])

    # One row of sums for each task and feature; Spark adds them in a second stage.
    kernel = rows.select(x, F.col(y).cast("double"), (F.lit(1.0) if weight is None else F.col(weight)).alias("w")).mapInArrow(partial, "feature int, g double, n long")
    found = kernel.groupBy("feature").agg(F.sum("g").alias("g"), F.sum("n").alias("n")).orderBy("feature").collect()
    return np.array([r.g for r in found]) if found else np.zeros(len(theta)), found[0].n if found else 0


def mean_gradient(rows: DataFrame, loss: Loss, theta, x: str = "x", y: str = "y") -> DataFrame:
    """feature and gradient: the mean gradient in long form, one pass without a shuffle of rows."""
    return rows.agg(gradient_sums(loss, theta, x, y).alias("g"), F.count(F.lit(1)).alias("n")).select(F.posexplode("g").alias("feature", "g"), "n").select("feature", (F.coalesce("g", F.lit(0.0)) / F.greatest("n", F.lit(1))).alias("gradient"))


def per_class_gradient(rows: DataFrame, loss: Loss, thetas, classes: list, label: str, x: str = "x") -> DataFrame:
    """One-vs-all: class_id, feature, gradient for all classes in one scan; targets are 1 and -1 (0 for a logistic loss)."""
    low = 0.0 if loss.name == "logistic" else -1.0
    cells = []
    for c, theta in zip(classes, thetas, strict=True):
        slope = loss.slope(dot(F.col(x), theta), F.when(F.col(label) == c, 1.0).otherwise(low))
        cells += [F.struct(F.lit(c).alias("class_id"), F.lit(i).alias("feature"), F.avg(slope * F.get(x, F.lit(i))).alias("gradient")) for i in range(len(theta))]
    return rows.agg(F.array(*cells).alias("cells")).select(F.inline("cells"))


@dataclass
class GramState:
    """A = sum x x', c = sum x y, n: the squared loss's total gradient at any theta is A theta - c, without a scan."""

    a: np.ndarray
    c: np.ndarray
    n: float

    @staticmethod
    def of(rows: DataFrame, d: int, x: str = "x", y: str = "y") -> GramState:
        if d <= 12:
            cells = [F.sum(F.get(x, F.lit(i)) * F.get(x, F.lit(j))) for i in range(d) for j in range(i, d)] + [F.sum(F.get(x, F.lit(i)) * F.col(y)) for i in range(d)]
            found = rows.agg(F.array(*cells).alias("s"), F.count(F.lit(1)).alias("n")).first()
            values = [v or 0.0 for v in found.s]
            a = np.zeros((d, d))
            a[np.triu_indices(d)] = values[: d * (d + 1) // 2]
            return GramState(a + np.triu(a, 1).T, np.array(values[-d:]), found.n)

        def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            total = np.zeros((d + 1, d + 1))
            for batch in batches:
                if batch.num_rows:
                    part = np.column_stack([np.stack(batch.column(0).to_numpy(zero_copy_only=False)), batch.column(1).to_numpy(zero_copy_only=False)])
                    total += part.T @ part
                    total[d, d] += len(part) - (part[:, d] ** 2).sum()
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(d + 1), d + 1), pa.int32()), pa.array(np.tile(np.arange(d + 1), d + 1), pa.int32()), pa.array(total.ravel())], ["i", "j", "v"])

        found = rows.select(x, F.col(y).cast("double")).mapInArrow(partial, "i int, j int, v double").groupBy("i", "j").agg(F.sum("v").alias("v")).collect()
        whole = np.zeros((d + 1, d + 1))
        for r in found:
            whole[r.i, r.j] = r.v
        return GramState(whole[:d, :d], whole[:d, d], whole[d, d])

    def total_gradient(self, theta: np.ndarray) -> np.ndarray:
        return self.a @ theta - self.c

    def add(self, x: np.ndarray, y: np.ndarray, sign: float = 1.0) -> None:
        """Moves rows in, or with sign -1 out: rank-b updates, exact."""
        self.a, self.c, self.n = self.a + sign * x.T @ x, self.c + sign * x.T @ y, self.n + sign * len(y)

    def solve(self, lam: float = 0.0) -> np.ndarray:
        """The minimiser of the mean loss + lam/2 |theta|^2; position 0 is the intercept and bears no penalty."""
        penalty = lam * np.eye(len(self.c))
        penalty[0, 0] = 0.0
        return np.linalg.lstsq(self.a / max(self.n, 1) + penalty, self.c / max(self.n, 1), rcond=None)[0]
