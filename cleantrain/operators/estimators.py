"""What cleaning changes on average: additive statistics of the ledger, and the estimators built on them."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.losses import Loss


def change_by_feature(ledger: DataFrame, by_class: bool = False, norm: str = "ratio") -> DataFrame:
    """[class_id,] feature, delta: the mean change (clean minus dirty) of each flagged feature, weighed by 1 / pi.

    ledger: x, x_c, err_features, pi (and class_id). `ratio` divides by the weights of the rows flagged on the feature;
    `population` by the number of ledger rows. Labels are not in it; see change_of_label.
    """
    keys = ["class_id", "feature"] if by_class else ["feature"]
    each = ledger.select(*keys[:-1], "x", "x_c", "pi", F.explode("err_features").alias("feature"))
    d = F.get("x_c", F.col("feature")) - F.get("x", F.col("feature"))
    out = each.groupBy(*keys).agg(F.sum(1 / F.col("pi")).alias("sum_w"), F.sum(d / F.col("pi")).alias("sum_wd"))
    if norm == "population":
        out = out.crossJoin(F.broadcast(ledger.agg(F.count(F.lit(1)).alias("k")))).withColumn("sum_w", F.col("k").cast("double"))
    return out.select(*keys, (F.col("sum_wd") / F.col("sum_w")).alias("delta"))


@dataclass
class ChangeStats:
    """The same sums kept on the driver as cleaning goes on: at most classes x features numbers."""

    d: int
    weight: dict = field(default_factory=dict)
    change: dict = field(default_factory=dict)
    label: dict = field(default_factory=dict)

    def update(self, x, x_c, y, y_c, flags: list, pi, class_id=None) -> None:
        for i in range(len(pi)):
            for c in {None, None if class_id is None else class_id[i]}:
                w, s = self.weight.setdefault(c, np.zeros(self.d)), self.change.setdefault(c, np.zeros(self.d))
                at = list(range(self.d)) if c is not None else list(flags[i])
                w[at] += 1 / pi[i]
                s[at] += (x_c[i] - x[i])[at] / pi[i]
                a = self.label.setdefault(c, [0.0, 0.0])
                a[0] += 1 / pi[i]
                a[1] += (y_c[i] - y[i]) / pi[i]

    def delta(self, c=None) -> np.ndarray:
        """Zero for features that no cleaned row was flagged on."""
        w = self.weight.get(c, np.zeros(self.d))
        return np.divide(self.change.get(c, np.zeros(self.d)), w, out=np.zeros(self.d), where=w > 0)

    def delta_y(self, c=None) -> float:
        a = self.label.get(c, (0.0, 0.0))
        return a[1] / a[0] if a[0] else 0.0

    def by_class(self) -> dict:
        return {c: (self.delta(c), self.delta_y(c)) for c in self.weight if c}


def fit_gradient_regression(dirty: np.ndarray, clean: np.ndarray, ridge: float = 1e-3) -> np.ndarray:
    """d x (d + 1): ridge regression of clean on dirty gradients of the cleaned rows."""
    x = np.column_stack([dirty, np.ones(len(dirty))])
    return np.linalg.solve(x.T @ x + ridge * len(x) * np.eye(x.shape[1]), x.T @ clean).T


def estimated_gradients(kind: str, loss: Loss, theta, x, y, flags: np.ndarray, seen: dict) -> np.ndarray:
    """Clean gradients of dirty rows as each estimator sees them; flags is a 0/1 matrix, `seen` the cleaned rows.

    kinds: dirty, taylor, feature_change, average_gradient, regression.
    """
    g = loss.np_gradients(x, y, theta)
    if kind == "dirty" or not len(seen["x"]):
        return g
    change = seen["x_c"] - seen["x"]
    w = (seen["flags"] / seen["pi"][:, None]).sum(0)
    delta = np.divide((change * seen["flags"] / seen["pi"][:, None]).sum(0), w, out=np.zeros(x.shape[1]), where=w > 0)
    if kind == "taylor":
        return loss.np_corrections(x, y, theta, flags * delta, np.zeros(len(y)))
    if kind == "feature_change":
        return loss.np_gradients(x + flags * delta, y, theta)
    before, after = loss.np_gradients(seen["x"], seen["y"], theta), loss.np_gradients(seen["x_c"], seen["y_c"], theta)
    if kind == "average_gradient":
        return g + (after - before).mean(0)
    if kind == "regression":
        b = fit_gradient_regression(before, after)
        return g @ b[:, :-1].T + b[:, -1]
    raise ValueError(kind)


def relative_error_sum(estimated: np.ndarray, true: np.ndarray, least: float = 1e-12) -> tuple[float, int]:
    """Sum of |estimate - truth| / |truth| over rows with a gradient, and their number."""
    size = np.linalg.norm(true, axis=1)
    some = size > least
    return float((np.linalg.norm(estimated - true, axis=1)[some] / size[some]).sum()), int(some.sum())
