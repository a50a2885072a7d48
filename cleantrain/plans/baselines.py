"""Baselines. All return history rows (see loop.HISTORY), so that runs compare point by point."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.losses import Loss
from ..functions.portable import uniform
from ..operators.detect import ClassifierDetector
from ..operators.gradient import GramState
from ..operators.train import Model, fit
from ..sources.tables import local_rows
from .loop import ProgressiveCleaner, RunResult

#: Rows that a baseline may hold on the driver; larger samples are fitted by Spark.
DRIVER_ROWS = 1_000_000


def _point(method: str, seed: int, iteration: int, cleaned: int, theta) -> tuple:
    return (f"{method}-{seed}", method, seed, iteration, cleaned, 0, 0.0, [float(v) for v in theta])


def no_cleaning(rows: DataFrame, loss: Loss, d: int, lam: float = 0.0) -> Model:
    return fit(rows, loss, d, lam)


def full_cleaning(rows: DataFrame, loss: Loss, d: int, lam: float = 0.0) -> Model:
    """On the truth x_c, y_c: what all errors are measured against."""
    return fit(rows, loss, d, lam, x="x_c", y="y_c")


def discard_dirty(rows: DataFrame, loss: Loss, d: int, lam: float = 0.0) -> Model:
    return fit(rows.where("not is_dirty"), loss, d, lam)


def trim_threshold(n: int, d: int, mode: str = "standardised") -> float:
    """4 sqrt(log p / n + log n / n) on values scaled by 1 / sqrt(n): on standardised values, 4 sqrt(log p + log n)."""
    literal = 4 * math.sqrt(math.log(max(d, 2)) / n + math.log(n) / n)
    return literal if mode == "literal" else literal * math.sqrt(n)


def robust_filter(rows: DataFrame, d: int, mode: str = "standardised", x: str = "x") -> DataFrame:
    """Rows without a coordinate that deviates from its mean by the threshold, in standard deviations (intercept aside)."""
    stats = rows.agg(F.count(F.lit(1)).alias("n"), F.array(*[F.avg(F.get(x, F.lit(i))) for i in range(1, d)]).alias("m"), F.array(*[F.stddev_pop(F.get(x, F.lit(i))) for i in range(1, d)]).alias("s")).first()
    if not stats.n:
        return rows
    limit = trim_threshold(stats.n, d, mode)
    far = [F.abs(F.get(x, F.lit(i)) - stats.m[i - 1]) / (stats.s[i - 1] or 1.0) for i in range(1, d)]
    return rows.where((F.greatest(*far) if len(far) > 1 else far[0]) < limit)


def robust_logistic(rows: DataFrame, loss: Loss, d: int, lam: float = 1e-3, mode: str = "standardised") -> tuple[Model, int]:
    """The model fitted to what the trimming leaves, and how many rows it removed."""
    kept = robust_filter(rows, d, mode)
    return fit(kept, loss, d, lam), rows.count() - kept.count()


def clean_sample_only(rows: DataFrame, cleaner, loss: Loss, d: int, sizes: list[int], lam: float = 0.0, seed: int = 0, dirty_only: bool = False) -> list[tuple]:
    """A uniform sample, cleaned, and a fit from scratch at each size; samples are nested by one order of hashes."""
    pool = rows.where("is_dirty") if dirty_only else rows
    top = pool.withColumn("_u", uniform("row_id", seed, "sample")).orderBy("_u", "row_id").limit(max(sizes))
    drawn = top.drop("_u").collect()  # one pass; as many rows as are cleaned
    ids = [r.row_id for r in drawn]
    cleaned = cleaner.clean(local_rows(rows.sparkSession, [r.asDict() for r in drawn], top.drop("_u").schema)).where("kept").select("row_id", F.col("x_c").alias("x"), F.col("y_c").alias("y"))
    held = {r.row_id: (list(r.x), r.y) for r in cleaned.collect()}
    out = []
    for k, size in enumerate(sizes, 1):
        part = [held[i] for i in ids[:size] if i in held]
        model = fit(local_rows(rows.sparkSession, [{"x": x, "y": y} for x, y in part], "x array<double>, y double"), loss, d, lam)
        out.append(_point("clean_sample_only", seed, k, min(size, len(ids)), model.theta))
    return out


def uncertainty_sampling(rows: DataFrame, cleaner, loss: Loss, d: int, mode: str = "prob", **options) -> RunResult:
    """Draws near the decision boundary, with the progressive update. mode 'topb' takes the nearest rows: their average
    gradient has no known probabilities and is biased."""
    return ProgressiveCleaner(rows, cleaner, loss, d, weight="uncertainty" if mode == "prob" else "top_uncertain", method=f"uncertainty_{mode}", **options).run()


def partial_clean(rows: DataFrame, cleaner, loss: Loss, d: int, sizes: list[int], lam: float = 0.0, seed: int = 0, detector: bool = False) -> list[tuple]:
    """Cleaned values are written back into the dirty table and the model is fitted to the mixture, at each size.

    With a squared loss the mixture's sufficient statistics are moved by the changed rows only; other losses refit.
    """
    method = "mix_detect" if detector else "mix_uniform"
    pool = rows.where("is_dirty") if detector else rows
    top = pool.withColumn("_u", uniform("row_id", seed, "sample")).orderBy("_u", "row_id").limit(max(sizes))
    drawn = top.drop("_u").collect()
    cleaned = {r.row_id: r for r in cleaner.clean(local_rows(rows.sparkSession, [r.asDict() for r in drawn], top.drop("_u").schema)).collect()}
    gram = GramState.of(rows, d) if loss.name == "squared" else None
    out, done = [], 0
    for k, size in enumerate(sizes, 1):
        part = drawn[done : min(size, len(drawn))]
        fixed = [cleaned[r.row_id] for r in part if r.row_id in cleaned]
        if gram is not None:
            if part:
                gram.add(np.array([r.x for r in part]), np.array([r.y for r in part], dtype=float), -1.0)
                kept = [f for f in fixed if f.kept]
                gram.add(np.array([f.x_c for f in kept]).reshape(len(kept), d), np.array([f.y_c for f in kept], dtype=float))
            theta = gram.solve(lam)
        else:
            repairs = rows.sparkSession.createDataFrame([(r.row_id, list(f.x_c), float(f.y_c), f.kept) for r in drawn[:size] if (f := cleaned.get(r.row_id))], "row_id long, _x array<double>, _y double, _k boolean")
            mixed = rows.select("row_id", "x", "y").join(F.broadcast(repairs), "row_id", "left").where("_k is null or _k").select(F.coalesce("_x", "x").alias("x"), F.coalesce("_y", "y").alias("y"))
            theta = fit(mixed, loss, d, lam).theta
        done = min(size, len(drawn))
        out.append(_point(method, seed, k, done, theta))
    return out


def progressive(rows: DataFrame, cleaner, loss: Loss, d: int, variant: str = "progressive", **options) -> RunResult:
    """The full method and its variants by name."""
    settings = {
        "progressive": {"detector": "known", "weight": "taylor"},
        "progressive_dirty_gradient": {"detector": "known", "weight": "dirty"},
        "progressive_oracle": {"detector": "known", "weight": "oracle"},
        "progressive_nodetect": {"detector": None, "weight": "dirty"},
        "progressive_nodetect_uniform": {"detector": None, "weight": "uniform"},
        "progressive_zero_start": {"detector": "known", "weight": "dirty", "init": "zeros"},
        "progressive_classifier": {"detector": None, "weight": "taylor_class"},
    }[variant]
    if variant == "progressive_classifier":
        settings = settings | {"detector": ClassifierDetector()}
    return ProgressiveCleaner(rows, cleaner, loss, d, method=variant, **(settings | options)).run()
