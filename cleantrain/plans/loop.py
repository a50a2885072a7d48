"""The progressive loop: train on dirty rows, then draw, clean, step; anytime, restartable, with plans of constant size.

Each iteration is one pass: the weighted keys of the dirty pool, the sums that make them a distribution, and the
clean part's gradient come out of the same job (an observation beside a top-b). Only b rows, and sums of the size of
theta, reach the driver. What was cleaned is left out by an anti-join with a bounded broadcast (the budget), never by
a growing lineage.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from ..functions.losses import Loss
from ..functions.portable import uniform
from ..functions.vectors import dot
from ..operators import sampling
from ..operators.detect import ClassifierDetector
from ..operators.estimators import ChangeStats
from ..operators.gradient import GramState
from ..operators.sampling import Weight, draw_key, draw_with_replacement, estimate, estimate_part
from ..operators.train import Model, Step, fit, held_gradient, hold, penalised
from ..sources.scratch import scratch_table
from ..sources.tables import local_rows

#: Drawn ids that an anti-join may broadcast; the budget is checked against it.
MAX_BUDGET = 1_000_000
DESIGNS = ("ordered", "literal", "poisson", "bottom_k", "with_replacement")
HISTORY = "run_id string, method string, seed int, iteration int, cleaned long, n_dirty long, step double, theta array<double>"


def combine(clean_sum_mean: np.ndarray, n_clean: float, dirty_mean: np.ndarray, n_dirty: float) -> np.ndarray:
    """The whole gradient from the parts' means by the parts' sizes."""
    n = n_clean + n_dirty
    return (n_clean * clean_sum_mean + n_dirty * dirty_mean) / n if n else np.zeros_like(dirty_mean)


def update(theta: np.ndarray, gradient: np.ndarray, step: float, lam: float = 0.0) -> np.ndarray:
    return theta - step * (gradient + penalised(theta, lam))


@dataclass
class RunResult:
    theta: np.ndarray
    model: Model
    history: list[tuple] = field(default_factory=list)
    ledger: list[dict] = field(default_factory=list)

    def history_rows(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.history, HISTORY)

    def ledger_rows(self, spark: SparkSession) -> DataFrame:
        kind = "run_id string, iteration int, row_id long, draw_order int, p double, n_dirty long, pi double, kept boolean, class_id int, x array<double>, x_c array<double>, y double, y_c double, err_features array<int>"
        names = [c.split()[0] for c in kind.split(", ")]
        return spark.createDataFrame([tuple(r[c] for c in names) for r in self.ledger], kind)


class ProgressiveCleaner:
    """rows: row_id, x, y dirty (and is_dirty, err_features, class_id where a detector has run).

    detector: None (every row is a candidate), 'known' (is_dirty), or a ClassifierDetector fitted as rows are cleaned.
    weight: uniform, dirty, oracle, taylor, taylor_class, feature_change, avg_gradient, regression, uncertainty, top_uncertain.
    clean_batch: a cleaner with clean(DataFrame); it sees only drawn rows.
    predicted_clean: 'floor' leaves rows that a classifier calls clean a chance; 'trust' takes them as clean, which is
    biased where it errs. Rows that cleaning removes stay counted and have gradient 0.
    design: ordered, literal (the same draw, the printed estimator), poisson (batches of random size, empty ones too),
    bottom_k, or with_replacement (two more passes; a row drawn twice is cleaned once and counts twice).
    stored: rows are a table, or worked out of one, that can be read again at little cost, so no copy is kept.
    """

    def __init__(
        self, rows: DataFrame, cleaner, loss: Loss, d: int, *, detector=None, weight: str = "dirty", budget: int = 500, batch: int = 50, step: Callable | None = None, lam: float = 0.0, seed: int = 0, floor: float = sampling.FLOOR,
        method: str = "progressive", init: str | np.ndarray = "dirty", predicted_clean: str = "floor", design: str = "ordered", update_every: int | None = None, target: Callable | None = None, tolerance: float | None = None, on_commit: Callable | None = None, stored: bool = False,
    ):
        if design not in DESIGNS:
            raise ValueError(f"design is one of {', '.join(DESIGNS)}")
        if design not in DESIGNS[:2] and (update_every or weight == "top_uncertain"):
            raise ValueError("parts of a batch, and the nearest rows, need rows in draw order")
        if budget > MAX_BUDGET:
            raise ValueError(f"a budget above {MAX_BUDGET} needs a ledger table joined by shuffle")
        self.rows, self.cleaner, self.loss, self.d = rows, cleaner, loss, d
        self.detector, self.weight, self.budget, self.batch, self.step, self.lam, self.seed, self.floor = detector, weight, budget, batch, step or Step.inv_sqrt(0.5), lam, seed, floor
        self.method, self.init, self.predicted_clean, self.design, self.update_every = method, init, predicted_clean, design, update_every
        self.target, self.tolerance, self.on_commit, self.stored = target, tolerance, on_commit, stored

    def _weight(self, theta: np.ndarray, stats: ChangeStats, seen: dict) -> Column:
        kind, loss = self.weight, self.loss
        if kind == "uniform":
            return Weight.uniform()
        if kind == "oracle":
            return Weight.oracle(loss, theta)
        if kind == "taylor":
            return Weight.taylor(loss, theta, stats.delta())
        if kind == "taylor_class":
            return Weight.taylor_by_class(loss, theta, stats.by_class())
        if kind == "feature_change":
            return Weight.feature_change(loss, theta, stats.delta())
        if kind in ("avg_gradient", "regression") and len(seen["x"]):
            before, after = loss.np_gradients(np.array(seen["x"]), np.array(seen["y"]), theta), loss.np_gradients(np.array(seen["x_c"]), np.array(seen["y_c"]), theta)
            if kind == "avg_gradient":
                return Weight.average_gradient(loss, theta, (after - before).mean(0))
            from ..operators.estimators import fit_gradient_regression

            return Weight.gradient_regression(loss, theta, fit_gradient_regression(before, after))
        if kind in ("uncertainty", "top_uncertain"):
            return Weight.uncertainty(theta)
        return Weight.dirty_gradient(loss, theta)

    def run(self) -> RunResult:
        spark, loss, d = self.rows.sparkSession, self.loss, self.d
        columns = [c for c in ("row_id", "x", "y", "x_c", "y_c", "is_dirty", "err_features", "class_id") if c in self.rows.columns]
        matrix = self.rows.select(*columns)
        if self.stored:
            return self._run(spark, matrix, loss, d)
        matrix = matrix.persist()
        try:
            return self._run(spark, matrix, loss, d)
        finally:
            matrix.unpersist()

    def _run(self, spark: SparkSession, matrix: DataFrame, loss: Loss, d: int) -> RunResult:
        if isinstance(self.init, np.ndarray):
            theta = self.init.astype(float).copy()
        elif self.init == "zeros":
            theta = np.zeros(d)
        else:
            theta = fit(matrix if self.init == "dirty" else matrix.where("not is_dirty"), loss, d, self.lam).theta
        columns, known = matrix.columns, self.detector == "known"
        classifier = self.detector if isinstance(self.detector, ClassifierDetector) else None
        # A squared loss needs no scan for the clean part: its sufficient statistics move with the ledger.
        gram = GramState.of(matrix.where("not is_dirty"), d) if known and loss.name == "squared" else None
        # For other losses a detector's clean part, which stays as it is, is set apart: a draw reads the dirty part alone.
        apart = None
        if known and gram is None:
            apart = hold(matrix.where("is_dirty = false"), d, pack=not self.stored)
            matrix = scratch_table(matrix.where("is_dirty is null or is_dirty"))
        stats, seen = ChangeStats(d), {k: [] for k in ("x", "y", "x_c", "y_c", "class_id", "kept", "id")}
        out = RunResult(theta, Model(theta, loss))
        total_before, iteration = None, 0
        out.history.append((f"{self.method}-{self.seed}", self.method, self.seed, 0, 0, 0, 0.0, [float(v) for v in theta]))
        while len(seen["id"]) < self.budget:
            iteration += 1
            b = min(self.batch, self.budget - len(seen["id"]))
            trusted = classifier is not None and bool(classifier.classes) and self.predicted_clean == "trust"
            step = self._draw(spark, matrix, theta, stats, seen, classifier, trusted, known, gram is None and apart is None, b, total_before, iteration)
            total_before = step["total"]
            drawn, n_dirty = step["rows"], step["n_dirty"]
            if not n_dirty or (not drawn and self.design != "poisson"):
                break
            cleaned = {} if not drawn else {r["row_id"]: r for r in self.cleaner.clean(local_rows(spark, [{c: r[c] for c in columns} | {"draw_order": k} for k, r in enumerate(drawn, 1)], self._batch_schema(matrix))).collect()}
            if self.weight == "top_uncertain":
                p = np.full(len(drawn), 1.0 / n_dirty)  # no known probability: a plain average, biased
            else:
                p = np.array([r["p"] for r in drawn])
            fixed = [cleaned.get(r["row_id"]) for r in drawn]
            kept = np.array([f is not None and bool(f["kept"]) for f in fixed])
            x_c = np.array([list(f["x_c"]) if k else [0.0] * d for f, k in zip(fixed, kept, strict=True)]).reshape(-1, d)
            y_c = np.array([f["y_c"] if k else 0.0 for f, k in zip(fixed, kept, strict=True)], dtype=float)
            pi = np.array([r.get("pi") or n_dirty * q / r.get("times", 1) for r, q in zip(drawn, p, strict=True)])
            size = self.update_every or max(len(drawn), 1)
            clean_n, clean_sum = self._clean_part(step, gram, seen, theta, apart)
            for start in range(0, max(len(drawn), 1), size):
                # Several steps on one draw: each takes the mean of its own draws' terms, at the present model.
                part = slice(start, start + size)
                g = np.where(kept[part][:, None], loss.np_gradients(x_c[part], y_c[part], theta), 0.0)
                if self.weight == "top_uncertain":
                    g_s = g.mean(0)
                elif size >= len(drawn):
                    # Both kinds of draws that are given their chances take the plain sum over them.
                    g_s = estimate(g, p, n_dirty, "poisson" if self.design == "bottom_k" else self.design, times=np.array([r.get("times", 1) for r in drawn]), pi=pi)
                else:
                    end = start + len(p[part])
                    g_s = estimate_part(np.where(kept[:end, None], loss.np_gradients(x_c[:end], y_c[:end], theta), 0.0), p[:end], n_dirty, start)
                if gram is not None:
                    clean_n, clean_sum = gram.n, gram.total_gradient(theta)
                elif start:
                    clean_n, clean_sum = self._clean_part(step, gram, seen, theta, apart, again=(matrix, known, trusted, classifier))
                gamma = self.step(iteration if size >= len(drawn) else (iteration - 1) * (-(-self.batch // size)) + start // size + 1, len(p[part]))
                theta = update(theta, combine(clean_sum / max(clean_n, 1), clean_n, g_s, n_dirty), gamma, self.lam)
            self._commit(out, seen, stats, gram, drawn, fixed, kept, x_c, y_c, p, pi, n_dirty, iteration)
            if classifier is not None and seen["id"]:
                classifier.fit(np.array(seen["x"]), np.array(seen["class_id"]))
            out.history.append((f"{self.method}-{self.seed}", self.method, self.seed, iteration, len(seen["id"]), int(n_dirty), float(gamma), [float(v) for v in theta]))
            if self.on_commit:
                self.on_commit(out)
            moved = np.linalg.norm(np.array(out.history[-1][-1]) - np.array(out.history[-2][-1]))
            if (self.target and self.target(theta)) or (self.tolerance is not None and moved < self.tolerance):
                break
        out.theta, out.model = theta, Model(theta, loss)
        return out

    @staticmethod
    def _batch_schema(matrix: DataFrame):
        from pyspark.sql import types as T

        return T.StructType([*matrix.schema.fields, T.StructField("draw_order", T.IntegerType())])

    def _draw(self, spark, matrix, theta, stats, seen, classifier, trusted, known, scan_clean, b, total_before, iteration) -> dict:
        """One pass: b drawn rows with p, the pool's size, and the clean part's sums."""
        rows = matrix
        if seen["id"]:
            rows = rows.join(F.broadcast(local_rows(spark, [{"row_id": i} for i in seen["id"]], "row_id long")), "row_id", "left_anti")
        predicted = classifier is not None and bool(classifier.classes)
        if predicted:
            rows = rows.withColumn("_class", classifier.class_column())  # worked out once for all that asks for it
        clean = F.col("is_dirty") == F.lit(False) if known else ((F.col("_class") if predicted else F.lit(1)) == 0 if trusted else F.lit(False))
        weight = F.coalesce(self._weight(theta, stats, seen), F.lit(0.0))
        if predicted and not trusted:
            weight = F.when(F.col("_class") > 0, weight).otherwise(F.lit(0.0))  # only the floor is left to them
            pool = F.count_if(F.col("_class") > 0)
        else:
            pool = F.count(F.lit(1))
        if predicted and self.weight == "taylor_class":
            rows = rows.withColumn("class_id", F.col("_class"))
        rows = rows.withColumn("_clean", clean).withColumn("_w", F.when(F.col("_clean"), F.lit(0.0)).otherwise(weight))
        if total_before is None:
            total_before = rows.where("not _clean").agg(F.sum("_w").alias("s"), F.count(F.lit(1)).alias("n")).first()
            total_before = (total_before.s or 0.0, total_before.n)
        s0, n0 = total_before
        if not n0:
            return {"rows": [], "n_dirty": 0, "total": total_before}
        # Any positive scale makes the same draw; the last pass's sum is near enough for the floor's share, and the exact
        # normaliser is summed in this pass.
        share = F.lit((1 - self.floor) / s0 if s0 > 0 else 0.0)
        a = F.col("_w") * share + F.lit((self.floor if s0 > 0 else 1.0) / n0)
        rows = rows.withColumn("_a", F.when(~F.col("_clean"), a))
        metrics = [F.sum("_a").alias("a"), F.sum("_w").alias("w"), F.count("_a").alias("n"), F.count_if(F.col("_clean")).alias("nc"), pool.alias("pool")]
        if scan_clean:
            # A column of its own: inside the sums it would be worked out again for each of them.
            rows = rows.withColumn("_slope", F.when(F.col("_clean"), loss_slope(self.loss, theta)))
            metrics += [F.sum(F.col("_slope") * F.get("x", F.lit(i))).alias(f"g{i}") for i in range(self.d)]
        seenat = Observation()
        rows = rows.observe(seenat, *metrics)
        drawn = self._drawn(rows, theta, b, iteration)
        found = seenat.get
        for r in drawn:
            r["p"] = r.pop("_a") / found["a"]
        sums = np.array([found[f"g{i}"] or 0.0 for i in range(self.d)]) if scan_clean else None
        return {"rows": drawn, "n_dirty": found["n"], "total": (found["w"] or 0.0, found["n"] - len(drawn)), "clean_n": found["nc"], "clean_sum": sums}

    def _drawn(self, rows: DataFrame, theta, b: int, iteration: int) -> list[dict]:
        """The batch by the design, with pi or times where the design has them. `_a` is p on a scale that is the same for all rows."""
        pool = rows.where("_a is not null").drop("_w", "_clean", "_slope", "_class")
        if self.design == "poisson":
            pi = F.least(F.lit(1.0), b * F.col("_a"))  # the scale is known here too, so these are the exact chances
            # Ordered here: behind an exchange, a plan whose batch is empty would be cut short together with its sums.
            return sorted((r.asDict() for r in pool.withColumn("pi", pi).where(uniform("row_id", self.seed, iteration) < F.col("pi")).collect()), key=lambda r: r["row_id"])
        if self.design == "with_replacement":
            times = draw_with_replacement(pool.select("row_id", F.col("_a").alias("p")), b, self.seed, iteration).select("row_id", "times")
            held = {r.row_id: r.times for r in times.collect()}  # at most b
            # The observed sums come with this pass: the batch is picked out by its ids behind the observation.
            return sorted((r.asDict() | {"times": held[r.row_id]} for r in pool.where(F.col("row_id").isin(list(held))).collect()), key=lambda r: r["row_id"])
        order = F.abs(dot(F.col("x"), theta)) if self.weight == "top_uncertain" else draw_key(F.col("_a"), self.seed, iteration)
        top = pool.withColumn("_key", order).orderBy("_key", "row_id").limit(b + (self.design == "bottom_k"))
        drawn = [r.asDict() for r in top.collect()]
        keys = [r.pop("_key") for r in drawn]
        if self.design == "bottom_k":
            for r in drawn:
                r["pi"] = -np.expm1(-r["_a"] * keys[-1]) if len(drawn) > b else 1.0
            drawn = drawn[:b]
        return drawn

    def _clean_part(self, step, gram, seen, theta, apart=None, again=None) -> tuple[float, np.ndarray]:
        """Size and summed gradient of rows known clean: by detection, and cleaned before this batch."""
        if gram is not None:
            return gram.n, gram.total_gradient(theta)
        if apart is not None:
            total, n = held_gradient(apart, self.loss, theta)
        else:
            n, total = step["clean_n"], step["clean_sum"]
        if apart is None and again is not None and n:
            matrix, known, trusted, classifier = again
            from ..operators.gradient import total_gradient

            clean = F.col("is_dirty") == F.lit(False) if known else classifier.class_column() == 0
            ids = [i for i in seen["id"]]
            rows = matrix.where(clean)
            if ids and trusted:
                rows = rows.where(~F.col("row_id").isin(ids))
            total, n = total_gradient(rows, self.loss, theta)
        if seen["id"]:
            kept = np.array(seen["kept"], bool)
            g = self.loss.np_gradients(np.array(seen["x_c"]), np.array(seen["y_c"]), theta)
            total = total + g[kept].sum(0)
            n = n + len(seen["id"])
        return n, total

    def _commit(self, out, seen, stats, gram, drawn, fixed, kept, x_c, y_c, p, pi, n_dirty, iteration) -> None:
        if not drawn:
            return
        pi = np.maximum(pi, 1e-300)
        flags = [list(r.get("err_features") or (f["err_features"] if f is not None and "err_features" in f.asDict() else []) or []) for r, f in zip(drawn, fixed, strict=True)]
        classes = [int((f["class_id"] if f is not None and "class_id" in f.asDict() and f["class_id"] is not None else r.get("class_id")) or 0) for r, f in zip(drawn, fixed, strict=True)]
        x, y = np.array([r["x"] for r in drawn]), np.array([r["y"] for r in drawn], dtype=float)
        if kept.any():
            k = np.flatnonzero(kept)
            stats.update(x[k], x_c[k], y[k], y_c[k], [flags[i] for i in k], pi[k], [classes[i] for i in k])
        if gram is not None:
            gram.add(x_c[kept], y_c[kept])
            gram.n += int((~kept).sum())  # removed rows were visited: they count, with gradient 0
        for i, r in enumerate(drawn):
            for k, v in (("x", x[i]), ("y", y[i]), ("x_c", x_c[i]), ("y_c", y_c[i]), ("class_id", classes[i]), ("kept", bool(kept[i])), ("id", r["row_id"])):
                seen[k].append(v)
            out.ledger.append({"run_id": f"{self.method}-{self.seed}", "iteration": iteration, "row_id": r["row_id"], "draw_order": i + 1, "p": float(p[i]), "n_dirty": int(n_dirty), "pi": float(pi[i]), "kept": bool(kept[i]), "class_id": classes[i], "x": x[i].tolist(), "x_c": x_c[i].tolist(), "y": float(y[i]), "y_c": float(y_c[i]), "err_features": [int(v) for v in flags[i]]})


def loss_slope(loss: Loss, theta) -> Column:
    return loss.slope(dot(F.col("x"), theta), F.col("y"))
