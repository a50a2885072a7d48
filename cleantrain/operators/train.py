"""Training to completion: exact solves where there are any, full-batch methods else. Parameters live on the driver."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.losses import Loss
from ..functions.vectors import dot
from ..sources.scratch import scratch_table
from .gradient import GramState, total_gradient


#: Rows times features up to which a Newton fit runs on the driver (160 MB); beyond, its passes are distributed.
LOCAL_CELLS = 20_000_000
#: Bytes of one block of a packed matrix, and of a row group of its file, which bounds what a task holds at once.
PACKED_BYTES, ROW_GROUP = 1 << 16, 8 << 20
#: Rows that a pass works on at once.
NEAR_ROWS = 4096
#: Cells of the rows near a hinge's corner that the driver holds, of those that a start is fitted to, and the last hinge's width.
CORNER_CELLS, START_CELLS, WIDTH = 8_000_000, 4_000_000, 0.003
#: A gradient below which a fit by the rows near the corner counts as ended.
ENDED = 1e-7


class Step:
    """Step sizes by iteration t = 1, 2, ... and batch size."""

    @staticmethod
    def constant(g: float) -> Callable[[int, int], float]:
        return lambda t, b: g

    @staticmethod
    def shrinking_batch(g: float = 0.1) -> Callable[[int, int], float]:
        """g / (b t): the published schedule, meant for summed gradients."""
        return lambda t, b: g / (b * t)

    @staticmethod
    def inv_t(g: float) -> Callable[[int, int], float]:
        return lambda t, b: g / t

    @staticmethod
    def inv_sqrt(g: float) -> Callable[[int, int], float]:
        return lambda t, b: g / math.sqrt(t)


def penalised(theta: np.ndarray, lam: float) -> np.ndarray:
    """The regulariser's gradient, added once a step; the intercept bears none."""
    out = lam * theta
    out[0] = 0.0
    return out


@dataclass
class Model:
    theta: np.ndarray
    loss: Loss
    gradient_norm: float = 0.0  # of the mean objective at theta: how tight the fit is

    def score(self, x: str | Column = "x") -> Column:
        return dot(F.col(x) if isinstance(x, str) else x, self.theta)

    def predict(self, x: str | Column = "x", threshold: float = 0.0, low: float = -1.0) -> Column:
        """1 from the threshold on, else `low` (-1 or 0)."""
        return F.when(self.score(x) >= threshold, F.lit(1.0)).otherwise(F.lit(low))

    def rows(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(i, float(v)) for i, v in enumerate(self.theta)], "component int, weight double")


def fit(rows: DataFrame, loss: Loss, d: int, lam: float = 0.0, x: str = "x", y: str = "y", steps: int = 60, tolerance: float = 1e-8) -> Model:
    """squared: normal equations, one pass. mean, absolute: exact aggregates. logistic: Newton. hinge: Newton on ever
    less smoothed hinges, whose last gradient is reported. Others: gradient descent with halving steps. Each pass returns a bounded sum to the driver."""
    rows = rows.select(F.col(x).alias("x"), F.col(y).cast("double").alias("y"))
    if loss.name == "squared":
        gram = GramState.of(rows, d)
        theta = gram.solve(lam)
        return Model(theta, loss, float(np.linalg.norm(gram.total_gradient(theta) / max(gram.n, 1) + penalised(theta, lam))))
    if loss.name in ("mean", "absolute"):
        value = rows.agg((F.avg("y") if loss.name == "mean" else F.expr("percentile(y, 0.5)")).alias("v")).first().v
        return Model(np.array([value if value is not None else 0.0]), loss)
    if loss.name != "hinge" and loss.curvature is None:
        theta = gradient_descent(rows.persist(), loss, np.zeros(d), Step.inv_sqrt(1.0), steps, lam)
        rows.unpersist()
        return Model(theta, loss)
    n, theta = rows.count(), np.zeros(d)
    if n * d > LOCAL_CELLS:
        start = _arrays(rows.where(F.monotonically_increasing_id() % (1 + n * d // START_CELLS) == 0), d)
        if loss.name == "hinge" and (found := _corner_fit(rows, n, d, lam, tolerance, start)) is not None:
            return Model(found[0], loss, found[1])
    if loss.name == "hinge":
        held, theta, slope = hold(rows, d, n=n), np.zeros(d), _smooth_hinge(WIDTH)[0]
        theta = _narrowing(held, theta, lam, tolerance)
    else:
        curves, slope = (loss.np_slope, loss.curvature, loss.np_value), loss.np_slope
        if n * d > LOCAL_CELLS:
            # Few passes are left from the optimum of some rows, so they read the rows where they are.
            held, theta = rows, _newton(start, *curves, theta, lam, min(steps, 25), tolerance)
        else:
            held = _arrays(rows, d)
        theta = _newton(held, *curves, theta, lam, min(steps, 25), tolerance)
    g, _, n, _ = _sums(held, slope, lambda z, y: 0 * z, theta)
    return Model(theta, loss, float(np.linalg.norm(g / max(n, 1) + penalised(theta, lam))))


def _narrowing(held: DataFrame | tuple, theta: np.ndarray, lam: float, tolerance: float) -> np.ndarray:
    """The wider hinges only lead to the last one, so they are solved roughly."""
    for width in (1.0, 0.3, 0.1, 0.03, 0.01, WIDTH):
        theta = _newton(held, *_smooth_hinge(width), theta, lam, 20, tolerance if width == WIDTH else 1e-3)
    return theta


def _corner_fit(rows: DataFrame, n: int, d: int, lam: float, tolerance: float, start: tuple) -> tuple[np.ndarray, float] | None:
    """The optimum over all rows and its gradient's norm, in few passes; None if it is not reached.

    A hinge bends only at its corner: while theta stays within `reach` of a point, rows too far from the corner for that
    add a linear term, whose sums one pass over all rows brings, and the others come to the driver. The optimum of the
    sum is that of all rows if it lies within reach; else the next pass starts there. Where passes begin, at the optimum
    of every m-th row, changes their number, not what they end at.
    """
    hinge, theta = _smooth_hinge(WIDTH), _narrowing(start, np.zeros(d), lam, tolerance)
    scale = np.sqrt((start[0] ** 2).mean(0)) if len(start[1]) else np.ones(d)
    scale = np.where(scale > 0, scale, 1.0)

    def gap(x: np.ndarray, y: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Margins, and how far theta may move, in units of scale, before a row gets to the corner."""
        m = y * (x @ at)
        return m, np.maximum(np.maximum(m - 1, 1 - WIDTH - m), 0) / np.maximum(np.sqrt(((x / scale) ** 2).sum(1)), 1e-300)

    for _ in range(8):
        share = 0.8 * CORNER_CELLS / (n * d)
        gaps = np.sort(gap(*start, theta)[1]) if share < 1 else np.zeros(0)
        reach = float(gaps[int(share * len(gaps))]) if len(gaps) else np.inf
        at = theta

        def parted(batches: Iterator[pa.RecordBatch], at=at, reach=reach) -> Iterator[pa.RecordBatch]:
            far, count = np.zeros(d + 1), 0
            for batch in batches:
                xs, ys, near = _cells(batch.column(0), d), batch.column(1).to_numpy(zero_copy_only=False), []
                for k in range(0, len(ys), NEAR_ROWS):
                    x, y = xs[k : k + NEAR_ROWS], ys[k : k + NEAR_ROWS]
                    m, far_off = gap(x, y, at)
                    on = (far_off > reach) & (m < 1)
                    far[:d] -= y[on] @ x[on]
                    far[d] += on.sum() * (1 - WIDTH / 2)
                    # Written so that a row with a NaN is near.
                    here = ~(far_off > reach)
                    count += int((~here).sum())
                    near.append((x[here], y[here]))
                if near:
                    yield pa.RecordBatch.from_arrays([pa.array([np.concatenate([v[i] for v in near]).tobytes()], pa.binary()) for i in (0, 1)] + [pa.array([None], pa.binary()), pa.array([0], pa.int64())], ["x", "y", "far", "n"])
            yield pa.RecordBatch.from_arrays([pa.array([None], pa.binary()), pa.array([None], pa.binary()), pa.array([far.tobytes()], pa.binary()), pa.array([count], pa.int64())], ["x", "y", "far", "n"])

        got = rows.select("x", "y").mapInArrow(parted, "x binary, y binary, far binary, n long").toArrow().to_pydict()
        far = sum((np.frombuffer(v) for v in got["far"] if v is not None), np.zeros(d + 1))
        x, y = (np.frombuffer(b"".join(v for v in got[c] if v is not None)) for c in ("x", "y"))
        held = (x.reshape(-1, d), y, (far[:d], far[d], sum(got["n"])))
        theta = _newton(held, *hinge, at, lam, 40, tolerance)
        away = float(np.linalg.norm(scale * (theta - at)))
        if away <= reach:
            g, _, whole, _ = _sums(held, hinge[0], hinge[1], theta)
            norm = float(np.linalg.norm(g / max(whole, 1) + penalised(theta, lam)))
            if norm < ENDED:
                return theta, norm
        else:
            theta = at + (theta - at) * min(1.0, 4 * reach / away)
    return None


def _cells(column: pa.Array, d: int) -> np.ndarray:
    """A column of packed blocks, or of rows' arrays, as a matrix."""
    return _unpacked(column).reshape(-1, d) if pa.types.is_binary(column.type) else column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), d)


def hold(rows: DataFrame, d: int, n: int | None = None, pack: bool = True) -> DataFrame | tuple:
    """x and y for many passes: arrays on the driver up to LOCAL_CELLS, packed blocks in the shared folder beyond (or the rows where they are, unless pack)."""
    rows = rows.select("x", F.col("y").cast("double").alias("y"))
    if (rows.count() if n is None else n) * d > LOCAL_CELLS:
        return _packed(rows, d) if pack else rows
    return _arrays(rows, d)


def _arrays(rows: DataFrame, d: int) -> tuple[np.ndarray, np.ndarray]:
    table = rows.select("x", F.col("y").cast("double").alias("y")).toArrow()
    n = table.num_rows
    return (table.column("x").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(n, d) if n else np.zeros((0, d))), table.column("y").to_numpy()


def held_gradient(held: DataFrame | tuple, loss: Loss, theta: np.ndarray) -> tuple[np.ndarray, int]:
    """The summed gradient of a held matrix and its number of rows."""
    g, _, n, _ = _sums(held, loss.np_slope, lambda z, y: 0 * z, theta)
    return g, n


def _packed(rows: DataFrame, d: int) -> DataFrame:
    """The matrix written down once as blocks of float64 bytes of about PACKED_BYTES, which later passes read without touching cells."""
    size = max(1, PACKED_BYTES // (8 * d))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, d), batch.column(1).to_numpy(zero_copy_only=False)
            starts = range(0, batch.num_rows, size)
            yield pa.RecordBatch.from_arrays([pa.array([v[k : k + size].tobytes() for k in starts], pa.binary()) for v in (x, y)], ["x", "y"])

    return scratch_table(rows.select("x", "y").mapInArrow(pack, "x binary, y binary"), ROW_GROUP)


def _unpacked(column: pa.BinaryArray) -> np.ndarray:
    """All numbers of a column of packed blocks, without a copy."""
    _, offsets, data = column.buffers()
    ends = np.frombuffer(offsets, np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(data, np.float64, (ends[-1] - ends[0]) // 8, ends[0]) if data is not None and ends[-1] > ends[0] else np.zeros(0)


def _smooth_hinge(width: float):
    """Slope, curvature and value of the hinge with its corner rounded over a margin of `width`."""
    slope = lambda z, y: -y * np.clip((1 - y * z) / width, 0.0, 1.0)
    curve = lambda z, y: np.where((y * z < 1) & (y * z > 1 - width), 1 / width, 0.0)

    def value(z, y):
        m = 1 - y * z
        return np.where(m <= 0, 0.0, np.where(m < width, m * m / (2 * width), m - width / 2))

    return slope, curve, value


def _newton(rows: DataFrame | tuple, np_slope, np_curve, np_value, theta: np.ndarray, lam: float, steps: int, tolerance: float) -> np.ndarray:
    """Newton steps with step halving. rows: packed blocks, or arrays (x, y) on the driver. A pass that tries a step also
    brings the sums at its full length, so a step costs one pass, and another only where a shorter one is taken."""
    d, tries = len(theta), 0.25 ** np.arange(6)
    g, h, n, _ = _sums(rows, np_slope, np_curve, theta)
    for _ in range(steps):
        if not n:
            return theta
        g, h = g / n + penalised(theta, lam), h / n + max(lam, 1e-6) * np.eye(d)
        if np.linalg.norm(g) < tolerance:
            break
        move = np.linalg.solve(h, g)
        thetas = np.stack([theta] + [theta - t * move for t in tries])
        g, h, _, values = _sums(rows, np_slope, np_curve, thetas[1], np_value, thetas)
        values = values / n + lam / 2 * (thetas[:, 1:] ** 2).sum(1)
        if values[1:].min() >= values[0]:
            break
        best = 1 + int(np.argmin(values[1:]))
        theta = thetas[best]
        if best > 1:
            g, h, _, _ = _sums(rows, np_slope, np_curve, theta)
    return theta


def _sums(rows: DataFrame | tuple, np_slope, np_curve, theta: np.ndarray, np_value=None, thetas: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, int, np.ndarray]:
    """Gradient, curvature and number of rows at theta, and the summed loss at each of thetas, in one pass.

    rows: packed blocks, rows with arrays, or arrays on the driver, with the sums (gradient, loss at 0, number) of rows whose loss is linear.
    """
    thetas = np.zeros((0, len(theta))) if thetas is None else thetas

    def of(x: np.ndarray, y: np.ndarray) -> tuple:
        g, h, values = np.zeros(len(theta)), np.zeros((len(theta), len(theta))), np.zeros(len(thetas))
        for k in range(0, len(y), NEAR_ROWS):  # a part at a time stays near the processor
            part, target = x[k : k + NEAR_ROWS], y[k : k + NEAR_ROWS]
            z = part @ theta
            g += np_slope(z, target) @ part
            curve = np_curve(z, target)
            on = np.flatnonzero(curve)  # rows off a hinge's corner have none
            held = part[on] if len(on) < len(part) else part
            h += (held * curve[on][:, None]).T @ held
            if len(thetas):
                values += np_value(part @ thetas.T, target[:, None]).sum(0)
        return g, h, len(y), values

    if isinstance(rows, tuple):
        g, h, n, values = of(*rows[:2])
        if len(rows) > 2:
            far, base, count = rows[2]
            g, n, values = g + far, n + count, values + base + thetas @ far
        return g, h, n, values
    d = len(theta)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(d * (d + 1) + len(thetas)), 0
        for batch in batches:
            y = _unpacked(batch.column(1)) if pa.types.is_binary(batch.column(1).type) else batch.column(1).to_numpy(zero_copy_only=False)
            g, h, k, values = of(_cells(batch.column(0), d), y)
            total, n = total + np.concatenate([g, h.ravel(), values]), n + k
        yield pa.RecordBatch.from_arrays([pa.array([total.tobytes()], pa.binary()), pa.array([n], pa.int64())], ["sums", "n"])

    total, n = np.zeros(d * (d + 1) + len(thetas)), 0
    for r in rows.mapInArrow(partial, "sums binary, n long").collect():  # one row a task
        total, n = total + np.frombuffer(r.sums), n + r.n
    return total[:d], total[d : d * (d + 1)].reshape(d, d), n, total[d * (d + 1) :]


def gradient_descent(rows: DataFrame, loss: Loss, theta: np.ndarray, step, steps: int, lam: float = 0.0, x: str = "x", y: str = "y") -> np.ndarray:
    """Full-batch (sub)gradient steps from theta."""
    for t in range(1, steps + 1):
        g, n = total_gradient(rows, loss, theta, x, y)
        if not n:
            break
        theta = theta - step(t, n) * (g / n + penalised(theta, lam))
    return theta


def fit_one_vs_all(rows: DataFrame, loss: Loss, d: int, classes: list, label: str, lam: float = 1e-3, x: str = "x") -> np.ndarray:
    """A row of parameters for each class."""
    low = 0.0 if loss.name == "logistic" else -1.0
    return np.stack([fit(rows.select(F.col(x).alias("x"), F.when(F.col(label) == c, 1.0).otherwise(low).alias("y")), loss, d, lam).theta for c in classes])


def predict_class(thetas: np.ndarray, classes: list, x: str = "x") -> Column:
    """The class of the highest score; ties go to the class listed first."""
    scores = F.array(*[dot(F.col(x), t) for t in thetas])
    return F.element_at(F.array(*[F.lit(c) for c in classes]), F.array_position(scores, F.array_max(scores)).cast("int"))


def aggregate_query(rows: DataFrame, kind: str, column: str, where: Column | None = None) -> DataFrame:
    """value and n of SUM, AVG or MEDIAN seen as losses; rows that fail the predicate have zero loss."""
    held = F.lit(True) if where is None else F.coalesce(where, F.lit(False))
    v = F.when(held, F.col(column).cast("double"))
    n = F.count(v).alias("n")
    value = {"avg": F.avg(v), "sum": F.avg(v) * F.count(v), "median": F.percentile(v, F.lit(0.5))}[kind]
    return rows.agg(value.alias("value"), n)
