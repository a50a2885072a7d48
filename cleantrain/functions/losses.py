"""Convex losses of a linear score z = theta . x, each as column expressions and as numpy, tested against each other.

A gradient is slope(z, y) * x. The first-order expansion of the clean gradient around a dirty row, with the expected
changes dx and dy (clean minus dirty), is alpha * x + beta * dx, where s = theta . dx; no matrix is ever formed, and
its norm needs only the scalars |x|^2, x . dx and |dx|^2.
AVG and MEDIAN are losses of a single parameter with x = [1] and y the value.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .vectors import dot, squared_norm


@dataclass(frozen=True)
class Loss:
    """slope, value: of (z, y); expansion: of (z, y, s, dy), the pair (alpha, beta). `np_` twins take arrays.

    A loss that is not convex may be given; only a local optimum can then be promised.
    """

    name: str
    slope: Callable
    value: Callable
    expansion: Callable
    np_slope: Callable
    np_value: Callable
    np_expansion: Callable
    curvature: Callable | None = None
    convex: bool = True

    def gradient(self, x: Column, y: Column, theta) -> Column:
        s = self.slope(dot(x, theta), y)
        return F.transform(x, lambda v: v * s)

    def gradient_norm(self, x: Column, y: Column, theta, norm: Column | None = None) -> Column:
        """|slope| * |x|; `norm` is a stored |x|."""
        return F.abs(self.slope(dot(x, theta), y)) * (F.sqrt(squared_norm(x, len(theta))) if norm is None else norm)

    def np_gradients(self, x: np.ndarray, y: np.ndarray, theta: np.ndarray) -> np.ndarray:
        return self.np_slope(x @ theta, y)[:, None] * x

    def correction(self, x: Column, y: Column, theta, dx: Column, dy: Column) -> Column:
        """alpha * x + beta * dx as an array."""
        d = len(theta)
        alpha, beta = self.expansion(dot(x, theta), y, dot(dx, theta), dy)
        return F.array(*[alpha * F.get(x, F.lit(i)) + beta * F.get(dx, F.lit(i)) for i in range(d)])

    def corrected_norm(self, x: Column, y: Column, theta, dx: Column, dy: Column) -> Column:
        d = len(theta)
        alpha, beta = self.expansion(dot(x, theta), y, dot(dx, theta), dy)
        cross = sum((F.get(x, F.lit(i)) * F.get(dx, F.lit(i)) for i in range(1, d)), F.get(x, F.lit(0)) * F.get(dx, F.lit(0)))
        return F.sqrt(F.greatest(alpha * alpha * squared_norm(x, d) + 2 * alpha * beta * cross + beta * beta * squared_norm(dx, d), F.lit(0.0)))

    def norm_of_parts(self, x: Column, y: Column, theta, s: Column, cross: Column, square: Column, dy: Column) -> Column:
        """The same norm where theta . dx, x . dx and |dx|^2 are at hand."""
        alpha, beta = self.expansion(dot(x, theta), y, s, dy)
        return F.sqrt(F.greatest(alpha * alpha * squared_norm(x, len(theta)) + 2 * alpha * beta * cross + beta * beta * square, F.lit(0.0)))

    def np_corrections(self, x, y, theta, dx, dy) -> np.ndarray:
        alpha, beta = self.np_expansion(x @ theta, y, dx @ theta, dy)
        return np.asarray(alpha)[:, None] * x + np.asarray(beta)[:, None] * dx


def _logistic(z):
    return 1 / (1 + F.exp(-z))


def _np_logistic(z):
    return 1 / (1 + np.exp(-np.clip(z, -700, 700)))


def squared() -> Loss:
    """Half the squared residual."""
    expand = lambda z, y, s, dy: (z - y + s - dy, z - y)
    return Loss("squared", lambda z, y: z - y, lambda z, y: 0.5 * (z - y) * (z - y), expand, lambda z, y: z - y, lambda z, y: 0.5 * (z - y) ** 2, expand, lambda z, y: np.ones_like(z))


def logistic() -> Loss:
    """Labels 0 and 1."""

    def expand(z, y, s, dy):
        h = _logistic(z)
        return h - y + h * (1 - h) * s - dy, h - y

    def np_expand(z, y, s, dy):
        h = _np_logistic(z)
        return h - y + h * (1 - h) * s - dy, h - y

    value = lambda z, y: F.greatest(z, F.lit(0.0)) - z * y + F.log1p(F.exp(-F.abs(z)))
    return Loss("logistic", lambda z, y: _logistic(z) - y, value, expand, lambda z, y: _np_logistic(z) - y, lambda z, y: np.logaddexp(0, z) - z * y, np_expand, lambda z, y: _np_logistic(z) * (1 - _np_logistic(z)))


def hinge() -> Loss:
    """Labels -1 and 1; a margin of exactly 1 is active."""
    on = lambda z, y, v: F.when(y * z <= 1, v).otherwise(F.lit(0.0))
    return Loss(
        "hinge",
        lambda z, y: on(z, y, -y),
        lambda z, y: F.greatest(F.lit(0.0), 1 - y * z),
        lambda z, y, s, dy: (on(z, y, -y - dy), on(z, y, -y)),
        lambda z, y: np.where(y * z <= 1, -y, 0.0),
        lambda z, y: np.maximum(0.0, 1 - y * z),
        lambda z, y, s, dy: (np.where(y * z <= 1, -y - dy, 0.0), np.where(y * z <= 1, -y, 0.0)),
    )


def mean() -> Loss:
    """(value - theta)^2, the whole square: the gradient is -2 (value - theta)."""
    zero = lambda z: z * 0.0
    expand = lambda z, y, s, dy: (2 * (z - y) - 2 * dy, zero(z))
    return Loss("mean", lambda z, y: 2 * (z - y), lambda z, y: (z - y) * (z - y), expand, lambda z, y: 2 * (z - y), lambda z, y: (z - y) ** 2, expand, lambda z, y: 2 * np.ones_like(z))


def absolute() -> Loss:
    """|value - theta|: its optimum is the median, its derivative's change is 0 almost everywhere."""
    return Loss(
        "absolute",
        lambda z, y: F.signum(z - y),
        lambda z, y: F.abs(z - y),
        lambda z, y, s, dy: (F.signum(z - y), z * 0.0),
        lambda z, y: np.sign(z - y),
        lambda z, y: np.abs(z - y),
        lambda z, y, s, dy: (np.sign(z - y), np.zeros_like(z)),
    )


def custom(name: str, slope, value, np_slope, np_value, expansion=None, np_expansion=None, convex: bool = True) -> Loss:
    """A user's loss; without an expansion the dirty gradient itself is used for weights."""
    import warnings

    if not convex:
        warnings.warn(f"{name} is not convex: only a local optimum is sought", stacklevel=2)
    plain = lambda f: lambda z, y, s, dy: (f(z, y), f(z, y) * 0.0)
    return Loss(name, slope, value, expansion or plain(slope), np_slope, np_value, np_expansion or plain(np_slope), convex=convex)


LOSSES = {f.__name__: f for f in (squared, logistic, hinge, mean, absolute)}
