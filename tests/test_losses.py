import numpy as np
import pytest
from pyspark.sql import functions as F

from cleantrain.functions import losses
from cleantrain.operators.gradient import GramState, mean_gradient, total_gradient

NAMES = ["squared", "logistic", "hinge"]


@pytest.mark.parametrize("name", NAMES)
def test_gradient_is_the_derivative(name):
    rng, loss = np.random.default_rng(1), losses.LOSSES[name]()
    x, theta = rng.normal(size=(20, 4)), rng.normal(size=4)
    y = np.where(rng.random(20) < 0.5, 1.0, 0.0 if name == "logistic" else -1.0)
    g, e = loss.np_gradients(x, y, theta), 1e-6
    for i in range(4):
        step = np.eye(4)[i] * e
        numeric = (loss.np_value(x @ (theta + step), y) - loss.np_value(x @ (theta - step), y)) / (2 * e)
        assert np.allclose(g[:, i], numeric, atol=1e-5)


@pytest.mark.parametrize("name", NAMES)
def test_expansion_is_first_order(name):
    rng, loss = np.random.default_rng(2), losses.LOSSES[name]()
    x, theta = rng.normal(size=(30, 4)), rng.normal(size=4)
    y = np.where(rng.random(30) < 0.5, 1.0, 0.0 if name == "logistic" else -1.0)
    dx, dy, e = rng.normal(size=(30, 4)), rng.normal(size=30), 1e-6
    if name == "hinge":
        dy = np.zeros(30)
    got = loss.np_corrections(x, y, theta, e * dx, e * dy) - loss.np_gradients(x, y, theta)
    true = loss.np_gradients(x + e * dx, y + e * dy, theta) - loss.np_gradients(x, y, theta)
    assert np.allclose(got / e, true / e, atol=1e-4)


def test_margin_of_one_is_active():
    loss = losses.hinge()
    assert loss.np_slope(np.array([1.0]), np.array([1.0]))[0] == -1.0


@pytest.mark.parametrize("name", [*NAMES, "mean", "absolute"])
def test_columns_equal_arrays(spark, name):
    rng, loss = np.random.default_rng(3), losses.LOSSES[name]()
    x, y, theta = rng.normal(size=(50, 3)), np.where(rng.random(50) < 0.5, 1.0, 0.0 if name == "logistic" else -1.0), np.array([0.3, -0.2, 0.5])
    dx = rng.normal(size=(50, 3))
    rows = spark.createDataFrame([(a.tolist(), float(b), c.tolist()) for a, b, c in zip(x, y, dx, strict=True)], "x array<double>, y double, dx array<double>")
    got = rows.select(loss.gradient(F.col("x"), F.col("y"), theta).alias("g"), loss.correction(F.col("x"), F.col("y"), theta, F.col("dx"), F.lit(0.1)).alias("c"), loss.corrected_norm(F.col("x"), F.col("y"), theta, F.col("dx"), F.lit(0.1)).alias("n")).collect()
    corrected = loss.np_corrections(x, y, theta, dx, np.full(50, 0.1))
    assert np.allclose([r.g for r in got], loss.np_gradients(x, y, theta), atol=1e-9)
    assert np.allclose([r.c for r in got], corrected, atol=1e-9)
    assert np.allclose([r.n for r in got], np.linalg.norm(corrected, axis=1), atol=1e-7)


def test_wide_kernel_and_gram(spark):
    rng = np.random.default_rng(4)
    x, y = rng.normal(size=(40, 60)), rng.normal(size=40)
    rows = spark.createDataFrame([(a.tolist(), float(b)) for a, b in zip(x, y, strict=True)], "x array<double>, y double").repartition(3)
    theta, loss = rng.normal(size=60), losses.squared()
    true = loss.np_gradients(x, y, theta).sum(0)
    g, n = total_gradient(rows, loss, theta)
    state = GramState.of(rows, 60)
    assert n == 40 == state.n and np.allclose(g, true) and np.allclose(state.total_gradient(theta), true)
    state.add(x[:5], y[:5], -1.0)
    assert np.allclose(state.total_gradient(theta), loss.np_gradients(x[5:], y[5:], theta).sum(0))


def test_empty_part_has_zero_gradient(spark):
    rows = spark.createDataFrame([], "x array<double>, y double")
    assert total_gradient(rows, losses.squared(), [1.0, 2.0])[1] == 0
    assert [r.gradient for r in mean_gradient(rows, losses.squared(), [1.0, 2.0]).collect()] in ([], [0.0, 0.0])
