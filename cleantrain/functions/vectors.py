"""Array arithmetic as column expressions.

Products with a parameter vector are unrolled over its positions, and the vector is one literal object, so the
generated code is the same from one iteration to the next and is compiled once.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def vector(values) -> Column:
    return F.array(*[F.lit(float(v)) for v in values])


def add_all(columns: list[Column]) -> Column:
    return reduce(lambda a, b: a + b, columns)


def dot(x: Column, theta, start: int = 0) -> Column:
    """x . theta for a numeric theta of known length."""
    theta = np.asarray(theta, dtype=float)
    t = vector(theta)
    return add_all([F.get(x, F.lit(start + i)) * F.get(t, F.lit(i)) for i in range(len(theta))])


def dot_arrays(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


def squared_norm(x: Column, d: int) -> Column:
    return add_all([F.get(x, F.lit(i)) * F.get(x, F.lit(i)) for i in range(d)])


def masked(delta, features: Column) -> Column:
    """delta with zeros where the position is not in the array of features."""
    return F.array(*[F.when(F.array_contains(features, i), F.lit(float(v))).otherwise(F.lit(0.0)) for i, v in enumerate(delta)])


def weighted_jaccard(a: Column, b: Column) -> Column:
    """Sum of minima over sum of maxima of two maps of token weights; two empty maps are equal."""
    keys = F.array_union(F.map_keys(a), F.map_keys(b))
    of = lambda m, k: F.coalesce(F.try_element_at(m, k), F.lit(0.0))
    low = F.aggregate(keys, F.lit(0.0), lambda s, k: s + F.least(of(a, k), of(b, k)))
    high = F.aggregate(keys, F.lit(0.0), lambda s, k: s + F.greatest(of(a, k), of(b, k)))
    return F.when(high == 0, F.lit(1.0)).otherwise(low / high)


def register(spark: SparkSession) -> None:
    """SQL functions dot, l2norm, squared_grad, logistic_grad, hinge_grad and weighted_jaccard, as JVM expressions."""
    fold = "aggregate(zip_with({0}, {1}, (p, q) -> p * q), 0d, (s, v) -> s + v)"
    scaled = "transform(x, v -> v * ({}))"
    z = fold.format("x", "t")
    for signature, kind, body in (
        ("dot(a array<double>, b array<double>)", "double", fold.format("a", "b")),
        ("l2norm(a array<double>)", "double", f"sqrt({fold.format('a', 'a')})"),
        ("squared_grad(x array<double>, y double, t array<double>)", "array<double>", scaled.format(f"{z} - y")),
        ("logistic_grad(x array<double>, y double, t array<double>)", "array<double>", scaled.format(f"1 / (1 + exp(-{z})) - y")),
        ("hinge_grad(x array<double>, y double, t array<double>)", "array<double>", scaled.format(f"if(y * {z} <= 1, -y, 0d)")),
        (
            "weighted_jaccard(a map<string, double>, b map<string, double>)",
            "double",
            "coalesce(aggregate(array_union(map_keys(a), map_keys(b)), 0d, (s, k) -> s + least(coalesce(try_element_at(a, k), 0d), coalesce(try_element_at(b, k), 0d)))"
            " / nullif(aggregate(array_union(map_keys(a), map_keys(b)), 0d, (s, k) -> s + greatest(coalesce(try_element_at(a, k), 0d), coalesce(try_element_at(b, k), 0d))), 0d), 1d)",
        ),
    ):
        spark.sql(f"create or replace temporary function {signature} returns {kind} return {body}")
