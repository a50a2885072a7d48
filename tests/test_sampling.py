import numpy as np
from pyspark.sql import functions as F

from cleantrain.operators import sampling
from cleantrain.operators.sampling import estimate


def _simulate(design: str, n: int, b: int, seeds: int, estimator: str | None = None) -> tuple[np.ndarray, np.ndarray, float]:
    rng = np.random.default_rng(5)
    g = rng.lognormal(0, 1.2, size=(n, 1))
    w = g[:, 0] * rng.uniform(0.5, 1.5, n)
    p = 0.9 * w / w.sum() + 0.1 / n
    out = []
    for s in range(seeds):
        r = np.random.default_rng([6, s])
        key = -np.log(r.random(n)) / p
        order = np.argsort(key)
        if design == "ordered":
            at = order[:b]
            out.append(estimate(g[at], p[at], n, estimator or "ordered", b=b))
        elif design == "bottom_k":
            out.append(estimate(g[order[:b]], p[order[:b]], n, "bottom_k", tau=key[order[b]]))
        elif design == "poisson":
            pi = np.minimum(1, b * p)
            at = np.flatnonzero(r.random(n) < pi)
            out.append(estimate(g[at], p[at], n, "poisson", pi=pi[at]))
        else:
            at, times = np.unique(r.choice(n, size=b, p=p), return_counts=True)
            out.append(estimate(g[at], p[at], n, "with_replacement", times=times))
    out = np.array(out)[:, 0]
    return out, g, float(abs(out.mean() - g.mean()) / (out.std() / np.sqrt(seeds)))


def test_designs_are_unbiased():
    for design in ("ordered", "bottom_k", "poisson", "with_replacement"):
        assert _simulate(design, 200, 50, 2000)[2] < 4, design


def test_naive_weights_are_biased():
    assert _simulate("ordered", 200, 50, 2000, "naive")[2] > 6


def test_literal_scale_is_larger_by_the_pool():
    g, p = np.ones((10, 1)), np.full(10, 0.05)
    assert np.isclose(estimate(g, p, 20, "literal")[0], 20 * estimate(g, p, 20, "naive")[0])


def test_distribution_sums_to_one_and_keeps_the_floor(spark):
    rows = spark.range(100).select(F.col("id").alias("row_id"), F.when(F.col("id") < 50, 0.0).otherwise(F.col("id").cast("double")).alias("v"))
    p = np.array([r.p for r in sampling.distribution(rows, F.col("v")).collect()])
    assert np.isclose(p.sum(), 1) and p.min() >= 0.1 / 100 - 1e-12


def test_all_zero_weights_fall_back_to_uniform(spark):
    rows = spark.range(10).select(F.col("id").alias("row_id"))
    assert {round(r.p, 9) for r in sampling.distribution(rows, F.lit(0.0)).collect()} == {0.1}


def test_draws_do_not_depend_on_partitions_and_plans_take_ordered(spark):
    rows = spark.range(500).select(F.col("id").alias("row_id"), F.lit(1 / 500).alias("p"))
    a = {r.row_id: r.draw_order for r in sampling.draw_ordered(rows.repartition(7), 20, 1, 1).collect()}
    b = {r.row_id: r.draw_order for r in sampling.draw_ordered(rows.coalesce(1), 20, 1, 1).collect()}
    assert a == b and sorted(a.values()) == list(range(1, 21))
    plan = rows.withColumn("key", sampling.draw_key(F.col("p"), 1, 1)).orderBy("key").limit(5)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in plan


def test_pool_smaller_than_batch(spark):
    rows = spark.range(3).select(F.col("id").alias("row_id"), F.lit(1 / 3).alias("p"))
    assert sampling.draw_ordered(rows, 50, 1, 1).count() == 3


def test_bottom_k_pool_smaller_than_batch(spark):
    rows = spark.range(3).select(F.col("id").alias("row_id"), F.lit(1 / 3).alias("p"))
    assert {r.pi for r in sampling.draw_bottom_k(rows, 3, 1, 1).collect()} == {1.0}
    assert all(0 < r.pi < 1 for r in sampling.draw_bottom_k(rows, 2, 1, 1).collect())
    none = rows.where("row_id < 0")
    assert sampling.draw_bottom_k(none, 2, 1, 1).count() == sampling.draw_with_replacement(none, 2, 1, 1).count() == 0


def test_with_replacement_counts_every_draw(spark):
    rows = spark.range(200).select(F.col("id").alias("row_id"), F.lit(1 / 200).alias("p"))
    assert sampling.draw_with_replacement(rows, 64, 1, 1).agg(F.sum("times")).first()[0] == 64


def test_each_part_of_an_ordered_draw_is_unbiased():
    from cleantrain.operators.sampling import estimate_part

    rng = np.random.default_rng(5)
    values, p = rng.normal(2, 1, 40), rng.random(40) + 0.2
    p /= p.sum()
    parts = []
    for _ in range(4000):
        order = np.argsort(rng.exponential(size=40) / p)[:20]
        parts.append([estimate_part(values[order[:end], None], p[order[:end]], 40, end - 5)[0] for end in (5, 10, 15, 20)])
    parts = np.array(parts)
    assert (abs(parts.mean(0) - values.mean()) < 4 * parts.std(0) / 4000**0.5).all()


def test_systematic_corruption_fills_its_share_under_ties(spark):
    from pyspark.sql import functions as F

    from cleantrain.operators import corrupt

    rows = spark.range(3000).select(F.col("id").alias("row_id"), F.array(F.lit(1.0), (F.col("id") % 4).cast("double"), (F.col("id") % 1000).cast("double"), F.lit(7.0)).alias("x"))
    out = corrupt.systematic(rows, 4, [0.0, 3.0, 2.0, 1.0], rate=0.06).select(F.explode("err_features").alias("f")).groupBy("f").count().collect()
    assert {r.f: r["count"] for r in out} == {1: 60, 2: 60, 3: 60}


def test_rules_of_one_name_and_columns_named_like_rules(spark):
    from cleantrain.operators.detect import ConstraintDetector, Rule

    rows = spark.createDataFrame([(1, -5.0, "own"), (2, 20.0, "own"), (3, 5.0, "own")], "row_id long, a double, range_a string")
    got = {r.row_id: r for r in ConstraintDetector([Rule.range("a", low=0), Rule.range("a", high=10)]).detect(rows).collect()}
    assert [got[k].violated for k in (1, 2, 3)] == [["range_a"], ["range_a_2"], []] and all(r.range_a == "own" for r in got.values())


def test_systematic_cut_offs_are_exact_ranks(spark):
    from cleantrain.functions.portable import uniform
    from cleantrain.operators import corrupt

    n = 400_000
    rows = spark.range(n).select(F.col("id").alias("row_id"), F.array(F.lit(1.0), uniform("id", "v") * 1e6, (F.col("id") % 7).cast("double")).alias("x"))
    out = corrupt.systematic(rows, 3, [0.0, 2.0, 1.0], rate=0.06, features=2)
    taken = {r.f: r["count"] for r in out.select(F.explode("err_features").alias("f")).groupBy("f").count().collect()}
    assert taken == {1: 12_000, 2: 12_000}
    edge = out.groupBy(F.array_contains("err_features", 1).alias("hit")).agg(F.min(F.get("x", F.lit(1))).alias("lo"), F.max(F.get("x", F.lit(1))).alias("hi")).collect()
    assert next(r.lo for r in edge if r.hit) > next(r.hi for r in edge if not r.hit)


def test_exact_cuts_at_odd_values(spark):
    from cleantrain.operators.corrupt import exact_cuts

    values = [None, float("nan"), float("inf"), float("inf"), float("-inf"), 1e308, -1e308, 5e-324, 0.0, -0.0, 2.0, 2.0]
    rows = spark.createDataFrame([(v,) for v in values], "v double")
    order = sorted((v for v in values if v is not None and v == v), reverse=True)
    for k in range(1, 13):
        cut = order[min(k, len(order)) - 1]
        assert exact_cuts(rows, {"v": F.col("v")}, {"v": k}, True) == {"v": (cut, sum(v > cut for v in order))}
        cut = order[::-1][min(k, len(order)) - 1]
        assert exact_cuts(rows, {"v": F.col("v")}, {"v": k}, False) == {"v": (cut, sum(v < cut for v in order))}
    assert exact_cuts(rows, {"v": F.col("v")}, {"v": 0}, True) == {}
    assert exact_cuts(rows.where("v > 3 and v < 4"), {"v": F.col("v")}, {"v": 2}, True) == {}
