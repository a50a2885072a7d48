import numpy as np
import pytest
from pyspark.sql import functions as F


@pytest.fixture(scope="module")
def matrix(spark):
    rng = np.random.default_rng(5)
    x = np.column_stack([np.ones(6000), rng.normal(size=(6000, 4))])
    y = np.where(x @ np.array([0.2, 1.5, -1.0, 0.5, 0.0]) + rng.normal(size=6000) > 0, 1.0, -1.0)
    rows = spark.createDataFrame([(v.tolist(), float(t)) for v, t in zip(x, y, strict=True)], "x array<double>, y double").repartition(5).persist()
    yield rows, x, y
    rows.unpersist()


@pytest.mark.parametrize("sorted_", [False, True])
def test_a_fit_by_the_rows_near_the_corner_ends_where_one_by_all_rows_does(spark, matrix, monkeypatch, sorted_):
    """F1 to F7: the passes over all rows are few, also where the start is poor, and no matrix is written."""
    from cleantrain.functions import losses
    from cleantrain.operators import train

    rows, x, y = matrix
    whole = train.fit(rows, losses.hinge(), 5, 0.01)
    written, passes = [], []
    pack, to_arrow = train._packed, type(rows).mapInArrow
    monkeypatch.setattr(train, "_packed", lambda *a: written.append(1) or pack(*a))
    monkeypatch.setattr(type(rows), "mapInArrow", lambda self, *a, **b: passes.append(1) or to_arrow(self, *a, **b))
    for name, cells in (("LOCAL_CELLS", 0), ("CORNER_CELLS", 12_000), ("START_CELLS", 300 if sorted_ else 3_000)):
        monkeypatch.setattr(train, name, cells)
    found = train.fit(rows.orderBy("y") if sorted_ else rows, losses.hinge(), 5, 0.01)
    assert np.allclose(found.theta, whole.theta, atol=1e-6) and found.gradient_norm < 1e-7
    assert not written and len(passes) <= 8
    g = train._smooth_hinge(train.WIDTH)[0](x @ found.theta, y) @ x / len(y) + train.penalised(found.theta, 0.01)
    assert np.linalg.norm(g) < 1e-7  # over all rows, the far ones too
    as01 = rows.withColumn("y", F.greatest("y", F.lit(0.0)))
    assert np.allclose(train.fit(as01, losses.logistic(), 5, 0.01).theta, _local(monkeypatch, train, as01, losses.logistic()), atol=1e-7)


def _local(monkeypatch, train, rows, loss):
    monkeypatch.setattr(train, "LOCAL_CELLS", 10**9)
    return train.fit(rows, loss, 5, 0.01).theta


def test_which_corruption_covers_both_data_sets(spark, small):
    """w01 returned after its first data set."""
    from cleantrain.plans.experiments import w01_which_corruption

    rows = w01_which_corruption(spark, small).collect()
    assert {r.data for r in rows} == {f"{k}/{c}" for k in ("income", "seizure") for c in ("random", "systematic")} and len(rows) == 24


def test_runs_on_stored_rows_write_their_dirty_part_alone(spark, small, monkeypatch):
    """the corrupted matrix, and its clean part for each run, were written down beside the table they come from."""
    from cleantrain.operators import corrupt, train
    from cleantrain.plans import experiments, fixtures, loop

    table = fixtures.covariates(spark, small)
    written, packed = [], []
    monkeypatch.setattr(train, "LOCAL_CELLS", 0)
    monkeypatch.setattr(train, "_packed", lambda *a: packed.append(a))
    store = experiments.scratch_table
    for module in (experiments, loop):
        monkeypatch.setattr(module, "scratch_table", lambda df, *a: written.append(df.columns) or store(df, *a))
    base = experiments.clean_base(table, "income")
    p = experiments.corrupted(base)
    first = experiments._runs(p, ["progressive"], 100)["progressive"]
    assert len(written) == 1 and "is_dirty" in written.pop() and not packed and [h[4] for h in first] == [0, 50, 100]
    # Corruption by hashes is written once, beside the columns, and is what it was.
    mixed = experiments.corrupted(base, mix=0.5)
    assert written == [[*table.columns, "_bits"]]
    train = base["base"].where("split < 4")
    plain = corrupt.systematic(train, base["d"], base["clean"].theta, 0.05, mix=0.5).select("row_id", F.col("x_d").alias("x"), "err_features", "class_id", "is_dirty")
    names = plain.columns
    assert mixed["rows"].where("is_dirty").count() > 100 and not mixed["rows"].select(*names).exceptAll(plain).count() and not plain.exceptAll(mixed["rows"].select(*names)).count()


def test_weights_by_class_write_the_norm_once(spark):
    """the expression grew by a whole norm with each class of error; the weights are those of the formula."""
    from cleantrain.functions import losses
    from cleantrain.operators.sampling import Weight

    rng = np.random.default_rng(7)
    theta, deltas = rng.normal(size=4), {c: (rng.normal(size=4), 0.0) for c in (1, 2, 5)}
    x, y, c = rng.normal(size=(60, 4)), np.where(rng.random(60) < 0.5, 1.0, -1.0), np.arange(60) % 7
    rows = spark.createDataFrame([(int(k), v.tolist(), float(t)) for k, v, t in zip(c, x, y, strict=True)], "class_id int, x array<double>, y double").coalesce(1)
    dx = np.array([deltas[k][0] if k in deltas else np.zeros(4) for k in c])
    for loss in (losses.hinge(), losses.squared()):
        weight = Weight.taylor_by_class(loss, theta, deltas)
        got = np.array([r.w for r in rows.select(weight.alias("w")).collect()])
        assert np.allclose(got, np.linalg.norm(loss.np_corrections(x, y, theta, dx, np.zeros(60)), axis=1))
        assert str(weight).count("sqrt") == 1 or str(weight).count("SQRT") == 1
