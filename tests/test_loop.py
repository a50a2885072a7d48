import numpy as np
import pytest
from pyspark.sql import functions as F

from cleantrain.functions import losses
from cleantrain.operators import cleaners, train
from cleantrain.plans import baselines, fixtures
from cleantrain.plans.loop import ProgressiveCleaner, combine, update

D = fixtures.D


@pytest.fixture(scope="module")
def rows(spark, small):
    out = fixtures.regression(spark, small).where("split = 0").persist()
    yield out
    out.unpersist()


def _run(rows, **options):
    return ProgressiveCleaner(rows, cleaners.LookupCleaner(rows.select("row_id", "x_c", "y_c")), losses.squared(), D, **({"budget": 40, "batch": 20, "step": train.Step.constant(0.3)} | options)).run()


def test_loop_equals_a_replay(rows):
    """A numpy replay with the same hashes draws the same rows and makes the same steps."""
    import hashlib

    run = _run(rows, detector="known", weight="dirty")
    data = rows.orderBy("row_id").collect()
    x, y, xc = np.array([r.x for r in data]), np.array([r.y for r in data]), np.array([r.x_c for r in data])
    ids, dirty, loss = np.array([r.row_id for r in data]), np.array([r.is_dirty for r in data]), losses.squared()
    theta, clean, seen = train.fit(rows, loss, D).theta, ~dirty, []
    u = lambda t, i: ((int(hashlib.md5(f"0|{t}|{i}".encode()).hexdigest()[:8], 16)) + 0.5) / 2**32
    before = None
    for t in (1, 2):
        pool = np.flatnonzero(dirty & ~np.isin(ids, seen))
        w = np.linalg.norm(loss.np_gradients(x[pool], y[pool], theta), axis=1)
        s0, n0 = before or (w.sum(), len(pool))
        a = 0.9 * w / s0 + 0.1 / n0
        order = pool[np.argsort([-np.log(u(t, ids[i])) / v for i, v in zip(pool, a, strict=True)])][:20]
        p = dict(zip(pool, a / a.sum(), strict=True))
        g = loss.np_gradients(xc[order], y[order], theta)
        from cleantrain.operators.sampling import estimate

        g_s = estimate(g, np.array([p[i] for i in order]), len(pool))
        part = np.concatenate([loss.np_gradients(x[clean], y[clean], theta), loss.np_gradients(xc[np.isin(ids, seen)], y[np.isin(ids, seen)], theta)])
        theta = update(theta, combine(part.mean(0), len(part), g_s, len(pool)), 0.3)
        before = (w.sum(), len(pool) - 20)
        seen += ids[order].tolist()
        assert {r["row_id"] for r in run.ledger if r["iteration"] == t} == set(ids[order].tolist())
        assert np.allclose(theta, run.history[t][-1], atol=1e-9)


@pytest.mark.parametrize("design", ["poisson", "bottom_k", "with_replacement"])
def test_other_designs_step_by_their_own_estimators(rows, design):
    """The first step is recomputed from the ledger, and a large budget uses up the pool without repeats."""
    run = _run(rows, detector="known", design=design, budget=25, batch=25)
    first = [r for r in run.ledger if r["iteration"] == 1]
    loss, theta, n = losses.squared(), np.array(run.history[0][-1]), first[0]["n_dirty"]
    g = loss.np_gradients(np.array([r["x_c"] for r in first]), np.array([r["y_c"] for r in first]), theta)
    pi = np.array([r["pi"] for r in first])
    times = np.array([r["p"] * n / r["pi"] for r in first])
    if design == "with_replacement":
        assert np.allclose(times, times.round()) and round(times.sum()) == 25
        g_s = (g * (times / np.array([r["p"] for r in first]))[:, None]).sum(0) / (25 * n)
    else:
        assert ((pi > 0) & (pi <= 1)).all()
        g_s = (g / pi[:, None]).sum(0) / n
    clean = rows.where("not is_dirty").collect()
    part = loss.np_gradients(np.array([r.x for r in clean]), np.array([r.y for r in clean], dtype=float), theta).mean(0)
    assert np.allclose(update(theta, combine(part, len(clean), g_s, n), 0.3), run.history[1][-1], atol=1e-9)
    few = rows.withColumn("k", F.pmod("row_id", F.lit(40))).where("not is_dirty or k < 8")
    ids = [r["row_id"] for r in _run(few, detector="known", design=design, budget=10_000, batch=20).ledger]
    assert len(ids) == len(set(ids)) == few.where("is_dirty").count()
    with pytest.raises(ValueError):
        _run(rows, design=design, update_every=5)


def test_ledger_keeps_budget_and_never_repeats(rows):
    run = _run(rows, detector=None, weight="uniform", budget=50, batch=20)
    ids = [r["row_id"] for r in run.ledger]
    assert len(ids) == len(set(ids)) == 50 and [h[4] for h in run.history] == [0, 20, 40, 50]


def test_exhausted_pool_ends_at_the_clean_gradient(rows):
    few = rows.withColumn("k", F.pmod("row_id", F.lit(40))).where("not is_dirty or k < 20")
    run = _run(few, detector="known", budget=10_000, batch=200)
    assert len(run.ledger) == few.where("is_dirty").count()


@pytest.mark.parametrize("weight", ["taylor", "taylor_class", "feature_change", "avg_gradient", "regression", "oracle", "uncertainty", "top_uncertain"])
def test_every_weight_runs(rows, weight):
    assert np.isfinite(_run(rows, detector="known", weight=weight).theta).all()


def test_removed_rows_count_with_zero_gradient(rows):
    cleaner = cleaners.FunctionCleaner(lambda r: None, "row_id long, x_c array<double>, y_c double")
    run = ProgressiveCleaner(rows.drop("x_c", "y_c").withColumn("x_c", F.col("x")).withColumn("y_c", F.col("y")), cleaner, losses.squared(), D, detector="known", budget=20, batch=20, step=train.Step.constant(0.1)).run()
    assert len(run.ledger) == 20 and not any(r["kept"] for r in run.ledger)


def test_other_losses_classifier_and_parts(rows):
    signs = rows.withColumn("y", F.col("ypm")).withColumn("y_c", F.col("ypm"))
    cleaner = cleaners.LookupCleaner(signs.select("row_id", "x_c", "y_c", "class_id", "err_features"))
    for predicted in ("floor", "trust"):
        from cleantrain.operators.detect import ClassifierDetector

        run = ProgressiveCleaner(signs, cleaner, losses.hinge(), D, detector=ClassifierDetector(), weight="taylor_class", predicted_clean=predicted, budget=60, batch=20, lam=0.01).run()
        assert np.isfinite(run.theta).all()
    run = ProgressiveCleaner(signs, cleaner, losses.hinge(), D, detector="known", budget=40, batch=40, update_every=10, lam=0.01).run()
    assert len(run.history) == 2


def test_baselines_share_the_history(rows):
    cleaner, loss = cleaners.LookupCleaner(rows.select("row_id", "x_c", "y_c")), losses.squared()
    points = baselines.clean_sample_only(rows, cleaner, loss, D, [30, 60]) + baselines.partial_clean(rows, cleaner, loss, D, [30, 60]) + baselines.uncertainty_sampling(rows, cleaner, loss, D, "topb", budget=20, batch=20).history
    assert all(len(p) == 8 and len(p[-1]) == D for p in points)
    mixed = rows.select("row_id", "x", "y", "x_c", "y_c", "is_dirty")
    whole = baselines.partial_clean(mixed, cleaner, loss, D, [mixed.count()])[-1][-1]
    assert np.allclose(whole, baselines.full_cleaning(rows, loss, D).theta, atol=1e-6)


def test_a_packed_matrix_fits_and_steps_as_arrays_do(spark, small, monkeypatch):
    from cleantrain.catalog import core
    from cleantrain.functions import losses
    from cleantrain.operators import train
    from cleantrain.operators.cleaners import LookupCleaner
    from cleantrain.plans import baselines

    rows = core.regression(spark, small).withColumn("y", F.col("ypm")).withColumn("y_c", F.col("ypm")).repartition(3, "row_id").persist()
    cleaner = LookupCleaner(rows.select("row_id", "x_c", "y_c"))
    passes = []
    sums = train._sums
    monkeypatch.setattr(train, "_sums", lambda *a: passes.append(1) or sums(*a))
    found = []
    for cells in (train.LOCAL_CELLS, 0):
        monkeypatch.setattr(train, "LOCAL_CELLS", cells)
        model = train.fit(rows, losses.hinge(), core.D, 0.01)
        counted = len(passes)
        run = baselines.progressive(rows, cleaner, losses.hinge(), core.D, budget=40, batch=20, lam=0.01, init=model.theta)
        found.append((model.theta, run.theta, sorted(r["row_id"] for r in run.ledger)))
        assert model.gradient_norm < 1e-7 and counted < 60
        passes.clear()
    assert np.allclose(found[0][0], found[1][0], atol=1e-9) and np.allclose(found[0][1], found[1][1], atol=1e-9) and found[0][2] == found[1][2]
    # A draw under a known detector leaves the clean part alone: its gradient comes from the held matrix.
    z = rows.where("not is_dirty").select("x", "y").toPandas()
    x, y = np.array(z.x.tolist()), z.y.to_numpy()
    g, n = train.held_gradient(train.hold(rows.where("not is_dirty"), core.D), losses.hinge(), found[0][0])
    assert n == len(y) and np.allclose(g, losses.hinge().np_gradients(x, y, found[0][0]).sum(0))
    rows.unpersist()
