"""Queries on losses, updates, draws, estimators, detectors, cleaners, corruption and measures, with their DuckDB twins.

Both sides round to six decimals (plus 0.0, so that no negative zero is left) and never sort in the result.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import losses
from ..functions.portable import uniform, uniform_sql
from ..functions.vectors import dot, vector
from ..operators import cleaners, corrupt, detect, estimators, gradient, metrics, sampling, train
from ..operators.sampling import Weight
from ..plans import baselines, fixtures
from ..plans.fixtures import D, THETA, regression, regression_sql
from ..plans.loop import combine, update
from ..sources.tables import read_table

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
FX = regression_sql()
BATCH, SEED = 50, 3
#: Rows that classifier_detector is fitted on, at most.
FITTED = 2000


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


def r6(c: Column) -> Column:
    return F.round(c, 6) + F.lit(0.0)


def s6(c: str) -> str:
    return f"round({c}, 6) + 0.0::double"


def zdot(theta, p: str = "d") -> str:
    return "(" + " + ".join(f"{p}{i} * {float(t)!r}::double" for i, t in enumerate(theta)) + ")"


SLOPE_SQL = {
    "squared": lambda z, y: f"({z} - {y})",
    "logistic": lambda z, y: f"(1 / (1 + exp(-({z}))) - {y})",
    "hinge": lambda z, y: f"(case when {y} * {z} <= 1 then -{y} else 0::double end)",
    "mean": lambda z, y: f"(2 * ({z} - {y}))",
    "absolute": lambda z, y: f"sign({z} - {y})",
}
TARGET = {"squared": "y", "logistic": "y01", "hinge": "ypm", "mean": "y", "absolute": "y"}


def long_sql(cells: list[str], source: str, names: str = "feature, gradient") -> str:
    a, b = names.split(", ")
    return " union all ".join(f"select {i}::int as {a}, {s6(c)} as {b} from {source}" for i, c in enumerate(cells))


def _gradient_query(name: str):
    z = zdot(THETA)
    slope = SLOPE_SQL[name](z, TARGET[name])
    sql = f"with {FX} " + long_sql([f"avg({slope} * d{i})" for i in range(D)], "fx")

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return gradient.mean_gradient(regression(spark, sf_dir), losses.LOSSES[name](), THETA, y=TARGET[name]).select("feature", r6(F.col("gradient")).alias("gradient"))

    run.__name__ = f"grad_{name}"
    query(sql)(run)


for _name in ("squared", "logistic", "hinge"):
    _gradient_query(_name)


def _location_query(name: str, theta: float):
    slope = SLOPE_SQL[name](f"{theta!r}::double", "(value / 50)")
    sql = f"select 0::int as feature, {s6(f'avg({slope})')} as gradient from events"

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = read_table(spark, sf_dir, "events", ["value"]).select(F.array(F.lit(1.0)).alias("x"), (F.col("value") / 50).alias("y"))
        return gradient.mean_gradient(rows, losses.LOSSES[name](), [theta]).select("feature", r6(F.col("gradient")).alias("gradient"))

    run.__name__ = f"grad_{name}"
    query(sql)(run)


_location_query("mean", 0.8)
_location_query("absolute", 0.7)


CLASSES = [0, 1, 2]
OVR = [np.roll(THETA, k) for k in CLASSES]


@query("with " + FX + " " + " union all ".join(f"select {c}::int as class_id, {i}::int as feature, {s6('avg(' + SLOPE_SQL['hinge'](zdot(t), f'(case when class_id = {c} then 1::double else -1::double end)') + f' * d{i})')} as gradient from fx" for c, t in zip(CLASSES, OVR, strict=True) for i in range(D)))
def grad_one_vs_all(spark, sf_dir):
    rows = regression(spark, sf_dir)
    return gradient.per_class_gradient(rows, losses.hinge(), OVR, CLASSES, "class_id").select("class_id", "feature", r6(F.col("gradient")).alias("gradient"))


@query(
    f"with {FX} select {s6('avg(0.5 * (z - y) * (z - y))')} as squared, {s6('avg(greatest(z, 0) - z * y01 + ln(1 + exp(-abs(z))))')} as logistic, {s6('avg(greatest(0, 1 - ypm * z))')} as hinge, {s6('avg((z - y) * (z - y))')} as mean, {s6('avg(abs(z - y))')} as absolute from (select *, {zdot(THETA)} as z from fx)"
)
def loss_values(spark, sf_dir):
    rows = regression(spark, sf_dir).withColumn("z", dot(F.col("x"), THETA))
    return rows.agg(*[r6(F.avg(f().value(F.col("z"), F.col(TARGET[n])))).alias(n) for n, f in losses.LOSSES.items()])


NORM2 = "(" + " + ".join(f"d{i} * d{i}" for i in range(D)) + ")"


@query(f"with {FX} select row_id, {s6(f'abs({zdot(THETA)} - y) * sqrt({NORM2})')} as norm from fx")
def grad_norms_per_row(spark, sf_dir):
    return regression(spark, sf_dir).select("row_id", r6(Weight.dirty_gradient(losses.squared(), THETA)).alias("norm"))


def _line_sql(x: str, y: str, lam: float = 0.0) -> str:
    m = f"select avg({x}) as mx, avg({y}) as my, avg({x} * {x}) as xx, avg({x} * {y}) as xy from fx"
    slope = f"((xy - mx * my) / (xx - mx * mx + {lam!r}::double))"
    return f"with {FX}, m as ({m}) select 0::int as component, {s6(f'my - {slope} * mx')} as weight from m union all select 1::int, {s6(slope)} from m"


def _line(spark, sf_dir, x: str, lam: float = 0.0) -> DataFrame:
    rows = regression(spark, sf_dir).select(F.array(F.lit(1.0), F.get(x, F.lit(1))).alias("x"), "y")
    return train.fit(rows, losses.squared(), 2, lam).rows(spark).select("component", r6(F.col("weight")).alias("weight"))


@query(_line_sql("d1", "y"))
def fit_line_dirty(spark, sf_dir):
    return _line(spark, sf_dir, "x")


@query(_line_sql("c1", "y"))
def fit_line_clean(spark, sf_dir):
    return _line(spark, sf_dir, "x_c")


@query(_line_sql("d1", "y", 0.5))
def fit_ridge(spark, sf_dir):
    return _line(spark, sf_dir, "x", 0.5)


@query(_line_sql("d1", "y").replace("from fx)", "from fx where class_id = 0)"))
def discard_dirty(spark, sf_dir):
    rows = regression(spark, sf_dir).select(F.array(F.lit(1.0), F.get("x", F.lit(1))).alias("x"), "y", "is_dirty")
    return baselines.discard_dirty(rows, losses.squared(), 2).rows(spark).select("component", r6(F.col("weight")).alias("weight"))


def _descent_sql(name: str, steps: int, gamma: float) -> str:
    parts, before = [f"s0 as (select {', '.join(f'0::double as t{i}' for i in range(D))})"], "s0"
    z = "(" + " + ".join(f"d{i} * t{i}" for i in range(D)) + ")"
    for t in range(1, steps + 1):
        slope = SLOPE_SQL[name](z, TARGET[name])
        parts.append(f"s{t} as (select {', '.join(f'any_value(t{i}) - {gamma / t**0.5!r}::double * avg({slope} * d{i}) as t{i}' for i in range(D))} from fx, {before})")
        before = f"s{t}"
    return f"with {FX}, {', '.join(parts)} " + long_sql([f"t{i}" for i in range(D)], before, "component, weight")


def _descent(spark, sf_dir, name: str, steps: int, gamma: float) -> DataFrame:
    rows = regression(spark, sf_dir).select("x", F.col(TARGET[name]).alias("y"))
    loss = losses.LOSSES[name]()
    theta = train.gradient_descent(rows, loss, np.zeros(D), train.Step.inv_sqrt(gamma), steps)
    return train.Model(theta, loss).rows(spark).select("component", r6(F.col("weight")).alias("weight"))


@query(_descent_sql("logistic", 3, 1.0))
def descent_logistic(spark, sf_dir):
    return _descent(spark, sf_dir, "logistic", 3, 1.0)


@query(_descent_sql("hinge", 3, 0.5))
def descent_hinge(spark, sf_dir):
    return _descent(spark, sf_dir, "hinge", 3, 0.5)


@query(
    f"select 'avg' as kind, {s6('avg(l_extendedprice) / 1000')} as value, count(*)::bigint as n from lineitem where l_quantity > 10 union all select 'sum', {s6('sum(l_extendedprice) / 1e9')}, count(*)::bigint from lineitem where l_quantity > 10 union all select 'median', {s6('quantile_cont(l_extendedprice, 0.5) / 1000')}, count(*)::bigint from lineitem where l_quantity > 10"
)
def aggregates_as_losses(spark, sf_dir):
    rows = read_table(spark, sf_dir, "lineitem", ["l_extendedprice", "l_quantity"])
    parts = [train.aggregate_query(rows, k, "l_extendedprice", F.col("l_quantity") > 10).select(F.lit(k).alias("kind"), r6(F.col("value") / s).alias("value"), "n") for k, s in (("avg", 1000), ("sum", 1e9), ("median", 1000))]
    return parts[0].union(parts[1]).union(parts[2])


# ---- draws and updates: the pool is all dirty rows; weights are dirty gradient norms


def pool(spark, sf_dir, weight: str = "dirty") -> DataFrame:
    rows = regression(spark, sf_dir).where("is_dirty")
    return sampling.distribution(rows, Weight.uniform() if weight == "uniform" else Weight.dirty_gradient(losses.squared(), THETA))


POOL = f"""{FX}, w as (select *, abs({zdot(THETA)} - y) * sqrt({NORM2}) as w from fx where class_id > 0),
pool as (select w.*, 0.9::double * w / (select sum(w) from w) + 0.1::double / (select count(*) from w) as p, (select count(*) from w) as n from w),
drawn as (select *, row_number() over (order by -ln({uniform_sql('row_id', SEED, 1)}) / p, row_id) as draw_order from pool qualify draw_order <= {BATCH})"""


@query(f"with {POOL} select row_id, {s6('p * n')} as relative_p from pool")
def weights_floored(spark, sf_dir):
    return pool(spark, sf_dir).select("row_id", r6(F.col("p") * F.col("n_dirty")).alias("relative_p"))


@query(f"with {POOL} select row_id, draw_order::int as draw_order from drawn")
def draw_ordered(spark, sf_dir):
    return sampling.draw_ordered(pool(spark, sf_dir), BATCH, SEED, 1).select("row_id", "draw_order")


@query(f"with {POOL} select row_id from pool where {uniform_sql('row_id', SEED, 1)} < least(1, {BATCH} * p)")
def draw_poisson(spark, sf_dir):
    return sampling.draw_poisson(pool(spark, sf_dir), BATCH, SEED, 1).select("row_id")


@query(f"""with {POOL}, placed as (select row_id, p, sum(p) over (order by row_id % {sampling.BUCKETS}, row_id) as upto from pool),
points as (select {uniform_sql('k', SEED, 1, 'point')} * (select sum(p) from pool) as point from (select unnest(range(1, {BATCH} + 1)) as k))
select row_id, {s6('p * (select count(*) from pool)')} as relative_p, count(*)::bigint as times from points join placed on point >= upto - p and point < upto group by row_id, p""")
def draw_with_replacement(spark, sf_dir):
    drawn = sampling.draw_with_replacement(pool(spark, sf_dir), BATCH, SEED, 1)
    n = pool(spark, sf_dir).agg(F.count(F.lit(1)).alias("n"))
    return drawn.crossJoin(F.broadcast(n)).select("row_id", r6(F.col("p") * F.col("n")).alias("relative_p"), "times")  # n is one row


@query(f"""with {POOL}, keyed as (select *, -ln({uniform_sql('row_id', SEED, 1)}) / p as key from pool),
low as (select *, row_number() over (order by key, row_id) as draw_order from keyed qualify draw_order <= {BATCH} + 1)
select row_id, draw_order::int as draw_order, {s6(f'case when (select count(*) from low) > {BATCH} then 1 - exp(-p * (select max(key) from low)) else 1 end')} as pi from low where draw_order <= {BATCH}""")
def draw_bottom_k(spark, sf_dir):
    return sampling.draw_bottom_k(pool(spark, sf_dir), BATCH, SEED, 1).select("row_id", "draw_order", r6(F.col("pi")).alias("pi"))


def _batch(spark, sf_dir):
    rows = sampling.draw_ordered(pool(spark, sf_dir), BATCH, SEED, 1)
    got = cleaners.LookupCleaner(regression(spark, sf_dir)).clean(rows.select("row_id", "p", "n_dirty", "draw_order")).orderBy("draw_order").collect()
    return np.array([r.x_c for r in got]), np.array([r.y_c for r in got]), np.array([r.p for r in got]), got[0].n_dirty if got else 0


def _dirty_estimate(spark, sf_dir, loss, theta) -> np.ndarray:
    x, y, p, n = _batch(spark, sf_dir)
    return sampling.estimate(loss.np_gradients(x, y, np.array(theta)), p, n)


def _vector_rows(spark, values, a: str = "feature", b: str = "gradient") -> DataFrame:
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(values)], f"{a} int, {b} double").select(a, r6(F.col(b)).alias(b))


GC = f"({zdot(THETA, 'c')} - y)"
G_SUMS = f"""before as (select draw_order, p, n, {', '.join(f'{GC} * c{i} as g{i}' for i in range(D))} from drawn),
run as (select *, 1 - (sum(p) over o - p) as rest, {', '.join(f'sum(g{i}) over o - g{i} as b{i}' for i in range(D))} from before window o as (order by draw_order)),
gs as (select {', '.join(f'sum(b{i} + g{i} * rest / p) / (count(*) * any_value(n)) as e{i}' for i in range(D))} from run)"""
GC_SUMS = f"gc as (select count(*) as n, {', '.join(f'avg({GC} * c{i}) as m{i}' for i in range(D))} from fx where class_id = 0)"
NPOOL = "(select count(*) from pool)"


@query(f"with {POOL}, {G_SUMS} " + long_sql([f"e{i}" for i in range(D)], "gs"))
def gradient_of_batch(spark, sf_dir):
    return _vector_rows(spark, _dirty_estimate(spark, sf_dir, losses.squared(), THETA))


@query(f"with {FX}, {GC_SUMS} " + long_sql([f"m{i}" for i in range(D)], "gc"))
def gradient_of_clean_part(spark, sf_dir):
    state = gradient.GramState.of(regression(spark, sf_dir).where("not is_dirty"), D)
    return _vector_rows(spark, state.total_gradient(np.array(THETA)) / max(state.n, 1))


COMBINED = [f"(gc.n * m{i} + {NPOOL} * e{i}) / (gc.n + {NPOOL})" for i in range(D)]


@query(f"with {POOL}, {G_SUMS}, {GC_SUMS} " + long_sql(COMBINED, "gs, gc"))
def gradient_combined(spark, sf_dir):
    return _vector_rows(spark, _combined(spark, sf_dir))


def _combined(spark, sf_dir) -> np.ndarray:
    rows = regression(spark, sf_dir)
    state = gradient.GramState.of(rows.where("not is_dirty"), D)
    n = rows.where("is_dirty").count()
    return combine(state.total_gradient(np.array(THETA)) / max(state.n, 1), state.n, _dirty_estimate(spark, sf_dir, losses.squared(), THETA), n)


@query(f"with {POOL}, {G_SUMS}, {GC_SUMS} " + long_sql([f"{THETA[i]!r}::double - 0.25::double * ({c})" for i, c in enumerate(COMBINED)], "gs, gc", "component, weight"))
def one_update(spark, sf_dir):
    return _vector_rows(spark, update(np.array(THETA), _combined(spark, sf_dir), 0.25), "component", "weight")


@query(f"select distinct l_linenumber::int as t, l_quantity::int as b, 0.1::double as constant, {s6('0.1::double / (l_quantity * l_linenumber)')} as shrinking_batch, {s6('0.1::double / l_linenumber')} as inv_t, {s6('0.1::double / sqrt(l_linenumber)')} as inv_sqrt from lineitem")
def step_schedules(spark, sf_dir):
    """Step sizes for each line number as the iteration and each quantity as the batch size."""
    kinds = {k: getattr(train.Step, k)(0.1) for k in ("constant", "shrinking_batch", "inv_t", "inv_sqrt")}

    def run(batches):
        for batch in batches:
            yield batch.assign(**{k: [f(t, b) for t, b in zip(batch["t"], batch["b"], strict=True)] for k, f in kinds.items()})

    asked = read_table(spark, sf_dir, "lineitem", ["l_linenumber", "l_quantity"]).select(F.col("l_linenumber").cast("int").alias("t"), F.col("l_quantity").cast("int").alias("b")).distinct()
    found = asked.mapInPandas(run, "t int, b int, constant double, shrinking_batch double, inv_t double, inv_sqrt double")
    return found.select("t", "b", "constant", *[r6(F.col(c)).alias(c) for c in ("shrinking_batch", "inv_t", "inv_sqrt")])


CHANGE = "select class_id as feature, sum((case class_id " + " ".join(f"when {i} then c{i} - d{i}" for i in range(1, D)) + " end) / pi) / sum(1 / pi) as delta from ledger group by class_id"
LEDGER_SQL = f"{POOL}, ledger as (select *, n * p as pi from pool where {uniform_sql('row_id', 9)} < 0.3)"


def _ledger(spark, sf_dir) -> DataFrame:
    return pool(spark, sf_dir).withColumn("pi", F.col("n_dirty") * F.col("p")).where(uniform("row_id", 9) < 0.3)


@query(f"with {LEDGER_SQL} select feature, {s6('delta')} as delta from ({CHANGE})")
def change_by_feature(spark, sf_dir):
    return estimators.change_by_feature(_ledger(spark, sf_dir)).select("feature", r6(F.col("delta")).alias("delta"))


@query(f"with {LEDGER_SQL} select feature as class_id, feature, {s6('delta')} as delta from ({CHANGE})")
def change_by_class(spark, sf_dir):
    return estimators.change_by_feature(_ledger(spark, sf_dir), by_class=True).select("class_id", "feature", r6(F.col("delta")).alias("delta"))


DELTA = (0.0, -5.0, -4.0, -6.0, -5.5, -6.5)


def _taylor_sql(name: str, y: str) -> str:
    z, s = zdot(THETA), "(case class_id " + " ".join(f"when {i} then {DELTA[i] * THETA[i]!r}::double" for i in range(1, D)) + " else 0::double end)"
    if name == "squared":
        alpha, beta = f"({z} - {y} + {s})", f"({z} - {y})"
    elif name == "logistic":
        h = f"(1 / (1 + exp(-({z}))))"
        alpha, beta = f"({h} - {y} + {h} * (1 - {h}) * {s})", f"({h} - {y})"
    else:
        alpha = beta = SLOPE_SQL["hinge"](z, y)
    parts = " + ".join(f"pow({alpha} * d{i} + {beta} * (case when class_id = {i} then {DELTA[i]!r}::double else 0::double end), 2)" for i in range(D))
    return f"with {FX} select row_id, {s6(f'sqrt({parts})')} as norm from fx where class_id > 0"


def _taylor_query(name: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = regression(spark, sf_dir).where("is_dirty")
        return rows.select("row_id", r6(Weight.taylor(losses.LOSSES[name](), THETA, DELTA, y=TARGET[name])).alias("norm"))

    run.__name__ = f"weight_taylor_{name}"
    query(_taylor_sql(name, TARGET[name]))(run)


for _name in ("squared", "logistic", "hinge"):
    _taylor_query(_name)


@query(f"with {FX} select row_id, {s6('abs(' + zdot(THETA, 'c') + ' - y) * sqrt(' + NORM2.replace('d', 'c') + ')')} as norm from fx where class_id > 0")
def weight_oracle(spark, sf_dir):
    return regression(spark, sf_dir).where("is_dirty").select("row_id", r6(Weight.oracle(losses.squared(), THETA)).alias("norm"))


MOVED = [f"(d{i} + case when class_id = {i} then {DELTA[i]!r}::double else 0::double end)" for i in range(D)]


@query(f"with {FX} select row_id, {s6('abs((' + ' + '.join(f'{m} * {THETA[i]!r}::double' for i, m in enumerate(MOVED)) + ') - y) * sqrt(' + ' + '.join(f'{m} * {m}' for m in MOVED) + ')')} as norm from fx where class_id > 0")
def weight_feature_change(spark, sf_dir):
    return regression(spark, sf_dir).where("is_dirty").select("row_id", r6(Weight.feature_change(losses.squared(), THETA, DELTA)).alias("norm"))


@query(f"with {FX} select row_id, {s6('sqrt(' + ' + '.join(f'pow(({zdot(THETA)} - y) * d{i} + 0.5::double, 2)' for i in range(D)) + ')')} as norm from fx where class_id > 0")
def weight_average_gradient(spark, sf_dir):
    return regression(spark, sf_dir).where("is_dirty").select("row_id", r6(Weight.average_gradient(losses.squared(), THETA, [0.5] * D)).alias("norm"))


@query(f"with {FX} select row_id, {s6(f'1 / (abs({zdot(THETA)}) / {float(np.linalg.norm(THETA))!r}::double + 1e-3::double)')} as weight from fx where class_id > 0")
def weight_uncertainty(spark, sf_dir):
    return regression(spark, sf_dir).where("is_dirty").select("row_id", r6(Weight.uncertainty(THETA)).alias("weight"))


@query(f"with {FX} select row_id from fx order by abs({zdot(THETA)}), row_id limit {BATCH}")
def uncertainty_top(spark, sf_dir):
    return regression(spark, sf_dir).select("row_id", F.abs(dot(F.col("x"), THETA)).alias("m")).orderBy("m", "row_id").limit(BATCH).select("row_id")


A = f"(abs({zdot(THETA, 'c')} - y) * sqrt({NORM2.replace('d', 'c')}))"


@query(f"with {POOL}, a as (select {A} as a, p, n from pool) select {s6('(sum(a * a / p) / pow(count(*), 2) - pow(avg(a), 2)) / 50')} as dirty_weights, {s6('(sum(a * a * n) / pow(count(*), 2) - pow(avg(a), 2)) / 50')} as uniform_weights from a")
def variance_by_design(spark, sf_dir):
    rows = pool(spark, sf_dir).withColumn("a", Weight.oracle(losses.squared(), THETA)).withColumn("u", 1.0 / F.col("n_dirty"))
    a = sampling.design_variance(rows, "p", "a", 50).select(r6(F.col("variance")).alias("dirty_weights"))
    return a.crossJoin(sampling.design_variance(rows, "u", "a", 50).select(r6(F.col("variance")).alias("uniform_weights")))  # one row each


# ---- corruption, detectors, cleaners, baselines, measures


@query(f"with {FX} select class_id, count(*)::bigint as n, {s6('avg(' + ' + '.join(f'd{i}' for i in range(1, D)) + ')')} as mean_sum from fx group by class_id")
def corrupt_random(spark, sf_dir):
    rows = regression(spark, sf_dir)
    return rows.groupBy("class_id").agg(F.count(F.lit(1)).alias("n"), r6(F.avg(dot(F.col("x"), [0.0] + [1.0] * (D - 1)))).alias("mean_sum"))


@query(
    f"""with {FX}, m as (select max(c1) as m1, max(c2) as m2, max(c3) as m3, max(c4) as m4, max(c5) as m5 from fx), hit as (select fx.*, m.*, {uniform_sql('row_id', 1, 'hit')} < 0.05 as h, (floor({uniform_sql('row_id', 1, 'feature')} * 5) + 1)::int as f from fx, m)
select case when h then power(2, f - 1)::int else 0 end as class_id, count(*)::bigint as n, {s6('avg(case when h then case f ' + ' '.join(f'when {i} then 3 * m{i}' for i in range(1, 6)) + ' end else 0 end)')} as mean_value from hit group by 1"""
)
def corrupt_random_magnitude(spark, sf_dir):
    rows = regression(spark, sf_dir).select("row_id", F.col("x_c").alias("x"))
    out = corrupt.random_magnitude(rows, D)
    changed = F.aggregate(F.transform("err_features", lambda i: F.get("x_d", i)), F.lit(0.0), lambda s, v: s + v)
    return out.groupBy("class_id").agg(F.count(F.lit(1)).alias("n"), r6(F.avg(changed)).alias("mean_value"))


SYSTEMATIC = sorted(sorted(range(1, D), key=lambda i: (-abs(THETA[i]), i))[:3])
TAKEN = ", ".join(f"row_number() over (order by c{i} desc, {uniform_sql('row_id', 1, 'tie', i)}) <= floor({0.05 / 3!r}::double * count(*) over ()) as f{i}" for i in SYSTEMATIC)


@query(f"with {FX}, taken as (select row_id, {TAKEN} from fx) select ({' + '.join(f'case when f{i} then {1 << k} else 0 end' for k, i in enumerate(SYSTEMATIC))})::int as class_id, count(*)::bigint as n from taken group by 1")
def corrupt_systematic(spark, sf_dir):
    rows = regression(spark, sf_dir).select("row_id", F.col("x_c").alias("x"))
    return corrupt.systematic(rows, D, THETA).groupBy("class_id").agg(F.count(F.lit(1)).alias("n"))


def _image_sql(cell) -> str:
    u = lambda s: uniform_sql("vec_id", 1, s)
    return f"""with i as (select vec_id, {u('hit')} < 0.05 as h, floor({u('top')} * 6)::int as t, floor({u('left')} * 6)::int as l, list_transform(embedding, lambda v: v::double) as x from embeddings)
select vec_id as row_id, h as is_dirty, {s6(cell)} as total from i"""


@query(_image_sql("case when h then list_sum(list_transform(range(0, 64), lambda k: case when k // 8 >= t and k // 8 < t + 3 and k % 8 >= l and k % 8 < l + 3 then 0 else x[k + 1] * (k + 1) end)) else list_sum(list_transform(range(0, 64), lambda k: x[k + 1] * (k + 1))) end"))
def corrupt_block(spark, sf_dir):
    out = corrupt.block_removal(fixtures.images(spark, sf_dir))
    return out.select("row_id", "is_dirty", r6(F.aggregate(F.transform("x_d", lambda v, i: v * (i + 1)), F.lit(0.0), lambda s, v: s + v)).alias("total"))


def _blur_cell() -> str:
    cells = []
    for i in range(64):
        r, c = divmod(i, 8)
        around = [a * 8 + b + 1 for a in range(r, min(8, r + 2)) for b in range(c, min(8, c + 2))]
        cells.append("(" + " + ".join(f"x[{k}]" for k in around) + f") / {len(around)} * {i + 1}")
    return f"case when h then {' + '.join(cells)} else list_sum(list_transform(range(0, 64), lambda k: x[k + 1] * (k + 1))) end"


@query(_image_sql(_blur_cell()))
def corrupt_blur(spark, sf_dir):
    out = corrupt.blur(fixtures.images(spark, sf_dir))
    return out.select("row_id", "is_dirty", r6(F.aggregate(F.transform("x_d", lambda v, i: v * (i + 1)), F.lit(0.0), lambda s, v: s + v)).alias("total"))


NAMES = f"named as (select s_suppkey, s_name as clean, case when {uniform_sql('s_suppkey', 1, 'hit')} < 0.18 then s_name || (['{corrupt.SUFFIXES[0]}', '{corrupt.SUFFIXES[1]}', '{corrupt.SUFFIXES[2]}', '{corrupt.SUFFIXES[3]}'])[floor({uniform_sql('s_suppkey', 1, 'suffix')} * 4)::int + 1] else s_name end as s_name from supplier)"


def _named(spark, sf_dir) -> DataFrame:
    return corrupt.name_variants(read_table(spark, sf_dir, "supplier", ["s_suppkey", "s_name"]), "s_name", key="s_suppkey")


@query(f"with {NAMES} select s_suppkey, s_name, s_name <> clean as is_dirty from named")
def corrupt_names(spark, sf_dir):
    return _named(spark, sf_dir).select("s_suppkey", "s_name", "is_dirty")


GROUPS = "g as (select c_custkey, count(*) as n, sum(o_totalprice) / 1e6 as total, coalesce(sum(case when o_orderdate < timestamp '1999-01-01' then o_totalprice end), 0) / 1e6 as stale from orders join customer on o_custkey = c_custkey group by c_custkey)"


@query(f"with {GROUPS} select c_custkey, n::bigint as n, n <= 8 and total <> stale as is_dirty, round((case when n <= 8 then stale else total end) * 1e8)::bigint as cents from g")
def corrupt_stale_groups(spark, sf_dir):
    return corrupt.stale_groups(fixtures.customer_groups(spark, sf_dir), 8).select("c_custkey", "n", "is_dirty", F.round(F.col("total_d") * 1e8).cast("long").alias("cents"))


@query(f"with {NAMES} select s_suppkey, trim(regexp_replace(trim(s_name), '(?i)[,\\s]+(Inc\\.|Inc|Incorporated|Ltd|LLC|Corp)\\s*$', '')) as s_name from named")
def normalise_names(spark, sf_dir):
    return cleaners.normalise_values(_named(spark, sf_dir), "s_name").select("s_suppkey", "s_name")


@query(f"with {NAMES}, seen as (select distinct s_name as v, clean as c from named where s_name <> clean and s_suppkey % 2 = 0) select s_suppkey, coalesce(c, s_name) as s_name, c is not null as replaced from named left join seen on s_name = v where s_name <> clean")
def set_of_records_clean(spark, sf_dir):
    rows = _named(spark, sf_dir).where("is_dirty")
    return cleaners.set_of_records(rows, rows.where("s_suppkey % 2 = 0"), "s_name").select("s_suppkey", "s_name", "replaced")


@query(f"with {NAMES} select s_suppkey, not regexp_matches(s_name, '^Supplier#[0-9]+$') as is_dirty from named")
def rule_regex(spark, sf_dir):
    return detect.ConstraintDetector([detect.Rule.regex("s_name", r"^Supplier#[0-9]+$")]).detect(_named(spark, sf_dir).drop("is_dirty")).select("s_suppkey", "is_dirty")


@query("select l_orderkey, l_linenumber, l_partkey, l_suppkey, l_returnflag not in ('A', 'N') as bad_flag, l_quantity > 45 as bad_quantity, concat_ws(',', case when l_quantity > 45 then 'l_quantity' end, case when l_returnflag not in ('A', 'N') then 'l_returnflag' end) as err_cols from lineitem")
def detect_union(spark, sf_dir):
    rules = [detect.Rule.domain("l_returnflag", ["A", "N"]), detect.Rule.range("l_quantity", None, 45)]
    out = detect.ConstraintDetector(rules).detect(read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_quantity"]))
    return out.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.array_contains("err_cols", "l_returnflag").alias("bad_flag"), F.array_contains("err_cols", "l_quantity").alias("bad_quantity"), F.array_join("err_cols", ",").alias("err_cols"))


TYPED = "p as (select p_partkey, case when p_type in ('SMALL', 'PROMO') then p_name end as drug, case when p_type in ('PROMO', 'LARGE') then p_name end as device, p_name, p_brand, p_size from part)"


def _typed(spark, sf_dir) -> DataFrame:
    part = read_table(spark, sf_dir, "part")
    return part.select("p_partkey", F.when(F.col("p_type").isin("SMALL", "PROMO"), F.col("p_name")).alias("drug"), F.when(F.col("p_type").isin("PROMO", "LARGE"), F.col("p_name")).alias("device"), "p_name", "p_brand", "p_size")


@query(f"with {TYPED} select p_partkey, (drug is null) = (device is null) as exactly_one, drug is not null and device is not null as at_most_one, drug is null as missing from p")
def rules_exclusive_and_null(spark, sf_dir):
    rows = _typed(spark, sf_dir)
    a, b, c = detect.Rule.exclusive("drug", "device"), detect.Rule.exclusive("drug", "device", True), detect.Rule.not_null("drug")
    return rows.select("p_partkey", a.predicate().alias("exactly_one"), b.predicate().alias("at_most_one"), c.predicate().alias("missing"))


@query("with k as (select p_name from part group by p_name having min(p_brand) <> max(p_brand)) select p_partkey, p_name in (select p_name from k) as broken from part")
def rule_functional(spark, sf_dir):
    rows = read_table(spark, sf_dir, "part", ["p_partkey", "p_name", "p_brand"])
    rule = detect.Rule.functional(["p_name"], "p_brand")
    return rule.mark(rows).select("p_partkey", F.col(rule.name).alias("broken"))


@query("select distinct a.o_orderkey from orders a join orders b on a.o_custkey = b.o_custkey and a.o_orderkey <> b.o_orderkey and a.o_orderdate < b.o_orderdate and a.o_totalprice > 3 * b.o_totalprice")
def rule_denial(spark, sf_dir):
    rows = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_orderdate", "o_totalprice"])
    rule = detect.Rule.denial("dear_before", ["o_custkey"], ("o_totalprice",), lambda a, b: f"{a}.o_orderdate < {b}.o_orderdate and {a}.o_totalprice > 3 * {b}.o_totalprice", "o_orderkey")
    return rule.mark(rows).where("dear_before").select("o_orderkey")


@query(
    f"""with {NAMES}, v as (select s_name as value from named union select clean from named), t as (select distinct value, unnest(list_filter(regexp_split_to_array(lower(value), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '')) as token from v),
n as (select value, count(*) as n from t group by value), pairs as (select a.value as a, b.value as b, count(*) as s from t a join t b on a.token = b.token and a.value < b.value group by 1, 2)
select a, b, {s6('s::double / (x.n + y.n - s)')} as similarity from pairs join n x on a = x.value join n y on b = y.value where s::double / (x.n + y.n - s) > 0.6"""
)
def rule_matching_pairs(spark, sf_dir):
    """Unit weights, so that six decimals agree in any order of summing."""
    names = _named(spark, sf_dir)
    return detect.similar_values(names.select("s_name").union(names.select("s_name_c")), "s_name", 0.6, weights="unit").select("a", "b", r6(F.col("similarity")).alias("similarity"))


@query("with t as (select l_returnflag, l_linestatus, case when l_quantity > 40 and l_returnflag = 'R' then 1 else 0 end as class_id from lineitem) select class_id, l_returnflag, null::varchar as l_linestatus, count(*) filter (where class_id = 1)::bigint as support from t where class_id = 1 group by 1, 2")
def pattern_support(spark, sf_dir):
    rows = read_table(spark, sf_dir, "lineitem", ["l_returnflag", "l_linestatus", "l_quantity"]).withColumn("class_id", ((F.col("l_quantity") > 40) & (F.col("l_returnflag") == "R")).cast("int"))
    out = detect.pattern_tableau(rows, ["l_returnflag", "l_linestatus"], min_confidence=0.0, max_length=1)
    return out.where("l_returnflag is not null").select("class_id", "l_returnflag", "l_linestatus", "support")


@query()
def classifier_detector(spark, sf_dir):
    rows = regression(spark, sf_dir)
    # A fitted classifier's sample: the FITTED rows of the least hashes, the same rows in any partitioning.
    seen = rows.select("x", "class_id", uniform("row_id", 4).alias("u"), "row_id").orderBy("u", "row_id").limit(FITTED).collect()
    fitted = detect.ClassifierDetector().fit(np.array([r.x for r in seen]), np.array([r.class_id for r in seen]))
    return metrics.confusion_by(rows.withColumn("found", fitted.class_column()), "class_id", "found")


@query(f"with {POOL} select drawn.row_id, {s6('c1')} as x1_c, {s6('d1')} as x1, class_id from drawn")
def lookup_clean(spark, sf_dir):
    got = cleaners.LookupCleaner(regression(spark, sf_dir)).clean(sampling.draw_ordered(pool(spark, sf_dir), BATCH, SEED, 1).select("row_id", "x"))
    return got.select("row_id", r6(F.get("x_c", F.lit(1))).alias("x1_c"), r6(F.get("x", F.lit(1))).alias("x1"), "class_id")


@query("select event_id, value <= 200 as kept from events")
def filter_outliers(spark, sf_dir):
    return cleaners.filter_outliers(read_table(spark, sf_dir, "events", ["event_id", "value"]), "value", 200).select("event_id", "kept")


@query("select p_partkey, round(p_size * case p_size % 3 when 0 then 1.609344::double when 1 then 1::double else null end, 6) as distance_km from part")
def unit_convert(spark, sf_dir):
    rows = read_table(spark, sf_dir, "part", ["p_partkey", "p_size"]).select("p_partkey", F.concat(F.col("p_size").cast("string"), F.element_at(F.array(F.lit(" miles"), F.lit(" km"), F.lit(" leagues")), F.col("p_size") % 3 + 1)).alias("distance"))
    return cleaners.convert_units(rows, "distance", {"miles": 1.609344, "km": 1.0}, "km").select("p_partkey", F.round("distance_km", 6).alias("distance_km"))


LIMIT = "4 * sqrt(ln(6) + ln((select count(*) from fx)))"


@query(f"with {FX}, s as (select {', '.join(f'avg(d{i}) as m{i}, stddev_pop(d{i}) as s{i}' for i in range(1, D))} from fx) select count(*)::bigint as kept from fx, s where greatest({', '.join(f'abs(d{i} - m{i}) / s{i}' for i in range(1, D))}) < {LIMIT}")
def robust_filter(spark, sf_dir):
    return baselines.robust_filter(regression(spark, sf_dir), D).agg(F.count(F.lit(1)).alias("kept"))


def _mix_sql(detector: bool) -> str:
    where = "class_id > 0" if detector else "true"
    m = "select avg(x) as mx, avg(y) as my, avg(x * x) as xx, avg(x * y) as xy from mixed"
    slope = "((xy - mx * my) / (xx - mx * mx))"
    return f"with {FX}, top as (select row_id from fx where {where} order by {uniform_sql('row_id', 0, 'sample')}, row_id limit 200), mixed as (select case when row_id in (select row_id from top) then c1 else d1 end as x, y from fx), m as ({m}) select 0::int as component, {s6(f'my - {slope} * mx')} as weight from m union all select 1::int, {s6(slope)} from m"


def _mix(spark, sf_dir, detector: bool) -> DataFrame:
    rows = regression(spark, sf_dir).select("row_id", F.array(F.lit(1.0), F.get("x", F.lit(1))).alias("x"), "y", F.array(F.lit(1.0), F.get("x_c", F.lit(1))).alias("x_c"), "y_c", "is_dirty")
    history = baselines.partial_clean(rows, cleaners.LookupCleaner(rows.select("row_id", "x_c", "y_c")), losses.squared(), 2, [100, 200], detector=detector)
    return _vector_rows(spark, history[-1][-1], "component", "weight")


@query(_mix_sql(False))
def mix_uniform(spark, sf_dir):
    return _mix(spark, sf_dir, False)


@query(_mix_sql(True))
def mix_detect(spark, sf_dir):
    return _mix(spark, sf_dir, True)


@query(_mix_sql(False).replace("mixed as (select case when row_id in (select row_id from top) then c1 else d1 end as x, y from fx)", "mixed as (select c1 as x, y from fx where row_id in (select row_id from top))"))
def clean_sample_only(spark, sf_dir):
    rows = regression(spark, sf_dir).select("row_id", F.array(F.lit(1.0), F.get("x", F.lit(1))).alias("x"), "y", F.array(F.lit(1.0), F.get("x_c", F.lit(1))).alias("x_c"), "y_c", "is_dirty")
    history = baselines.clean_sample_only(rows, cleaners.LookupCleaner(rows.select("row_id", "x_c", "y_c")), losses.squared(), 2, [200])
    return _vector_rows(spark, history[-1][-1], "component", "weight")


#: Events as runs: a kind of event is a method, a user its seed, a day a point at 50 cleaned rows more, and the day's least value the error.
#: The small constant moves means off the rounding boundary, where a float's last bit would decide.
HISTORY_SQL = "h as (select event_type || '-' || user_id as run_id, event_type as method, user_id as seed, date_diff('day', date '2024-01-01', ts::date) as iteration, 50 * date_diff('day', date '2024-01-01', ts::date) as cleaned, min(value) / 100 + 0.000000012345::double as error from events where value is not null group by all)"


def _history(spark, sf_dir) -> DataFrame:
    events = read_table(spark, sf_dir, "events", ["user_id", "ts", "event_type", "value"], "value is not null")
    day = F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date"))
    each = events.groupBy(F.concat_ws("-", "event_type", F.col("user_id").cast("string")).alias("run_id"), F.col("event_type").alias("method"), F.col("user_id").alias("seed"), day.alias("iteration"))
    return each.agg((F.min("value") / 100 + 0.000000012345).alias("error")).withColumn("cleaned", F.col("iteration").cast("long") * 50)


@query(f"with {HISTORY_SQL}, w as (select *, max(error) over (partition by run_id order by cleaned rows between current row and unbounded following) as worst from h) select run_id, coalesce(min(case when error <= 0.26 then cleaned end), -1)::bigint as first, coalesce(min(case when worst <= 0.26 then cleaned end), -1)::bigint as staying from w group by run_id")
def measure_cleaned_to_reach(spark, sf_dir):
    a = metrics.cleaned_to_reach(_history(spark, sf_dir), "error", 0.26).withColumnRenamed("cleaned", "first")
    return a.join(metrics.cleaned_to_reach(_history(spark, sf_dir), "error", 0.26, True).withColumnRenamed("cleaned", "staying"), "run_id").fillna(-1)


@query(f"with {HISTORY_SQL}, a as (select method, avg(error) as e from h where cleaned = 200 group by method) select method, {s6('e / (select e from a where method = ' + chr(39) + 'error' + chr(39) + ')')} as ratio from a")
def measure_ratio(spark, sf_dir):
    return metrics.ratio_at(_history(spark, sf_dir), 200, "error", "error").select("method", r6(F.col("ratio")).alias("ratio"))


@query(f"with {HISTORY_SQL} select cleaned::bigint as cleaned, {s6('1 - avg(error) filter (where method = ' + chr(39) + 'click' + chr(39) + ') / avg(error) filter (where method = ' + chr(39) + 'error' + chr(39) + ')')} as reduction from h group by cleaned")
def measure_reduction(spark, sf_dir):
    return metrics.error_reduction(_history(spark, sf_dir), "click", "error", "error").select("cleaned", r6(F.col("reduction")).alias("reduction"))


@query(f"with {HISTORY_SQL}, m as (select method, cleaned, avg(error) as e, stddev_samp(error) as sd, max(error) as worst from h group by 1, 2) select method, cleaned::bigint as cleaned, {s6('e')} as mean_error, {s6('sd')} as sd, {s6('worst')} as worst, coalesce(e <= lag(e) over (partition by method order by cleaned), false) as falling from m")
def measure_reliability(spark, sf_dir):
    return metrics.reliability(_history(spark, sf_dir), "error").select("method", "cleaned", *[r6(F.col(c)).alias(c) for c in ("mean_error", "sd", "worst")], F.coalesce("falling", F.lit(False)).alias("falling"))


@query(f"with {FX}, c as (select class_id > 0 as t, d1 > 3 or d2 > 3 as f from fx) select {s6('count(*) filter (where t and f)::double / count(*) filter (where t)')} as tpr, {s6('count(*) filter (where not t and f)::double / count(*) filter (where not t)')} as fpr, {s6('count(*) filter (where t and f)::double / count(*) filter (where f)')} as precision, {s6('count(*) filter (where t = f)::double / count(*)')} as accuracy from c")
def measure_detection(spark, sf_dir):
    rows = regression(spark, sf_dir)
    c = metrics.confusion(rows, F.col("is_dirty"), (F.get("x", F.lit(1)) > 3) | (F.get("x", F.lit(2)) > 3))
    return c.select(*[r6(F.col(n)).alias(n) for n in ("tpr", "fpr", "precision", "accuracy")])


@query(f"with {FX} select {s6('avg(case when (' + zdot(THETA, 'c') + ' >= 1.5::double) = (ypm > 0) then 1::double else 0::double end)')} as accuracy, {s6('avg(pow(' + zdot(THETA, 'c') + ' - y, 2))')} as mse from fx")
def measure_test_error(spark, sf_dir):
    rows, model = regression(spark, sf_dir), train.Model(np.array(THETA), losses.squared())
    a = metrics.accuracy(rows, model.predict("x_c", 1.5), "ypm").select(r6(F.col("accuracy")).alias("accuracy"))
    return a.crossJoin(metrics.mean_squared_error(rows, model, "x_c").select(r6(F.col("mse")).alias("mse")))  # one row each


SQUARES = " + ".join(f"pow(avg(d{i}) - {p!r}::double, 2)" for i, p in enumerate(fixtures.PLANTED))


@query(f"with {FX} select split, class_id, {s6(f'sqrt({SQUARES})')} as model_error, {s6(f'sqrt({SQUARES}) / {float(np.linalg.norm(fixtures.PLANTED))!r}::double')} as rel_model_error from fx group by split, class_id")
def measure_model_error(spark, sf_dir):
    """Distances of the parameters that each part of the rows gives (its mean row) from the planted ones."""
    h = regression(spark, sf_dir).groupBy("split", "class_id").agg(F.array(*[F.avg(F.get("x", F.lit(i))) for i in range(D)]).alias("theta"))
    return metrics.relative_error_rows(h, fixtures.PLANTED).select("split", "class_id", r6(F.col("model_error")).alias("model_error"), r6(F.col("rel_model_error")).alias("rel_model_error"))


@query()
def progressive_loop(spark, sf_dir):
    """The whole method on the regression fixture: history with relative errors."""
    rows = regression(spark, sf_dir)
    clean = train.fit(rows, losses.squared(), D, x="x_c", y="y_c").theta
    run = baselines.progressive(rows, cleaners.LookupCleaner(rows.select("row_id", "x_c", "y_c")), losses.squared(), D, budget=300, step=train.Step.constant(0.3))
    return metrics.relative_error_rows(run.history_rows(spark), clean)


@query(f"with {POOL}, b as (select row_number() over (partition by split order by row_id) as k, row_id from pool) select k::int as k, row_id from b where k <= 20")
def window_rank(spark, sf_dir):
    w = Window.partitionBy("split").orderBy("row_id")
    return pool(spark, sf_dir).select(F.row_number().over(w).alias("k"), "row_id").where("k <= 20")
