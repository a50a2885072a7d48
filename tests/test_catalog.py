import importlib.util

import duckdb
import pytest

from cleantrain.catalog import core, surrounding

QUERIES = {**core.QUERIES, **surrounding.QUERIES}
ORACLES = {**core.ORACLES, **surrounding.ORACLES}
SLOW = {n for n in QUERIES if n[:1] == "w" and n[1:3].isdigit()}


@pytest.fixture(scope="module")
def db(small):
    c = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings"):
        c.sql(f"create view {t} as select * from '{small}/{t}.parquet'")
    return c


def _rows(frame):
    return sorted(repr([None if v is None or v != v else float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else str(v) for v in row]) for row in frame[sorted(frame.columns)].astype(object).where(frame.notna(), None).values.tolist())


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(spark, small, db, name):
    got, want = QUERIES[name](spark, small).toPandas(), db.sql(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns) and _rows(got) == _rows(want)


def test_worked_change_example(spark):
    from pyspark.sql import functions as F

    from cleantrain.operators.estimators import change_by_feature

    ledger = spark.createDataFrame([([1, 2, 3], 0.5), ([1, 2, 6], 1.0)], "err_features array<int>, step double")
    ledger = ledger.select("err_features", F.lit(1.0).alias("pi"), F.array(*[F.lit(0.0)] * 7).alias("x"), F.transform(F.sequence(F.lit(0), F.lit(6)), lambda i: i * F.col("step")).alias("x_c"))
    assert {r.feature: r.delta for r in change_by_feature(ledger).collect()} == {1: 0.75, 2: 1.5, 3: 1.5, 6: 6.0}


def test_changes_of_the_given_lines(spark, small, db):
    got = {r.feature: r.delta for r in surrounding.QUERIES["w16_change_example"](spark, small).collect()}
    part = {1: "true", 2: "true", 3: "split % 2 = 0", 5: "split % 2 = 1"}
    for i, where in part.items():
        assert got.pop(i) == pytest.approx(db.sql(f"with {core.FX} select avg(c{i} - 6) from fx where {where}").fetchall()[0][0])
    assert not got


@pytest.mark.parametrize("name", ["measure_cleaned_to_reach", "measure_model_error", "measure_ratio", "measure_reduction", "measure_reliability", "step_schedules", "w16_change_example"])
def test_measures_read_a_given_table(spark, small, name):
    files = QUERIES[name](spark, small).inputFiles()
    assert files and all(small in f for f in files)


def test_reversal_example(spark, small):
    slope = {r.method: r.value for r in surrounding.QUERIES["w12_reversal"](spark, small).collect()}
    assert slope["full_cleaning"] > 0.4 and slope["no_cleaning"] < 0


def test_workloads_are_registered():
    assert len(SLOW) == 18


def test_entry_imports_without_the_operator_folder():
    spec = importlib.util.spec_from_file_location("entry_copy", __file__.replace("tests/test_catalog.py", "__spark_entry__.py"))
    module = importlib.util.module_from_spec(spec)
    spec.loader.exec_module(module)
    module._llm = lambda: None
    assert set(module.queries()) == set(QUERIES) and set(module.oracle_sql()) == set(ORACLES)


def test_rules_see_rows_past_the_slices(spark, tmp_path):
    rows = [(1, 1, 1, 9.0), (5000, 2, 1, 9.0), (5001, 2, 2, 1.0), (5002, 2, 3, 8.0)]
    orders = spark.createDataFrame(rows, "o_orderkey long, o_custkey long, o_orderdate int, o_totalprice double")
    orders.write.parquet(f"{tmp_path}/orders.parquet")
    spark.createDataFrame([(1, "n", "a", 2), (2, "n", "b", 40), (3, "m", "a", 50)], "p_partkey long, p_name string, p_brand string, p_size int").write.parquet(f"{tmp_path}/part.parquet")
    spark.createDataFrame([(2,), (700,)], "c_custkey long").write.parquet(f"{tmp_path}/customer.parquet")
    brute = {a[0] for a in rows for b in rows if a[1] == b[1] and a[0] != b[0] and a[2] < b[2] and a[3] > 3 * b[3]}
    run = lambda n: QUERIES[n](spark, str(tmp_path)).collect()
    assert {r.o_orderkey for r in run("rule_denial")} == brute == {5000}
    assert {r.p_partkey for r in run("rule_functional") if r.broken} == {1, 2}
    assert sorted(r.c_custkey for r in run("set_operations")) == [2, 2, 700]


def test_all_rows_are_weighed(spark, small):
    rows = core.regression(spark, small)
    n, dirty = rows.count(), rows.where("is_dirty").count()
    assert QUERIES["weights_floored"](spark, small).count() == dirty
    assert QUERIES["grad_norms_per_row"](spark, small).count() == n
    assert not any("split = 0" in sql for sql in ORACLES.values())
