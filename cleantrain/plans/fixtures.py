"""Experiment inputs on the given tables, with SQL twins: planted targets, injected corruption, and the clean truth.

The star tables' measures are independent of each other, so targets are planted: y follows a fixed theta and hashed noise.
Corruption leaves the clean row beside the dirty one. Nothing is drawn at random at run time.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.portable import hashed_id, hashed_id_sql, noise, noise_sql, uniform, uniform_sql
from ..functions.vectors import add_all
from ..operators.features import Featurizer
from ..sources.scratch import scratch_table
from ..sources.tables import read_table

#: Column, centre and scale of each covariate after the intercept.
LINE = (("l_quantity", 25.5, 14.4), ("l_extendedprice", 50000.0, 29000.0), ("l_discount", 0.05, 0.0316), ("l_tax", 0.04, 0.0258), ("l_linenumber", 4.0, 2.0))
PLANTED = (2.0, -1.5, 1.0, 0.5, -0.25, 0.3)
SIGMA = 0.5
D = len(PLANTED)
RATE, SPIKE = 0.05, 6.0
#: The point at which gradients are compared with SQL.
THETA = (1.5, -1.0, 0.5, 0.25, 0.5, -0.5)


def row_key():
    return F.concat_ws("|", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")], F.round(F.col("l_extendedprice") * 100).cast("long").cast("string"))


def regression(spark: SparkSession, sf_dir: str) -> DataFrame:
    """row_id, split, x_c, y, y01, ypm, x (dirty), is_dirty, err_features, class_id from lineitem.

    5 % of rows have one covariate at SPIKE; class_id is the number of that covariate, 0 for clean rows.
    """
    raw = read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", *[c for c, _, _ in LINE if c != "l_linenumber"]])
    rows = raw.select(row_key().alias("rk"), *[((F.col(c) - m) / s).alias(f"c{i}") for i, (c, m, s) in enumerate(LINE, 1)])
    score = F.lit(PLANTED[0]) + add_all([F.col(f"c{i}") * PLANTED[i] for i in range(1, D)])
    rows = rows.withColumn("row_id", hashed_id(F.col("rk"))).withColumn("y", score + SIGMA * noise("rk", "y"))
    hit = uniform("rk", "err") < RATE
    rows = rows.withColumn("class_id", F.when(hit, (F.floor(uniform("rk", "feature") * (D - 1)) + 1).cast("int")).otherwise(0))
    x_c = F.array(F.lit(1.0), *[F.col(f"c{i}") for i in range(1, D)])
    x = F.array(F.lit(1.0), *[F.when(F.col("class_id") == i, SPIKE).otherwise(F.col(f"c{i}")) for i in range(1, D)])
    return rows.select(
        "row_id", F.floor(uniform("rk", "split") * 5).cast("int").alias("split"), x_c.alias("x_c"), x.alias("x"), "y", F.col("y").alias("y_c"),
        (F.col("y") > PLANTED[0]).cast("double").alias("y01"), F.when(F.col("y") > PLANTED[0], 1.0).otherwise(-1.0).alias("ypm"), (F.col("class_id") > 0).alias("is_dirty"),
        F.when(F.col("class_id") > 0, F.array("class_id")).otherwise(F.array().cast("array<int>")).alias("err_features"), "class_id",
    )


def regression_sql() -> str:
    """The CTE fx of the same rows: c0..c5 clean, d0..d5 dirty."""
    clean = ", ".join(f"({c} - {m!r}::double) / {s!r}::double as c{i}" for i, (c, m, s) in enumerate(LINE, 1))
    score = " + ".join([f"{PLANTED[0]!r}::double", *[f"c{i} * {PLANTED[i]!r}::double" for i in range(1, D)]])
    dirty = ", ".join(f"case when class_id = {i} then {SPIKE!r}::double else c{i} end as d{i}" for i in range(1, D))
    return f"""fx1 as (select concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, round(l_extendedprice * 100)::bigint) as rk, 1::double as c0, {clean} from lineitem),
fx2 as (select *, {hashed_id_sql('rk')} as row_id, ({score}) + {SIGMA!r}::double * {noise_sql('rk', 'y')} as y,
  case when {uniform_sql('rk', 'err')} < {RATE!r}::double then (floor({uniform_sql('rk', 'feature')} * {D - 1}) + 1)::int else 0 end as class_id, floor({uniform_sql('rk', 'split')} * 5)::int as split from fx1),
fx as (select *, 1::double as d0, {dirty}, case when y > {PLANTED[0]!r}::double then 1::double else 0::double end as y01, case when y > {PLANTED[0]!r}::double then 1::double else -1::double end as ypm from fx2)"""


#: Rows up to which a table of the star is sent to all executors whole; larger ones are dealt out by their key.
SENT_ROWS = 1_500_000


def _side(rows: DataFrame) -> DataFrame:
    """A side table of a join: broadcast where its count, which Parquet's footers give, is bounded; else hashed part by part, not sorted."""
    return F.broadcast(rows) if rows.count() <= SENT_ROWS else rows.hint("shuffle_hash")


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its part, supplier, order and customer; only the columns used are read. Customers meet orders first, so
    lineitem is dealt out by its order alone while the other tables are bounded. Keys are made after the joins: no text is shuffled for them."""
    line = read_table(spark, sf_dir, "lineitem").drop("l_linestatus")
    part = read_table(spark, sf_dir, "part", ["p_partkey", "p_name", "p_type", "p_size", "p_retailprice"])
    supplier = read_table(spark, sf_dir, "supplier", ["s_suppkey", "s_name", "s_acctbal", "s_nationkey"])
    order = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey", "o_totalprice", "o_orderdate", "o_orderpriority"])
    customer = read_table(spark, sf_dir, "customer", ["c_custkey", "c_acctbal", "c_mktsegment", "c_nationkey"])
    order = order.join(_side(customer), F.col("o_custkey") == F.col("c_custkey"))
    out = line.join(order.hint("shuffle_hash"), F.col("l_orderkey") == F.col("o_orderkey"))
    out = out.join(_side(part), F.col("l_partkey") == F.col("p_partkey")).join(_side(supplier), F.col("l_suppkey") == F.col("s_suppkey"))
    return out.withColumn("rk", row_key()).withColumn("row_id", hashed_id(F.col("rk")))


INCOME = (["l_quantity", "l_extendedprice", "l_discount", "l_tax", "p_size", "p_retailprice", "c_acctbal", "o_totalprice"], ["l_returnflag", "c_mktsegment", "p_type", "o_orderpriority"])
SEIZURE = (["l_quantity", "l_extendedprice", "l_discount", "l_tax", "p_size", "p_retailprice", "c_acctbal", "o_totalprice", "s_acctbal", "l_linenumber", "ship_lag", "order_day", "ship_day", "s_nationkey"], [])


def covariates(spark: SparkSession, sf_dir: str, skewed: bool = True) -> DataFrame:
    """row_id, split, noise, and the covariates of both classifications as columns, written down once: the joins and the
    hashes are made once for all that is fitted, and a column of few values takes few bytes.

    skewed: the first covariates are squared before scaling, so that cutting their tops off matters.
    """
    rows = star(spark, sf_dir).withColumn("ship_lag", F.datediff(F.to_date("l_shipdate"), F.to_date("o_orderdate")).cast("double")).withColumn("order_day", F.dayofyear("o_orderdate").cast("double")).withColumn("ship_day", F.dayofyear("l_shipdate").cast("double"))
    names = list(dict.fromkeys(INCOME[0] + SEIZURE[0] + INCOME[1] + SEIZURE[1]))
    squared = INCOME[0][:4] if skewed else []
    columns = [(F.col(c) * F.abs(F.col(c))).alias(c) if c in squared else F.col(c) for c in names]
    return scratch_table(rows.select("row_id", F.floor(uniform("rk", "split") * 5).cast("int").alias("split"), noise("rk", "label").alias("noise"), *columns))


def classification(table: DataFrame, kind: str = "income", sigma: float | None = None) -> tuple[Callable[[DataFrame], DataFrame], int]:
    """(what adds x clean and y planted in {-1, 1} to the rows of `covariates`; size of x). `seizure` has more noise: about
    65 % clean accuracy. Each reader works x and y out of the columns, which takes less than reading them: no matrix is written.
    """
    numeric, categorical = INCOME if kind == "income" else SEIZURE
    features = Featurizer(list(numeric), list(categorical)).fit(table)
    sigma = (0.5 if kind == "income" else 4.0) if sigma is None else sigma
    theta = [0.0] + [(1.6, -1.2, 0.9, 0.7, -0.5, 0.4, 0.3, -0.2)[i % 8] / (1 + i // 8) for i in range(features.size - 1)]
    score = add_all([F.get("x", F.lit(i)) * t for i, t in enumerate(theta)]) + sigma * F.col("noise")
    return lambda rows: rows.withColumn("x", features.vector()).withColumn("y", F.when(score > 0, 1.0).otherwise(-1.0)), features.size


def images(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings as 8 x 8 grids: row_id, x, label, planted (the largest of ten fixed projections)."""
    rows = read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("row_id"), F.col("embedding").cast("array<double>").alias("x"), "label")
    from .projections import PROJECTIONS

    scores = F.array(*[add_all([F.get("x", F.lit(i)) * p for i, p in enumerate(row)]) for row in PROJECTIONS])
    return rows.withColumn("planted", F.array_position(scores, F.array_max(scores)).cast("int") - 1)


def contributions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Company payments: specialty, drug_name or device_name, corporation, amount, dispute, and a planted status that depends on the name."""
    rows = star(spark, sf_dir)
    drug = F.col("p_type").isin("SMALL", "PROMO", "ECONOMY")
    bad = uniform("rk", "status") < F.when(F.col("p_name").rlike("ring|gear|gizmo"), 0.45).otherwise(0.05)
    return rows.select(
        "row_id", F.col("c_mktsegment").alias("specialty"), F.when(drug, F.col("p_name")).alias("drug_name"), F.when(~drug, F.col("p_name")).alias("device_name"), F.col("s_name").alias("corporation"),
        F.col("l_extendedprice").alias("amount"), (F.col("l_returnflag") == "R").alias("dispute"), F.when(bad, "not covered").otherwise("covered").alias("status"),
    )


def customer_groups(spark: SparkSession, sf_dir: str, keys: tuple[str, ...] = ("c_custkey",), cutoff: str = "1999-01-01") -> DataFrame:
    """n orders, total and stale total (orders before the cutoff) in millions, by customer or by nation and segment."""
    order = read_table(spark, sf_dir, "orders", ["o_custkey", "o_totalprice", "o_orderdate"])
    customer = read_table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey", "c_mktsegment"])
    rows = order.join(customer, F.col("o_custkey") == F.col("c_custkey"))
    old = F.col("o_orderdate") < F.lit(cutoff).cast("timestamp_ntz")
    return rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), (F.sum("o_totalprice") / 1e6).alias("total"), (F.coalesce(F.sum(F.when(old, F.col("o_totalprice"))), F.lit(0.0)) / 1e6).alias("stale_total"))
