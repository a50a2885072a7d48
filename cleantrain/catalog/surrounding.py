"""Queries on the operators around training: joins, windows, aggregates, functions, files and streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors
from ..operators import features, joins
from ..plans.experiments import WORKLOADS
from ..sources.tables import read_dirty_csv, read_table
from ..streaming import streams
from .core import r6, s6

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return add


@query("select l_returnflag, count(*)::bigint as n, round(sum(l_quantity), 2) + 0.0::double as quantity from lineitem where l_quantity < 24 and l_discount between 0.05::double and 0.07::double group by 1")
def scan_pruned(spark, sf_dir):
    rows = read_table(spark, sf_dir, "lineitem", ["l_returnflag", "l_quantity", "l_discount"], "l_quantity < 24 and l_discount between 0.05d and 0.07d")
    return rows.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), (F.round(F.sum("l_quantity"), 2) + 0.0).alias("quantity"))


AS_OF = "select e.event_id, (select arg_max(v.value, v.ts) from events v where v.user_id = e.user_id and v.event_type = 'error' and v.ts <= e.ts) as value_before from events e where e.event_type = 'click'"


@query(AS_OF)
def join_as_of(spark, sf_dir):
    events = read_table(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type", "value"])
    left = events.where("event_type = 'click'").select("event_id", "user_id", "ts")
    return joins.as_of(left, events.where("event_type = 'error'").select("user_id", "ts", "value"), "user_id", "ts", "value").select("event_id", "value_before")


@query("select a.event_id, b.event_id as r_event_id from events a join events b on a.user_id = b.user_id and abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 600000000 where a.event_type = 'click' and b.event_type = 'error'")
def join_interval(spark, sf_dir):
    events = read_table(spark, sf_dir, "events", ["event_id", "user_id", "ts", "event_type"])
    return joins.within(events.where("event_type = 'click'").drop("event_type"), events.where("event_type = 'error'").drop("event_type"), "user_id", "ts", 600).select("event_id", "r_event_id")


@query("select p_partkey, case when p_size < 10 then 'small' when p_size < 30 then 'middle' when p_size < 50 then 'large' end as name from part")
def join_ranges(spark, sf_dir):
    bounds = spark.createDataFrame([("small", 0, 10), ("middle", 10, 30), ("large", 30, 50)], "name string, low int, high int")
    return joins.in_ranges(read_table(spark, sf_dir, "part", ["p_partkey", "p_size"]), "p_size", F.broadcast(bounds)).select("p_partkey", "name")


@query("select c.c_custkey, case when c_custkey % 7 = 0 then 'FIXED' else c_mktsegment end as c_mktsegment from customer c")
def join_write_back(spark, sf_dir):
    rows = read_table(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment"])
    return joins.write_back(rows, rows.where("c_custkey % 7 = 0").withColumn("c_mktsegment", F.lit("FIXED")), "c_custkey", "c_mktsegment")


@query("select c_custkey from customer where c_custkey not in (select o_custkey from orders where o_orderstatus = 'F')")
def join_anti(spark, sf_dir):
    """Customers without a finished order; each has some order, so the bare join would compare nothing."""
    orders = read_table(spark, sf_dir, "orders", ["o_custkey", "o_orderstatus"]).where("o_orderstatus = 'F'")
    return read_table(spark, sf_dir, "customer", ["c_custkey"]).join(orders, F.col("c_custkey") == F.col("o_custkey"), "left_anti")


@query("select 'c_mktsegment' as \"column\", count(*) filter (where c_custkey % 7 = 0)::bigint as changed from customer union all select 'c_nationkey', 0::bigint")
def join_differences(spark, sf_dir):
    rows = read_table(spark, sf_dir, "customer", ["c_custkey", "c_mktsegment", "c_nationkey"])
    clean = rows.withColumn("c_mktsegment", F.when(F.col("c_custkey") % 7 == 0, "FIXED").otherwise(F.col("c_mktsegment")))
    return joins.cell_differences(rows, clean, "c_custkey", ["c_mktsegment", "c_nationkey"])


@query("select l_returnflag, l_linestatus, count(*)::bigint as n, grouping(l_returnflag)::int as g1, grouping(l_linestatus)::int as g2 from lineitem group by cube(l_returnflag, l_linestatus)")
def aggregate_cube(spark, sf_dir):
    rows = read_table(spark, sf_dir, "lineitem", ["l_returnflag", "l_linestatus"])
    return rows.cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.grouping("l_returnflag").cast("int").alias("g1"), F.grouping("l_linestatus").cast("int").alias("g2"))


@query(f"select c_mktsegment, {s6('avg(c_acctbal) / 1000')} as mean, {s6('stddev_samp(c_acctbal) / 1000')} as sd, {s6('quantile_cont(c_acctbal, 0.25) / 1000')} as q, min(c_nationkey)::int as lo, count(distinct c_nationkey)::bigint as nations from customer group by 1")
def aggregate_moments(spark, sf_dir):
    a = lambda c: r6(c / 1000)
    return read_table(spark, sf_dir, "customer").groupBy("c_mktsegment").agg(a(F.avg("c_acctbal")).alias("mean"), a(F.stddev_samp("c_acctbal")).alias("sd"), a(F.percentile("c_acctbal", F.lit(0.25))).alias("q"), F.min("c_nationkey").alias("lo"), F.count_distinct("c_nationkey").alias("nations"))


@query("select o_custkey, o_orderkey, row_number() over w as k, coalesce(lag(o_orderkey) over w, -1) as before, rank() over (partition by o_custkey order by o_orderpriority) as r from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)")
def window_functions(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    rows = read_table(spark, sf_dir, "orders", ["o_custkey", "o_orderkey", "o_orderdate", "o_orderpriority"])
    return rows.select("o_custkey", "o_orderkey", F.row_number().over(w).alias("k"), F.coalesce(F.lag("o_orderkey").over(w), F.lit(-1)).alias("before"), F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("r"))


@query("select o_orderpriority, count(*) filter (where o_orderstatus = 'F')::bigint as \"F\", count(*) filter (where o_orderstatus = 'O')::bigint as \"O\", count(*) filter (where o_orderstatus = 'P')::bigint as \"P\" from orders group by 1")
def pivot_status(spark, sf_dir):
    return read_table(spark, sf_dir, "orders", ["o_orderpriority", "o_orderstatus"]).groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0)


@query("select event_id, (props::json->>'k')::bigint as k from events")
def json_fields(spark, sf_dir):
    return read_table(spark, sf_dir, "events", ["event_id", "props"]).select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("select o_orderkey, year(o_orderdate)::int as y, month(o_orderdate)::int as m, dayofyear(o_orderdate)::int as d, date_diff('day', date '1995-01-01', o_orderdate::date)::int as days from orders")
def date_parts(spark, sf_dir):
    return read_table(spark, sf_dir, "orders", ["o_orderkey", "o_orderdate"]).select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.dayofyear("o_orderdate").alias("d"), F.datediff(F.to_date("o_orderdate"), F.lit("1995-01-01").cast("date")).alias("days"))


@query("select c_custkey from (select c_custkey from customer intersect select o_custkey from orders) union all select c_custkey from customer")
def set_operations(spark, sf_dir):
    customer, orders = read_table(spark, sf_dir, "customer", ["c_custkey"]), read_table(spark, sf_dir, "orders", ["o_custkey"])
    return customer.intersect(orders.select(F.col("o_custkey").alias("c_custkey"))).union(customer)


@query("select 'p_name' as \"column\", count(*) filter (where p_name is null)::bigint as nulls, count(distinct p_name)::bigint as distinct_values from part union all select 'p_brand', count(*) filter (where p_brand is null)::bigint, count(distinct p_brand)::bigint from part")
def profile_columns(spark, sf_dir):
    return joins.null_profile(read_table(spark, sf_dir, "part", ["p_name", "p_brand"]))


@query("select p_name, count(*)::bigint as n from part group by 1 having count(*) > 1")
def profile_duplicates(spark, sf_dir):
    return joins.duplicate_groups(read_table(spark, sf_dir, "part", ["p_name"]), ["p_name"])


@query("with t as (select p_partkey, unnest(string_split(p_name, ' ')) as token from part), tf as (select p_partkey, token, count(*) as tf from t group by 1, 2), df as (select token, count(*) as df from tf group by 1) select p_partkey, token, tf::bigint as tf, df::bigint as df, " + s6("tf * ln((select count(*) from part) / df)") + " as tfidf from tf join df using (token)")
def text_tf_idf(spark, sf_dir):
    return features.tf_idf(read_table(spark, sf_dir, "part", ["p_partkey", "p_name"]), "p_partkey", "p_name").select("p_partkey", "token", "tf", "df", r6(F.col("tfidf")).alias("tfidf"))


@query("select p_partkey, " + s6("(p_retailprice - (select min(p_retailprice) from part)) / ((select max(p_retailprice) from part) - (select min(p_retailprice) from part))") + " as price from part")
def feature_min_max(spark, sf_dir):
    return features.min_max(read_table(spark, sf_dir, "part", ["p_partkey", "p_retailprice"]), "p_retailprice").select("p_partkey", r6(F.col("p_retailprice_mm")).alias("price"))


@query("select vec_id, " + s6("list_sum(list_transform(embedding, lambda v: v::double * v::double))") + " as square, " + s6("sqrt(list_sum(list_transform(embedding, lambda v: v::double * v::double)))") + " as norm from embeddings")
def sql_functions(spark, sf_dir):
    vectors.register(spark)
    read_table(spark, sf_dir, "embeddings").createOrReplaceTempView("embeddings_for_functions")
    return spark.sql("select vec_id, round(dot(cast(embedding as array<double>), cast(embedding as array<double>)), 6) + 0d as square, round(l2norm(cast(embedding as array<double>)), 6) + 0d as norm from embeddings_for_functions")


@query("select r_regionkey::int as r_regionkey, r_name, null::varchar as _corrupt from region union all select -1, null, 'oops,ASIA,7'")
def files_dirty_csv(spark, sf_dir):
    from ..sources.scratch import scratch_path

    at = scratch_path(spark)
    region = read_table(spark, sf_dir, "region")
    region.select(F.concat_ws(",", "r_regionkey", "r_name").alias("value")).union(spark.range(1).select(F.lit("oops,ASIA,7"))).write.text(at)
    rows = read_dirty_csv(spark, at, "r_regionkey int, r_name string", header=False)
    return rows.select(F.coalesce("r_regionkey", F.lit(-1)).alias("r_regionkey"), F.when(F.col("_corrupt").isNull(), F.col("r_name")).alias("r_name"), "_corrupt")


def _stream(spark, sf_dir) -> DataFrame:
    from ..sources.scratch import scratch_path

    at = scratch_path(spark)
    rows = read_table(spark, sf_dir, "events")
    rows.repartitionByRange(4, "ts").write.parquet(at)
    return streams.detect_stream(streams.event_stream(spark, at, rows.schema, files=10, delay="40 days"), F.col("value") > 100)


@query("select time_bucket(interval '1 day', ts) as start, count(*)::bigint as n, count(*) filter (where value > 100)::bigint as dirty from events group by 1")
def stream_error_rates(spark, sf_dir):
    from ..sources.scratch import scratch_path

    rows = streams.error_rates(_stream(spark, sf_dir), "1 day")
    return streams.run_to_memory(spark, rows, "stream_error_rates_result", scratch_path(spark), "complete").select(F.col("start").cast("timestamp_ntz").alias("start"), "n", "dirty")


# The small constant moves means off the rounding boundary, where a float's last bit would decide.
@query(f"select user_id, count(*)::bigint as n, {s6('avg(value) / 100 + 0.000000012345::double')} as theta from events group by 1")
def stream_running_means(spark, sf_dir):
    from ..sources.scratch import scratch_path

    rows = streams.running_means(_stream(spark, sf_dir).drop("is_dirty"), "user_id", "value")
    out = streams.run_to_memory(spark, rows, "stream_running_means_result", scratch_path(spark), "update")
    return out.groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("theta", "n").alias("theta")).select("user_id", "n", r6(F.col("theta") / 100 + 0.000000012345).alias("theta"))


QUERIES |= WORKLOADS
