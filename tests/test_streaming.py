import numpy as np
from pyspark.sql import functions as F

from cleantrain.functions import losses
from cleantrain.operators import train
from cleantrain.sources.tables import LedgerTable, read_dirty_json
from cleantrain.streaming import streams


def _events(spark, small, tmp_path):
    rows = spark.read.parquet(f"{small}/events.parquet")
    rows.repartitionByRange(3, "ts").write.parquet(f"{tmp_path}/in")
    return rows, streams.event_stream(spark, f"{tmp_path}/in", rows.schema, delay="40 days")


def test_updates_from_a_stream_count_a_replayed_batch_once(spark, tmp_path):
    cleaned = spark.createDataFrame([(k, [1.0, float(k)], 2.0 * k, 0.1, 100, k) for k in range(1, 6)], "row_id long, x_c array<double>, y_c double, p double, n_dirty long, draw_order int")
    cleaned.write.parquet(f"{tmp_path}/cleaned")
    saved = {}
    updater = streams.StreamUpdater(losses.squared(), np.zeros(2), lambda t: (0, np.zeros(2)), train.Step.constant(0.1), lambda n, t: saved.update({n: t}))
    query = spark.readStream.schema(cleaned.schema).parquet(f"{tmp_path}/cleaned").writeStream.foreachBatch(updater).option("checkpointLocation", f"{tmp_path}/c").trigger(availableNow=True).start()
    query.awaitTermination()
    theta = updater.theta.copy()
    assert np.abs(theta).max() > 0 and np.allclose(saved[updater.last], theta)
    updater(cleaned, updater.last)
    assert np.allclose(updater.theta, theta)


def test_windows_sessions_and_repeats_equal_the_batch(spark, small, tmp_path):
    rows, stream = _events(spark, small, tmp_path)
    got = streams.run_to_memory(spark, streams.sessions(stream, "user_id", "30 minutes"), "sessions_result", f"{tmp_path}/c1", "complete")
    assert got.agg(F.sum("n")).first()[0] == rows.count()
    once = streams.run_to_memory(spark, streams.once_each(stream, "event_id"), "once_result", f"{tmp_path}/c2")
    assert once.count() == rows.select("event_id").distinct().count()
    static = spark.createDataFrame([("click", 1)], "event_type string, known int")
    joined = streams.run_to_memory(spark, streams.with_static(stream, static, "event_type"), "static_result", f"{tmp_path}/c3")
    assert joined.where("known = 1").count() == rows.where("event_type = 'click'").count()
    sliding = streams.run_to_memory(spark, streams.error_rates(streams.detect_stream(stream, F.col("value") > 100), "2 days", "1 day"), "sliding_result", f"{tmp_path}/c4", "complete")
    assert sliding.agg(F.sum("dirty")).first()[0] == 2 * rows.where("value > 100").count()


def test_two_streams_join_within_an_interval(spark, small, tmp_path):
    rows, stream = _events(spark, small, tmp_path)
    left = stream.where("event_type = 'click'").select("user_id", "ts")
    right = stream.where("event_type = 'error'").select("user_id", F.col("ts").alias("ts2"))
    got = streams.run_to_memory(spark, streams.joined_within(left, right, "user_id", 36000), "near_result", f"{tmp_path}/c5")
    a, b = rows.where("event_type = 'click'").select("user_id", "ts"), rows.where("event_type = 'error'").select(F.col("user_id").alias("u"), F.col("ts").alias("ts2"))
    want = a.join(b, (F.col("user_id") == F.col("u")) & (F.col("ts2") >= F.col("ts")) & (F.col("ts2") <= F.col("ts") + F.expr("interval 36000 seconds")))
    assert got.count() == want.count()


def test_ledger_counts_marked_iterations_only(spark, tmp_path):
    ledger = LedgerTable(spark, f"{tmp_path}/ledger")
    rows = spark.range(3).withColumnRenamed("id", "row_id")
    ledger.append("r", 1, rows)
    ledger.append("r", 1, rows)  # a retry
    rows.write.parquet(f"{tmp_path}/ledger/rows/run_id=r/iteration=2")  # broke off before its mark
    assert ledger.read("r").count() == 3


def test_malformed_json_is_kept(spark, tmp_path):
    spark.createDataFrame([('{"k": 1}',), ("{oops",)], "value string").write.text(f"{tmp_path}/j")
    got = read_dirty_json(spark, f"{tmp_path}/j", "k int").orderBy("k").collect()
    assert [(r.k, r._corrupt) for r in got] == [(None, "{oops"), (1, None)]
