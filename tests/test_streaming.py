import pytest
from pyspark.sql import functions as F

from coverdistinct.operators import counters, estimators, fused, sampling
from coverdistinct.sources import streams
from coverdistinct.streaming import live

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def rows(spark, times, first=0):
    return spark.createDataFrame([(first + i, t, i % 3, "a", 0.0, "{}") for i, t in enumerate(times)], "event_id long, ts string, user_id long, event_type string, value double, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))


def test_replayed_batches_change_nothing(spark, sf, tmp_path):
    x = streams.load(spark, sf, "user").cache()
    r = live.Running(f"file://{tmp_path}/state", m=50, u=100)
    a, b = x.where("crc32(occ) % 2 = 0"), x.where("crc32(occ) % 2 = 1")
    for batch, i in ((a, 0), (b, 1), (b, 1)):
        r.fold(batch, i)
    got, want = r.estimate(spark).first(), estimators.estimate_subsampled(x, 100, counters.HyperLogLog(50)).first()
    assert got["l"] == x.count() and got["ns_hat"] == pytest.approx(want["ns_hat"]) and got["n_hat"] == pytest.approx(want["n_hat"])


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    for i, (name, times) in enumerate((("a", ["2024-01-01 00:00:00", "2024-01-01 01:00:00"]), ("b", ["2024-03-01 00:00:00"]), ("c", ["2024-01-01 02:00:00"]), ("d", ["2024-06-01 00:00:00"]))):
        rows(spark, times, 10 * i).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        q = live.window_sampled(live.source(spark, f"{tmp_path}/in")).writeStream.format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/log").trigger(availableNow=True).start()
        q.awaitTermination()
        if name == "c":
            assert live.late_rows(q) == 1
    out = {str(r["start"])[:10]: r["l"] for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    assert out["2023-12-28"] == 2 and sum(out.values()) == 3


def test_the_fused_scan_gives_the_same_row(spark, sf):
    y = sampling.bernoulli(streams.load(spark, sf, "order_key"), 0.2, fast=True)
    hll = counters.HyperLogLog(100, fast=True)
    a, b = fused.fused(y.repartition(5), 150, hll, 0.2).first(), estimators.estimate_subsampled(y, 150, hll, rate=0.2, fast=True).first()
    assert {k: round(v, 9) if isinstance(v, float) else v for k, v in a.asDict().items()} == {k: round(v, 9) if isinstance(v, float) else v for k, v in b.asDict().items()}
    assert fused.fused(y.where("false"), 10, hll).first()["status"] == "empty_sample"


def test_a_stored_hash_reads_the_leading_partitions_alone(spark, sf, tmp_path):
    df = spark.read.parquet(f"{sf}/orders.parquet")
    fused.write_hashed(df, F.col("o_orderkey").cast("string"), f"{tmp_path}/h")
    got = fused.read_sample(spark, f"{tmp_path}/h", 0.1)
    want = sampling.bernoulli(streams.load(spark, sf, "cust_key"), 0.1, fast=True)
    assert sorted(str(r["o_orderkey"]) for r in got.collect()) == sorted(r["occ"] for r in want.collect())
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "<= 25)" in plan.split("PartitionFilters:")[1].split("]")[0]  # 26 of 256 folders


def test_parts_are_added_until_the_interval_is_narrow(spark, sf):
    x = streams.load(spark, sf, "user")
    parts = [x.where(f"crc32(occ) % 10 = {i}") for i in range(10)]
    out, used = fused.estimate_until(iter(parts), 0.6, counters.HyperLogLog(500))
    assert 1 <= used <= 10 and out.first()["status"] == "ok"
