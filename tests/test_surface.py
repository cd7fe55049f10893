import pytest
from pyspark.sql import functions as F

from veilstream import observe
from veilstream.plans import replay
from veilstream.sources import tables
from veilstream.spec import TEST_SECRET, Measure, StreamSpec, Timing
from veilstream.surface import PrivateHistogram


def builder(spark, sf):
    rec = tables.line_records(spark, sf).withColumn("flag", F.col("key").cast("int") % 2)
    return PrivateHistogram(rec).unit("unit").keys("key", "flag").record_id("record_id").bound(10).triggers(8).secret(TEST_SECRET)


def test_builder_releases_what_replay_releases(spark, sf):
    got = builder(spark, sf).count().sum("l_quantity", 20, "qty").releases()
    assert got.columns == ["key", "flag", "trigger_idx", "round", "cause", "users_hat", "count_hat", "qty_hat"]
    rec = tables.line_records(spark, sf).withColumn("key", F.to_json(F.struct("key", (F.col("key").cast("int") % 2).alias("flag"))))
    spec = StreamSpec(secret=TEST_SECRET, bound=10, timing=Timing(8), measures=(Measure("count"), Measure("qty", "l_quantity", 20.0)))
    want = replay.run(rec, spec).withColumn("key", F.get_json_object("key", "$.key"))
    rows = sorted(map(tuple, got.drop("flag").collect()))
    assert rows and rows == sorted(map(tuple, want.collect()))


def test_what_has_no_bound_is_refused(spark, sf):
    b = builder(spark, sf)
    for bad in (lambda: b.aggregate("median", "l_quantity", 1), lambda: b.session("event_ts", 60), lambda: b.window("event_ts", 100, 30), lambda: PrivateHistogram(b.records).releases()):
        with pytest.raises(ValueError):
            bad()


def test_sliding_windows_pay_for_their_overlap(spark, sf):
    b = builder(spark, sf).count().window("event_ts", 86_400 * 4, 86_400)
    assert b.overlap == 4 and b.calibrated().bound == 40
    one = b.bounded().groupBy("record_id").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("window_start").alias("w")).select("n", "w").distinct().collect()
    assert [tuple(r) for r in one] == [(4, 4)]
    assert {r.component for r in b.ledger().collect()} >= {"gate tree", "value count", "total"}


def test_derived_aggregates_come_from_sums(spark, sf):
    out = builder(spark, sf).avg("l_quantity", 50).variance("l_quantity", 50).releases()
    assert {"avg_l_quantity_hat", "variance_l_quantity_hat"} <= set(out.columns)
    assert out.filter("variance_l_quantity_hat < 0").count() == 0


def test_latency_rows_and_scaling(spark, sf, tmp_path):
    rec = tables.line_records(spark, sf)
    times = observe.latency_grid({1.0: rec}, StreamSpec(secret=TEST_SECRET, bound=10, timing=Timing(8)), str(tmp_path), triggers=1, runs=1)
    assert times.count() == 1 and times.filter("millis > 0 and rows > 0").count() == 1
    made = spark.createDataFrame([(1.0, 4, 0, 1, 100, 50.0), (5.0, 4, 0, 1, 500, 85.0), (5.0, 8, 0, 1, 500, 51.0), (1.0, 8, 0, 1, 100, 40.0)], observe.TIMES)
    rows = {r.cores: r for r in observe.scaling(observe.latency(made)).collect()}
    assert rows[4].data_growth == 5 and round(rows[4].latency_growth, 6) == 1.7 and round(rows[4].cut_by_cores, 6) == 0.4
