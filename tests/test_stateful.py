from pyspark.sql import functions as F

from veilstream.operators import timing
from veilstream.plans import replay
from veilstream.sources import tables
from veilstream.spec import TEST_SECRET, Budget, GateConfig, Measure, StreamSpec, Timing
from veilstream.streaming import stateful


def strip(rows):
    return sorted((tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in rows), key=repr)


def files_by_trigger(rec, base, ticks, order):
    for i in ticks:
        rec.filter(order == i).drop("_tick").coalesce(1).write.mode("append").parquet(base)
    return rec.sparkSession.readStream.schema(rec.drop("_tick").schema).option("maxFilesPerTrigger", 1).parquet(base)


def test_the_whole_mechanism_on_a_stream_releases_what_replay_releases(spark, sf, tmp_path):
    for k, gate in enumerate((GateConfig(), GateConfig(count_mode="round_distinct"))):
        spec = StreamSpec(secret=TEST_SECRET, bound=6, timing=Timing(6), gate=gate, measures=(Measure("count"), Measure("qty", "l_quantity", 20.0)))
        rec = timing.assign_triggers(tables.line_records(spark, sf), 6).filter("key <> '3' or trigger_idx < 5")
        rec = rec.withColumn("key", F.nullif("key", F.lit("5"))).withColumn("unit", F.nullif("unit", F.lit(7)))
        want = replay.run(rec, spec).collect()
        end = rec.limit(1).withColumn("key", F.lit("")).withColumn("trigger_idx", F.lit(8)).withColumn("record_id", F.lit("end")).withColumn("unit", F.lit(-1).cast("long"))
        source = files_by_trigger(rec.unionByName(end), str(tmp_path / f"in{k}"), (1, 2, 3, 4, 5, 6, 8), F.col("trigger_idx"))
        got = stateful.run(source, spec, str(tmp_path / f"run{k}")).collect()
        assert want and strip(map(tuple, got)) == strip(map(tuple, want))


def test_windows_of_a_stream_have_their_own_trees(spark, sf, tmp_path):
    spec = StreamSpec(secret=TEST_SECRET, bound=2, timing=Timing(3, "arrival", window_s=3600 * 24 * 30), budget=Budget(eps=90, delta=1e-2))
    ev = tables.event_records(spark, sf).withColumn("event_ts", F.col("event_ts").cast("timestamp")).withColumn("arrival_ts", F.col("event_ts"))
    rec = timing.in_time(ev, spec.timing).withColumn("unit", F.concat_ws(":", "unit", "window_start"))  # a user and window is a unit
    rec = rec.select("window_start", "unit", "key", F.format_string("%08d", "record_id").alias("record_id"), "trigger_idx")
    want = replay.run(rec, spec).collect()
    assert len({r.window_start for r in want}) == 2
    later = [(r.window_start, r.trigger_idx) for r in rec.select("window_start", "trigger_idx").distinct().orderBy("window_start", "trigger_idx").collect()]
    tick = F.array_position(F.lit([f"{w} {i}" for w, i in later]), F.concat_ws(" ", F.col("window_start").cast("string"), F.col("trigger_idx").cast("string")))
    end = rec.limit(1).withColumn("window_start", F.lit(later[-1][0])).withColumn("key", F.lit("")).withColumn("trigger_idx", F.lit(5)).withColumn("unit", F.lit("end"))
    rec = rec.withColumn("_tick", tick).unionByName(end.withColumn("_tick", F.lit(len(later) + 1).cast("long")))
    got = stateful.run(files_by_trigger(rec, str(tmp_path / "in"), range(1, len(later) + 2), F.col("_tick")), spec, str(tmp_path / "run")).collect()
    assert strip(map(tuple, got)) == strip(map(tuple, want))
