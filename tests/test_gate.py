import pytest
from pyspark.sql import functions as F

from veilstream.functions.calibrate import Plan
from veilstream.operators import aggregate, baselines, bounding, metrics, timing, tuning
from veilstream.operators.gate import KeyGate
from veilstream.plans import replay
from veilstream.sources import synth, tables
from veilstream.spec import TEST_SECRET, Budget, GateConfig, Measure, StreamSpec, Timing
from veilstream.streaming import microbatch


def scripted(taus, gate=GateConfig(), noise=None):
    """A gate whose noise is 0 and whose thresholds are given."""
    g = KeyGate(Plan(len(taus), 0.0, tuple(taus), (0.0,), 0, 0, 0), gate, "s", ("count",), "k")
    return g


def test_silent_release_then_a_new_round():
    g = scripted([99, 99, 99, 2, 99, 2, 99, 99])
    assert g.arrive(2, 5, [5.0], 5) == []
    assert g.forecast() == 4
    out = g.arrive(6, 3, [3.0], 3)
    assert [(r[0], r[1], r[2], r[3], r[4]) for r in out] == [(4, 1, "silent", 5.0, 5.0), (6, 2, "arrival", 3.0, 8.0)]


def test_arrival_before_the_forecast_discards_it():
    g = scripted([99] * 6 + [2, 99])
    g.arrive(2, 5, [5.0], 5)
    assert g.forecast() == 7
    assert g.arrive(6, 1, [1.0], 1) == []
    assert g.state.users == 6 and g.forecast() == 7


def test_arrival_wins_a_tie_with_the_forecast():
    g = scripted([99, 99, 2, 99])
    g.arrive(1, 5, [5.0], 5)
    assert g.forecast() == 3
    out = g.arrive(3, 1, [1.0], 1)
    assert [(r[0], r[2], r[3]) for r in out] == [(3, "arrival", 6.0)]


def test_pre_threshold_is_strict():
    for users, shown in ((3, 0), (4, 1)):
        g = scripted([0], GateConfig(mu=3))
        assert len(g.arrive(1, users, [1.0], 1)) == shown
    assert len(scripted([-1], GateConfig(mu=3, pre_inclusive=True)).arrive(1, 3, [1.0], 1)) == 1


def test_bare_gate_keeps_its_users():
    g = scripted([2, 2, 2], GateConfig(restart=False))
    rows = g.arrive(1, 5, [5.0], 5) + g.silent_until(3)
    assert [(r[0], r[1], r[3]) for r in rows] == [(1, 1, 5.0), (2, 1, 5.0), (3, 1, 5.0)]


def test_round_distinct_counts_a_unit_once_a_round():
    g = scripted([99, 99, 1, 99], GateConfig(count_mode="round_distinct"))
    g.arrive(1, 2, [2.0], 2, [(0, 2)])  # a, b
    g.arrive(2, 2, [2.0], 2, [(0, 1), (1, 1)])  # b again, c
    assert g.state.users == 3
    assert g.arrive(3, 1, [1.0], 1, [(1, 1)])[0][3] == 3  # a again: a new round begins
    g.arrive(4, 2, [2.0], 2, [(2, 1), (3, 1)])  # c and a count anew
    assert g.state.users == 2


def frame(spark, rows):
    return spark.createDataFrame(rows, "unit long, key string, record_id string, trigger_idx int, v double")


def test_bounding_keeps_the_first_and_touches_no_other_unit(spark):
    rows = [(1, "a", f"r{i}", 1 + i // 3, 1.0) for i in range(8)] + [(2, "b", "x", 1, 1.0)]
    got = {r.record_id for r in bounding.bound_records(frame(spark, rows), 5).collect()}
    assert got == {"r0", "r1", "r2", "r3", "r4", "x"}
    alone = {r.record_id for r in bounding.bound_records(frame(spark, rows[:8]), 5).collect()}
    assert got - alone == {"x"}


def test_clamp_and_nulls(spark):
    rows = [(i, "a", str(i), 1, v) for i, v in enumerate([-20.0, -10.0, 0.0, 10.0, 20.0, None])]
    got = [r.c for r in frame(spark, rows).orderBy("record_id").select(bounding.clamped(F.col("v"), 10).alias("c")).collect()]
    assert got[:5] == [-10, -10, 0, 10, 10]


def test_count_modes(spark):
    rows = frame(spark, [(1, "k", "a", 1, 1.0), (1, "k", "b", 2, 1.0), (2, "k", "c", 2, 1.0)])
    by = lambda m: {r.trigger_idx: r.new_users for r in aggregate.delta_hist(rows, (Measure("count"),), m).collect()}
    assert by("pair_once") == {1: 1, 2: 1} and by("batch_additive") == {1: 1, 2: 2}


def test_zero_noise_selects_exactly_the_keys_over_mu(spark, sf, monkeypatch):
    spec = StreamSpec(secret=TEST_SECRET, bound=10, timing=Timing(4), gate=GateConfig(mu=90))
    flat = Plan(4, 0.0, (0.0,) * 4, (0.0,), 0, 0, 0)
    monkeypatch.setattr("veilstream.functions.calibrate.plan", lambda s: flat)
    rec = tables.line_records(spark, sf)
    once = StreamSpec(secret=TEST_SECRET, bound=10, timing=Timing(4), gate=GateConfig(mu=90, restart=False))
    got = {r.key for r in replay.run(rec, once).select("key").distinct().collect()}
    true = {r.key for r in replay.admitted(rec, spec).groupBy("key").agg(F.countDistinct("unit").alias("n")).filter("n > 90").collect()}
    assert got == true


def strip(rows):
    return sorted((tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in rows), key=repr)


def with_nulls(rec):
    """Some keys and units become null, and one key a text that starts like the name of null."""
    key = F.when(F.col("key") == "3", F.lit(None)).when(F.col("key") == "4", F.lit("\x00")).otherwise(F.col("key"))
    return rec.withColumn("key", key).withColumn("unit", F.when(F.col("unit") % 10 > 0, F.col("unit")))


@pytest.mark.parametrize("mode", ["pair_once", "round_distinct", "batch_additive"])
def test_engines_agree_and_retries_repeat(spark, sf, tmp_path, mode):
    spec = StreamSpec(secret=TEST_SECRET, bound=10, timing=Timing(8), measures=(Measure("count"), Measure("qty", "l_quantity", 20.0)), budget=Budget(30 if mode != "batch_additive" else 300, 1e-3), gate=GateConfig(count_mode=mode))
    rec = with_nulls(tables.line_records(spark, sf))
    want = strip(map(tuple, replay.run(rec, spec).collect()))
    assert {r[0] for r in want} >= {None, "\x00", "1"}
    src = timing.assign_triggers(rec, 8)
    assert strip(map(tuple, microbatch.run_batches(spark, src, spec, str(tmp_path / "s")).collect())) == want
    compacted = microbatch.run_batches(spark, src, spec, str(tmp_path / "c"), compact=3, buckets=5)
    assert strip(map(tuple, compacted.collect())) == want
    tabs = microbatch.StateTables(spark, str(tmp_path / "s"))
    microbatch.step(tabs, src.filter("trigger_idx = 5"), 5, spec)  # a batch tried again
    assert strip(map(tuple, microbatch.releases(tabs, spec, 8).collect())) == want


def test_the_bound_holds_for_the_null_unit_across_batches(spark, tmp_path):
    rec = frame(spark, [(None, "k", f"{i:02}", 1 + i // 4, 1.0) for i in range(12)])
    spec = StreamSpec(secret=TEST_SECRET, bound=2, timing=Timing(3))
    microbatch.run_batches(spark, rec, spec, str(tmp_path))
    tabs = microbatch.StateTables(spark, str(tmp_path))
    assert tabs.read("admitted", 3, microbatch.ADMITTED).count() == 2 == replay.admitted(rec, spec).count()


def test_a_step_reads_only_the_buckets_it_touches(spark, tmp_path):
    spec = StreamSpec(secret=TEST_SECRET, bound=50, timing=Timing(8))
    tabs = microbatch.StateTables(spark, str(tmp_path), buckets=32)
    microbatch.step(tabs, frame(spark, [(i, f"k{i}", str(i), 1, 1.0) for i in range(400)]), 1, spec)
    read = {}
    whole = tabs.read

    def spy(table, last, schema, base=None, only=None):
        out = whole(table, last, schema, base, only)
        read[table] = len(out.inputFiles()) if only is None else len({r[0] for r in out.select(F.input_file_name()).distinct().collect()})
        return out

    tabs.read = spy
    microbatch.step(tabs, frame(spark, [(1, "k1", "r", 2, 1.0), (2, "k2", "s", 2, 1.0)]), 2, spec)
    files = lambda t: len(spark.read.parquet(tabs.path(t, 1)).inputFiles())
    assert files("keys") >= 30 and files("admitted") >= 30
    due = whole("due", 1, microbatch.DUE, only=("due", [2])).select("kb").distinct().count()
    assert read["admitted"] <= 2 and read["keys"] <= 2 + due and read["due"] <= 32


def test_a_stream_longer_than_a_window_opens_the_next(spark, sf, tmp_path):
    spec = StreamSpec(secret=TEST_SECRET, bound=10, timing=Timing(2), budget=Budget(40, 1e-3))
    rec = timing.assign_triggers(tables.line_records(spark, sf), 3)
    base = str(tmp_path / "in")
    for i in range(1, 4):
        rec.filter(F.col("trigger_idx") == i).drop("trigger_idx").coalesce(1).write.mode("append").parquet(base)
    source = spark.readStream.schema(rec.drop("trigger_idx").schema).option("maxFilesPerTrigger", 1).parquet(base)
    assert microbatch.stream(source, spec, str(tmp_path / "state"), str(tmp_path / "cp")).awaitTermination(180)
    first, second = (microbatch.window_tables(spark, str(tmp_path / "state"), n) for n in (0, 1))
    late = rec.filter("trigger_idx = 3").withColumn("trigger_idx", F.lit(1))
    assert strip(map(tuple, microbatch.releases(first, spec, 2).collect())) == strip(map(tuple, replay.run(rec.filter("trigger_idx < 3"), spec).collect()))
    got = strip(map(tuple, microbatch.close_window(second, spec, 1).collect()))
    plain = strip(map(tuple, replay.run(late, spec).collect()))
    assert got and second.read("admitted", 2, microbatch.ADMITTED).count() == replay.admitted(late, spec).count()
    assert not {r[4] for r in got} & {r[4] for r in plain}  # the second window has trees of its own


def test_windows_at_a_clock_change_have_different_noise_in_every_time_zone(spark):
    # 2023-10-29 in Berlin: 02:00 comes twice
    starts = [1698537600 + 3600 * h for h in range(4)]
    rows = [(w, i, "k", f"{w}-{i}") for w in starts for i in range(400)]
    rec = spark.createDataFrame(rows, "w long, unit long, key string, record_id string").withColumn("window_start", F.timestamp_seconds("w")).withColumn("unit", F.col("unit") + F.col("w"))
    spec = StreamSpec(secret=TEST_SECRET, bound=1, timing=Timing(1))
    seen, zone = {}, spark.conf.get("spark.sql.session.timeZone")
    try:
        for z in ("UTC", "Europe/Berlin"):
            spark.conf.set("spark.sql.session.timeZone", z)
            out = replay.run(rec, spec).select(F.unix_micros("window_start").alias("w"), "users_hat").collect()
            seen[z] = {r.w: r.users_hat for r in out}
    finally:
        spark.conf.set("spark.sql.session.timeZone", zone)
    assert seen["UTC"] == seen["Europe/Berlin"] and len(set(seen["UTC"].values())) == 4


def test_no_plan_holds_the_secret(spark, sf, capsys):
    spec = StreamSpec(secret="plain-in-sight", bound=10, timing=Timing(4))
    rec = tables.line_records(spark, sf)
    deltas = replay.delta(rec, spec)
    from veilstream.operators import oneshot

    frames = [
        replay.run(rec, spec), oneshot.oneshot_hist(replay.admitted(rec, spec), spec), baselines.repeated_queries(deltas, spec, last_only=False),
        baselines.incremental_batches(deltas, spec), tuning.choose_c_dp(rec, 0.99, 1.0, 50, "plain-in-sight"),
        tuning.c_sweep(bounding.ranked(timing.assign_triggers(rec, 4)), (1, 2), aggregate.plain_hist(rec), lambda c: (1.0, 1.0), lambda c: 1.0, "plain-in-sight"),
    ]
    for f in frames:
        f.explain("extended")
        text = capsys.readouterr().out
        assert "Physical Plan" in text and "plain-in-sight" not in text


def test_equal_shares_are_those_of_ntile(spark):
    from pyspark.sql import Window

    for n, t in ((103, 10), (5, 8), (64, 8)):
        rec = spark.range(n).select((F.col("id") % 3).alias("window_start"), F.format_string("r%05d", "id").alias("record_id"))
        want = rec.withColumn("t", F.ntile(t).over(Window.partitionBy("window_start").orderBy("record_id")))
        got = timing.assign_triggers(rec, t, "rows").join(want, ["window_start", "record_id"])
        assert got.count() == n and got.filter("t <> trigger_idx").count() == 0


def test_lateness_widens_the_triggers_and_drops_the_rest(spark):
    rows = [(s, s + d) for s in (0, 3599) for d in (0, 600, 1799, 1801, 7200)]
    rec = spark.createDataFrame(rows, "e long, a long").select(F.timestamp_seconds("e").alias("event_ts"), F.timestamp_seconds("a").alias("arrival_ts"), "a")
    got = {r.a: r.trigger_idx for r in timing.in_time(rec, Timing(9, "arrival", lateness_s=1800, window_s=3600)).collect()}
    assert got == {a: a // 600 + 1 for _, a in rows if a < 5400}


def test_structured_streaming_equals_replay(spark, sf, tmp_path):
    spec = StreamSpec(secret=TEST_SECRET, bound=10, timing=Timing(4))
    rec = timing.assign_triggers(tables.line_records(spark, sf), 4)
    base = str(tmp_path / "in")
    for i in range(1, 5):
        rec.filter(F.col("trigger_idx") == i).coalesce(1).write.mode("append").parquet(base)
    source = spark.readStream.schema(rec.schema).option("maxFilesPerTrigger", 1).parquet(base)
    q = microbatch.stream(source, spec, str(tmp_path / "state"), str(tmp_path / "cp"))
    assert q.awaitTermination(180)
    got = microbatch.releases(microbatch.window_tables(spark, str(tmp_path / "state"), 0), spec, 4)
    assert strip(map(tuple, got.collect())) == strip(map(tuple, replay.run(rec, spec).collect()))


def test_empty_stream(spark):
    assert replay.run(frame(spark, []), StreamSpec(secret=TEST_SECRET, bound=2, timing=Timing(3))).count() == 0


def test_main_keeps_more_keys_than_the_baselines(spark):
    sf = "/root/testdata/sf0.01"
    spec = StreamSpec(secret=TEST_SECRET, bound=17, timing=Timing(16))
    rec = tables.brand_type_records(spark, sf)
    deltas = replay.delta(rec, spec)
    truth = aggregate.plain_hist(rec)
    main = metrics.utility(truth, replay.snapshot(replay.run(rec, spec), spec), "count_hat").first()
    for b in (baselines.repeated_queries(deltas, spec), baselines.incremental_batches(deltas, spec)):
        r = metrics.utility(truth, b).first()
        assert main["keys"] > r["keys"] and main.l1 < r.l1 and main.l2 < r.l2


def test_tuning_and_generator(spark):
    rec = synth.zipf_mandelbrot(spark, 3000, 500)
    per = rec.groupBy("unit").count().agg(F.avg("count")).first()[0]
    assert 5 < per < 7.5
    assert 25 <= tuning.choose_c(rec).first().c <= 40
    assert abs(tuning.choose_c_dp(rec, 0.99, 5.0, 100, TEST_SECRET).first().c - tuning.choose_c(rec).first().c) <= 6
    assert synth.uniform_keys(spark, 100, 50).count() == 600


def test_validation():
    with pytest.raises(ValueError):
        Timing(0)
