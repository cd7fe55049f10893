"""Stateful engine: the whole mechanism on a stream with point access to state, in two stages.

Stage 1 (`bounded`) is keyed by privacy unit: its state is the unit's number of records and the last
trigger at which each of its at most `bound` keys was seen. Stage 2 (`releases`) is keyed by window
and key: its state is the key's counts and sums as JSON, and its forecast is an event-time timer.
`run` joins them by a folder whose files appear a batch at a time, exactly once.

Trigger i of a window is an event time: the window's start plus i steps (one second each from the
epoch without windows). The watermark follows the newest trigger seen without delay, so a timer set at the forecast
trigger fires once a later trigger has data: a key that gets records at its forecast trigger is served by
them first. All records of a trigger must come in one batch.
"""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import calibrate
from ..functions.noise import key_text, resolve
from ..operators.gate import KeyGate, KeyState
from ..spec import StreamSpec


def bounded(source: DataFrame, spec: StreamSpec) -> DataFrame:
    """Streaming frame of admitted records from a stream with unit, key, record_id, trigger_idx, values and perhaps window_start.

    window_start?, key, trigger_idx, previous (last trigger of the pair, 0 if none; null but for the first record of a batch), values.
    """
    bound = spec.bound
    windows = ["window_start"] if "window_start" in source.columns else []
    values = list(dict.fromkeys(m.column for m in spec.measures if m.column))
    out = [*windows, "key", "trigger_idx", "previous", *values]

    def serve(group, frames, state):
        kept = json.loads(state.get[0]) if state.exists else {"used": 0, "seen": []}
        used, seen = kept["used"], {(w, k): i for w, k, i in kept["seen"]}
        data = pd.concat(list(frames)).sort_values(["trigger_idx", "record_id"], kind="stable").head(bound - used)
        previous, own = [], list(zip(data["window_start"].astype("int64") if windows else [0] * len(data), data["key"], data["trigger_idx"]))
        for w, k, i in own:
            k = k if isinstance(k, str) else None
            before = seen.get((int(w), k), 0)
            previous.append(None if before == i else before)
            seen[(int(w), k)] = int(i)
        state.update((json.dumps({"used": used + len(data), "seen": [[w, k, i] for (w, k), i in seen.items()]}),))
        data["previous"] = pd.array(previous, dtype="Int32")
        yield data[out]

    src = source.select(*windows, "unit", F.col("key").cast("string").alias("key"), F.col("record_id").cast("string").alias("record_id"), F.col("trigger_idx").cast("int").alias("trigger_idx"), *[F.col(v).cast("double").alias(v) for v in values])
    head = "window_start timestamp, " if windows else ""
    schema = f"{head}key string, trigger_idx int, previous int" + "".join(f", {v} double" for v in values)
    return src.groupBy("unit").applyInPandasWithState(serve, schema, "blob string", "append", "NoTimeout")


def releases(source: DataFrame, spec: StreamSpec) -> DataFrame:
    """Streaming frame of releases from a stream of admitted records (see `bounded`).

    A record of trigger T + 1 under the key '' closes a window: it moves the watermark, and
    what is still due is released.
    """
    plan, gate, secret, names = calibrate.plan(spec), spec.gate, spec.secret, tuple(m.name for m in spec.measures)
    columns = [(m.column, m.clamp, 2 if m.square else 1) for m in spec.measures]
    last, mode = spec.timing.triggers, spec.gate.count_mode
    windowed = "window_start" in source.columns
    step = (spec.timing.window_s + spec.timing.lateness_s) / last if windowed else 1.0
    machine, make, look, text = KeyGate, KeyState, resolve, key_text
    head = ["window_start"] if windowed else []
    cols = [*head, "key", "trigger_idx", "round", "cause", "users_hat", *[f"{n}_hat" for n in names]]

    def serve(group, frames, state):
        key = group[-1]
        start = pd.Timestamp(group[0]).value // 1000 if windowed else 0  # microseconds
        at_ms = lambda i: int(start // 1000 + i * step * 1000)
        kept = json.loads(state.get[0]) if state.exists else None
        s = make(**kept["state"]) if kept else make()
        g = machine(plan, gate, look(secret), names, key, s, text(start) if windowed else "")
        rows = []
        if state.hasTimedOut:
            rows += g.silent_until(kept["due"])
        else:
            data = pd.concat(list(frames))
            data = data[data["trigger_idx"] <= last]
            for i, part in sorted(data.groupby("trigger_idx"), key=lambda x: x[0]):
                sums = [float((part[c].clip(-limit, limit) ** power).sum()) if c else float(len(part)) for c, limit, power in columns]
                first = part["previous"].dropna().astype("int64")
                users = int((first == 0).sum()) if mode == "pair_once" else len(first)
                before = list(first.value_counts().items()) if mode == "round_distinct" else None
                rows += g.arrive(int(i), users, sums, len(part), before)
        due = g.forecast()
        while due is not None and at_ms(due) <= state.getCurrentWatermarkMs():
            rows += g.silent_until(due)
            due = g.forecast()
        state.update((json.dumps({"state": vars(g.state), "due": due}),))
        if due is not None:
            state.setTimeoutTimestamp(at_ms(due))
        yield pd.DataFrame([(*group, *r) for r in rows], columns=cols)

    at = F.timestamp_seconds(F.unix_micros("window_start") / 1_000_000 + F.col("trigger_idx") * step) if windowed else F.timestamp_seconds(F.col("trigger_idx"))
    timed = source.withColumn("at", at).withWatermark("at", "0 seconds")
    schema = ("window_start timestamp, " if windowed else "") + "key string, trigger_idx int, round int, cause string, users_hat double" + "".join(f", {n}_hat double" for n in names)
    return timed.groupBy(*head, "key").applyInPandasWithState(serve, schema, "blob string", "append", "EventTimeTimeout")


def run(source: DataFrame, spec: StreamSpec, root: str, every: str | None = None) -> DataFrame:
    """Both stages over what is available (or, with `every`, at that interval until stopped): the releases so far as a table.

    root: a folder that the driver and the executors share; it holds the checkpoints, the admitted
    records and the releases, so a run that is started again goes on where it was.
    """
    spec.validate(source)
    spark = source.sparkSession

    def start(frame: DataFrame, name: str):
        sink = frame.writeStream.format("parquet").option("path", f"{root}/{name}").option("checkpointLocation", f"{root}/{name}-checkpoint")
        return (sink.trigger(processingTime=every) if every else sink.trigger(availableNow=True)).start()

    admitted = bounded(source, spec)
    first = start(admitted, "admitted")
    if not every:
        first.awaitTermination()
    out = releases(spark.readStream.schema(admitted.schema).parquet(f"{root}/admitted"), spec)
    second = start(out, "releases")
    if not every:
        second.awaitTermination()
    return spark.read.schema(out.schema).parquet(f"{root}/releases")
