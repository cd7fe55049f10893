"""Batch replay of the whole mechanism: one shuffle by unit, one by key, then a fold a key."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import calibrate
from ..functions.noise import key_column, resolve
from ..operators import aggregate, bounding
from ..operators.gate import KeyGate
from ..operators.timing import assign_triggers, in_time
from ..spec import StreamSpec


def admitted(records: DataFrame, spec: StreamSpec) -> DataFrame:
    spec.validate(records)
    if "trigger_idx" not in records.columns:
        records = in_time(records, spec.timing) if spec.timing.assign == "arrival" else assign_triggers(records, spec.timing.triggers, spec.timing.assign)
    return bounding.bound_records(records, spec.bound)


def delta(records: DataFrame, spec: StreamSpec) -> DataFrame:
    return aggregate.delta_hist(admitted(records, spec), spec.measures, spec.gate.count_mode)


def timelines(deltas: DataFrame, spec: StreamSpec) -> DataFrame:
    """key (and window), with at most T structs of one trigger each."""
    by = [c for c in ("window_start", "key") if c in deltas.columns]
    previous = [F.col("previous")] if "previous" in deltas.columns else []
    row = F.struct("trigger_idx", "new_users", "n_records", *[F.col(f"sum_{m.name}").cast("double") for m in spec.measures], *previous)
    # a given number of partitions: the fold is heavy for the bytes it reads, so they must not be merged by size
    dealt = deltas.repartition(int(deltas.sparkSession.conf.get("spark.sql.shuffle.partitions", "200")), *by)
    out = dealt.groupBy(*by).agg(F.array_sort(F.collect_list(row)).alias("steps"), F.sum("new_users").alias("all_users"))
    if spec.gate.count_mode == "pair_once" and not spec.gate.pre_inclusive:
        out = out.filter(F.col("all_users") > spec.gate.mu)  # such a key is never tested
    return out


def window_name(start: Column) -> Column:
    """A window's part of its keys' noise name: microseconds since the epoch, which no time zone or DST change moves."""
    return key_column(F.unix_micros(start))


def fold(lines: DataFrame, spec: StreamSpec, mode: str = "releases") -> DataFrame:
    """Run the state machine of every key.

    mode: `releases`; `forecasts` (made_at, predicted trigger after each arrival); `cost`
    (tests, wasted forecast tests and state loads of a key, naive and forecast).
    """
    plan, gate, secret, names = calibrate.plan(spec), spec.gate, spec.secret, tuple(m.name for m in spec.measures)
    windowed = "window_start" in lines.columns
    by = ["window_start", "key"] if windowed else ["key"]
    lines = lines.select(*by, (window_name(F.col("window_start")) if windowed else F.lit("")).alias("_w"), "steps")
    head = [f for f in lines.schema.fields if f.name in by]
    tails = {
        "releases": "trigger_idx int, round int, cause string, users_hat double" + "".join(f", {m}_hat double" for m in names),
        "forecasts": "made_at int, predicted int",
        "cost": "tests long, wasted long, loads_naive long, loads_forecast long",
    }
    machine, look = KeyGate, resolve
    n_by, n_sums = len(by), len(names)

    def run(batches):
        known = look(secret)
        for b in batches:
            heads, out = [], []
            steps = b.column(n_by + 1)
            cuts = steps.offsets.to_pylist()
            cells = steps.values.flatten()
            triggers, users, records = (c.to_pylist() for c in cells[:3])
            sums = list(zip(*(c.to_pylist() for c in cells[3 : 3 + n_sums]))) or [()] * len(triggers)
            previous = [None if x is None else [(y["trigger"], y["units"]) for y in x] for x in cells[3 + n_sums].to_pylist()] if len(cells) > 3 + n_sums else [None] * len(triggers)
            for k, (key, window) in enumerate(zip(b.column(n_by - 1).to_pylist(), b.column(n_by).to_pylist())):
                g = machine(plan, gate, known, names, key, window=window)
                rows, wasted, loads, due = [], 0, 0, None
                for c in range(cuts[k], cuts[k + 1]):
                    i = triggers[c]
                    if mode == "cost" and due is not None and due < i:
                        loads += 1
                    rows += g.arrive(i, users[c], sums[c], records[c], previous[c])
                    if mode != "releases":
                        loads += 1
                        before = g.cost.tests
                        due = g.forecast()
                        wasted += g.cost.tests - before
                        if mode == "forecasts" and due is not None:
                            out.append((i, due))
                            heads.append(k)
                rows += g.silent_until(plan.triggers)
                if mode == "releases":
                    heads += [k] * len(rows)
                    out += rows
                elif mode == "cost":
                    heads.append(k)
                    out.append((g.cost.tests - wasted, wasted, plan.triggers - triggers[cuts[k]] + 1, loads + (due is not None)))
            yield pa.RecordBatch.from_pydict(
                {**{f.name: b.column(j).take(pa.array(heads, pa.int64())) for j, f in enumerate(head)}, **{f.name: pa.array([r[j] for r in out], t) for j, (f, t) in enumerate(fields)}}
            )

    from pyspark.sql.pandas.types import to_arrow_type
    from pyspark.sql.types import StructType, _parse_datatype_string

    tail = _parse_datatype_string(tails[mode])
    fields = [(f, to_arrow_type(f.dataType)) for f in tail.fields]
    return lines.mapInArrow(run, StructType([*head, *tail.fields]))


def run(records: DataFrame, spec: StreamSpec, mode: str = "releases") -> DataFrame:
    return fold(timelines(delta(records, spec), spec), spec, mode)


def snapshot(releases: DataFrame, spec: StreamSpec, at: int | None = None) -> DataFrame:
    """The latest release of each key as of a trigger."""
    if at is not None:
        releases = releases.filter(F.col("trigger_idx") <= at)
    by = [c for c in ("window_start", "key") if c in releases.columns]
    hats = [f"{m.name}_hat" for m in spec.measures]
    return releases.groupBy(*by).agg(F.max("trigger_idx").alias("trigger_idx"), *[F.max_by(h, "trigger_idx").alias(h) for h in ("users_hat", *hats)])
