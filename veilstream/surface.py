"""Builder and SQL surface of the private histogram.

    PrivateHistogram(df).unit("user").keys("url", "day").record_id("id").count().sum("price", 50)
        .bound(10).triggers(100).budget(6, 1e-9).secret(s).releases()
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import accounting, calibrate
from .functions.noise import Secret, resolve
from .operators import aggregate, bounding, timing
from .operators.gate import KeyGate
from .plans import replay
from .spec import Budget, GateConfig, Measure, StreamSpec, Timing

EXACT_ONLY = ("min", "max", "median", "percentile", "first", "last", "count_distinct")


class PrivateHistogram:
    def __init__(self, records: DataFrame):
        self.records = records
        self._unit: tuple[str, ...] = ()
        self._keys: tuple[str, ...] = ()
        self._id: tuple[str, ...] = ()
        self._window: tuple[str, int, int] | None = None
        self._derived: list[tuple[str, str, str, str]] = []
        self.spec = StreamSpec(bound=1, measures=(), secret=None)

    def unit(self, *columns: str) -> PrivateHistogram:
        """The privacy unit: a user, or (user, period), or (user, key)."""
        self._unit = columns
        return self

    def keys(self, *columns: str) -> PrivateHistogram:
        self._keys = columns
        return self

    def record_id(self, *columns: str) -> PrivateHistogram:
        self._id = columns
        return self

    def count(self, name: str = "count") -> PrivateHistogram:
        return self._add(Measure(name))

    def sum(self, column: str, clamp: float, name: str | None = None) -> PrivateHistogram:
        return self._add(Measure(name or f"sum_{column}", column, float(clamp)))

    def _add(self, m: Measure) -> PrivateHistogram:
        if m not in self.spec.measures:
            self.spec = replace(self.spec, measures=(*self.spec.measures, m))
        return self

    def avg(self, column: str, clamp: float) -> PrivateHistogram:
        self._derived.append(("avg", f"sum_{column}", "", column))
        return self.count().sum(column, clamp)

    def variance(self, column: str, clamp: float) -> PrivateHistogram:
        self._derived.append(("variance", f"sum_{column}", f"sq_{column}", column))
        return self.count().sum(column, clamp)._add(Measure(f"sq_{column}", column, float(clamp), square=True))

    def aggregate(self, kind: str, column: str, clamp: float) -> PrivateHistogram:
        """By name; only aggregates that are functions of clamped sums have a bounded sensitivity."""
        if kind in EXACT_ONLY:
            raise ValueError(f"{kind} is not a function of clamped sums: one record can move it without bound")
        if kind not in ("sum", "avg", "variance"):
            raise ValueError(f"unknown aggregate {kind}")
        return getattr(self, kind)(column, clamp)

    def bound(self, c: int) -> PrivateHistogram:
        self.spec = replace(self.spec, bound=c)
        return self

    def triggers(self, t: int, assign: str = "shuffled") -> PrivateHistogram:
        self.spec = replace(self.spec, timing=Timing(t, assign))
        return self

    def budget(self, eps: float, delta: float, **split: float) -> PrivateHistogram:
        self.spec = replace(self.spec, budget=Budget(eps, delta, **split))
        return self

    def gate(self, **settings) -> PrivateHistogram:
        self.spec = replace(self.spec, gate=GateConfig(**settings))
        return self

    def secret(self, secret: Secret) -> PrivateHistogram:
        """What keys the noise; releases need one."""
        self.spec = replace(self.spec, secret=secret)
        return self

    def window(self, ts: str, seconds: int, slide: int | None = None) -> PrivateHistogram:
        """Tumbling windows of event time, or sliding ones, where a record counts in seconds / slide windows."""
        slide = slide or seconds
        if slide < 1 or seconds % slide:
            raise ValueError("a window must be a whole number of slides")
        self._window = (ts, seconds, slide)
        return self

    def session(self, ts: str, gap_s: int) -> PrivateHistogram:
        raise ValueError("session windows depend on the data, so their bounds would leak; use fixed windows")

    @property
    def overlap(self) -> int:
        return self._window[1] // self._window[2] if self._window else 1

    def calibrated(self) -> StreamSpec:
        """The spec that noise is scaled by: each of C records may touch every window that overlaps it."""
        return replace(self.spec, bound=self.spec.bound * self.overlap)

    def ledger(self) -> DataFrame:
        return accounting.ledger(self.records.sparkSession, self.calibrated())

    def bounded(self) -> DataFrame:
        """unit, key (JSON of the key columns), record_id, trigger_idx, values, window_start?: C records a unit, then windows."""
        if not (self._unit and self._keys and self._id and self.spec.measures):
            raise ValueError("unit, keys, record_id and at least one measure are needed")
        values = dict.fromkeys(m.column for m in self.spec.measures if m.column)
        text = lambda cs: F.to_json(F.struct(*cs)) if len(cs) > 1 else F.col(cs[0])
        ts = [F.col(self._window[0]).cast("timestamp").alias("event_ts")] if self._window else []
        out = self.records.select(text(self._unit).alias("unit"), F.to_json(F.struct(*self._keys)).alias("key"), text(self._id).alias("record_id"), *[F.col(v) for v in values], *ts)
        self.spec.validate(out)
        t = self.spec.timing
        if t.assign != "shuffled":
            raise ValueError("the builder spreads records by the hash of their id; use plans.replay for other timings")
        out = bounding.bound_records(timing.assign_triggers(out, t.triggers), self.spec.bound)
        if not self._window:
            return out
        _, size, slide = self._window
        out = timing.assign_windows(out, slide)
        if self.overlap > 1:
            starts = F.transform(F.sequence(F.lit(0), F.lit(self.overlap - 1)), lambda k: F.timestamp_micros(F.unix_micros("window_start") - k.cast("bigint") * slide * 1_000_000))
            out = out.withColumn("window_start", F.explode(starts))
        return out

    def releases(self) -> DataFrame:
        """window_start?, the key columns, trigger_idx, round, cause, users_hat, a _hat a measure and the derived ones."""
        spec = self.calibrated()
        deltas = aggregate.delta_hist(self.bounded(), spec.measures, spec.gate.count_mode)
        out = replay.fold(replay.timelines(deltas, spec), spec)
        schema = self.records.select(*self._keys).schema
        out = out.withColumn("key", F.from_json("key", schema))
        n = F.greatest("count_hat", F.lit(1.0)) if any(m.name == "count" for m in spec.measures) else None
        for kind, total, squares, column in self._derived:
            mean = F.col(f"{total}_hat") / n
            out = out.withColumn(f"{kind}_{column}_hat", mean if kind == "avg" else F.greatest(F.lit(0.0), F.col(f"{squares}_hat") / n - mean * mean))
        head = ["window_start"] if self._window else []
        return out.select(*head, "key.*", *[c for c in out.columns if c not in ("key", "window_start")])


def register_gate(spark: SparkSession, spec: StreamSpec, name: str = "private_releases") -> None:
    """A SQL table function over deltas: the state machine of one key a partition.

    SELECT * FROM private_releases(TABLE(deltas) PARTITION BY key ORDER BY trigger_idx), where
    deltas holds key, trigger_idx, new_users, n_records and sum_<measure>.
    """
    from pyspark.sql.functions import udtf

    plan, gate, secret, names = calibrate.plan(spec), spec.gate, spec.secret, tuple(m.name for m in spec.measures)
    machine, look = KeyGate, resolve
    if gate.count_mode == "round_distinct":
        raise ValueError("the table function takes additive user counts")

    class Releases:
        def __init__(self):
            self.g = None

        def eval(self, row):
            if self.g is None:
                self.key = row["key"]
                self.g = machine(plan, gate, look(secret), names, self.key)
            for r in self.g.arrive(row["trigger_idx"], row["new_users"], [row[f"sum_{m}"] for m in names], row["n_records"]):
                yield (self.key, *r)

        def terminate(self):
            if self.g is not None:
                for r in self.g.silent_until(plan.triggers):
                    yield (self.key, *r)

    columns = "key: string, trigger_idx: int, round: int, cause: string, users_hat: double" + "".join(f", {m}_hat: double" for m in names)
    spark.udtf.register(name, udtf(Releases, returnType=columns.replace(": ", " ")))
