"""Micro-batch engine: foreachBatch steps over versioned, bucketed state tables.

Tables under the root of a window, each a folder of versions written whole by the step of that
number (a step that is tried again writes its versions anew from those before it):

- admitted/n=i/b=: admitted records of batch i by bucket of the unit: unit, key, place among the
  unit's records, previous trigger of the pair (first record of a batch only), values. A unit has at
  most `bound` rows in all versions, which are its state.
- keys/n=i/b=: state of the keys that batch i touched or that were due, by bucket of the key, with
  what the step released of them
- due/n=i/due=j: key and bucket of the keys that step i forecast to pass at trigger j

A step reads the buckets of the batch's units in `admitted`, the one `due` partition of its
trigger, and the buckets of the batch's and the due keys in `keys`: what it reads follows what is
touched, not what is stored. Every `compact` steps the newest rows are written as the base n=-i,
so a step reads one base and fewer than `compact` later versions; a newer version of a key supersedes
its older forecasts. Buckets are those of Spark's hash partitioning: where their number and that of
the shuffle partitions divide each other, a task writes whole buckets and nothing is shuffled for it.
Null units and null keys are values like any other.

A stream that goes on after the last trigger opens the next window: with its own folder, trees,
rounds and contribution bound, under the ledger of a window.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Observation, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from ..functions import calibrate
from ..functions.noise import key_text, resolve
from ..operators import aggregate
from ..operators.gate import KeyGate, KeyState
from ..operators.timing import assign_triggers
from ..shared import shared_path
from ..spec import StreamSpec

ADMITTED = "unit string, key string, place int, previous int, trigger int, sums array<double>, kb int, b int"
OUT = "array<struct<trigger_idx: int, r: int, cause: string, users_hat: double, hats: array<double>>>"
STATE = f"key string, round int, at int, users long, begin int, buffer array<double>, released array<double>, records long, due int, v int, out {OUT}, b int"
DUE = "key string, kb int, due int"


class StateTables:
    """The tables of one window: `window` names its trees (empty for a single window)."""

    def __init__(self, spark: SparkSession, root: str, compact: int = 16, buckets: int = 8, window: str = ""):
        self.spark, self.root, self.compact_every, self.buckets, self.window = spark, root.rstrip("/"), compact, buckets, window

    def bucket(self, c: str) -> Column:
        return F.pmod(F.hash(c), F.lit(self.buckets)).cast("int")

    def path(self, table: str, version: int) -> str:
        return f"{self.root}/{table}/n={version}"

    def write(self, df: DataFrame, table: str, version: int, by: str) -> None:
        df.write.mode("overwrite").partitionBy(by).parquet(self.path(table, version))

    def versions(self, table: str, last: int, base: int | None = None) -> list[str]:
        """The newest base not after `last` and the versions since."""
        base = last // self.compact_every * self.compact_every if base is None else base
        return [*([self.path(table, -base)] if base else []), *(self.path(table, v) for v in range(base + 1, last + 1))]

    def read(self, table: str, last: int, schema: str, base: int | None = None, only: tuple[str, list[int]] | None = None) -> DataFrame:
        """A table as of version `last`, or the partitions `only` of it; rows may have older versions of themselves beside them."""
        paths = self.versions(table, last, base)
        if not paths:
            return self.spark.createDataFrame([], schema)
        out = self.spark.read.schema(schema).option("basePath", f"{self.root}/{table}").parquet(*paths)
        return out.filter(F.col(only[0]).isin(only[1])) if only is not None else out

    def compact(self, i: int) -> None:
        """Write the newest rows of all tables as the base of version i."""
        before = i - self.compact_every
        self.write(self.read("admitted", i, ADMITTED, before).repartition("b"), "admitted", -i, "b")
        newest = F.row_number().over(Window.partitionBy("key").orderBy(F.desc("v")))
        state = self.read("keys", i, STATE, before).withColumn("_r", newest).filter("_r = 1").drop("_r")
        self.write(state.withColumn("out", F.lit(None).cast(OUT)), "keys", -i, "b")
        keys = self.spark.read.schema(STATE).parquet(self.path("keys", -i))
        self.write(keys.filter(F.col("due") > i).select("key", F.col("b").alias("kb"), "due"), "due", -i, "due")


def encoded(c: str) -> Column:
    """Text in which null has a name of its own, so that equality finds it; see decoded."""
    v = F.col(c).cast("string")
    return F.when(v.isNull(), F.lit("\x00")).when(v.startswith("\x00"), F.concat(F.lit("\x00"), v)).otherwise(v)


def decoded(c: str) -> Column:
    v = F.col(c)
    return F.when(v == "\x00", F.lit(None)).when(v.startswith("\x00"), F.substring(v, 2, 1 << 30)).otherwise(v)


def admit(tables: StateTables, batch: DataFrame, i: int, spec: StreamSpec) -> list[int]:
    """Bound the batch against what its units have used, write the admitted records; the buckets of their keys."""
    values = F.array(*[aggregate.measure_column(m) for m in spec.measures])
    new = batch.select(encoded("unit").alias("unit"), encoded("key").alias("key"), values.alias("sums"), "record_id")
    bucket, place, used, seen = tables.bucket("unit"), F.row_number().over(Window.partitionBy("unit").orderBy("record_id")), F.lit(0), F.lit(0)
    if i > 1:
        touched = new.agg(F.collect_set(bucket)).first()[0]  # at most `buckets`
        past = tables.read("admitted", i - 1, ADMITTED, only=("b", touched))
        # at most `bound` rows a unit
        past = past.groupBy("unit").agg(F.max("place").alias("used"), F.collect_set(F.struct("key", "trigger")).alias("pairs"))
        new = new.join(past, "unit", "left")
        used = F.coalesce("used", F.lit(0))
        seen = F.coalesce(F.array_max(F.transform(F.filter("pairs", lambda p: p["key"] == F.col("key")), lambda p: p["trigger"])), F.lit(0))
    new = new.withColumn("place", (place + used).cast("int")).filter(F.col("place") <= spec.bound)
    first = F.row_number().over(Window.partitionBy("unit", "key").orderBy("place")) == 1
    new = new.select("unit", "key", "place", F.when(first, seen).cast("int").alias("previous"), F.lit(i).alias("trigger"), "sums", tables.bucket("key").alias("kb"), bucket.alias("b"))
    met = Observation()
    tables.write(new.observe(met, F.collect_set("kb").alias("kb")), "admitted", i, "b")
    return list(met.get["kb"])


def deltas_of(tables: StateTables, i: int, spec: StreamSpec) -> DataFrame:
    """kb, key, new_users, n_records, sums, previous of the batch's admitted records."""
    rows = tables.spark.read.schema(ADMITTED).parquet(tables.path("admitted", i))
    sums = [F.sum(F.get("sums", F.lit(j))).alias(f"s{j}") for j in range(len(spec.measures))]
    n, units = F.count(F.lit(1)).alias("n_records"), F.count("previous")
    mode = spec.gate.count_mode
    if mode == "round_distinct":
        parts = rows.groupBy("key", "previous").agg(n, units.alias("units"), *sums)
        pair = F.when(F.col("units") > 0, F.struct(F.col("previous").alias("trigger"), F.col("units")))
        out = parts.groupBy("key").agg(F.sum("n_records").alias("n_records"), F.sum("units").alias("new_users"), F.collect_list(pair).alias("arrived"), *[F.sum(f"s{j}").alias(f"s{j}") for j in range(len(spec.measures))])
    else:
        users = F.sum((F.col("previous") == 0).cast("long")) if mode == "pair_once" else units
        out = rows.groupBy("key").agg(n, F.coalesce(users, F.lit(0)).alias("new_users"), *sums).withColumn("arrived", F.lit(None).cast("array<struct<trigger: int, units: bigint>>"))
    return out.select(tables.bucket("key").alias("kb"), "key", F.col("new_users").cast("long"), F.col("n_records").cast("long"), F.array(*[F.col(f"s{j}") for j in range(len(spec.measures))]).alias("sums"), "arrived")


def step(tables: StateTables, batch: DataFrame, i: int, spec: StreamSpec) -> DataFrame:
    """Process the records of trigger i; returns the releases it published."""
    names = tuple(m.name for m in spec.measures)
    touched = set(admit(tables, batch, i, spec))
    deltas = deltas_of(tables, i, spec)
    due = tables.read("due", i - 1, DUE, only=("due", [i]))
    touched |= set(due.agg(F.collect_set("kb")).first()[0]) if i > 1 else set()  # at most `buckets`
    state = tables.read("keys", i - 1, STATE, only=("b", sorted(touched))).drop("out")
    # the newest row of each key of the touched buckets; only wanted ones go on
    kept = F.struct("round", "at", "users", "begin", "buffer", "released", "records", "due")
    state = state.groupBy("key").agg(F.max_by(kept, "v").alias("s"), F.first("b").alias("b"))
    work = deltas.join(state, "key", "full_outer").filter(F.col("n_records").isNotNull() | (F.col("s.due") == i))
    work = work.select("key", F.coalesce("kb", "b").alias("b"), "s", "new_users", "n_records", "sums", "arrived")
    plan, gate, secret, machine, make, look = calibrate.plan(spec), spec.gate, spec.secret, KeyGate, KeyState, resolve
    window = key_text(tables.window) if tables.window else ""

    def run(batches):
        known = look(secret)
        for b in batches:
            out = []
            for r in b.to_pylist():
                s = r["s"]
                s = make(s["round"], s["at"], s["users"], s["begin"], list(s["buffer"]), list(s["released"]), s["records"]) if s is not None else make()
                key = None if r["key"] == "\x00" else r["key"].removeprefix("\x00")
                g = machine(plan, gate, known, names, key, s, window)
                arrived = None if r["arrived"] is None else [(x["trigger"], x["units"]) for x in r["arrived"]]
                got = g.arrive(i, r["new_users"], r["sums"], r["n_records"], arrived) if r["n_records"] else g.silent_until(i)
                s = g.state
                out.append({"key": r["key"], "round": s.round, "at": s.at, "users": s.users, "begin": s.begin, "buffer": s.buffer, "released": s.released, "records": s.records, "due": g.forecast(), "v": i, "out": [{"trigger_idx": x[0], "r": x[1], "cause": x[2], "users_hat": x[3], "hats": list(x[4:])} for x in got], "b": r["b"]})
            yield pa.RecordBatch.from_pylist(out, schema=arrow)

    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    full: StructType = _parse_datatype_string(STATE)
    arrow = to_arrow_schema(full)
    tables.write(work.mapInArrow(run, full), "keys", i, "b")
    new = tables.spark.read.schema(full).parquet(tables.path("keys", i))
    if i < spec.timing.triggers:
        tables.write(new.filter(F.col("due").isNotNull()).select("key", F.col("b").alias("kb"), "due"), "due", i, "due")
    if i % tables.compact_every == 0 and i < spec.timing.triggers:
        tables.compact(i)
    return released(new, names)


def released(keys: DataFrame, names: tuple[str, ...]) -> DataFrame:
    return keys.select(decoded("key").alias("key"), F.explode("out").alias("o")).select("key", "o.trigger_idx", F.col("o.r").alias("round"), "o.cause", "o.users_hat", *[F.get("o.hats", F.lit(j)).alias(f"{n}_hat") for j, n in enumerate(names)])


def releases(tables: StateTables, spec: StreamSpec, last: int) -> DataFrame:
    """All releases up to trigger `last`: key, trigger_idx, round, cause, users_hat and a _hat a measure."""
    return released(tables.read("keys", last, STATE, base=0), tuple(m.name for m in spec.measures))


def run_batches(spark: SparkSession, records: DataFrame, spec: StreamSpec, root: str, compact: int = 16, buckets: int = 8) -> DataFrame:
    """All triggers of one window, one step each (an empty trigger still serves the keys that are due)."""
    spec.validate(records)
    if "trigger_idx" not in records.columns:
        records = assign_triggers(records, spec.timing.triggers, spec.timing.assign)
    tables = StateTables(spark, root, compact, buckets)
    for i in range(1, spec.timing.triggers + 1):
        step(tables, records.filter(F.col("trigger_idx") == i).drop("trigger_idx"), i, spec)
    return releases(tables, spec, spec.timing.triggers)


def run_in_memory(records: DataFrame, spec: StreamSpec) -> DataFrame:
    """run_batches on the shared folder of the session."""
    spark = records.sparkSession
    src = shared_path(spark, "records")
    assign_triggers(records, spec.timing.triggers, spec.timing.assign).write.partitionBy("trigger_idx").parquet(src)
    return run_batches(spark, spark.read.parquet(src), spec, shared_path(spark, "state"))


def window_tables(spark: SparkSession, root: str, number: int) -> StateTables:
    """State of the n-th run of T batches, from 0; later windows have trees of their own."""
    return StateTables(spark, f"{root.rstrip('/')}/window={number}", window=f"window {number}" if number else "")


def close_window(tables: StateTables, spec: StreamSpec, done: int) -> DataFrame:
    """Serve the silent triggers after batch `done`, up to the last one; all releases of the window."""
    none = tables.spark.createDataFrame([], "unit string, key string, record_id string" + "".join(f", {c} double" for c in dict.fromkeys(m.column for m in spec.measures if m.column)))
    for i in range(done + 1, spec.timing.triggers + 1):
        step(tables, none, i, spec)
    return releases(tables, spec, spec.timing.triggers)


def stream(source: DataFrame, spec: StreamSpec, root: str, checkpoint: str, every: str | None = None):
    """A streaming query whose batches are the triggers: batch n is trigger n mod T + 1 of window n div T. Idempotent under retries.

    every: interval of a processing-time trigger ('10 minutes'); by default all that is available is
    processed batch by batch. Batches that arrive with the data, at no fixed times, are outside the guarantee.
    """
    spark, t = source.sparkSession, spec.timing.triggers
    spec.validate(source)

    def on_batch(df: DataFrame, batch_id: int) -> None:
        step(window_tables(spark, root, batch_id // t), df.drop("trigger_idx"), batch_id % t + 1, spec)

    writer = source.writeStream.foreachBatch(on_batch).option("checkpointLocation", checkpoint)
    return (writer.trigger(processingTime=every) if every else writer.trigger(availableNow=True)).start()
