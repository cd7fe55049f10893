"""Windows, triggers and lateness as arithmetic on columns; no join, no shuffle."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..shared import materialize
from ..spec import Timing


def hashed_trigger(record_id: Column, triggers: int) -> Column:
    """1..T from the leading digits of SHA-256: independent of the data's order and values."""
    return (F.conv(F.substring(F.sha2(record_id.cast("string"), 256), 1, 8), 16, 10).cast("bigint") % triggers + 1).cast("int")


def arrival_trigger(arrival: Column, start: Column, seconds: int, triggers: int) -> Column:
    """1..T by arrival time on a window of `seconds`; later arrivals get the last trigger."""
    at = F.unix_micros(arrival) - F.unix_micros(start)
    return F.least(F.lit(triggers), F.floor(at * triggers / (seconds * 1_000_000)).cast("int") + 1)


def assign_triggers(records: DataFrame, triggers: int, how: str = "shuffled", seconds: int = 86_400) -> DataFrame:
    if how == "shuffled":
        return records.withColumn("trigger_idx", hashed_trigger(F.col("record_id"), triggers))
    if how == "arrival":
        return records.withColumn("trigger_idx", arrival_trigger(F.col("arrival_ts"), F.col("window_start"), seconds, triggers))
    return equal_shares(records, triggers)


def equal_shares(records: DataFrame, triggers: int) -> DataFrame:
    """Equal shares in record order inside a window, as ntile deals them, without sorting a window in one task.

    Ranks come from ranges: rows are range-partitioned by (window, record), counted by window and
    range, and ranked inside their range; counts of ranges are as many rows as windows x ranges.
    Rows equal in window and record id are interchangeable. The dealt rows are written to the shared folder once.
    """
    by = ["window_start"] if "window_start" in records.columns else []
    order = [F.col(c).asc_nulls_first() for c in (*by, "record_id")]
    names = records.columns
    dealt = materialize(records.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()), "shares")
    w = Window.partitionBy(*by)
    cells = dealt.groupBy(*by, "_part").agg(F.count(F.lit(1)).alias("_n"))
    before = F.coalesce(F.sum("_n").over(w.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    cells = cells.select(*[F.col(c).alias("_w") for c in by], F.col("_part").alias("_p"), before.alias("_before"), F.sum("_n").over(w).alias("_all"))
    place = F.row_number().over(Window.partitionBy(*by, "_part").orderBy("record_id"))
    same = F.col("_part") == F.col("_p")
    if by:
        same = same & F.col("window_start").eqNullSafe(F.col("_w"))
    ranked = dealt.withColumn("_at", place).join(cells, same)
    at, small = F.col("_before") + F.col("_at") - 1, F.floor(F.col("_all") / triggers)
    extra = F.col("_all") % triggers  # the first shares hold one more
    cut = extra * (small + 1)
    share = F.when(at < cut, F.floor(at / (small + 1))).otherwise(extra + F.floor((at - cut) / F.greatest(small, F.lit(1))))
    return ranked.select(*names, (share + 1).cast("int").alias("trigger_idx"))


def assign_windows(records: DataFrame, seconds: int = 86_400, ts: str = "event_ts") -> DataFrame:
    """Half-open tumbling windows [start, start + seconds) of event time."""
    micros = F.unix_micros(F.col(ts).cast("timestamp"))
    size = seconds * 1_000_000
    return records.withColumn("window_start", F.timestamp_micros(micros - F.pmod(micros, F.lit(size))))


def in_time(records: DataFrame, timing: Timing, ts: str = "event_ts") -> DataFrame:
    """Windows, triggers and lateness of a Timing in one step: the triggers span a window and its lateness."""
    out = drop_late(assign_windows(records, timing.window_s, ts), timing.window_s, timing.lateness_s)
    return assign_triggers(out, timing.triggers, timing.assign, timing.window_s + timing.lateness_s)


def drop_late(records: DataFrame, seconds: int, lateness: int) -> DataFrame:
    """Records that arrive no later than the end of their window plus the allowed lateness."""
    end = F.unix_micros("window_start") + (seconds + lateness) * 1_000_000
    return records.filter(F.unix_micros("arrival_ts") < end)
