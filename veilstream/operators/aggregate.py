"""Cross-user aggregation: deltas by key and trigger, and the non-private truth."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..spec import Measure
from .bounding import clamped


def measure_column(m: Measure):
    value = clamped(F.col(m.column), m.clamp) if m.column else F.lit(1.0)
    return value * value if m.square else value


def delta_hist(admitted: DataFrame, measures: tuple[Measure, ...], count_mode: str = "pair_once") -> DataFrame:
    """window_start?, key, trigger_idx, n_records, new_users, sum_<measure>..., previous (round_distinct).

    pair_once marks the first record of a unit for a key, which makes user counts additive
    over triggers; batch_additive counts the units of a trigger; round_distinct counts them by the
    trigger at which they were last seen with the key (0: never), at most T numbers a row.
    """
    by = [c for c in ("window_start", "key") if c in admitted.columns]
    sums = [F.sum(measure_column(m)).alias(f"sum_{m.name}") for m in measures]
    n = F.count(F.lit(1)).alias("n_records")
    if count_mode == "batch_additive":
        # null units are one unit too
        users = (F.countDistinct("unit") + F.max(F.col("unit").isNull().cast("long"))).alias("new_users")
        return admitted.groupBy(*by, "trigger_idx").agg(n, users, *sums)
    order = Window.partitionBy(*by, "unit").orderBy("trigger_idx", "record_id")
    before = F.coalesce(F.lag("trigger_idx").over(order), F.lit(0))
    if count_mode == "pair_once":
        marked = admitted.withColumn("_new", (before == 0).cast("long"))
        return marked.groupBy(*by, "trigger_idx").agg(n, F.sum("_new").alias("new_users"), *sums)
    marked = admitted.withColumn("_prev", before.cast("int"))
    fresh = (F.col("_prev") < F.col("trigger_idx")).cast("long")  # later records of a unit at a trigger have the trigger itself
    parts = marked.groupBy(*by, "trigger_idx", "_prev").agg(n, F.sum(fresh).alias("_units"), *sums)
    pair = F.struct(F.col("_prev").alias("trigger"), F.col("_units").alias("units"))
    return parts.groupBy(*by, "trigger_idx").agg(
        F.sum("n_records").alias("n_records"),
        F.sum("_units").alias("new_users"),
        *[F.sum(f"sum_{m.name}").alias(f"sum_{m.name}") for m in measures],
        F.array_sort(F.collect_list(F.when(F.col("_units") > 0, pair))).alias("previous"),  # at most T
    )


def plain_hist(records: DataFrame, value=None) -> DataFrame:
    """key, users, truth: the exact histogram of raw records."""
    return records.groupBy("key").agg(F.countDistinct("unit").alias("users"), F.sum(F.lit(1.0) if value is None else value).alias("truth"))


def plain_stream_hist(records: DataFrame) -> DataFrame:
    """Non-private updates: the running count of a key at every trigger that has records of it."""
    per = records.groupBy("key", "trigger_idx").agg(F.count(F.lit(1)).alias("n"))
    run = Window.partitionBy("key").orderBy("trigger_idx").rowsBetween(Window.unboundedPreceding, 0)
    return per.select("key", "trigger_idx", F.sum("n").over(run).alias("total"))
