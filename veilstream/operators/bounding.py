"""User contribution bounding."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

ORDER = ("trigger_idx", "record_id")


def ranked(records: DataFrame, by: tuple[str, ...] = ("unit",)) -> DataFrame:
    """unit_rank: place of a record among its unit's, in stream order."""
    return records.withColumn("unit_rank", F.row_number().over(Window.partitionBy(*by).orderBy(*ORDER)))


def bound_records(records: DataFrame, bound: int, by: tuple[str, ...] = ("unit",)) -> DataFrame:
    """The first `bound` records of each privacy unit; Spark applies the limit below the shuffle too."""
    return ranked(records, by).filter(F.col("unit_rank") <= bound)


def clamped(value: Column, limit: float) -> Column:
    return F.greatest(F.lit(-float(limit)), F.least(F.lit(float(limit)), value.cast("double")))


def bound_keys_and_values(records: DataFrame, value: str, max_keys: int, max_value: float) -> DataFrame:
    """One-shot bounding: a unit's sum for a key is clamped, and only its first max_keys keys stay."""
    per_pair = records.groupBy("unit", "key").agg(F.min(F.struct("trigger_idx", "record_id")).alias("first"), F.sum(value).alias("total"))
    rank = F.row_number().over(Window.partitionBy("unit").orderBy("first.trigger_idx", "first.record_id"))
    kept = per_pair.withColumn("key_rank", rank).filter(F.col("key_rank") <= max_keys)
    return kept.select("unit", "key", clamped(F.col("total"), max_value).alias("total"))


def l1_sensitivity(bound: int, clamp: float) -> float:
    return bound * clamp
