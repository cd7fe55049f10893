"""Utility and cost measures; all are computed from raw data and are not private outputs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def utility(truth: DataFrame, estimate: DataFrame, value: str = "value_hat") -> DataFrame:
    """keys, linf, l1, l2, retained_mass, rel_error over all true keys; an unreleased key counts as 0."""
    e = estimate.select(F.col("key").alias("_key"), F.col(value).alias("_hat"))
    both = truth.join(e, F.col("key").eqNullSafe(F.col("_key")), "full_outer")
    shown = F.col("_hat").isNotNull()
    err = F.abs(F.coalesce("_hat", F.lit(0.0)) - F.coalesce("truth", F.lit(0.0)))
    on = lambda c: F.coalesce(F.sum(F.when(shown, c)), F.lit(0.0))
    return both.agg(
        F.sum(shown.cast("long")).alias("keys"),
        F.max(err).alias("linf"),
        F.sum(err).alias("l1"),
        F.sqrt(F.sum(err * err)).alias("l2"),
        (on(F.col("truth")) / F.sum("truth")).alias("retained_mass"),
        (on(err) / F.nullif(on(F.col("truth")), F.lit(0.0))).alias("rel_error"),
    )


def retained_mass(truth: DataFrame, estimate: DataFrame, hours: float, rates: tuple[float, ...] = (0.0, 1.0, 60.0)) -> DataFrame:
    """rate, keys, retained: share of the true mass that is released, among keys of at least `rate` records an hour."""
    e = estimate.select(F.col("key").alias("_key"), F.lit(True).alias("_shown")).distinct()
    both = truth.join(e, F.col("key").eqNullSafe(F.col("_key")), "left").crossJoin(F.broadcast(truth.sparkSession.createDataFrame([(float(r),) for r in rates], "rate double")))
    fast = both.filter(F.col("truth") >= F.col("rate") * hours)
    return fast.groupBy("rate").agg(F.count(F.lit(1)).alias("keys"), (F.sum(F.when(F.col("_shown"), F.col("truth")).otherwise(0.0)) / F.sum("truth")).alias("retained"))


def relative_change(ours: DataFrame, theirs: DataFrame, names: tuple[str, ...] = ("linf", "l1", "l2")) -> DataFrame:
    """1 - ours / theirs and theirs / ours of one-row utility frames."""
    o, t = ours.select(*[F.col(n).alias(f"o_{n}") for n in names]), theirs.select(*[F.col(n).alias(f"t_{n}") for n in names])
    both = o.join(t)
    return both.select(*[(1 - F.col(f"o_{n}") / F.col(f"t_{n}")).alias(f"{n}_change") for n in names], *[(F.col(f"t_{n}") / F.col(f"o_{n}")).alias(f"{n}_ratio") for n in names])


def average(rows: DataFrame, by: list[str], names: list[str]) -> DataFrame:
    """Mean and standard error over repeated runs."""
    return rows.groupBy(*by).agg(*[F.avg(n).alias(n) for n in names], *[(F.coalesce(F.stddev(n), F.lit(0.0)) / F.sqrt(F.count(F.lit(1)))).alias(f"{n}_se") for n in names])


def bounding_loss(ranked: DataFrame, bound: int) -> DataFrame:
    """records, dropped, units_cut, share: what the contribution bound removes."""
    over = F.col("unit_rank") > bound
    return ranked.agg(F.count(F.lit(1)).alias("records"), F.sum(over.cast("long")).alias("dropped"), F.countDistinct(F.when(over, F.col("unit"))).alias("units_cut"), F.avg(over.cast("double")).alias("share"))
