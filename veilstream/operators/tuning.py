"""Choosing the contribution bound."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.noise import Secret, normal_column, uniform_column


def choose_c(records: DataFrame, p: float = 0.99, sample: float = 1.0) -> DataFrame:
    """c: the discrete p-quantile of records a unit, on a hash sample of the units (non-private)."""
    if sample < 1:
        cut = int(sample * 2**32)
        records = records.filter(F.conv(F.substring(F.sha2(F.col("unit").cast("string"), 256), 1, 8), 16, 10).cast("bigint") < cut)
    per = records.groupBy("unit").agg(F.count(F.lit(1)).alias("n"))
    sizes = per.groupBy("n").agg(F.count(F.lit(1)).alias("units"))  # at most as many rows as there are sizes
    run = F.sum("units").over(Window.orderBy("n")) / F.sum("units").over(Window.partitionBy())
    return sizes.withColumn("at", run).filter(F.col("at") >= p).agg(F.min("n").alias("c"))


def choose_c_dp(records: DataFrame, p: float, eps: float, most: int, secret: Secret) -> DataFrame:
    """c: private p-quantile by the exponential mechanism over 1..most (Gumbel noise from hashed uniforms).

    The score of c is minus the distance of the number of units with at most c records from its
    target; one unit moves it by 1. eps is to be charged to the ledger.
    """
    per = records.groupBy("unit").agg(F.count(F.lit(1)).alias("n"))
    hist = per.select(F.least("n", F.lit(most + 1)).alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("units"))
    grid = records.sparkSession.range(1, most + 1).select(F.col("id").alias("c"))
    total = hist.agg(F.sum("units").alias("total"))
    below = grid.join(F.broadcast(hist), F.col("n") <= F.col("c"), "left").groupBy("c").agg(F.coalesce(F.sum("units"), F.lit(0)).alias("below"))  # most x most rows
    u = uniform_column(secret, "quantile", F.col("c"))
    scored = below.join(total).withColumn("score", -eps / 2 * F.abs(F.col("below") - p * F.col("total")) - F.log(-F.log(u)))
    return scored.agg(F.max_by("c", "score").alias("c"))


def c_sweep(ranked: DataFrame, bounds: tuple[int, ...], truth: DataFrame, sigma_of, threshold_of, secret: Secret) -> DataFrame:
    """c, keys, linf, l1, l2 for each bound from one ranked scan (one-trigger mechanism).

    sigma_of(c), threshold_of(c): value and gate scales of a bound; a key is shown if its noisy
    users pass.
    """
    rows = [(c, *sigma_of(c), threshold_of(c)) for c in bounds]
    grid = F.broadcast(ranked.sparkSession.createDataFrame(rows, "c int, user_sigma double, value_sigma double, threshold double"))
    inside = ranked.filter(F.col("unit_rank") <= max(bounds))
    by_rank = inside.groupBy("key", "unit").agg(F.collect_list("unit_rank").alias("ranks"))  # at most max(bounds)
    per = by_rank.join(grid).withColumn("n", F.size(F.filter("ranks", lambda r: r <= F.col("c")))).filter("n > 0")
    hist = per.groupBy("c", "key").agg(F.count(F.lit(1)).alias("users"), F.sum("n").cast("double").alias("total"), F.first("user_sigma").alias("user_sigma"), F.first("value_sigma").alias("value_sigma"), F.first("threshold").alias("threshold"))
    z = lambda stream: normal_column(secret, stream, F.col("key"), F.col("c"), F.lit(0), F.lit(0))
    shown = hist.filter(F.col("users") + F.col("user_sigma") * z("sweep-users") > F.col("threshold")).select("c", F.col("key").alias("_key"), (F.col("total") + F.col("value_sigma") * z("sweep-value")).alias("hat"))
    all_keys = truth.select("key", "truth").join(grid.select(F.col("c").alias("_c")))
    both = all_keys.join(shown, (F.col("_c") == F.col("c")) & (F.col("key") == F.col("_key")), "left")
    err = F.abs(F.coalesce("hat", F.lit(0.0)) - F.col("truth"))
    return both.groupBy(F.col("_c").alias("c")).agg(F.count("hat").alias("keys"), F.max(err).alias("linf"), F.sum(err).alias("l1"), F.sqrt(F.sum(err * err)).alias("l2"))
