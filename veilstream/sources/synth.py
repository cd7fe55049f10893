"""Seeded generator of long-tail streams: shifted power laws for users and keys, by inverse CDF."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shifted_power_cdf(n: int, q: float, s: float) -> np.ndarray:
    w = (np.arange(1, n + 1) + q) ** -s
    return np.cumsum(w / w.sum())


class Law:
    """The two shifted power laws as lists: of a user's number of records (CDF), and of keys (quantiles, uniform between them)."""

    grid = 4096  # keeps the literal of the key law small

    def __init__(self, keys: int, max_per_user: int = 200, q_u: float = 26.0, s_u: float = 6.738, q_k: float = 1000.0, s_k: float = 1.4):
        self.per_user = shifted_power_cdf(max_per_user, q_u, s_u).tolist()
        cdf = shifted_power_cdf(keys, q_k, s_k)
        self.cuts = np.searchsorted(cdf, np.arange(self.grid + 1) / self.grid, side="left").clip(0, keys - 1).tolist()


def uniform(seed: int, name: str):
    h = F.sha2(F.concat_ws("|", F.lit(str(seed)), F.lit(name), F.col("id").cast("string")), 256)
    return (F.conv(F.substring(h, 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


def zipf_mandelbrot(spark: SparkSession, users: int, keys: int, seed: int = 42, **law) -> DataFrame:
    """unit, key, record_id: the number of a user's records and each record's key follow the two laws."""
    laws = Law(keys, **law)
    n = F.size(F.filter(F.lit(laws.per_user), lambda c: c < F.col("u"))) + 1
    base = spark.range(users).withColumn("u", uniform(seed, "records")).select(F.col("id").alias("unit"), F.explode(F.sequence(F.lit(1), n)).alias("i"))
    rec = base.withColumn("id", F.concat_ws("-", F.col("unit").cast("string"), F.col("i").cast("string"))).withColumn("v", uniform(seed, "key"))
    slot = F.floor(F.col("v") * laws.grid).cast("int")
    lo, hi = F.get(F.lit(laws.cuts), slot), F.get(F.lit(laws.cuts), slot + 1)
    return rec.select("unit", (lo + F.floor((F.col("v") * laws.grid - slot) * (hi - lo + 1))).cast("string").alias("key"), F.col("id").alias("record_id"))


def uniform_keys(spark: SparkSession, users: int, keys: int, per_user: int = 6, seed: int = 42) -> DataFrame:
    rec = spark.range(users * per_user).withColumn("v", uniform(seed, "key"))
    return rec.select(F.floor(F.col("id") / per_user).alias("unit"), F.floor(F.col("v") * keys).cast("string").alias("key"), F.col("id").cast("string").alias("record_id"))
