"""The two repeated uses of the one-shot mechanism that the streaming method is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import accounting
from ..spec import StreamSpec
from .oneshot import oneshot_plan, perturb


def repeated_queries(deltas: DataFrame, spec: StreamSpec, last_only: bool = True, composition: str = "optimal") -> DataFrame:
    """A fresh one-shot query over the grown data at every trigger; T-fold composition.

    Bounding keeps a unit's first records, so the bounded prefix is a prefix of the bounded
    stream and running sums of the deltas replace T scans. trigger_idx, key, users_hat, value_hat.
    """
    t, m = spec.timing.triggers, spec.measures[0]
    eps0, delta0 = accounting.compose_inverse(t, spec.budget.eps, spec.budget.delta, composition)
    p = oneshot_plan(eps0, delta0, spec.bound, m.sensitivity, spec.budget.gate_eps_frac, spec.budget.gate_delta_frac)
    if last_only:
        hist = deltas.groupBy("key").agg(F.sum("new_users").alias("users"), F.sum(f"sum_{m.name}").alias("total")).withColumn("trigger_idx", F.lit(t))
    else:
        w = Window.partitionBy("key").orderBy("trigger_idx")
        run = w.rowsBetween(Window.unboundedPreceding, 0)
        grown = deltas.select("key", "trigger_idx", F.sum("new_users").over(run).alias("users"), F.sum(f"sum_{m.name}").over(run).alias("total"), F.coalesce(F.lead("trigger_idx").over(w), F.lit(t + 1)).alias("_next"))
        hist = grown.select("key", "users", "total", F.explode(F.sequence(F.col("trigger_idx"), F.col("_next") - 1)).alias("trigger_idx"))
    return perturb(hist, p, spec.secret, F.col("trigger_idx")).select("trigger_idx", "key", "users_hat", "value_hat")


def incremental_batches(deltas: DataFrame, spec: StreamSpec, composition_k: str = "min(C,T)", composition: str = "optimal") -> DataFrame:
    """One-shot on every micro-batch, results summed: key, users_hat, value_hat, batches."""
    t, m = spec.timing.triggers, spec.measures[0]
    k = min(spec.bound, t) if composition_k == "min(C,T)" else t
    eps0, delta0 = accounting.compose_inverse(k, spec.budget.eps, spec.budget.delta, composition)
    p = oneshot_plan(eps0, delta0, spec.bound, m.sensitivity, spec.budget.gate_eps_frac, spec.budget.gate_delta_frac)
    hist = deltas.select("key", "trigger_idx", F.col("new_users").alias("users"), F.col(f"sum_{m.name}").alias("total"))
    shown = perturb(hist, p, spec.secret, F.col("trigger_idx"), kind="batch")
    return shown.groupBy("key").agg(F.sum("users_hat").alias("users_hat"), F.sum("value_hat").alias("value_hat"), F.count(F.lit(1)).alias("batches"))
