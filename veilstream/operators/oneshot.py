"""One-shot private histogram over unknown keys: noisy user count over a threshold, Gaussian values."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import calibrate
from ..functions.noise import Secret, normal_column
from ..spec import StreamSpec


@dataclass(frozen=True)
class OneShotPlan:
    user_sigma: float
    threshold: float
    value_sigma: float


def oneshot_plan(eps: float, delta: float, bound: int, clamp: float, gate_eps_frac: float = 0.5, gate_delta_frac: float = 2 / 3, max_keys: int | None = None, max_value: float | None = None, analytic: bool = True) -> OneShotPlan:
    """Scales of one run; with per-key caps the sensitivities are those of the caps."""
    ek, dk = eps * gate_eps_frac, delta * gate_delta_frac
    keys = max_keys or bound
    user = calibrate.gaussian_sigma(ek, dk / 2, keys**0.5, analytic)
    value = calibrate.gaussian_sigma(eps - ek, delta - dk, keys**0.5 * max_value if max_value else bound * clamp, analytic)
    return OneShotPlan(user, 1 + calibrate.upper_quantile(dk / 2 / keys) * user, value)


def perturb(hist: DataFrame, plan: OneShotPlan, secret: Secret, run: Column, users: str = "users", value: str = "total", kind: str = "once") -> DataFrame:
    """key columns of hist, users_hat and value_hat of the keys over the threshold; kind names the noise streams."""
    z = lambda stream: normal_column(secret, stream, F.col("key"), run, F.lit(0), F.lit(0))
    hats = hist.withColumn("users_hat", F.col(users) + plan.user_sigma * z(f"{kind}-users")).withColumn("value_hat", F.col(value) + plan.value_sigma * z(f"{kind}-value"))
    return hats.filter(F.col("users_hat") > plan.threshold)


def oneshot_hist(admitted: DataFrame, spec: StreamSpec, run: int = 0) -> DataFrame:
    m = spec.measures[0]
    from .aggregate import measure_column

    p = oneshot_plan(spec.budget.eps, spec.budget.delta, spec.bound, m.sensitivity, spec.budget.gate_eps_frac, spec.budget.gate_delta_frac)
    hist = admitted.groupBy("key").agg(F.countDistinct("unit").alias("users"), F.sum(measure_column(m)).alias("total"))
    return perturb(hist, p, spec.secret, F.lit(run)).select("key", "users_hat", "value_hat")


def oneshot_capped(records: DataFrame, spec: StreamSpec, max_keys: int, max_value: float, run: int = 0) -> DataFrame:
    """The variant that caps keys a unit and value a pair (three shuffles)."""
    from .bounding import bound_keys_and_values

    p = oneshot_plan(spec.budget.eps, spec.budget.delta, max_keys, max_value, max_keys=max_keys, max_value=max_value)
    pairs = bound_keys_and_values(records.withColumn("_one", F.lit(1.0)), "_one", max_keys, max_value)
    hist = pairs.groupBy("key").agg(F.count(F.lit(1)).alias("users"), F.sum("total").alias("total"))
    return perturb(hist, p, spec.secret, F.lit(run)).select("key", "users_hat", "value_hat")
