"""Composition of budgets and the ledger of a run."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession

from ..spec import StreamSpec
from . import calibrate


def compose_basic(k: int, eps: float, delta: float) -> tuple[float, float]:
    return k * eps, k * delta


def compose_advanced(k: int, eps: float, delta: float, slack: float) -> tuple[float, float]:
    return eps * math.sqrt(2 * k * math.log(1 / slack)) + k * eps * math.expm1(eps), k * delta + slack


def optimal_delta(k: int, eps0: float, eps: float) -> float:
    """Exact delta at eps of k pure eps0 mechanisms (k-fold randomized response)."""
    p, q = -math.log1p(math.exp(-eps0)), -eps0 - math.log1p(math.exp(-eps0))
    out = 0.0
    for i in range(k + 1):
        ways = math.lgamma(k + 1) - math.lgamma(i + 1) - math.lgamma(k - i + 1)
        a, b = ways + (k - i) * p + i * q, eps + ways + i * p + (k - i) * q
        if a > b:
            out += math.exp(a) * -math.expm1(b - a)
    return out


def compose_optimal(k: int, eps0: float, delta0: float, eps: float) -> float:
    """delta of k (eps0, delta0) mechanisms at eps."""
    return 1 - (1 - delta0) ** k * (1 - optimal_delta(k, eps0, eps))


def compose_optimal_inverse(k: int, eps: float, delta: float) -> tuple[float, float]:
    """Per-run (eps0, delta0) whose k-fold composition is (eps, delta); half of delta goes to the runs' own."""
    if k == 1:
        return eps, delta
    lo, hi = 0.0, eps
    for _ in range(100):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if optimal_delta(k, mid, eps) <= delta / 2 else (lo, mid)
    return lo, delta / (2 * k)


def compose_inverse(k: int, eps: float, delta: float, how: str = "optimal") -> tuple[float, float]:
    if how == "optimal":
        return compose_optimal_inverse(k, eps, delta)
    if how == "basic":
        return eps / k, delta / k
    if how != "advanced":
        raise ValueError("how must be optimal, advanced or basic")
    lo, hi = 0.0, eps
    for _ in range(100):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if compose_advanced(k, mid, 0, delta / 2)[0] <= eps else (lo, mid)
    return lo, delta / (2 * k)


def ledger_rows(spec: StreamSpec) -> list[tuple]:
    p = calibrate.plan(spec)
    (ek, dk), (ev, dv) = spec.budget.gate, spec.budget.value
    rounds = spec.bound
    t = spec.timing.triggers
    charged = p.beta * (1 if spec.gate.beta_union else t)
    note = "unions the triggers" if spec.gate.beta_union else "per-trigger quantile: the failure chance is charged for each trigger"
    if spec.timing.assign == "arrival":
        note += "; triggers must not depend on the data"
    rows = [
        ("gate tree", "gaussian tree", ek, dk / 2, p.rho_round * rounds, rounds, p.sigma, "zCDP over the rounds of a unit"),
        ("gate threshold", "tail", 0.0, rounds * (math.exp(ek) + 1) * charged, 0.0, rounds, 0.0, note),
        *((f"value {m.name}", "gaussian tree", ev, dv, p.rho_value / len(spec.measures), 1, s, "sensitivity = bound x a record's most") for m, s in zip(spec.measures, p.value_sigma)),
    ]
    return [*rows, ("total", "sum", ek + ev, rows[0][3] + rows[1][3] + dv, 0.0, 1, 0.0, "gate plus values")]


def ledger(spark: SparkSession, spec: StreamSpec) -> DataFrame:
    return spark.createDataFrame(ledger_rows(spec), "component string, mechanism string, eps double, delta double, rho double, fold int, sigma double, note string")
