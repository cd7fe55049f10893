"""Noise scales and thresholds from budgets; plain Python, results enter plans as literals."""

from __future__ import annotations

import math
from dataclasses import dataclass

from ..spec import StreamSpec
from . import tree


def delta_of(rho: float, eps: float) -> float:
    """Smallest delta for which rho-zCDP implies (eps, delta)-DP, by the best Renyi order."""
    if rho <= 0:
        return 0.0

    def log_delta(a: float) -> float:
        return (a - 1) * (a * rho - eps) + a * math.log1p(-1 / a) - math.log(a - 1)

    lo, hi = 1 + 1e-9, max(2.0, 4 * (eps + 10) / rho)
    ratio = (math.sqrt(5) - 1) / 2
    llo, lhi = math.log(lo - 1), math.log(hi - 1)
    for _ in range(200):  # golden section over log(order - 1)
        x, y = lhi - ratio * (lhi - llo), llo + ratio * (lhi - llo)
        if log_delta(1 + math.exp(x)) < log_delta(1 + math.exp(y)):
            lhi = y
        else:
            llo = x
    return min(1.0, math.exp(min(0.0, log_delta(1 + math.exp((llo + lhi) / 2)))))


def rho_of(eps: float, delta: float) -> float:
    """Largest rho whose zCDP implies (eps, delta)-DP."""
    lo, hi = 0.0, max(eps, 1.0) * 4
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if delta_of(mid, eps) <= delta else (lo, mid)
    return lo


def tail(z: float) -> float:
    return 0.5 * math.erfc(z / math.sqrt(2))


def upper_quantile(p: float) -> float:
    """z with P(N(0,1) > z) = p, accurate far in the tail."""
    lo, hi = -40.0, 40.0
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if tail(mid) > p else (lo, mid)
    return (lo + hi) / 2


def node_sigma(triggers: int, rho: float, sensitivity: float = 1.0) -> float:
    """Noise of a tree node: a record touches one node on each level."""
    return sensitivity * math.sqrt((tree.height(triggers) + 1) / (2 * rho))


def gate_delta_total(eps: float, delta: float, beta: float) -> float:
    return delta + (math.exp(eps) + 1) * beta


def tau_theorem(triggers: int, beta: float, eps: float, delta: float) -> float:
    """Universal threshold of the utility bound: tail over all triggers of a plain prefix."""
    sigma = node_sigma(triggers, rho_of(eps, delta))
    return sigma * math.sqrt(tree.height(triggers) + 1) * math.sqrt(2 * math.log(2 * triggers / beta))


def gaussian_sigma(eps: float, delta: float, sensitivity: float, analytic: bool = True) -> float:
    """One-shot Gaussian noise: exact calibration or the classic bound."""
    if not analytic:
        return sensitivity * math.sqrt(2 * math.log(1.25 / delta)) / eps

    def spent(s: float) -> float:
        a, b = sensitivity / (2 * s), eps * s / sensitivity
        low = tail(a + b)
        return tail(b - a) - (math.exp(eps + math.log(low)) if low > 0 else 0.0)

    lo, hi = 1e-6 * sensitivity, 1e7 * sensitivity
    for _ in range(200):
        mid = math.sqrt(lo * hi)
        lo, hi = (mid, hi) if spent(mid) > delta else (lo, mid)
    return hi


@dataclass(frozen=True)
class Plan:
    """Literals of a run: gate noise, thresholds by trigger (index 0 = trigger 1), value noise by measure."""

    triggers: int
    sigma: float
    taus: tuple[float, ...]
    value_sigma: tuple[float, ...]
    beta: float
    rho_round: float
    rho_value: float


def plan(spec: StreamSpec) -> Plan:
    g, t, c = spec.gate, spec.timing.triggers, spec.bound
    eps_k, delta_k = spec.budget.gate
    rounds = c  # a unit is in at most C rounds, or, without rounds, in the trees of at most C keys
    rho_round = rho_of(eps_k, delta_k / 2) / rounds
    # a unit may hit many leaves of one tree when every batch counts it anew
    sens = float(c) if g.count_mode == "batch_additive" else 1.0
    sigma = node_sigma(t, rho_round, sens)
    slack_eps = eps_k if g.beta_eps == "total" else math.sqrt(2 * rho_round * math.log(1 / delta_k))
    beta = delta_k / 2 / (rounds * (math.exp(slack_eps) + 1))
    share = beta / t if g.beta_union else beta
    var = [tree.variance(i, g.variance) for i in range(1, t + 1)]
    if g.tau_mode == "per_trigger":
        taus = [upper_quantile(share) * sigma * math.sqrt(v) for v in var]
    elif g.tau_mode == "universal":
        taus = [max(upper_quantile(share) * sigma * math.sqrt(v) for v in var)] * t
    else:
        taus = [sigma * math.sqrt(tree.height(t) + 1) * math.sqrt(2 * math.log(2 * t / beta))] * t
    rho_value = rho_of(*spec.budget.value)
    each = rho_value / len(spec.measures)
    return Plan(t, sigma, tuple(taus), tuple(node_sigma(t, each, c * m.sensitivity) for m in spec.measures), beta, rho_round, rho_value)


def equivalent_threshold(eps: float, delta: float, triggers: int, bound: int = 1, mu: int = 0) -> float:
    """Users that a key needs at the first trigger, a single node's noise."""
    sigma = node_sigma(triggers, rho_of(eps, delta / 2) / bound)
    return mu + upper_quantile(delta / 2 / (bound * (math.exp(eps) + 1))) * sigma
