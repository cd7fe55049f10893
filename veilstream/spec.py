"""What a private stream aggregation is: its columns, windows, budget and gate settings."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from .functions.noise import Secret

#: Public secret for tests. Releases made with it can be recomputed by anyone and are not private.
TEST_SECRET = "public-test-secret"


@dataclass(frozen=True)
class Measure:
    """A summed value column; `clamp` bounds the absolute value of a record (1 for counts).

    square: sum the squares of the clamped values, for a variance.
    """

    name: str
    column: str | None = None
    clamp: float = 1.0
    square: bool = False

    @property
    def sensitivity(self) -> float:
        """The most that one record adds."""
        return self.clamp**2 if self.square else self.clamp


@dataclass(frozen=True)
class Timing:
    """T fixed, data-independent triggers a window.

    assign: `shuffled` spreads records over the triggers by a hash of their id, `rows`
    takes equal shares in id order, `arrival` maps arrival time linearly on the window
    (of window_s seconds of event time) and its lateness; later records are dropped.
    """

    triggers: int = 8
    assign: str = "shuffled"
    lateness_s: int = 0
    window_s: int = 86_400

    def __post_init__(self):
        if self.triggers < 1 or self.assign not in ("shuffled", "rows", "arrival"):
            raise ValueError("triggers must be positive and assign one of shuffled, rows, arrival")


@dataclass(frozen=True)
class Budget:
    """Total (eps, delta) and the gate's shares of both; the rest pays for values."""

    eps: float = 6.0
    delta: float = 1e-9
    gate_eps_frac: float = 0.5
    gate_delta_frac: float = 2 / 3

    @property
    def gate(self) -> tuple[float, float]:
        return self.eps * self.gate_eps_frac, self.delta * self.gate_delta_frac

    @property
    def value(self) -> tuple[float, float]:
        return self.eps - self.gate[0], self.delta - self.gate[1]


@dataclass(frozen=True)
class GateConfig:
    """Key gate: pre-threshold, rounds, how users are counted, thresholds.

    count_mode: `pair_once` counts a unit once for a key, `round_distinct` once a round,
    `batch_additive` once a trigger. tau_mode: `per_trigger`, `universal` or `theorem`.
    variance: `bottom_up` or `plain` prefix sums. beta_union: share the failure chance over
    the triggers; beta_eps: which epsilon stands in the slack factor. noise: `gaussian`, or
    `discrete` for whole-number node noise (with `plain` prefix sums).
    """

    mu: int = 0
    pre_inclusive: bool = False
    restart: bool = True
    count_mode: str = "pair_once"
    tau_mode: str = "per_trigger"
    variance: str = "bottom_up"
    beta_union: bool = True
    beta_eps: str = "total"
    noise: str = "gaussian"

    def __post_init__(self):
        if self.noise not in ("gaussian", "discrete") or (self.noise == "discrete" and self.variance != "plain"):
            raise ValueError("noise is gaussian, or discrete with plain prefix sums")


@dataclass(frozen=True)
class StreamSpec:
    """Columns of the record frame, the contribution bound C of a privacy unit, and the secret that keys the noise.

    secret: text, or functions.noise.EnvSecret or FileSecret to be looked up where noise is drawn; there is no default.
    """

    bound: int
    measures: tuple[Measure, ...] = (Measure("count"),)
    timing: Timing = field(default_factory=Timing)
    budget: Budget = field(default_factory=Budget)
    gate: GateConfig = field(default_factory=GateConfig)
    secret: Secret | None = field(kw_only=True, repr=False)

    def validate(self, records: DataFrame) -> None:
        need = {"unit", "key", "record_id"} | {m.column for m in self.measures if m.column}
        if missing := need - set(records.columns):
            raise ValueError(f"records lack the columns {sorted(missing)}")
        if self.bound < 1:
            raise ValueError("the contribution bound must be positive")
        if not self.secret:
            raise ValueError("a secret is required: releases made with a known one are not private")
