"""The per-key state machine: key gate with rounds, forecast and value release.

For one key it receives the triggers that have data, in order. Between two of them it walks
the silent triggers with an unchanged buffer, which is the forecast: the first one that passes is
when the key would be released without new records. A key is tested only while its buffer is not empty and
its exact user count is over the pre-threshold.

Users that count once a round come as numbers by previous trigger: a unit counts in a round if
its previous trigger for the key lies before the round. So no set of users is ever kept.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from ..functions.calibrate import Plan
from ..functions.noise import noise_key
from ..functions.tree import PrefixNoise, discrete_draws
from ..spec import GateConfig


@dataclass
class KeyState:
    """What a key carries between triggers; `at` is the last trigger walked, `begin` the one before the round."""

    round: int = 1
    at: int = 0
    users: int = 0
    begin: int = 0
    buffer: list[float] = field(default_factory=list)
    released: list[float] = field(default_factory=list)
    records: int = 0


@dataclass
class Cost:
    tests: int = 0


class KeyGate:
    def __init__(self, plan: Plan, gate: GateConfig, secret: str, measures: tuple[str, ...], key: str | None, state: KeyState | None = None, window: str = ""):
        self.plan, self.gate, self.secret, self.measures = plan, gate, secret, measures
        self.key = window + noise_key(key)
        self.state = state or KeyState()
        if not self.state.buffer:
            self.state.buffer, self.state.released = [0.0] * len(measures), self.state.released or [0.0] * len(measures)
        self.cost = Cost()
        self._users: tuple[int, np.ndarray, np.ndarray] | None = None
        self._values: list[PrefixNoise] = []

    def tree(self, stream: str, round_: int, sigma: float) -> PrefixNoise:
        draws = discrete_draws(self.secret, stream, self.key, round_, sigma) if self.gate.noise == "discrete" and sigma else None
        return PrefixNoise(self.secret, stream, self.key, round_, self.gate.variance, self.plan.triggers, draws)

    def users_noise(self) -> tuple[np.ndarray, np.ndarray]:
        """Noise of the round's user counts by trigger, and what exact count passes at each: more than that."""
        r = self.state.round
        if self._users is None or self._users[0] != r:
            z = self.plan.sigma * self.tree("gate", r, self.plan.sigma).all()
            self._users = (r, z, self.gate.mu + np.asarray(self.plan.taus) - z)
        return self._users[1], self._users[2]

    def value_noise(self, j: int, i: int) -> float:
        if not self._values:
            self._values = [self.tree(f"value-{m}", 0, s) for m, s in zip(self.measures, self.plan.value_sigma)]
        return self._values[j].at(i)

    def open(self) -> bool:
        """Whether there is anything to test: unreleased records, or, without rounds, any user so far."""
        return bool(self.state.records) or (not self.gate.restart and bool(self.state.users))

    def testable(self) -> bool:
        s, mu = self.state, self.gate.mu
        return (s.users >= mu if self.gate.pre_inclusive else s.users > mu) and self.open()

    def first_pass(self, begin: int, last: int) -> int | None:
        """The first trigger in begin..last at which the present buffer passes."""
        if begin > last or not self.testable():
            return None
        over = self.state.users > self.users_noise()[1][begin - 1 : last]
        at = int(np.argmax(over))
        self.cost.tests += at + 1 if over[at] else len(over)
        return begin + at if over[at] else None

    def release(self, i: int, cause: str) -> tuple:
        s = self.state
        s.released = [a + b for a, b in zip(s.released, s.buffer)]
        hats = [v + sd * self.value_noise(j, i) for j, (v, sd) in enumerate(zip(s.released, self.plan.value_sigma))]
        row = (i, s.round, cause, float(s.users + self.users_noise()[0][i - 1]), *hats)
        s.buffer = [0.0] * len(self.measures)
        s.records = 0
        if self.gate.restart:
            s.round += 1
            s.users, s.begin = 0, i
        return row

    def silent_until(self, last: int) -> list[tuple]:
        """Walk the triggers after the last one walked up to `last` without new records."""
        out = []
        while (i := self.first_pass(self.state.at + 1, last)) is not None:
            self.state.at = i
            out.append(self.release(i, "silent"))
        self.state.at = max(self.state.at, last)
        return out

    def forecast(self) -> int | None:
        """The first later trigger at which the present buffer would pass; the state stays."""
        return self.first_pass(self.state.at + 1, self.plan.triggers)

    def arrive(self, i: int, users: int, sums: list[float], records: int, previous: list[tuple[int, int]] | None = None) -> list[tuple]:
        """Silent triggers before i, then the data of trigger i and its test (an arrival wins a tie with a forecast).

        previous: numbers of units by their previous trigger for the key (0: none), if a unit counts once a round.
        """
        out = self.silent_until(i - 1)
        s = self.state
        s.at = i
        s.users += users if previous is None else sum(n for p, n in previous if p <= s.begin)
        s.buffer = [a + b for a, b in zip(s.buffer, sums)]
        s.records += records
        if self.first_pass(i, i) is not None:
            out.append(self.release(i, "arrival"))
        return out
