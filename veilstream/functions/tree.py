"""Noise of prefix sums in a binary tree whose nodes all carry noise.

Level 0 holds the leaves. A prefix is the sum of the dyadic blocks of its length's binary
form. `plain` takes each block's own node; `bottom_up` averages it with what its
descendants say, which is the same as a recursive inverse-variance mean.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np

from .noise import discrete_normal, normals


def height(triggers: int) -> int:
    return max(0, math.ceil(math.log2(triggers)))


def block_variance(level: int) -> float:
    """Of a block's bottom-up estimate, in units of a node's variance; also its own node's weight."""
    return 1 / (2 * (1 - 2.0 ** -(level + 1)))


def variance(i: int, kind: str = "bottom_up") -> float:
    if kind == "plain":
        return float(i.bit_count())
    if kind == "leaf":
        return float(i)
    return sum(block_variance(b) for b in range(i.bit_length()) if i >> b & 1)


#: Gives, for the numbers of nodes of levels 0, 1, ..., the noise of the nodes of each.
Draws = Callable[[list[int]], list[np.ndarray]]


def prefix_noise(triggers: int, kind: str, draws: Draws) -> np.ndarray:
    """Standard noise of the prefixes 1..T. Only the blocks that end by T are drawn, about 2 T of them."""
    if kind == "leaf":
        return np.cumsum(draws([triggers])[0])
    at = np.arange(1, triggers + 1)
    out, below = np.zeros(triggers), np.zeros(0)
    for level, est in enumerate(draws([triggers >> level for level in range(triggers.bit_length())])):
        if kind == "bottom_up" and level:
            w = block_variance(level)
            est = w * est + (1 - w) * (below[0 : 2 * len(est) : 2] + below[1 : 2 * len(est) : 2])
        has = (at >> level & 1) == 1
        out[has] += est[(at[has] >> level) - 1]
        below = est
    return out


class PrefixNoise:
    """at(i): standard noise of the prefix of length i, up to T triggers, drawn at first use."""

    def __init__(self, secret: str, stream: str, key: str, round_: int = 0, kind: str = "bottom_up", triggers: int = 1, draws: Draws | None = None):
        self.kind, self.triggers = kind, triggers
        self.draws = draws or (lambda sizes: normals(secret, stream, key, round_, sizes))
        self._all: np.ndarray | None = None

    def all(self) -> np.ndarray:
        if self._all is None:
            self._all = prefix_noise(self.triggers, self.kind, self.draws)
        return self._all

    def at(self, i: int) -> float:
        return float(self.all()[i - 1])


def discrete_draws(secret: str, stream: str, key: str, round_: int, sigma: float) -> Draws:
    """Node noise of whole numbers, in units of sigma."""
    return lambda sizes: [np.array([discrete_normal(secret, stream, key, round_, level, j, sigma) / sigma for j in range(n)]) for level, n in enumerate(sizes)]


def sqrt_factor(triggers: int) -> np.ndarray:
    """First column of the square root of the all-ones lower triangular Toeplitz matrix."""
    out = np.ones(triggers)
    for i in range(1, triggers):
        out[i] = out[i - 1] * (2 * i - 1) / (2 * i)
    return out


def prefix_noise_sqrt(draws: np.ndarray) -> np.ndarray:
    """Matrix-factorization noise of all prefixes from independent draws."""
    f = sqrt_factor(len(draws))
    return np.array([float(f[: i + 1][::-1] @ draws[: i + 1]) for i in range(len(draws))])


def sqrt_sensitivity(triggers: int) -> float:
    return float(np.linalg.norm(sqrt_factor(triggers)))


class BruteTree:
    """The tree as an object, for tests: exact sums and noise in every node."""

    def __init__(self, triggers: int, noise: Callable[[int, int], float]):
        self.h = height(triggers)
        self.nodes = [[noise(level, j) for j in range(1 << (self.h - level))] for level in range(self.h + 1)]

    def add(self, leaf: int, value: float) -> None:
        for level in range(self.h + 1):
            self.nodes[level][leaf >> level] += value

    def prefix(self, i: int, kind: str) -> float:
        total, begin = 0.0, 0
        for b in reversed(range(i.bit_length())):
            if i >> b & 1:
                if kind == "plain":
                    total += self.nodes[b][begin >> b]
                else:
                    c = [2.0**-j for j in range(b + 1)]
                    total += sum(w / sum(c) * sum(self.nodes[b - j][(begin >> (b - j)) : (begin >> (b - j)) + (1 << j)]) for j, w in enumerate(c))
                begin += 1 << b
        return total
