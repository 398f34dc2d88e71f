"""The noisy gate: threshold tests on bucket counts with noise, charged only when they pass.

A test asks whether the number of active buckets that satisfy a predicate is at least (or at most) a
level. Noise is a fixed function of a secret seed and the test's identity, so a replay repeats the same
draws. A passing test adds one to the access count of every bucket that satisfied it; a bucket whose
count reaches the limit is retired. ``noise='theory'`` has the scales of the analysis, ``'scaled'``
shrinks them by a visible factor and proves nothing, ``'none'`` has no noise.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from math import exp, log, sqrt

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, mix64, uniform
from .sizing import privacy_parameters

AT_LEAST, AT_MOST = 1, -1


def gate_delta(eps: float, delta: float) -> float:
    inner = log(1 / delta) / eps
    return inner * max(1.0, log(inner))


@dataclass(frozen=True)
class Gate:
    eps: float
    delta: float
    limit: int | None
    seed: int = 99
    noise: str = "theory"
    factor: float = 1.0

    @staticmethod
    def for_reports(limit: int, n: int, m: int, width: int, weights: bool = False, c1: float = 1.0, c2: float = 1.0, seed: int = 99, noise: str = "theory", factor: float = 1.0) -> Gate:
        """The gate of reports over n keys and at most m queries: both privacy parameters follow from the access limit.

        Weights cost one more passing test for each reported key, so with them the limit is doubled.
        """
        eps, delta = privacy_parameters(limit, n, m, width, c1, c2)
        return Gate(eps, delta, 2 * limit if weights else limit, seed, noise, factor)

    @property
    def _factor(self) -> float:
        return {"theory": 1.0, "scaled": self.factor, "none": 0.0}[self.noise]

    @property
    def cap(self) -> float:
        return gate_delta(self.eps, self.delta) * self._factor

    @property
    def scales(self) -> tuple[float, float]:
        return 10 * self.cap, log(1 / self.delta) / self.eps * self._factor

    def noise_column(self, kind: int, direction: int, *parts: Column) -> Column:
        """Noise of the test that ``parts`` and ``kind`` name."""
        wide, narrow = self.scales
        a = laplace(uniform(self.seed, *parts, F.lit(2 * kind)), wide)
        b = laplace(uniform(self.seed, *parts, F.lit(2 * kind + 1)), narrow)
        capped = F.least(F.lit(self.cap), b) if direction == AT_LEAST else F.greatest(F.lit(-self.cap), b)
        return a + capped

    def noise_value(self, kind: int, direction: int, *parts: int) -> float:
        """The same number in Python, for the serial replay."""
        wide, narrow = self.scales
        a = _laplace(_uniform(self.seed, *parts, 2 * kind), wide)
        b = _laplace(_uniform(self.seed, *parts, 2 * kind + 1), narrow)
        return a + (min(self.cap, b) if direction == AT_LEAST else max(-self.cap, b))

    def pass_probability(self, count: float, level: float, direction: int = AT_LEAST) -> float:
        return survival((level - count) * direction, *self.scales, self.cap)

    def privacy(self) -> tuple[float, float]:
        """(epsilon, delta) of the whole sequence, up to a constant."""
        limit = self.limit or 0
        return sqrt(limit) * self.eps + limit * self.eps**2, limit * self.delta

    def radius(self, tests: int, beta: float) -> float:
        """Error of all of that many tests, up to a constant."""
        return gate_delta(self.eps, self.delta) * log(tests / beta)


def laplace(u: Column, scale: float) -> Column:
    drawn = F.transform(F.array(u - 0.5), lambda side: F.lit(-scale) * F.signum(side) * F.log(1 - 2 * F.abs(side)))
    return F.element_at(drawn, 1)


def _laplace(u: float, scale: float) -> float:
    side = u - 0.5
    return -scale * (1 if side > 0 else -1) * log(1 - 2 * abs(side))


def _uniform(seed: int, *parts: int) -> float:
    state = mix64(seed) % PRIME
    for k, part in enumerate(parts):
        a, b, c = (mix64(seed * 31 + k * 7 + j) % PRIME for j in range(3))
        state = ((state * a + part % PRIME) % PRIME * b + c) % PRIME
        state = (state * state % PRIME * state + c) % PRIME
    return (state + 0.5) / PRIME


def survival(x: float, wide: float, narrow: float, cap: float) -> float:
    """P(A + min(cap, B) >= x) for independent Laplace A and B of the two scales.

    Between break points the integrand is a sum of exponentials, which is integrated piece by piece.
    """
    if wide == 0:
        return float(x <= 0)
    # So far out nothing is left of either tail, and the terms below would overflow.
    if abs(x) > cap + 40 * (wide + narrow):
        return float(x < 0)

    def tail(z: float) -> float:
        return 0.5 * exp(-z / wide) if z >= 0 else 1 - 0.5 * exp(z / wide)

    def power(scale: float, rate: float, low: float, high: float) -> float:
        """Integral of scale * exp(rate * y); the exponent is never positive at the far end."""
        if abs(rate) < 1e-15:
            return scale * (high - low)
        at = lambda y: 0.0 if y == float("-inf") else exp(rate * y)
        return scale * (at(high) - at(low)) / rate

    total = 0.5 * exp(-cap / narrow) * tail(x - cap)
    cuts = sorted({min(c, cap) for c in (0.0, x, cap)})
    low = float("-inf")
    for high in cuts:
        middle = high - 1.0 if low == float("-inf") else (low + high) / 2
        rate = 1 / narrow if middle < 0 else -1 / narrow
        if x - middle >= 0:
            total += power(0.25 / narrow * exp(-x / wide), rate + 1 / wide, low, high)
        else:
            total += power(0.5 / narrow, rate, low, high) - power(0.25 / narrow * exp(x / wide), rate - 1 / wide, low, high)
        low = high
    return min(1.0, max(0.0, total))


@dataclass
class Accesses:
    """Access counts of the buckets charged so far, and the retired ones: what the gate remembers."""

    limit: int | None
    counts: dict[tuple[int, int], int] = field(default_factory=dict)
    retired: set[tuple[int, int]] = field(default_factory=set)
    passes: int = 0
    asks: int = 0

    def charge(self, buckets: list[tuple[int, int]]) -> None:
        self.passes += 1
        for b in buckets:
            self.counts[b] = self.counts.get(b, 0) + 1
            if self.limit is not None and self.counts[b] >= self.limit:
                self.retired.add(b)

    def histogram(self) -> dict[int, int]:
        values, n = np.unique(list(self.counts.values()) or [0], return_counts=True)
        return dict(zip(values.tolist(), n.tolist()))
