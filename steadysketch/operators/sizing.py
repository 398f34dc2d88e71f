"""Parameter rules: sketch sizes, privacy parameters and thresholds, with the calibrated constants."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil, log, sqrt

#: Calibrated by simulation of a Gaussian tail with chance collisions; not given in closed form anywhere.
C_A, C_B = 2.0, 4.0
TAU_A, TAU_B = 0.85, 0.96
TAU_B_COMPACT, C_B_COMPACT = 0.94, 3.0
#: Trigger levels of the weight scan.
TRIGGER_DOWN, TRIGGER_UP = 0.1, 0.9
TRIGGER = (TRIGGER_DOWN + TRIGGER_UP) / 2


def mid(tau_a: float = TAU_A, tau_b: float = TAU_B) -> float:
    return (tau_a + tau_b) / 2


def step_levels(tau_a: float = TAU_A, tau_b: float = TAU_B) -> tuple[float, float]:
    """Leave and enter levels of the continuous report."""
    gap = tau_b - tau_a
    return tau_a + gap / 5, tau_b - gap / 5


def width_for(k: int, c_b: float = C_B) -> int:
    return ceil(c_b * c_b * k)


def suspect_cap(k: int, c_a: float = C_A, c_b: float = C_B) -> int:
    return ceil((c_a + 1) * width_for(k, c_b))


def size_median(k: int, alpha: float, delta: float, n: int, m: int = 1) -> tuple[int, int]:
    """(rows, width) of a row-hashed sketch for m inputs fixed in advance."""
    rows = ceil(4 * log(n * m / delta))
    return rows + 1 - rows % 2, ceil(8 * k / alpha)


def size_agreement(n: int, m: int, beta: float, slack: float) -> int:
    """Expected buckets per key so that all agreements of m fixed inputs are within ``slack``."""
    return ceil(3 * log(2 * 2 * m * n / beta) / slack**2)


def slack(tau_a: float = TAU_A, tau_b: float = TAU_B, continuous: bool = False) -> float:
    """How far an estimated agreement may be off for the reports to be right."""
    return (tau_b - tau_a) / (25 if continuous else 10)


def budget_share(slack_: float, form: str = "markov") -> float:
    """Largest cost of a sequence, as a share of the access limit, that leaves enough useful buckets.

    By Markov's inequality the expected share of used-up buckets must stay below half the slack; the
    second-moment bound allows its root.
    """
    return slack_ / 2 if form == "markov" else sqrt(slack_ / 2)


def privacy_parameters(limit: int, n: int, m: int, width: int, c1: float = 1.0, c2: float = 1.0) -> tuple[float, float]:
    """(epsilon, delta) of one test for an access limit, n keys and m queries of a sketch."""
    if m < limit:
        raise ValueError(f"at least as many queries ({m}) as accesses of a bucket ({limit}) are needed")
    return c1 / sqrt(limit), c2 / (n * m * width * limit)


@dataclass(frozen=True)
class RobustSize:
    buckets: int
    width: int
    eps: float
    delta: float
    limit: int


def size_robust(k: int, n: int, m: int, limit: int, beta: float = 0.01, c1: float = 1.0, c2: float = 1.0, c3: float = 1.0) -> RobustSize:
    """Theory sizes. They are far beyond any table at hand; the constants are the caller's."""
    b = width_for(k)
    eps, delta = privacy_parameters(limit, n, m, b, c1, c2)
    logs = log(max(2.0, limit * log(m * n * b * limit))) * log(m * n * limit) * log(m * n / beta)
    return RobustSize(ceil(c3 * b * sqrt(limit) * logs), b, eps, delta, limit)


def generalization_terms(d: int, b: int, n: int, m: int, beta: float, slack_: float) -> dict[str, float]:
    """The parameters of the generalization bound for n keys and m queries, and whether d buckets keep every term in its third."""
    t = ceil(2 * n * (4 * m + 1) / beta)
    xi, eta = slack_ / 6, slack_ / (6 * t * b)
    least = 12 * b * log(t + 1) / (xi * slack_)
    return {"repetitions": float(t), "xi": xi, "eta": eta, "least_buckets": least, "bound": generalization_bound(d, b, eta, xi, t), "allowed": slack_ / (3 * b)}


def generalization_bound(d: int, b: int, eta: float, xi: float, t: int) -> float:
    """Largest of the three terms that bound bucket means against their expectation."""
    return max(2 * xi / b, 2 * eta * t, 4 * log(t + 1) / (xi * d))


def size_baselines(m: int, k: int) -> dict[str, float]:
    """Sketch sizes up to logarithms: private ensemble and noisy median against the robust reports."""
    return {"private_ensemble": sqrt(m) * k**1.5, "noisy_median": sqrt(m) * k**1.5, "robust": sqrt(m) * k, "fresh_copies": float(m * k)}
