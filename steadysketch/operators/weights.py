"""Weights of reported keys through the gate: the first value up to which half of a key's buckets lie.

Asking about every integer in turn is the naive scan. The answer's law depends on the number of bucket
estimates up to the asked value only, so all integers between two neighbouring estimates pass with one
probability, and the first pass among them is one geometric draw: the skipping scan.
"""

from __future__ import annotations

from collections.abc import Callable
from math import floor, log, log1p

import numpy as np

from .gate import AT_LEAST, Gate
from .sizing import TRIGGER


def scan_naive(estimates: np.ndarray, most: int, level: float, noise: Callable[[int], float]) -> int:
    """The first integer of -most..most whose noisy count reaches the level, else ``most``; ``noise`` draws for each ask."""
    for w in range(-most, most + 1):
        if np.count_nonzero(estimates <= w) + noise(w) >= level:
            return w
    return most


def scan(estimates: np.ndarray, most: int, level: float, gate: Gate, draw: Callable[[int], float]) -> int:
    """A value with the law of the naive scan: cells between sorted estimates, one draw of ``draw(cell)`` in (0, 1) each."""
    edges = np.ceil(np.sort(np.clip(estimates, -most, most + 1)))
    starts = np.unique(np.concatenate(([-most], edges[edges <= most]))).astype(np.int64)
    for cell, start in enumerate(starts):
        stop = int(starts[cell + 1]) if cell + 1 < len(starts) else most + 1
        p = gate.pass_probability(int(np.count_nonzero(estimates <= start)), level, AT_LEAST)
        if p <= 0:
            continue
        step = 0 if p >= 1 else floor(log(draw(cell)) / log1p(-p))
        if step < stop - start:
            return int(start) + step
    return most


def weight_of(estimates: np.ndarray, per_key: float, most: int, gate: Gate, draw: Callable[[int], float]) -> tuple[int, np.ndarray]:
    """The scanned weight and which buckets the passing test charges."""
    w = scan(estimates, most, per_key * TRIGGER, gate, draw)
    return w, estimates <= w


def private_median(estimates: np.ndarray, eps: float, grid: np.ndarray, draw: float) -> float:
    """A median by the exponential mechanism over a sorted grid: the score is the distance of ranks."""
    below = np.searchsorted(np.sort(estimates), grid, side="right")
    score = -np.abs(below - len(estimates) / 2)
    weight = np.exp(eps / 2 * (score - score.max()))
    return float(grid[np.searchsorted(np.cumsum(weight), draw * weight.sum()).clip(0, len(grid) - 1)])
