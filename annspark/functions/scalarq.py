"""Scalar quantizers of least mean squared error for one coordinate of a random unit vector.

``design`` is for the Gaussian limit N(0, 1/d): levels are conditional means of their cells, edges midpoints of
neighbouring levels. They depend on (bits, d) alone; no data is looked at. ``design_exact`` uses the exact law of
the coordinate at finite d. The refinement bit says on which side of its level a value lies; it decodes to
the conditional mean of that half of the cell.
"""

from __future__ import annotations

import functools
import math
from dataclasses import dataclass

import numpy as np

_erf = np.vectorize(math.erf, otypes=[float])


def _pdf(x: np.ndarray) -> np.ndarray:
    return np.where(np.isinf(x), 0.0, np.exp(-0.5 * np.where(np.isinf(x), 0.0, x) ** 2)) / math.sqrt(2 * math.pi)


def _cdf(x: np.ndarray) -> np.ndarray:
    return 0.5 * (1 + _erf(np.asarray(x, float) / math.sqrt(2)))


def _means(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (_pdf(a) - _pdf(b)) / (_cdf(b) - _cdf(a))


@dataclass(frozen=True)
class Quantizer:
    """2^bits levels for coordinates of unit vectors in R^d; ``halves`` are the means of lower and upper half cells."""

    bits: int
    d: int
    levels: np.ndarray
    edges: np.ndarray
    halves: np.ndarray
    distortion: float
    distortion_refined: float

    def encode(self, x: np.ndarray) -> np.ndarray:
        """Number of inner edges at or below each value."""
        return np.searchsorted(self.edges, x, side="right").astype(np.uint8)

    def signs(self, x: np.ndarray, codes: np.ndarray) -> np.ndarray:
        return (x > self.levels[codes]).astype(np.uint8)

    def decode(self, codes: np.ndarray, signs: np.ndarray | None = None) -> np.ndarray:
        return self.levels[codes] if signs is None else self.halves[codes, signs]


def _half(levels: np.ndarray) -> np.ndarray:
    """Conditional means for positive levels of a symmetric quantizer."""
    edges = np.concatenate(([0.0], (levels[1:] + levels[:-1]) / 2, [np.inf]))
    return _means(edges[:-1], edges[1:])


@functools.lru_cache(maxsize=64)
def design(bits: int, d: int = 1) -> Quantizer:
    """Plain alternation from companded quantiles, then Newton steps on the positive half until stationary."""
    k = 1 << (bits - 1)
    p = 0.5 + (np.arange(k) + 0.5) / (2 * k)
    x = np.sqrt(3) * _quantile(p)
    for _ in range(200):
        x = _half(x)
    for _ in range(50):
        f = _half(x) - x
        if np.abs(f).max() < 5e-14:
            break
        jac = -np.eye(k)
        step = 1e-6
        for j in range(k):  # the map is tridiagonal, but k is at most 128
            y, z = x.copy(), x.copy()
            y[j] += step
            z[j] -= step
            jac[:, j] += (_half(y) - _half(z)) / (2 * step)
        x = x - np.linalg.solve(jac, f)
    levels = np.concatenate((-x[::-1], x))
    edges = (levels[1:] + levels[:-1]) / 2
    edges[k - 1] = 0.0
    lo, hi = np.concatenate(([-np.inf], edges)), np.concatenate((edges, [np.inf]))
    halves = np.stack((_means(lo, levels), _means(levels, hi)), axis=1)

    def distortion(a: np.ndarray, b: np.ndarray, v: np.ndarray) -> float:
        # from the full second moment, right away from the fixed point too
        return float(1 + ((_cdf(b) - _cdf(a)) * v * v - 2 * v * (_pdf(a) - _pdf(b))).sum())

    s = 1 / math.sqrt(d)
    return Quantizer(bits, d, levels * s, edges * s, halves * s, distortion(lo, hi, levels), distortion(np.concatenate((lo, levels)), np.concatenate((levels, hi)), np.concatenate((halves[:, 0], halves[:, 1]))))


def _quantile(p: np.ndarray) -> np.ndarray:
    lo, hi = np.full_like(p, -10.0), np.full_like(p, 10.0)
    for _ in range(80):
        mid = (lo + hi) / 2
        up = _cdf(mid) < p
        lo, hi = np.where(up, mid, lo), np.where(up, hi, mid)
    return (lo + hi) / 2


@functools.lru_cache(maxsize=64)
def design_exact(bits: int, d: int, points: int = 200_001, rounds: int = 2_000) -> Quantizer:
    """The same for the coordinate of a uniform unit vector, density proportional to (1 - t^2)^((d - 3) / 2), by quadrature."""
    reach = min(1.0, 12 / math.sqrt(d))
    t = np.linspace(-reach, reach, points)
    with np.errstate(divide="ignore"):
        w = np.exp((d - 3) / 2 * np.log1p(-np.minimum(t * t, 1 - 1e-15)))
    w /= w.sum()
    mass, first = np.concatenate(([0], np.cumsum(w))), np.concatenate(([0], np.cumsum(w * t)))
    levels = design(bits, d).levels.copy()

    def cells(at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        i = np.concatenate(([0], np.searchsorted(t, at, side="left"), [points]))
        return np.diff(mass[i]), np.diff(first[i])

    for _ in range(rounds):
        m, f = cells((levels[1:] + levels[:-1]) / 2)
        new = np.where(m > 0, f / np.maximum(m, 1e-300), levels)
        if np.abs(new - levels).max() < 1e-12:
            break
        levels = new
    edges = (levels[1:] + levels[:-1]) / 2
    both = np.sort(np.concatenate((edges, levels)))
    m, f = cells(both)
    halves = (f / np.maximum(m, 1e-300)).reshape(-1, 2)
    code = np.searchsorted(edges, t, side="right")
    plain = d * float((w * (t - levels[code]) ** 2).sum())
    fine = d * float((w * (t - halves[code, (t > levels[code]).astype(int)]) ** 2).sum())
    return Quantizer(bits, d, levels, edges, halves, plain, fine)
