"""Error bounds of the rotated scalar quantizer that depend on (bits, d, delta) alone."""

from __future__ import annotations

import math

import numpy as np

from annspark.functions import scalarq


def db(bits: int, refine: bool = False) -> float:
    """Rate-distortion constant: d times the squared error of a coordinate under the Gaussian law."""
    q = scalarq.design(bits)
    return q.distortion_refined if refine else q.distortion


def single(bits: int, d: int, delta: float) -> float:
    """With probability 1 - delta over rotations, a fixed unit vector is rebuilt within this distance.

    The deviation of the coordinate's law from its Gaussian limit enters by the designs' own difference.
    """
    gap = abs(math.sqrt(scalarq.design_exact(bits, d).distortion) - math.sqrt(db(bits)))
    return math.sqrt(db(bits)) + gap + math.sqrt(8 * math.log(2 / delta) / (d - 2))


def uniform(bits: int, d: int, delta: float, eps: float = 0.1) -> float:
    """Inner-product error for all unit vectors at once, by a net of radius eps over which delta is shared (own derivation).

    Log of the net's size is at most d log(1 + 2 / eps). Off the net, a vector moves by eps and its image by no more than
    eps plus one worst-case error each way.
    """
    log_net = d * math.log1p(2 / eps)
    on_net = math.sqrt(db(bits)) + math.sqrt(8 * (math.log(2 / delta) + log_net) / (d - 2))
    return min(on_net + 2 * eps, worst_case(bits, d)[1])


def worst_case(bits: int, d: int, grid: int = 20_001) -> tuple[float, float]:
    """(lower, upper) on the largest rebuild error over the whole sphere: no rotation can beat it uniformly.

    Upper: one-dimensional dual of the constrained maximum. Lower: a coordinate vector.
    """
    q = scalarq.design(bits, d)
    t = np.linspace(-1, 1, grid)
    err = (t - q.levels[q.encode(t)]) ** 2

    def dual(lam: float) -> float:
        return lam + d * float((err - lam * t * t).max())

    lo, hi = 0.0, 4.0
    for _ in range(100):
        a, b = lo + (hi - lo) / 3, hi - (hi - lo) / 3
        lo, hi = (lo, b) if dual(a) < dual(b) else (a, hi)
    top = float(q.levels[-1])
    near = float(np.abs(q.levels).min())
    return math.sqrt((1 - top) ** 2 + (d - 1) * near**2), math.sqrt(dual((lo + hi) / 2))
