"""Fixed rotations made from a seed by a counter-based generator, so that every engine and version agrees."""

from __future__ import annotations

import functools

import numpy as np

_U = np.uint64


def splitmix(seed: int, n: int) -> np.ndarray:
    """n values of the SplitMix64 stream of the seed."""
    with np.errstate(over="ignore"):
        x = _U(seed) + (np.arange(1, n + 1, dtype=np.uint64)) * _U(0x9E3779B97F4A7C15)
        x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
        return x ^ (x >> _U(31))


def gaussians(seed: int, n: int) -> np.ndarray:
    """Standard normals by the Box-Muller transform."""
    m = (n + 1) // 2
    u = ((splitmix(seed, 2 * m) >> _U(11)).astype(np.float64) + 0.5) / 2.0**53
    r, t = np.sqrt(-2 * np.log(u[:m])), 2 * np.pi * u[m:]
    return np.concatenate((r * np.cos(t), r * np.sin(t)))[:n]


@functools.lru_cache(maxsize=32)
def dense(d: int, seed: int = 42) -> np.ndarray:
    """A Haar-distributed orthogonal d x d matrix: QR of a Gaussian one, with a positive diagonal of R."""
    q, r = np.linalg.qr(gaussians(seed * 1_000_003 + d, d * d).reshape(d, d))
    out = q * np.sign(np.diag(r))[None, :]
    out.setflags(write=False)
    return out


class Hadamard:
    """Sign flips and fast Walsh-Hadamard transforms, three rounds, on the next power of two: O(d log d) a vector.

    Rotates zero-padded vectors, so inner products are kept; outputs have ``width`` components.
    """

    def __init__(self, d: int, seed: int = 42, rounds: int = 3):
        self.d, self.width = d, 1 << max(0, (d - 1).bit_length())
        bits = splitmix(seed * 7_919 + d, self.width * rounds) >> _U(63)
        self.signs = (bits.astype(np.float64) * 2 - 1).reshape(rounds, self.width)

    def apply(self, x: np.ndarray) -> np.ndarray:
        y = np.zeros((len(x), self.width))
        y[:, : self.d] = x
        for s in self.signs:
            y = y * s
            h = 1
            while h < self.width:
                z = y.reshape(len(y), -1, 2, h)
                y = np.concatenate((z[:, :, :1] + z[:, :, 1:], z[:, :, :1] - z[:, :, 1:]), axis=2).reshape(len(y), -1)
                h *= 2
            y /= np.sqrt(self.width)
        return y


def hadamard(d: int, seed: int = 42) -> Hadamard:
    return Hadamard(d, seed)
