"""Accounting of bits, memory and storage."""

from __future__ import annotations

import math

OVERHEAD = 32
MIB = 1 << 20


def bits(b: int, d: int, refine: bool = True, cells: int | None = None, norm_bits: int = 16) -> int:
    """Bits a vector: codes, one more a coordinate if refined, and id and norm: a fixed 32, or exact if ``cells`` is given."""
    return b * d + d * int(refine) + (OVERHEAD if cells is None else math.ceil(math.log2(max(cells, 2))) + norm_bits)


def pq_bits(m: int, bits_each: int) -> int:
    return m * bits_each


def memory_mib(n: int, bits_each: float, cells: int = 0, d: int = 0) -> float:
    """Codes of n vectors and the coarse centroids as 32-bit floats, in MiB."""
    return (n * bits_each / 8 + cells * d * 4) / MIB


def graph_bytes(n: int, d: int, links: int) -> int:
    """Raw vectors and 2 * links neighbour ids of 4 bytes each."""
    return n * (4 * d + 8 * links)


def rerank_memory_mib(n: int, bits_each: float, cells: int, d: int) -> tuple[float, float, float]:
    """(raw, codes, both) in MiB."""
    raw, codes = n * d * 4 / MIB, memory_mib(n, bits_each, cells, d)
    return raw, codes, raw + codes


def regime(m: int, bits_each: int, d: int, b: int = 4) -> float:
    """A product quantizer's bits over those of the inverted index at b bits and refinement."""
    return pq_bits(m, bits_each) / bits(b, d)


class Ledger:
    """Machine-independent costs of a run: seconds, rows encoded again, bytes written."""

    def __init__(self) -> None:
        self.rows: list[tuple[str, float, int, int]] = []

    def add(self, what: str, seconds: float, encoded: int = 0, written: int = 0) -> None:
        self.rows.append((what, seconds, encoded, written))

    def totals(self) -> dict[str, tuple[float, int, int]]:
        out: dict[str, tuple[float, int, int]] = {}
        for what, s, e, w in self.rows:
            a = out.get(what, (0.0, 0, 0))
            out[what] = (a[0] + s, a[1] + e, a[2] + w)
        return out
