"""Golden values and properties of the functions under the index."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from annspark.functions import bounds, codes, cost, rotation, scalarq, stats
from annspark.operators import cfi

# Distortion of stage 1, with refinement, and largest level, for unit variance.
DESIGN = {1: (0.363380, 0.125083, 0.797885), 2: (0.117482, 0.037245, 1.510418), 3: (0.034548, 0.010106, 2.151946), 4: (0.009501, 0.002612, 2.732590), 5: (0.002505, 0.000661, 3.260732), 6: (0.000644, 0.000166, 3.744101)}


@pytest.mark.parametrize("b", DESIGN)
def test_design(b):
    q, (plain, fine, top) = scalarq.design(b), DESIGN[b]
    assert q.distortion == pytest.approx(plain, abs=6e-7) and q.distortion_refined == pytest.approx(fine, abs=6e-7) and q.levels[-1] == pytest.approx(top, abs=1e-6)
    assert np.allclose(q.levels, -q.levels[::-1]) and (np.diff(q.levels) > 0).all()
    assert (q.encode(q.levels) == np.arange(1 << b)).all()
    assert ((q.halves[:, 0] < q.levels) & (q.levels < q.halves[:, 1])).all()
    assert np.allclose(scalarq.design(b, 64).levels * 8, q.levels)


def test_exact_law_has_lighter_tails():
    assert scalarq.design_exact(4, 64).distortion < scalarq.design(4).distortion
    assert scalarq.design_exact(4, 2000).distortion == pytest.approx(scalarq.design(4).distortion, rel=0.01)


@pytest.mark.parametrize("d", [2, 64, 96])
def test_rotation(d):
    r = rotation.dense(d, 7)
    assert np.abs(r @ r.T - np.eye(d)).max() < 1e-10 and not np.allclose(r, rotation.dense(d, 8))
    x = np.random.default_rng(1).standard_normal((5, d))
    h = rotation.hadamard(d, 7).apply(x)
    assert np.allclose(h @ h.T, x @ x.T) and h.shape[1] == rotation.hadamard(d, 7).width


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 8), st.integers(1, 40), st.integers(0, 5), st.integers(0, 1000))
def test_packing(bits, d, n, seed):
    c = np.random.default_rng(seed).integers(0, 1 << bits, (n, d)).astype(np.uint8)
    p = codes.pack(c, bits)
    assert p.shape[1] == -(-d * bits // 8) and (codes.unpack(p, bits, d) == c).all()
    assert (codes.from_binary(codes.to_binary(p), p.shape[1]) == p).all()


def test_half_norms():
    x = np.random.default_rng(2).uniform(0.01, 2, 1000)
    assert np.abs(codes.from_half(codes.half_bits(x)) / x - 1).max() < 2**-11 + 1e-9


def test_accounting():
    assert [cost.bits(4, d) for d in (96, 128, 200)] == [512, 672, 1032]
    # Printed MiB at one million vectors, a thousand cells
    for d, printed in ((128, (65, 81, 96)), (96, (50, 61, 73)), (100, (52, 64, 76))):
        assert [round(cost.memory_mib(1_000_000, cost.bits(b - 1, d), 1000, d)) for b in (4, 5, 6)] == list(printed)
    assert round(cost.graph_bytes(1_000_000, 128, 32) / cost.MIB) == 732
    assert [round(x) for x in cost.rerank_memory_mib(1_000_000, cost.bits(4, 128), 1000, 128)] == [488, 81, 569]
    assert [round(cost.regime(m, b, 96), 2) for m, b in ((48, 8), (48, 10), (96, 8))] == [0.75, 0.94, 1.5]


def test_statistics():
    assert stats.t_quantile(2) == pytest.approx(stats.T_TWO, abs=1e-9) and stats.t_quantile(8) == pytest.approx(2.306004, abs=1e-6)
    t = 1.7
    assert stats.t_p(t, 2) == pytest.approx(1 - t / math.sqrt(2 + t * t), abs=1e-12)
    # Printed changes of nine matched cells
    diff = [-0.38, 0.01, 0.52, 0.18, 0.19, 0.33, -0.50, -0.04, 0.43]
    m, half, p = stats.paired_t(diff, [0.0] * 9)
    assert (round(m, 2), round(half, 2), round(p, 2)) == (0.08, 0.27, 0.5)
    mean, half = 0.80, 0.25
    assert stats.t_p(mean / (half / stats.T_TWO), 2) == pytest.approx(0.0052, abs=1e-4)


def test_bounds_hold():
    b, d, delta = 4, 64, 0.05
    q, v = scalarq.design(b, d), np.zeros(d)
    v[:3] = (0.6, 0.48, 0.64)
    err = []
    for s in range(200):
        y = rotation.dense(d, 500 + s) @ v
        err.append(np.linalg.norm(y - q.decode(q.encode(y))))
    assert np.quantile(err, 1 - delta) < bounds.single(b, d, delta)
    low, high = bounds.worst_case(b, d)
    assert max(err) <= high + 1e-9 and low <= high + 1e-9 and bounds.uniform(b, d, delta) <= high
    assert np.mean(np.square(err)) == pytest.approx(bounds.db(b), rel=0.12)


def test_worked_search():
    """Two dimensions, no rotation, one bit: the residual of (0.6, 0.8) to the cell (1, 0)."""
    index = cfi.Index(2, 1, np.array([[1.0, 0.0]]), "sign", 42, exact_norm=True)
    x = np.array([[0.6, 0.8]])
    r = x - index.c
    n = np.linalg.norm(r)
    u = r / n
    code = index.q.encode(u)
    sign = index.q.signs(u, code)
    assert n == pytest.approx(0.894427, abs=1e-6) and code.tolist() == [[0, 1]] and sign.tolist() == [[1, 1]]
    for query, exact, plain, fine in (((0, 1), 0.8, 0.504627, 0.863783), ((0.8, 0.6), 0.96, 0.699075, 1.126885)):
        q = np.array(query, float)
        base = q @ index.c[0]
        assert q @ x[0] == pytest.approx(exact)
        assert base + n * (q @ index.q.decode(code)[0]) == pytest.approx(plain, abs=1e-5)
        assert base + n * (q @ index.q.decode(code, sign)[0]) == pytest.approx(fine, abs=1e-5)
