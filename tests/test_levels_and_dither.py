"""Level tables, symbols, dither, packing: against independent numpy and the standard library."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from blockquant.functions import bits as bitlib
from blockquant.functions.dither import uniform_array
from blockquant.functions.levels import levels, lloyd_max, n_levels, nan_symbol, zero_symbol
from blockquant.operators import kernels
from blockquant.schema import TABLES


@pytest.mark.parametrize("label", TABLES)
@pytest.mark.parametrize("bits", [2, 3, 5, 8, 12])
def test_tables_are_monotone_symmetric_and_end_at_one(label, bits):
    t = levels(TABLES[label][0], bits, TABLES[label][1])
    assert len(t) == n_levels(bits) == 2**bits - 1
    assert (np.diff(t) > 0).all() and np.allclose(t, -t[::-1], atol=0) and t[-1] == 1 and t[zero_symbol(bits)] == 0


def test_two_bits_are_the_same_for_every_table():
    assert all(levels(q, 2, t).tolist() == [-1, 0, 1] for q, t in TABLES.values())


def test_eight_bit_symbols():
    t = levels("tgauss", 8, 2.5)
    v = np.array([0.0, np.nan, 3.0, -3.0])
    assert kernels.quantised(v, np.full(4, 3.0), t, np.full(4, 0.5), 8).tolist() == [127, 255, 254, 0]
    assert (zero_symbol(8), nan_symbol(8)) == (127, 255)


def test_midpoint_gauss_levels_follow_the_inverse_cdf():
    from statistics import NormalDist

    raw = np.array([NormalDist().inv_cdf((i + 0.5) / 15) for i in range(15)])
    assert np.allclose(levels("gauss", 4), raw / raw[-1])


def test_lloyd_max_has_published_levels():
    assert np.allclose(lloyd_max(3), [-1.2240, 0, 1.2240], atol=1e-3)


def test_endpoint_and_midpoint_uniform_agree_after_scaling():
    assert np.allclose(levels("uniform", 5), np.linspace(-1, 1, 31))


def test_exact_levels_never_move_and_midpoints_split_evenly():
    t = levels("tgauss", 4, 1.5)
    u = uniform_array(np.arange(200_000))
    for i in (3, 7, 11):
        assert (kernels.quantised(np.full(1000, t[i]), np.ones(1000), t, u[:1000], 4) == i).all()
    mid = (t[4] + t[5]) / 2
    up = (kernels.quantised(np.full(len(u), mid), np.ones(len(u)), t, u, 4) == 5).mean()
    assert abs(up - 0.5) < 5 * 0.5 / np.sqrt(len(u))


def test_dither_is_unbiased_and_its_variance_is_closed_form():
    t = levels("gauss", 3)
    u = uniform_array(np.arange(400_000), 5)
    y = 0.3137
    out = t[kernels.quantised(np.full(len(u), y), np.ones(len(u)), t, u, 3)]
    lo = t[t <= y].max()
    hi = t[t > y].min()
    sd = np.sqrt((y - lo) * (hi - y))
    assert abs(out.mean() - y) < 5 * sd / np.sqrt(len(u))
    assert abs(out.std() / sd - 1) < 0.01


def test_dither_numbers_are_uniform():
    u = uniform_array(np.arange(200_000))
    assert abs(u.mean() - 0.5) < 0.005 and abs(u.var() * 12 - 1) < 0.02 and abs(np.corrcoef(u[1:], u[:-1])[0, 1]) < 0.01 and len(np.unique(u)) == len(u)


@settings(max_examples=60, deadline=None)
@given(st.integers(2, 16), st.integers(0, 70), st.integers(0, 2**31))
def test_packing_round_trip(bits, n, seed):
    s = np.random.default_rng(seed).integers(0, 1 << bits, n)
    p = bitlib.packed(s, bits)
    assert len(p) == -(-n * bits // 8) and bitlib.unpacked(p, bits, n).tolist() == s.tolist()


@settings(max_examples=30, deadline=None)
@given(st.integers(2, 9), st.integers(1, 200), st.integers(0, 2**31))
def test_rice_round_trip(bits, n, seed):
    s = np.clip(np.random.default_rng(seed).normal(2 ** (bits - 1) - 1, 2, n).round(), 0, 2**bits - 1).astype(int)
    assert kernels.unrice(kernels.rice(s, bits), bits, n).tolist() == s.tolist()


def test_subtractive_dither_halves_nothing_but_bounds_the_error():
    v = np.linspace(-0.9, 0.9, 5000)
    u = uniform_array(np.arange(5000))
    s = kernels.subtractive(v, np.ones(5000), u, 5)
    back = kernels.unshifted(s, np.ones(5000), u, 5)
    assert np.abs(back - v).max() <= 1 / 30 + 1e-12
