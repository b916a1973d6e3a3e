"""Scale factors: planted gains, rank-one fits, bounds, greedy steps, edges."""

import numpy as np
import pyarrow as pa
import pytest

from blockquant.operators import kernels
from blockquant.schema import CELLS, CodecConfig
from blockquant.sources.tables import pairs


def block(n_ant=8, n_ch=8, n_pol=2, seed=0, gains=True, block_id=0):
    rng = np.random.default_rng(seed)
    rows = []
    for r, (a, b) in enumerate(pairs(n_ant)):
        for ch in range(n_ch):
            for pol in range(n_pol):
                g = (0.5 + 1.5 * a / (n_ant - 1)) * (0.5 + 1.5 * b / (n_ant - 1)) * (1 + 0.2 * ch) if gains else 1.0
                rows.append({"block_id": block_id, "row_id": block_id * 36 + r, "ant_a": a, "ant_b": b, "ch": ch, "pol": pol, "re": rng.normal() * g, "im": rng.normal() * g, "weight": 1.0, "flagged": False})
    return pa.Table.from_pylist(rows, kernels.arrow(CELLS))


def of(t, autos="keep", pol=0):
    return kernels.usable(t, t["pol"].to_numpy() == pol, autos)


def test_solvers_recover_an_exact_rank_one_matrix():
    g = np.array([0.5, 1.0, 2.0, 3.0, 0.7])
    var = np.outer(g, g)
    for solver in ("loglsq", "als"):
        assert np.allclose(kernels.solve_antennas(var.copy(), solver), g, rtol=1e-6)


def test_incomplete_matrices_are_solved_iteratively():
    g = np.array([0.5, 1.0, 2.0, 3.0, 0.7])
    var = np.outer(g, g)
    var[0, 1] = var[1, 0] = np.nan
    assert np.allclose(kernels.solve_antennas(var, "loglsq"), g, rtol=1e-3)


def test_two_antennas_fall_back_to_the_rms():
    assert np.allclose(kernels.solve_antennas(np.array([[1.0, 4.0], [4.0, 1.0]])), 2.0)


def test_planted_gains_come_back_to_a_common_scale():
    t = block(8, 64, 1)
    b = of(t, "zero")
    _, f = kernels.fit_antenna_channel(b, CodecConfig(max_steps=0))
    want = np.sqrt((0.5 + 1.5 * np.arange(8) / 7) ** 2)  # f_a = g_a
    r = f["antennas"] / want
    assert r.std() / r.mean() < 0.1
    ch = f["channels"] / (1 + 0.2 * np.arange(64))
    assert ch.std() / ch.mean() < 0.15


@pytest.mark.parametrize("scaling", ["row", "row_channel", "row_channel_af", "antenna_channel"])
def test_nothing_exceeds_the_top_level(scaling):
    b = of(block(), "zero" if scaling == "antenna_channel" else "keep")
    sigma, _ = kernels.fit(b, CodecConfig(scaling=scaling))
    cross = b.a != b.b if scaling == "antenna_channel" else np.ones(len(b.a), bool)
    assert (b.peak[cross] <= sigma[cross] * (1 + 1e-6)).all()


def test_greedy_raises_the_sum_and_ends():
    log = []
    kernels.fit_antenna_channel(of(block(), "zero"), CodecConfig(), log)
    assert (np.diff(log) > 0).all() and len(log) <= 66


def test_polarisations_are_apart_except_for_rows():
    t = block()
    other = t.set_column(t.schema.get_field_index("re"), "re", pa.array(np.where(t["pol"].to_numpy() == 1, t["re"].to_numpy() * 100, t["re"].to_numpy())))
    for s in ("antenna_channel", "row_channel", "row"):
        cfg = CodecConfig(scaling=s, autos="zero" if s == "antenna_channel" else "keep")
        a, b = (kernels.compress_block(x, cfg).to_pylist()[0]["payload"] for x in (t, other))
        assert (a == b) == (s != "row")


def test_one_loud_channel_spoils_rows_and_not_channel_methods():
    t = block(n_pol=1)
    loud = np.where(t["ch"].to_numpy() == 3, 1000.0, 1.0)
    t = t.set_column(6, "re", pa.array(t["re"].to_numpy() * loud)).set_column(7, "im", pa.array(t["im"].to_numpy() * loud))
    err = {}
    for s in ("row", "row_channel", "antenna_channel"):
        b = of(t, "zero")
        sigma, _ = kernels.fit(b, CodecConfig(scaling=s))
        table = kernels.table_of(CodecConfig())
        y = np.clip(b.v / np.where(sigma > 0, sigma, 1)[:, None], -1, 1)
        lo = np.clip(np.searchsorted(table, y, "right") - 1, 0, len(table) - 2)
        var = (y - table[lo]) * (table[lo + 1] - y) * (sigma**2)[:, None]
        keep = (b.ch != 3) & (b.a != b.b)
        err[s] = np.sqrt(var[keep].mean())
    assert err["row"] > 50 * max(err["row_channel"], err["antenna_channel"])


@pytest.mark.parametrize("scaling", ["row", "row_channel", "row_channel_af", "antenna_channel"])
def test_edges_code_and_decode(scaling):
    t = block(3, 2, 1)
    bad = t.set_column(6, "re", pa.array([float("nan")] * t.num_rows)).set_column(7, "im", pa.array([float("inf")] * t.num_rows))
    zero = t.set_column(6, "re", pa.array([0.0] * t.num_rows)).set_column(7, "im", pa.array([0.0] * t.num_rows))
    cfg = CodecConfig(scaling=scaling, autos="zero" if scaling == "antenna_channel" else "keep")
    for x in (bad, zero, t.slice(0, 1), t.slice(1, 2)):
        for r in kernels.compress_block(x, cfg).to_pylist():
            back = kernels.decompress_row(r)
            if x is zero:
                assert (back["re"] == 0).all() and (back["im"] == 0).all()
            if x is bad:
                assert np.isnan(back["re"]).all()


def test_entropy_stages_and_missing_cells_round_trip():
    t = block().take([i for i in range(block().num_rows) if i % 7])
    plain = None
    for e in (None, "rice", "deflate"):
        rows = kernels.compress_block(t, CodecConfig(scaling="row_channel", autos="keep", bits=5, entropy=e)).to_pylist()
        back = [kernels.decompress_row(r) for r in rows]
        assert sum(len(b["re"]) for b in back) == t.num_rows
        if plain is None:
            plain = back
        assert all(np.array_equal(a["re"], b["re"]) for a, b in zip(plain, back, strict=True))


def test_bit_ratio_follows_theory():
    b = of(block(8, 32, 1), "zero")
    sigma, _ = kernels.fit_row_channel(b)
    e = {}
    for bits in (8, 16):
        t = np.linspace(-1, 1, (1 << bits) - 1)
        y = np.clip(b.v / sigma[:, None], -1, 1)[b.a != b.b]
        lo = np.clip(np.searchsorted(t, y, "right") - 1, 0, len(t) - 2)
        e[bits] = np.sqrt(((y - t[lo]) * (t[lo + 1] - y)).mean())
    assert abs(e[8] / e[16] / 258.0 - 1) < 0.03


def test_rice_codes_of_any_length_come_back():
    rng = np.random.default_rng(4)
    for bits in (2, 3, 5, 8, 12):
        for n in (0, 1, 2, 7, 1000):
            symbols = rng.integers(0, 1 << bits, n)
            assert np.array_equal(kernels.unrice(kernels.rice(symbols, bits), bits, n), symbols)
        skewed = np.clip(np.round(rng.normal(kernels.zero_symbol(bits), 0.3, 5000)), 0, (1 << bits) - 1).astype(int)
        assert np.array_equal(kernels.unrice(kernels.rice(skewed, bits), bits, 5000), skewed)


def test_each_block_takes_its_own_truncation():
    """The stored truncation is the one of least expected error, block by block, and decoding uses it."""
    from blockquant.functions.levels import levels

    rng, flat, chosen = np.random.default_rng(1), block(8, 32, 1, gains=False), set()
    shapes = {"uniform": rng.uniform(-1, 1, (2, flat.num_rows)), "normal": rng.normal(0, 1, (2, flat.num_rows)), "heavy": rng.standard_t(2, (2, flat.num_rows))}
    for values in shapes.values():
        t = flat.set_column(6, "re", pa.array(values[0])).set_column(7, "im", pa.array(values[1]))
        for bits in (3, 8):
            cfg = CodecConfig(scaling="antenna_channel", autos="keep", bits=bits, trunc_grid=(3.5, 1.5, 2.5))
            r, b = kernels.compress_block(t, cfg).to_pylist()[0], of(t)
            sigma = kernels.fit(b, cfg)[0][:, None]
            y, errors = np.clip(b.v / sigma, -1, 1), {}
            for trunc in cfg.trunc_grid:
                table = levels("tgauss", bits, trunc)
                lo = np.clip(np.searchsorted(table, y, "right") - 1, 0, len(table) - 2)
                errors[trunc] = np.sqrt(np.mean((y - table[lo]) * (table[lo + 1] - y) * sigma**2))
            assert errors[r["trunc"]] <= min(errors.values()) + 1e-12
            back, cross = kernels.decompress_row(r), t["ant_a"].to_numpy() != t["ant_b"].to_numpy()
            assert np.sqrt(np.mean((back["re"] - values[0])[cross] ** 2)) < 3 * errors[r["trunc"]]
            chosen.add(r["trunc"])
    assert len(chosen) > 1
