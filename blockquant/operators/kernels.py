"""One block at a time in numpy: scaling by any method, quantising, packing.

A block is what a group of ``applyInArrow`` holds: one polarisation and sub-band of a block of the observation, bounded by its
antennas and the sub-band's channels, not by its length (row scaling needs the row's polarisations together).
"""

from __future__ import annotations

import bz2
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import bits as bitlib
from ..functions.dither import uniform_array
from ..functions.levels import levels, nan_symbol, zero_symbol
from ..schema import CELLS, PACKED, CodecConfig

N_CH_LIMIT, N_POL_LIMIT = 1024, 4


@dataclass
class Block:
    """Samples of one polarisation of one block, NaN where unusable; ``re`` and ``im`` as columns of ``v``."""

    row: np.ndarray
    a: np.ndarray
    b: np.ndarray
    ch: np.ndarray
    v: np.ndarray

    @property
    def peak(self) -> np.ndarray:
        return np.nan_to_num(np.abs(self.v)).max(1)


def usable(t: pa.Table, where: np.ndarray, autos: str) -> Block:
    col = lambda n, k: t[n].to_numpy().astype(k)[where]
    v = np.column_stack([col("re", float), col("im", float)])
    v[~np.isfinite(v).all(1) | pc.fill_null(t["flagged"], False).to_numpy()[where]] = np.nan
    b = Block(col("row_id", np.int64), col("ant_a", np.int64), col("ant_b", np.int64), col("ch", np.int64), v)
    if autos == "zero":
        v[(b.a == b.b) & ~np.isnan(v[:, 0])] = 0
    return b


def rows_as_blocks(t: pa.Table, n_pol: int, autos: str, first_ch: int = 0) -> list[Block]:
    """The polarisations of a block in rows layout: ``vis`` as [ch][pol][re, im], and ``flag`` as [ch][pol] if there."""
    n = t.num_rows
    v = pc.fill_null(t["vis"].combine_chunks().flatten(), float("nan")).to_numpy(zero_copy_only=False).astype(float).reshape(n, -1, n_pol, 2)
    bad = ~np.isfinite(v).all(3)
    if "flag" in t.column_names:
        bad |= pc.fill_null(t["flag"].combine_chunks().flatten(), False).to_numpy(zero_copy_only=False).reshape(bad.shape)
    k = v.shape[1]
    col = lambda name: np.repeat(t[name].to_numpy().astype(np.int64), k)
    row, a, b, ch = col("row_id"), col("ant_a"), col("ant_b"), np.tile(np.arange(first_ch, first_ch + k), n)
    out = []
    for p in range(n_pol):
        own = v[:, :, p].reshape(-1, 2)
        own[bad[:, :, p].ravel()] = np.nan
        if autos == "zero":
            own[(a == b) & ~np.isnan(own[:, 0])] = 0
        out.append(Block(row, a, b, ch, own))
    return out


def grouped(values: np.ndarray, index: np.ndarray, n: int, how) -> np.ndarray:
    out = np.zeros(n)
    how.at(out, index, values)
    return out


def ratio(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.divide(x, y, out=np.zeros_like(x, dtype=float), where=y > 0)


def channel_rms(b: Block, ch: np.ndarray, n_ch: int, keep: np.ndarray, centre: bool = False) -> np.ndarray:
    ok = keep & ~np.isnan(b.v[:, 0])
    v = b.v[ok]
    if centre:
        mean = np.column_stack([ratio(grouped(v[:, p], ch[ok], n_ch, np.add), grouped(np.ones(ok.sum()), ch[ok], n_ch, np.add)) for p in (0, 1)])
        v = v - mean[ch[ok]]
    return np.sqrt(ratio(grouped((v**2).sum(1) / 2, ch[ok], n_ch, np.add), grouped(np.ones(ok.sum()), ch[ok], n_ch, np.add)))


def solve_antennas(var: np.ndarray, solver: str = "als", sweeps: int = 50) -> np.ndarray:
    """g with var[a, b] ~ g[a] g[b] off the diagonal; NaN marks missing baselines. The scale factor of an antenna is sqrt(g)."""
    n = len(var)
    there = np.isfinite(var) & (var > 0)
    np.fill_diagonal(there, False)
    if n < 3 or not there.any():
        level = np.nanmean(var[there]) if there.any() else 0.0
        return np.full(n, np.sqrt(level))
    complete = (there.sum(1) == n - 1).all()
    if complete:
        logs = np.where(there, np.log(np.where(there, var, 1.0)), 0.0).sum(1)
        g = np.exp((logs - logs.sum() / (2 * (n - 1))) / (n - 2))
        if solver == "loglsq":
            return g
    else:
        g = np.sqrt(ratio(np.where(there, var, 0).sum(1), there.sum(1)))
        g[g == 0] = np.sqrt(var[there].mean())
    w, partners = np.where(there, var, 0.0), there.astype(float)
    alone = ~there.any(1)
    for _ in range(sweeps):
        new = np.sqrt(g * (w @ g) / np.maximum(partners @ (g * g), 1e-300))  # damped by the geometric mean: plain substitution oscillates
        new[alone] = g[alone]
        if (np.abs(new - g) <= 1e-10 * g).all():
            break
        g = new
    return g


def stored(f: np.ndarray, cfg: CodecConfig) -> np.ndarray:
    return f.astype(np.float32) if cfg.round_factors else f


def fit_row(b: Block, row_peak: np.ndarray) -> tuple[np.ndarray, dict]:
    rows, at = np.unique(b.row, return_inverse=True)
    f = grouped(row_peak, at, len(rows), np.maximum).astype(np.float32)
    return f[at].astype(float), {"rows": f}


def fit_row_channel(b: Block, start: np.ndarray | None = None, centre: bool = False) -> tuple[np.ndarray, dict]:
    rows, r = np.unique(b.row, return_inverse=True)
    chans, c = np.unique(b.ch, return_inverse=True)
    f1 = channel_rms(b, c, len(chans), np.ones(len(b.row), bool), centre)[c] if start is None else start
    row = grouped(ratio(b.peak, f1), r, len(rows), np.maximum).astype(np.float32)
    if start is not None:
        return f1 * row[r], {"rows": row}
    m = grouped(ratio(b.peak, f1 * row[r]), c, len(chans), np.maximum)
    base = grouped(f1, c, len(chans), np.maximum)
    ch = (base * m).astype(np.float32)
    return ch[c].astype(float) * row[r], {"rows": row, "channels": ch}


def fit_antenna_channel(b: Block, cfg: CodecConfig, log: list[float] | None = None) -> tuple[np.ndarray, dict]:
    """Channels to unit rms, antennas by the rank-one fit, everything under the top level, then greedy maximisation."""
    chans, c = np.unique(b.ch, return_inverse=True)
    ants = np.unique(np.concatenate([b.a, b.b]))
    a, bb = np.searchsorted(ants, b.a), np.searchsorted(ants, b.b)
    n, k = len(ants), len(chans)
    cross = b.a != b.b
    ok = cross & ~np.isnan(b.v[:, 0])
    f_ch = channel_rms(b, c, k, cross, cfg.centre)
    y = b.v / np.where(f_ch > 0, f_ch, 1)[c][:, None]
    power = grouped((y[ok] ** 2).sum(1) / 2, a[ok] * n + bb[ok], n * n, np.add)
    count = grouped(np.ones(ok.sum()), a[ok] * n + bb[ok], n * n, np.add)
    var = np.where(count > 0, ratio(power, count), np.nan).reshape(n, n)
    var = np.fmax(var, var.T)
    f_ant = np.sqrt(solve_antennas(var, cfg.solver))
    dead = f_ant <= 0
    f_ant[dead] = 1
    peak, total = np.where(cross, b.peak, 0), np.where(cross, np.nan_to_num(np.abs(b.v)).sum(1), 0)
    sigma = f_ch[c] * f_ant[a] * f_ant[bb]
    top = ratio(peak, sigma).max(initial=0)
    f_ch = f_ch * (top or 1)
    for step in range(cfg.max_steps + 1):
        sigma = f_ch[c] * f_ant[a] * f_ant[bb]
        y, s = ratio(peak, sigma), ratio(total, sigma)
        whole = s.sum()
        if log is not None:
            log.append(float(whole))
        if step == cfg.max_steps:
            break
        tops = np.concatenate([grouped(y, c, k, np.maximum), np.maximum(grouped(y, a, n, np.maximum), grouped(y, bb, n, np.maximum))])
        sums = np.concatenate([grouped(s, c, k, np.add), grouped(s, a, n, np.add) + grouped(s, bb, n, np.add)])
        gain = np.where(tops > 0, ratio(np.ones(len(tops)), tops) - 1, 0) * sums
        best = int(gain.argmax())
        if gain[best] < cfg.tau * whole or not whole:
            break
        if best < k:
            f_ch[best] *= tops[best]
        else:
            f_ant[best - k] *= tops[best]
    f_ch, f_ant = stored(f_ch, cfg), stored(f_ant, cfg)
    sigma = f_ch[c].astype(float) * f_ant[a] * f_ant[bb]
    factors = {"channels": f_ch, "antennas": f_ant, "ant_ids": ants}
    auto = ~cross
    if cfg.autos == "own_factor" and auto.any():
        own = ratio(b.peak, f_ch[c].astype(float))[auto]
        per = grouped(own, a[auto], n, np.maximum).astype(np.float32)
        sigma[auto] = f_ch[c[auto]].astype(float) * per[a[auto]]
        factors["autos"] = per
    elif auto.any() and cfg.scaling == "antenna_channel":
        sigma[auto] = np.where(cfg.autos == "zero", 0.0, np.maximum(sigma, b.peak)[auto])
    return sigma, factors


def fit(b: Block, cfg: CodecConfig, row_peak: np.ndarray | None = None) -> tuple[np.ndarray, dict]:
    if cfg.scaling == "row":
        return fit_row(b, b.peak if row_peak is None else row_peak)
    if cfg.scaling == "row_channel":
        return fit_row_channel(b, centre=cfg.centre)
    sigma, factors = fit_antenna_channel(b, cfg)
    if cfg.scaling == "row_channel_af":
        sigma, rows = fit_row_channel(b, sigma)
        factors |= rows
    return sigma, factors


def ordinals(b: Block, pol: int) -> np.ndarray:
    base = ((b.row * N_CH_LIMIT + b.ch) * N_POL_LIMIT + pol) * 2
    return np.column_stack([base, base + 1])


def quantised(v: np.ndarray, sigma: np.ndarray, table: np.ndarray, u: np.ndarray, bits: int) -> np.ndarray:
    """Symbols: of the two levels around v / sigma the upper one if u is below its share of the way; NaN has its own."""
    y = np.clip(np.where(sigma > 0, v / np.where(sigma > 0, sigma, 1), 0.0), -1, 1)
    bad = np.isnan(v)
    y[bad] = 0
    lo = np.clip(np.searchsorted(table, y, "right") - 1, 0, len(table) - 2)
    share = (y - table[lo]) / (table[lo + 1] - table[lo])
    return np.where(bad, nan_symbol(bits), lo + (u < share))


def dequantised(symbols: np.ndarray, sigma: np.ndarray, table: np.ndarray) -> np.ndarray:
    out = np.append(table, np.nan)[symbols] * sigma
    return np.where(symbols == len(table), np.nan, out)


def subtractive(v: np.ndarray, sigma: np.ndarray, u: np.ndarray, bits: int) -> np.ndarray:
    """Uniform levels: the dither shifts the value before rounding; ``unshifted`` takes it off again."""
    n = (1 << bits) - 1
    y = np.clip(np.where(sigma > 0, v / np.where(sigma > 0, sigma, 1), 0.0), -1, 1)
    at = np.clip(np.floor((y + 1) / 2 * (n - 1) + u), 0, n - 1)
    return np.where(np.isnan(v), nan_symbol(bits), np.nan_to_num(at)).astype(np.int64)


def unshifted(symbols: np.ndarray, sigma: np.ndarray, u: np.ndarray, bits: int) -> np.ndarray:
    n = (1 << bits) - 1
    y = (symbols - u + 0.5) / (n - 1) * 2 - 1
    return np.where(symbols == nan_symbol(bits), np.nan, np.where(sigma > 0, y * sigma, 0.0))


def table_of(cfg: CodecConfig) -> np.ndarray:
    return levels(cfg.quantiser, cfg.bits, cfg.trunc if cfg.quantiser == "tgauss" else None, cfg.sampling)


def fit_by_kernel(cells: DataFrame, cfg: CodecConfig) -> DataFrame:
    """Cells with ``sigma``, null where unusable; one shuffle by block."""
    from .scaling import masked

    def run(t: pa.Table) -> pa.Table:
        pols = t["pol"].to_numpy()
        sigma = np.zeros(t.num_rows)
        for p in np.unique(pols):
            where = pols == p
            sigma[where] = fit(usable(t, where, cfg.autos), cfg)[0]
        return t.append_column("sigma", pa.array(sigma, pa.float64()))

    schema = T.StructType([*CELLS.fields, T.StructField("sigma", T.DoubleType())])
    group = ["block_id"] if cfg.scaling == "row" else ["block_id", "pol"]
    return masked(cells.select(*CELLS.fieldNames()), cfg.autos).select(*CELLS.fieldNames()).groupBy(*group).applyInArrow(run, schema)


# Packing.


def entropy_coded(payload: bytes, symbols: np.ndarray, cfg: CodecConfig) -> bytes:
    if cfg.entropy == "deflate":
        return zlib.compress(payload, 6)
    if cfg.entropy == "rice":
        return rice(symbols, cfg.bits)
    return payload


def rice(symbols: np.ndarray, bits: int) -> bytes:
    """Distance from the zero symbol, folded to be positive, in Rice code; the first byte is the parameter of least length."""
    d = symbols.astype(np.int64) - zero_symbol(bits)
    folded = np.where(d >= 0, 2 * d, -2 * d - 1)
    k = min(range(bits + 1), key=lambda k: int((folded >> k).sum()) + len(folded) * (1 + k))
    high = (folded >> k).astype(np.int64)
    width = high + 1 + k
    ends = np.cumsum(width)
    stream = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
    starts = ends - width
    ones = np.repeat(starts, high) + np.arange(high.sum()) - np.repeat(np.cumsum(high) - high, high)
    stream[ones] = 1
    for i in range(k):
        stream[starts + high + 1 + i] = (folded >> (k - 1 - i)) & 1
    return bytes([k]) + np.packbits(stream).tobytes()


def unrice(payload: bytes, bits: int, n: int) -> np.ndarray:
    """Where a code ends depends on where it starts: the places of the first 1, 2, 4 ... codes follow from jumps over as many."""
    k, stream = payload[0], np.unpackbits(np.frombuffer(payload, np.uint8, offset=1))
    end = len(stream)
    zeros = np.flatnonzero(stream == 0)
    after = np.append(zeros, end)[np.searchsorted(zeros, np.arange(end + 1))]  # the first zero at or after each place
    jump = np.minimum(after + 1 + k, end)
    starts = np.zeros(1, np.int64)
    while len(starts) < n:
        starts = np.concatenate([starts, jump[starts]])
        jump = jump[jump]
    starts = starts[:n]
    z = after[starts]
    low = np.zeros(n, np.int64)
    for i in range(k):
        low = low << 1 | stream[np.minimum(z + 1 + i, end - 1)]
    out = (z - starts) << k | low
    return np.where(out % 2 == 0, out // 2, -(out + 1) // 2) + zero_symbol(bits)


def best_trunc(b: Block, sigma: np.ndarray, cfg: CodecConfig) -> float | None:
    """The truncation of least expected error, ties to the smaller; the configured one without a grid."""
    if not cfg.trunc_grid:
        return cfg.trunc if cfg.quantiser == "tgauss" else None
    v, s = b.v[~np.isnan(b.v[:, 0])], sigma[~np.isnan(b.v[:, 0])][:, None]
    y = np.clip(np.divide(v, s, out=np.zeros_like(v), where=s > 0), -1, 1)
    errors = []
    for t in sorted(cfg.trunc_grid):
        table = levels(cfg.quantiser, cfg.bits, t, cfg.sampling)
        lo = np.clip(np.searchsorted(table, y, "right") - 1, 0, len(table) - 2)
        errors.append((round(float(np.sqrt(np.mean((y - table[lo]) * (table[lo + 1] - y) * s * s))), 12) if len(v) else 0.0, t))
    return min(errors)[1]


def packed_row(block_id: int, p: int, b: Block, cfg: CodecConfig, peak: np.ndarray | None) -> dict:
    """One polarisation of a block as a packed row. Cells are laid on the grid of the block's rows and channels."""
    sigma, factors = fit(b, cfg, peak)
    trunc = best_trunc(b, sigma, cfg)
    u = uniform_array(ordinals(b, p), cfg.seed) if cfg.dither != "none" else np.full(b.v.shape, 0.5)
    s2 = np.column_stack([sigma, sigma])
    table = levels(cfg.quantiser, cfg.bits, trunc, cfg.sampling)
    symbols = subtractive(b.v, s2, u, cfg.bits) if cfg.dither == "subtractive" else quantised(b.v, s2, table, u, cfg.bits)
    rows, first, r = np.unique(b.row, return_index=True, return_inverse=True)
    chans, c = np.unique(b.ch, return_inverse=True)
    grid = np.full((len(rows) * len(chans), 2), nan_symbol(cfg.bits), np.int64)
    grid[r * len(chans) + c] = symbols
    there = np.zeros(len(grid), bool)
    there[r * len(chans) + c] = True
    payload = bitlib.packed(grid.ravel(), cfg.bits)
    return {
        "block_id": block_id,
        "pol": p,
        "row_ids": rows,
        "ants_a": b.a[first],
        "ants_b": b.b[first],
        "channels": chans,
        "present": None if there.all() else np.packbits(there).tobytes(),
        "row_factors": factors.get("rows"),
        "ant_ids": factors.get("ant_ids"),
        "ant_factors": np.concatenate([factors["antennas"], factors["autos"]]) if "autos" in factors else factors.get("antennas"),
        "ch_factors": factors.get("channels"),
        "scaling": cfg.scaling,
        "quantiser": cfg.quantiser,
        "trunc": trunc,
        "sampling": cfg.sampling,
        "dither": cfg.dither,
        "seed": cfg.seed,
        "bits": cfg.bits,
        "max_abs": float(b.peak.max(initial=0)),
        "entropy": cfg.entropy,
        "payload": entropy_coded(payload, grid.ravel(), cfg),
    }


def row_peaks(blocks: list[Block]) -> list[np.ndarray]:
    """Each cell's row's largest magnitude over all polarisations."""
    rows, at = np.unique(np.concatenate([b.row for b in blocks]), return_inverse=True)
    top = grouped(np.concatenate([b.peak for b in blocks]), at, len(rows), np.maximum)
    return np.split(top[at], np.cumsum([len(b.row) for b in blocks])[:-1])


def used_autos(cfg: CodecConfig) -> str:
    """Only the plain antenna method takes autocorrelations out; the others keep them."""
    return cfg.autos if cfg.scaling == "antenna_channel" else "keep"


def compress_block(t: pa.Table, cfg: CodecConfig) -> pa.Table:
    """The polarisations of a block's cells as packed rows."""
    pols = t["pol"].to_numpy()
    blocks = {int(p): usable(t, pols == p, used_autos(cfg)) for p in np.unique(pols)}
    peaks = row_peaks(list(blocks.values())) if cfg.scaling == "row" else [None] * len(blocks)  # one factor for all polarisations of a row
    block_id = t["block_id"][0].as_py()
    return pa.Table.from_pylist([packed_row(block_id, p, b, cfg, peak) for (p, b), peak in zip(blocks.items(), peaks, strict=True)], ARROW_PACKED)


def compress_rows_block(t: pa.Table, cfg: CodecConfig, n_pol: int) -> pa.Table:
    """The same from rows layout."""
    blocks = rows_as_blocks(t, n_pol, used_autos(cfg), t["first_ch"][0].as_py() if "first_ch" in t.column_names else 0)
    peaks = row_peaks(blocks) if cfg.scaling == "row" else [None] * n_pol
    block_id = t["block_id"][0].as_py()
    return pa.Table.from_pylist([packed_row(block_id, p, b, cfg, peak) for p, (b, peak) in enumerate(zip(blocks, peaks, strict=True))], ARROW_PACKED)


def sigma_of(r: dict) -> np.ndarray:
    """Grid of scale factors from a packed row's stored floats."""
    n, k = len(r["row_ids"]), len(r["channels"])
    ch = np.array(r["ch_factors"], np.float32).astype(float) if r["ch_factors"] else np.ones(k)
    rows = np.array(r["row_factors"], np.float32).astype(float) if r["row_factors"] else np.ones(n)
    if not r["ant_ids"]:
        return rows[:, None] * ch[None, :]
    m = len(r["ant_ids"])
    factors = np.array(r["ant_factors"], np.float32).astype(float)
    a, b = (np.searchsorted(r["ant_ids"], r[x]) for x in ("ants_a", "ants_b"))
    out = (factors[a] * factors[b] * rows)[:, None] * ch[None, :]
    auto = a == b
    if auto.any() and r["scaling"] == "antenna_channel":
        out[auto] = factors[m:][a[auto]][:, None] * ch[None, :] if len(factors) > m else 0.0
    return out


def decompress_row(r: dict) -> dict[str, np.ndarray]:
    """Cells of one packed row."""
    n, k, bits = len(r["row_ids"]), len(r["channels"]), r["bits"]
    if r["entropy"] == "rice":
        symbols = unrice(r["payload"], bits, n * k * 2)
    else:
        symbols = bitlib.unpacked(zlib.decompress(r["payload"]) if r["entropy"] == "deflate" else r["payload"], bits, n * k * 2)
    symbols = symbols.reshape(n * k, 2)
    sigma = np.repeat(sigma_of(r).reshape(-1, 1), 2, axis=1)
    row, ch = np.repeat(np.array(r["row_ids"], np.int64), k), np.tile(np.array(r["channels"], np.int64), n)
    a, b = (np.repeat(np.array(r[x], np.int64), k) for x in ("ants_a", "ants_b"))
    if r["dither"] == "subtractive":
        u = uniform_array(ordinals(Block(row, a, b, ch, symbols), r["pol"]), r["seed"])
        v = unshifted(symbols, sigma, u, bits)
    else:
        v = dequantised(symbols, sigma, levels(r["quantiser"], bits, r["trunc"], r["sampling"]))
    keep = np.ones(n * k, bool) if r["present"] is None else np.unpackbits(np.frombuffer(r["present"], np.uint8), count=n * k).astype(bool)
    return {"row_id": row[keep], "ant_a": a[keep], "ant_b": b[keep], "ch": ch[keep], "re": v[keep, 0], "im": v[keep, 1]}


def arrow(schema: T.StructType) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(schema)


ARROW_PACKED = arrow(PACKED)


def bz2_size(values: bytes) -> int:
    return len(bz2.compress(values, 9))
