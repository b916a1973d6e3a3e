"""Level tables: 2^bits - 1 symmetric levels with 0 in the middle and 1 at the end; one more symbol is NaN.

A table samples the inverse of a cumulative distribution at equally spaced probabilities, so levels are dense where values
are frequent. Probabilities are the midpoints of equal cells, which also works for distributions without bounds.
"""

from __future__ import annotations

from functools import lru_cache
from statistics import NormalDist

import numpy as np

NORMAL = NormalDist()


def n_levels(bits: int) -> int:
    return (1 << bits) - 1


def zero_symbol(bits: int) -> int:
    return (1 << (bits - 1)) - 1


def nan_symbol(bits: int) -> int:
    return (1 << bits) - 1


@lru_cache(maxsize=256)
def levels(quantiser: str, bits: int, trunc: float | None = None, sampling: str = "midpoint") -> np.ndarray:
    """``quantiser``: gauss, tgauss (needs ``trunc``), uniform or lloyd. ``sampling='endpoint'``: of bounded tables only."""
    n = n_levels(bits)
    if quantiser == "uniform":
        out = np.linspace(-1, 1, n)
    elif quantiser == "lloyd":
        out = lloyd_max(n)
    else:
        lo, hi = (NORMAL.cdf(-trunc), NORMAL.cdf(trunc)) if quantiser == "tgauss" else (0.0, 1.0)
        if sampling == "endpoint":
            if quantiser != "tgauss":
                raise ValueError("endpoint sampling needs a bounded distribution")
            p = lo + (hi - lo) * np.arange(n) / (n - 1)
        else:
            p = lo + (hi - lo) * (np.arange(n) + 0.5) / n
        out = np.array([NORMAL.inv_cdf(x) for x in p])
    half = (out[n // 2 + 1 :] - out[: n // 2][::-1]) / 2  # exactly symmetric, with an exact zero
    out = np.concatenate([-half[::-1], [0.0], half])
    out /= out[-1]
    out.setflags(write=False)
    return out


def lloyd_max(n: int, rounds: int = 400) -> np.ndarray:
    """Levels of least squared error for a normal distribution: each is the mean of the values nearest to it."""
    x = np.array([NORMAL.inv_cdf((i + 0.5) / n) for i in range(n)])
    for _ in range(rounds):
        edges = np.concatenate([[-np.inf], (x[1:] + x[:-1]) / 2, [np.inf]])
        density = np.exp(-np.clip(edges, -40, 40) ** 2 / 2) / np.sqrt(2 * np.pi)
        density[[0, -1]] = 0
        mass = np.diff([NORMAL.cdf(float(np.clip(e, -40, 40))) for e in edges])
        new = -np.diff(density) / np.maximum(mass, 1e-300)
        if np.abs(new - x).max() < 1e-12:
            break
        x = new
    return x
