"""Keyed dither: a uniform number that depends on a cell's logical ordinal and a seed alone.

Unlike rand() it survives retries, speculation and repartitioning, and any engine with 64-bit integers can repeat it. The
mixer keeps 32 bits between steps, so products stay inside a long.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

MASK = 0xFFFFFFFF
#: Fixed values of the mixer: shift, multiplier, shift, multiplier, shift.
S1, M1, S2, M2, S3 = 15, 739982445, 12, 695872825, 15
SEED_STEP = 40503


def hash32(ordinal: Column, seed: int = 0) -> Column:
    h = (ordinal + F.lit(seed * SEED_STEP)).cast("long").bitwiseAND(F.lit(MASK))
    for shift, factor in ((S1, M1), (S2, M2)):
        h = (h.bitwiseXOR(F.shiftrightunsigned(h, shift)) * F.lit(factor)).bitwiseAND(F.lit(MASK))
    return h.bitwiseXOR(F.shiftrightunsigned(h, S3))


def uniform(ordinal: Column, seed: int = 0) -> Column:
    """In (0, 1)."""
    return (hash32(ordinal, seed) + F.lit(0.5)) / F.lit(4294967296.0)


def uniform_array(ordinal: np.ndarray, seed: int = 0) -> np.ndarray:
    h = (ordinal.astype(np.int64) + seed * SEED_STEP) & MASK
    for shift, factor in ((S1, M1), (S2, M2)):
        h = ((h ^ (h >> shift)) * factor) & MASK
    return ((h ^ (h >> S3)) + 0.5) / 4294967296.0


def uniform_sql(ordinal: str, seed: int = 0) -> str:
    """The same in DuckDB's SQL."""
    h = f"((({ordinal}) + {seed * SEED_STEP})::BIGINT & {MASK})"
    for shift, factor in ((S1, M1), (S2, M2)):
        h = f"((xor({h}, {h} >> {shift}) * {factor}) & {MASK})"
    return f"((xor({h}, {h} >> {S3}) + 0.5::DOUBLE) / 4294967296.0::DOUBLE)"


def ordinal(row_id: str = "row_id", ch: str = "ch", pol: str = "pol", part: int = 0, n_ch: int = 1024, n_pol: int = 4) -> Column:
    """Number of a sample among all samples of an observation: row, channel, polarisation, part (0 re, 1 im)."""
    return ((F.col(row_id).cast("long") * n_ch + F.col(ch)) * n_pol + F.col(pol)) * 2 + part


def ordinal_sql(part: int, n_ch: int = 1024, n_pol: int = 4) -> str:
    return f"(((row_id::BIGINT * {n_ch} + ch) * {n_pol} + pol) * 2 + {part})"
