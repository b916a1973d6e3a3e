"""Python-side functions: a grouped aggregate and two table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from . import bits as bitlib
from .levels import levels


@F.pandas_udf("double")
def entropy_agg(values: pd.Series) -> float:
    """Bits per value of a group."""
    n = values.value_counts().to_numpy(float)
    p = n / n.sum()
    return float(-(p * np.log2(p)).sum())


@F.pandas_udf("double")
def robust_sigma(values: pd.Series) -> float:
    """1.4826 times the median distance from the median."""
    v = values.to_numpy(float)
    return float(1.4826 * np.median(np.abs(v - np.median(v)))) if len(v) else float("nan")


@F.udtf(returnType="idx int, level double")
class LevelTable:
    """``level_table(kind, bits, trunc)``: the levels of a table as rows."""

    def eval(self, kind: str, bits: int, trunc: float | None) -> Iterator[tuple[int, float]]:
        for i, x in enumerate(levels(kind, bits, trunc)):
            yield i, float(x)


@F.udtf(returnType="idx int, sym int")
class UnpackBlock:
    """``unpack_block(payload, bits, n)``: the symbols of a payload as rows."""

    def eval(self, payload: bytes, bits: int, n: int) -> Iterator[tuple[int, int]]:
        for i, s in enumerate(bitlib.unpacked(payload, bits, n)):
            yield i, int(s)
