"""Dithered quantising of scaled samples, and its expected error.

Three ways to the two levels around a value: arithmetic for uniform levels; a binary search over a literal table, as a
higher-order function, for up to 8 bits; and numpy over Arrow batches for any table. All three give the same symbols.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.dither import ordinal, uniform
from ..functions.levels import levels, n_levels, nan_symbol
from ..schema import TABLES, CodecConfig


def samples(cells: DataFrame, n_ch: int = 1024) -> DataFrame:
    """One row per real or imaginary part: the cell's keys, sigma if there, part, v and the sample's ordinal."""
    keys = [c for c in ("block_id", "row_id", "ant_a", "ant_b", "ch", "pol", "sigma", "weight") if c in cells.columns]
    part = F.explode(F.array(F.struct(F.lit(0).alias("part"), F.col("re").alias("v")), F.struct(F.lit(1).alias("part"), F.col("im").alias("v")))).alias("s")
    return cells.select(*keys, part).select(*keys, "s.part", "s.v").withColumn("ord", ordinal(n_ch=n_ch) + F.col("part"))


def scaled(v: Column | str = "v", sigma: Column | str = "sigma") -> Column:
    """v / sigma in -1..1; 0 where sigma is 0."""
    v, s = (F.col(x) if isinstance(x, str) else x for x in (v, sigma))
    return F.greatest(F.least(F.when(s > 0, v / F.nullif(s, F.lit(0.0))).otherwise(0.0), F.lit(1.0)), F.lit(-1.0))


def table(cfg: CodecConfig) -> np.ndarray:
    return levels(cfg.quantiser, cfg.bits, cfg.trunc if cfg.quantiser == "tgauss" else None, cfg.sampling)


def literal(values: np.ndarray) -> Column:
    return F.lit([float(x) for x in values])


def position(y: Column, cfg: CodecConfig) -> tuple[Column, Column, Column]:
    """Index of the level below y, that level, and the one above."""
    n = n_levels(cfg.bits)
    if cfg.quantiser == "uniform":
        lo = F.least(F.floor((y + 1.0) * ((n - 1) / 2.0)), F.lit(n - 2)).cast("int")
        return lo, lo * (2.0 / (n - 1)) - 1.0, (lo + 1) * (2.0 / (n - 1)) - 1.0
    if cfg.bits > 8:
        raise ValueError("tables of more than 255 levels stay out of plans: use the Arrow engine")
    t = literal(table(cfg))
    steps = F.array(*(F.lit(1 << k) for k in range(cfg.bits - 1, -1, -1)))
    lo = F.aggregate(steps, F.lit(0), lambda at, s: F.when((at + s <= n - 2) & (F.element_at(t, F.least(at + s, F.lit(n - 2)) + 1) <= y), at + s).otherwise(at))
    return lo, F.element_at(t, lo + 1), F.element_at(t, lo + 2)


def symbol(cfg: CodecConfig, v: str = "v", sigma: str = "sigma", ord_: str = "ord") -> Column:
    """Symbol of one sample; null and NaN get the NaN symbol."""
    y = scaled(v, sigma)
    n = n_levels(cfg.bits)
    u = F.lit(0.5) if cfg.dither == "none" else uniform(F.col(ord_), cfg.seed)
    if cfg.dither == "subtractive":
        s = F.greatest(F.least(F.floor((y + 1.0) * ((n - 1) / 2.0) + u), F.lit(n - 1)), F.lit(0)).cast("int")
    else:
        lo, below, above = position(y, cfg)
        s = lo + F.when(u < (y - below) / (above - below), 1).otherwise(0)
    return F.when(F.col(v).isNull() | F.isnan(v), nan_symbol(cfg.bits)).otherwise(s).cast("int")


def value(cfg: CodecConfig, sym: str = "sym", sigma: str = "sigma", ord_: str = "ord") -> Column:
    """Decoded sample; the NaN symbol gives NaN."""
    n = n_levels(cfg.bits)
    s = F.col(sym)
    if cfg.dither == "subtractive":
        y = (s - uniform(F.col(ord_), cfg.seed) + 0.5) * (2.0 / (n - 1)) - 1.0
        y = F.when(F.col(sigma) > 0, y).otherwise(0.0)
    elif cfg.quantiser == "uniform":
        y = s * (2.0 / (n - 1)) - 1.0
    else:
        y = F.element_at(literal(table(cfg)), F.least(s, F.lit(n - 1)) + 1)
    return F.when(s == nan_symbol(cfg.bits), float("nan")).otherwise(y * F.col(sigma))


def encode(sampled: DataFrame, cfg: CodecConfig, engine: str = "auto") -> DataFrame:
    """``sampled`` (v, sigma, ord) with ``sym``."""
    native = cfg.quantiser == "uniform" or cfg.bits <= 8
    if engine == "native" or engine == "auto" and native:
        return sampled.withColumn("sym", symbol(cfg))
    return sampled.withColumn("sym", symbol_udf(cfg)(F.col("v"), F.col("sigma"), F.col("ord")))


def symbol_udf(cfg: CodecConfig):
    """The same by numpy over Arrow batches, for any number of levels."""
    from pyspark.sql.functions import arrow_udf

    from . import kernels
    from ..functions.dither import uniform_array

    @arrow_udf(T.IntegerType())
    def sym(v: pa.Array, sigma: pa.Array, ord_: pa.Array) -> pa.Array:
        x, s = (np.array(a.to_numpy(zero_copy_only=False), float) for a in (v, sigma))
        s = np.nan_to_num(s)
        u = uniform_array(ord_.to_numpy(zero_copy_only=False), cfg.seed) if cfg.dither != "none" else np.full(len(x), 0.5)
        out = kernels.subtractive(x, s, u, cfg.bits) if cfg.dither == "subtractive" else kernels.quantised(x, s, kernels.table_of(cfg), u, cfg.bits)
        return pa.array(out.astype(np.int32))

    return sym


def decode(coded: DataFrame, cfg: CodecConfig) -> DataFrame:
    return coded.withColumn("v_hat", value(cfg))


def expected_square(cfg: CodecConfig) -> Column:
    """Variance of the dithered choice in closed form: (y - below)(above - y) sigma^2."""
    y = scaled()
    _, below, above = position(y, cfg)
    return (y - below) * (above - y) * F.col("sigma") * F.col("sigma")


def expected_rms(sampled: DataFrame, cfg: CodecConfig, *by: str) -> DataFrame:
    return sampled.where("v is not null and not isnan(v)").groupBy(*by).agg(F.sqrt(F.avg(expected_square(cfg))).alias("rms"))


def expected_rms_many(sampled: DataFrame, bits: tuple[int, ...], tables: tuple[str, ...] = tuple(TABLES)) -> DataFrame:
    """table, bits, rms for every combination in one pass: each Arrow batch gives its sums, which are added up. Nothing else moves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            v, s = (np.array(batch.column(i).to_numpy(zero_copy_only=False), float) for i in (0, 1))
            ok = np.isfinite(v) & np.isfinite(s)
            v, s = v[ok], s[ok]
            y = np.clip(np.divide(v, s, out=np.zeros_like(v), where=s > 0), -1, 1)
            out = []
            for name in tables:
                quantiser, trunc = TABLES[name]
                for b in bits:
                    t = levels(quantiser, b, trunc)
                    lo = np.clip(np.searchsorted(t, y, "right") - 1, 0, len(t) - 2)
                    out.append((name, b, float(((y - t[lo]) * (t[lo + 1] - y) * s * s).sum()), len(y)))
            yield pa.RecordBatch.from_arrays([pa.array([o[i] for o in out], k) for i, k in enumerate((pa.string(), pa.int32(), pa.float64(), pa.int64()))], names=["quantiser", "bits", "total", "n"])

    sums = sampled.select("v", "sigma").mapInArrow(run, "quantiser string, bits int, total double, n bigint")
    return sums.groupBy("quantiser", "bits").agg(F.sqrt(F.sum("total") / F.sum("n")).alias("rms"))


def repeat_codec(sampled: DataFrame, cfg: CodecConfig, repeats: int, id_col: str = "ord") -> DataFrame:
    """Each sample coded ``repeats`` times with fresh dither: its mean. Repeats are an array in the row, not copies of it."""
    y = scaled()
    _, below, above = position(y, cfg)
    share = (y - below) / (above - below)
    ks = F.sequence(F.lit(0), F.lit(repeats - 1))
    start = F.struct(F.lit(0.0).alias("up"), share.alias("share"))  # the share goes along, so it is found once a sample and not once a repeat
    one = lambda acc, k: acc["up"] + F.when(uniform(F.col(id_col) + k * 1_000_003, cfg.seed) < acc["share"], 1.0).otherwise(0.0)
    up = F.aggregate(ks, start, lambda acc, k: F.struct(one(acc, k).alias("up"), acc["share"].alias("share")), lambda acc: acc["up"])
    return sampled.withColumn("v_mean", (below + (above - below) * up / repeats) * F.col("sigma"))


def fit_truncation(sampled: DataFrame, bits: int, grid: tuple[float, ...] = (1.5, 2.0, 2.5, 3.0, 3.5), *by: str) -> DataFrame:
    """Per group the truncation of least expected error, ties to the smaller, with that error."""
    errors = [F.sqrt(F.avg(expected_square(CodecConfig(quantiser="tgauss", trunc=t, bits=bits)))).alias(f"e{i}") for i, t in enumerate(grid)]
    g = sampled.where("v is not null").groupBy(*by).agg(*errors)
    options = F.array(*(F.struct(F.round(f"e{i}", 12).alias("rms"), F.lit(t).alias("trunc")) for i, t in enumerate(grid)))
    best = F.array_min(options)
    return g.select(*by, best["trunc"].alias("best_trunc"), best["rms"].alias("rms"))
