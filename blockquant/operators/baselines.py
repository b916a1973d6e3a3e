"""What the block codec is compared with."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..schema import CodecConfig
from . import kernels
from .quantise import decode, encode, samples
from .scaling import masked, scale_row


def identity(cells: DataFrame) -> DataFrame:
    return cells


def row_uniform(cells: DataFrame, bits: int, dither: str = "hash", seed: int = 0) -> DataFrame:
    """Row scaling and equal steps: v and v_hat per sample."""
    cfg = CodecConfig(scaling="row", quantiser="uniform", trunc=None, bits=bits, dither=dither, seed=seed)
    return decode(encode(samples(scale_row(masked(cells))), cfg), cfg)


def legacy_row16(cells: DataFrame) -> DataFrame:
    """Row packing to 16 bits by rounding, without dither: half the volume."""
    return row_uniform(cells, 16, dither="none")


def exponent(v: Column) -> Column:
    """Power of two at or below the magnitude; null for zero."""
    return F.floor(F.log2(F.nullif(F.abs(v), F.lit(0.0))))


def mantissa_round(v: Column, bits: int) -> Column:
    """Keep so many bits after the leading one: the step follows the value's own size, so the relative error is constant."""
    step = F.pow(F.lit(2.0), exponent(v) - bits)
    return F.coalesce(F.floor(v / step + 0.5) * step, F.lit(0.0))


def mantissa_dithered(v: Column, bits: int, u: Column) -> Column:
    """The same with a dither added before rounding and taken off after it."""
    step = F.pow(F.lit(2.0), exponent(v) - bits)
    return F.coalesce((F.floor(v / step + u) - u + 0.5) * step, F.lit(0.0))


def noise_round(cells: DataFrame, share: float, *by: str) -> DataFrame:
    """Steps are a share of the noise expected of a sample, here the rms of its channel and polarisation in the block."""
    keys = by or ("block_id", "pol", "ch")
    s = samples(masked(cells)).withColumn("noise", F.sqrt(F.avg(F.col("v") * F.col("v")).over(Window.partitionBy(*keys))))
    step = F.nullif(F.col("noise") * share, F.lit(0.0))
    return s.withColumn("k", F.floor(F.col("v") / step + 0.5).cast("long")).withColumn("v_hat", F.coalesce(F.col("k") * step, F.lit(0.0)))


def planes(values: np.ndarray) -> bytes:
    """32-bit integers with their bits transposed: all first bits, then all second bits, and so on."""
    b = (values.astype(np.int32).view(np.uint32)[None, :] >> np.arange(31, -1, -1, dtype=np.uint32)[:, None]) & 1
    return np.packbits(b.astype(np.uint8), axis=1).tobytes()


def noise_round_size(rounded: DataFrame, rows_per_unit: int = 65536) -> DataFrame:
    """raw_bytes (float32) and packed_bytes of rounded samples after bit transposition and LZ77."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            k = np.nan_to_num(np.array(batch.column(0).to_numpy(zero_copy_only=False), float)).astype(np.int64)
            parts = [k[i : i + rows_per_unit] for i in range(0, len(k), rows_per_unit)]
            yield pa.RecordBatch.from_arrays([pa.array([4 * len(k)], pa.int64()), pa.array([sum(len(zlib.compress(planes(p), 6)) for p in parts)], pa.int64())], names=["raw_bytes", "packed_bytes"])

    return rounded.select("k").mapInArrow(run, "raw_bytes bigint, packed_bytes bigint").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("packed_bytes").alias("packed_bytes"))


def backend_size(coded: DataFrame, bits: int, backend: str, rows_per_unit: int = 65536) -> DataFrame:
    """Bytes of symbols (column ``sym``) under ``rice``, ``deflate`` or ``bz2``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import bz2

        from ..functions import bits as bitlib

        for batch in batches:
            s = np.array(batch.column(0).to_numpy(zero_copy_only=False)).astype(np.int64)
            n = 0
            for i in range(0, len(s), rows_per_unit):
                part = s[i : i + rows_per_unit]
                data = bitlib.packed(part, bits)
                n += len(kernels.rice(part, bits)) if backend == "rice" else len(zlib.compress(data, 6)) if backend == "deflate" else len(bz2.compress(data))
            yield pa.RecordBatch.from_arrays([pa.array([len(s)], pa.int64()), pa.array([n], pa.int64())], names=["n", "bytes"])

    return coded.select("sym").mapInArrow(run, "n bigint, bytes bigint").agg(F.sum("n").alias("n"), F.sum("bytes").alias("bytes"))


def entropy(counts: DataFrame, n: str = "n") -> DataFrame:
    """Bits per symbol of a histogram."""
    t = counts.agg(F.sum(n).alias("total"), F.sum(F.col(n) * F.log2(n)).alias("s"))
    return t.select(F.col("total"), (F.log2("total") - F.col("s") / F.col("total")).alias("entropy_bits"))


def exponent_entropy(sampled: DataFrame) -> DataFrame:
    """Entropy of the exponent, and the share of 32 bits that is left if only sign-free exponent bits compress."""
    h = sampled.where("v <> 0").groupBy(exponent(F.col("v")).alias("e")).agg(F.count("*").alias("n"))
    return entropy(h).withColumn("lossless_share", (F.lit(24.0) + F.col("entropy_bits")) / 32)


def nonlinear_gain(results: DataFrame) -> DataFrame:
    """scaling, ratio: error of uniform levels over the best table's."""
    return results.groupBy("scaling").agg((F.max(F.when(F.col("quantiser") == "uniform", F.col("err"))) / F.min("err")).alias("ratio"), F.min_by("quantiser", "err").alias("best"))


def average_cells(cells: DataFrame, kt: int, kf: int) -> DataFrame:
    """Weighted means over ``kt`` blocks and ``kf`` channels; flagged and NaN samples don't count."""
    c = masked(cells).where("re is not null")
    mean = lambda x: F.sum(F.col(x) * F.col("weight")) / F.nullif(F.sum("weight"), F.lit(0.0))
    g = c.groupBy(F.floor(F.col("block_id") / kt).cast("long").alias("block_id"), "ant_a", "ant_b", F.floor(F.col("ch") / kf).cast("int").alias("ch"), "pol")
    out = g.agg(mean("re").alias("re"), mean("im").alias("im"), F.sum("weight").alias("weight"))
    row = (F.col("block_id") * 4096 + F.col("ant_a")) * 4096 + F.col("ant_b")
    return out.select("block_id", row.alias("row_id"), "ant_a", "ant_b", "ch", "pol", "re", "im", "weight", F.lit(False).alias("flagged"))


def length_class(longest: int) -> Column:
    """Blocks that may be averaged: 1 for the longest spacings, twice as many for each halving, at most ``longest``."""
    spacing = F.greatest(F.abs(F.col("ant_b") - F.col("ant_a")), F.lit(1))
    return F.least(F.pow(F.lit(2.0), F.floor(F.log2(F.lit(8.0) / spacing))).cast("int"), F.lit(longest))


def average_by_length(cells: DataFrame, longest: int = 4) -> DataFrame:
    """Longer means on short spacings, capped by the calibration interval (``longest`` blocks)."""
    k = F.greatest(length_class(longest), F.lit(1))
    c = masked(cells).where("re is not null and ant_a <> ant_b").withColumn("k", k)
    mean = lambda x: F.sum(F.col(x) * F.col("weight")) / F.nullif(F.sum("weight"), F.lit(0.0))
    return c.groupBy("k", F.floor(F.col("block_id") / F.col("k")).cast("long").alias("block_id"), "ant_a", "ant_b", "ch", "pol").agg(mean("re").alias("re"), mean("im").alias("im"), F.sum("weight").alias("weight"))
