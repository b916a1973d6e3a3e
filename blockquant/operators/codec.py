"""Compress and decompress: one shuffle by block on the way in, none on the way out."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import CELLS, PACKED, CodecConfig
from . import kernels

RESTORED = "block_id bigint, row_id bigint, ant_a int, ant_b int, ch int, pol int, re double, im double"


def compress(cells: DataFrame, cfg: CodecConfig) -> DataFrame:
    """Cells to packed rows, one per block, polarisation and sub-band; flagged samples become the NaN symbol. Polarisations and
    sub-bands are groups of their own, but for row scaling, whose factor spans the polarisations."""
    band = F.floor(F.col("ch") / cfg.sub_band)
    keys = [F.col("block_id"), band] if cfg.scaling == "row" else [F.col("block_id"), F.col("pol"), band]
    return cells.select(*CELLS.fieldNames()).groupBy(*keys).applyInArrow(lambda t: kernels.compress_block(t, cfg), PACKED)


def compress_visibilities(rows: DataFrame, cfg: CodecConfig, n_ch: int, n_pol: int = 4) -> DataFrame:
    """The same from rows layout (block_id, row_id, ant_a, ant_b, vis as [ch][pol][re, im], flag as [ch][pol] if there): arrays
    move, not cells. Rows wider than a sub-band are cut before they move."""
    flag = ["flag"] if "flag" in rows.columns else []
    source = rows.select("block_id", "row_id", "ant_a", "ant_b", "vis", *flag)
    if n_ch > cfg.sub_band:
        part = lambda c, wide: F.slice(c, F.col("first_ch") * wide + 1, F.lit(cfg.sub_band * wide))
        source = source.withColumn("first_ch", F.explode(F.sequence(F.lit(0), F.lit(n_ch - 1), F.lit(cfg.sub_band)))).withColumn("vis", part("vis", 2 * n_pol))
        source = source.withColumn("flag", part("flag", n_pol)) if flag else source
        return source.groupBy("block_id", "first_ch").applyInArrow(lambda t: kernels.compress_rows_block(t, cfg, n_pol), PACKED)
    return source.groupBy("block_id").applyInArrow(lambda t: kernels.compress_rows_block(t, cfg, n_pol), PACKED)


def decompress(packed: DataFrame) -> DataFrame:
    """Packed rows to cells, each task on its own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                c = kernels.decompress_row(r)
                n = len(c["re"])
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(n, r["block_id"]), pa.int64()), pa.array(c["row_id"], pa.int64()), pa.array(c["ant_a"], pa.int32()), pa.array(c["ant_b"], pa.int32()), pa.array(c["ch"], pa.int32()), pa.array(np.full(n, r["pol"]), pa.int32()), pa.array(c["re"], pa.float64()), pa.array(c["im"], pa.float64())],
                    names=["block_id", "row_id", "ant_a", "ant_b", "ch", "pol", "re", "im"],
                )

    return packed.select(*PACKED.fieldNames()).mapInArrow(run, RESTORED)


def as_cells(restored: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """Restored cells with weight and flag columns again; NaN counts as flagged. ``weights``: as ``weights.unpack`` gives them; a cell
    without one weighs 1."""
    if weights is not None:
        restored = restored.join(weights.select("block_id", "row_id", "ch", "weight"), ["block_id", "row_id", "ch"], "left")
    weight = F.lit(1.0) if weights is None else F.coalesce("weight", F.lit(1.0))
    return restored.withColumns({"weight": weight, "flagged": F.isnan("re") | F.isnan("im")}).select(*CELLS.fieldNames())


def factors(packed: DataFrame) -> DataFrame:
    """block_id, pol, kind, idx, f of what is stored."""
    kinds = {"channel": ("channels", "ch_factors"), "antenna": ("ant_ids", "ant_factors"), "row": ("row_ids", "row_factors")}
    none = F.array().cast("array<struct<kind:string,idx:bigint,f:float>>")

    def entry(kind: str):
        return lambda z: F.struct(F.lit(kind).alias("kind"), z["i"].alias("idx"), z["f"].alias("f"))

    entries = [F.when(F.col(f).isNotNull(), F.transform(F.arrays_zip(F.col(i).cast("array<bigint>").alias("i"), F.col(f).alias("f")), entry(kind))).otherwise(none) for kind, (i, f) in kinds.items()]
    return packed.select("block_id", "pol", F.explode(F.concat(*entries)).alias("e")).select("block_id", "pol", "e.kind", "e.idx", "e.f")


def compress_twice(cells: DataFrame, cfg: CodecConfig, between) -> DataFrame:
    """Compress, decompress, apply ``between`` (calibration, for one) and compress again: the cells that come out."""
    once = as_cells(decompress(compress(cells, cfg)))
    return as_cells(decompress(compress(between(once), cfg)))


def compress_rows(rows: DataFrame, bits: int, seed: int = 0, dither: bool = True) -> DataFrame:
    """Row scaling with uniform levels on rows layout: a projection and an Arrow packing step, no shuffle."""
    from ..functions import bits as bitlib
    from ..functions.dither import uniform_array
    from ..functions.levels import levels
    from .scaling import scale_row_arrays

    table = levels("uniform", bits)

    @F.pandas_udf("binary")
    def payload(row_id, vis, sigma):  # noqa: ANN001, ANN202
        import pandas as pd

        out = []
        for i, v, s in zip(row_id, vis, sigma, strict=True):
            v = np.array(v, float)
            u = uniform_array(int(i) * kernels.N_CH_LIMIT * 8 + np.arange(len(v)), seed) if dither else np.full(len(v), 0.5)
            out.append(bitlib.packed(kernels.quantised(v, np.full(len(v), s), table, u, bits), bits))
        return pd.Series(out)

    return scale_row_arrays(rows).select("block_id", "row_id", "ant_a", "ant_b", F.size("vis").alias("n"), "sigma", F.lit(bits).alias("bits"), payload("row_id", "vis", "sigma").alias("payload"))


def mask_flags(cells: DataFrame) -> DataFrame:
    """Flags as NaN, a step of its own."""
    bad = F.coalesce(F.col("flagged"), F.lit(False))
    return cells.withColumns({c: F.when(bad, float("nan")).otherwise(F.col(c)) for c in ("re", "im")})


def compress_column(df: DataFrame, column: str, block: str, order: str, cfg: CodecConfig | None = None) -> DataFrame:
    """Any numeric column as packed blocks: ``block`` (long) groups values, ``order`` (long, distinct in a block) tells them apart.

    Rows of a block are laid as rows of one channel, so row x channel scaling gives each value its own factor range; the
    default scales the whole block by its largest magnitude, as channel scaling of one polarisation.
    """
    cfg = cfg or CodecConfig(scaling="antenna_channel", quantiser="uniform", trunc=None, max_steps=0, autos="keep")
    v = F.col(f"`{column}`").cast("double")
    cells = df.select(F.col(f"`{block}`").cast("long").alias("block_id"), F.col(f"`{order}`").cast("long").alias("row_id"), F.lit(0).alias("ant_a"), F.lit(1).alias("ant_b"), F.lit(0).alias("ch"), F.lit(0).alias("pol"), v.alias("re"), F.when(v.isNotNull(), 0.0).alias("im"), F.lit(1.0).alias("weight"), v.isNull().alias("flagged"))
    return compress(cells, cfg)


def decompress_column(packed: DataFrame, column: str, block: str, order: str) -> DataFrame:
    """block, order and the column again; missing values as null."""
    c = decompress(packed)
    return c.select(F.col("block_id").alias(block), F.col("row_id").alias(order), F.nullif("re", F.lit(float("nan"))).alias(column))
