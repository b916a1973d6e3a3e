"""Error by set, scaling, table and bit-rate, in samples and in images; and the stand-ins for the four test sets.

In images a set goes its whole way: compressed in every variant, then averaged, calibrated, subtracted or compressed again, and
imaged next to the uncompressed set. All variants go it side by side: a variant's blocks are numbered from a multiple of
``VARIANT`` on, so each step that works by block keeps them apart, and one job makes the images of all of them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.dither import uniform_array
from ..schema import CELLS, TABLES, CodecConfig, table_config
from ..sources import tables
from . import baselines, calibrate, imaging, kernels
from .quantise import expected_rms_many, samples
from .scaling import fit_scales

BITS = (2, 3, 4, 5, 6, 7, 8, 10, 12, 16)
#: Blocks that a variant has room for; a multiple of every averaging interval.
VARIANT = 1 << 24
#: Signal of each set in the parallel hands.
SIGNAL = {"A": 0.5, "B": 0.2, "C": 2.0}
NPIX = 16


def stand_in(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Cells of a set as they are when compressed. A is averaged over 4 blocks, B is at full resolution and flagged, C has its gains
    taken off before; all three carry signal. D is the volume set."""
    if name == "D":
        return tables.vis_lineitem(spark, sf_dir)
    cells = tables.inject_signal(tables.vis_embeddings(spark, sf_dir), SIGNAL[name])
    if name == "A":
        return baselines.average_cells(cells, 4, 1)
    return calibrate.flag_outliers(cells) if name == "B" else without_gains(cells)


def without_gains(cells: DataFrame, bandpass: bool = True, n_ant: int = 8) -> DataFrame:
    """Known gains, as transferred solutions give them, taken off."""
    g = tables.gain(F.col("ant_a"), n_ant) * tables.gain(F.col("ant_b"), n_ant)
    g = g * tables.bandpass(F.col("ch")) if bandpass else g
    return cells.withColumns({"re": F.col("re") / g, "im": F.col("im") / g})


def configs_of(scaling: str, labels: tuple[str, ...], bits: tuple[int, ...], **more: object) -> list[CodecConfig]:
    return [table_config(x, b, scaling=scaling, **more) for x in labels for b in bits]


def variants(scaled: DataFrame, configs: list[CodecConfig], again: bool = False) -> DataFrame:
    """Cells of variant 0, as they come, and of one variant for each configuration, coded and decoded. ``scaled``: cells with sigma.
    With ``again`` the cells are variants already, and each is coded once more by its own configuration."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 16384):
                t = batch.slice(at, 16384)
                name = lambda c: t.column(t.schema.get_field_index(c))  # noqa: B023, E731
                ints = {c: name(c).to_numpy().astype(np.int64) for c in ("block_id", "row_id", "ant_a", "ant_b", "ch", "pol")}
                v = np.column_stack([name(c).to_numpy(zero_copy_only=False).astype(float) for c in ("re", "im")])
                v[~np.isfinite(v).all(1) | name("flagged").fill_null(False).to_numpy(zero_copy_only=False)] = np.nan
                sigma = np.nan_to_num(name("sigma").to_numpy(zero_copy_only=False).astype(float))
                base = ((ints["row_id"] * kernels.N_CH_LIMIT + ints["ch"]) * kernels.N_POL_LIMIT + ints["pol"]) * 2
                ordinal = np.column_stack([base, base + 1])
                own = ints["block_id"] // VARIANT

                def cells(block: np.ndarray, values: np.ndarray, where: np.ndarray) -> pa.RecordBatch:
                    made = {"block_id": pa.array(block), "re": pa.array(values[:, 0]), "im": pa.array(values[:, 1]), "flagged": pa.array(np.isnan(values[:, 0]))}
                    mask = pa.array(where)
                    return pa.RecordBatch.from_arrays([made[c] if c in made else name(c).filter(mask) for c in CELLS.fieldNames()], names=CELLS.fieldNames())  # noqa: B023

                every = np.ones(t.num_rows, bool)
                for i, cfg in [(0, None), *enumerate(configs, 1)]:
                    where = own == i if again else every
                    if not where.any():
                        continue
                    values = v[where]
                    if cfg:
                        s2, table = np.repeat(sigma[where, None], 2, axis=1), kernels.table_of(cfg)
                        values = kernels.dequantised(kernels.quantised(values, s2, table, uniform_array(ordinal[where], cfg.seed), cfg.bits), s2, table)
                    yield cells(ints["block_id"][where] + (0 if again else i * VARIANT), values, where)

    return scaled.select(*CELLS.fieldNames(), "sigma").mapInArrow(run, CELLS)


def after(cells: DataFrame, name: str, configs: list[CodecConfig]) -> DataFrame:
    """What happens to a set after compression. A: calibration on its signal, which is then subtracted. B: averaging over 16 blocks
    and 8 channels, then calibration. C: nothing, it was calibrated before. D: known solutions, then compression again."""
    if name == "C":
        return cells
    if name == "D":
        solved = without_gains(cells, False, 10)
        return variants(fit_scales(solved, configs[0]), [c.but(seed=c.seed + 1) for c in configs], again=True)
    if name == "B":
        cells = baselines.average_cells(cells, 16, 8).withColumn("block_id", F.col("block_id") * 16)  # numbers of variants stay what they were
    out = calibrate.apply_gains(cells, calibrate.solve_gains(cells.where("pol in (0, 3)"), SIGNAL[name]))
    return calibrate.subtract_model(out, SIGNAL[name]) if name == "A" else out


def processed(cells: DataFrame, name: str, configs: list[CodecConfig]) -> DataFrame:
    """Stokes products of a set's whole way, in all variants: block_id, variant and those of ``calibrate.stokes``."""
    scaled = fit_scales(cells, configs[0])
    s = calibrate.stokes(after(variants(scaled, configs), name, configs)).where("ant_a <> ant_b")
    return s.withColumn("variant", F.floor(F.col("block_id") / VARIANT).cast("int"))


def image_sweep(sets: dict[str, DataFrame], scaling: str, labels: tuple[str, ...] = tuple(TABLES), bits: tuple[int, ...] = BITS, clean: bool = False) -> DataFrame:
    """set, scaling, quantiser, bits, diff_rms, v_rms and, with ``clean``, noise and noise_ref: rms of the difference to the image without
    compression, system noise (rms of the Stokes V image), and the cleaned image's noise with and without compression."""
    spark = next(iter(sets.values())).sparkSession
    configs = configs_of(scaling, labels, bits)
    out = None
    for name, cells in sets.items():
        s = processed(cells, name, configs)
        images = imaging.dirty_image(imaging.uv_grid(s, "i_re", "i_im", by=("variant",)), NPIX, by=("variant",))
        plain = images.where("variant = 0").select("l", "m", F.col("value").alias("plain"))
        diff = images.where("variant > 0").join(F.broadcast(plain), ["l", "m"])  # one image's pixels
        one = diff.groupBy("variant").agg(F.sqrt(F.avg((F.col("value") - F.col("plain")) ** 2)).alias("diff_rms"))
        v = imaging.dirty_image(imaging.uv_grid(s.where("variant = 0"), "v_re", "v_im"), NPIX).agg(F.sqrt(F.avg(F.col("value") ** 2)).alias("v_rms"))
        one = one.crossJoin(F.broadcast(v))  # one row
        if clean:
            noise = imaging.cleaned_noise(images, ("variant",), NPIX)
            ref = noise.where("variant = 0").select(F.col("noise").alias("noise_ref"))
            one = one.join(noise, "variant").crossJoin(F.broadcast(ref))  # one row
        one = one.withColumn("set", F.lit(name))
        out = one if out is None else out.unionByName(one)
    named = spark.createDataFrame([(i, scaling, c.label, c.bits) for i, c in enumerate(configs, 1)], "variant int, scaling string, quantiser string, bits int")
    return out.join(F.broadcast(named), "variant").select("set", "scaling", "quantiser", "bits", *(c for c in out.columns if c not in ("set", "variant")))


def difference_images(cells: DataFrame, name: str, cfg: CodecConfig, *by: str) -> DataFrame:
    """[by,] l, m, value, plain, diff: image with and without compression and their difference."""
    s = processed(cells, name, [cfg]).withColumn("block", F.col("block_id") % VARIANT)
    images = imaging.dirty_image(imaging.uv_grid(s, "i_re", "i_im", by=("variant", *by)), NPIX, by=("variant", *by))
    plain = images.where("variant = 0").select(*by, "l", "m", F.col("value").alias("plain"))
    both = images.where("variant = 1").join(plain, [*by, "l", "m"])
    return both.select(*by, "l", "m", "value", "plain", (F.col("value") - F.col("plain")).alias("diff"))


def minimum_bits(results: DataFrame) -> DataFrame:
    """set, rule, bits: the fewest bits for which the difference is below a tenth or a hundredth of the system noise, or the cleaned noise
    within a tenth or a hundredth of what it is without compression. ``results``: of a clean image sweep."""
    change = F.abs(F.col("noise") / F.col("noise_ref") - 1)
    rules = {"diff<10%": F.col("diff_rms") < 0.1 * F.col("v_rms"), "diff<1%": F.col("diff_rms") < 0.01 * F.col("v_rms"), "noise<10%": change < 0.1, "noise<1%": change < 0.01}
    g = results.groupBy("set").agg(*(F.min(F.when(c, F.col("bits"))).alias(k) for k, c in rules.items()))
    return g.unpivot(["set"], [F.col(f"`{k}`") for k in rules], "rule", "bits")


def sweep(sets: dict[str, DataFrame], scaling: str, bits: tuple[int, ...] = BITS) -> DataFrame:
    """set, scaling, quantiser, bits, rms: expected errors of all tables and bit-rates in one pass over each set."""
    out = None
    for name, cells in sets.items():
        s = samples(fit_scales(cells, CodecConfig(scaling=scaling))).where("ant_a <> ant_b and v is not null and not isnan(v)")
        one = expected_rms_many(s, bits).select(F.lit(name).alias("set"), F.lit(scaling).alias("scaling"), "quantiser", "bits", "rms")
        out = one if out is None else out.unionAll(one)
    return out


def references(sets: dict[str, DataFrame]) -> DataFrame:
    """set, ref: noise of the Stokes V product per sample, what a difference is held against."""
    out = None
    for name, cells in sets.items():
        v = calibrate.stokes(cells).where("ant_a <> ant_b").agg(F.sqrt(F.avg((F.col("v_re") ** 2 + F.col("v_im") ** 2) / 2)).alias("ref"))
        one = v.select(F.lit(name).alias("set"), "ref")
        out = one if out is None else out.unionAll(one)
    return out
