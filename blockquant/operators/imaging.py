"""Images: grid first, so that the Fourier sum runs over grid cells and a bounded number of pixels, not over samples."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Antenna a stands at (POSITION_X * a mod 97, POSITION_Y * a mod 89): a fixed layout without regular spacings.
POSITION_X, POSITION_Y = 29, 53


def uv(spacing: float = 10.0) -> tuple[Column, Column]:
    """Spacings of a row's baseline in wavelengths over ``spacing``."""
    x = lambda ant: (F.col(ant) * POSITION_X) % 97
    y = lambda ant: (F.col(ant) * POSITION_Y) % 89
    return (x("ant_b") - x("ant_a")) / spacing, (y("ant_b") - y("ant_a")) / spacing


def uv_grid(values: DataFrame, re: str = "re", im: str = "im", spacing: float = 10.0, weighting: str = "uniform", by: tuple[str, ...] = ()) -> DataFrame:
    """gu, gv, re, im, w: mean visibility of each grid cell; weight 1 per cell (uniform) or its count (natural). One shuffle of partial
    sums. ``by``: columns that tell apart images made side by side."""
    u, v = uv(spacing)
    g = values.where(F.col(re).isNotNull() & ~F.isnan(re)).groupBy(*by, F.floor(u + 0.5).cast("int").alias("gu"), F.floor(v + 0.5).cast("int").alias("gv"))
    return g.agg(F.avg(re).alias("re"), F.avg(im).alias("im"), (F.lit(1.0) if weighting == "uniform" else F.count("*").cast("double")).alias("w"))


def dirty_image(grid: DataFrame, npix: int = 16, by: tuple[str, ...] = ()) -> DataFrame:
    """l, m, value, and with ``by`` the beam too: sums of w (re cos - im sin), and of w cos, over grid cells. Pixels, at most 65,536, are
    broadcast; grid cells stay where they are."""
    if npix > 256:
        raise ValueError("an image holds at most 256 x 256 pixels: tile larger ones")
    half = npix // 2
    pixels = grid.sparkSession.range(npix * npix).select((F.floor(F.col("id") / npix) - half).cast("int").alias("l"), (F.col("id") % npix - half).cast("int").alias("m"))
    j = grid.crossJoin(F.broadcast(pixels))
    phase = (F.col("gu") * F.col("l") + F.col("gv") * F.col("m")) * (2 * math.pi / npix)
    mean = lambda x: F.sum(F.col("w") * x) / F.sum("w")
    more = [mean(F.cos(phase)).alias("beam")] if by else []
    return j.groupBy(*by, "l", "m").agg(mean(F.col("re") * F.cos(phase) - F.col("im") * F.sin(phase)).alias("value"), *more)


def cleaned_noise(images: DataFrame, by: tuple[str, ...], npix: int = 16, gain: float = 0.1, iterations: int = 200) -> DataFrame:
    """``by`` and noise: rms of each image's cleaned residual in a corner without sources. A group is one image's pixels."""

    def run(t: pa.Table) -> pa.Table:
        half = npix // 2
        image, psf = np.zeros((npix, npix)), np.zeros((npix, npix))
        at = (t["l"].to_numpy() + half, t["m"].to_numpy() + half)
        image[at], psf[at] = t["value"].to_numpy(), t["beam"].to_numpy()
        residual, _ = clean(image, psf, gain, iterations)
        box = residual[: npix // 4, : npix // 4]
        return pa.table({**{c: t[c].slice(0, 1) for c in by}, "noise": [float((box**2).mean() ** 0.5)]})

    schema = T.StructType([*(images.schema[c] for c in by), T.StructField("noise", T.DoubleType())])
    return images.select(*by, "l", "m", "value", "beam").groupBy(*by).applyInArrow(run, schema)


def beam(grid: DataFrame, npix: int = 16) -> DataFrame:
    return dirty_image(grid.withColumns({"re": F.lit(1.0), "im": F.lit(0.0)}), npix)


def image_array(image: DataFrame, npix: int) -> np.ndarray:
    """The pixels on the driver: npix x npix of them."""
    out, half = np.zeros((npix, npix)), npix // 2
    for r in image.collect():
        out[r["l"] + half, r["m"] + half] = r["value"]
    return out


def clean(image: np.ndarray, psf: np.ndarray, gain: float = 0.1, iterations: int = 200, stop: float = 0.0) -> tuple[np.ndarray, list[tuple[int, int, float]]]:
    """Take a share of the beam off at the brightest pixel, again and again: residual and components."""
    n = len(image)
    half = n // 2
    residual, parts = image.copy(), []
    for _ in range(iterations):
        i, j = np.unravel_index(np.abs(residual).argmax(), residual.shape)
        flux = gain * residual[i, j]
        if abs(residual[i, j]) <= stop:
            break
        residual -= flux * np.roll(np.roll(psf, i - half, 0), j - half, 1)
        parts.append((int(i) - half, int(j) - half, float(flux)))
    return residual, parts


def box_rms(image: DataFrame, l0: int, l1: int, m0: int, m1: int) -> DataFrame:
    return image.where(F.col("l").between(l0, l1) & F.col("m").between(m0, m1)).agg(F.sqrt(F.avg(F.col("value") * F.col("value"))).alias("rms"))


def difference(image: DataFrame, other: DataFrame) -> DataFrame:
    return image.join(other.select("l", "m", F.col("value").alias("other")), ["l", "m"]).select("l", "m", (F.col("value") - F.col("other")).alias("value"))
