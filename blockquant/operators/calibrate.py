"""Processing around the codec: gains, sources, flags, phases, Stokes products."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .scaling import masked


def gain_round(cells: DataFrame, gains: DataFrame, model: float = 1.0, interval: int = 1) -> DataFrame:
    """One round of alternating least squares for V_ab = g_a conj(g_b) M with a constant model: block_id, ant, re, im.

    ``gains``: block_id (of the interval), ant, re, im of the round before. Each baseline counts for both of its antennas.
    """
    c = masked(cells).where("ant_a <> ant_b and re is not null").withColumn("t", F.floor(F.col("block_id") / interval).cast("long"))
    two = c.select("t", F.explode(F.array(F.struct(F.col("ant_a").alias("ant"), F.col("ant_b").alias("other"), F.col("re"), F.col("im")), F.struct(F.col("ant_b").alias("ant"), F.col("ant_a").alias("other"), F.col("re"), (-F.col("im")).alias("im")))).alias("s")).select("t", "s.*")
    two = two.groupBy("t", "ant", "other").agg(F.sum("re").alias("re"), F.sum("im").alias("im"), F.count("*").alias("n"))
    o = gains.select(F.col("block_id").alias("t"), F.col("ant").alias("other"), F.col("re").alias("gr"), F.col("im").alias("gi"))
    j = two.join(o, ["t", "other"])
    # V_ab g_b / |g_b|^2, summed: with conj(g_b) in the model the numerator is V times g_b.
    s = j.groupBy("t", "ant").agg(F.sum((F.col("re") * F.col("gr") - F.col("im") * F.col("gi")) * model).alias("nr"), F.sum((F.col("re") * F.col("gi") + F.col("im") * F.col("gr")) * model).alias("ni"), F.sum(F.col("n") * (F.col("gr") * F.col("gr") + F.col("gi") * F.col("gi")) * model * model).alias("d"))
    d = F.nullif("d", F.lit(0.0))
    return s.select(F.col("t").alias("block_id"), "ant", (F.col("nr") / d).alias("re"), (F.col("ni") / d).alias("im"))


def unit_gains(cells: DataFrame, interval: int = 1) -> DataFrame:
    ants = cells.select(F.floor(F.col("block_id") / interval).cast("long").alias("block_id"), F.explode(F.array("ant_a", "ant_b")).alias("ant")).distinct()
    return ants.select("block_id", "ant", F.lit(1.0).alias("re"), F.lit(0.0).alias("im"))


def gains_of(var: np.ndarray, weight: np.ndarray, iterations: int) -> np.ndarray:
    """Complex gains of a matrix of mean visibilities over the model; damped by averaging every second round."""
    n = len(var)
    g = np.ones(n, complex) * np.sqrt(np.abs(var[weight > 0]).mean() if (weight > 0).any() else 1)
    for k in range(iterations):
        d = weight @ np.abs(g) ** 2
        new = np.divide((weight * var) @ g, d, out=g.copy(), where=d > 0)
        g = (g + new) / 2 if k % 2 else new
    return g * np.exp(-1j * np.angle(g[0]))


def solve_gains(cells: DataFrame, model: float = 1.0, iterations: int = 40, interval: int = 1) -> DataFrame:
    """block_id (interval), ant, re, im. Sums per baseline come first, so the solver's groups have N^2 rows, whatever the number of samples."""
    c = masked(cells).where("ant_a <> ant_b and re is not null")
    sums = c.groupBy(F.floor(F.col("block_id") / interval).cast("long").alias("block_id"), "ant_a", "ant_b").agg(F.avg("re").alias("re"), F.avg("im").alias("im"), F.count("*").alias("n"))

    def run(t: pa.Table) -> pa.Table:
        a, b = t["ant_a"].to_numpy(), t["ant_b"].to_numpy()
        ants = np.unique(np.concatenate([a, b]))
        ia, ib = np.searchsorted(ants, a), np.searchsorted(ants, b)
        v, w = np.zeros((len(ants),) * 2, complex), np.zeros((len(ants),) * 2)
        v[ia, ib] = (t["re"].to_numpy() + 1j * t["im"].to_numpy()) / model
        v[ib, ia] = np.conj(v[ia, ib])
        w[ia, ib] = w[ib, ia] = t["n"].to_numpy()
        g = gains_of(v, w, iterations)
        return pa.table({"block_id": pa.array(np.full(len(ants), t["block_id"][0].as_py()), pa.int64()), "ant": pa.array(ants, pa.int32()), "re": pa.array(g.real), "im": pa.array(g.imag)})

    return sums.groupBy("block_id").applyInArrow(run, "block_id bigint, ant int, re double, im double")


def apply_gains(cells: DataFrame, gains: DataFrame, interval: int = 1) -> DataFrame:
    """V_ab / (g_a conj(g_b)). Gains are a few numbers a block; the planner sends them to the cells or shuffles, by size."""
    g = lambda side: gains.select(F.col("block_id").alias("t"), F.col("ant").alias(f"ant_{side}"), F.col("re").alias(f"{side}r"), F.col("im").alias(f"{side}i"))
    c = cells.withColumn("t", F.floor(F.col("block_id") / interval).cast("long")).join(g("a"), ["t", "ant_a"]).join(g("b"), ["t", "ant_b"])
    pr, pi = F.col("ar") * F.col("br") + F.col("ai") * F.col("bi"), F.col("ai") * F.col("br") - F.col("ar") * F.col("bi")
    n = F.nullif(pr * pr + pi * pi, F.lit(0.0))
    out = c.withColumns({"re2": (F.col("re") * pr + F.col("im") * pi) / n, "im2": (F.col("im") * pr - F.col("re") * pi) / n})
    return out.drop("re", "im", "t", "ar", "ai", "br", "bi").withColumnsRenamed({"re2": "re", "im2": "im"}).select(*cells.columns)


def subtract_model(cells: DataFrame, amp: Column | float, pols: tuple[int, ...] = (0, 3)) -> DataFrame:
    """Take a source at the phase centre off the parallel hands."""
    a = amp if isinstance(amp, Column) else F.lit(amp)
    return cells.withColumn("re", F.when(F.col("pol").isin(*pols), F.col("re") - a).otherwise(F.col("re")))


def transfer_gains(cells: DataFrame, gains: DataFrame) -> DataFrame:
    """As-of: for every block and antenna of ``cells`` the latest solution at or before it. One union, one window; no range join."""
    want = cells.select("block_id", F.explode(F.array("ant_a", "ant_b")).alias("ant")).distinct().select("block_id", "ant", F.lit(None).cast("double").alias("re"), F.lit(None).cast("double").alias("im"), F.lit(1).alias("asks"))
    have = gains.select("block_id", "ant", "re", "im", F.lit(0).alias("asks"))
    w = Window.partitionBy("ant").orderBy("block_id", "asks").rowsBetween(Window.unboundedPreceding, 0)
    both = have.unionByName(want).withColumns({c: F.last(c, True).over(w) for c in ("re", "im")})
    return both.where("asks = 1").select("block_id", "ant", "re", "im")


def flag_outliers(cells: DataFrame, k: float = 5.0, exact: bool = False) -> DataFrame:
    """Flag samples further than k robust sigmas from their channel's median magnitude (1.4826 times the median deviation)."""
    med = (lambda c: F.expr(f"percentile({c}, 0.5)")) if exact else (lambda c: F.percentile_approx(c, 0.5, 10000))
    c = masked(cells).withColumn("mag", F.sqrt(F.col("re") * F.col("re") + F.col("im") * F.col("im")))
    keys = ["pol", "ch"]
    m = c.groupBy(*keys).agg(med("mag").alias("med"))
    d = c.join(m, keys).withColumn("dev", F.abs(F.col("mag") - F.col("med")))
    s = d.groupBy(*keys).agg(F.first("med").alias("med"), (med("dev") * 1.4826).alias("sig"))
    out = c.join(s, keys)
    return out.withColumn("flagged", F.coalesce(F.abs(F.col("mag") - F.col("med")) > k * F.col("sig"), F.lit(True))).select(*cells.columns)


def rotate_phase(cells: DataFrame, l: float, m: float, spacing: float = 10.0) -> DataFrame:  # noqa: E741
    """Multiply by exp(2 pi i (u l + v m)): the direction (l, m) becomes the centre. u, v as in ``imaging.uv``."""
    from .imaging import uv

    u, v = uv(spacing)
    phase = (u * l + v * m) * (2 * np.pi)
    c, s = F.cos(phase), F.sin(phase)
    return cells.withColumns({"re": F.col("re") * c - F.col("im") * s, "im": F.col("re") * s + F.col("im") * c})


def stokes(cells: DataFrame) -> DataFrame:
    """I = (XX + YY) / 2 and V = (XY - YX) / 2i per row and channel: i_re, i_im, v_re, v_im."""
    p = lambda k, c: F.max(F.when(F.col("pol") == k, F.col(c)))
    g = masked(cells).groupBy("block_id", "row_id", "ant_a", "ant_b", "ch").agg(*(p(k, c).alias(f"{c}{k}") for k in range(4) for c in ("re", "im")))
    half = lambda e: e / 2
    return g.select("block_id", "row_id", "ant_a", "ant_b", "ch", half(F.col("re0") + F.col("re3")).alias("i_re"), half(F.col("im0") + F.col("im3")).alias("i_im"), half(F.col("im1") - F.col("im2")).alias("v_re"), half(F.col("re2") - F.col("re1")).alias("v_im"))


def dynamic_spectrum(cells: DataFrame, pol: int = 0) -> DataFrame:
    """block_id, ch, amplitude: mean magnitude over baselines."""
    return masked(cells).where(F.col("pol") == pol).groupBy("block_id", "ch").agg(F.avg(F.sqrt(F.col("re") * F.col("re") + F.col("im") * F.col("im"))).alias("amplitude"))
