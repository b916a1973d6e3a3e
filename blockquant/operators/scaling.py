"""Scale factors per block: row; row x channel; antenna x channel; and their variants.

Native forms add ``sigma`` to cells with window sums after one repartition by block, so no statistic is joined back.
The antenna x channel method iterates; its scale form is a kernel over one block's arrays (``kernels``), and
``antenna_channel_native`` is the closed-form twin with a fixed number of greedy rounds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..schema import CodecConfig


def masked(cells: DataFrame, autos: str = "keep") -> DataFrame:
    """Flagged, NaN and infinite samples become null, which every statistic skips; autos become zero if asked for."""
    bad = F.coalesce(F.col("flagged"), F.lit(False)) | F.isnan("re") | F.isnan("im") | (F.abs("re") == float("inf")) | (F.abs("im") == float("inf")) | F.col("re").isNull() | F.col("im").isNull()
    auto = (F.col("ant_a") == F.col("ant_b")) if autos == "zero" else F.lit(False)
    return cells.withColumns({c: F.when(bad, None).when(auto, 0.0).otherwise(F.col(c)) for c in ("re", "im")})


def peak() -> Column:
    return F.greatest(F.abs("re"), F.abs("im"))


def power() -> Column:
    return (F.col("re") * F.col("re") + F.col("im") * F.col("im")) / 2


def as_stored(c: Column) -> Column:
    """Factors are kept as 32-bit floats; samples are divided by what is kept."""
    return c.cast("float").cast("double")


def over(*keys: str):
    return Window.partitionBy("block_id", *keys)


def by_block(cells: DataFrame) -> DataFrame:
    """The one shuffle of a native fit."""
    return cells.repartition("block_id")


def scale_row(cells: DataFrame) -> DataFrame:
    """sigma = largest magnitude of the row, over all channels and polarisations."""
    return by_block(cells).withColumn("sigma", as_stored(F.coalesce(F.max(peak()).over(over("row_id")), F.lit(0.0))))


def scale_row_arrays(rows: DataFrame) -> DataFrame:
    """The same on rows layout: a projection, no shuffle."""
    usable = F.filter("vis", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return rows.withColumn("sigma", as_stored(F.coalesce(F.array_max(F.transform(usable, lambda x: F.abs(x))), F.lit(0.0))))


def scale_row_channel(cells: DataFrame, start: str = "rms") -> DataFrame:
    """Channels to unit rms, rows to their maxima, channels to their maxima; per polarisation. ``start='sigma'``: rows of an earlier fit."""
    c = by_block(cells)
    if start == "sigma":
        c = c.withColumn("f1", F.col("sigma"))
    else:
        c = c.withColumn("f1", F.sqrt(F.avg(power()).over(over("pol", "ch"))))
    c = c.withColumn("f_row", as_stored(F.max(peak() / F.nullif("f1", F.lit(0.0))).over(over("pol", "row_id"))))
    if start == "sigma":
        return c.withColumn("sigma", F.coalesce(F.col("f1") * F.col("f_row"), F.lit(0.0)))
    c = c.withColumn("m", F.max(peak() / F.nullif(F.col("f1") * F.col("f_row"), F.lit(0.0))).over(over("pol", "ch")))
    c = c.withColumn("f_ch", as_stored(F.col("f1") * F.col("m")))
    return c.withColumn("sigma", F.coalesce(F.col("f_ch") * F.col("f_row"), F.lit(0.0))).drop("f1", "m")


def scale_trimmed(scaled: DataFrame, k: float) -> DataFrame:
    """After a fit: k times the rms of the scaled block maps to the top level, and what exceeds it is clipped by the quantiser."""
    y = power() / F.nullif(F.col("sigma") * F.col("sigma"), F.lit(0.0))
    return scaled.withColumn("sigma", F.col("sigma") * F.coalesce(F.sqrt(F.avg(y).over(over("pol"))) * k, F.lit(1.0)))


def channel_rms(cells: DataFrame) -> DataFrame:
    """block_id, pol, ch, f over cross rows: the step that both channel methods begin with."""
    return masked(cells).where("ant_a <> ant_b").groupBy("block_id", "pol", "ch").agg(F.sqrt(F.avg(power())).alias("f"))


def baseline_variance(cells: DataFrame) -> DataFrame:
    """block_id, pol, ant_a, ant_b, var after channels have unit rms."""
    c = masked(cells).where("ant_a <> ant_b")
    c = by_block(c).withColumn("f", F.sqrt(F.avg(power()).over(over("pol", "ch"))))
    return c.groupBy("block_id", "pol", "ant_a", "ant_b").agg(F.avg(power() / F.nullif(F.col("f") * F.col("f"), F.lit(0.0))).alias("var"))


def antenna_loglsq(variance: DataFrame) -> DataFrame:
    """Closed form of log var_ab = x_a + x_b on complete blocks: block_id, pol, ant, f = sqrt of the antenna's factor.

    Blocks that miss a baseline come without rows; the kernel's iterative solver takes those.
    """
    v = variance.where("var > 0").withColumn("l", F.log("var"))
    both = v.select("block_id", "pol", F.explode(F.array("ant_a", "ant_b")).alias("ant"), "l")
    s = both.groupBy("block_id", "pol", "ant").agg(F.sum("l").alias("s"), F.count("*").alias("k"))
    w = Window.partitionBy("block_id", "pol")
    s = s.withColumn("n", F.count("*").over(w)).withColumn("total", F.sum("s").over(w)).withColumn("fewest", F.min("k").over(w))
    x = (F.col("s") - F.col("total") / (2 * (F.col("n") - 1))) / (F.col("n") - 2)
    return s.where("n >= 3 and fewest = n - 1").select("block_id", "pol", "ant", F.exp(x / 2).alias("f"))


def antenna_channel_native(cells: DataFrame, rounds: int = 2) -> DataFrame:
    """Antenna x channel scaling in functions of the engine: closed-form antennas, common rescale, ``rounds`` greedy steps.

    Antenna factors of a block travel as one small map per (block, pol), so cells are shuffled by block once.
    """
    c = masked(cells, "zero").where("ant_a <> ant_b")
    c = by_block(c).withColumn("f_ch", F.sqrt(F.avg(power()).over(over("pol", "ch"))))
    ants = antenna_loglsq(baseline_variance(cells)).groupBy("block_id", "pol").agg(F.map_from_entries(F.collect_list(F.struct("ant", "f"))).alias("f_ant"))
    c = c.join(ants, ["block_id", "pol"])
    c = c.withColumn("sigma", F.col("f_ch") * F.col("f_ant")[F.col("ant_a")] * F.col("f_ant")[F.col("ant_b")])
    c = c.withColumn("sigma", F.col("sigma") * F.max(peak() / F.nullif("sigma", F.lit(0.0))).over(over("pol"))).drop("f_ch", "f_ant")
    for _ in range(rounds):
        c = greedy_round(c)
    return c


def greedy_round(c: DataFrame) -> DataFrame:
    """Find, per block and polarisation, the channel or antenna whose maximisation adds most to the sum of magnitudes, and apply it."""
    y = peak() / F.nullif("sigma", F.lit(0.0))
    total = (F.abs("re") + F.abs("im")) / F.nullif("sigma", F.lit(0.0))
    each = c.select("block_id", "pol", F.explode(F.array(F.struct(F.lit("ch").alias("kind"), F.col("ch").alias("idx")), F.struct(F.lit("ant").alias("kind"), F.col("ant_a").alias("idx")), F.struct(F.lit("ant").alias("kind"), F.col("ant_b").alias("idx")))).alias("t"), y.alias("y"), total.alias("s"))
    gains = each.groupBy("block_id", "pol", "t").agg(F.max("y").alias("top"), F.sum("s").alias("s")).where("top > 0").withColumn("gain", (1 / F.col("top") - 1) * F.col("s"))
    best = gains.groupBy("block_id", "pol").agg(F.max_by(F.struct("t", "top"), F.struct("gain", F.col("t.kind"), -F.col("t.idx"))).alias("b"))
    c = c.join(best, ["block_id", "pol"], "left")
    hit = F.when(F.col("b.t.kind") == "ch", F.col("ch") == F.col("b.t.idx")).otherwise((F.col("ant_a") == F.col("b.t.idx")) | (F.col("ant_b") == F.col("b.t.idx")))
    return c.withColumn("sigma", F.when(F.coalesce(hit, F.lit(False)), F.col("sigma") * F.col("b.top")).otherwise(F.col("sigma"))).drop("b")


def fit_scales(cells: DataFrame, cfg: CodecConfig) -> DataFrame:
    """Cells with ``sigma``. Row and row x channel natively, the others by the block kernel."""
    if cfg.scaling in ("row", "row_channel"):
        c = masked(cells, "keep")
        out = scale_row(c) if cfg.scaling == "row" else scale_row_channel(c)
        out = out.drop("f_row", "f_ch")
    else:
        from .kernels import fit_by_kernel

        out = fit_by_kernel(cells, cfg)
    return scale_trimmed(out, cfg.clip_sigma) if cfg.clip_sigma else out


def factor_count(scaling: str, n_ch: int, n_ant: int, n_pol: int = 4) -> int:
    """Stored factors of a block with autos; the bound printed for row x channel, with all ordered pairs, is ``n_pol * (n_ch + n_ant**2)``."""
    rows = n_ant * (n_ant + 1) // 2
    return {"row": rows, "row_channel": n_pol * (n_ch + rows), "row_channel_af": n_pol * (n_ch + n_ant + rows), "antenna_channel": n_pol * (n_ch + n_ant)}[scaling]


def sample_count(n_ch: int, n_ant: int, n_pol: int = 4) -> int:
    return n_pol * 2 * n_ch * n_ant * (n_ant + 1) // 2
