"""Accuracy, cost and volume measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..schema import CodecConfig
from .scaling import factor_count, sample_count


def rms(c: Column) -> Column:
    return F.sqrt(F.avg(c * c))


def diff_rms(image: DataFrame, other: DataFrame) -> DataFrame:
    from .imaging import difference

    return difference(image, other).agg(rms(F.col("value")).alias("rms"))


def noise_change(before: float, after: float) -> float:
    return after / before - 1


def cell_error(coded: DataFrame, *by: str) -> DataFrame:
    """n, rmse, bias, snr of v_hat against v."""
    e = F.col("v_hat") - F.col("v")
    g = coded.where("v is not null and not isnan(v_hat)").groupBy(*by)
    return g.agg(F.count("*").alias("n"), rms(e).alias("rmse"), F.avg(e).alias("bias"), (rms(F.col("v")) / F.nullif(rms(e), F.lit(0.0))).alias("snr"))


def balanced_mean(results: DataFrame, *by: str, value: str = "err") -> DataFrame:
    """Mean over sets after each set is brought to the overall mean; ``ci2`` is two standard errors of it."""
    results = results.crossJoin(F.broadcast(results.groupBy("set").agg(F.avg(value).alias("m")).agg(F.avg("m").alias("overall"))))  # one row
    x = F.col(value) / F.avg(value).over(Window.partitionBy("set")) * F.col("overall")
    return results.withColumn("x", x).groupBy(*by).agg(F.avg("x").alias("avg"), (2 * F.stddev_samp("x") / F.sqrt(F.count("*"))).alias("ci2"))


def ci2(results: DataFrame, *by: str, value: str = "err") -> DataFrame:
    """Plain mean with its interval of two standard errors."""
    return results.groupBy(*by).agg(F.avg(value).alias("avg"), (2 * F.stddev_samp(value) / F.sqrt(F.count("*"))).alias("ci2"))


def bit_ratio(results: DataFrame, *by: str, low: int = 8, high: int = 16) -> DataFrame:
    """Error at ``low`` bits over that at ``high`` bits; equal steps give (2^high - 2) / (2^low - 2)."""
    pick = lambda b: F.max(F.when(F.col("bits") == b, F.col("rms")))
    return results.groupBy(*by).agg((pick(low) / pick(high)).alias("ratio"))


def bit_slope(results: DataFrame, *by: str) -> DataFrame:
    """Error at b bits over that at the next bit-rate measured."""
    w = Window.partitionBy(*by).orderBy("bits") if by else Window.orderBy("bits")
    nxt = results.withColumn("next_bits", F.lead("bits").over(w)).withColumn("step", F.col("rms") / F.lead("rms").over(w))
    return nxt.where("next_bits is not null")


def min_bits(results: DataFrame, reference: DataFrame, limits: dict[str, float]) -> DataFrame:
    """set, rule, bits: the fewest bits whose error stays under a share of the set's reference."""
    rules = F.explode(F.array(*(F.struct(F.lit(k).alias("rule"), F.lit(v).alias("limit")) for k, v in limits.items()))).alias("r")
    j = results.join(F.broadcast(reference), "set").select("*", rules)
    return j.where(F.col("rms") < F.col("r.limit") * F.col("ref")).groupBy("set", F.col("r.rule").alias("rule")).agg(F.min("bits").alias("bits"))


def ratio(cfg: CodecConfig, n_ch: int | None = None, n_ant: int | None = None, n_pol: int = 4) -> float:
    """32 / bits; with the block's shape, factors count too."""
    if n_ch is None:
        return 32 / cfg.bits
    n = sample_count(n_ch, n_ant, n_pol)
    return 32 * n / (cfg.bits * n + 32 * factor_count(cfg.scaling, n_ch, n_ant, n_pol))


def metadata_share(cfg: CodecConfig, n_ch: int, n_ant: int, n_pol: int = 4) -> float:
    """Factor bytes over payload bytes."""
    return 4 * factor_count(cfg.scaling, n_ch, n_ant, n_pol) / (sample_count(n_ch, n_ant, n_pol) * cfg.bits / 8)


def packed_metadata_share(packed: DataFrame) -> DataFrame:
    """The same of packed rows, as they are: one row. A row's factor that all its polarisations have in common counts once."""
    n = lambda c: F.coalesce(F.size(c), F.lit(0))
    rows = F.array_distinct(F.flatten(F.collect_list(F.arrays_zip("row_ids", F.col("row_factors")))))
    g = packed.groupBy("block_id", "scaling").agg(F.size(rows).alias("own"), F.sum(n("row_factors") + n("ant_factors") + n("ch_factors")).alias("all"), F.sum(F.octet_length("payload")).alias("payload"))
    return g.agg((4 * F.sum(F.when(F.col("scaling") == "row", F.col("own")).otherwise(F.col("all"))) / F.sum("payload")).alias("share"))


def volume_report(packed: DataFrame, weights: DataFrame, raw: DataFrame, meta_bytes: int = 16) -> DataFrame:
    """component, raw_bytes, packed_bytes and their shares of the raw whole, from what is stored. Data are payloads, masks and factors,
    as factors belong to the samples; weights are codes and row maxima; metadata of rows stay as they are. ``raw``: cells, of
    8 bytes and a weight of 4."""
    n = lambda c: F.coalesce(F.size(c), F.lit(0))
    data = packed.agg(F.sum(F.octet_length("payload") + F.coalesce(F.octet_length("present"), F.lit(0)) + 4 * (n("row_factors") + n("ant_factors") + n("ch_factors"))).cast("long").alias("data"))
    held = weights.agg(F.sum(F.octet_length("payload") + 4 * F.size("row_max")).cast("long").alias("weights"))
    t = raw.agg(F.count("*").alias("n"), F.countDistinct("block_id", "row_id").alias("rows")).crossJoin(data).crossJoin(held)  # single rows
    part = lambda name, before, now: F.struct(F.lit(name).alias("component"), before.cast("long").alias("raw_bytes"), now.cast("long").alias("packed_bytes"))
    meta = F.col("rows") * meta_bytes
    parts = F.explode(F.array(part("data", F.col("n") * 8, F.col("data")), part("weights", F.col("n") * 4, F.col("weights")), part("metadata", meta, meta))).alias("c")
    whole = F.col("n") * 12 + meta
    return t.select(parts, whole.alias("whole")).select("c.component", "c.raw_bytes", "c.packed_bytes", (F.col("c.raw_bytes") / F.col("whole")).alias("raw_share"), (F.col("c.packed_bytes") / F.col("whole")).alias("packed_share"))


def structure_stats(df: DataFrame, value: str = "value", reference: str | None = None) -> DataFrame:
    """Skewness and excess kurtosis of a difference, and its correlation with what should not show in it."""
    more = [F.corr(value, reference).alias("corr")] if reference else []
    return df.agg(F.avg(value).alias("mean"), F.skewness(value).alias("skewness"), F.kurtosis(value).alias("kurtosis"), *more)


def zeroed_fraction(coded: DataFrame, zero: int, *by: str) -> DataFrame:
    """Share of non-zero samples that are coded as zero."""
    return coded.where("v <> 0").groupBy(*by).agg(F.avg(F.when(F.col("sym") == zero, 1.0).otherwise(0.0)).alias("share_zero"))


def bias(coded: DataFrame) -> DataFrame:
    return coded.agg(F.avg(F.col("v_hat") - F.col("v")).alias("bias"))
