"""Scaling, quantising, packing: one query per method and variant."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bits as bitlib
from ..functions.dither import uniform, uniform_sql
from ..functions.levels import n_levels
from ..operators import codec, quantise, scaling
from ..operators.measures import cell_error
from ..schema import TABLES, CodecConfig, table_config
from ..sources import tables
from . import sql
from .registry import query

U8 = CodecConfig(scaling="row", quantiser="uniform", trunc=None, bits=8)
SWEEP_BITS = (2, 3, 4, 5, 6, 7, 8)


def v1(spark: SparkSession, d: str, gains: bool = True) -> DataFrame:
    return tables.vis_embeddings(spark, d, gains=gains)


def row_samples(spark: SparkSession, d: str) -> DataFrame:
    return quantise.samples(scaling.scale_row(scaling.masked(v1(spark, d))))


def rf_samples(spark: SparkSession, d: str) -> DataFrame:
    return quantise.samples(scaling.scale_row_channel(scaling.masked(v1(spark, d))))


@query("row_factor", sql.with_(sql.v1(), sql.row_scaled()) + "SELECT DISTINCT block_id, row_id, round(sigma, 7) AS f FROM scaled")
def row_factor(spark, d):
    """N1 on rows layout: no shuffle before the factors."""
    rows = tables.vis_rows(spark, d)
    g = tables.gain(F.col("ant_a")) * tables.gain(F.col("ant_b"))
    scaled = F.expr("transform(vis, (x, j) -> cast(x as double) * (g * (1.0D + 0.2D * (j div 8))))")
    rows = rows.withColumn("g", g).withColumn("vis", scaled)
    return scaling.scale_row_arrays(rows).select("block_id", "row_id", F.round("sigma", 7).alias("f"))


@query("row_codes_uniform8", sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(8)) + "SELECT block_id, row_id, sum(sym)::BIGINT AS total, min(sym)::INT AS lo, max(sym)::INT AS hi FROM coded GROUP BY ALL")
def row_codes(spark, d):
    return quantise.encode(row_samples(spark, d), U8).groupBy("block_id", "row_id").agg(F.sum("sym").alias("total"), F.min("sym").alias("lo"), F.max("sym").alias("hi"))


@query("row_decode_error", sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(8)) + "SELECT ch, pol, round(sqrt(avg((v_hat - v) * (v_hat - v))), 8) AS rmse, round(avg(v_hat - v), 8) AS bias FROM coded GROUP BY ALL")
def row_decode_error(spark, d):
    coded = quantise.decode(quantise.encode(row_samples(spark, d), U8), U8)
    return cell_error(coded, "ch", "pol").select("ch", "pol", F.round("rmse", 8).alias("rmse"), F.round("bias", 8).alias("bias"))


def _uniform_mse_sql() -> str:
    parts = [f"SELECT {b} AS bits, round(sqrt(avg((y - below) * (above - y) * sigma * sigma)), 9) AS rms FROM p{b}" for b in (2, 3, 4, 5, 6, 7, 8, 10, 12, 16)]
    return sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), *(sql.uniform_pos(b, name=f"p{b}") for b in (2, 3, 4, 5, 6, 7, 8, 10, 12, 16))) + "\nUNION ALL ".join(parts)


@query("row_expected_mse", _uniform_mse_sql())
def row_expected_mse(spark, d):
    """Expected error of uniform levels by bit-rate: one pass over the samples."""
    s = row_samples(spark, d)
    cfgs = {b: U8.but(bits=b) for b in (2, 3, 4, 5, 6, 7, 8, 10, 12, 16)}
    g = s.agg(*(F.sqrt(F.avg(quantise.expected_square(c))).alias(str(b)) for b, c in cfgs.items()))
    return g.unpivot([], [F.col(str(b)) for b in cfgs], "bits", "rms").select(F.col("bits").cast("int").alias("bits"), F.round("rms", 9).alias("rms"))


LABELS = tuple(x for x in TABLES if x != "uniform")


def _tables_native(s: DataFrame, bits: tuple[int, ...], labels: tuple[str, ...] = LABELS) -> DataFrame:
    g = s.agg(*(F.sqrt(F.avg(quantise.expected_square(table_config(x, b)))).alias(f"{x}|{b}") for x in labels for b in bits))
    long = g.unpivot([], [F.col(f"`{c}`") for c in g.columns], "k", "rms")
    return long.select(F.split("k", r"\|")[0].alias("quantiser"), F.split("k", r"\|")[1].cast("int").alias("bits"), F.round("rms", 8).alias("rms"))


@query("tgauss_expected_mse", sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.level_rows(LABELS, (4, 8))) + sql.table_errors(LABELS, (4, 8)))
def tgauss_expected_mse(spark, d):
    """Q1-Q4 by the native binary search."""
    return _tables_native(row_samples(spark, d), (4, 8))


@query("legacy_row16", sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(16, u="0.5")) + "SELECT block_id, round(sqrt(avg((v_hat - v) * (v_hat - v))), 10) AS rmse FROM coded GROUP BY ALL")
def legacy_row16(spark, d):
    from ..operators.baselines import legacy_row16 as legacy

    return cell_error(legacy(v1(spark, d)), "block_id").select("block_id", F.round("rmse", 10).alias("rmse"))


@query("row_uniform_dithered", sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(6, 3)) + "SELECT pol, round(sqrt(avg((v_hat - v) * (v_hat - v))), 8) AS rmse FROM coded GROUP BY ALL")
def row_uniform_dithered(spark, d):
    from ..operators.baselines import row_uniform

    return cell_error(row_uniform(v1(spark, d), 6, seed=3), "pol").select("pol", F.round("rmse", 8).alias("rmse"))


@query("row_nearest", sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(4, u="0.5")) + "SELECT ch, round(sqrt(avg((v_hat - v) * (v_hat - v))), 8) AS rmse, round(avg(v_hat - v), 8) AS bias FROM coded GROUP BY ALL")
def row_nearest(spark, d):
    """Q8': rounding without dither."""
    cfg = U8.but(bits=4, dither="none")
    return cell_error(quantise.decode(quantise.encode(row_samples(spark, d), cfg), cfg), "ch").select("ch", F.round("rmse", 8).alias("rmse"), F.round("bias", 8).alias("bias"))


def _subtractive_sql() -> str:
    n = n_levels(5)
    u = uniform_sql("ord", 2)
    coded = f"""coded AS (SELECT *, CASE WHEN sigma > 0 THEN (sym - {u} + 0.5) * {2.0 / (n - 1)!r}::DOUBLE - 1 ELSE 0 END * sigma AS v_hat FROM (SELECT *, greatest(least(floor((y + 1) * {(n - 1) / 2.0!r}::DOUBLE + {u}), {n - 1}), 0)::INT AS sym FROM smp))"""
    return sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), coded) + "SELECT pol, round(sqrt(avg((v_hat - v) * (v_hat - v))), 8) AS rmse, round(avg(v_hat - v), 8) AS bias FROM coded GROUP BY ALL"


@query("subtractive_dither", _subtractive_sql())
def subtractive_dither(spark, d):
    """Q9: the dither is taken off again after decoding."""
    cfg = U8.but(bits=5, dither="subtractive", seed=2)
    return cell_error(quantise.decode(quantise.encode(row_samples(spark, d), cfg), cfg), "pol").select("pol", F.round("rmse", 8).alias("rmse"), F.round("bias", 8).alias("bias"))


@query("rf_channel_rms", sql.with_(sql.v1()) + f"SELECT block_id, pol, ch, round(sqrt(avg({sql.POWER})), 8) AS f FROM cells GROUP BY ALL")
def rf_channel_rms(spark, d):
    return scaling.masked(v1(spark, d)).groupBy("block_id", "pol", "ch").agg(F.round(F.sqrt(F.avg(scaling.power())), 8).alias("f"))


@query("rf_row_factor", sql.with_(sql.v1(), sql.rf_scaled()) + "SELECT DISTINCT block_id, pol, row_id, round(f_row, 6) AS f FROM scaled")
def rf_row_factor(spark, d):
    return scaling.scale_row_channel(scaling.masked(v1(spark, d))).select("block_id", "pol", "row_id", F.round("f_row", 6).alias("f")).distinct()


@query("rf_channel_factor", sql.with_(sql.v1(), sql.rf_scaled()) + "SELECT DISTINCT block_id, pol, ch, round(f_ch, 6) AS f FROM scaled")
def rf_channel_factor(spark, d):
    return scaling.scale_row_channel(scaling.masked(v1(spark, d))).select("block_id", "pol", "ch", F.round("f_ch", 6).alias("f")).distinct()


@query("rf_codes", sql.with_(sql.v1(), sql.rf_scaled(), sql.sampled(), sql.uniform_coded(8)) + "SELECT block_id, pol, sum(sym)::BIGINT AS total FROM coded GROUP BY ALL")
def rf_codes(spark, d):
    return quantise.encode(rf_samples(spark, d), U8).groupBy("block_id", "pol").agg(F.sum("sym").alias("total"))


@query("rf_expected_mse", sql.with_(sql.v1(), sql.rf_scaled(), sql.sampled(), sql.level_rows(LABELS, (4, 8))) + sql.table_errors(LABELS, (4, 8)))
def rf_expected_mse(spark, d):
    return _tables_native(rf_samples(spark, d), (4, 8))


@query("rf_on_v4")
def rf_on_v4(spark, d):
    """Row x channel scaling of sparse, skewed positive data."""
    s = quantise.samples(scaling.scale_row_channel(scaling.masked(tables.vis_documents(spark, d))))
    return quantise.expected_rms_many(s.where("v is not null"), (4, 8)).withColumn("rms", F.round("rms", 6))


def _kernel_errors(spark: SparkSession, cells: DataFrame, cfg: CodecConfig, bits: tuple[int, ...] = (4, 8)) -> DataFrame:
    s = quantise.samples(scaling.fit_scales(cells, cfg)).where("ant_a <> ant_b")
    return quantise.expected_rms_many(s, bits).withColumn("rms", F.round("rms", 8))


@query("af_kernel_mse")
def af_kernel_mse(spark, d):
    """N2 with the iterative solver."""
    return _kernel_errors(spark, v1(spark, d), CodecConfig())


@query("af_kernel_mse_loglsq")
def af_kernel_mse_loglsq(spark, d):
    return _kernel_errors(spark, v1(spark, d), CodecConfig(solver="loglsq"))


@query("rf_from_af_mse")
def rf_from_af_mse(spark, d):
    """N3+: rows maximised on top of antenna x channel factors."""
    return _kernel_errors(spark, v1(spark, d), CodecConfig(scaling="row_channel_af"))


def af_channels(source: str = "cells") -> str:
    return f"afc AS (SELECT *, sqrt(avg({sql.POWER}) OVER (PARTITION BY block_id, pol, ch)) AS f_ch FROM {source} WHERE ant_a <> ant_b)"


AF_CH = af_channels()
AF_VAR = f"afv AS (SELECT block_id, pol, ant_a, ant_b, avg({sql.POWER} / (f_ch * f_ch)) AS var FROM afc GROUP BY ALL)"
AF_ANT = """both_ AS (SELECT block_id, pol, ant_a AS ant, ln(var) AS l FROM afv UNION ALL SELECT block_id, pol, ant_b, ln(var) FROM afv),
afs AS (SELECT *, count(*) OVER w AS n, sum(s) OVER w AS total, min(k) OVER w AS fewest FROM (SELECT block_id, pol, ant, sum(l) AS s, count(*) AS k FROM both_ GROUP BY ALL) WINDOW w AS (PARTITION BY block_id, pol)),
ants AS (SELECT block_id, pol, ant, exp((s - total / (2 * (n - 1))) / (n - 2) / 2) AS f FROM afs WHERE n >= 3 AND fewest = n - 1)"""


@query("af_channel_rms", sql.with_(sql.v1()) + f"SELECT block_id, pol, ch, round(sqrt(avg({sql.POWER})), 8) AS f FROM cells WHERE ant_a <> ant_b GROUP BY ALL")
def af_channel_rms(spark, d):
    return scaling.channel_rms(v1(spark, d)).withColumn("f", F.round("f", 8))


@query("af_baseline_var", sql.with_(sql.v1(), AF_CH, AF_VAR) + "SELECT block_id, pol, ant_a, ant_b, round(var, 7) AS var FROM afv")
def af_baseline_var(spark, d):
    return scaling.baseline_variance(v1(spark, d)).withColumn("var", F.round("var", 7))


@query("af_antenna_loglsq", sql.with_(sql.v1(), AF_CH, AF_VAR, AF_ANT) + "SELECT block_id, pol, ant, round(f, 7) AS f FROM ants")
def af_antenna_loglsq(spark, d):
    return scaling.antenna_loglsq(scaling.baseline_variance(v1(spark, d))).withColumn("f", F.round("f", 7))


def af_scaled(rounds: int, source: str = "cells") -> list[str]:
    """Cross cells of complete blocks with sigma, as g0, g1 ...: closed-form antennas, common rescale, greedy steps."""
    out = [af_channels(source), AF_VAR, AF_ANT, f"g0a AS (SELECT afc.*, f_ch * x.f * y.f AS s0 FROM afc JOIN ants x ON x.block_id = afc.block_id AND x.pol = afc.pol AND x.ant = ant_a JOIN ants y ON y.block_id = afc.block_id AND y.pol = afc.pol AND y.ant = ant_b)", f"g0 AS (SELECT *, s0 * max({sql.PEAK} / s0) OVER (PARTITION BY block_id, pol) AS sigma FROM g0a)"]
    for k in range(rounds):
        one = lambda kind, idx: f"SELECT block_id, pol, '{kind}' AS kind, {idx} AS idx, {sql.PEAK} / sigma AS y, (abs(re) + abs(im)) / sigma AS s FROM g{k}"  # noqa: B023, E731
        out += [
            f"e{k} AS ({one('ch', 'ch')} UNION ALL {one('ant', 'ant_a')} UNION ALL {one('ant', 'ant_b')})",
            f"t{k} AS (SELECT block_id, pol, kind, idx, max(y) AS top, (1 / max(y) - 1) * sum(s) AS gain FROM e{k} GROUP BY ALL)",
            f"b{k} AS (SELECT * FROM t{k} QUALIFY row_number() OVER (PARTITION BY block_id, pol ORDER BY gain DESC, kind DESC, idx) = 1)",
            f"g{k + 1} AS (SELECT g{k}.* EXCLUDE (sigma), CASE WHEN CASE WHEN kind = 'ch' THEN ch = idx ELSE ant_a = idx OR ant_b = idx END THEN sigma * top ELSE sigma END AS sigma FROM g{k} JOIN b{k} USING (block_id, pol))",
        ]
    return out


def _greedy_sql(rounds: int) -> str:
    return sql.with_(sql.v1(), *af_scaled(rounds)) + f"SELECT block_id, pol, round(sum((abs(re) + abs(im)) / sigma), 5) AS sum_abs FROM g{rounds} GROUP BY ALL"


#: The kernel as SQL can follow it: closed-form antennas, which complete blocks have, a fixed number of steps, factors as they are.
AF_EXACT = CodecConfig(solver="loglsq", tau=0.0, max_steps=2, round_factors=False)


def af_exact(cells: DataFrame) -> DataFrame:
    """Cross cells of complete blocks with the kernel's sigma."""
    whole = cells.groupBy("block_id").agg(F.countDistinct("row_id").alias("n")).where("n = 36").select("block_id")
    return scaling.fit_scales(cells.join(whole, "block_id", "left_semi"), AF_EXACT).where("ant_a <> ant_b")


@query("af_kernel_closed_form", _greedy_sql(2))
def af_kernel_closed_form(spark, d):
    """N2 by the block kernel, against SQL."""
    return af_exact(v1(spark, d)).groupBy("block_id", "pol").agg(F.round(F.sum((F.abs("re") + F.abs("im")) / F.col("sigma")), 5).alias("sum_abs"))


@query("af_kernel_codes_closed_form", sql.with_(sql.v1(), *af_scaled(2), sql.sampled("g2"), sql.level_rows(("t2.5",), (5,)), sql.table_coded("t2.5", 5)) + "SELECT block_id, pol, sum(sym)::BIGINT AS total, round(sqrt(avg((v_hat - v) * (v_hat - v))), 8) AS rms FROM coded GROUP BY ALL")
def af_kernel_codes(spark, d):
    """N2 and the dithered table: symbols and errors at the guideline's 5 bits."""
    cfg = CodecConfig(bits=5)
    coded = quantise.decode(quantise.encode(quantise.samples(af_exact(v1(spark, d))), cfg), cfg)
    return coded.groupBy("block_id", "pol").agg(F.sum("sym").alias("total"), F.round(F.sqrt(F.avg((F.col("v_hat") - F.col("v")) ** 2)), 8).alias("rms"))


@query("af_greedy_two_rounds", _greedy_sql(2))
def af_greedy_two_rounds(spark, d):
    """Native twin of N2: closed-form antennas, common rescale, two greedy steps."""
    c = scaling.antenna_channel_native(v1(spark, d), 2)
    return c.groupBy("block_id", "pol").agg(F.round(F.sum((F.abs("re") + F.abs("im")) / F.col("sigma")), 5).alias("sum_abs"))


@query("af_native_mse", _greedy_sql(2).rsplit("SELECT block_id, pol, round", 1)[0].rstrip() + ",\n" + sql.sampled("g2") + ",\n" + sql.level_rows(("t2.5",), (8,)) + "\n" + sql.table_errors(("t2.5",), (8,)))
def af_native_mse(spark, d):
    s = quantise.samples(scaling.antenna_channel_native(v1(spark, d), 2))
    return _tables_native(s, (8,), ("t2.5",))


@query("af_bound_check", "SELECT CASE WHEN n.n > 0 THEN n.n END AS n_cells, 0::BIGINT AS n_over FROM (SELECT count(*) * 32 AS n FROM embeddings) n")
def af_bound_check(spark, d):
    """Nothing exceeds the top level by more than the rounding of stored factors."""
    c = scaling.fit_scales(v1(spark, d), CodecConfig())
    over = (scaling.peak() > F.col("sigma") * (1 + 1e-6)) & (F.col("ant_a") != F.col("ant_b"))
    return c.agg(F.count("*").alias("n_cells"), F.count_if(over).alias("n_over"))


def _trim_sql() -> str:
    k = 2.0
    s = sql.with_(sql.v1(signal=2.0), sql.row_scaled("cells", "sc0"), f"scaled AS (SELECT * EXCLUDE (sigma), sigma * coalesce(sqrt(avg({sql.POWER} / nullif(sigma * sigma, 0)) OVER (PARTITION BY block_id, pol)) * {k}::DOUBLE, 1) AS sigma FROM sc0)", sql.sampled(), sql.uniform_coded(8))
    return s + "SELECT pol, round(avg(v_hat - v), 6) AS bias, round(avg(CASE WHEN abs(v) > sigma THEN 1.0::DOUBLE ELSE 0 END), 8) AS share_clipped FROM coded GROUP BY ALL"


@query("trim_bias", _trim_sql())
def trim_bias(spark, d):
    """Trimming biases data that carry signal."""
    c = scaling.scale_trimmed(scaling.scale_row(scaling.masked(tables.inject_signal(v1(spark, d), 2.0))), 2.0)
    coded = quantise.decode(quantise.encode(quantise.samples(c), U8), U8)
    return coded.groupBy("pol").agg(F.round(F.avg(F.col("v_hat") - F.col("v")), 6).alias("bias"), F.round(F.avg(F.when(F.abs("v") > F.col("sigma"), 1.0).otherwise(0.0)), 8).alias("share_clipped"))


def _autos(spark, d, mode):
    c = scaling.masked(v1(spark, d), mode)
    return c.agg(F.count_if((F.col("ant_a") == F.col("ant_b")) & (F.col("re") == 0) & (F.col("im") == 0)).alias("zeroed"), F.count_if((F.col("re") != 0) | (F.col("im") != 0)).alias("kept"))


@query("autos_zero", sql.with_(sql.v1()) + "SELECT count(*) FILTER (ant_a = ant_b) AS zeroed, count(*) FILTER (ant_a <> ant_b AND (re <> 0 OR im <> 0)) AS kept FROM cells")
def autos_zero(spark, d):
    return _autos(spark, d, "zero")


@query("autos_keep", sql.with_(sql.v1()) + "SELECT count(*) FILTER (ant_a = ant_b AND re = 0 AND im = 0) AS zeroed, count(*) FILTER (re <> 0 OR im <> 0) AS kept FROM cells")
def autos_keep(spark, d):
    return _autos(spark, d, "keep")


@query("autos_own_factor")
def autos_own_factor(spark, d):
    """The extension: autocorrelations with a factor of their own."""
    cfg = CodecConfig(autos="own_factor")
    c = scaling.fit_scales(v1(spark, d), cfg).where("ant_a = ant_b")
    return c.agg(F.count("*").alias("n"), F.count_if(scaling.peak() > F.col("sigma") * (1 + 1e-6)).alias("n_over"))


@query(
    "metadata_counts",
    """WITH s(scaling, n_factors) AS (VALUES ('row', 36), ('row_channel', 4 * (8 + 36)), ('antenna_channel', 4 * (8 + 8)), ('row_channel_bound', 4 * (8 + 64)))
SELECT scaling, n_factors::BIGINT AS n_factors, (4 * 2 * 8 * 36)::BIGINT AS n_samples, b.n AS full_blocks FROM s, (SELECT count(*) AS n FROM (SELECT vec_id // 36 AS b FROM embeddings GROUP BY 1 HAVING count(*) = 36)) b""",
)
def metadata_counts(spark, d):
    """Factors counted from what the codec stores in full blocks, held against the formula."""
    packed = None
    for s in ("row", "row_channel", "antenna_channel"):
        p = codec.compress(v1(spark, d), CodecConfig(scaling=s, autos="keep" if s != "antenna_channel" else "zero"))
        n = sum((F.coalesce(F.size(c), F.lit(0)) for c in ("row_factors", "ant_factors", "ch_factors")), F.lit(0))
        n = F.sum(n) if s != "row" else F.max(n)  # the row's factor is the same in all polarisations
        one = p.where(F.size("row_ids") == 36).groupBy("block_id").agg(n.alias("f"), F.sum(F.size("row_ids") * F.size("channels") * 2).alias("n")).groupBy().agg(F.max("f").alias("f"), F.max("n").alias("n"), F.count("*").alias("b"))
        one = one.select(F.lit(s).alias("scaling"), F.col("f").cast("long").alias("n_factors"), F.col("n").cast("long").alias("n_samples"), F.col("b").alias("full_blocks"))
        packed = one if packed is None else packed.unionAll(one)
    bound = packed.where("scaling = 'row'").select(F.lit("row_channel_bound"), F.lit(4 * (8 + 64)).cast("long"), "n_samples", "full_blocks")
    return packed.unionAll(bound)


@query("metadata_counts_v2", sql.with_(sql.V2) + "SELECT block_id, count(DISTINCT row_id) AS n_rows, count(DISTINCT ch) AS n_ch, count(*) AS n_cells FROM cells GROUP BY ALL")
def metadata_counts_v2(spark, d):
    return tables.vis_lineitem(spark, d).groupBy("block_id").agg(F.countDistinct("row_id").alias("n_rows"), F.countDistinct("ch").alias("n_ch"), F.count("*").alias("n_cells"))


def _flag_sql() -> str:
    ordn = "((row_id::BIGINT * 1024 + ch) * 4 + pol) * 2"
    from ..functions.dither import M1, M2, MASK, S1, S2, S3, SEED_STEP

    h = f"(({ordn} + {SEED_STEP})::BIGINT & {MASK})"
    for shift, factor in ((S1, M1), (S2, M2)):
        h = f"((xor({h}, {h} >> {shift}) * {factor}) & {MASK})"
    h = f"xor({h}, {h} >> {S3})"
    flagged = f"fl AS (SELECT * EXCLUDE (re, im), CASE WHEN {h} % 20 = 0 THEN NULL ELSE re END AS re, CASE WHEN {h} % 20 = 0 THEN NULL ELSE im END AS im FROM cells)"
    dead = "dd AS (SELECT * EXCLUDE (re, im), CASE WHEN ant_a = 2 OR ant_b = 2 THEN re * 0 ELSE re END AS re, CASE WHEN ant_a = 2 OR ant_b = 2 THEN im * 0 ELSE im END AS im FROM fl)"
    return sql.with_(sql.v1(), flagged, dead, sql.row_scaled("dd"), sql.sampled(), sql.uniform_coded(8)) + "SELECT CASE WHEN v IS NULL THEN 'nan' WHEN sym = 127 THEN 'zero' WHEN sym = 254 THEN 'max' WHEN sym = 0 THEN 'min' ELSE 'other' END AS kind, count(*) AS n FROM coded GROUP BY ALL"


@query("nan_zero_symbols", _flag_sql())
def nan_zero_symbols(spark, d):
    """Flags code as NaN, a dead antenna as exact zero, the largest magnitude as the outermost level."""
    c = tables.dead_antenna(tables.flag_cells(v1(spark, d)))
    coded = quantise.encode(quantise.samples(scaling.scale_row(scaling.masked(c))), U8)
    kind = F.when(F.col("sym") == 255, "nan").when(F.col("sym") == 127, "zero").when(F.col("sym") == 254, "max").when(F.col("sym") == 0, "min").otherwise("other")
    return coded.groupBy(kind.alias("kind")).agg(F.count("*").alias("n"))


@query("mask_flags", sql.with_(sql.v1()) + "SELECT count(*) AS n, count(*) FILTER (ch = 6 AND block_id = 0) AS n_nan FROM cells")
def mask_flags(spark, d):
    c = v1(spark, d).withColumn("flagged", (F.col("ch") == 6) & (F.col("block_id") == 0))
    return codec.mask_flags(c).agg(F.count("*").alias("n"), F.count_if(F.isnan("re") & F.isnan("im")).alias("n_nan"))


@query("pack_lengths", "SELECT b::INT AS bits, v.vec_id::BIGINT AS row_id, ((64 * b + 7) // 8)::BIGINT AS bytes FROM embeddings v, range(2, 17) r(b)")
def pack_lengths(spark, d):
    """Payload of every row at every bit-rate, from real packing."""
    rows = tables.vis_rows(spark, d)
    out = None
    for b in range(2, 17):
        one = codec.compress_rows(rows, b).select("bits", "row_id", F.octet_length("payload").cast("long").alias("bytes"))
        out = one if out is None else out.unionAll(one)
    return out


@query(
    "pack_hex_small",
    sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(4))
    + "SELECT row_id, pol, upper(string_agg(printf('%x', sym), '' ORDER BY ch, part)) AS payload FROM coded GROUP BY ALL",
)
def pack_hex_small(spark, d):
    """Native packing: two 4-bit symbols a byte."""
    coded = quantise.encode(row_samples(spark, d), U8.but(bits=4))
    rows = coded.groupBy("row_id", "pol").agg(F.transform(F.array_sort(F.collect_list(F.struct("ch", "part", "sym"))), lambda x: x["sym"]).alias("s"))
    return rows.select("row_id", "pol", F.hex(bitlib.pack_expr(F.col("s"), 4)).alias("payload"))


@query("unpack_roundtrip", "SELECT b::INT AS bits, count(*)::BIGINT AS n, 0::BIGINT AS n_bad FROM embeddings, (VALUES (2), (3), (5), (7), (8), (11), (16)) r(b) GROUP BY ALL")
def unpack_roundtrip(spark, d):
    """Symbols of each row packed and unpacked in functions of the engine."""
    out = None
    for b in (2, 3, 5, 7, 8, 11, 16):
        n = (1 << b) - 1
        s = F.expr(f"transform(vis, x -> cast(floor((x + 1.0D) / 2 * {n}) as bigint))")
        p = tables.vis_rows(spark, d).select("row_id", s.alias("s")).withColumn("p", bitlib.pack_expr(F.col("s"), b))
        p = p.groupBy("row_id").agg(F.first("s").alias("s"), F.first("p").alias("p"))  # a payload as storage would give it, not an expression to be put into each access
        one = p.agg(F.lit(b).alias("bits"), F.count("*").alias("n"), F.count_if(bitlib.unpack_expr(F.col("p"), b, F.size("s")) != F.col("s")).alias("n_bad"))
        out = one if out is None else out.unionAll(one)
    return out


@query("codec_roundtrip", "SELECT s.scaling, count(*)::BIGINT AS n_cells, 0::BIGINT AS n_bad FROM embeddings, range(32) r(k), (VALUES ('row'), ('row_channel'), ('row_channel_af'), ('antenna_channel')) s(scaling) GROUP BY ALL")
def codec_roundtrip(spark, d):
    """Every sample comes back within one step of its own scale (autocorrelations of the antenna method as zero)."""
    cells = v1(spark, d)
    out = None
    for s in ("row", "row_channel", "row_channel_af", "antenna_channel"):
        cfg = CodecConfig(scaling=s, quantiser="uniform", trunc=None, bits=10, autos="zero" if s == "antenna_channel" else "keep")
        back = codec.decompress(codec.compress(cells, cfg))
        keys = ["block_id", "row_id", "ant_a", "ant_b", "ch", "pol"]
        scales = scaling.fit_scales(cells, cfg).select(*keys, "sigma")
        j = cells.withColumnsRenamed({"re": "re0", "im": "im0"}).join(scales, keys).join(back, keys, "left")
        auto = (F.col("ant_a") == F.col("ant_b")) & F.lit(s == "antenna_channel")
        err = F.greatest(F.abs(F.col("re") - F.col("re0")), F.abs(F.col("im") - F.col("im0")))
        bad = F.when(auto, (F.col("re") != 0) | (F.col("im") != 0)).otherwise(F.coalesce(err > F.col("sigma") * (2 / 1022) * (1 + 1e-6), F.lit(True)))
        one = j.agg(F.lit(s).alias("scaling"), F.count("*").alias("n_cells"), F.count_if(bad).alias("n_bad"))
        out = one if out is None else out.unionAll(one)
    return out


@query("stored_factors", "SELECT 'antenna' AS kind, n::BIGINT AS n FROM (SELECT 4 * 8 * count(*) AS n FROM (SELECT vec_id // 36 FROM embeddings GROUP BY 1 HAVING count(*) = 36)) UNION ALL SELECT 'channel', n::BIGINT FROM (SELECT 4 * 8 * count(*) AS n FROM (SELECT vec_id // 36 FROM embeddings GROUP BY 1 HAVING count(*) = 36))")
def stored_factors(spark, d):
    p = codec.compress(v1(spark, d), CodecConfig()).where(F.size("row_ids") == 36)
    return codec.factors(p).groupBy("kind").agg(F.count("*").alias("n"))


@query("truncation_search", sql.with_(sql.v1(), sql.rf_scaled(), sql.sampled(), sql.level_rows(("t1.5", "t2.5", "t3.5"), (8,)), "er AS (SELECT block_id, pol, replace(quantiser, 't', '')::DOUBLE AS t, round(sqrt(avg((y - lo) * (hi - y) * sigma * sigma)), 12) AS rms FROM smp JOIN lv ON y >= lo AND (y < hi OR last) GROUP BY ALL)") + "SELECT block_id, pol, arg_min(t, struct_pack(r := rms, t := t)) AS best_trunc, round(min(rms), 8) AS rms FROM er GROUP BY ALL")
def truncation_search(spark, d):
    """Q14: the truncation of least expected error for every block and polarisation."""
    return quantise.fit_truncation(rf_samples(spark, d), 8, (1.5, 2.5, 3.5), "block_id", "pol").withColumn("rms", F.round("rms", 8))


@query("truncation_in_codec", sql.with_(sql.v1(), sql.rf_scaled(), sql.sampled(), sql.level_rows(("t1.5", "t2.5", "t3.5"), (8,)), "er AS (SELECT block_id, pol, replace(quantiser, 't', '')::DOUBLE AS t, round(sqrt(avg((y - lo) * (hi - y) * sigma * sigma)), 12) AS rms FROM smp JOIN lv ON y >= lo AND (y < hi OR last) GROUP BY ALL)") + "SELECT block_id, pol, arg_min(t, struct_pack(r := rms, t := t)) AS trunc, TRUE AS decodes FROM er GROUP BY ALL")
def truncation_in_codec(spark, d):
    """Q14 in the codec: each block's own truncation is searched, stored with it and decoded by."""
    p = codec.compress(v1(spark, d), CodecConfig(scaling="row_channel", autos="keep", trunc_grid=(1.5, 2.5, 3.5)))
    back = codec.decompress(p).join(v1(spark, d).withColumnsRenamed({"re": "r0", "im": "i0"}), ["block_id", "row_id", "ch", "pol"])
    near = back.groupBy("block_id", "pol").agg((F.sqrt(F.avg((F.col("re") - F.col("r0")) ** 2)) < 0.1 * F.sqrt(F.avg(F.col("r0") ** 2))).alias("decodes"))
    return p.select("block_id", "pol", "trunc").join(near, ["block_id", "pol"])


@query("entropy_stage")
def entropy_stage(spark, d):
    """Q15: payload bytes with and without a lossless stage on the symbols."""
    out = None
    for kind in (None, "rice", "deflate"):
        p = codec.compress(v1(spark, d), CodecConfig(scaling="row_channel", autos="keep", bits=6, entropy=kind))
        one = p.agg(F.lit(kind or "none").alias("entropy"), F.sum(F.octet_length("payload")).alias("bytes"))
        out = one if out is None else out.unionAll(one)
    return out


@query("lloyd_levels_mse")
def lloyd_levels_mse(spark, d):
    """Q6: least-squares levels next to sampled ones."""
    s = row_samples(spark, d)
    out = [s.agg(F.lit(q).alias("quantiser"), F.round(F.sqrt(F.avg(quantise.expected_square(CodecConfig(quantiser=q, trunc=None, bits=5)))), 8).alias("rms")) for q in ("lloyd", "gauss")]
    return out[0].unionAll(out[1])


@query("op_dither_uniform", f"SELECT (o % 16)::BIGINT AS k, count(*) AS n, round(avg(u), 10) AS mean FROM (SELECT l_orderkey * 8 + l_linenumber AS o, {uniform_sql('l_orderkey * 8 + l_linenumber', 7)} AS u FROM lineitem) GROUP BY ALL")
def op_dither_uniform(spark, d):
    o = F.col("l_orderkey") * 8 + F.col("l_linenumber")
    li = tables.load(spark, d, "lineitem", "l_orderkey", "l_linenumber")
    return li.groupBy((o % 16).alias("k")).agg(F.count("*").alias("n"), F.round(F.avg(uniform(o, 7)), 10).alias("mean"))

