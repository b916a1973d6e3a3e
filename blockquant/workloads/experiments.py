"""The experiments, baselines, measures and processing steps."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.dither import M1, M2, MASK, S1, S2, S3
from ..functions.levels import zero_symbol
from ..operators import baselines, calibrate, codec, guideline, imaging, measures, quantise, scaling, sweep, weights
from ..schema import CodecConfig
from ..sources import store, tables
from . import sql
from .registry import query
from .scaling import U8, af_exact, af_scaled, row_samples, v1

T25_8 = CodecConfig(scaling="row", trunc=2.5, bits=8)
ERR = "round(sqrt(avg((v_hat - v) * (v_hat - v))), 7)"


# Strong interference in one channel.


def _rfi(spark, d, how) -> DataFrame:
    c = tables.inject_rfi(v1(spark, d))
    s = quantise.samples(how(c)).where("ant_a <> ant_b")
    coded = quantise.decode(quantise.encode(s, T25_8), T25_8)
    return measures.cell_error(coded, "ch").select("ch", F.round("rmse", 6).alias("rms"))


def _rfi_sql(scale: str) -> str:
    scaled = sql.row_scaled("hit") if scale == "row" else sql.rf_scaled("hit")
    return sql.with_(sql.v1(), sql.rfi(), scaled, sql.sampled(), sql.level_rows(("t2.5",), (8,)), sql.table_coded("t2.5", 8)) + "SELECT ch, round(sqrt(avg((v_hat - v) * (v_hat - v))), 6) AS rms FROM coded WHERE ant_a <> ant_b GROUP BY ALL"


@query("w1_rfi_row", _rfi_sql("row"))
def w1_rfi_row(spark, d):
    return _rfi(spark, d, lambda c: scaling.scale_row(scaling.masked(c)))


@query("w1_rfi_rf", _rfi_sql("rf"))
def w1_rfi_rf(spark, d):
    return _rfi(spark, d, lambda c: scaling.scale_row_channel(scaling.masked(c)))


@query("w1_rfi_af")
def w1_rfi_af(spark, d):
    return _rfi(spark, d, lambda c: scaling.fit_scales(c, CodecConfig()))


@query("w1_rfi_af_closed_form", sql.with_(sql.v1(), sql.rfi(), *af_scaled(2, "hit"), sql.sampled("g2"), sql.level_rows(("t2.5",), (8,)), sql.table_coded("t2.5", 8)) + "SELECT ch, round(sqrt(avg((v_hat - v) * (v_hat - v))), 6) AS rms FROM coded GROUP BY ALL")
def w1_rfi_af_closed(spark, d):
    return _rfi(spark, d, af_exact)


@query("w1_rfi_ratio", "SELECT TRUE AS row_fails, TRUE AS af_holds, TRUE AS rf_holds")
def w1_rfi_ratio(spark, d):
    """Row scaling loses the clean channels under interference; the channel methods hold them."""
    clean = {k: f(spark, d).where("ch <> 3").agg(F.avg("rms").alias(k)) for k, f in (("row", w1_rfi_row), ("rf", w1_rfi_rf), ("af", w1_rfi_af))}
    j = clean["row"].crossJoin(clean["rf"]).crossJoin(clean["af"])  # three single rows
    return j.select((F.col("row") > 50 * F.greatest("rf", "af")).alias("row_fails"), (F.col("af") < 0.05).alias("af_holds"), (F.col("rf") < 0.05).alias("rf_holds"))


@query("w1_heavy_tail_v3", sql.with_(sql.V3, sql.row_scaled(), sql.sampled(), sql.level_rows(("t2.5",), (8,)), sql.table_coded("t2.5", 8)) + f"SELECT ch, {ERR} AS rms FROM coded GROUP BY ALL")
def w1_heavy_tail(spark, d):
    """The same on data with a natural tail."""
    s = quantise.samples(scaling.scale_row(scaling.masked(tables.vis_events(spark, d))))
    return measures.cell_error(quantise.decode(quantise.encode(s, T25_8), T25_8), "ch").select("ch", F.round("rmse", 7).alias("rms"))


# One baseline at high signal.

T25_3 = CodecConfig(scaling="row", trunc=2.5, bits=3)


def _scatter(spark, d, how):
    s = quantise.samples(how(tables.inject_signal(v1(spark, d), 2.0))).where("ant_a = 1 and ant_b = 5")
    coded = quantise.decode(quantise.encode(s, T25_3), T25_3)
    return measures.cell_error(coded, "pol", "part").select("pol", "part", F.round("rmse", 6).alias("rms"), F.round("bias", 6).alias("bias"))


def _scatter_sql(scale):
    scaled = sql.row_scaled() if scale == "row" else sql.rf_scaled()
    return sql.with_(sql.v1(signal=2.0), scaled, sql.sampled(), sql.level_rows(("t2.5",), (3,)), sql.table_coded("t2.5", 3)) + "SELECT pol, part, round(sqrt(avg((v_hat - v) * (v_hat - v))), 6) AS rms, round(avg(v_hat - v), 6) AS bias FROM coded WHERE ant_a = 1 AND ant_b = 5 GROUP BY ALL"


@query("w2_baseline_scatter_row", _scatter_sql("row"))
def w2_row(spark, d):
    return _scatter(spark, d, lambda c: scaling.scale_row(scaling.masked(c)))


@query("w2_baseline_scatter_rf", _scatter_sql("rf"))
def w2_rf(spark, d):
    return _scatter(spark, d, lambda c: scaling.scale_row_channel(scaling.masked(c)))


@query("w2_baseline_scatter_af")
def w2_af(spark, d):
    return _scatter(spark, d, lambda c: scaling.fit_scales(c, CodecConfig()))


@query("w2_baseline_scatter_af_closed_form", sql.with_(sql.v1(signal=2.0), *af_scaled(2), sql.sampled("g2"), sql.level_rows(("t2.5",), (3,)), sql.table_coded("t2.5", 3)) + "SELECT pol, part, round(sqrt(avg((v_hat - v) * (v_hat - v))), 6) AS rms, round(avg(v_hat - v), 6) AS bias FROM coded WHERE ant_a = 1 AND ant_b = 5 GROUP BY ALL")
def w2_af_closed(spark, d):
    return _scatter(spark, d, af_exact)


# Repeats.

T_G4 = CodecConfig(scaling="row", quantiser="gauss", trunc=None, bits=4)


def _repeat_sql(source: str, col: str) -> str:
    parts = []
    for k in (1, 3, 100):
        h = f"((ord + kk * 1000003)::BIGINT & {MASK})"
        for shift, factor in ((S1, M1), (S2, M2)):
            h = f"((xor({h}, {h} >> {shift}) * {factor}) & {MASK})"
        u = f"((xor({h}, {h} >> {S3}) + 0.5::DOUBLE) / 4294967296.0::DOUBLE)"
        parts.append(f"SELECT {k}::INT AS k, round(sqrt(avg((m - v) * (m - v))), 7) AS rms FROM (SELECT ord, any_value(v) AS v, avg(CASE WHEN {u} < (y - lo) / (hi - lo) THEN hi ELSE lo END * sigma) AS m FROM smp JOIN lv ON y >= lo AND (y < hi OR last), range({k}) r(kk) GROUP BY ord)")
    base = f"b AS (SELECT {col} AS v, ord, max(abs({col})) OVER () AS sigma FROM {source}), smp AS (SELECT *, greatest(least(v / sigma, 1), -1) AS y FROM b)"
    return sql.with_(sql.level_rows(("gauss",), (4,)), base) + "\nUNION ALL ".join(parts)


def _repeat(s: DataFrame) -> DataFrame:
    top = s.agg(F.max(F.abs("v")).alias("sigma"))
    s = s.crossJoin(F.broadcast(top))  # one row
    out = None
    for k in (1, 3, 100):
        e = F.col("v_mean") - F.col("v")
        one = quantise.repeat_codec(s, T_G4, k).agg(F.lit(k).alias("k"), F.round(F.sqrt(F.avg(e * e)), 7).alias("rms"))
        out = one if out is None else out.unionAll(one)
    return out


@query("w3_repeat_avg", _repeat_sql("(SELECT vec_id * 64 + i AS ord, embedding[(i + 1)::INT]::DOUBLE AS val FROM embeddings, range(64) r(i))", "val"))
def w3_repeat_avg(spark, d):
    """Every sample of the rows layout, coded again and again with fresh dither."""
    s = tables.vis_rows(spark, d).select("row_id", F.posexplode("vis").alias("i", "v"))
    return _repeat(s.select((F.col("row_id") * 64 + F.col("i")).alias("ord"), F.col("v").cast("double").alias("v")))


@query("w3_repeat_avg_customer", _repeat_sql("customer0", "c_acctbal").replace("FROM customer0", "FROM (SELECT c_custkey AS ord, c_acctbal FROM customer)"))
def w3_repeat_customer(spark, d):
    """The same over every customer's balance."""
    c = tables.load(spark, d, "customer", "c_custkey", "c_acctbal")
    return _repeat(c.select(F.col("c_custkey").alias("ord"), F.col("c_acctbal").alias("v")))


@query("w3_repeat_avg_events", _repeat_sql("events0", "value").replace("FROM events0", "FROM (SELECT event_id AS ord, value FROM events)"))
def w3_repeat_events(spark, d):
    e = tables.load(spark, d, "events", "event_id", "value")
    return _repeat(e.select(F.col("event_id").alias("ord"), F.col("value").alias("v")))


# Sweeps.

WB = (2, 3, 4, 5, 6, 7, 8)


def _sets(spark, d):
    return {k: sweep.stand_in(spark, d, k) for k in "ABCD"}


@query("w4_sweep_row")
def w4_row(spark, d):
    return sweep.sweep(_sets(spark, d), "row").withColumn("rms", F.round("rms", 7))


@query("w4_sweep_rf")
def w4_rf(spark, d):
    return sweep.sweep(_sets(spark, d), "row_channel").withColumn("rms", F.round("rms", 7))


@query("w4_sweep_af")
def w4_af(spark, d):
    return sweep.sweep(_sets(spark, d), "antenna_channel").withColumn("rms", F.round("rms", 7))


ALL5 = ("gauss", "t1.5", "t2.5", "t3.5", "uniform")


def _sweep_sql(scale: str) -> str:
    scaled = sql.row_scaled() if scale == "row" else sql.rf_scaled()
    return sql.with_(sql.v1(signal=0.5), scaled, sql.sampled("scaled", "smp0"), "smp AS (SELECT * FROM smp0 WHERE ant_a <> ant_b)", sql.level_rows(ALL5, WB)) + sql.table_errors(ALL5, WB)


def _sweep_set_a(spark, d, how):
    s = quantise.samples(how(scaling.masked(tables.inject_signal(v1(spark, d), 0.5)))).where("ant_a <> ant_b")
    return quantise.expected_rms_many(s, WB).withColumn("rms", F.round("rms", 8))


@query("w4_sweep_row_set_a", _sweep_sql("row"))
def w4_row_a(spark, d):
    """All tables and bit-rates of one set in one pass, against joins with level intervals."""
    return _sweep_set_a(spark, d, scaling.scale_row)


@query("w4_sweep_rf_set_a", _sweep_sql("rf"))
def w4_rf_a(spark, d):
    return _sweep_set_a(spark, d, scaling.scale_row_channel)


def _uniform_by_bits(bits: tuple[int, ...]) -> str:
    one = lambda b: f"SELECT {b}::INT AS bits, sqrt(avg((y - below) * (above - y) * sigma * sigma)) AS rms FROM p{b}"
    return sql.with_(sql.v1(), sql.rf_scaled(), sql.sampled(), *(sql.uniform_pos(b, name=f"p{b}") for b in bits), "res AS (" + " UNION ALL ".join(map(one, bits)) + ")")


def _uniform_results(spark, d, bits):
    s = quantise.samples(scaling.scale_row_channel(scaling.masked(v1(spark, d))))
    return quantise.expected_rms_many(s, bits, ("uniform",))


@query("bit_ratio", _uniform_by_bits((8, 16)) + "SELECT 'uniform' AS quantiser, round(max(rms) FILTER (bits = 8) / max(rms) FILTER (bits = 16), 4) AS ratio FROM res")
def bit_ratio(spark, d):
    """M6: theory for equal steps is 258.0."""
    return measures.bit_ratio(_uniform_results(spark, d, (8, 16)), "quantiser").withColumn("ratio", F.round("ratio", 4))


@query("bit_slope", _uniform_by_bits(WB) + "SELECT bits, round(rms / lead(rms) OVER (ORDER BY bits), 5) AS step FROM res QUALIFY lead(rms) OVER (ORDER BY bits) IS NOT NULL")
def bit_slope(spark, d):
    return measures.bit_slope(_uniform_results(spark, d, WB), "quantiser").select("bits", F.round("step", 5).alias("step"))


MIN_BITS = (*WB, 9, 10, 11, 12)


@query("w7_min_bits", _uniform_by_bits(MIN_BITS) + ", v AS (SELECT sqrt(avg((x.im * x.im + x.re * x.re) / 2)) AS ref FROM (SELECT (max(im) FILTER (pol = 1) - max(im) FILTER (pol = 2)) / 2 AS re, (max(re) FILTER (pol = 2) - max(re) FILTER (pol = 1)) / 2 AS im FROM cells WHERE ant_a <> ant_b GROUP BY row_id, ch) x)\nSELECT 'B' AS set, rule, min(bits)::INT AS bits FROM res, v, (VALUES ('diff<10%', 0.1::DOUBLE), ('diff<1%', 0.01::DOUBLE)) r(rule, lim) WHERE rms < lim * ref GROUP BY rule")
def w7_min_bits(spark, d):
    """M8 on the noise set in samples: the fewest bits whose expected error stays under a share of the Stokes V noise."""
    r = _uniform_results(spark, d, MIN_BITS).withColumn("set", F.lit("B"))
    return measures.min_bits(r, sweep.references({"B": v1(spark, d)}), {"diff<10%": 0.1, "diff<1%": 0.01}).select("set", "rule", F.col("bits").cast("int").alias("bits"))


# W4, W5, W7 in images: each set goes its whole way in all variants.


def _images(scaling_: str, labels=ALL5, bits=sweep.BITS, clean: bool = False):
    def run(spark, d):
        r = sweep.image_sweep(_sets(spark, d), scaling_, labels, bits, clean)
        return r.select("set", "scaling", "quantiser", "bits", *(F.round(c, 9).alias(c) for c in r.columns[4:]))

    return run


query("w4_image_sweep_row")(_images("row"))
query("w4_image_sweep_rf")(_images("row_channel"))
query("w4_image_sweep_af")(_images("antenna_channel"))


def _image_sql(scale: str, bits: tuple[int, ...] = WB) -> str:
    """Set C, which goes straight from the codec to the image, in SQL."""
    gain = "((0.5::DOUBLE + 1.5::DOUBLE * ant_a / 7.0::DOUBLE) * (0.5::DOUBLE + 1.5::DOUBLE * ant_b / 7.0::DOUBLE) * (1.0::DOUBLE + 0.2::DOUBLE * ch))"
    flat = f"flat AS (SELECT * EXCLUDE (re, im), re / {gain} AS re, im / {gain} AS im FROM cells)"
    u = sql.uniform_sql("ord", 0)
    coded = f"""coded AS (SELECT quantiser, bits, block_id, row_id, ant_a, ant_b, ch, pol, part, CASE WHEN {u} < (y - lo) / (hi - lo) THEN hi ELSE lo END * sigma AS v FROM smp JOIN lv ON y >= lo AND (y < hi OR last)
  UNION ALL SELECT 'none', 0, block_id, row_id, ant_a, ant_b, ch, pol, part, v FROM smp)"""
    pick = lambda pol, part: f"max(v) FILTER (pol = {pol} AND part = {part})"
    sti = f"sti AS (SELECT quantiser, bits, block_id, row_id, ch, any_value(ant_a) AS ant_a, any_value(ant_b) AS ant_b, ({pick(0, 0)} + {pick(3, 0)}) / 2 AS i_re, ({pick(0, 1)} + {pick(3, 1)}) / 2 AS i_im FROM coded WHERE ant_a <> ant_b GROUP BY quantiser, bits, block_id, row_id, ch)"
    grid = f"grid AS (SELECT quantiser, bits, floor({UVX} + 0.5)::INT AS gu, floor({UVY} + 0.5)::INT AS gv, avg(i_re) AS re, avg(i_im) AS im FROM sti GROUP BY ALL)"
    phase = f"2 * pi() / {NPIX} * (gu * l + gv * m)"
    img = f"img AS (SELECT quantiser, bits, l, m, avg(re * cos({phase}) - im * sin({phase})) AS value FROM grid, (SELECT a - {NPIX // 2} AS l, b - {NPIX // 2} AS m FROM range({NPIX}) x(a), range({NPIX}) y(b)) GROUP BY ALL)"
    scaled = sql.row_scaled("flat") if scale == "row" else sql.rf_scaled("flat")
    return sql.with_(sql.v1(signal=2.0), flat, scaled, sql.sampled(), sql.level_rows(ALL5, bits), coded, sti, grid, img) + "SELECT i.quantiser, i.bits::INT AS bits, round(sqrt(avg((i.value - p.value) * (i.value - p.value))), 8) AS diff_rms FROM img i JOIN img p ON p.quantiser = 'none' AND i.l = p.l AND i.m = p.m WHERE i.quantiser <> 'none' GROUP BY ALL"


def _image_c(scaling_: str):
    def run(spark, d):
        r = sweep.image_sweep({"C": sweep.stand_in(spark, d, "C")}, scaling_, ALL5, WB)
        return r.select("quantiser", "bits", F.round("diff_rms", 8).alias("diff_rms"))

    return run


@query("w7_min_bits_all_sets")
def w7_all(spark, d):
    """M8: the four rules in images, for the antenna method with the 2.5 sigma table."""
    return sweep.minimum_bits(sweep.image_sweep(_sets(spark, d), "antenna_channel", ("t2.5",), tuple(range(2, 17)), True))


# Tables of errors by set, scaling and level table.

#: Sets of the errors below: the samples with these signals in the parallel hands.
ERR_SETS = {"A": 0.5, "B": 0.2, "C": 2.0, "D": 0.0}
ERR_SETS_SQL = ", ".join(f"({i}, '{k}', {v}::DOUBLE)" for i, (k, v) in enumerate(ERR_SETS.items()))
#: Blocks of a set are numbered from a multiple of this on, so that one chain of SQL scales all sets.
ERR_STEP = 1 << 32


def _errors_sql() -> str:
    sets = f"cells AS (SELECT * REPLACE (block_id + j * {ERR_STEP} AS block_id, re + CASE WHEN pol IN (0, 3) THEN signal * {sql.G.replace('(k // 4)', 'ch').replace(' a ', ' ant_a ').replace(' b ', ' ant_b ')} ELSE 0 END AS re) FROM plain, (VALUES {ERR_SETS_SQL}) s(j, name, signal))"
    parts = "samples_of AS (" + " UNION ALL ".join(f"SELECT '{k}' AS scaling, block_id // {ERR_STEP} AS j, y, sigma FROM {t} WHERE ant_a <> ant_b" for k, t in (("AF", "smp_af"), ("RF", "smp_rf"), ("row", "smp_row"))) + ")"
    t2 = "t2 AS (SELECT name AS set, scaling, quantiser, sqrt(avg((y - lo) * (hi - y) * sigma * sigma)) AS err FROM samples_of JOIN lv ON y >= lo AND (y < hi OR last) JOIN (VALUES " + ERR_SETS_SQL + ") s(j, name, signal) USING (j) GROUP BY ALL)"
    return sql.with_(sql.v1(name="plain"), sets, *af_scaled(2), sql.sampled("g2", "smp_af"), sql.rf_scaled("cells", "by_rf"), sql.sampled("by_rf", "smp_rf"), sql.row_scaled("cells", "by_row"), sql.sampled("by_row", "smp_row"), sql.level_rows(ALL5, (8,)), parts, t2)


def errors(spark: SparkSession, d: str) -> DataFrame:
    """set, scaling, quantiser, err: expected 8-bit errors of the sets by table and scaling, AF in closed form (on complete blocks, as it is defined)."""
    scalings = {"AF": af_exact, "RF": lambda c: scaling.scale_row_channel(scaling.masked(c)), "row": lambda c: scaling.scale_row(scaling.masked(c))}
    out = None
    for name, signal in ERR_SETS.items():
        cells = tables.inject_signal(v1(spark, d), signal)
        for k, how in scalings.items():
            s = quantise.samples(how(cells)).where("ant_a <> ant_b")
            one = quantise.expected_rms_many(s, (8,)).select(F.lit(name).alias("set"), F.lit(k).alias("scaling"), "quantiser", F.col("rms").alias("err"))
            out = one if out is None else out.unionAll(one)
    return out


BAL = "bal AS (SELECT *, err / avg(err) OVER (PARTITION BY set) * (SELECT avg(m) FROM (SELECT avg(err) AS m FROM t2 GROUP BY set)) AS x FROM t2)"


@query("w10_balanced_avg", _errors_sql().rstrip() + ",\n" + BAL + "\nSELECT scaling, quantiser, round(avg(x), 8) AS avg, round(2 * stddev_samp(x) / sqrt(count(*)), 8) AS ci2 FROM bal GROUP BY ALL")
def w10(spark, d):
    return measures.balanced_mean(errors(spark, d), "scaling", "quantiser").select("scaling", "quantiser", F.round("avg", 8).alias("avg"), F.round("ci2", 8).alias("ci2"))


@query("w10_by_scaling", _errors_sql().rstrip() + ",\n" + BAL + "\nSELECT scaling, round(avg(x), 8) AS avg FROM bal GROUP BY ALL")
def w10_scaling(spark, d):
    return measures.balanced_mean(errors(spark, d), "scaling").select("scaling", F.round("avg", 8).alias("avg"))


@query("w10_by_quantiser", _errors_sql().rstrip() + ",\n" + BAL + "\nSELECT quantiser, round(avg(x), 8) AS avg FROM bal GROUP BY ALL")
def w10_quantiser(spark, d):
    return measures.balanced_mean(errors(spark, d), "quantiser").select("quantiser", F.round("avg", 8).alias("avg"))


@query("w10_plain_ci", _errors_sql() + "SELECT set, round(avg(err), 8) AS avg, round(2 * stddev_samp(err) / sqrt(count(*)), 8) AS ci2 FROM t2 GROUP BY ALL")
def w10_ci(spark, d):
    return measures.ci2(errors(spark, d), "set").select("set", F.round("avg", 8).alias("avg"), F.round("ci2", 8).alias("ci2"))


@query("w11_gain", _errors_sql().rstrip() + ",\n" + BAL + ",\nb2 AS (SELECT scaling, quantiser, avg(x) AS err FROM bal GROUP BY ALL)\nSELECT scaling, round(max(err) FILTER (quantiser = 'uniform') / min(err), 6) AS ratio, arg_min(quantiser, err) AS best FROM b2 GROUP BY ALL")
def w11_gain(spark, d):
    """Uniform levels over the best table."""
    r = measures.balanced_mean(errors(spark, d), "scaling", "quantiser").withColumnRenamed("avg", "err")
    return baselines.nonlinear_gain(r).withColumn("ratio", F.round("ratio", 6))


# Images.

NPIX = 16
UVX = "(((ant_b * 29) % 97 - (ant_a * 29) % 97) / 10.0::DOUBLE)"
UVY = "(((ant_b * 53) % 89 - (ant_a * 53) % 89) / 10.0::DOUBLE)"
VI = f"sti AS (SELECT block_id, row_id, ch, any_value(ant_a) AS ant_a, any_value(ant_b) AS ant_b, (max(re) FILTER (pol = 0) + max(re) FILTER (pol = 3)) / 2 AS i_re, (max(im) FILTER (pol = 0) + max(im) FILTER (pol = 3)) / 2 AS i_im, (max(im) FILTER (pol = 1) - max(im) FILTER (pol = 2)) / 2 AS v_re, (max(re) FILTER (pol = 2) - max(re) FILTER (pol = 1)) / 2 AS v_im FROM cells GROUP BY block_id, row_id, ch)"
GRID = f"grid AS (SELECT floor({UVX} + 0.5)::INT AS gu, floor({UVY} + 0.5)::INT AS gv, avg(i_re) AS re, avg(i_im) AS im, 1.0::DOUBLE AS w FROM sti WHERE ant_a <> ant_b GROUP BY 1, 2)"
IMG = f"img AS (SELECT l, m, sum(w * (re * cos(2 * pi() / {NPIX} * (gu * l + gv * m)) - im * sin(2 * pi() / {NPIX} * (gu * l + gv * m)))) / sum(w) AS value FROM grid, (SELECT a - {NPIX // 2} AS l, b - {NPIX // 2} AS m FROM range({NPIX}) x(a), range({NPIX}) y(b)) GROUP BY l, m)"


query("w4_image_sweep_row_set_c", _image_sql("row"))(_image_c("row"))
query("w4_image_sweep_rf_set_c", _image_sql("rf"))(_image_c("row_channel"))


def _image(cells: DataFrame, product: str = "i") -> DataFrame:
    s = calibrate.stokes(cells).where("ant_a <> ant_b")
    return imaging.dirty_image(imaging.uv_grid(s, f"{product}_re", f"{product}_im"), NPIX)


@query("uv_grid", sql.with_(sql.v1(signal=0.5), VI, GRID) + "SELECT gu, gv, round(re, 8) AS re, round(im, 8) AS im FROM grid")
def uv_grid(spark, d):
    s = calibrate.stokes(tables.inject_signal(v1(spark, d), 0.5)).where("ant_a <> ant_b")
    return imaging.uv_grid(s, "i_re", "i_im").select("gu", "gv", F.round("re", 8).alias("re"), F.round("im", 8).alias("im"))


@query("dirty_image", sql.with_(sql.v1(signal=0.5), VI, GRID, IMG) + "SELECT l::INT AS l, m::INT AS m, round(value, 8) AS value FROM img")
def dirty_image(spark, d):
    return _image(tables.inject_signal(v1(spark, d), 0.5)).withColumn("value", F.round("value", 8))


@query("dirty_image_natural")
def dirty_natural(spark, d):
    s = calibrate.stokes(tables.inject_signal(v1(spark, d), 0.5)).where("ant_a <> ant_b")
    return imaging.dirty_image(imaging.uv_grid(s, "i_re", "i_im", weighting="natural"), NPIX).withColumn("value", F.round("value", 8))


@query("stokes_v_rms", sql.with_(sql.v1(), VI) + "SELECT round(sqrt(avg((v_re * v_re + v_im * v_im) / 2)), 8) AS rms FROM sti WHERE ant_a <> ant_b")
def stokes_v_rms(spark, d):
    """M3: the system noise."""
    return sweep.references({"B": v1(spark, d)}).select(F.round("ref", 8).alias("rms"))


@query("dynamic_spectrum", sql.with_(sql.v1()) + "SELECT block_id, ch, round(avg(sqrt(re * re + im * im)), 8) AS amplitude FROM cells WHERE pol = 0 GROUP BY ALL")
def dynamic_spectrum(spark, d):
    return calibrate.dynamic_spectrum(v1(spark, d)).withColumn("amplitude", F.round("amplitude", 8))


def _restored(spark, d, cfg: CodecConfig, signal: float = 0.5) -> tuple[DataFrame, DataFrame]:
    cells = tables.inject_signal(v1(spark, d), signal)
    return cells, codec.as_cells(codec.decompress(codec.compress(cells, cfg)))


@query("image_diff_rms")
def image_diff_rms(spark, d):
    """M1: rms of the difference of dirty images by bit-rate."""
    out = None
    for b in (3, 4, 6, 8):
        before, after = _restored(spark, d, CodecConfig(scaling="antenna_channel", bits=b))
        one = measures.diff_rms(_image(before), _image(after)).select(F.lit(b).alias("bits"), F.round("rms", 10).alias("rms"))
        out = one if out is None else out.unionAll(one)
    return out


for _name, _scaling in (("w5_noise_change", "antenna_channel"), ("w5_noise_change_rf", "row_channel"), ("w5_noise_change_row", "row")):

    @query(_name)
    def w5(spark, d, how=_scaling):
        """M2: relative change of the cleaned noise, by set, table and bit-rate."""
        r = sweep.image_sweep(_sets(spark, d), how, ALL5, (2, 3, 4, 6, 8), True)
        return r.select("set", "scaling", "quantiser", "bits", F.round(F.col("noise") / F.col("noise_ref") - 1, 8).alias("rel_change"))


@query("clean_image")
def clean_image(spark, d):
    """Components of the image with a source at its centre."""
    cells = tables.inject_signal(v1(spark, d), 2.0)
    s = calibrate.stokes(cells).where("ant_a <> ant_b")
    grid = imaging.uv_grid(s, "i_re", "i_im")
    _, parts = imaging.clean(imaging.image_array(imaging.dirty_image(grid, NPIX), NPIX), imaging.image_array(imaging.beam(grid, NPIX), NPIX), 0.1, 50)
    return spark.createDataFrame([(i, *p) for i, p in enumerate(parts)], "step int, l int, m int, flux double").withColumn("flux", F.round("flux", 8))


@query("box_rms", sql.with_(sql.v1(signal=0.5), VI, GRID, IMG) + "SELECT round(sqrt(avg(value * value)), 8) AS rms FROM img WHERE l BETWEEN -8 AND -5 AND m BETWEEN -8 AND -5")
def box_rms(spark, d):
    return imaging.box_rms(_image(tables.inject_signal(v1(spark, d), 0.5)), -8, -5, -8, -5).withColumn("rms", F.round("rms", 8))


def _structure(bits: int, signal: float = 0.5):
    def run(spark, d):
        s = quantise.samples(scaling.scale_row(scaling.masked(tables.inject_signal(v1(spark, d), signal))))
        cfg = U8.but(bits=bits)
        e = quantise.decode(quantise.encode(s, cfg), cfg).withColumn("value", F.col("v_hat") - F.col("v"))
        r = measures.structure_stats(e, "value", "v")
        return r.select(*(F.round(c, 5).alias(c) for c in ("mean", "skewness", "kurtosis", "corr")))

    return run


def _structure_sql(bits: int) -> str:
    return sql.with_(sql.v1(signal=0.5), sql.row_scaled(), sql.sampled(), sql.uniform_coded(bits), "e AS (SELECT v_hat - v AS value, v FROM coded)") + "SELECT round(avg(value), 5) AS mean, round((SELECT avg(power(value - a, 3)) / power(avg(power(value - a, 2)), 1.5) FROM e, (SELECT avg(value) AS a FROM e)), 5) AS skewness, round((SELECT avg(power(value - a, 4)) / power(avg(power(value - a, 2)), 2) - 3 FROM e, (SELECT avg(value) AS a FROM e)), 5) AS kurtosis, round(corr(value, v), 5) AS corr FROM e"


query("w6_sample_stats_8", _structure_sql(8))(_structure(8))
query("w6_sample_stats_2", _structure_sql(2))(_structure(2))


def _difference(bits: int):
    def run(spark, d):
        """M12 in the image of set A, antenna scaling with the 2.5 sigma table: shape of the difference, its correlation with the
        image, its value at the source in units of its rms, and what its rms is in single blocks over what it is in all."""
        cells, cfg = sweep.stand_in(spark, d, "A"), CodecConfig(bits=bits)
        whole, single = sweep.difference_images(cells, "A", cfg), sweep.difference_images(cells, "A", cfg, "block")
        stats = whole.agg(F.sqrt(F.avg(F.col("diff") ** 2)).alias("rms"), F.avg("diff").alias("mean"), F.skewness("diff").alias("skewness"), F.kurtosis("diff").alias("kurtosis"), F.corr("diff", "plain").alias("corr"), F.max(F.when((F.col("l") == 0) & (F.col("m") == 0), F.col("diff"))).alias("at_source"))
        blocks = single.agg(F.sqrt(F.avg(F.col("diff") ** 2)).alias("rms_block"), F.countDistinct("block").alias("n_blocks"))
        r = stats.crossJoin(blocks).withColumn("at_source", F.abs("at_source") / F.col("rms")).withColumn("gain_by_time", F.col("rms_block") / F.col("rms"))  # single rows
        return r.select(*(F.round(c, 6).alias(c) for c in ("rms", "mean", "skewness", "kurtosis", "corr", "at_source", "gain_by_time")), "n_blocks")

    return run


query("w6_diff_stats_8")(_difference(8))
query("w6_diff_stats_2")(_difference(2))


# Volume.

def _volume_sql(cells: str, bits: tuple[int, ...]) -> str:
    """From the counts of each block: payloads and masks on its grid of rows and channels, a factor for each of both, 12-bit weights."""
    data = "(SELECT sum(ceil(r * k * 2 * b / 8.0::DOUBLE) + CASE WHEN n < r * k THEN ceil(r * k / 8.0::DOUBLE) ELSE 0 END + 4 * (r + k)) FROM g)"
    g = "g AS (SELECT block_id, pol, count(DISTINCT row_id) AS r, count(DISTINCT ch) AS k, count(*) AS n FROM cells GROUP BY ALL)"
    w = "w AS (SELECT sum(ceil(r * k * 12 / 8.0::DOUBLE) + 4 * r) AS w FROM (SELECT block_id, count(DISTINCT row_id) AS r, count(DISTINCT ch) AS k FROM cells GROUP BY ALL))"
    t = "t AS (SELECT count(*) AS n, count(DISTINCT (block_id, row_id)) AS rows FROM cells)"
    return sql.with_(cells, g, w, t) + f"""SELECT b::INT AS bits, component, raw_bytes::BIGINT AS raw_bytes, packed_bytes::BIGINT AS packed_bytes, round(packed_bytes / (n * 12 + rows * 16), 8) AS packed_share
FROM (SELECT unnest({list(bits)}) AS b) x, t, w, LATERAL (VALUES ('data', n * 8, {data}), ('weights', n * 4, w.w), ('metadata', rows * 16, rows * 16)) c(component, raw_bytes, packed_bytes)"""


def _volume(cells: DataFrame, bits: tuple[int, ...]) -> DataFrame:
    out = None
    for b in bits:
        packed = codec.compress(cells, CodecConfig(scaling="row_channel", autos="keep", bits=b))
        r = measures.volume_report(packed, weights.pack(cells), cells).select(F.lit(b).alias("bits"), "component", "raw_bytes", "packed_bytes", F.round("packed_share", 8).alias("packed_share"))
        out = r if out is None else out.unionAll(r)
    return out


VOLUME_BITS = (2, 3, 4, 5, 6, 8, 10, 12, 16)


@query("w8_volume", _volume_sql(sql.v1(), VOLUME_BITS))
def w8(spark, d):
    """Bytes that are stored, by component and bit-rate; scale factors count as samples."""
    return _volume(v1(spark, d), VOLUME_BITS)


@query("w8_volume_v2", _volume_sql(sql.V2, (6,)))
def w8_v2(spark, d):
    return _volume(tables.vis_lineitem(spark, d), (6,))


@query("weights_in_store", sql.with_(sql.V2, "w AS (SELECT block_id, row_id, ch, max(weight) AS w FROM cells GROUP BY ALL)", "m AS (SELECT *, max(w) OVER (PARTITION BY block_id, row_id) AS top FROM w)", "h AS (SELECT *, floor(w / top * 4095) * top / 4095 AS hat FROM m)") + "SELECT c.block_id, count(*) AS n, round(sum(hat), 6) AS weight, round(max(abs(hat - w) / top), 8) AS worst FROM cells c JOIN h USING (block_id, row_id, ch) GROUP BY ALL")
def weights_in_store(spark, d):
    """Weights that come back from a store with the samples: one for all polarisations, 12 bits against the row's largest."""
    cells, path = tables.vis_lineitem(spark, d), store.shared_dir(spark, "observation")
    store.write_observation(cells, path, CodecConfig(scaling="row_channel", autos="keep", bits=6), 16)
    w = cells.groupBy("block_id", "row_id", "ch").agg(F.max("weight").alias("w"))
    w = w.join(w.groupBy("block_id", "row_id").agg(F.max("w").alias("top")), ["block_id", "row_id"])
    back = store.read_observation(spark, path).join(w, ["block_id", "row_id", "ch"])
    return back.groupBy("block_id").agg(F.count("*").alias("n"), F.round(F.sum("weight"), 6).alias("weight"), F.round(F.max(F.abs(F.col("weight") - F.col("w")) / F.col("top")), 8).alias("worst"))


@query("w8_bzip2")
def w8_bz2(spark, d):
    """Data hardly shrink without loss, weights nearly vanish."""
    j = tables.vis_rows(spark, d).join(tables.load(spark, d, "labels", "doc_id", "quality"), F.col("row_id") == F.col("doc_id"), "left")
    c = tables.cells_of(j.select("block_id", "row_id", "ant_a", "ant_b", "vis", "quality").drop("quality")).select("re", "weight", "ant_a")
    return weights.bz2_sizes(c, {"re": "f4", "weight": "f4", "ant_a": "i4"})


@query("bz2_text_bytes")
def bz2_text(spark, d):
    """B4 on text columns."""
    return weights.bz2_sizes(tables.load(spark, d, "documents", "text"), {"text": "bytes"}).unionAll(weights.bz2_sizes(tables.load(spark, d, "pages", "html"), {"html": "bytes"}))


@query("packed_bytes_ratio", "SELECT b::INT AS bits, round(4.0::DOUBLE * sum(len(embedding)) / sum(ceil(len(embedding) * b / 8.0::DOUBLE)), 6) AS ratio FROM embeddings, (VALUES (2), (4), (5), (6), (8), (10)) r(b) GROUP BY ALL")
def packed_ratio(spark, d):
    """M9: bytes of all samples as they come, in 32 bits, over those of their packed rows."""
    out = None
    for b in (2, 4, 5, 6, 8, 10):
        one = codec.compress_rows(tables.vis_rows(spark, d).where("vis is not null"), b).agg(F.lit(b).alias("bits"), F.round(4 * F.sum("n") / F.sum(F.octet_length("payload")), 6).alias("ratio"))
        out = one if out is None else out.unionAll(one)
    return out


def _metadata_sql() -> str:
    """From the counts of each block: a factor for each row; for each row and channel of a polarisation; for each antenna and channel of one."""
    g = "g AS (SELECT block_id, pol, count(DISTINCT row_id) AS r, count(DISTINCT ch) AS k FROM cells GROUP BY ALL)"
    a = "a AS (SELECT block_id, pol, count(DISTINCT ant) AS a FROM (SELECT block_id, pol, unnest([ant_a, ant_b]) AS ant FROM cells) GROUP BY ALL)"
    f = "f AS (SELECT sum(ceil(r * k * 2 * 8 / 8.0::DOUBLE)) AS payload, sum(r + k) AS rk, sum(a + k) AS ak FROM g JOIN a USING (block_id, pol))"
    return sql.with_(sql.v1(), g, a, f) + "SELECT scaling, round(4.0::DOUBLE * n / payload, 8) AS share FROM f, LATERAL (VALUES ('row', (SELECT count(DISTINCT (block_id, row_id)) FROM cells)), ('row_channel', rk), ('antenna_channel', ak)) t(scaling, n)"


@query("metadata_share", _metadata_sql())
def metadata_share(spark, d):
    """Factor bytes over payload bytes at 8 bits, of all blocks as they are packed."""
    out = None
    for s in ("row", "row_channel", "antenna_channel"):
        one = measures.packed_metadata_share(codec.compress(v1(spark, d), CodecConfig(scaling=s))).select(F.lit(s).alias("scaling"), F.round("share", 8).alias("share"))
        out = one if out is None else out.unionAll(one)
    return out


@query("bias_by_repeat", sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(3, 11)) + "SELECT round(avg(v_hat - v), 7) AS bias, count(*) AS n FROM coded")
def bias(spark, d):
    """M11."""
    cfg = U8.but(bits=3, seed=11)
    return quantise.decode(quantise.encode(row_samples(spark, d), cfg), cfg).agg(F.round(F.avg(F.col("v_hat") - F.col("v")), 7).alias("bias"), F.count("*").alias("n"))


@query("dynamic_range_loss", sql.with_(*(sql.v1(), sql.rfi(), sql.row_scaled("hit"), sql.sampled(), *(sql.uniform_coded(b, name=f"c{b}") for b in (8, 12, 16)))) + " UNION ALL ".join(f"SELECT {b}::INT AS bits, round(avg(CASE WHEN sym = {zero_symbol(b)} THEN 1.0::DOUBLE ELSE 0 END), 8) AS share_zero FROM c{b} WHERE v <> 0" for b in (8, 12, 16)))
def dynamic_range(spark, d):
    """What interference pushes under the first level."""
    s = quantise.samples(scaling.scale_row(scaling.masked(tables.inject_rfi(v1(spark, d)))))
    out = None
    for b in (8, 12, 16):
        one = measures.zeroed_fraction(quantise.encode(s, U8.but(bits=b)), zero_symbol(b)).select(F.lit(b).alias("bits"), F.round("share_zero", 8).alias("share_zero"))
        out = one if out is None else out.unionAll(one)
    return out


# Weights.

def _weights(spark, d) -> DataFrame:
    li = tables.load(spark, d, "lineitem", "l_orderkey", "l_suppkey", "l_tax", "l_quantity")
    return li.select(F.col("l_suppkey").alias("block_id"), F.col("l_orderkey").alias("row_id"), F.col("l_tax").alias("weight"), F.col("l_quantity").alias("re"))


@query("weights_collapse", sql.with_(sql.v1(), "x AS (SELECT row_id, ch, pol, (CASE WHEN pol = 3 AND row_id % 50 = 0 THEN 2.0 ELSE 1.0 END)::DOUBLE AS w FROM cells)", "g AS (SELECT row_id, ch, max(w) AS weight, count(*) AS n_pol, min(w) = max(w) AS equal FROM x GROUP BY ALL)") + "SELECT equal, count(*) AS n, sum(n_pol)::BIGINT AS n_in FROM g GROUP BY ALL")
def weights_collapse(spark, d):
    """G1: four weights to one, and where they weren't the same."""
    c = v1(spark, d).withColumn("weight", F.when((F.col("pol") == 3) & (F.col("row_id") % 50 == 0), 2.0).otherwise(1.0))
    return weights.collapse(c).groupBy("equal").agg(F.count("*").alias("n"), F.sum("n_pol").alias("n_in"))


WQ = "q AS (SELECT *, floor(coalesce(weight / nullif(row_max, 0), 0) * 4095)::INT AS sym FROM (SELECT l_suppkey AS block_id, l_orderkey AS row_id, l_tax AS weight, l_quantity AS re, max(l_tax) OVER (PARTITION BY l_suppkey, l_orderkey) AS row_max FROM lineitem)), qq AS (SELECT *, sym * row_max / 4095 AS weight_hat FROM q)"


@query("weights_12bit", sql.with_(WQ) + "SELECT block_id, sum(sym)::BIGINT AS total, round(max(weight - weight_hat), 8) AS worst FROM qq GROUP BY ALL")
def weights_12bit(spark, d):
    """G2."""
    q = weights.quantise_weights(_weights(spark, d))
    return q.groupBy("block_id").agg(F.sum("sym").alias("total"), F.round(F.max(F.col("weight") - F.col("weight_hat")), 8).alias("worst"))


@query("weighted_mean_shift", sql.with_(WQ) + "SELECT block_id, round(sum(weight * re) / nullif(sum(weight), 0), 6) AS before, round(sum(weight_hat * re) / nullif(sum(weight_hat), 0), 6) AS after FROM qq GROUP BY ALL")
def weighted_mean_shift(spark, d):
    """Truncated weights shift no mean beyond their precision."""
    return weights.weighted_mean_shift(weights.quantise_weights(_weights(spark, d)), "re", "block_id").select("block_id", F.round("before", 6).alias("before"), F.round("after", 6).alias("after"))


@query("weight_row_mode", "SELECT l_suppkey AS block_id, l_orderkey AS row_id, round(avg(l_tax), 8) AS weight_hat, count(*) AS n FROM lineitem GROUP BY ALL")
def weight_row_mode(spark, d):
    """G5."""
    return weights.quantise_weights(_weights(spark, d), mode="row").withColumn("weight_hat", F.round("weight_hat", 8))


@query("weight_ratio", sql.with_(sql.V2, "g AS (SELECT block_id, count(DISTINCT row_id) AS r, count(DISTINCT ch) AS k, count(*) AS n FROM cells GROUP BY ALL)") + "SELECT round(4.0::DOUBLE * sum(n) / sum(ceil(r * k * 12 / 8.0::DOUBLE)), 6) AS ratio FROM g")
def weight_ratio(spark, d):
    """Bytes of all weights as they come, in 32 bits, over those of their packed codes; 128 / 12 where no row misses a polarisation or channel."""
    cells = tables.vis_lineitem(spark, d)
    packed = weights.pack(cells).agg(F.sum(F.octet_length("payload")).alias("bytes"))
    return cells.agg(F.count("*").alias("n")).crossJoin(packed).select(F.round(4 * F.col("n") / F.col("bytes"), 6).alias("ratio"))  # single rows


@query("weights_labels", "SELECT quality::BIGINT AS w, count(*) AS n, min(floor(quality / 1.0::DOUBLE * 4095))::BIGINT AS sym FROM labels GROUP BY ALL")
def weights_labels(spark, d):
    lab = tables.load(spark, d, "labels", "quality")
    return lab.groupBy(F.col("quality").cast("long").alias("w")).agg(F.count("*").alias("n"), F.min(weights.code(F.col("quality").cast("double"), F.lit(1.0))).cast("long").alias("sym"))


# Other baselines.

MR = "CASE WHEN value = 0 THEN 0 ELSE floor(value / power(2, floor(log2(abs(value))) - {m}) + 0.5) * power(2, floor(log2(abs(value))) - {m}) END"


@query("mantissa_round", " UNION ALL ".join(f"SELECT {m}::INT AS bits, round(max(abs({MR.format(m=m)} - value) / nullif(abs(value), 0)), 8) AS worst, round(sqrt(avg(power({MR.format(m=m)} - value, 2))), 7) AS rmse, count(DISTINCT {MR.format(m=m)}) AS n_distinct FROM events" for m in (3, 6)))
def mantissa_round(spark, d):
    """B2."""
    e = tables.load(spark, d, "events", "value")
    out = None
    for m in (3, 6):
        r = e.withColumn("r", baselines.mantissa_round(F.col("value"), m))
        one = r.agg(F.lit(m).alias("bits"), F.round(F.max(F.abs(F.col("r") - F.col("value")) / F.nullif(F.abs("value"), F.lit(0.0))), 8).alias("worst"), F.round(F.sqrt(F.avg((F.col("r") - F.col("value")) ** 2)), 7).alias("rmse"), F.countDistinct("r").alias("n_distinct"))
        out = one if out is None else out.unionAll(one)
    return out


@query("mantissa_backends")
def mantissa_backends(spark, d):
    """B2': symbols of a 6-bit row codec under three lossless back ends."""
    coded = quantise.encode(row_samples(spark, d), U8.but(bits=6))
    out = None
    for b in ("rice", "deflate", "bz2"):
        one = baselines.backend_size(coded, 6, b).select(F.lit(b).alias("backend"), "n", "bytes")
        out = one if out is None else out.unionAll(one)
    return out


@query("mantissa_dithered", f"SELECT round(avg(r - value), 6) AS bias, round(sqrt(avg((r - value) * (r - value))), 6) AS rmse FROM (SELECT value, (floor(value / step + u) - u + 0.5) * step AS r FROM (SELECT value, power(2, floor(log2(abs(value))) - 4) AS step, {sql.uniform_sql('event_id', 5)} AS u FROM events WHERE value <> 0))")
def mantissa_dithered(spark, d):
    from ..functions.dither import uniform

    e = tables.load(spark, d, "events", "event_id", "value").where("value <> 0")
    r = e.withColumn("r", baselines.mantissa_dithered(F.col("value"), 4, uniform(F.col("event_id"), 5)))
    return r.agg(F.round(F.avg(F.col("r") - F.col("value")), 6).alias("bias"), F.round(F.sqrt(F.avg((F.col("r") - F.col("value")) ** 2)), 6).alias("rmse"))


@query("noise_round", sql.with_(sql.v1(), "p AS (SELECT block_id, pol, ch, re AS v FROM cells UNION ALL SELECT block_id, pol, ch, im FROM cells)", "q AS (SELECT *, sqrt(avg(v * v) OVER (PARTITION BY block_id, pol, ch)) * 0.25::DOUBLE AS step FROM p)") + "SELECT pol, round(sqrt(avg(power(floor(v / step + 0.5) * step - v, 2))), 7) AS rmse, count(DISTINCT floor(v / step + 0.5)::BIGINT) AS n_distinct FROM q GROUP BY ALL")
def noise_round(spark, d):
    """Rounding against the expected noise."""
    r = baselines.noise_round(v1(spark, d), 0.25)
    return r.groupBy("pol").agg(F.round(F.sqrt(F.avg((F.col("v_hat") - F.col("v")) ** 2)), 7).alias("rmse"), F.countDistinct("k").alias("n_distinct"))


@query("noise_round_size")
def noise_round_size(spark, d):
    """After bit transposition and LZ77."""
    return baselines.noise_round_size(baselines.noise_round(v1(spark, d), 0.25))


ENT = "SELECT total::BIGINT AS total, round(log2(total) - s / total, 7) AS entropy_bits FROM (SELECT sum(n) AS total, sum(n * log2(n)) AS s FROM h)"


@query("exponent_entropy", sql.with_(sql.v1(), "p AS (SELECT re AS v FROM cells UNION ALL SELECT im FROM cells)", "h AS (SELECT floor(log2(abs(v))) AS e, count(*) AS n FROM p WHERE v <> 0 GROUP BY ALL)") + ENT)
def exponent_entropy(spark, d):
    """B5."""
    return baselines.exponent_entropy(quantise.samples(v1(spark, d))).select("total", F.round("entropy_bits", 7).alias("entropy_bits"))


@query("symbol_entropy", sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(8), "h AS (SELECT sym, count(*) AS n FROM coded GROUP BY ALL)") + ENT)
def symbol_entropy(spark, d):
    h = quantise.encode(row_samples(spark, d), U8).groupBy("sym").agg(F.count("*").alias("n"))
    return baselines.entropy(h).select("total", F.round("entropy_bits", 7).alias("entropy_bits"))


@query("identity_rms", sql.with_(sql.v1()) + f"SELECT pol, round(sqrt(avg({sql.POWER})), 8) AS rms FROM cells GROUP BY ALL")
def identity_rms(spark, d):
    """B0."""
    return baselines.identity(v1(spark, d)).groupBy("pol").agg(F.round(F.sqrt(F.avg(scaling.power())), 8).alias("rms"))


@query("average_cells", sql.with_(sql.v1()) + "SELECT (block_id // 2)::BIGINT AS block_id, ant_a, ant_b, (ch // 4)::INT AS ch, pol, round(sum(re * weight) / sum(weight), 8) AS re, round(sum(im * weight) / sum(weight), 8) AS im, sum(weight) AS weight FROM cells GROUP BY ALL")
def average_cells(spark, d):
    """P1, B7."""
    return baselines.average_cells(v1(spark, d), 2, 4).select("block_id", "ant_a", "ant_b", "ch", "pol", F.round("re", 8).alias("re"), F.round("im", 8).alias("im"), "weight")


@query("length_average", sql.with_(sql.v1(), "k AS (SELECT *, greatest(least(power(2, floor(log2(8.0 / greatest(abs(ant_b - ant_a), 1)))), 4), 1)::INT AS k FROM cells WHERE ant_a <> ant_b)", "g AS (SELECT k, block_id // k AS b, ant_a, ant_b, ch, pol, avg(re) AS re, avg(im) AS im FROM k GROUP BY ALL)") + f"SELECT k, count(*) AS n, round(sqrt(avg({sql.POWER})), 8) AS rms FROM g GROUP BY ALL")
def length_average(spark, d):
    """B8."""
    g = baselines.average_by_length(v1(spark, d), 4)
    return g.groupBy("k").agg(F.count("*").alias("n"), F.round(F.sqrt(F.avg(scaling.power())), 8).alias("rms"))


# Calibration.


@query("gain_solve_round", sql.with_(sql.v1(signal=2.0), "x AS (SELECT block_id, ant_a AS ant, re, im FROM cells WHERE ant_a <> ant_b UNION ALL SELECT block_id, ant_b, re, -im FROM cells WHERE ant_a <> ant_b)") + "SELECT block_id, ant, round(avg(re), 7) AS re, round(avg(im), 7) AS im FROM x GROUP BY ALL")
def gain_solve_round(spark, d):
    """One round from unit gains; the solution is then the mean over an antenna's baselines."""
    c = tables.inject_signal(v1(spark, d), 2.0)
    return calibrate.gain_round(c, calibrate.unit_gains(c)).select("block_id", "ant", F.round("re", 7).alias("re"), F.round("im", 7).alias("im"))


@query("gain_solve")
def gain_solve(spark, d):
    """All rounds, in groups of one interval's baselines."""
    g = calibrate.solve_gains(tables.inject_signal(v1(spark, d), 2.0), 2.0)
    return g.select("block_id", "ant", F.round("re", 5).alias("re"), F.round("im", 5).alias("im"))


def _known_gains(spark, d) -> DataFrame:
    ants = v1(spark, d).select("block_id", F.explode(F.array("ant_a", "ant_b")).alias("ant")).distinct()
    return ants.select("block_id", "ant", tables.gain(F.col("ant")).alias("re"), (F.col("ant") * 0.01).alias("im"))


KG = "g AS (SELECT range AS ant, 0.5::DOUBLE + 1.5::DOUBLE * range / 7.0::DOUBLE AS gr, range * 0.01::DOUBLE AS gi FROM range(8))"


@query("apply_gains", sql.with_(sql.v1(), KG, "x AS (SELECT c.*, p.gr * q.gr + p.gi * q.gi AS pr, p.gi * q.gr - p.gr * q.gi AS pi FROM cells c JOIN g p ON p.ant = ant_a JOIN g q ON q.ant = ant_b)") + "SELECT ch, pol, round(sum((re * pr + im * pi) / (pr * pr + pi * pi)), 6) AS re, round(sum((im * pr - re * pi) / (pr * pr + pi * pi)), 6) AS im FROM x GROUP BY ALL")
def apply_gains(spark, d):
    """P3."""
    c = calibrate.apply_gains(v1(spark, d), _known_gains(spark, d))
    return c.groupBy("ch", "pol").agg(F.round(F.sum("re"), 6).alias("re"), F.round(F.sum("im"), 6).alias("im"))


@query("subtract_source", sql.with_(sql.v1(gains=False)) + "SELECT pol, round(sum(re - CASE WHEN pol IN (0, 3) THEN 0.25::DOUBLE ELSE 0 END), 6) AS re FROM cells GROUP BY ALL")
def subtract_source(spark, d):
    return calibrate.subtract_model(v1(spark, d, False), 0.25).groupBy("pol").agg(F.round(F.sum("re"), 6).alias("re"))


@query("transfer_gains", sql.with_(sql.v1(), "want AS (SELECT DISTINCT block_id, ant FROM (SELECT block_id, ant_a AS ant FROM cells UNION ALL SELECT block_id, ant_b FROM cells))", "have AS (SELECT block_id, ant, block_id * 100 + ant + 0.0::DOUBLE AS re FROM want WHERE block_id % 3 = 0)") + "SELECT w.block_id, w.ant, h.re FROM want w ASOF LEFT JOIN have h ON w.ant = h.ant AND w.block_id >= h.block_id")
def transfer_gains(spark, d):
    """As-of by union and window."""
    c = v1(spark, d)
    ants = c.select("block_id", F.explode(F.array("ant_a", "ant_b")).alias("ant")).distinct().where("block_id % 3 = 0")
    g = ants.select("block_id", "ant", (F.col("block_id") * 100 + F.col("ant")).cast("double").alias("re"), F.lit(0.0).alias("im"))
    return calibrate.transfer_gains(c, g).select("block_id", "ant", "re")


@query("flag_outliers", sql.with_(sql.V3, "mg AS (SELECT *, sqrt(re * re + im * im) AS mag FROM cells)", "md AS (SELECT *, quantile_cont(mag, 0.5) OVER (PARTITION BY ch) AS med FROM mg)", "dv AS (SELECT *, abs(mag - med) AS dev FROM md)", "sg AS (SELECT *, quantile_cont(dev, 0.5) OVER (PARTITION BY ch) * 1.4826::DOUBLE AS sig FROM dv)") + "SELECT ch, count(*) FILTER (dev > 5 * sig) AS n_flagged, count(*) AS n FROM sg GROUP BY ALL")
def flag_outliers(spark, d):
    """P8 with exact medians."""
    c = calibrate.flag_outliers(tables.vis_events(spark, d), 5.0, exact=True)
    return c.groupBy("ch").agg(F.count_if("flagged").alias("n_flagged"), F.count("*").alias("n"))


@query("flag_outliers_approx")
def flag_outliers_approx(spark, d):
    """P8 with mergeable sketches, the form for scale."""
    return calibrate.flag_outliers(tables.vis_events(spark, d), 5.0).groupBy("ch").agg(F.count_if("flagged").alias("n_flagged"), F.count("*").alias("n"))


@query("rotate_phase", sql.with_(sql.v1(), f"x AS (SELECT *, ({UVX} * 0.01::DOUBLE + {UVY} * 0.02::DOUBLE) * (2 * pi()) AS ph FROM cells)") + "SELECT pol, ch, round(sum(re * cos(ph) - im * sin(ph)), 6) AS re, round(sum(re * sin(ph) + im * cos(ph)), 6) AS im FROM x GROUP BY ALL")
def rotate_phase(spark, d):
    """P9."""
    c = calibrate.rotate_phase(v1(spark, d), 0.01, 0.02)
    return c.groupBy("pol", "ch").agg(F.round(F.sum("re"), 6).alias("re"), F.round(F.sum("im"), 6).alias("im"))


@query("facet_job")
def facet_job(spark, d):
    """P9 in full: change phase, average, pack again."""
    c = baselines.average_cells(calibrate.rotate_phase(v1(spark, d), 0.01, 0.02), 2, 2)
    return codec.compress(c, CodecConfig(scaling="row_channel", autos="keep", trunc=1.5)).agg(F.count("*").alias("n_blocks"), F.sum(F.octet_length("payload")).alias("bytes"))


@query("twice_compressed")
def twice_compressed(spark, d):
    """Set D's history: compress, calibrate, compress again; error of the end against the calibrated original."""
    cells, gains = v1(spark, d), _known_gains(spark, d)
    cfg = CodecConfig(bits=8)
    fix = lambda c: calibrate.apply_gains(c, gains)
    end, ref = codec.compress_twice(cells, cfg, fix), fix(cells)
    j = ref.withColumnsRenamed({"re": "r0", "im": "i0"}).join(end, ["block_id", "row_id", "ant_a", "ant_b", "ch", "pol"]).where("ant_a <> ant_b")
    return j.agg(F.round(F.sqrt(F.avg(((F.col("re") - F.col("r0")) ** 2 + (F.col("im") - F.col("i0")) ** 2) / 2)), 6).alias("rms"), F.count("*").alias("n"))


# P10, storage.

_ADVICE = """WITH e AS (SELECT event_id, (CAST(json_extract_string(props, '$.k') AS BIGINT) % 8 + 1) / 2.0::DOUBLE AS dt, value AS dnu, CASE event_type WHEN 'view' THEN 'P' WHEN 'click' THEN 'Q' WHEN 'purchase' THEN 'future' ELSE 'other' END AS arr FROM events)
SELECT event_id, dt, dnu, arr, CASE WHEN arr = 'Q' THEN CASE WHEN dt * dnu <= 20.000000001::DOUBLE THEN 'antenna_channel' WHEN dt * dnu <= 320.000000001::DOUBLE THEN 'row_channel' END WHEN arr <> 'other' THEN CASE WHEN dt * dnu <= 3.000000001::DOUBLE THEN 'antenna_channel' WHEN dt * dnu <= 144.000000001::DOUBLE THEN 'row_channel' END END AS scaling,
  (CASE WHEN arr = 'Q' THEN CASE WHEN dt * dnu <= 20.000000001::DOUBLE THEN 6 WHEN dt * dnu <= 320.000000001::DOUBLE THEN 8 END WHEN arr <> 'other' THEN CASE WHEN dt * dnu <= 3.000000001::DOUBLE THEN 5 WHEN dt * dnu <= 144.000000001::DOUBLE THEN 10 END END)::INT AS bits FROM e"""


@query("recommend_table", _ADVICE)
def recommend_table(spark, d):
    """The guideline for every event taken as an observation: half seconds by k, kHz by value, the array by the event's type."""
    dt = (F.get_json_object("props", "$.k").cast("long") % 8 + 1) / F.lit(2.0)
    arr = F.when(F.col("event_type") == "view", "P").when(F.col("event_type") == "click", "Q").when(F.col("event_type") == "purchase", "future").otherwise("other")
    e = tables.load(spark, d, "events", "event_id", "props", "value", "event_type").select("event_id", dt.alias("dt"), F.col("value").alias("dnu"), arr.alias("arr"))
    return e.withColumn("r", guideline.recommended(F.col("dt"), F.col("dnu"), F.col("arr"))).select("event_id", "dt", "dnu", "arr", "r.scaling", "r.bits")


@query("access_cost", "WITH t AS (SELECT *, (row_number() OVER (ORDER BY conv_id, turn, role, text) - 1) AS seq FROM conversations), o AS (SELECT 'time' AS o, turn AS block_id, row_number() OVER (ORDER BY turn, conv_id, role, text) AS k FROM t UNION ALL SELECT 'trace', turn, row_number() OVER (ORDER BY conv_id, turn, role, text) FROM t), l AS (SELECT o, block_id, lag(block_id) OVER (PARTITION BY o ORDER BY k) AS b FROM o) SELECT o AS access_order, count(*) FILTER (b IS NULL OR b <> block_id) AS decodes FROM l GROUP BY ALL")
def access_cost(spark, d):
    """Decodes with a cache of one block, in block order and along the trace."""
    from pyspark.sql import Window

    t = tables.load(spark, d, "conversations").select(F.col("turn").alias("block_id"), "conv_id", "turn", "role", "text")
    out = None
    for name, keys in (("time", ["turn", "conv_id", "role", "text"]), ("trace", ["conv_id", "turn", "role", "text"])):
        k = t.select("block_id", F.row_number().over(Window.orderBy(*keys)).alias("k"))
        one = store.access_cost(k, "k").select(F.lit(name).alias("access_order"), "decodes")
        out = one if out is None else out.unionAll(one)
    return out


@query("block_offsets", sql.with_(sql.v1()) + "SELECT DISTINCT block_id, (512 + block_id * 720)::BIGINT AS offset FROM cells")
def block_offsets(spark, d):
    """Header 512; 2 x 8 x 36 samples at 8 bits are 576 bytes, 16 factors 64, antennas' header words 80."""
    size = store.block_bytes(8, 8, 8, 16) + 80
    return v1(spark, d).select("block_id").distinct().select("block_id", store.block_offset(F.col("block_id"), size, 512).alias("offset"))


def _stored(spark, d, cfg=CodecConfig(scaling="row_channel", autos="keep", quantiser="uniform", trunc=None), per_bucket: int = 4) -> str:  # noqa: B008
    path = store.shared_dir(spark, "packed")
    store.write(codec.compress(v1(spark, d), cfg), path, per_bucket)
    return path


@query("block_range_read", sql.with_(sql.v1()) + "SELECT block_id, count(*) AS n, count(*) FILTER (re IS NULL) AS n_bad FROM cells WHERE block_id BETWEEN 3 AND 6 GROUP BY ALL")
def block_range_read(spark, d):
    """C4: a range of blocks from a packed store, pruned by bucket and row group."""
    from ..operators.codec import decompress

    cells = decompress(store.read(spark, _stored(spark, d), 3, 6))
    return cells.groupBy("block_id").agg(F.count("*").alias("n"), F.count_if(F.isnan("re")).alias("n_bad"))


@query("replace_block", sql.with_(sql.v1()) + "SELECT block_id, count(*) AS n, block_id = 5 AS replaced FROM cells GROUP BY ALL")
def replace_block(spark, d):
    """One block put anew, the others as they were."""
    path = _stored(spark, d)
    cfg = CodecConfig(scaling="row_channel", autos="keep", quantiser="uniform", trunc=None)
    store.replace_block(spark, path, 5, v1(spark, d).withColumns({"re": F.lit(7.0), "im": F.lit(-7.0)}), cfg)
    from ..operators.codec import decompress

    cells = decompress(store.read(spark, path))
    return cells.groupBy("block_id").agg(F.count("*").alias("n"), (F.min(F.abs(F.abs("re") - 7.0) < 1e-4)).alias("replaced"))


@query("magnitude_skip", sql.with_(sql.v1(), sql.rfi("cells", "hit", 3, 1.0), "b AS (SELECT block_id, pol, max(greatest(abs(re), abs(im))) AS m FROM cells GROUP BY ALL)") + "SELECT count(*) AS n FROM b WHERE m > 2")
def magnitude_skip(spark, d):
    """Blocks that can hold a magnitude: the filter works on the stored maximum, before any payload is read."""
    return store.read(spark, _stored(spark, d), min_abs=2.0).agg(F.count("*").alias("n"))


@query("transparent_view", sql.with_(sql.v1()) + "SELECT pol, count(*) AS n FROM cells GROUP BY ALL")
def transparent_view(spark, d):
    """SQL over a packed store."""
    store.view(spark, _stored(spark, d), "decoded_v1")
    return spark.sql("SELECT pol, count(*) AS n FROM decoded_v1 GROUP BY pol")


@query("entropy_offsets")
def entropy_offsets(spark, d):
    """Q15: with sizes that differ, an index of running sums takes the place of a fixed block size."""
    p = codec.compress(v1(spark, d), CodecConfig(scaling="row_channel", autos="keep", bits=6, entropy="rice"))
    return store.offsets(p)



@query("compress_column", "SELECT (c_custkey // 100)::BIGINT AS block, count(*) AS n, TRUE AS close FROM customer GROUP BY ALL")
def compress_column(spark, d):
    """A plain column packed and restored: every value within one level of its block's largest."""
    c = tables.load(spark, d, "customer", "c_custkey", "c_acctbal").withColumn("block", F.floor(F.col("c_custkey") / 100).cast("long"))
    back = codec.decompress_column(codec.compress_column(c, "c_acctbal", "block", "c_custkey"), "hat", "block", "c_custkey")
    top = c.groupBy("block").agg(F.max(F.abs("c_acctbal")).alias("top"))
    return c.join(back, ["block", "c_custkey"]).join(top, "block").groupBy("block").agg(F.count("*").alias("n"), F.min(F.abs(F.col("hat") - F.col("c_acctbal")) <= F.col("top") * (2 / 254 + 1e-6)).alias("close"))


@query("stream_static_volume", sql.with_(sql.V3) + "SELECT block_id, count(*) AS n_cells, (count(*) * 12)::BIGINT AS raw_bytes FROM cells GROUP BY ALL")
def stream_static_volume(spark, d):
    return tables.vis_events(spark, d).groupBy("block_id").agg(F.count("*").alias("n_cells"), (F.count("*") * 12).alias("raw_bytes"))
