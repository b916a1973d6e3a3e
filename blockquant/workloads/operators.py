"""Surrounding operators: sources, joins, aggregates, windows, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import bits as bitlib
from ..operators import calibrate, quantise, scaling
from ..schema import CodecConfig
from ..sources import store, tables
from . import sql
from .registry import query
from .scaling import U8, row_samples, v1

CODED = sql.with_(sql.v1(), sql.row_scaled(), sql.sampled(), sql.uniform_coded(8))


@query("op_scan_pruned", "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 4) AS qty FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' GROUP BY ALL")
def op_scan_pruned(spark, d):
    """Two columns read, the date filter at the scan."""
    li = tables.load(spark, d, "lineitem", "l_returnflag", "l_quantity", "l_shipdate").where(F.col("l_shipdate") >= F.lit("1997-01-01").cast("timestamp_ntz"))
    return li.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 4).alias("qty"))


@query("op_channel_slice", sql.with_(sql.v1()) + "SELECT row_id, ch, round(re, 9) AS re FROM cells WHERE ch IN (2, 5) AND pol = 1")
def op_channel_slice(spark, d):
    return v1(spark, d).where(F.col("ch").isin(2, 5) & (F.col("pol") == 1)).select("row_id", "ch", F.round("re", 9).alias("re"))


@query("op_block_range", sql.with_(sql.v1()) + "SELECT block_id, count(*) AS n FROM cells WHERE block_id BETWEEN 2 AND 4 GROUP BY ALL")
def op_block_range(spark, d):
    return v1(spark, d).where(F.col("block_id").between(2, 4)).groupBy("block_id").agg(F.count("*").alias("n"))


@query("op_nan_filter", sql.with_(sql.v1()) + "SELECT ch, count(*) FILTER (row_id % 7 <> 0) AS n_good, count(*) FILTER (row_id % 7 = 0) AS n_nan FROM cells GROUP BY ALL")
def op_nan_filter(spark, d):
    c = v1(spark, d).withColumn("re", F.when(F.col("row_id") % 7 == 0, float("nan")).otherwise(F.col("re")))
    return c.groupBy("ch").agg(F.count_if(~F.isnan("re")).alias("n_good"), F.count_if(F.isnan("re")).alias("n_nan"))


@query("op_join_factors", sql.with_(sql.v1(), "f AS (SELECT block_id, pol, ch, sqrt(avg((re * re + im * im) / 2)) AS f FROM cells GROUP BY ALL)") + "SELECT c.block_id, c.pol, round(sum(abs(c.re) / f.f), 6) AS s FROM cells c JOIN f USING (block_id, pol, ch) GROUP BY ALL")
def op_join_factors(spark, d):
    """Samples with factors of their block: both sides by block."""
    c = v1(spark, d)
    f = c.groupBy("block_id", "pol", "ch").agg(F.sqrt(F.avg(scaling.power())).alias("f"))
    return c.join(f.hint("merge"), ["block_id", "pol", "ch"]).groupBy("block_id", "pol").agg(F.round(F.sum(F.abs("re") / F.col("f")), 6).alias("s"))


@query("op_antenna_dim", "SELECT r_name, n_name, count(*) AS antennas FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def op_antenna_dim(spark, d):
    """Suppliers as antennas, nations as sites, regions as arrays."""
    s, n, r = tables.load(spark, d, "supplier"), tables.load(spark, d, "nation"), tables.load(spark, d, "region")
    return s.join(n, s["s_nationkey"] == n["n_nationkey"]).join(r, n["n_regionkey"] == r["r_regionkey"]).groupBy("r_name", "n_name").agg(F.count("*").alias("antennas"))


@query("op_level_range_join", sql.with_(sql.level_rows(("t2.5",), (4,)), "m AS (SELECT max(abs(c_acctbal)) AS top FROM customer)") + "SELECT i::INT AS idx, count(*) AS n FROM customer, m, lv WHERE c_acctbal / top >= lo AND (c_acctbal / top < hi OR last) GROUP BY ALL")
def op_level_range_join(spark, d):
    """Which interval a value falls in, by a range join with 14 broadcast intervals."""
    from ..functions.levels import levels

    t = levels("tgauss", 4, 2.5)
    lv = spark.createDataFrame([(i, float(t[i]), float(t[i + 1]), i == len(t) - 2) for i in range(len(t) - 1)], "idx int, lo double, hi double, last boolean")
    c = tables.load(spark, d, "customer", "c_acctbal")
    top = c.agg(F.max(F.abs("c_acctbal")).alias("top"))
    y = F.col("c_acctbal") / F.col("top")
    j = c.crossJoin(F.broadcast(top)).withColumn("y", y).join(F.broadcast(lv), (F.col("y") >= F.col("lo")) & ((F.col("y") < F.col("hi")) | F.col("last")))
    return j.groupBy("idx").agg(F.count("*").alias("n"))


@query("op_asof_gain", "WITH o AS (SELECT o_custkey AS k, o_orderdate AS t, o_totalprice AS p, o_orderkey FROM orders WHERE o_orderkey % 2 = 0), q AS (SELECT o_custkey AS k, o_orderdate AS t, o_orderkey FROM orders WHERE o_orderkey % 2 = 1), b AS (SELECT k, t, max(p) AS p FROM o GROUP BY ALL) SELECT q.o_orderkey, round(b.p, 4) AS latest FROM q ASOF LEFT JOIN b ON q.k = b.k AND q.t >= b.t")
def op_asof_gain(spark, d):
    """Latest value at or before each row of another table, as union and window."""
    o = tables.load(spark, d, "orders", "o_custkey", "o_orderdate", "o_totalprice", "o_orderkey")
    have = o.where("o_orderkey % 2 = 0").groupBy("o_custkey", "o_orderdate").agg(F.max("o_totalprice").alias("p")).select("o_custkey", "o_orderdate", "p", F.lit(None).cast("long").alias("o_orderkey"), F.lit(0).alias("asks"))
    want = o.where("o_orderkey % 2 = 1").select("o_custkey", "o_orderdate", F.lit(None).cast("double").alias("p"), "o_orderkey", F.lit(1).alias("asks"))
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "asks").rowsBetween(Window.unboundedPreceding, 0)
    return have.unionByName(want).withColumn("latest", F.round(F.last("p", True).over(w), 4)).where("asks = 1").select("o_orderkey", "latest")


@query("op_interval_events", "SELECT e.event_type, count(*) AS n FROM events e JOIN (SELECT DISTINCT ts::DATE AS day FROM events) s ON e.ts >= s.day AND e.ts < s.day + INTERVAL 6 HOUR GROUP BY ALL")
def op_interval_events(spark, d):
    """Events in the first quarter of each solution interval: an equi-join on the day plus a range condition."""
    e = tables.load(spark, d, "events", "ts", "event_type").withColumn("day", F.to_date("ts"))
    s = e.select("day").distinct().withColumn("end", F.col("day").cast("timestamp_ntz") + F.expr("interval 6 hours"))
    return e.join(s, "day").where(F.col("ts") < F.col("end")).groupBy("event_type").agg(F.count("*").alias("n"))


@query("op_complete_blocks", sql.with_(sql.v1(), "ok AS (SELECT block_id FROM cells GROUP BY 1 HAVING count(DISTINCT row_id) = 36)") + "SELECT block_id, count(*) AS n FROM cells SEMI JOIN ok USING (block_id) GROUP BY ALL")
def op_complete_blocks(spark, d):
    c = v1(spark, d)
    ok = c.groupBy("block_id").agg(F.countDistinct("row_id").alias("k")).where("k = 36")
    return c.join(ok, "block_id", "left_semi").groupBy("block_id").agg(F.count("*").alias("n"))


@query("op_missing_rows", sql.with_(sql.v1(), "g AS (SELECT b AS block_id, pos FROM (SELECT DISTINCT block_id AS b FROM cells), range(36) r(pos))") + "SELECT block_id, (block_id * 36 + pos)::BIGINT AS row_id FROM g WHERE NOT EXISTS (SELECT 1 FROM cells c WHERE c.row_id = g.block_id * 36 + pos)")
def op_missing_rows(spark, d):
    rows = tables.vis_rows(spark, d).select("block_id", "row_id")
    grid = rows.select("block_id").distinct().select("block_id", F.explode(F.sequence(F.col("block_id") * 36, F.col("block_id") * 36 + 35)).alias("row_id"))
    return grid.join(rows, ["block_id", "row_id"], "left_anti")


@query("op_full_outer", "SELECT coalesce(a.k, b.k) AS k, a.n AS n_docs, b.n AS n_vecs FROM (SELECT doc_id % 50 AS k, count(*) AS n FROM documents GROUP BY 1) a FULL JOIN (SELECT 10 + vec_id % 50 AS k, count(*) AS n FROM embeddings GROUP BY 1) b USING (k)")
def op_full_outer(spark, d):
    """All documents and vectors; the key ranges alone leave keys of each side unmatched."""
    a = tables.load(spark, d, "documents", "doc_id").groupBy((F.col("doc_id") % 50).alias("k")).agg(F.count("*").alias("n_docs"))
    b = tables.load(spark, d, "embeddings", "vec_id").groupBy((F.col("vec_id") % 50 + 10).alias("k")).agg(F.count("*").alias("n_vecs"))
    return a.join(b, "k", "full_outer")


@query("op_lateral_peak", sql.with_(sql.v1(), "p AS (SELECT block_id, ch, round(max(greatest(abs(re), abs(im))), 8) AS peak FROM cells GROUP BY ALL)") + "SELECT b.block_id, t.ch, t.peak FROM (SELECT DISTINCT block_id FROM cells) b, LATERAL (SELECT ch, peak FROM p WHERE p.block_id = b.block_id ORDER BY peak DESC, ch LIMIT 1) t")
def op_lateral_peak(spark, d):
    """Each block's strongest channel by a correlated sub-select."""
    v1(spark, d).groupBy("block_id", "ch").agg(F.round(F.max(scaling.peak()), 8).alias("peak")).createOrReplaceTempView("block_peaks")
    return spark.sql("SELECT b.block_id, t.ch, t.peak FROM (SELECT DISTINCT block_id FROM block_peaks) b, LATERAL (SELECT max_by(struct(p.ch, p.peak), struct(p.peak, -p.ch)) AS m FROM block_peaks p WHERE p.block_id = b.block_id) s, LATERAL (SELECT s.m.ch AS ch, s.m.peak AS peak) t")


@query("op_channel_rms", sql.with_(sql.v1()) + "SELECT ch, round(max(greatest(abs(re), abs(im))), 8) AS top, round(stddev_pop(re), 8) AS sd, round(corr(re, im), 6) AS corr, count(*) FILTER (re > 0) AS n_pos, arg_max(row_id, re) AS top_row FROM cells GROUP BY ALL")
def op_channel_rms(spark, d):
    return v1(spark, d).groupBy("ch").agg(F.round(F.max(scaling.peak()), 8).alias("top"), F.round(F.stddev_pop("re"), 8).alias("sd"), F.round(F.corr("re", "im"), 6).alias("corr"), F.count_if(F.col("re") > 0).alias("n_pos"), F.max_by("row_id", "re").alias("top_row"))


ERRS = "er AS (SELECT ch, pol, (v_hat - v) * (v_hat - v) AS e FROM coded)"


def _errors(spark, d) -> DataFrame:
    coded = quantise.decode(quantise.encode(row_samples(spark, d), U8), U8)
    return coded.select("ch", "pol", ((F.col("v_hat") - F.col("v")) ** 2).alias("e"))


@query("op_error_rollup", CODED.rstrip() + ",\n" + ERRS + "\nSELECT ch, pol, round(sqrt(avg(e)), 8) AS rmse, grouping_id(ch, pol)::BIGINT AS g FROM er GROUP BY ROLLUP (ch, pol)")
def op_error_rollup(spark, d):
    return _errors(spark, d).rollup("ch", "pol").agg(F.round(F.sqrt(F.avg("e")), 8).alias("rmse"), F.grouping_id().cast("long").alias("g"))


@query("op_error_cube", CODED.rstrip() + ",\n" + ERRS + "\nSELECT ch, pol, count(*) AS n, round(sqrt(avg(e)), 8) AS rmse FROM er GROUP BY CUBE (ch, pol)")
def op_error_cube(spark, d):
    return _errors(spark, d).cube("ch", "pol").agg(F.count("*").alias("n"), F.round(F.sqrt(F.avg("e")), 8).alias("rmse"))


@query("op_grouping_sets", CODED.rstrip() + ",\n" + ERRS + "\nSELECT ch, pol, count(*) AS n FROM er GROUP BY GROUPING SETS ((ch), (pol), ())")
def op_grouping_sets(spark, d):
    return _errors(spark, d).groupingSets([["ch"], ["pol"], []], "ch", "pol").agg(F.count("*").alias("n"))


@query("op_symbol_histogram", CODED + "SELECT sym, count(*) AS n FROM coded GROUP BY ALL")
def op_symbol_histogram(spark, d):
    return quantise.encode(row_samples(spark, d), U8).groupBy("sym").agg(F.count("*").alias("n"))


@query("op_symbol_entropy", CODED.rstrip() + ",\nh AS (SELECT pol, sym, count(*) AS n FROM coded GROUP BY ALL)\nSELECT pol, round(log2(sum(n)) - sum(n * log2(n)) / sum(n), 7) AS bits FROM h GROUP BY ALL")
def op_symbol_entropy(spark, d):
    h = quantise.encode(row_samples(spark, d), U8).groupBy("pol", "sym").agg(F.count("*").alias("n"))
    return h.groupBy("pol").agg(F.round(F.log2(F.sum("n")) - F.sum(F.col("n") * F.log2("n")) / F.sum("n"), 7).alias("bits"))


@query("op_distinct_counts", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_tax) AS taxes FROM lineitem GROUP BY ALL")
def op_distinct_counts(spark, d):
    return tables.load(spark, d, "lineitem", "l_returnflag", "l_suppkey", "l_tax").groupBy("l_returnflag").agg(F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_tax").alias("taxes"))


@query("op_approx_distinct")
def op_approx_distinct(spark, d):
    """The sketch forms: distinct counts and quantiles that merge."""
    e = tables.load(spark, d, "events", "event_type", "user_id", "value")
    return e.groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", F.array(F.lit(0.5), F.lit(0.99)), 1000).alias("q"))


@query("op_stokes_pivot", sql.with_(sql.v1()) + "SELECT row_id, ch, round((max(re) FILTER (pol = 0) + max(re) FILTER (pol = 3)) / 2, 8) AS i FROM cells GROUP BY ALL")
def op_stokes_pivot(spark, d):
    p = v1(spark, d).groupBy("row_id", "ch").pivot("pol", [0, 3]).agg(F.max("re"))
    return p.select("row_id", "ch", F.round((F.col("0") + F.col("3")) / 2, 8).alias("i"))


@query("op_unpivot", "SELECT r_regionkey AS k, 'retail' AS name, 1::BIGINT AS n FROM region UNION ALL SELECT r_regionkey, 'whole', 2 FROM region")
def op_unpivot(spark, d):
    w = tables.load(spark, d, "region", "r_regionkey").select(F.col("r_regionkey").alias("k"), F.lit(1).cast("long").alias("retail"), F.lit(2).cast("long").alias("whole"))
    return w.unpivot("k", ["retail", "whole"], "name", "n")


@query("op_offsets_prefix", "SELECT doc_id, coalesce(sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS offset FROM documents")
def op_offsets_prefix(spark, d):
    w = Window.partitionBy("source").orderBy("doc_id").rowsBetween(Window.unboundedPreceding, -1)
    return tables.load(spark, d, "documents", "doc_id", "source", "n_chars").select("doc_id", F.coalesce(F.sum("n_chars").over(w), F.lit(0)).alias("offset"))


@query("op_moving_rms", "SELECT event_id, round(sqrt(avg(value * value) OVER (PARTITION BY event_type ORDER BY event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW)), 6) AS rms FROM events")
def op_moving_rms(spark, d):
    w = Window.partitionBy("event_type").orderBy("event_id").rowsBetween(-4, 0)
    return tables.load(spark, d, "events", "event_id", "event_type", "value").select("event_id", F.round(F.sqrt(F.avg(F.col("value") * F.col("value")).over(w)), 6).alias("rms"))


@query("op_range_window", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def op_range_window(spark, d):
    """Half seconds go to the even second, as in the SQL, and times are taken as they stand, whatever the session's zone."""
    w = Window.partitionBy("event_type").orderBy("s").rangeBetween(-3600, 0)
    s = F.expr("cast(cast(cast(ts as timestamp_ntz) - timestamp_ntz'1970-01-01' as interval second) as decimal(18, 6))")
    e = tables.load(spark, d, "events", "event_id", "event_type", "ts").withColumn("s", F.rint(s.cast("double")).cast("long"))
    return e.select("event_id", F.count("*").over(w).alias("n"))


@query("op_bit_slope", "SELECT o_custkey, o_orderkey, round(o_totalprice - lead(o_totalprice) OVER w, 4) AS step FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) QUALIFY lead(o_totalprice) OVER w IS NOT NULL")
def op_bit_slope(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return tables.load(spark, d, "orders", "o_custkey", "o_orderkey", "o_orderdate", "o_totalprice").withColumn("nxt", F.lead("o_totalprice").over(w)).where("nxt is not null").select("o_custkey", "o_orderkey", F.round(F.col("o_totalprice") - F.col("nxt"), 4).alias("step"))


@query("op_rank_methods", "SELECT p_brand, p_partkey, (rank() OVER w)::INT AS r, (dense_rank() OVER w)::INT AS dr, (row_number() OVER u)::INT AS rn, (ntile(4) OVER u)::INT AS q FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size DESC), u AS (PARTITION BY p_brand ORDER BY p_size DESC, p_partkey)")
def op_rank_methods(spark, d):
    w, u = Window.partitionBy("p_brand").orderBy(F.desc("p_size")), Window.partitionBy("p_brand").orderBy(F.desc("p_size"), "p_partkey")
    return tables.load(spark, d, "part", "p_brand", "p_partkey", "p_size").select("p_brand", "p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.row_number().over(u).alias("rn"), F.ntile(4).over(u).alias("q"))


@query("op_top_configs", CODED.rstrip() + ",\n" + ERRS + "\nSELECT ch, pol, round(sqrt(avg(e)), 8) AS rmse FROM er GROUP BY ALL ORDER BY rmse, ch, pol LIMIT 5")
def op_top_configs(spark, d):
    """Top-k report."""
    return _errors(spark, d).groupBy("ch", "pol").agg(F.round(F.sqrt(F.avg("e")), 8).alias("rmse")).orderBy("rmse", "ch", "pol").limit(5)


@query("op_peak_pixels", sql.with_(sql.v1()) + "SELECT row_id, ch, pol, round(abs(re), 8) AS mag FROM cells ORDER BY mag DESC, row_id, ch, pol LIMIT 10")
def op_peak_pixels(spark, d):
    return v1(spark, d).select("row_id", "ch", "pol", F.round(F.abs("re"), 8).alias("mag")).orderBy(F.desc("mag"), "row_id", "ch", "pol").limit(10)


@query("op_blocks_intersect", "SELECT s_nationkey AS k FROM supplier INTERSECT ALL SELECT c_nationkey FROM customer")
def op_blocks_intersect(spark, d):
    return tables.load(spark, d, "supplier", "s_nationkey").intersectAll(tables.load(spark, d, "customer", "c_nationkey")).select(F.col("s_nationkey").alias("k"))


@query("op_blocks_except", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def op_blocks_except(spark, d):
    return tables.load(spark, d, "customer", "c_nationkey").exceptAll(tables.load(spark, d, "supplier", "s_nationkey")).select(F.col("c_nationkey").alias("k"))


@query("op_union_sets", "SELECT 'v1' AS set, count(*) AS n FROM embeddings UNION ALL SELECT 'v3', count(*) FROM events")
def op_union_sets(spark, d):
    a = tables.load(spark, d, "embeddings", "vec_id").select(F.lit("v1").alias("set"))
    b = tables.load(spark, d, "events", "event_id").select(F.lit("v3").alias("set"))
    return a.unionByName(b).groupBy("set").agg(F.count("*").alias("n"))


@query("op_sql_min_bits", "WITH r(bits, err) AS (VALUES (2, 0.5), (4, 0.12), (6, 0.03), (8, 0.007)), m AS (SELECT avg(l_tax) AS ref FROM lineitem) SELECT min(bits)::INT AS bits FROM r WHERE err < (SELECT ref FROM m) AND EXISTS (SELECT 1 FROM lineitem WHERE l_tax > r.err)")
def op_sql_min_bits(spark, d):
    """Scalar and correlated sub-selects in SQL."""
    tables.load(spark, d, "lineitem", "l_tax").createOrReplaceTempView("taxes")
    return spark.sql("WITH r AS (SELECT * FROM VALUES (2, 0.5D), (4, 0.12D), (6, 0.03D), (8, 0.007D) AS t(bits, err)) SELECT min(bits) AS bits FROM r WHERE err < (SELECT avg(l_tax) FROM taxes) AND err < (SELECT max(l_tax) FROM taxes)")


@query("op_width_bucket", "SELECT least(greatest(floor((l_quantity - 1) / 49.0 * 7)::BIGINT + 1, 0), 8) AS b, count(*) AS n FROM lineitem GROUP BY ALL")
def op_width_bucket(spark, d):
    return tables.load(spark, d, "lineitem", "l_quantity").groupBy(F.width_bucket("l_quantity", F.lit(1.0), F.lit(50.0), F.lit(7)).alias("b")).agg(F.count("*").alias("n"))


@query("op_math", "SELECT (o_orderkey % 8)::BIGINT AS k, round(sum(sqrt(o_totalprice) + ln(o_totalprice) + sin(o_totalprice) + atan2(o_totalprice, 2) + sign(o_totalprice - 1e5)), 4) AS s FROM orders GROUP BY ALL")
def op_math(spark, d):
    p = F.col("o_totalprice")
    return tables.load(spark, d, "orders", "o_orderkey", "o_totalprice").groupBy((F.col("o_orderkey") % 8).alias("k")).agg(F.round(F.sum(F.sqrt(p) + F.log(p) + F.sin(p) + F.atan2(p, F.lit(2.0)) + F.signum(p - 1e5)), 4).alias("s"))


@query("op_bits_hash", "SELECT user_id, (user_id & 12)::BIGINT AS a, xor(user_id, 5)::BIGINT AS x, bit_count(user_id)::INT AS b, md5(user_id::VARCHAR) AS h FROM (SELECT DISTINCT user_id FROM events)")
def op_bits_hash(spark, d):
    u = tables.load(spark, d, "events", "user_id").distinct()
    c = F.col("user_id")
    return u.select("user_id", c.bitwiseAND(F.lit(12)).alias("a"), c.bitwiseXOR(F.lit(5)).alias("x"), F.bit_count(c).alias("b"), F.md5(c.cast("string")).alias("h"))


def _packed_hex(samples):
    coded = quantise.encode(samples, U8)
    rows = coded.groupBy("row_id", "pol").agg(F.transform(F.array_sort(F.collect_list(F.struct("ch", "part", "sym"))), lambda x: x["sym"]).alias("s"))
    return rows.select("row_id", "pol", F.hex(bitlib.pack_expr(F.col("s"), 8)).alias("payload"))


@query("op_pack_hex", CODED.rstrip() + "\nSELECT row_id, pol, upper(string_agg(printf('%02x', sym), '' ORDER BY ch, part)) AS payload FROM coded GROUP BY ALL")
def op_pack_hex(spark, d):
    return _packed_hex(row_samples(spark, d))


@query("op_unpack_at", "SELECT vec_id AS row_id, floor((embedding[11]::DOUBLE + 1) / 2 * 1023)::BIGINT AS sym FROM embeddings")
def op_unpack_at(spark, d):
    """One 10-bit symbol out of a payload, from the bytes it lies in."""
    s = F.expr("transform(vis, x -> cast(floor((cast(x as double) + 1) / 2 * 1023) as bigint))")
    p = tables.vis_rows(spark, d).select("row_id", bitlib.pack_expr(s, 10).alias("p"))
    return p.select("row_id", bitlib.unpack_at(F.col("p"), 10, F.lit(10)).alias("sym"))


@query("op_array_scale", "SELECT vec_id AS row_id, round(list_aggregate(list_transform(embedding, lambda x: abs(x)), 'max')::DOUBLE, 6) AS top, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS power FROM embeddings")
def op_array_scale(spark, d):
    v = F.col("vis")
    return tables.vis_rows(spark, d).select("row_id", F.round(F.array_max(F.transform(v, F.abs)).cast("double"), 6).alias("top"), F.round(F.aggregate(v, F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 6).alias("power"))


@query("op_factor_map", sql.with_(sql.v1(), "f AS (SELECT block_id, ch, round(sqrt(avg((re * re + im * im) / 2)), 8) AS f FROM cells WHERE pol = 0 GROUP BY ALL)") + "SELECT block_id, f AS ch5, (SELECT count(*) FROM f g WHERE g.block_id = f.block_id)::INT AS n FROM f WHERE ch = 5")
def op_factor_map(spark, d):
    f = v1(spark, d).where("pol = 0").groupBy("block_id", "ch").agg(F.round(F.sqrt(F.avg(scaling.power())), 8).alias("f"))
    m = f.groupBy("block_id").agg(F.map_from_entries(F.collect_list(F.struct("ch", "f"))).alias("m"))
    return m.select("block_id", F.element_at("m", F.lit(5)).alias("ch5"), F.size("m").alias("n"))


@query("op_props_k", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) % 10 AS k, count(*) AS n FROM events GROUP BY ALL")
def op_props_k(spark, d):
    return tables.load(spark, d, "events", "props").groupBy((F.get_json_object("props", "$.k").cast("long") % 10).alias("k")).agg(F.count("*").alias("n"))


@query("op_header_json", "SELECT '{\"block\":' || b || ',\"bits\":8}' AS header FROM (SELECT DISTINCT vec_id // 36 AS b FROM embeddings)")
def op_header_json(spark, d):
    return tables.vis_rows(spark, d).select("block_id").distinct().select(F.to_json(F.struct(F.col("block_id").alias("block"), F.lit(8).alias("bits"))).alias("header"))


@query("op_source_number", "SELECT CAST(regexp_extract(source, '([0-9]+)', 1) AS INT) AS ch, count(*) AS n, sum(len(string_split(text, ' ')))::BIGINT AS words FROM documents GROUP BY ALL")
def op_source_number(spark, d):
    return tables.load(spark, d, "documents", "source", "text").groupBy(F.regexp_extract("source", r"([0-9]+)", 1).cast("int").alias("ch")).agg(F.count("*").alias("n"), F.sum(F.size(F.split("text", " "))).alias("words"))


@query("op_time_blocks", "SELECT date_trunc('hour', ts) AS hour, count(*) AS n, round(sum(value), 4) AS v FROM events GROUP BY ALL")
def op_time_blocks(spark, d):
    return tables.load(spark, d, "events", "ts", "value").groupBy(F.date_trunc("hour", "ts").cast("timestamp_ntz").alias("hour")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("v"))


@query("op_udf_quantise", CODED + "SELECT ch, sum(sym)::BIGINT AS total FROM coded GROUP BY ALL")
def op_udf_quantise(spark, d):
    """The Arrow engine gives the native engine's symbols."""
    return quantise.encode(row_samples(spark, d), U8, "arrow").groupBy("ch").agg(F.sum("sym").alias("total"))


@query("op_udaf_entropy", CODED.rstrip() + ",\nh AS (SELECT ch, sym, count(*) AS n FROM coded GROUP BY ALL)\nSELECT ch, round(log2(sum(n)) - sum(n * log2(n)) / sum(n), 7) AS bits FROM h GROUP BY ALL")
def op_udaf_entropy(spark, d):
    """A grouped aggregate in Python, on counts per symbol's sample of a channel; ``op_symbol_entropy`` is the mergeable form."""
    from ..functions.udfs import entropy_agg

    return quantise.encode(row_samples(spark, d), U8).groupBy("ch").agg(F.round(entropy_agg("sym"), 7).alias("bits"))


@query("op_udaf_robust", sql.with_(sql.V3, "m AS (SELECT ch, re, quantile_cont(re, 0.5) OVER (PARTITION BY ch) AS med FROM cells)") + "SELECT ch, round(1.4826::DOUBLE * quantile_cont(abs(re - med), 0.5), 6) AS sigma FROM m GROUP BY ALL")
def op_udaf_robust(spark, d):
    from ..functions.udfs import robust_sigma

    return tables.vis_events(spark, d).groupBy("ch").agg(F.round(robust_sigma("re"), 6).alias("sigma"))


LEVELS_OF = sql.with_("used AS (SELECT (2 + (l_linenumber - 1) % 7)::INT AS bits, count(*) AS n FROM lineitem WHERE l_linenumber IS NOT NULL GROUP BY ALL)", sql.level_rows(("t2.5",), tuple(range(2, 9))))


@query("op_udtf_levels", LEVELS_OF + "SELECT bits, n, i::INT AS idx, round(lo, 9) AS level FROM used JOIN lv USING (bits) UNION ALL SELECT bits, n, i + 1, round(hi, 9) FROM used JOIN lv USING (bits) WHERE last")
def op_udtf_levels(spark, d):
    """Tables of levels by a lateral table function, one for each number of bits that line items ask for by their number, and how many do."""
    from ..functions.udfs import LevelTable

    bits = (F.lit(2) + (F.col("l_linenumber") - 1) % 7).cast("int").alias("bits")
    used = tables.load(spark, d, "lineitem", "l_linenumber").where("l_linenumber is not null").groupBy(bits).agg(F.count("*").alias("n"))
    return used.lateralJoin(LevelTable(F.lit("tgauss"), F.col("bits").outer(), F.lit(2.5))).select("bits", "n", "idx", F.round("level", 9).alias("level"))


@query("op_udtf_unpack", "SELECT vec_id AS row_id, i::INT AS idx, floor((embedding[(i + 1)::INT]::DOUBLE + 1) / 2 * 63)::INT AS sym FROM embeddings, range(64) r(i)")
def op_udtf_unpack(spark, d):
    """A payload as rows, by a lateral table function."""
    from ..functions.udfs import UnpackBlock

    s = F.expr("transform(vis, x -> cast(floor((cast(x as double) + 1) / 2 * 63) as bigint))")
    tables.vis_rows(spark, d).select("row_id", bitlib.pack_expr(s, 6).alias("p")).createOrReplaceTempView("packed_rows")
    spark.udtf.register("unpack_block", UnpackBlock)
    return spark.sql("SELECT row_id, u.idx, u.sym FROM packed_rows, LATERAL unpack_block(p, 6, 64) u")


@query("op_hash_sample", f"SELECT block_id, count(*) AS n FROM (SELECT vec_id // 36 AS block_id FROM embeddings) WHERE {sql.uniform_sql('block_id', 9)} < 0.4 GROUP BY ALL")
def op_hash_sample(spark, d):
    """A sample of whole blocks, by a hash of their number: what a method is chosen on."""
    from ..functions.dither import uniform

    return tables.vis_rows(spark, d).where(uniform(F.col("block_id"), 9) < 0.4).groupBy("block_id").agg(F.count("*").alias("n"))


@query("op_stokes_products", sql.with_(sql.v1()) + "SELECT row_id, ch, round((max(im) FILTER (pol = 1) - max(im) FILTER (pol = 2)) / 2, 8) AS v_re FROM cells GROUP BY ALL")
def op_stokes_products(spark, d):
    return calibrate.stokes(v1(spark, d)).select("row_id", "ch", F.round("v_re", 8).alias("v_re"))


# Streams: run to the end of the table, compared with batch SQL.


def _run(spark: SparkSession, stream: DataFrame, mode: str, name: str) -> DataFrame:
    from ..streaming.codec import run_to_table

    path = store.shared_dir(spark, name)
    run_to_table(stream, path, mode, path + "-checkpoint")
    return spark.read.parquet(path)


@query("st_tumbling_blocks", "SELECT ts::DATE::TIMESTAMP AS day, count(*) AS n, round(sum(value), 4) AS v FROM events GROUP BY ALL")
def st_tumbling_blocks(spark, d):
    """Daily windows in update mode; the last version of each window is the result."""
    from ..streaming.codec import events

    s = events(spark, d).groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("v"))
    out = _run(spark, s.select(F.col("window.start").alias("day"), "n", "v"), "update", "tumbling")
    w = Window.partitionBy("day").orderBy(F.desc("batch"))
    return out.withColumn("r", F.row_number().over(w)).where("r = 1").select(F.col("day").cast("timestamp_ntz").alias("day"), "n", "v")


@query("st_sliding_rms", "SELECT h AS start, round(sqrt(avg(value * value)), 6) AS rms FROM (SELECT value, unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS h FROM events) GROUP BY ALL")
def st_sliding_rms(spark, d):
    from ..streaming.codec import events

    s = events(spark, d).groupBy(F.window("ts", "2 hours", "1 hour")).agg(F.round(F.sqrt(F.avg(F.col("value") * F.col("value"))), 6).alias("rms"))
    out = _run(spark, s.select(F.col("window.start").alias("start"), "rms"), "complete", "sliding")
    last = out.agg(F.max("batch").alias("batch"))
    return out.join(F.broadcast(last), "batch").select(F.col("start").cast("timestamp_ntz").alias("start"), "rms")


@query("st_session_users", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS s FROM events), h AS (SELECT user_id, ts, sum(s) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM h GROUP BY user_id, k HAVING max(ts) + INTERVAL 12 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def st_session_users(spark, d):
    """Sessions that the watermark has closed."""
    from ..streaming.codec import events

    s = events(spark, d).groupBy(F.session_window("ts", "12 hours"), "user_id").agg(F.count("*").alias("n"))
    return _run(spark, s.select("user_id", F.col("session_window.start").alias("start"), "n"), "append", "sessions").select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@query("st_dedup", "SELECT count(DISTINCT event_id) AS n, count(DISTINCT event_id) AS n_ids FROM events")
def st_dedup(spark, d):
    """Each event twice in the stream, once behind the de-duplication."""
    from ..streaming.codec import events

    s = events(spark, d).withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).dropDuplicatesWithinWatermark(["event_id"])
    return _run(spark, s.select("event_id"), "append", "dedup").agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("n_ids"))


@query("st_static_join", "SELECT s_name, count(*) AS n FROM events JOIN supplier ON user_id % 10 + 1 = s_suppkey GROUP BY ALL")
def st_static_join(spark, d):
    """Stream rows meet a static table."""
    from ..streaming.codec import events

    sup = tables.load(spark, d, "supplier", "s_suppkey", "s_name")
    s = events(spark, d).join(sup, F.col("user_id") % 10 + 1 == F.col("s_suppkey")).select("s_name")
    return _run(spark, s, "append", "static").groupBy("s_name").agg(F.count("*").alias("n"))


V3C = "e AS (SELECT ts, (ts::DATE - DATE '1970-01-01')::BIGINT AS block_id FROM events)"


@query("st_block_codec", sql.with_(V3C) + "SELECT block_id, count(*) AS n FROM e GROUP BY 1 HAVING max(ts) + INTERVAL 1 MILLISECOND < (SELECT max(ts) - INTERVAL 1 HOUR FROM e)")
def st_block_codec(spark, d):
    """Days assembled in state, packed when the watermark passes them; counted after decoding."""
    from ..operators.codec import decompress
    from ..schema import PACKED
    from ..streaming.codec import compress_stream, events

    e = events(spark, d)
    one = e.select("ts", F.datediff(F.to_date("ts"), F.lit("1970-01-01")).cast("long").alias("block_id"), F.col("event_id").alias("row_id"), F.lit(0).alias("ant_a"), F.lit(1).alias("ant_b"), F.lit(0).alias("ch"), F.lit(0).alias("pol"), (F.col("value") - 50).alias("re"), F.lit(0.0).alias("im"), F.lit(1.0).alias("weight"), F.lit(False).alias("flagged"))
    cfg = CodecConfig(scaling="row_channel", autos="keep", quantiser="uniform", trunc=None)
    packed = _run(spark, compress_stream(one, cfg), "append", "blocks").select(*PACKED.fieldNames())
    return decompress(packed).groupBy("block_id").agg(F.count("*").alias("n"))
