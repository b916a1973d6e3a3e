"""What the second round's findings showed, on tables small enough to see it."""

import duckdb
import pytest

from blockquant.workloads import ORACLES, QUERIES

from test_queries import rows


def against_sql(spark, name, d, *names):
    """The query's rows, once they equal those of its SQL."""
    c = duckdb.connect()
    for t in names:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{d}/{t}.parquet')")
    got = QUERIES[name](spark, str(d)).toPandas()
    assert rows(got) == rows(c.execute(ORACLES[name]).fetchdf())
    return got


@pytest.mark.parametrize("zone", ["UTC", "America/New_York"])
def test_range_window_rounds_half_seconds_as_its_sql(spark, tmp_path, zone):
    """F1. Half seconds before and after even and odd ones, an hour that New York skips, years before 1970, no time or type at all."""
    duckdb.connect().execute(f"""COPY (SELECT row_number() OVER () AS event_id, ts, kind AS event_type FROM (
      SELECT TIMESTAMP '2024-03-10 01:00:00' + to_milliseconds(i * 500) + to_microseconds(j) AS ts FROM range(15000) r(i), (VALUES (-1), (0), (1)) s(j) WHERE i % 7 < 2 OR i % 7200 < 9
      UNION ALL SELECT TIMESTAMP '1969-12-31 22:59:00' + to_milliseconds(i * 500) FROM range(300) r(i) UNION ALL SELECT NULL FROM range(3)), (VALUES ('view'), (NULL)) k(kind)) TO '{tmp_path}/events.parquet'""")
    before = spark.conf.get("spark.sql.session.timeZone")
    spark.conf.set("spark.sql.session.timeZone", zone)
    try:
        against_sql(spark, "op_range_window", tmp_path, "events")
    finally:
        spark.conf.set("spark.sql.session.timeZone", before)


def test_metadata_share_is_of_the_given_blocks(spark, sf, tmp_path):
    """F2. A full block has the shares of the formula; half a block has others."""
    from blockquant.operators import measures
    from blockquant.schema import CodecConfig

    def shares(n):
        duckdb.connect().execute(f"COPY (SELECT * FROM '{sf}/embeddings.parquet' WHERE vec_id < {n}) TO '{tmp_path}/embeddings.parquet'")
        return dict(against_sql(spark, "metadata_share", tmp_path, "embeddings")[["scaling", "share"]].itertuples(index=False))

    full = shares(36)
    assert full == {s: pytest.approx(measures.metadata_share(CodecConfig(scaling=s), 8, 8), abs=1e-8) for s in full} and len(full) == 3
    half = shares(18)
    assert half["row"] == full["row"] and half["row_channel"] > full["row_channel"] and half["antenna_channel"] > full["antenna_channel"]


def test_udtf_levels_follow_the_line_items(spark, tmp_path):
    """F3. Tables of the bits that are asked for alone, with their numbers."""
    duckdb.connect().execute(f"COPY (SELECT l::INT AS l_linenumber FROM (VALUES (1), (3), (3), (8), (NULL)) t(l)) TO '{tmp_path}/lineitem.parquet'")
    got = against_sql(spark, "op_udtf_levels", tmp_path, "lineitem")
    assert got.groupby("bits")["n"].agg(["size", "max"]).to_dict("index") == {2: {"size": 3, "max": 2}, 4: {"size": 15, "max": 2}}


def test_packed_bytes_ratio_is_of_packed_rows(spark, tmp_path):
    """F5. Rows of odd lengths fill no whole bytes, so the ratio is below 32 / bits."""
    duckdb.connect().execute(f"COPY (SELECT i AS vec_id, [x::FLOAT FOR x IN range(i % 3 * 2 + 1)] AS embedding FROM range(10) r(i) UNION ALL SELECT 10, NULL) TO '{tmp_path}/embeddings.parquet'")
    got = dict(against_sql(spark, "packed_bytes_ratio", tmp_path, "embeddings")[["bits", "ratio"]].itertuples(index=False))
    assert got[8] == 4 and got[5] < 6.4


def test_recommend_table_gives_each_event_the_guidelines_method(spark, tmp_path):
    """F6. Products below, at and above every limit, for all arrays, and what is missing."""
    from blockquant.operators.guideline import recommend

    duckdb.connect().execute(f"""COPY (SELECT row_number() OVER () AS event_id, '{{"k": ' || k || '}}' AS props, v::DOUBLE AS value, t AS event_type FROM
      (VALUES (0), (5), (7), (15)) a(k), (VALUES (0.01), (1.0), (5.0), (6.0), (36.0), (40.0), (40.01), (48.0), (80.0), (80.01), (640.0), (NULL)) b(v), (VALUES ('view'), ('click'), ('purchase'), ('error'), (NULL)) c(t)) TO '{tmp_path}/events.parquet'""")
    got = against_sql(spark, "recommend_table", tmp_path, "events")
    assert len(got) == 240 and got["scaling"].nunique() == 2
    for r in got.dropna(subset=["dnu"]).itertuples():
        cfg, _ = recommend(r.dt, r.dnu, r.arr)
        assert (r.scaling, r.bits) == (cfg.scaling, cfg.bits) if cfg else r.scaling is None


def test_repeats_average_out_on_given_samples(spark, sf, tmp_path):
    """F12. The error falls with repeats, and follows the table."""
    def errors(scale):
        duckdb.connect().execute(f"COPY (SELECT vec_id, [x * {scale} FOR x IN embedding] AS embedding FROM '{sf}/embeddings.parquet') TO '{tmp_path}/embeddings.parquet'")
        return dict(against_sql(spark, "w3_repeat_avg", tmp_path, "embeddings")[["k", "rms"]].itertuples(index=False))

    one, eight = errors("1::FLOAT"), errors("8::FLOAT")
    assert one[1] > 1.5 * one[3] > 6 * one[100] > 0 and all(eight[k] == pytest.approx(8 * one[k], abs=1e-6) for k in one)


def test_weight_ratio_is_of_packed_weights(spark, tmp_path):
    """F13. The formula's ratio where all is there, less where polarisations are missing."""
    from blockquant.operators import weights

    def ratio(flags):
        duckdb.connect().execute(f"""COPY (SELECT s AS l_suppkey, p AS l_partkey, l::INT AS l_linenumber, f AS l_returnflag, o AS l_linestatus, 1.0::DOUBLE AS l_quantity, 2.0::DOUBLE AS l_extendedprice, TIMESTAMP '1995-03-01' + to_days((30 * (s % 2))::INT) AS l_shipdate
          FROM range(10) a(s), range(10) b(p), range(1, 9) c(l), (VALUES {flags}) d(f), (VALUES ('F'), ('O')) e(o)) TO '{tmp_path}/lineitem.parquet'""")
        return against_sql(spark, "weight_ratio", tmp_path, "lineitem")["ratio"][0]

    assert ratio("('N'), ('R')") == pytest.approx(weights.ratio(), abs=1e-6)
    assert ratio("('R')") == pytest.approx(weights.ratio(2), abs=1e-6)


@pytest.fixture(scope="module")
def two_scales(sf, tmp_path_factory):
    """Two folders of samples, the second's eight times as large but for the signals that sets have."""
    out = []
    for scale in (1, 8):
        out.append(tmp_path_factory.mktemp("scale"))
        duckdb.connect().execute(f"COPY (SELECT vec_id, [x * {scale}::FLOAT FOR x IN embedding] AS embedding FROM '{sf}/embeddings.parquet' WHERE vec_id < 90) TO '{out[-1]}/embeddings.parquet'")
    return out


def follows_table(spark, name, two_scales, rows_, column):
    a, b = (against_sql(spark, name, d, "embeddings") for d in two_scales)
    assert len(a) == len(b) == rows_ and sorted(a[column]) != sorted(b[column])


def test_balanced_mean_of_given_samples(spark, two_scales):
    """F7."""
    follows_table(spark, "w10_balanced_avg", two_scales, 15, "avg")


def test_balanced_mean_by_table_of_given_samples(spark, two_scales):
    """F8."""
    follows_table(spark, "w10_by_quantiser", two_scales, 5, "avg")


def test_balanced_mean_by_scaling_of_given_samples(spark, two_scales):
    """F9."""
    follows_table(spark, "w10_by_scaling", two_scales, 3, "avg")


def test_plain_interval_of_given_samples(spark, two_scales):
    """F10."""
    follows_table(spark, "w10_plain_ci", two_scales, 4, "avg")


#: 8-bit errors in uJy of the four sets by table (rows) and scaling (AF, RF, row), as published.
_T2 = (
    ("A", "gauss", 179, 462, 612), ("A", "t1.5", 227, 92, 105), ("A", "t2.5", 178, 209, 265), ("A", "t3.5", 178, 437, 572), ("A", "uniform", 299, 78, 82),
    ("B", "gauss", 117, 174, 224), ("B", "t1.5", 98, 212, 75), ("B", "t2.5", 91, 160, 113), ("B", "t3.5", 115, 174, 196), ("B", "uniform", 128, 290, 82),
    ("C", "gauss", 421, 452, 406), ("C", "t1.5", 616, 327, 360), ("C", "t2.5", 453, 318, 309), ("C", "t3.5", 422, 459, 394), ("C", "uniform", 827, 411, 462),
    ("D", "gauss", 81, 104, 93), ("D", "t1.5", 76, 67, 74), ("D", "t2.5", 68, 70, 70), ("D", "t3.5", 79, 99, 90), ("D", "uniform", 95, 81, 91),
)
PUBLISHED = [(s, q, k, float(v)) for s, q, *vals in _T2 for k, v in zip(("AF", "RF", "row"), vals, strict=True)]


def test_gain_over_uniform_levels(spark, two_scales):
    """F11. On given samples; and the operators on the published table, whose gains are 1.60 and 1.25 for the channel methods."""
    from blockquant.operators import baselines, measures

    follows_table(spark, "w11_gain", two_scales, 3, "ratio")
    published = spark.createDataFrame(PUBLISHED, "set string, quantiser string, scaling string, err double")
    r = measures.balanced_mean(published, "scaling", "quantiser").withColumnRenamed("avg", "err")
    got = {x.scaling: round(x.ratio, 2) for x in baselines.nonlinear_gain(r).collect()}
    assert got["AF"] == 1.6 and got["RF"] == 1.25
