"""Every query with SQL against DuckDB, on the smallest tables; the rest must run and give rows."""

import math

import duckdb
import pytest

from blockquant.workloads import ORACLES, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    return c


def rows(df):
    def plain(v):
        if v is None or isinstance(v, float) and math.isnan(v) or str(v) in ("NaT", "<NA>"):
            return None
        if hasattr(v, "item"):
            v = v.item()
        return float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else v if isinstance(v, bool) else str(v)

    out = [tuple(plain(v) for v in r) for r in df[sorted(df.columns)].itertuples(index=False)]
    return sorted(out, key=lambda r: tuple((v is None, str(type(v)), v if v is not None else 0) for v in r))


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, sf, con, name):
    got = QUERIES[name](spark, sf).toPandas()
    if name in ORACLES:
        want = con.execute(ORACLES[name]).fetchdf()
        assert sorted(got.columns) == sorted(want.columns)
        assert rows(got) == rows(want)
    else:
        assert len(got) > 0


@pytest.mark.parametrize("name", ["w3_repeat_avg_customer", "w3_repeat_avg_events", "op_full_outer", "op_pack_hex"])
def test_whole_tables_are_read(spark, name):
    """On tables large enough for a subset of ids to show, against the SQL."""
    d, c = "/root/testdata/sf0.01", duckdb.connect()
    for t in ("customer", "events", "documents", "embeddings"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{d}/{t}.parquet')")
    got = QUERIES[name](spark, d).toPandas()
    assert rows(got) == rows(c.execute(ORACLES[name]).fetchdf())
    n_docs, n_vecs, n_samples = c.execute("SELECT (SELECT count(*) FROM documents), (SELECT count(*) FROM embeddings), (SELECT sum(len(embedding)) FROM embeddings)").fetchone()
    if name == "op_full_outer":
        assert (got["n_docs"].sum(), got["n_vecs"].sum()) == (n_docs, n_vecs) and got["n_docs"].isna().any() and got["n_vecs"].isna().any()
    if name == "op_pack_hex":
        assert got["payload"].str.len().sum() == 2 * n_samples
