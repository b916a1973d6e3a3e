"""Building blocks of the oracles: the fixtures and codec steps as DuckDB common table expressions."""

from __future__ import annotations

from ..functions.dither import hash32, ordinal_sql, uniform_sql  # noqa: F401
from ..functions.levels import levels, n_levels
from ..schema import TABLES
from ..sources.tables import pairs

PAIRS = ", ".join(f"({i}, {a}, {b})" for i, (a, b) in enumerate(pairs(8)))
G = "((0.5::DOUBLE + 1.5::DOUBLE * a / 7.0::DOUBLE) * (0.5::DOUBLE + 1.5::DOUBLE * b / 7.0::DOUBLE) * (1.0::DOUBLE + 0.2::DOUBLE * (k // 4)))"


def v1(gains: bool = True, name: str = "cells", signal: float = 0.0, extra: str = "") -> str:
    """``extra`` may change the expressions re_ and im_ by further SQL on a sub-select."""
    g = f" * {G}" if gains else ""
    sig = f" + CASE WHEN k % 4 IN (0, 3) THEN {signal}::DOUBLE * {G} ELSE 0 END" if signal else ""
    return f"""{name} AS (SELECT (vec_id // 36)::BIGINT AS block_id, vec_id::BIGINT AS row_id, a AS ant_a, b AS ant_b, (k // 4)::INT AS ch, (k % 4)::INT AS pol,
  embedding[(2 * k + 1)::INT]::DOUBLE{g}{sig} AS re, embedding[(2 * k + 2)::INT]::DOUBLE{g} AS im, 1.0::DOUBLE AS weight, FALSE AS flagged
  FROM embeddings, (VALUES {PAIRS}) p(pos, a, b), range(32) r(k) WHERE pos = vec_id % 36 {extra})"""


def rfi(source: str = "cells", name: str = "hit", ch: int = 3, strength: float = 1000.0) -> str:
    one = lambda c: f"CASE WHEN ch = {ch} THEN {c} * {strength}::DOUBLE ELSE {c} END AS {c}"
    return f"{name} AS (SELECT * EXCLUDE (re, im), {one('re')}, {one('im')} FROM {source})"


V2 = """cells AS (SELECT *, (block_id * 100 + ant_a * 10 + ant_b)::BIGINT AS row_id, FALSE AS flagged FROM (
  SELECT ((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1)::BIGINT AS block_id, least(l_suppkey % 10, l_partkey % 10)::INT AS ant_a, greatest(l_suppkey % 10, l_partkey % 10)::INT AS ant_b,
    (l_linenumber - 1)::INT AS ch, ((CASE WHEN l_returnflag = 'N' THEN 2 ELSE 0 END) + (CASE WHEN l_linestatus = 'F' THEN 0 ELSE 1 END))::INT AS pol,
    avg(l_quantity) - 25.5::DOUBLE AS re, avg(l_extendedprice) / 1000 - 53 AS im, count(*)::DOUBLE AS weight
  FROM lineitem GROUP BY ALL))"""

V3 = """cells AS (SELECT *, (block_id * 36 + ant_a * 6 + ant_b)::BIGINT AS row_id, 0 AS pol, FALSE AS flagged FROM (
  SELECT (ts::DATE - DATE '1970-01-01')::BIGINT AS block_id, least(user_id % 6, kk % 6)::INT AS ant_a, greatest(user_id % 6, kk % 6)::INT AS ant_b, ch, avg(value) - 50 AS re, max(value) - 50 AS im, count(*)::DOUBLE AS weight
  FROM (SELECT *, CAST(json_extract_string(props, '$.k') AS BIGINT) AS kk, (dense_rank() OVER (ORDER BY event_type) - 1)::INT AS ch FROM events) GROUP BY ALL))"""

PEAK = "greatest(abs(re), abs(im))"
POWER = "((re * re + im * im) / 2)"


def row_scaled(source: str = "cells", name: str = "scaled") -> str:
    return f"{name} AS (SELECT *, coalesce(max({PEAK}) OVER (PARTITION BY block_id, row_id), 0)::FLOAT::DOUBLE AS sigma FROM {source})"


def rf_scaled(source: str = "cells", name: str = "scaled") -> str:
    return f"""rf1 AS (SELECT *, sqrt(avg({POWER}) OVER (PARTITION BY block_id, pol, ch)) AS f1 FROM {source}),
rf2 AS (SELECT *, max({PEAK} / nullif(f1, 0)) OVER (PARTITION BY block_id, pol, row_id)::FLOAT::DOUBLE AS f_row FROM rf1),
rf3 AS (SELECT *, max({PEAK} / nullif(f1 * f_row, 0)) OVER (PARTITION BY block_id, pol, ch) AS m FROM rf2),
{name} AS (SELECT *, (f1 * m)::FLOAT::DOUBLE AS f_ch, coalesce((f1 * m)::FLOAT::DOUBLE * f_row, 0) AS sigma FROM rf3)"""


def sampled(source: str = "scaled", name: str = "smp", n_ch: int = 1024) -> str:
    keys = "block_id, row_id, ant_a, ant_b, ch, pol, sigma"
    y = "CASE WHEN sigma > 0 THEN greatest(least(v / sigma, 1), -1) ELSE 0 END AS y"
    return f"""{name} AS (SELECT *, {y} FROM (SELECT {keys}, 0 AS part, re AS v, {ordinal_sql(0, n_ch)} AS ord FROM {source} UNION ALL SELECT {keys}, 1, im, {ordinal_sql(1, n_ch)} FROM {source}))"""


def uniform_pos(bits: int, source: str = "smp", name: str = "pos") -> str:
    n = n_levels(bits)
    step = f"{2.0 / (n - 1)!r}::DOUBLE"
    return f"""{name} AS (SELECT *, lo * {step} - 1 AS below, (lo + 1) * {step} - 1 AS above FROM (SELECT *, least(floor((y + 1) * {(n - 1) / 2.0!r}::DOUBLE), {n - 2}) AS lo FROM {source}))"""


def uniform_coded(bits: int, seed: int = 0, source: str = "smp", name: str = "coded", u: str | None = None) -> str:
    n = n_levels(bits)
    u = u or uniform_sql("ord", seed)
    return f"""{uniform_pos(bits, source, name + "_p")},
{name} AS (SELECT *, (sym * {2.0 / (n - 1)!r}::DOUBLE - 1) * sigma AS v_hat FROM (SELECT *, (lo + CASE WHEN {u} < (y - below) / (above - below) THEN 1 ELSE 0 END)::INT AS sym FROM {name}_p))"""


def level_rows(labels: tuple[str, ...], bits: tuple[int, ...], name: str = "lv") -> str:
    """Intervals between neighbouring levels as literals: label, bits, i, lo, hi, last."""
    rows = []
    for label in labels:
        quantiser, trunc = TABLES[label]
        for b in bits:
            t = levels(quantiser, b, trunc)
            rows += [f"('{label}', {b}, {i}, {float(t[i])!r}, {float(t[i + 1])!r}, {i == len(t) - 2})" for i in range(len(t) - 1)]
    return f"{name}(quantiser, bits, i, lo, hi, last) AS (SELECT c0, c1, c2, c3::DOUBLE, c4::DOUBLE, c5 FROM (VALUES {', '.join(rows)}) t(c0, c1, c2, c3, c4, c5))"


def table_errors(labels: tuple[str, ...], bits: tuple[int, ...], source: str = "smp", by: str = "") -> str:
    """SELECT of [by,] quantiser, bits, rms: expected errors by a join of samples with level intervals."""
    keys = f"{by}, " if by else ""
    return f"""SELECT {keys}quantiser, bits::INT AS bits, round(sqrt(avg((y - lo) * (hi - y) * sigma * sigma)), 8) AS rms FROM {source} JOIN lv ON y >= lo AND (y < hi OR last) GROUP BY ALL"""


def table_coded(label: str, bits: int, seed: int = 0, source: str = "smp", name: str = "coded") -> str:
    return f"""{name} AS (SELECT {source}.*, (i + CASE WHEN {uniform_sql("ord", seed)} < (y - lo) / (hi - lo) THEN 1 ELSE 0 END)::INT AS sym,
  (CASE WHEN {uniform_sql("ord", seed)} < (y - lo) / (hi - lo) THEN hi ELSE lo END) * sigma AS v_hat FROM {source} JOIN lv ON y >= lo AND (y < hi OR last) WHERE quantiser = '{label}' AND bits = {bits})"""


def with_(*ctes: str) -> str:
    return "WITH " + ",\n".join(ctes) + "\n"
