"""The given tables, and sample cells made of them.

V1 (embeddings) is noise-dominated, V2 (lineitem) uniform and sparse, V3 (events) heavy-tailed, V4 (documents) skewed.
All are projections or one aggregation; perturbations are functions of logical keys.
"""

from __future__ import annotations

from itertools import combinations_with_replacement

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def pairs(n_ant: int) -> list[tuple[int, int]]:
    return list(combinations_with_replacement(range(n_ant), 2))


def gain(ant: Column, n_ant: int = 8) -> Column:
    return F.lit(0.5) + F.lit(1.5) * ant / F.lit(float(n_ant - 1))


def bandpass(ch: Column) -> Column:
    return F.lit(1.0) + F.lit(0.2) * ch


def vis_rows(spark: SparkSession, sf_dir: str, n_ant: int = 8) -> DataFrame:
    """V1 in rows layout: block_id, row_id, ant_a, ant_b, vis array<float> as [ch][pol][re, im]. No shuffle."""
    own = pairs(n_ant)
    of = lambda side: F.element_at(F.array(*(F.lit(p[side]) for p in own)), (F.col("vec_id") % len(own) + 1).cast("int"))
    e = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
    return e.select((F.floor(F.col("vec_id") / len(own))).cast("long").alias("block_id"), F.col("vec_id").alias("row_id"), of(0).alias("ant_a"), of(1).alias("ant_b"), F.col("embedding").alias("vis"))


def cells_of(rows: DataFrame, n_ch: int = 8, n_pol: int = 4) -> DataFrame:
    """Rows layout to cells."""
    k = F.explode(F.sequence(F.lit(0), F.lit(n_ch * n_pol - 1))).alias("k")
    c = rows.select("block_id", "row_id", "ant_a", "ant_b", "vis", k)
    return c.select(
        "block_id", "row_id", "ant_a", "ant_b",
        F.floor(F.col("k") / n_pol).cast("int").alias("ch"), (F.col("k") % n_pol).cast("int").alias("pol"),
        F.element_at("vis", 2 * F.col("k") + 1).cast("double").alias("re"), F.element_at("vis", 2 * F.col("k") + 2).cast("double").alias("im"),
        F.lit(1.0).alias("weight"), F.lit(False).alias("flagged"),
    )


def vis_embeddings(spark: SparkSession, sf_dir: str, n_ant: int = 8, gains: bool = True) -> DataFrame:
    """V1: 8 channels x 4 polarisations, 36 rows a block; the last block is short on purpose."""
    cells = cells_of(vis_rows(spark, sf_dir, n_ant))
    if not gains:
        return cells
    g = gain(F.col("ant_a"), n_ant) * gain(F.col("ant_b"), n_ant) * bandpass(F.col("ch"))
    return cells.withColumns({"re": F.col("re") * g, "im": F.col("im") * g})


def vis_lineitem(spark: SparkSession, sf_dir: str, n_ant: int = 10) -> DataFrame:
    """V2: a block is a month; cells are mean quantity and price of a supplier-part pair; one shuffle."""
    li = load(spark, sf_dir, "lineitem", "l_suppkey", "l_partkey", "l_linenumber", "l_returnflag", "l_linestatus", "l_quantity", "l_extendedprice", "l_shipdate")
    a, b = F.col("l_suppkey") % n_ant, F.col("l_partkey") % n_ant
    keys = {
        "block_id": ((F.year("l_shipdate") - 1995) * 12 + F.month("l_shipdate") - 1).cast("long"),
        "ant_a": F.least(a, b).cast("int"),
        "ant_b": F.greatest(a, b).cast("int"),
        "ch": (F.col("l_linenumber") - 1).cast("int"),
        "pol": (F.when(F.col("l_returnflag") == "N", 2).otherwise(0) + F.when(F.col("l_linestatus") == "F", 0).otherwise(1)).cast("int"),
    }
    cells = li.groupBy(*(c.alias(n) for n, c in keys.items())).agg((F.avg("l_quantity") - 25.5).alias("re"), (F.avg("l_extendedprice") / 1000 - 53).alias("im"), F.count("*").cast("double").alias("weight"))
    row = F.col("block_id") * (n_ant * n_ant) + F.col("ant_a") * n_ant + F.col("ant_b")
    return cells.select("block_id", row.alias("row_id"), "ant_a", "ant_b", "ch", "pol", "re", "im", "weight", F.lit(False).alias("flagged"))


EVENT_TYPES_SQL = "dense rank of event_type"


def vis_events(spark: SparkSession, sf_dir: str, n_ant: int = 6) -> DataFrame:
    """V3: a block is a day; channels are event types in alphabetical order."""
    e = load(spark, sf_dir, "events", "ts", "user_id", "event_type", "value", "props")
    kinds = e.select("event_type").distinct().agg(F.array_sort(F.collect_set("event_type")).alias("kinds"))  # one row of a closed set of types
    a, b = F.col("user_id") % n_ant, F.get_json_object("props", "$.k").cast("long") % n_ant
    day = F.datediff(F.to_date("ts"), F.lit("1970-01-01")).cast("long")
    cells = e.join(F.broadcast(kinds)).groupBy(day.alias("block_id"), F.least(a, b).cast("int").alias("ant_a"), F.greatest(a, b).cast("int").alias("ant_b"), (F.array_position("kinds", F.col("event_type")) - 1).cast("int").alias("ch"))
    cells = cells.agg((F.avg("value") - 50).alias("re"), (F.max("value") - 50).alias("im"), F.count("*").cast("double").alias("weight"))
    row = F.col("block_id") * (n_ant * n_ant) + F.col("ant_a") * n_ant + F.col("ant_b")
    return cells.select("block_id", row.alias("row_id"), "ant_a", "ant_b", "ch", F.lit(0).alias("pol"), "re", "im", "weight", F.lit(False).alias("flagged"))


def vis_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """V4: a row is a document, its channel the source, its polarisation the language."""
    d = load(spark, sf_dir, "documents", "doc_id", "text", "lang", "source", "n_chars")
    words = F.size(F.split(F.coalesce("text", F.lit("")), " "))
    lang = F.array_position(F.array(*(F.lit(x) for x in ("de", "en", "es", "fr"))), F.col("lang")) - 1
    return d.select(F.floor(F.col("doc_id") / 100).cast("long").alias("block_id"), F.col("doc_id").alias("row_id"), F.lit(0).alias("ant_a"), F.lit(1).alias("ant_b"), F.regexp_extract("source", r"(\d+)", 1).cast("int").alias("ch"), lang.cast("int").alias("pol"), (F.col("n_chars") - 2400).cast("double").alias("re"), (words - 370).cast("double").alias("im"), F.lit(1.0).alias("weight"), F.lit(False).alias("flagged"))


# Perturbations.


def inject_rfi(cells: DataFrame, ch: int = 3, strength: float = 1000.0, where: Column | None = None) -> DataFrame:
    """One channel (of the rows that ``where`` names) times ``strength``."""
    hit = F.col("ch") == ch if where is None else (F.col("ch") == ch) & where
    return cells.withColumns({c: F.when(hit, F.col(c) * strength).otherwise(F.col(c)) for c in ("re", "im")})


def inject_signal(cells: DataFrame, amp: float, pols: tuple[int, ...] = (0, 3), n_ant: int = 8) -> DataFrame:
    """A constant source in the parallel hands, seen through the gains."""
    g = gain(F.col("ant_a"), n_ant) * gain(F.col("ant_b"), n_ant) * bandpass(F.col("ch"))
    return cells.withColumn("re", F.when(F.col("pol").isin(*pols), F.col("re") + amp * g).otherwise(F.col("re")))


def flag_cells(cells: DataFrame, one_in: int = 20, seed: int = 1) -> DataFrame:
    from ..functions.dither import hash32, ordinal

    return cells.withColumn("flagged", F.col("flagged") | (hash32(ordinal(), seed) % one_in == 0))


def dead_antenna(cells: DataFrame, ant: int = 2) -> DataFrame:
    dead = (F.col("ant_a") == ant) | (F.col("ant_b") == ant)
    return cells.withColumns({c: F.when(dead, 0.0).otherwise(F.col(c)) for c in ("re", "im")})
