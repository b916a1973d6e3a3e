"""Session settings the library relies on. Queries work with the session as given; these are for one's own sessions."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: Joins that share a block reuse its partitioning instead of shuffling on every key.
SETTINGS = {
    "spark.sql.session.timeZone": "UTC",
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.parquet.filterPushdown": "true",
}


def session(master: str = "local[*]", shuffle_partitions: int | None = None, **more: str) -> SparkSession:
    builder = SparkSession.builder.master(master).config(map=SETTINGS | more)
    if shuffle_partitions:
        builder = builder.config("spark.sql.shuffle.partitions", str(shuffle_partitions))
    return builder.getOrCreate()
