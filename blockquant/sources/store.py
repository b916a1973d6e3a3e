"""Packed observations on disk: Parquet, partitioned by ranges of blocks.

A bucket holds ``per_bucket`` blocks, so files stay large, reads of a block range prune to a few buckets and row groups,
and replacing a block rewrites one bucket. Data, factors and keys are columns of their own and prune apart; weights are a
table of their own beside them. How many blocks make a bucket follows from the bytes of one.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import weights as weightlib
from ..operators.codec import as_cells, compress, decompress
from ..schema import PACKED, WEIGHTS, CodecConfig

PER_BUCKET = 1024
BUCKET_BYTES = 256 << 20


def shared_dir(spark: SparkSession, name: str) -> str:
    """A new folder that every executor sees, under ``spark.checkpoint.dir``. Where that is unset a temp folder will do only if
    the driver is the one executor."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="blockquant-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def blocks_a_bucket(block_bytes: int, n_pol: int = 4) -> int:
    """As many blocks as give a bucket of a few hundred megabytes, for blocks of so many bytes a polarisation."""
    return max(1, min(PER_BUCKET, BUCKET_BYTES // max(1, block_bytes * n_pol)))


def bucket(block: Column | str, per_bucket: int = PER_BUCKET) -> Column:
    return F.floor((F.col(block) if isinstance(block, str) else block) / per_bucket).cast("long")


def write(packed: DataFrame, path: str, per_bucket: int = PER_BUCKET, mode: str = "overwrite") -> None:
    """Blocks in order inside each file, for statistics that prune. No more shuffle than bringing a bucket together.

    The bucket's size is a folder level of its own, so readers need not be told it.
    """
    out = packed.withColumns({"per_bucket": F.lit(per_bucket), "bucket": bucket("block_id", per_bucket)}).repartition("bucket").sortWithinPartitions("bucket", "block_id", *(["pol"] if "pol" in packed.columns else []))
    out.write.mode(mode).partitionBy("per_bucket", "bucket").parquet(path)


def write_observation(cells: DataFrame, path: str, cfg: CodecConfig, per_bucket: int = PER_BUCKET) -> None:
    """Samples and weights of cells, side by side under ``path``."""
    write(compress(cells, cfg), f"{path}/data", per_bucket)
    write(weightlib.pack(cells), f"{path}/weights", per_bucket)


def read_observation(spark: SparkSession, path: str, lo: int | None = None, hi: int | None = None) -> DataFrame:
    """Cells with their weights again."""
    weights = within(spark.read.parquet(f"{path}/weights"), lo, hi).select(*WEIGHTS.fieldNames())
    return as_cells(decompress(read(spark, f"{path}/data", lo, hi)), weightlib.unpack(weights))


def within(df: DataFrame, lo: int | None, hi: int | None) -> DataFrame:
    """Blocks lo..hi: both the folder and the row groups are pruned."""
    if lo is not None:
        df = df.where((F.col("block_id") >= lo) & (F.col("bucket") >= F.floor(F.lit(lo) / F.col("per_bucket"))))
    if hi is not None:
        df = df.where((F.col("block_id") <= hi) & (F.col("bucket") <= F.floor(F.lit(hi) / F.col("per_bucket"))))
    return df


def read(spark: SparkSession, path: str, lo: int | None = None, hi: int | None = None, min_abs: float | None = None) -> DataFrame:
    """Packed rows of blocks lo..hi. ``min_abs``: only blocks that can hold such a magnitude; both filters reach the scan."""
    df = within(spark.read.parquet(path), lo, hi)
    if min_abs is not None:
        df = df.where(F.col("max_abs") > min_abs)
    return df.select(*PACKED.fieldNames())


def read_blocks(spark: SparkSession, path: str, lo: int, hi: int) -> DataFrame:
    """Cells of a range of blocks."""
    return decompress(read(spark, path, lo, hi))


def replace_block(spark: SparkSession, path: str, block_id: int, cells: DataFrame, cfg: CodecConfig) -> None:
    """Put a block in the place of the one of its number: its bucket is written anew, the others stay."""
    stored = spark.read.parquet(path).where(F.col("bucket") == F.floor(F.lit(block_id) / F.col("per_bucket")))
    size = stored.select("per_bucket").first() or spark.read.parquet(path).select("per_bucket").first()
    per_bucket = size["per_bucket"] if size else PER_BUCKET
    kept = stored.where(F.col("block_id") != block_id).select(*PACKED.fieldNames())
    new = kept.unionByName(compress(cells.where(F.col("block_id") == block_id), cfg))
    staged = _staged(spark, new.withColumns({"per_bucket": F.lit(per_bucket), "bucket": bucket("block_id", per_bucket)}))
    staged.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("per_bucket", "bucket").parquet(path)


def _staged(spark: SparkSession, df: DataFrame) -> DataFrame:
    """A bucket can't be read while it is overwritten: its new content goes through the shared folder first."""
    path = shared_dir(spark, "bucket")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


class BlockCache:
    """Access to single blocks of a packed store: the block at hand stays decoded until another is asked for, and is packed and
    put back then, if it was changed. ``decodes`` and ``writes`` count what that cost."""

    def __init__(self, spark: SparkSession, path: str, cfg: CodecConfig) -> None:
        self.spark, self.path, self.cfg = spark, path, cfg
        self.block_id: int | None = None
        self.cells: DataFrame | None = None
        self.dirty, self.decodes, self.writes = False, 0, 0

    def __enter__(self) -> BlockCache:
        return self

    def __exit__(self, *_: object) -> None:
        self.flush()

    def block(self, block_id: int) -> DataFrame:
        if block_id != self.block_id:
            self.flush()
            self.block_id, self.cells = block_id, as_cells(read_blocks(self.spark, self.path, block_id, block_id)).cache()
            self.decodes += 1
        return self.cells

    def change(self, block_id: int, how: Callable[[DataFrame], DataFrame]) -> None:
        """The block after ``how``; it reaches the store with the next flush."""
        before = self.block(block_id)
        self.cells, self.dirty = how(before).cache(), True

    def flush(self) -> None:
        if self.dirty:
            replace_block(self.spark, self.path, self.block_id, self.cells, self.cfg)
            self.writes += 1
        if self.cells is not None:
            self.cells.unpersist()
        self.block_id, self.cells, self.dirty = None, None, False


def view(spark: SparkSession, path: str, name: str) -> DataFrame:
    """A temporary view of plain cells over a packed store: clients query it like any table."""
    cells = decompress(read(spark, path))
    cells.createOrReplaceTempView(name)
    return cells


def block_bytes(n_ch: int, n_ant: int, bits: int, n_factors: int) -> int:
    """Fixed size of an encoded block of one polarisation."""
    return -(-(n_ch * n_ant * (n_ant + 1)) * bits // 8) + 4 * n_factors


def block_offset(block: Column, size: int, header: int = 0) -> Column:
    """Where a block stands in a file of equal blocks: no index is needed."""
    return F.lit(header) + block * F.lit(size)


def offsets(packed: DataFrame) -> DataFrame:
    """block_id, pol, bytes, offset where an entropy stage makes sizes differ: running sums per bucket, then over buckets."""
    p = packed.select("block_id", "pol", F.octet_length("payload").cast("long").alias("bytes"), bucket("block_id").alias("bucket"))
    totals = p.groupBy("bucket").agg(F.sum("bytes").alias("t"))  # one row per bucket of a thousand blocks
    starts = totals.withColumn("start", F.coalesce(F.sum("t").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    inside = F.coalesce(F.sum("bytes").over(Window.partitionBy("bucket").orderBy("block_id", "pol").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return p.withColumn("inside", inside).join(starts, "bucket").select("block_id", "pol", "bytes", (F.col("start") + F.col("inside")).alias("offset"))


def access_cost(trace: DataFrame, order: str, block: str = "block_id") -> DataFrame:
    """Blocks decoded along an access order with a cache of one block: each change of block is one."""
    before = F.lag(block).over(Window.orderBy(order))
    return trace.withColumn("b", before).agg(F.sum(F.when(F.col("b").isNull() | (F.col("b") != F.col(block)), 1).otherwise(0)).alias("decodes"))
