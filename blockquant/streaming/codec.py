"""Blocks from a stream: assembled in state until complete or past the watermark, then packed and appended.

Event-time windows are blocks. Samples that come after their block has closed are dropped by the watermark; the state holds
open blocks only, so it is bounded by the watermark's delay and not by the stream's length.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..schema import PACKED, CodecConfig

STATE = "rows binary"
SAMPLES = "block_id bigint, row_id bigint, ant_a int, ant_b int, ch int, pol int, re double, im double, weight double, flagged boolean"


def events(spark: SparkSession, sf_dir: str, delay: str = "1 hour", files: int = 1) -> DataFrame:
    """The events table as a stream: timestamps get a zone, so that a watermark may stand on them."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(f"{sf_dir}/events.parque[t]")  # as a pattern, it may be a file as well as a folder
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def compress_stream(samples: DataFrame, cfg: CodecConfig, expected: int | None = None) -> DataFrame:
    """``samples`` with ``ts`` (watermarked) and the columns of cells: packed rows, as each block completes or times out."""
    import pyarrow as pa

    from ..operators import kernels

    def assemble(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        import pickle

        held = pickle.loads(state.get[0]) if state.exists else pd.DataFrame()
        parts = [held, *batches] if not state.hasTimedOut else [held]
        rows = pd.concat([p for p in parts if len(p)], ignore_index=True) if any(len(p) for p in parts) else held
        if state.hasTimedOut or (expected is not None and len(rows) >= expected):
            state.remove()
            if len(rows):
                table = pa.Table.from_pandas(rows.drop(columns=["ts"]).sort_values(["pol", "row_id", "ch"]), preserve_index=False)
                yield pd.DataFrame(kernels.compress_block(table, cfg).to_pylist())
        else:
            state.update((pickle.dumps(rows),))
            state.setTimeoutTimestamp(int(rows["ts"].max().timestamp() * 1000) + 1)

    schema = "struct<" + ",".join(f"{f.name}:{f.dataType.simpleString()}" for f in PACKED.fields) + ">"
    return samples.groupBy("block_id").applyInPandasWithState(assemble, schema, STATE, "append", GroupStateTimeout.EventTimeTimeout)


def run_to_table(stream: DataFrame, path: str, mode: str, checkpoint: str, each: Callable[[DataFrame], DataFrame] | None = None) -> None:
    """Run to the end of what is there, into Parquet. Update and complete modes write versions by batch number; readers take the last."""

    def write(batch: DataFrame, number: int) -> None:
        (each(batch) if each else batch).withColumn("batch", F.lit(number)).write.mode("append").parquet(path)

    q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
