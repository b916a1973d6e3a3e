"""Weights: equal ones collapse, the rest are truncated linearly at 12 bits against the row's largest, or kept lossless."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import bits as bitlib
from ..schema import WEIGHTS
from . import kernels


def collapse(cells: DataFrame) -> DataFrame:
    """block_id, row_id, ch, weight, equal: one weight for all polarisations, and whether they were the same."""
    g = cells.groupBy("block_id", "row_id", "ch").agg(F.min("weight").alias("lo"), F.max("weight").alias("hi"), F.count("*").alias("n_pol"))
    return g.select("block_id", "row_id", "ch", F.col("hi").alias("weight"), "n_pol", (F.col("lo") == F.col("hi")).alias("equal"))


def code(weight: Column, top: Column, bits: int = 12) -> Column:
    return F.floor(F.coalesce(weight / F.nullif(top, F.lit(0.0)), F.lit(0.0)) * ((1 << bits) - 1)).cast("int")


def decoded(sym: Column, top: Column, bits: int = 12) -> Column:
    return sym * top / ((1 << bits) - 1)


def quantise_weights(weights: DataFrame, bits: int = 12, mode: str = "cell") -> DataFrame:
    """Adds row_max, sym and weight_hat. ``mode='row'``: one weight a row, its mean, and no symbols."""
    w = Window.partitionBy("block_id", "row_id")
    if mode == "row":
        return weights.groupBy("block_id", "row_id").agg(F.avg("weight").alias("weight_hat"), F.count("*").alias("n"))
    out = weights.withColumn("row_max", F.max("weight").over(w)).withColumn("sym", code(F.col("weight"), F.col("row_max"), bits))
    return out.withColumn("weight_hat", decoded(F.col("sym"), F.col("row_max"), bits))


def pack(cells: DataFrame, bits: int = 12) -> DataFrame:
    """A block's weights as one packed row: the largest of a sample's polarisations, truncated against its row's largest. Where
    a row has no sample in a channel the code is 0."""

    def run(t: pa.Table) -> pa.Table:
        rows, r = np.unique(t["row_id"].to_numpy(), return_inverse=True)
        chans, c = np.unique(t["ch"].to_numpy(), return_inverse=True)
        w = t["weight"].to_numpy().astype(float)
        top = kernels.grouped(w, r, len(rows), np.maximum).astype(np.float32)
        codes = np.zeros(len(rows) * len(chans), np.int64)
        codes[r * len(chans) + c] = np.floor(np.minimum(kernels.ratio(w, top[r].astype(float)), 1) * ((1 << bits) - 1))
        row = {"block_id": t["block_id"][0].as_py(), "row_ids": rows, "channels": chans, "row_max": top, "payload": bitlib.packed(codes, bits)}
        return pa.Table.from_pylist([row], kernels.arrow(WEIGHTS))

    one = cells.groupBy("block_id", "row_id", "ch").agg(F.coalesce(F.max("weight"), F.lit(0.0)).alias("weight"))
    return one.groupBy("block_id").applyInArrow(run, WEIGHTS)


def unpack(packed: DataFrame, bits: int = 12) -> DataFrame:
    """block_id, row_id, ch, weight."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p in batch.to_pylist():
                n, k = len(p["row_ids"]), len(p["channels"])
                top = np.repeat(np.array(p["row_max"], np.float32).astype(float), k)
                w = bitlib.unpacked(p["payload"], bits, n * k) * top / ((1 << bits) - 1)
                columns = [pa.array(np.full(n * k, p["block_id"]), pa.int64()), pa.array(np.repeat(p["row_ids"], k), pa.int64()), pa.array(np.tile(p["channels"], n), pa.int32()), pa.array(w)]
                yield pa.RecordBatch.from_arrays(columns, names=["block_id", "row_id", "ch", "weight"])

    return packed.mapInArrow(run, "block_id bigint, row_id bigint, ch int, weight double")


def ratio(n_pol: int = 4, bits: int = 12, raw_bits: int = 32) -> float:
    return raw_bits * n_pol / bits


def weighted_mean_shift(df: DataFrame, value: str = "re", *by: str) -> DataFrame:
    """Weighted mean with weights as they were and as they come back."""
    mean = lambda w: F.sum(F.col(w) * F.col(value)) / F.nullif(F.sum(w), F.lit(0.0))
    return df.groupBy(*by).agg(mean("weight").alias("before"), mean("weight_hat").alias("after"))


def bz2_sizes(df: DataFrame, columns: dict[str, str], rows_per_unit: int = 65536) -> DataFrame:
    """column, raw_bytes, packed_bytes: each column's raw bytes of a batch under a general-purpose compressor. Units compress alone and sizes add up."""
    names = list(columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for i, name in enumerate(names):
                for at in range(0, batch.num_rows, rows_per_unit):
                    col = batch.column(i).slice(at, rows_per_unit)
                    raw = "".join(x or "" for x in col.to_pylist()).encode() if pa.types.is_string(col.type) else np.ascontiguousarray(col.to_numpy(zero_copy_only=False)).astype(columns[name]).tobytes()
                    out.append((name, len(raw), kernels.bz2_size(raw) if raw else 0))
            yield pa.RecordBatch.from_arrays([pa.array([o[k] for o in out], t) for k, t in enumerate((pa.string(), pa.int64(), pa.int64()))], names=["column", "raw_bytes", "packed_bytes"])

    sizes = df.select(*names).mapInArrow(run, "column string, raw_bytes bigint, packed_bytes bigint")
    return sizes.groupBy("column").agg(F.sum("raw_bytes").alias("raw_bytes"), F.sum("packed_bytes").alias("packed_bytes"))
