"""Quality by compression: a text belongs to the class whose dictionary shrinks it more.

Two zstandard dictionaries are trained, one on good and one on bad labelled text. Every whole text is compressed with
each, block by block so that the dictionary keeps its weight in long texts; the difference of the two sizes, divided by the
text's own size, is the only signal. A logistic curve of it, fitted on texts that the dictionaries have not seen, gives the
probability of label 1.

The model is fitted on a bounded sample of labelled rows, ``dict_rows + curve_rows`` of each label, of which at most
``dict_text_bytes`` of each label come to the driver (the fit's only bounds; texts are whole in the fit as in scoring). Rows
come in hash order of their ids, so the sample doesn't depend on partitioning; it reaches the documents as a broadcast of
that many ids. The model is a few hundred kilobytes.

Defined results: null and empty texts get the share of label 1 among the training rows; without rows of both labels every
text gets that share (1.0 without any label); repeated rows each keep their row; null labels are left out; a text over a
sixteenth of ``dict_text_bytes`` is no part of a dictionary.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common


@dataclass(frozen=True)
class CompressionModel:
    """Dictionaries as bytes, the curve (constant and slope; None without a fit) and the share of label 1."""

    good: bytes
    bad: bytes
    curve: tuple[float, float] | None
    base_rate: float
    block: int = 1024
    level: int = 3


class Sizes:
    """Compressors with either dictionary."""

    def __init__(self, model: CompressionModel) -> None:
        def with_dict(data: bytes) -> zstandard.ZstdCompressor:
            d = zstandard.ZstdCompressionDict(data)
            d.precompute_compress(level=model.level)
            return zstandard.ZstdCompressor(dict_data=d, write_checksum=False, write_content_size=False)

        self.block, self.good, self.bad = model.block, with_dict(model.good), with_dict(model.bad)

    def difference(self, text: str) -> float:
        """How many bytes of a text's own the good dictionary saves over the bad one."""
        data = text.encode()
        parts = [data[i : i + self.block] for i in range(0, len(data), self.block)]
        good, bad = (sum(len(c.compress(p)) for p in parts) for c in (self.good, self.bad))
        return (bad - good) / len(data)


def _dictionary(texts: list[str], size: int) -> bytes:
    """Trained; raw text where there is too little for training."""
    parts = [d[i : i + 2048] for t in texts if (d := t.encode()) for i in range(0, len(d), 2048)]
    try:
        return zstandard.train_dictionary(size, parts, level=3).as_bytes()
    except zstandard.ZstdError:
        return b"".join(parts)[-size:] or b" " * 8


def logistic(x: np.ndarray, y: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """Constant and slope by Newton steps on the ridge-penalised likelihood, on the standardised variable."""
    mean, scale = x.mean(), x.std() + 1e-9
    z = np.column_stack([np.ones(len(x)), (x - mean) / scale])
    w = np.zeros(2)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        h = (z * (p * (1 - p))[:, None]).T @ z + 1e-2 * np.eye(2)
        step = np.linalg.solve(h, z.T @ (p - y) + 1e-2 * w)
        w -= step
        if np.abs(step).max() < 1e-8:
            break
    slope = float(w[1] / scale)
    return float(w[0]) - slope * float(mean), slope


def fit(docs: DataFrame, training: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "quality", dict_rows: int = 1000, curve_rows: int = 3000, dict_bytes: int = 112_640, dict_text_bytes: int = 32 << 20) -> CompressionModel:
    """``training``: ids and labels that may be learnt from. Of each label, ``dict_rows`` whole texts come to the driver for the
    dictionary and the sizes of ``curve_rows`` others are computed on the executors for the curve."""
    spark = docs.sparkSession
    known = training.where(F.col(f"`{label}`").isin(0, 1)).select(F.col(f"`{id_col}`").alias("__id"), F.col(f"`{label}`").cast("int").alias("__y"), F.xxhash64(F.col(f"`{id_col}`").cast("string"), F.lit("quality")).alias("__h"))
    count = {r["__y"]: r["count"] for r in known.groupBy("__y").count().collect()}
    total = sum(count.values())
    base = count.get(1, 0) / total if total else 1.0
    empty = CompressionModel(b"", b"", None, base)
    if len(count) < 2:
        return empty
    drawn = []
    for y, n in sorted(count.items()):
        take = min(dict_rows, max(1, n // 3))
        rows = known.where(F.col("__y") == y).orderBy("__h", "__id").limit(take + curve_rows).collect()
        drawn += [(r["__id"], y, i < take) for i, r in enumerate(rows)]
    rank = iter(range(len(drawn)))
    ids = spark.createDataFrame([(*d, next(rank)) for d in drawn], T.StructType([known.schema["__id"], T.StructField("__y", T.IntegerType()), T.StructField("__words", T.BooleanType()), T.StructField("__rank", T.IntegerType())]))
    sample = docs.select(F.col(f"`{id_col}`").alias("__id"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("t")).join(F.broadcast(ids), "__id").where(F.length("t") > 0)
    # Whole texts of the dictionary's rows, in their order, as long as the bytes of their label last.
    upto = F.sum(F.octet_length("t").cast("long")).over(Window.partitionBy("__y").orderBy("__rank", "t"))
    taken = sample.where(F.col("__words") & (F.octet_length("t") <= dict_text_bytes // 16)).withColumn("__upto", upto).where(F.col("__upto") <= dict_text_bytes)
    texts = sorted((r["__y"], r["t"]) for r in taken.select("__y", "t").collect())
    good, bad = (_dictionary([t for y, t in texts if y == k], dict_bytes) for k in (1, 0))
    model = CompressionModel(good, bad, None, base)

    def differences(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizes = Sizes(model)
        for part in common.pieces(batches, 1):
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array([sizes.difference(t) for t in common.texts_of(part.column(1))], pa.float64())], names=["y", "x"])

    rows = sorted((r["y"], r["x"]) for r in sample.where("not __words").select("__y", "t").mapInArrow(differences, "y int, x double").collect())
    y, x = np.array([r[0] for r in rows], float), np.array([r[1] for r in rows])
    if not 0 < y.sum() < len(y):
        return empty
    (constant, slope), share = logistic(x, y), y.mean()
    constant += math.log(base / (1 - base)) - math.log(share / (1 - share))  # from the sample's share of label 1 to that of all
    return replace(model, curve=(constant, slope))


def score(docs: DataFrame, model: CompressionModel, text: str = "text", out: str = "score") -> DataFrame:
    """Add the calibrated probability of label 1; a clashing column is replaced."""
    kept = [c for c in docs.columns if c.lower() != out.lower()]
    source = docs.select(*(docs[f"`{c}`"] for c in kept), F.coalesce(docs[f"`{text}`"], F.lit("")).alias("__text"))
    schema = T.StructType([*source.schema.fields[:-1], T.StructField(out, T.DoubleType())])
    at = len(kept)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sizes = Sizes(model) if model.curve else None

        def one(t: str) -> float:
            if not t or sizes is None:
                return model.base_rate
            z = model.curve[0] + model.curve[1] * sizes.difference(t)
            return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))

        for part in common.pieces(batches, at):
            yield pa.RecordBatch.from_arrays([*part.columns[:at], pa.array([one(t) for t in common.texts_of(part.column(at))], pa.float64())], names=schema.fieldNames())

    return source.mapInArrow(run, schema)


def fit_on_labels(docs: DataFrame, labels: DataFrame) -> CompressionModel:
    """Rows with crc32(doc_id) mod 3 = 1 are held out; of repeated ids the lowest label counts."""
    training = labels.where(common.bucket_of("doc_id", 3) != 1).dropna(subset=["doc_id", "quality"]).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    return fit(docs, training)


def op9_compression_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit_on_labels(docs, common.table(spark, sf_dir, "labels"))
    out = score(docs, model)
    return out.select("doc_id", (common.bucket_of("doc_id", 3) == 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
