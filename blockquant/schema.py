"""Declared layouts: cells (long), rows (arrays), packed (storage), factors."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import types as T

CELLS = T.StructType(
    [
        T.StructField("block_id", T.LongType()),
        T.StructField("row_id", T.LongType()),
        T.StructField("ant_a", T.IntegerType()),
        T.StructField("ant_b", T.IntegerType()),
        T.StructField("ch", T.IntegerType()),
        T.StructField("pol", T.IntegerType()),
        T.StructField("re", T.DoubleType()),
        T.StructField("im", T.DoubleType()),
        T.StructField("weight", T.DoubleType()),
        T.StructField("flagged", T.BooleanType()),
    ]
)
PACKED = T.StructType(
    [
        T.StructField("block_id", T.LongType()),
        T.StructField("pol", T.IntegerType()),
        T.StructField("row_ids", T.ArrayType(T.LongType())),
        T.StructField("ants_a", T.ArrayType(T.IntegerType())),
        T.StructField("ants_b", T.ArrayType(T.IntegerType())),
        T.StructField("channels", T.ArrayType(T.IntegerType())),
        T.StructField("present", T.BinaryType()),  # a bit per grid cell; null: all there
        T.StructField("row_factors", T.ArrayType(T.FloatType())),
        T.StructField("ant_ids", T.ArrayType(T.IntegerType())),
        T.StructField("ant_factors", T.ArrayType(T.FloatType())),
        T.StructField("ch_factors", T.ArrayType(T.FloatType())),
        T.StructField("scaling", T.StringType()),
        T.StructField("quantiser", T.StringType()),
        T.StructField("trunc", T.DoubleType()),
        T.StructField("sampling", T.StringType()),
        T.StructField("dither", T.StringType()),
        T.StructField("seed", T.IntegerType()),
        T.StructField("bits", T.IntegerType()),
        T.StructField("max_abs", T.DoubleType()),
        T.StructField("entropy", T.StringType()),
        T.StructField("payload", T.BinaryType()),
    ]
)
#: Weights of a block: one for all polarisations, codes of 12 bits against each row's largest.
WEIGHTS = T.StructType(
    [
        T.StructField("block_id", T.LongType()),
        T.StructField("row_ids", T.ArrayType(T.LongType())),
        T.StructField("channels", T.ArrayType(T.IntegerType())),
        T.StructField("row_max", T.ArrayType(T.FloatType())),
        T.StructField("payload", T.BinaryType()),
    ]
)
SCALINGS = ("row", "row_channel", "row_channel_af", "antenna_channel")
QUANTISERS = ("gauss", "tgauss", "uniform", "lloyd")


@dataclass(frozen=True)
class CodecConfig:
    """How blocks are scaled, quantised and dithered. ``trunc``: truncation of ``tgauss`` in sigma; with ``trunc_grid`` each block
    and polarisation takes the one of the grid that has the least expected error. ``sub_band``: channels that are fitted and
    packed together at most, which bounds what a task holds. ``round_factors``: scale by factors as they are stored, in 32 bits."""

    scaling: str = "antenna_channel"
    quantiser: str = "tgauss"
    trunc: float | None = 2.5
    bits: int = 8
    dither: str = "hash"
    seed: int = 0
    autos: str = "zero"
    sampling: str = "midpoint"
    tau: float = 0.01
    max_steps: int = 64
    solver: str = "als"
    clip_sigma: float | None = None
    entropy: str | None = None
    centre: bool = False
    trunc_grid: tuple[float, ...] | None = None
    sub_band: int = 64
    round_factors: bool = True

    def __post_init__(self) -> None:
        if self.scaling not in SCALINGS or self.quantiser not in QUANTISERS:
            raise ValueError(f"unknown scaling {self.scaling} or quantiser {self.quantiser}")
        if not 2 <= self.bits <= 16:
            raise ValueError("bits must be 2 to 16")
        if self.dither not in ("hash", "none", "subtractive") or self.autos not in ("zero", "keep", "own_factor"):
            raise ValueError(f"unknown dither {self.dither} or autos {self.autos}")
        if self.trunc_grid and self.quantiser != "tgauss":
            raise ValueError("a grid of truncations needs the tgauss quantiser")
        if self.dither == "subtractive" and self.quantiser != "uniform":
            raise ValueError("subtractive dither needs uniform levels")

    def but(self, **changes: object) -> CodecConfig:
        return replace(self, **changes)

    @property
    def label(self) -> str:
        return f"t{self.trunc:g}" if self.quantiser == "tgauss" else self.quantiser


#: The five tables that are compared, by label.
TABLES = {"gauss": ("gauss", None), "t1.5": ("tgauss", 1.5), "t2.5": ("tgauss", 2.5), "t3.5": ("tgauss", 3.5), "uniform": ("uniform", None)}


def table_config(label: str, bits: int, **more: object) -> CodecConfig:
    quantiser, trunc = TABLES[label]
    return CodecConfig(quantiser=quantiser, trunc=trunc, bits=bits, **more)


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """``df`` reduced to the declared columns; an error names what is missing or of another type."""
    have = {f.name: f.dataType.simpleString() for f in df.schema}
    wrong = [f"{f.name} {f.dataType.simpleString()} (is {have.get(f.name)})" for f in schema if have.get(f.name) != f.dataType.simpleString()]
    if wrong:
        raise TypeError("expected " + ", ".join(wrong))
    return df.select(*schema.fieldNames())
