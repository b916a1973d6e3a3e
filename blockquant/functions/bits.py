"""Packing of b-bit symbols, most significant bit first, into ceil(n * b / 8) bytes."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def packed(symbols: np.ndarray, bits: int) -> bytes:
    planes = (symbols.astype(np.uint32)[:, None] >> np.arange(bits - 1, -1, -1, dtype=np.uint32)) & 1
    return np.packbits(planes.astype(np.uint8).ravel()).tobytes()


def unpacked(payload: bytes, bits: int, n: int) -> np.ndarray:
    planes = np.unpackbits(np.frombuffer(payload, np.uint8), count=n * bits).reshape(n, bits)
    return planes.astype(np.int64) @ (1 << np.arange(bits - 1, -1, -1, dtype=np.int64))


def payload_bytes(n: int | Column, bits: int | Column) -> int | Column:
    if isinstance(n, Column) or isinstance(bits, Column):
        return F.ceil((F.lit(n) if isinstance(n, int) else n) * bits / 8).cast("long")
    return -(-n * bits // 8)


def pack_expr(symbols: Column, bits: int) -> Column:
    """Array of symbols to binary, in functions of the engine."""
    text = F.array_join(F.transform(symbols, lambda s: F.lpad(F.bin(s.cast("long")), bits, "0")), "")
    even = F.rpad(text, (F.ceil(F.length(text) / 8) * 8).cast("int"), F.lit("0"))
    nibbles = F.transform(F.sequence(F.lit(0), (F.length(even) / 4).cast("int") - 1), lambda i: F.conv(F.substring(even, i * 4 + 1, F.lit(4)), 2, 16))
    return F.when(F.size(symbols) == 0, F.unhex(F.lit(""))).otherwise(F.unhex(F.array_join(nibbles, "")))


def unpack_at(payload: Column, bits: int, index: Column) -> Column:
    """One symbol, from the two or three bytes it lies in; the rest of the payload isn't decoded."""
    first = index * bits
    start = F.floor(first / 8).cast("int")
    window = F.rpad(F.hex(F.substring(payload, start + 1, F.lit(3))), 6, "0")
    value = F.conv(window, 16, 10).cast("long")
    return F.floor(value / F.pow(F.lit(2.0), 24 - bits - (first % 8))).cast("long") % (1 << bits)


def unpack_expr(payload: Column, bits: int, n: Column) -> Column:
    """All symbols of a payload, in functions of the engine."""
    return F.when(n <= 0, F.array().cast("array<bigint>")).otherwise(F.transform(F.sequence(F.lit(0).cast("long"), n.cast("long") - 1), lambda i: unpack_at(payload, bits, i)))
