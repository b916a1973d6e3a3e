"""Which method for which data: the guideline as a function and as a table."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..schema import CodecConfig

#: Fixed values: (resolution product limit in s kHz, arrays, scaling, truncation, bits), finest first.
RULES = (
    (0.5 * 6, ("P", "future"), "antenna_channel", 2.5, 5),
    (0.5 * 40, ("Q",), "antenna_channel", 2.5, 6),
    (4.0 * 36, ("P", "future"), "row_channel", 1.5, 10),
    (4.0 * 80, ("Q",), "row_channel", 1.5, 8),
)
ADVICE = {
    "row": "simplest; couples polarisations and channels and fails under interference",
    "antenna_channel": "fewest factors; needs care for autocorrelations; goes with centrally dense tables and many channels and antennas",
    "row_channel": "keeps autocorrelations; goes with flatter tables",
}


def recommend(dt_s: float, dnu_khz: float, array: str) -> tuple[CodecConfig | None, str]:
    """Between an array's two limits the coarser rule holds; beyond both more bits or none are advised."""
    own = [r for r in RULES if array in r[1]]
    if not own:
        return None, "untested array: needs experiments of its own"
    for limit, _, scaling, trunc, bits in own:
        if dt_s * dnu_khz <= limit + 1e-9:
            return CodecConfig(scaling=scaling, quantiser="tgauss", trunc=trunc, bits=bits), ADVICE[scaling]
    return None, "coarser than the guideline covers: use more bits, or no compression"


def recommended(dt_s: Column, dnu_khz: Column, array: Column) -> Column:
    """The same of columns: a struct of scaling, trunc and bits, null where ``recommend`` gives no method."""
    out = F.lit(None)
    for limit, arrays, scaling, trunc, bits in reversed(RULES):  # each array's finest rule is asked first
        one = F.struct(F.lit(scaling).alias("scaling"), F.lit(trunc).alias("trunc"), F.lit(bits).alias("bits"))
        out = F.when(array.isin(*arrays) & (dt_s * dnu_khz <= limit + 1e-9), one).otherwise(out)
    return out
