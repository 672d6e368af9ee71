"""Vector expressions on array columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(x: Column, y: Column) -> Column:
    return F.aggregate(F.zip_with(x, y, lambda a, b: a.cast("double") * b.cast("double")), F.lit(0.0), lambda s, v: s + v)


def add(x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda a, b: a + b)


def combine(slots: list[Column], how: str) -> Column:
    """Vectors of one id from its internal tables: ``sum`` (equal widths) or ``concat``."""
    if how == "concat":
        return F.concat(*slots)
    out = slots[0]
    for s in slots[1:]:
        out = add(out, s)
    return out


def quantize(vec: Column, bits: int, scale: float) -> Column:
    """Nearest of 2**bits - 1 symmetric levels in [-scale, scale]."""
    top = (1 << (bits - 1)) - 1
    level = lambda x: F.greatest(F.least(F.round(x * top / scale), F.lit(float(top))), F.lit(float(-top)))
    return F.transform(vec, lambda x: level(x) * scale / top)


def norm_count(count: Column, norm: Column) -> Column:
    """Use counts brought to 1 .. 2: 1 + count / L2 norm of the counts; 1 where all are zero."""
    return F.when(norm > 0, 1 + count / norm).otherwise(F.lit(1.0))


def bits_needed(rows: Column) -> Column:
    """Bits of a map entry that can name ``rows`` rows."""
    return F.greatest(F.ceil(F.log2(rows.cast("double"))), F.lit(1)).cast("int")
