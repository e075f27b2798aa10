"""The three forms of choosing the smaller of two values, and the arithmetic of changes."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

STYLES = ("least", "mask", "case")


def smaller(a: Column, b: Column, style: str = "least") -> Column:
    """``least``: a conditional move; ``mask``: arithmetic on a 0/1 flag; ``case``: a conditional store."""
    if style == "least":
        return F.least(a, b)
    if style == "mask":
        flag = (b < a).cast("bigint")
        return b * flag + a * (F.lit(1) - flag)
    if style == "case":
        return F.when(b < a, b).otherwise(a)
    raise ValueError(f"style must be one of {STYLES}")


def change_mask(new: Column, old: Column) -> Column:
    """Zero if and only if no row changed."""
    return F.bit_or(new.bitwiseXOR(old))


def ratio(a: Column, b: Column, digits: int = 6) -> Column:
    return F.round(F.try_divide(a.cast("double"), b.cast("double")), digits)
