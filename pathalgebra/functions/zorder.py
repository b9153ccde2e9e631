"""z-order codes as column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

_STEPS = ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555))


def _spread(x: Column) -> Column:
    for shift, mask in _STEPS:
        x = x.bitwiseOR(F.shiftleft(x, shift)).bitwiseAND(F.lit(mask).cast("long"))
    return x


def zorder(r: Column, c: Column) -> Column:
    """Bits of r and c in turn, r's first; both below 2^31."""
    return F.shiftleft(_spread(r.cast("long")), 1).bitwiseOR(_spread(c.cast("long")))
