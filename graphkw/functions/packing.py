"""Distance and leaf in one long, so that the least of both is a plain minimum (a hash aggregate)."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Leaves take the low 44 bits, distances the 19 above.
LEAF_BITS = 44


def pack(d: Column, leaf: Column) -> Column:
    return F.shiftleft(d.cast("long"), LEAF_BITS).bitwiseOR(leaf)


def distance(packed: Column) -> Column:
    return F.shiftright(packed, LEAF_BITS)


def leaf(packed: Column) -> Column:
    return packed.bitwiseAND(F.lit((1 << LEAF_BITS) - 1))
