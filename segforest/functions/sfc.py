"""Morton keys of quad- and octrees (up to 20 levels in a long), as Column expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def _spread(v: Column, steps: list[tuple[int, int]]) -> Column:
    for shift, mask in steps:
        v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask))
    return v


# Fixed masks of bit interleaving.
_THREE = [(32, 0x1F00000000FFFF), (16, 0x1F0000FF0000FF), (8, 0x100F00F00F00F00F), (4, 0x10C30C30C30C30C3), (2, 0x1249249249249249)]
_TWO = [(16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)]


def morton3(x: Column, y: Column, z: Column) -> Column:
    sx, sy, sz = (_spread(v.cast("long"), _THREE) for v in (x, y, z))
    return sx.bitwiseOR(F.shiftleft(sy, 1)).bitwiseOR(F.shiftleft(sz, 2))


def morton2(x: Column, y: Column) -> Column:
    return _spread(x.cast("long"), _TWO).bitwiseOR(F.shiftleft(_spread(y.cast("long"), _TWO), 1))


def prefix(key: Column, level: int, top: int, d: int = 3) -> Column:
    """The ancestor at ``level``, as a number of d * level bits; ``key`` has ``top`` levels."""
    return F.shiftright(key, d * (top - level))


def child_id(key: Column, level: int, top: int, d: int = 3) -> Column:
    return prefix(key, level, top, d).bitwiseAND(F.lit((1 << d) - 1))


def coordinate(key: Column, axis: int, levels: int, d: int = 3) -> Column:
    """One integer coordinate out of a key of ``levels`` levels."""
    return sum((F.shiftleft(F.shiftright(key, d * i + axis).bitwiseAND(F.lit(1)), i) for i in range(levels)), F.lit(0))


def cell(v: Column, levels: int) -> Column:
    """Integer cell of a coordinate in [0, 1]; 1 belongs to the last cell."""
    return F.least(F.lit((1 << levels) - 1), F.greatest(F.lit(0), F.floor(v * (1 << levels)))).cast("long")
