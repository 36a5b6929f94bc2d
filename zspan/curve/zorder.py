"""Z-order codes: cells of coordinates and the interleaving of their bits."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

CELL = 5e-7
#: Masks of the five spreading rounds for 32-bit inputs, as (shift, mask).
_ROUNDS = ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555))


def cell_x(lon: Column, cell: float = CELL) -> Column:
    return F.floor((lon.cast("double") + F.lit(180.0)) / F.lit(cell)).cast("long")


def cell_y(lat: Column, cell: float = CELL) -> Column:
    return F.floor((lat.cast("double") + F.lit(90.0)) / F.lit(cell)).cast("long")


def cell_of_units(u: Column, units_per_cell: int) -> Column:
    """Cell of a fixed-point coordinate in units of the default cell."""
    return u if units_per_cell == 1 else F.floor(u / F.lit(units_per_cell)).cast("long")


def _spread(v: Column) -> Column:
    for shift, mask in _ROUNDS:
        v = v.bitwiseOR(F.shiftleft(v, shift)).bitwiseAND(F.lit(mask))
    return v


def _squeeze(v: Column) -> Column:
    v = v.bitwiseAND(F.lit(_ROUNDS[-1][1]))
    for (shift, _), mask in zip(reversed(_ROUNDS), [*(m for _, m in reversed(_ROUNDS[:-1])), 0x00000000FFFFFFFF], strict=True):
        v = v.bitwiseOR(F.shiftright(v, shift)).bitwiseAND(F.lit(mask))
    return v


def z_address(x: Column, y: Column) -> Column:
    """Code of a cell, x in the even bits; x below 2^31 and y below 2^31."""
    return _spread(x.cast("long")).bitwiseOR(F.shiftleft(_spread(y.cast("long")), 1))


def z_decode(z: Column) -> tuple[Column, Column]:
    return _squeeze(z), _squeeze(F.shiftright(z, 1))


def z_address_wide(x: Column, y: Column) -> Column:
    """Codes of cells up to 2^46, which need more than 63 bits, as DECIMAL(30,0)."""
    low = z_address(x.bitwiseAND(F.lit((1 << 24) - 1)), y.bitwiseAND(F.lit((1 << 24) - 1)))
    high = z_address(F.shiftright(x.cast("long"), 24), F.shiftright(y.cast("long"), 24))
    return (high.cast("decimal(20,0)") * F.lit(1 << 48).cast("decimal(20,0)") + low.cast("decimal(20,0)")).cast("decimal(30,0)")


def bits_needed(cell: float) -> int:
    """Bits of a code over the whole domain at this cell size."""
    return (int(360 / cell) - 1).bit_length() + (int(180 / cell) - 1).bit_length()


def check_bits(cell: float) -> None:
    if (int(360 / cell) - 1).bit_length() > 31:
        raise ValueError(f"cell {cell} needs {bits_needed(cell)} bits: use z_address_wide")
