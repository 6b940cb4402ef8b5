"""Column functions over grid cells: cell = cy * n + cx."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def axis_index(v: Column, lo: float, hi: float, n: int) -> Column:
    """Index of the equal-width interval of v on one axis; the upper bound belongs to the last, outside values to the nearest, and an empty axis is interval 0."""
    if hi == lo:
        return F.lit(0)
    at = F.floor((v - F.lit(lo)) / F.lit(hi - lo) * F.lit(n))
    return F.greatest(F.lit(0), F.least(F.lit(n - 1), at)).cast("int")


def grid_cell(x: Column, y: Column, grid) -> Column:
    return axis_index(y, grid.ymin, grid.ymax, grid.n) * grid.n + axis_index(x, grid.xmin, grid.xmax, grid.n)


def cell_x(cell: Column, n: int) -> Column:
    return F.pmod(cell, F.lit(n))


def cell_y(cell: Column, n: int) -> Column:
    return F.floor(cell / F.lit(n)).cast("int")


def chebyshev(a: Column, b: Column, n: int) -> Column:
    return F.greatest(F.abs(cell_x(a, n) - cell_x(b, n)), F.abs(cell_y(a, n) - cell_y(b, n)))


def is_adjacent(a: Column, b: Column, n: int) -> Column:
    """Whether two different cells touch, by side or corner."""
    return chebyshev(a, b, n) == 1


def euclid(a: Column, b: Column, grid) -> Column:
    """Distance of two cells' centres."""
    dx = (cell_x(a, grid.n) - cell_x(b, grid.n)) * F.lit(grid.width)
    dy = (cell_y(a, grid.n) - cell_y(b, grid.n)) * F.lit(grid.height)
    return F.sqrt(dx * dx + dy * dy)


def haversine(lat1: Column, lon1: Column, lat2: Column, lon2: Column, radius: float = 6371008.8) -> Column:
    """Great-circle distance in metres, for points given in degrees."""
    p, q = F.radians(lat2 - lat1) / 2, F.radians(lon2 - lon1) / 2
    h = F.sin(p) * F.sin(p) + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * F.sin(q) * F.sin(q)
    return F.lit(2 * radius) * F.asin(F.sqrt(F.least(F.lit(1.0), h)))


def encode_trip(cells: Column) -> Column:
    """A trip as text: cells joined by '-'."""
    return F.array_join(F.transform(cells, lambda c: c.cast("string")), "-")


def decode_trip(text: Column) -> Column:
    return F.transform(F.split(text, "-"), lambda c: c.cast("int"))
