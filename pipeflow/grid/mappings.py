"""Cell mappings as column expressions: for a target cell, the source cell, or null off the source grid."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

from pipeflow.grid.shape import GridShape, div


@dataclass(frozen=True)
class CellMap:
    """source, target: the shapes; of(t): the source cell of target cell t."""

    name: str
    source: GridShape
    target: GridShape
    of: Callable[[Column], Column]


def _by_xy(name: str, source: GridShape, target: GridShape, f: Callable[[Column, Column], tuple[Column, Column]], checked: bool = False) -> CellMap:
    def of(t: Column) -> Column:
        x, y = f(target.x(t), target.y(t))
        cell = source.cell(x, y)
        return F.when(source.holds(x, y), cell) if checked else cell

    return CellMap(name, source, target, of)


def identity(s: GridShape) -> CellMap:
    return CellMap("identity", s, s, lambda t: t)


def transpose(s: GridShape) -> CellMap:
    return _by_xy("transpose", s, GridShape(s.height, s.width), lambda x, y: (y, x))


def flip_x(s: GridShape) -> CellMap:
    return _by_xy("flip_x", s, s, lambda x, y: (F.lit(s.width - 1) - x, y))


def flip_y(s: GridShape) -> CellMap:
    return _by_xy("flip_y", s, s, lambda x, y: (x, F.lit(s.height - 1) - y))


def rotate90(s: GridShape) -> CellMap:
    """Clockwise."""
    return _by_xy("rot90", s, GridShape(s.height, s.width), lambda x, y: (y, F.lit(s.height - 1) - x))


def rotate180(s: GridShape) -> CellMap:
    return CellMap("rot180", s, s, lambda t: F.lit(s.n - 1) - t)


def rotate270(s: GridShape) -> CellMap:
    return _by_xy("rot270", s, GridShape(s.height, s.width), lambda x, y: (F.lit(s.width - 1) - y, x))


def shift(s: GridShape, dx: int, dy: int) -> CellMap:
    """The target shows the source moved by (dx, dy); what comes from outside has no source."""
    return _by_xy("shift", s, s, lambda x, y: (x - F.lit(dx), y - F.lit(dy)), checked=True)


def roll(s: GridShape, dx: int, dy: int) -> CellMap:
    return _by_xy("roll", s, s, lambda x, y: (F.pmod(x - F.lit(dx), F.lit(s.width)), F.pmod(y - F.lit(dy), F.lit(s.height))))


def upscale(s: GridShape, k: int) -> CellMap:
    return _by_xy("upscale", s, GridShape(s.width * k, s.height * k), lambda x, y: (div(x, k), div(y, k)))


def downscale(s: GridShape, k: int) -> CellMap:
    return _by_xy("downscale", s, GridShape(s.width // k, s.height // k), lambda x, y: (x * k, y * k))


def affine(s: GridShape, x_by: tuple[int, int, int], y_by: tuple[int, int, int], scale: int) -> CellMap:
    """Source x = (p x + q y + r) // scale, y likewise, in whole numbers; off the grid where they are."""

    def f(x: Column, y: Column) -> tuple[Column, Column]:
        return tuple(F.floor((x * p + y * q + r) / F.lit(float(scale))).cast("long") for p, q, r in (x_by, y_by))  # type: ignore[return-value]

    return _by_xy("affine", s, s, f, checked=True)


def scatter(s: GridShape, a: int, c: int) -> CellMap:
    """src = (a t + c) mod n: no locality at all. a is raised until it has no factor in common with n."""
    while math.gcd(a, s.n) != 1:
        a += 1
    return CellMap("scatter", s, s, lambda t: F.pmod(t * a + c, F.lit(s.n).cast("long")))


# Projections. Planes are scaled to the unit square: u to the right, v downwards, both in [0, 1].
Forward = Callable[[Column, Column], tuple[Column, Column]]


def equirectangular_inverse(u: Column, v: Column) -> tuple[Column, Column]:
    """Longitude and latitude in radians."""
    return (u - F.lit(0.5)) * (2 * math.pi), (F.lit(0.5) - v) * math.pi


def equirectangular(lon: Column, lat: Column) -> tuple[Column, Column]:
    return lon / (2 * math.pi) + 0.5, F.lit(0.5) - lat / math.pi


def sinusoidal(lon: Column, lat: Column) -> tuple[Column, Column]:
    return lon * F.cos(lat) / (2 * math.pi) + 0.5, F.lit(0.5) - lat / math.pi


def mercator(lon: Column, lat: Column) -> tuple[Column, Column]:
    """The square Mercator plane; the polar caps lie off it."""
    return lon / (2 * math.pi) + 0.5, F.lit(0.5) - F.log(F.tan(lat / 2 + math.pi / 4)) / (2 * math.pi)


def azimuthal_equal_area(lon: Column, lat: Column) -> tuple[Column, Column]:
    k = F.sqrt(F.lit(2.0) / (F.lit(1.0) + F.cos(lat) * F.cos(lon)))
    return k * F.cos(lat) * F.sin(lon) / 4 + 0.5, F.lit(0.5) - k * F.sin(lat) / 4


def stereographic(lon: Column, lat: Column) -> tuple[Column, Column]:
    """Centred on the equator; scaled so that the near hemisphere fills the square."""
    k = F.lit(2.0) / (F.lit(1.0) + F.cos(lat) * F.cos(lon))
    return k * F.cos(lat) * F.sin(lon) / 4 + 0.5, F.lit(0.5) - k * F.sin(lat) / 4


PROJECTIONS: dict[str, Forward] = {"equirectangular": equirectangular, "sinusoidal": sinusoidal, "mercator": mercator, "laea": azimuthal_equal_area, "stereographic": stereographic}


def through_sphere(s: GridShape, source: str, target_inverse: Forward = equirectangular_inverse, target: GridShape | None = None) -> CellMap:
    """Target plane to sphere to source plane, from cell centre to the cell that holds its image."""
    t_shape = target or s

    def f(x: Column, y: Column) -> tuple[Column, Column]:
        lon, lat = target_inverse((x + F.lit(0.5)) / float(t_shape.width), (y + F.lit(0.5)) / float(t_shape.height))
        u, v = PROJECTIONS[source](lon, lat)
        return F.floor(u * float(s.width)).cast("long"), F.floor(v * float(s.height)).cast("long")

    return _by_xy(f"sphere_{source}", s, t_shape, f, checked=True)
