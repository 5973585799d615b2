"""Distances, sectors, conics and arcs as Column expressions (code-generated, no UDF)."""

from __future__ import annotations

from math import pi, sqrt

from pyspark.sql import Column
from pyspark.sql import functions as F

ROOT3 = sqrt(3.0)
#: Conic tests only save work, so they may be cautious: a relative margin that covers rounding.
MARGIN = 1e-12


def col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c if isinstance(c, Column) else F.lit(c)


def dist2(ax, ay, bx, by) -> Column:
    """Squared planar distance; the same bits from both sides."""
    dx, dy = col(ax) - col(bx), col(ay) - col(by)
    return dx * dx + dy * dy


def dist(ax, ay, bx, by) -> Column:
    return F.sqrt(dist2(ax, ay, bx, by))


def dist_v(a, b) -> Column:
    """Euclidean distance of two arrays, in double precision."""
    square = F.zip_with(col(a), col(b), lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double")))
    return F.sqrt(F.aggregate(square, F.lit(0.0), lambda s, x: s + x))


def sector(dx, dy) -> Column:
    """0..5, half-open sectors of 60 degrees from the x axis; -1 at the query's own place. Sign tests, no angle."""
    x, y = col(dx), col(dy)
    up, down = y - ROOT3 * x, y + ROOT3 * x
    upper = F.when((y >= 0) & (x > 0) & (up < 0), 0).when((y > 0) & (down > 0), 1).otherwise(2)
    lower = F.when((x < 0) & (up > 0), 3).when(down < 0, 4).otherwise(5)
    return F.when((x == 0) & (y == 0), -1).when((y > 0) | ((y == 0) & (x > 0)), upper).when((y == 0) & (x < 0), 3).otherwise(lower)


def sector_any(dx, dy, sectors: int = 6) -> Column:
    """As :func:`sector` for other counts of sectors."""
    if sectors == 6:
        return sector(dx, dy)
    angle = F.atan2(col(dy), col(dx))
    turn = F.when(angle < 0, angle + 2 * pi).otherwise(angle)
    return F.when((col(dx) == 0) & (col(dy) == 0), -1).otherwise(F.least(F.floor(turn * sectors / (2 * pi)).cast("int"), F.lit(sectors - 1)))


def ellipse_side(px, py, ax, ay, bx, by, total) -> Column:
    """-1 inside, 0 on, 1 outside the ellipse with foci a and b and sum of distances `total`."""
    return F.signum(dist(px, py, ax, ay) + dist(px, py, bx, by) - col(total)).cast("int")


def hyperbola_side(px, py, ax, ay, bx, by, difference) -> Column:
    """1 where dist(p, a) - dist(p, b) is larger than `difference` (the side of b's branch), else 0 or -1."""
    return F.signum(dist(px, py, ax, ay) - dist(px, py, bx, by) - col(difference)).cast("int")


def arcs(dx, dy, s, sectors: int = 6) -> tuple[Column, Column]:
    """Lower and upper arc of a pruner at (dx, dy) from the query, in sector s (a number or a column): where its bisector meets the sector.

    Points of the sector beyond the upper arc are surely nearer to the pruner, points within the lower arc surely not."""
    width = 2 * pi / sectors
    d = F.sqrt(col(dx) * col(dx) + col(dy) * col(dy))
    angle = F.atan2(col(dy), col(dx)) - col(s) * width
    turn = F.pmod(angle, F.lit(2 * pi))
    to = lambda edge: F.least(F.abs(turn - edge), 2 * pi - F.abs(turn - edge))
    far = F.greatest(to(0.0), to(width))
    near = F.when(turn <= width, 0.0).otherwise(F.least(to(0.0), to(width)))
    reach = lambda a, slack: F.when(F.cos(a) > 1e-12, d / (2 * F.cos(a)) * slack).otherwise(F.lit(float("inf")))
    return reach(near, 1 - MARGIN), F.when(far >= pi / 2, F.lit(float("inf"))).otherwise(reach(far, 1 + MARGIN))
