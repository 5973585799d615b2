"""Grid cells: the equi-join form of a distance join, and batch nearest neighbours in growing discs.

A disc is the set of cells of side `side` that its bounding square touches. Exploding the (few) query rows to cells
turns "within radius" into a hash join on (cx, cy) with a residual distance test, so no nested-loop join is planned.
`side` doubles with the disc, so a query never explodes to more than about 5 x 5 cells; points carry no copies."""

from __future__ import annotations

from math import floor, log2, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import DoubleType, StructField, StructType

from revnn.functions.geometry import dist2

#: Query rows up to which their cells are broadcast.
BROADCAST_QUERIES = 20_000


def box_of(p: DataFrame) -> tuple[int, float, float, float, float]:
    """n and the bounding box: one row to the driver."""
    r = p.agg(F.count(F.lit(1)), F.min("x"), F.min("y"), F.max("x"), F.max("y")).first()
    return (r[0], *(0.0 if v is None else float(v) for v in r[1:]))


def first_radius(box, expected: float) -> float:
    """Radius within which a uniform set of this box would hold `expected` points."""
    n, x0, y0, x1, y1 = box
    w, h = max(x1 - x0, 1e-9), max(y1 - y0, 1e-9)
    # on a (nearly) flat box the points lie on a line
    return max(sqrt(w * h * expected / max(n, 1) / 3.14159), max(w, h) * min(1.0, expected / max(n, 1)) / 2)


def cell(x, y, side) -> tuple[Column, Column]:
    c = lambda v: F.floor((F.col(v) if isinstance(v, str) else v) / side).cast("long")
    return c(x), c(y)


def zorder(cx: Column, cy: Column, bits: int = 20) -> Column:
    """Interleaved bits of two non-negative cell numbers: near cells, near keys."""
    z = F.lit(0).cast("long")
    for b in range(bits):
        bit = lambda c, b=b: F.shiftright(c, b).bitwiseAND(F.lit(1).cast("long"))
        z = z.bitwiseOR(F.shiftleft(bit(cx), 2 * b)).bitwiseOR(F.shiftleft(bit(cy), 2 * b + 1))
    return z


def bounded(q: DataFrame) -> list | None:
    """The query rows, if there are at most BROADCAST_QUERIES of them; else None."""
    rows = q.limit(BROADCAST_QUERIES + 1).collect()
    return rows if len(rows) <= BROADCAST_QUERIES else None


def local(rows: list, like: DataFrame, **more: list) -> DataFrame:
    """Rows on the driver as a DataFrame with further double columns: a local relation, nothing runs to read it."""
    schema = StructType([*like.schema.fields, *(StructField(c, DoubleType()) for c in more)])
    plain = [r.asDict(recursive=True) | dict(zip(more, x, strict=True)) for r, *x in zip(rows, *more.values(), strict=True)]
    return like.sparkSession.createDataFrame(pa.Table.from_pylist(plain, to_arrow_schema(schema)), schema)


#: How much discs grow that did not hold enough.
GROWTH = 4


def sector_reaches(box, xy: np.ndarray, sectors: int = 6) -> np.ndarray:
    """(queries, sectors): how far a sector of a query can see points of the box, rounded up."""
    _, x0, y0, x1, y1 = box
    corners = np.array([(a, b) for a in (x0, x1) for b in (y0, y1)])
    to = corners[None] - xy[:, None]
    far = np.hypot(to[..., 0], to[..., 1])
    place = np.mod(np.arctan2(to[..., 1], to[..., 0]), 2 * np.pi) * sectors / (2 * np.pi)
    rays = []
    with np.errstate(divide="ignore", invalid="ignore"):
        for a in range(sectors):
            ux, uy = np.cos(2 * np.pi * a / sectors), np.sin(2 * np.pi * a / sectors)
            tx = ((x1 if ux > 0 else x0) - xy[:, 0]) / ux if abs(ux) > 1e-12 else np.full(len(xy), np.inf)
            ty = ((y1 if uy > 0 else y0) - xy[:, 1]) / uy if abs(uy) > 1e-12 else np.full(len(xy), np.inf)
            rays.append(np.minimum(tx, ty))
    out = np.empty((len(xy), sectors))
    for s in range(sectors):
        # a corner at an edge counts for both sides
        off = np.mod(place - s + sectors / 2, sectors) - sectors / 2
        inside = np.where((off >= -1e-9) & (off <= 1 + 1e-9), far, 0.0).max(axis=1)
        out[:, s] = np.maximum(inside, np.maximum(rays[s], rays[(s + 1) % sectors])) * (1 + 1e-9)
    beyond = ~((xy[:, 0] >= x0) & (xy[:, 0] <= x1) & (xy[:, 1] >= y0) & (xy[:, 1] <= y1))
    out[beyond] = far[beyond].max(axis=1, keepdims=True) * (1 + 1e-9)
    return out


#: Powers of two between the smallest and the largest radius of a batch that have grids of their own.
LEVELS = 12


def within_each(p: DataFrame, rows: list, like: DataFrame, radii: list[float], box, **more: list) -> DataFrame:
    """As :func:`within` for a :func:`bounded` batch with a radius (column _r) for each of its rows.

    Radii that share a power of two share a grid, so a disc explodes to about 5 x 5 cells whatever the others are; a
    point is looked up once for each grid. `more` are further columns of the batch."""
    exact = [int(floor(log2(max(r, 1e-300)))) for r in radii]
    least = max(exact) - LEVELS + 1
    levels = [max(u, least) for u in exact]
    used = sorted(set(levels))
    side, r = F.pow(F.lit(2.0), F.col("_level") + 1), F.col("_r")

    def span(v: str, lo: float, hi: float) -> Column:
        first = F.greatest(F.floor((F.col(v) - r) / side), F.floor(F.lit(lo) / side)).cast("long")
        last = F.least(F.floor((F.col(v) + r) / side), F.floor(F.lit(hi) / side)).cast("long")
        return F.when(first <= last, F.sequence(first, last)).otherwise(F.array().cast("array<bigint>"))

    ask = local(rows, like, _r=list(map(float, radii)), _level=list(map(float, levels)), **more).withColumn("_level", F.col("_level").cast("int"))
    ask = ask.withColumn("cx", F.explode(span("qx", box[1], box[3]))).withColumn("cy", F.explode(span("qy", box[2], box[4])))
    at = p.withColumn("_level", F.explode(F.array(*map(F.lit, used))) if len(used) > 1 else F.lit(used[0]))
    at = at.withColumns({"cx": F.floor(F.col("x") / side).cast("long"), "cy": F.floor(F.col("y") / side).cast("long")})
    found = at.join(F.broadcast(ask), ["_level", "cx", "cy"]).drop("_level", "cx", "cy")
    return found.withColumn("d2", dist2("x", "y", "qx", "qy")).where(F.col("d2") <= r * r)


def within(p: DataFrame, q: DataFrame, radius: str, side: float, n_queries: int | None = None, box=None) -> DataFrame:
    """Rows of q joined with the points at most `radius` away (squared distance d2), by cells of `side`.

    With the box of p, cells beyond it are not asked for."""
    r = F.col(radius)
    bounds = (box[1], box[3], box[2], box[4]) if box else (None,) * 4

    def span(v: str, lo, hi) -> Column:
        a, b = cell(F.col(v) - r, F.lit(0), side)[0], cell(F.col(v) + r, F.lit(0), side)[0]
        if lo is not None:
            a, b = F.greatest(a, F.lit(int(lo // side))), F.least(b, F.lit(int(hi // side)))
        return F.when(a <= b, F.sequence(a, b)).otherwise(F.array().cast("array<bigint>"))

    ask = q.withColumn("cx", F.explode(span("qx", *bounds[:2]))).withColumn("cy", F.explode(span("qy", *bounds[2:])))
    if n_queries is not None and n_queries <= BROADCAST_QUERIES:
        ask = F.broadcast(ask)
    cx, cy = cell("x", "y", side)
    found = p.withColumns({"cx": cx, "cy": cy}).join(ask, ["cx", "cy"]).drop("cx", "cy")
    return found.withColumn("d2", dist2("x", "y", "qx", "qy")).where(F.col("d2") <= r * r)
