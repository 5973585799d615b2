"""Candidates of reverse-neighbour queries: six sectors, k nearest in each.

In a half-open sector of 60 degrees, k points nearer to the query keep every farther point from being a member. Points
at the query's own place prune nothing and are always members (sector -1)."""

from __future__ import annotations

from functools import reduce
from math import cos, pi, sin

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from revnn.functions.geometry import sector_any
from revnn.operators.knn import OTHER
from revnn.plans import grid
from revnn.plans.cuts import cut
from revnn.plans.density import Density, density


def top_by_sector(near: DataFrame, sectors: int = 6, most: int | None = None) -> DataFrame:
    """(qid, id, x, y, d2, sector, rank_in_sector) from (qid, qx, qy, k, id, x, y, d2)."""
    d = near.withColumn("sector", sector_any(F.col("x") - F.col("qx"), F.col("y") - F.col("qy"), sectors))
    if most is None:
        w = Window.partitionBy("qid", "sector").orderBy("d2", "id")
        return d.withColumn("rank_in_sector", F.row_number().over(w)).where("rank_in_sector <= k OR sector = -1")
    # a constant bound lets each task drop the rest before the exchange; points at the query's place all count as first
    w = Window.partitionBy("qid", "sector", "_own").orderBy("d2", "id")
    d = d.withColumn("_own", F.when(F.col("sector") == -1, F.col("id"))).withColumn("rank_in_sector", F.row_number().over(w))
    d = d.where(F.col("rank_in_sector") <= most).where("rank_in_sector <= k").drop("_own")
    own = F.row_number().over(Window.partitionBy("qid", "sector").orderBy("d2", "id"))
    return d.withColumn("rank_in_sector", F.when(F.col("sector") == -1, own).otherwise(F.col("rank_in_sector")))


def sector_reach(box, s: int, sectors: int = 6) -> Column:
    """How far sector s of a query within the box can see points: its corners and where its rays leave the box."""
    _, x0, y0, x1, y1 = box
    qx, qy = F.col("qx"), F.col("qy")
    inside = (qx >= x0) & (qx <= x1) & (qy >= y0) & (qy <= y1)
    seen = []
    for a in (s, s + 1):
        ux, uy = cos(2 * pi * a / sectors), sin(2 * pi * a / sectors)
        tx = ((x1 if ux > 0 else x0) - qx) / ux if abs(ux) > 1e-12 else F.lit(float("inf"))
        ty = ((y1 if uy > 0 else y0) - qy) / uy if abs(uy) > 1e-12 else F.lit(float("inf"))
        seen.append(F.least(tx, ty))
    far = []
    for cx in (x0, x1):
        for cy in (y0, y1):
            d = F.sqrt((cx - qx) * (cx - qx) + (cy - qy) * (cy - qy))
            far.append(d)
            seen.append(F.when(sector_any(cx - qx, cy - qy, sectors) == s, d).otherwise(F.lit(0.0)))
    return F.when(inside, F.greatest(*seen) * (1 + 1e-9)).otherwise(F.greatest(*far))


COLUMNS = ("qid", "id", "x", "y", "d2", "sector", "rank_in_sector")


def six_sector(p: DataFrame, q: DataFrame, sectors: int = 6, box=None, spread: Density | None = None, rows: list | None = None) -> DataFrame:
    """(qid, id, x, y, d2, sector, rank_in_sector): discs grow until every sector holds k points or all it can see.

    A bounded batch starts with discs that fit the density around each query, so that one round mostly does; the
    driver sees a count for each query and sector. Larger batches start alike everywhere; one count for each round
    comes to the driver. Queries that are finished leave the loop."""
    rows = grid.bounded(q) if rows is None else rows
    if rows is not None:
        spread = spread or density(p)
        return _batch(p, q, rows, sectors, spread) if rows and spread.box[0] else _none(p, q, sectors)
    box = box or grid.box_of(p)
    q = cut(q)
    k = q.agg(F.max("k")).first()[0] or 1
    radius, done = grid.first_radius(box, 1.5 * sectors * k), []
    while (left := q.count()) and box[0]:
        near = grid.within(p, q.withColumn("_r", F.lit(radius)), "_r", radius, left, box).where(OTHER)
        top = cut(top_by_sector(near, sectors).select(*COLUMNS))
        held = top.groupBy("qid").pivot("sector", list(range(sectors))).count()
        state = q.join(held, "qid", "left")
        fine = reduce(lambda a, b: a & b, ((F.coalesce(F.col(f"`{s}`"), F.lit(0)) >= F.col("k")) | (sector_reach(box, s, sectors) <= radius) for s in range(sectors)))
        state = cut(state.withColumn("_done", fine).drop(*map(str, range(sectors))))
        done.append(top.join(state.where("_done").select("qid"), "qid", "left_semi"))
        q = cut(state.where("NOT _done").drop("_done"))
        radius *= 2
    return reduce(DataFrame.unionByName, done) if done else _none(p, q, sectors)


def _none(p: DataFrame, q: DataFrame, sectors: int) -> DataFrame:
    return top_by_sector(q.join(p, F.lit(False)).withColumn("d2", F.lit(0.0)), sectors).select(*COLUMNS)


def _batch(p: DataFrame, q: DataFrame, rows: list, sectors: int, spread: Density) -> DataFrame:
    box, done = spread.box, []
    if all(r["k"] is None for r in rows):
        return _none(p, q, sectors)
    xy, k = np.array([(r["qx"], r["qy"]) for r in rows], float), np.array([r["k"] for r in rows], float)
    # room for the emptiest of the sectors
    radii = spread.radius(xy, sectors * (k + 2.5 * np.sqrt(k) + 1))
    reach = grid.sector_reaches(box, xy, sectors)
    while rows:
        near = grid.within_each(p, rows, q, radii.tolist(), box).where(OTHER)
        top = cut(top_by_sector(near, sectors, int(max(r["k"] for r in rows))).select(*COLUMNS))
        held = {}
        for r in top.groupBy("qid", "sector").count().collect():
            held.setdefault(r.qid, {})[r.sector] = r["count"]
        full = np.array([all(held.get(r["qid"], {}).get(s, 0) >= r["k"] or far[s] <= radius for s in range(sectors)) for r, far, radius in zip(rows, reach, radii, strict=True)])
        if full.all():
            done.append(top)
            break
        if full.any():
            done.append(top.join(F.broadcast(grid.local([r for r, f in zip(rows, full, strict=True) if f], q).select("qid")), "qid", "left_semi"))
        rows, radii, reach = [r for r, f in zip(rows, full, strict=True) if not f], grid.GROWTH * radii[~full], reach[~full]
    return reduce(DataFrame.unionByName, done)


def six_sector_exact(p: DataFrame, q: DataFrame, sectors: int = 6) -> DataFrame:
    """As :func:`six_sector`, every query meeting every point. For small sets and as a reference."""
    from revnn.functions.geometry import dist2

    d = q.join(p, F.expr(OTHER)).withColumn("d2", dist2("x", "y", "qx", "qy"))
    return top_by_sector(d, sectors).select("qid", "id", "x", "y", "d2", "sector", "rank_in_sector")
