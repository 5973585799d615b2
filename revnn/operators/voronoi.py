"""Voronoi cells and the neighbour index, built per grid cell with a halo and certified.

A point's cell is the data box clipped by bisectors with its neighbours from near to far; once the next point is farther
than twice the farthest vertex, nothing can change. A cell is certified if that happened before the halo ended; the
others are built again on cells twice as wide. Near-equal locations must be merged before (sources.distinct_points)."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from revnn.plans import grid
from revnn.plans.cuts import cut

CELLS = "id long, x double, y double, ring array<struct<x:double,y:double>>, nbrs array<struct<id:long,x:double,y:double>>, certified boolean"
#: Shared edges count from this share of the box on.
EDGE = 1e-12


def clip(own: np.ndarray, others: np.ndarray, box, reach: float = np.inf) -> tuple[list, list[int], bool]:
    """Ring, positions of neighbours in `others`, certified; others hold every point within `reach` of own."""
    x0, y0, x1, y1 = box
    ring = [(x0, y0), (x1, y0), (x1, y1), (x0, y1)]
    edge = [-1, -1, -1, -1]  # whose bisector runs from a vertex to the next
    rel = others - own
    d2 = (rel * rel).sum(axis=1)
    far2 = max((x - own[0]) ** 2 + (y - own[1]) ** 2 for x, y in ring)
    for j in np.argsort(d2, kind="stable"):
        if d2[j] > 4 * far2:
            break
        if d2[j] == 0:
            continue
        nx, ny = rel[j]
        c = nx * own[0] + ny * own[1] + d2[j] / 2
        side = [nx * x + ny * y - c for x, y in ring]
        if max(side) <= 0:
            continue
        new, kinds, n = [], [], len(ring)
        for i in range(n):
            a, b, sa, sb = ring[i], ring[(i + 1) % n], side[i], side[(i + 1) % n]
            if sa <= 0:
                new.append(a)
                kinds.append(edge[i])
            if (sa < 0 < sb) or (sb < 0 < sa):
                t = sa / (sa - sb)
                new.append((a[0] + t * (b[0] - a[0]), a[1] + t * (b[1] - a[1])))
                kinds.append(int(j) if sa < 0 else edge[i])
            elif sa == 0 and sb > 0:
                kinds[-1] = int(j)
        ring, edge = new, kinds
        far2 = max(((x - own[0]) ** 2 + (y - own[1]) ** 2 for x, y in ring), default=0.0)
    tiny = EDGE * max(x1 - x0, y1 - y0)
    near = []
    for i, j in enumerate(edge):
        a, b = ring[i], ring[(i + 1) % len(ring)]
        if j >= 0 and (a[0] - b[0]) ** 2 + (a[1] - b[1]) ** 2 > tiny * tiny:
            near.append(j)
    return ring, sorted(set(near)), 4 * far2 <= reach * reach


def box_for(p: DataFrame):
    """n and the box that cells are clipped to: the data's own, widened where it is flat."""
    n, x0, y0, x1, y1 = grid.box_of(p)
    w, h = x1 - x0, y1 - y0
    wide = max(w, h, 1e-9)
    px, py = (wide / 2 if v < wide * 1e-9 else 0.0 for v in (w, h))
    return n, (x0 - px, y0 - py, x1 + px, y1 + py)


def _local(box, side: float):
    def build(part: pd.DataFrame) -> pd.DataFrame:
        xy, ids = part[["x", "y"]].to_numpy(), part["id"].to_numpy()
        home = part["home"].to_numpy()
        cx, cy = int(part["cx"].iloc[0]), int(part["cy"].iloc[0])
        out = []
        lo = ((cx - 1) * side, (cy - 1) * side)
        hi = ((cx + 2) * side, (cy + 2) * side)
        for i in np.flatnonzero(home):
            own = xy[i]
            # surely present: up to the nearest side of the halo that lies within the data box
            sides = [own[0] - lo[0] if lo[0] > box[0] else np.inf, own[1] - lo[1] if lo[1] > box[1] else np.inf, hi[0] - own[0] if hi[0] <= box[2] else np.inf, hi[1] - own[1] if hi[1] <= box[3] else np.inf]
            ring, near, sure = clip(own, xy, box, min(sides))
            out.append((int(ids[i]), own[0], own[1], [{"x": a, "y": b} for a, b in ring], [{"id": int(ids[j]), "x": xy[j, 0], "y": xy[j, 1]} for j in near], sure))
        return pd.DataFrame(out, columns=["id", "x", "y", "ring", "nbrs", "certified"])

    return build


def cells(p: DataFrame, per_cell: int = 60, only: DataFrame | None = None) -> DataFrame:
    """(id, x, y, ring, nbrs, certified) for every point of a set without equal locations, or for the ids of `only`."""
    n, box = box_for(p)
    span = max(box[2] - box[0], box[3] - box[1], 1e-9)
    side = max(grid.first_radius((n, *box), per_cell), span * 1e-7)
    left, done = (p if only is None else only).select(F.col("id").alias("own_id")), []
    while True:
        # a cell reads itself and the eight around it; for what that doesn't certify, cells double
        cx, cy = grid.cell("x", "y", side)
        here = p.withColumns({"hx": cx, "hy": cy})
        whole = side >= span
        near = lambda c: F.explode(F.sequence(F.col(c) - 1, F.col(c) + 1))
        here = here.join(left, F.col("id") == F.col("own_id"), "left").withColumn("open", F.col("own_id").isNotNull()).drop("own_id")
        wanted = here.where("open").select(F.col("hx").alias("wx"), F.col("hy").alias("wy")).distinct()
        halo = here.withColumn("cx", near("hx")).withColumn("cy", near("hy"))
        halo = halo.join(wanted, (F.col("cx") == F.col("wx")) & (F.col("cy") == F.col("wy")), "left_semi")
        home = F.col("open") & (F.col("cx") == F.col("hx")) & (F.col("cy") == F.col("hy"))
        built = cut(halo.select("id", "x", "y", "cx", "cy", home.alias("home")).groupBy("cx", "cy").applyInPandas(_local(box, side), CELLS))
        done.append(built.withColumn("certified", F.lit(True)) if whole else built.where("certified"))
        left = cut(built.where("NOT certified").select(F.col("id").alias("own_id")))
        if whole or left.isEmpty():
            return reduce(DataFrame.unionByName, done)
        side *= 2


def neighbors(p: DataFrame) -> DataFrame:
    """(src, dst) both ways: points whose cells share an edge."""
    c = cells(p).select(F.col("id").alias("src"), F.explode("nbrs.id").alias("dst"))
    return c.unionByName(c.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def delaunay_edges(p: DataFrame) -> DataFrame:
    """(src, dst, len) with src < dst."""
    e = neighbors(p).where("src < dst")
    a, b = p.select(F.col("id").alias("src"), F.col("x").alias("ax"), F.col("y").alias("ay")), p.select(F.col("id").alias("dst"), F.col("x").alias("bx"), F.col("y").alias("by"))
    from revnn.functions.geometry import dist

    return e.join(a, "src").join(b, "dst").select("src", "dst", dist("ax", "ay", "bx", "by").alias("len"))


#: Points that share a task's look for their edges; third points of a first look.
ASKS, THIRDS = 512, 8


def neighbors_by_intervals(p: DataFrame, box=None) -> DataFrame:
    """(src, dst), src < dst, for small sets: every third point bounds the part of a pair's bisector in their edge.

    Every triple counts, but a pair whose part is empty already needs no further ones, so near third points come first.
    This is for checks; the same formula is the SQL reference."""
    box = box or box_for(p)[1]
    parts = -(-max(p.count(), 1) // ASKS)
    part = F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int")
    every = p.select("id", "x", "y").withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).withColumn("asks", F.col("part") == part)

    def build(f: pd.DataFrame) -> pd.DataFrame:
        ids, x, y = f["id"].to_numpy(), f["x"].to_numpy(float), f["y"].to_numpy(float)
        out = [(ids[i], ids[j]) for i in np.flatnonzero(f["asks"]) for j in _by_intervals(i, ids, x, y, box)]
        return pd.DataFrame(out, columns=["src", "dst"])

    return every.groupBy("part").applyInPandas(build, "src long, dst long")


def _by_intervals(i: int, ids: np.ndarray, x: np.ndarray, y: np.ndarray, box) -> np.ndarray:
    """Positions of the points of larger id that share an edge with point i."""
    x0, y0, x1, y1 = box
    ax, ay = x[i], y[i]
    dst = np.flatnonzero((ids > ids[i]) & ((x != ax) | (y != ay)))
    lo, hi = np.full(len(dst), -np.inf), np.full(len(dst), np.inf)
    mx, my, ux, uy = (ax + x[dst]) / 2, (ay + y[dst]) / 2, ay - y[dst], x[dst] - ax
    fine = np.ones(len(dst), bool)

    def bound(slope: np.ndarray, room: np.ndarray, counts=True) -> None:
        # each bound reads: slope * t <= room
        with np.errstate(divide="ignore", invalid="ignore"):
            t = room / slope
        np.minimum(hi, np.where(counts & (slope > 0), t, np.inf).min(axis=0), out=hi)
        np.maximum(lo, np.where(counts & (slope < 0), t, -np.inf).max(axis=0), out=lo)
        np.logical_and(fine, ~(counts & (slope == 0) & (room < 0)).any(axis=0), out=fine)

    bound(np.stack([ux, -ux, uy, -uy]), np.stack([x1 - mx, mx - x0, y1 - my, my - y0]))
    thirds = np.argsort((x - ax) ** 2 + (y - ay) ** 2, kind="stable")
    thirds, at, many = thirds[thirds != i], 0, THIRDS
    while at < len(thirds) and len(dst):
        some = thirds[at : at + many]
        cx, cy = (x[some] - ax)[:, None], (y[some] - ay)[:, None]
        square = (x[some] * x[some] + y[some] * y[some] - ax * ax - ay * ay)[:, None]
        bound(ux * cx + uy * cy, square / 2 - (mx * cx + my * cy), ids[some][:, None] != ids[dst])
        left = fine & (lo < hi)
        dst, lo, hi, mx, my, ux, uy, fine = (a[left] for a in (dst, lo, hi, mx, my, ux, uy, fine))
        at += many
        many = max(THIRDS, 200_000 // max(len(dst), 1))
    return dst[fine & (lo < hi)]


def build_index(p: DataFrame, path: str, version: int = 0) -> DataFrame:
    """Writes the neighbour index: a row for each point with its neighbours, sorted by Z-order key, by super cell."""
    return write_index(cells(p).select("id", "x", "y", "nbrs", F.size("nbrs").alias("deg"), "certified"), path, version)


def write_index(c: DataFrame, path: str, version: int) -> DataFrame:
    """Writes rows (id, x, y, nbrs, deg, certified) as one version; other versions at `path` stay."""
    n, box = box_for(c)
    side = max(max(box[2] - box[0], box[3] - box[1]) / 1024, 1e-12)
    cx, cy = grid.cell(F.col("x") - box[0], F.col("y") - box[1], side)
    c = c.withColumns({"cell": grid.zorder(cx, cy, 11), "version": F.lit(version)}).withColumn("super_cell", F.shiftright("cell", 16))
    out = c.repartition("super_cell").sortWithinPartitions("cell").drop("version")
    out.write.mode("overwrite").partitionBy("super_cell").parquet(f"{path}/version={version}")
    return read_index(c.sparkSession, path, version)


def read_index(spark, path: str, version: int | None = None) -> DataFrame:
    """The index at one version (the newest by default)."""
    d = spark.read.parquet(path)
    version = d.agg(F.max("version")).first()[0] if version is None else version
    return d.where(F.col("version") == version)


def patch(index: DataFrame, added: DataFrame, removed: DataFrame) -> DataFrame:
    """The index (id, x, y, nbrs) after points (id, x, y) come and points (id) go, with deg, certified and changed.

    A removed point changes the cells of its former neighbours only, a new one those of the neighbours that it gets:
    these cells are built anew from the grid cells around them, all others are taken over. Only where the points'
    bounding box changes, which every border cell ends at, the whole index is built again."""
    old = index.select("id", "x", "y")
    now = cut(old.join(removed.select("id"), "id", "left_anti").unionByName(added.select("id", "x", "y")))
    shape = lambda d: d.select("id", "x", "y", "nbrs", F.size("nbrs").alias("deg"), "certified")
    if box_for(old)[1] != box_for(now)[1]:
        fresh = cut(shape(cells(now)))
    else:
        left = index.join(removed.select("id"), "id", "left_semi").select(F.explode("nbrs.id").alias("id"))
        # an index may name a pair at one of its ends only, where cells meet in a corner
        linked = index.select("id", F.explode("nbrs.id").alias("to")).join(removed.select(F.col("id").alias("to")), "to", "left_semi").select("id")
        first = cut(left.unionByName(linked).unionByName(added.select("id")).distinct().join(now, "id", "left_semi"))
        built = cut(shape(cells(now, only=first)))
        reached = built.join(added.select("id"), "id", "left_semi").select(F.explode("nbrs.id").alias("id")).distinct()
        second = cut(reached.join(first, "id", "left_anti"))
        fresh = built if second.isEmpty() else cut(built.unionByName(shape(cells(now, only=second))))
    before = index.select("id", F.array_sort(F.transform("nbrs", lambda n: n["id"])).alias("was"))
    after = fresh.join(before, "id", "left").withColumn("now", F.array_sort(F.transform("nbrs", lambda n: n["id"])))
    after = after.withColumn("changed", ~F.coalesce(F.col("was") == F.col("now"), F.lit(False))).drop("was", "now")
    same = index.select("id", "x", "y", "nbrs").join(removed.select("id"), "id", "left_anti").join(fresh.select("id"), "id", "left_anti")
    return after.unionByName(same.select("id", "x", "y", "nbrs", F.size("nbrs").alias("deg"), F.lit(True).alias("certified"), F.lit(False).alias("changed")))


def insert_query(index: DataFrame, q: DataFrame) -> DataFrame:
    """(qid, id): the Voronoi neighbours a free query point would have, from the points around it.

    Candidates are the nearest points by doubling discs; clipping certifies when enough were read."""
    p = index.select("id", "x", "y")
    n, box = box_for(p)
    q = cut(q.select("qid", "qx", "qy"))
    radius, done = grid.first_radius((n, *box), 30.0), []
    wide = max(box[2] - box[0], box[3] - box[1]) * 2 + radius
    kind = "qid int, nbrs array<long>, certified boolean"

    def build(part: pd.DataFrame) -> pd.DataFrame:
        own = part[["qx", "qy"]].to_numpy()[0]
        bigger = (min(box[0], own[0]), min(box[1], own[1]), max(box[2], own[0]), max(box[3], own[1]))
        _, near, sure = clip(own, part[["x", "y"]].to_numpy(), bigger, float(part["_r"].iloc[0]))
        return pd.DataFrame([(int(part["qid"].iloc[0]), [int(part["id"].iloc[j]) for j in near], sure)], columns=["qid", "nbrs", "certified"])

    while not q.isEmpty():
        near = grid.within(p, q.withColumn("_r", F.lit(radius)), "_r", radius, q.count(), (n, *box))
        built = cut(near.groupBy("qid").applyInPandas(build, kind))
        fine = built.where("certified") if radius < wide else built
        done.append(fine.select("qid", F.explode("nbrs").alias("id")))
        q = cut(q.join(fine.select("qid"), "qid", "left_anti")) if radius < wide else q.limit(0)
        radius *= 2
    return reduce(DataFrame.unionByName, done)


def ring_area(points: list) -> float:
    x, y = [p[0] for p in points], [p[1] for p in points]
    return abs(sum(x[i - 1] * y[i] - x[i] * y[i - 1] for i in range(len(x)))) / 2
