"""What the conic engine is compared with. All return (qid, id) of members unless stated."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, DoubleType, IntegerType, LongType, StructField, StructType

from revnn.functions.geometry import arcs, dist2, sector_any
from revnn.operators import candidates as cand
from revnn.operators import rknn, verify
from revnn.operators.knn import OTHER, knn_grid, knn_radius
from revnn.plans import grid
from revnn.plans.cuts import cut
from revnn.plans.density import density


def six_sector(p: DataFrame, q: DataFrame) -> DataFrame:
    """The same candidates, one kNN query for each."""
    return verify.by_knn(cut(cand.six_sector(p, q)), p, q).where("member").select("qid", "id")


def brute_force(p: DataFrame, q: DataFrame) -> DataFrame:
    return rknn.rknn_definition(p, q)


def arc_scan(p: DataFrame, q: DataFrame, sectors: int = 6) -> tuple[DataFrame, DataFrame]:
    """Bounds (qid, sector, bound) and the pruners' arcs (qid, sector, id, x, y, d2, own, lower, upper).

    A point counts itself among its own pruners, so the bound is the (k+1)-th smallest upper arc. Discs double until
    no unread point could lower a bound (an upper arc is at least half of the distance)."""
    rows = grid.bounded(q)
    if rows is not None:
        return _arc_batch(p, q, rows, sectors)
    box = grid.box_of(p)
    q = cut(q)
    k = q.agg(F.max("k")).first()[0] or 1
    radius, bounds, pruners = grid.first_radius(box, 4.0 * k + 16), [], []
    far = F.sqrt(F.pow(F.greatest(F.col("qx") - box[1], box[3] - F.col("qx")), 2) + F.pow(F.greatest(F.col("qy") - box[2], box[4] - F.col("qy")), 2))
    while (left := q.count()) and box[0]:
        arc = cut(_with_arcs(grid.within(p, q.withColumn("_r", F.lit(radius)), "_r", radius, left, box), sectors))
        w = Window.partitionBy("qid", "sector").orderBy("upper", "id")
        kth = arc.withColumn("n", F.row_number().over(w)).where(F.col("n") == F.col("k") + 1).select("qid", "sector", F.col("upper").alias("bound"))
        every = q.withColumn("sector", F.explode(F.sequence(F.lit(0), F.lit(sectors - 1)))).join(kth, ["qid", "sector"], "left").withColumn("bound", F.coalesce("bound", F.lit(float("inf"))))
        every = cut(every.withColumn("fine", (2 * F.col("bound") <= radius) | (far <= radius)))
        fine = cut(every.groupBy("qid").agg(F.min("fine").alias("fine")).where("fine").select("qid"))
        bounds.append(every.join(fine, "qid", "left_semi").select("qid", "sector", "bound"))
        pruners.append(arc.join(fine, "qid", "left_semi").select("qid", "sector", "id", "x", "y", "d2", "own", "lower", "upper"))
        q = cut(q.join(fine, "qid", "left_anti"))
        radius *= 2
    return (reduce(DataFrame.unionByName, bounds), reduce(DataFrame.unionByName, pruners)) if bounds else _no_arcs(p, q)


ARC = ("qid", "sector", "id", "x", "y", "d2", "own", "lower", "upper")


def _no_arcs(p: DataFrame, q: DataFrame) -> tuple[DataFrame, DataFrame]:
    empty = q.join(p, F.lit(False)).selectExpr("qid", "0 AS sector", "id", "x", "y", "x AS d2", "0 AS own", "x AS lower", "x AS upper")
    return empty.selectExpr("qid", "sector", "upper AS bound"), empty


def _with_arcs(near: DataFrame, sectors: int) -> DataFrame:
    """A row for each point and each sector that it can prune in, or lies in."""
    dx, dy = F.col("x") - F.col("qx"), F.col("y") - F.col("qy")
    near = near.where(OTHER).withColumn("own", sector_any(dx, dy, sectors)).where("own >= 0")
    arc = near.withColumn("sector", F.explode(F.sequence(F.lit(0), F.lit(sectors - 1))))
    lower, upper = arcs(dx, dy, "sector", sectors)
    return arc.withColumns({"lower": lower, "upper": upper}).select(*ARC, "k").where("lower < double('Infinity') OR own = sector")


def _arc_batch(p: DataFrame, q: DataFrame, rows: list, sectors: int) -> tuple[DataFrame, DataFrame]:
    """The scan for a bounded batch: first discs fit the density around each query, the driver holds the bounds."""
    spread = density(p)
    box, inf = spread.box, float("inf")
    if not rows or not box[0]:
        return _no_arcs(p, q)
    xy, k = np.array([(r["qx"], r["qy"]) for r in rows], float), np.array([r["k"] for r in rows], float)
    radii = spread.radius(xy, 12 * (k + 3 * np.sqrt(k) + 2))
    far = np.hypot(np.maximum(xy[:, 0] - box[1], box[3] - xy[:, 0]), np.maximum(xy[:, 1] - box[2], box[4] - xy[:, 1])) * (1 + 1e-9)
    reach = grid.sector_reaches(box, xy, sectors)
    found, pruners = [], []
    while rows:
        arc = cut(_with_arcs(grid.within_each(p, rows, q, radii.tolist(), box), sectors))
        nth = F.row_number().over(Window.partitionBy("qid", "sector").orderBy("upper"))
        kth = arc.select("qid", "k", "sector", "upper", nth.alias("n")).where(F.col("n") <= int(max(r["k"] for r in rows)) + 1).where("n = k + 1")
        bound = {(r.qid, r.sector): r.upper for r in kth.collect()}
        # no point of a sector lies beyond what the sector sees of the box
        ends = [[min(bound.get((r["qid"], s), inf), sees[s]) for s in range(sectors)] for r, sees in zip(rows, reach, strict=True)]
        full = np.array([b <= a or 2 * max(e) <= a for e, a, b in zip(ends, radii, far, strict=True)])
        done = [r for r, f in zip(rows, full, strict=True) if f]
        found += [(r["qid"], s, float(e[s])) for r, e, f in zip(rows, ends, full, strict=True) if f for s in range(sectors)]
        pruners.append(arc.drop("k") if full.all() else arc.drop("k").join(F.broadcast(grid.local(done, q).select("qid")), "qid", "left_semi"))
        rows, radii, far, reach = [r for r, f in zip(rows, full, strict=True) if not f], grid.GROWTH * radii[~full], far[~full], reach[~full]
    bounds = q.sparkSession.createDataFrame(found, StructType([q.schema["qid"], StructField("sector", IntegerType()), StructField("bound", DoubleType())]))
    return bounds, reduce(DataFrame.unionByName, pruners)


def arc_candidates(bounds: DataFrame, pruners: DataFrame) -> DataFrame:
    """(qid, sector, id, x, y, d2): points of a sector within its bound."""
    d = pruners.where("own = sector").join(bounds, ["qid", "sector"])
    return d.where(F.sqrt("d2") <= F.col("bound")).select("qid", "sector", "id", "x", "y", "d2")


def count_closer(d2: np.ndarray, ids: np.ndarray, xy: np.ndarray, k: int, pid: np.ndarray, pxy: np.ndarray, lower: np.ndarray, upper: np.ndarray) -> tuple[np.ndarray, int]:
    """For each candidate of a sector, whether fewer than k pruners are closer to it than the query; distances taken.

    Pruners stand in order of their lower arcs, so those beyond a candidate end the look; those whose upper arc lies
    before it are counted by a search, and the look ends early when k are found."""
    turn = np.argsort(lower, kind="stable")
    pid, pxy, lower, upper = pid[turn], pxy[turn], lower[turn], upper[turn]
    sure, at, own = np.sort(upper), np.sqrt(d2), dict(zip(pid.tolist(), upper.tolist(), strict=True))
    member, taken = np.zeros(len(d2), bool), 0
    for i in range(len(d2)):
        closer = int(np.searchsorted(sure, at[i])) - (own.get(int(ids[i]), np.inf) < at[i])
        end = int(np.searchsorted(lower, at[i]))
        for first in range(0, end, STEP):
            if closer >= k:
                break
            part = slice(first, min(end, first + STEP))
            open_ = np.flatnonzero((upper[part] >= at[i]) & (pid[part] != ids[i])) + first
            dx, dy = xy[i, 0] - pxy[open_, 0], xy[i, 1] - pxy[open_, 1]
            closer += int((dx * dx + dy * dy < d2[i]).sum())
            taken += len(open_)
        member[i] = closer < k
    return member, taken


#: Pruners that are looked at before the count is.
STEP = 256


def arc_verify(c: DataFrame, bounds: DataFrame, pruners: DataFrame, q: DataFrame) -> DataFrame:
    """(qid, id, member): counts pruners by their arcs, a sector of a query at a time (both sides hold O(k) rows); only
    where a candidate lies between the arcs a distance is taken."""
    use = pruners.join(bounds, ["qid", "sector"]).where("lower < bound").select(F.col("qid").alias("p_qid"), F.col("sector").alias("p_sector"), F.col("id").alias("pid"), F.col("x").alias("px"), F.col("y").alias("py"), "lower", "upper")
    d = c.join(q.select("qid", "k"), "qid").select("qid", "sector", "id", "x", "y", "d2", "k")

    def check(cand: pd.DataFrame, by: pd.DataFrame) -> pd.DataFrame:
        if cand.empty:
            return pd.DataFrame({"qid": [], "id": [], "member": []})
        xy = lambda f, a, b: f[[a, b]].to_numpy(float)
        member, _ = count_closer(cand["d2"].to_numpy(), cand["id"].to_numpy(), xy(cand, "x", "y"), int(cand["k"].iloc[0]), by["pid"].to_numpy(), xy(by, "px", "py"), by["lower"].to_numpy(float), by["upper"].to_numpy(float))
        return pd.DataFrame({"qid": cand["qid"], "id": cand["id"], "member": member})

    return d.groupBy("qid", "sector").cogroup(use.groupBy("p_qid", "p_sector")).applyInPandas(check, StructType([q.schema["qid"], StructField("id", LongType()), StructField("member", BooleanType())]))


def arc_bound(p: DataFrame, q: DataFrame, sectors: int = 6) -> DataFrame:
    """Per-sector arc bounds for candidates, counting for verification."""
    bounds, pruners = arc_scan(p, q, sectors)
    m = arc_verify(arc_candidates(bounds, pruners), bounds, pruners, q).where("member").select("qid", "id")
    return m.unionByName(same_place(p, q))


def same_place(p: DataFrame, q: DataFrame) -> DataFrame:
    """Points at a query's own location: members whatever else there is."""
    return p.join(q, (F.col("x") == F.col("qx")) & (F.col("y") == F.col("qy"))).where(OTHER).select("qid", "id")


def stored_radii(p: DataFrame, k: int) -> DataFrame:
    """(id, x, y, k, r): every point's radius, to be kept as a table for one k."""
    return p.join(knn_radius(p, None, k), "id")


def lookup(r: DataFrame, q: DataFrame) -> DataFrame:
    """Members from stored radii: which circles hold the query; equal k only.

    A circle belongs to the grid whose cells are at least as wide as it is, so it touches four of them at most whatever
    the other radii are; a query looks into its cell of each grid that occurs."""
    r = r.where("r IS NOT NULL")
    finite = r.where("r < double('Infinity')").withColumn("level", F.ceil(F.log2(F.greatest(2 * F.col("r"), F.lit(1e-300)))).cast("int") + 1)
    side = F.pow(F.lit(2.0), F.col("level"))
    span = lambda c: F.explode(F.sequence(F.floor((F.col(c) - F.col("r")) / side), F.floor((F.col(c) + F.col("r")) / side)))
    circles = finite.withColumn("cx", span("x")).withColumn("cy", span("y"))
    asked = q.join(finite.select("level").distinct())
    asked = asked.withColumns({"cx": F.floor(F.col("qx") / side), "cy": F.floor(F.col("qy") / side)})
    hit = circles.join(asked, ["level", "cx", "cy", "k"]).where(OTHER).where(F.sqrt(dist2("x", "y", "qx", "qy")) <= F.col("r"))
    whole = r.where("r = double('Infinity')").join(q, "k").where(OTHER)
    return hit.select("qid", "id").unionByName(whole.select("qid", "id"))


def knn_as_rknn(p: DataFrame, q: DataFrame) -> DataFrame:
    """The kNN answer given for the reverse one: (qid, id). It differs; see measures.recall."""
    return knn_grid(p, q).select("qid", "id")
