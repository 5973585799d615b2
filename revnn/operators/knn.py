"""Nearest neighbours: by definition, by growing discs on a grid, and kNN radii.

A point is no neighbour of itself (identity by id, so a duplicate location is one). Results are tie-inclusive: every
point at the distance of the k-th is returned."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from revnn.functions.geometry import dist2
from revnn.plans import blocks, grid
from revnn.plans.cuts import cut
from revnn.plans.density import Density, density

OTHER = "q_id IS NULL OR id <> q_id"


def knn_exact(p: DataFrame, q: DataFrame) -> DataFrame:
    """(qid, id, dist, rank) by definition: every query meets every point. For small sets and as a reference."""
    d = q.join(p, F.expr(OTHER)).withColumn("d2", dist2("x", "y", "qx", "qy"))
    return ranked(d)


def ranked(d: DataFrame) -> DataFrame:
    w = Window.partitionBy("qid").orderBy("d2")
    return d.withColumn("rank", F.rank().over(w)).where("rank <= k").select("qid", "id", F.sqrt("d2").alias("dist"), "rank")


def knn_grid(p: DataFrame, q: DataFrame, spread: Density | None = None) -> DataFrame:
    """As :func:`knn_exact` without a nested-loop join: discs grow until they hold k points or the whole box.

    A bounded batch starts with discs that fit the density around each query."""
    rows = grid.bounded(q)
    if rows is not None:
        spread = spread or density(p)
        return _batch(p, q, rows, spread) if rows and spread.box[0] else ranked(q.join(p, F.lit(False)).withColumn("d2", F.lit(0.0)))
    box = grid.box_of(p)
    q = cut(q)
    k = q.agg(F.max("k")).first()[0] or 1
    radius, done = grid.first_radius(box, 2.0 * k), []
    while (left := q.count()) and box[0]:
        reach = q.withColumn("_r", F.lit(radius))
        near = grid.within(p, reach, "_r", radius, left, box).where(OTHER)
        w = Window.partitionBy("qid").orderBy("d2")
        near = near.withColumn("rank", F.rank().over(w)).where("rank <= k")
        enough = near.groupBy("qid").agg(F.count(F.lit(1)).alias("_n"))
        far = F.sqrt(F.pow(F.greatest(F.col("qx") - box[1], box[3] - F.col("qx")), 2) + F.pow(F.greatest(F.col("qy") - box[2], box[4] - F.col("qy")), 2))
        state = cut(q.join(enough, "qid", "left").withColumn("_all", far <= radius).withColumn("_done", (F.coalesce("_n", F.lit(0)) >= F.col("k")) | F.col("_all")))
        finished = state.where("_done").select("qid")
        done.append(cut(near.join(finished, "qid", "left_semi").select("qid", "id", F.sqrt("d2").alias("dist"), "rank")))
        q = cut(state.where("NOT _done").drop("_n", "_all", "_done"))
        radius *= 2
    if not done:
        return ranked(q.join(p, F.lit(False)).withColumn("d2", F.lit(0.0)))
    return reduce(DataFrame.unionByName, done)


def _batch(p: DataFrame, q: DataFrame, rows: list, spread: Density) -> DataFrame:
    box, done = spread.box, []
    xy, k = np.array([(r["qx"], r["qy"]) for r in rows], float), np.array([r["k"] for r in rows], float)
    far = np.hypot(np.maximum(xy[:, 0] - box[1], box[3] - xy[:, 0]), np.maximum(xy[:, 1] - box[2], box[4] - xy[:, 1])) * (1 + 1e-9)
    radii = spread.radius(xy, k + 3 * np.sqrt(k) + 2)
    while rows:
        near = grid.within_each(p, rows, q, radii.tolist(), box).where(OTHER)
        near = near.withColumn("rank", F.rank().over(Window.partitionBy("qid").orderBy("d2"))).where(F.col("rank") <= int(max(r["k"] for r in rows)))
        near = cut(near.where("rank <= k").select("qid", "id", F.sqrt("d2").alias("dist"), "rank"))
        held = {r.qid: r["count"] for r in near.groupBy("qid").count().collect()}
        full = np.array([held.get(r["qid"], 0) >= r["k"] or a <= b for r, a, b in zip(rows, far, radii, strict=True)])
        if full.all():
            done.append(near)
            break
        if full.any():
            done.append(near.join(F.broadcast(grid.local([r for r, f in zip(rows, full, strict=True) if f], q).select("qid")), "qid", "left_semi"))
        rows, radii, far = [r for r, f in zip(rows, full, strict=True) if not f], grid.GROWTH * radii[~full], far[~full]
    return reduce(DataFrame.unionByName, done)


def knn_radius(p: DataFrame, ids: DataFrame | None, k: int, method: str = "blocks") -> DataFrame:
    """(id, k, r): distance to the k-th of the other points, infinite if there are fewer. ids: (id), or all points.

    method: 'blocks' for any number of points, 'grid' for few of them, 'exact' by definition."""
    some = p if ids is None else p.join(ids.select("id"), "id", "left_semi")
    if method == "blocks":
        at = blocks.layout(p, k)
        asked = None if ids is None else some.join(at.places.select("at", "x", "y"), ["x", "y"]).select("at").distinct()
        r = blocks.radii(at, k, asked).join(at.places.select("at", F.explode("ids").alias("id")), "at")
        if ids is not None:
            r = r.join(ids.select("id"), "id", "left_semi")
        return r.select("id", F.lit(k).alias("k"), F.sqrt("r2").alias("r"))
    q = some.select(F.col("id").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"), F.col("id").alias("q_id"), F.lit(k).alias("k"))
    near = (knn_grid if method == "grid" else knn_exact)(p, q)
    r = near.groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.max("dist").alias("far"))
    r = some.select("id").join(r, F.col("id") == F.col("qid"), "left")
    return r.select("id", F.lit(k).alias("k"), F.when(F.coalesce("n", F.lit(0)) >= k, F.col("far")).otherwise(F.lit(float("inf"))).alias("r"))


def knn_self(p: DataFrame, k: int, method: str = "blocks") -> DataFrame:
    """(qid, id, dist, rank) for every point of p."""
    if method == "blocks":
        at = blocks.layout(p, k)
        near = blocks.within(at, blocks.radii(at, k))
        ids = at.places.select("at", F.explode("ids").alias("id"))
        d = near.join(ids.toDF("at", "qid"), "at").join(ids.toDF("other", "id"), "other").where("id <> qid")
        # all of them rank within k, so ranks are only taken where they are read
        return d.select("qid", "id", F.sqrt("d2").alias("dist"), F.rank().over(Window.partitionBy("qid").orderBy("d2")).alias("rank"))
    q = p.select(F.col("id").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"), F.col("id").alias("q_id"), F.lit(k).alias("k"))
    return (knn_grid if method == "grid" else knn_exact)(p, q)


def nn_graph(p: DataFrame) -> DataFrame:
    """(src, dst) of each point's nearest neighbours, src < dst."""
    e = knn_self(p, 1)
    return e.select(F.least("qid", "id").alias("src"), F.greatest("qid", "id").alias("dst")).distinct()
