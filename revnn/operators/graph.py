"""Walks on the Delaunay graph: hop distances, candidate expansion, nearest neighbours by hops."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from revnn.functions.geometry import dist2, sector
from revnn.operators.knn import OTHER
from revnn.plans.cuts import cut


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.select("src", "dst").unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def hops(edges: DataFrame, sources: DataFrame, max_hops: int | None = None) -> DataFrame:
    """(src, id, hops) from each source (src), level by level; stops when a level is empty or at max_hops."""
    e = cut(both_ways(edges)).select(F.col("src").alias("at"), F.col("dst").alias("id"))
    level = cut(sources.select("src", F.col("src").alias("id"), F.lit(0).alias("hops")))
    seen, n = [level], 0
    while (max_hops is None or n < max_hops) and not level.isEmpty():
        n += 1
        step = level.select("src", F.col("id").alias("at")).join(e, "at").select("src", "id").distinct()
        known = reduce(DataFrame.unionByName, seen).select("src", "id")
        level = cut(step.join(known, ["src", "id"], "left_anti").withColumn("hops", F.lit(n)))
        seen.append(level)
    return reduce(DataFrame.unionByName, seen)


def delaunay_expand(index: DataFrame, q: DataFrame, first: DataFrame | None = None, max_hops: int | None = -1, expand: str = "accepted") -> tuple[DataFrame, DataFrame]:
    """Candidates by expansion over the index (id, x, y, nbrs), and per query how many points were seen and expanded.

    A level is accepted where a point is within k hops and among the k nearest of its sector so far; accepted points
    (or all within the limit: expand='all') hand on to their neighbours. Points at the query's place are carried as
    sector -1. first: (qid, id) neighbours of free queries; members start from their own row. max_hops: -1 for k,
    None for no limit. Expansion of all points without a limit goes through as many levels as the graph is wide: graphs
    of up to WALK_NUMBERS numbers go to a task for each query instead."""
    points = index.select("id", "x", "y", F.col("nbrs.id").alias("next"))
    if first is None:
        first = q.join(index.select(F.col("id").alias("q_id"), F.explode("nbrs.id").alias("id")), "q_id").select("qid", "id")
    if expand == "all" and max_hops is None and (points.agg(F.sum(F.size("next") + 2)).first()[0] or 0) <= WALK_NUMBERS:
        return _walk_all(points, q, first)
    asked = q.select("qid", "qx", "qy", "q_id", "k")
    level = cut(first.select("qid", "id").distinct())
    held, seen, expanded, n = None, level, None, 0
    limit = F.col("k") if max_hops == -1 else F.lit(2**31 - 1 if max_hops is None else max_hops)
    while not level.isEmpty():
        n += 1
        rows = level.join(points, "id").join(asked, "qid").where(OTHER).where(F.lit(n) <= limit).withColumn("d2", dist2("x", "y", "qx", "qy"))
        rows = cut(rows.withColumn("sector", sector(F.col("x") - F.col("qx"), F.col("y") - F.col("qy"))))
        slim = rows.select("qid", "id", "x", "y", "d2", "sector", "k", F.lit(n).alias("hop"))
        pool = slim if held is None else held.unionByName(slim)
        w = Window.partitionBy("qid", "sector").orderBy("d2", "id")
        held = cut(pool.withColumn("rank_in_sector", F.row_number().over(w)).where("rank_in_sector <= k OR sector = -1").drop("rank_in_sector"))
        go = rows if expand == "all" else rows.join(held.where(F.col("hop") == n).select("qid", "id"), ["qid", "id"], "left_semi")
        expanded = cut(go.select("qid", "id") if expanded is None else expanded.unionByName(go.select("qid", "id")))
        step = go.select("qid", "q_id", F.explode("next").alias("id")).where(OTHER).select("qid", "id").distinct()
        level = cut(step.join(seen, ["qid", "id"], "left_anti"))
        seen = cut(seen.unionByName(level))
    w = Window.partitionBy("qid", "sector").orderBy("d2", "id")
    out = held.withColumn("rank_in_sector", F.row_number().over(w)).select("qid", "id", "x", "y", "d2", "sector", "rank_in_sector")
    counts = seen.groupBy("qid").agg(F.count(F.lit(1)).alias("n_seen")).join(expanded.groupBy("qid").agg(F.count(F.lit(1)).alias("n_expanded")), "qid", "left")
    return out, counts


#: Numbers of a graph (points and links) up to which it goes to each query's task as a whole.
WALK_NUMBERS = 2_000_000


def _walk_all(points: DataFrame, q: DataFrame, first: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Every point that a walk from `first` reaches without passing the query's own, a query in a task."""
    packed = points.agg(F.collect_list(F.struct("id", "next")).alias("a")).select(F.col("a.id").alias("ids"), F.transform("a.next", F.size).alias("n"), F.flatten("a.next").alias("next"))
    begin = q.select("qid", "q_id").join(first.groupBy("qid").agg(F.collect_set("id").alias("begin")), "qid")

    def walk(batches):
        for f in batches:
            for qid, q_id, start, ids, n, flat in zip(f["qid"], f["q_id"], f["begin"], f["ids"], f["n"], f["next"], strict=True):
                turn = np.argsort(ids, kind="stable")
                known = ids[turn]
                to = np.minimum(np.searchsorted(known, flat), len(ids) - 1)
                begins = np.concatenate([[0], np.cumsum(n)])
                # links of a point, those to points that are not there left out
                link = np.where(known[to] == flat, turn[to], -1)
                seen = np.zeros(len(ids), bool)
                level = np.flatnonzero(np.isin(ids, start))
                closed = ids == q_id if not pd.isna(q_id) else np.zeros(len(ids), bool)
                level = level[~closed[level]]
                while len(level):
                    seen[level] = True
                    width = n[level]
                    at = np.repeat(begins[level] - np.concatenate([[0], np.cumsum(width)[:-1]]), width) + np.arange(width.sum())
                    step = np.unique(link[at])
                    step = step[step >= 0]
                    level = step[~seen[step] & ~closed[step]]
                yield pd.DataFrame({"qid": qid, "id": ids[seen]})

    reached = cut(begin.join(F.broadcast(packed)).mapInPandas(walk, f"qid {q.schema['qid'].dataType.simpleString()}, id long"))
    rows = reached.join(points.select("id", "x", "y"), "id").join(q.select("qid", "qx", "qy", "k"), "qid").withColumn("d2", dist2("x", "y", "qx", "qy"))
    rows = rows.withColumn("sector", sector(F.col("x") - F.col("qx"), F.col("y") - F.col("qy")))
    w = Window.partitionBy("qid", "sector").orderBy("d2", "id")
    held = rows.withColumn("rank_in_sector", F.row_number().over(w)).where("rank_in_sector <= k OR sector = -1")
    return held.select("qid", "id", "x", "y", "d2", "sector", "rank_in_sector"), reached.groupBy("qid").agg(F.count(F.lit(1)).alias("n_seen"), F.count(F.lit(1)).alias("n_expanded"))


def knn_voronoi(index: DataFrame, q: DataFrame) -> DataFrame:
    """(qid, id, dist, rank): nearest neighbours of members by growing over the graph: the next one always touches an
    earlier one. Each round reads the neighbours of all that are among the k nearest so far."""
    points = index.select("id", "x", "y", F.col("nbrs.id").alias("next"))
    asked = q.select("qid", "qx", "qy", "q_id", "k")
    level = cut(q.join(index.select(F.col("id").alias("q_id"), F.explode("nbrs.id").alias("id")), "q_id").select("qid", "id").distinct())
    held, seen, n = None, level, 0
    w = Window.partitionBy("qid").orderBy("d2")
    while not level.isEmpty():
        n += 1
        rows = level.join(points, "id").join(asked, "qid").where(OTHER).withColumn("d2", dist2("x", "y", "qx", "qy")).withColumn("hop", F.lit(n))
        rows = rows.select("qid", "q_id", "id", "d2", "k", "hop", "next")
        pool = rows if held is None else held.unionByName(rows)
        held = cut(pool.withColumn("rank", F.rank().over(w)).where("rank <= k").drop("rank"))
        step = held.where(F.col("hop") == n).select("qid", "q_id", F.explode("next").alias("id")).where(OTHER).select("qid", "id").distinct()
        level = cut(step.join(seen, ["qid", "id"], "left_anti"))
        seen = cut(seen.unionByName(level))
    return held.withColumn("rank", F.rank().over(w)).select("qid", "id", F.sqrt("d2").alias("dist"), "rank")
