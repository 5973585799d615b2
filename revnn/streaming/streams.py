"""Streams: query points against a point table, snapshots of event windows, late and repeated rows, sessions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from revnn.functions.geometry import dist
from revnn.operators import rknn, voronoi
from revnn.plans import grid
from revnn.plans.cuts import cut

MEMBERS = "window_start timestamp, qid long, id long"


def answer_stream(queries: DataFrame, points, path: str, checkpoint: str, **options):
    """Answers each micro-batch of a query stream (qid, qx, qy, q_id, k) and appends (batch, qid, id) to a table.

    points: a DataFrame, or a function that gives the newest one, so that index versions can move between batches.
    A batch that is run again after a failure replaces its own partition: results are exactly once."""

    def put(batch: DataFrame, n: int) -> None:
        p = points() if callable(points) else points
        out = rknn.conic(p, batch, **options).withColumn("batch", F.lit(n))
        out.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch").parquet(path)

    return queries.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def without_repeats(events: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    """First row of each key; rows behind the watermark go."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def snapshots(points: DataFrame, k: int, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(window_start, qid, id): all-points answers of each closed tumbling window of a stream (ts, id, x, y).

    Points of an open window are kept as state; when the watermark closes it, members are found by every point's
    radius. Windows have to fit a task; a grid of the window's points as key would split larger ones."""
    keyed = points.withWatermark("ts", late).withColumn("window_start", F.window("ts", width)["start"])

    def update(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            ids, xs, ys = state.get
            state.remove()
            ids, x = np.array(ids), np.column_stack([xs, ys])
            rows = []
            for i in range(len(ids)):
                d2 = ((x - x[i]) ** 2).sum(axis=1)
                d2[i] = np.inf
                r2 = np.partition(d2, k - 1)[k - 1] if len(ids) > k else np.inf
                rows += [(key[0], int(ids[j]), int(ids[i])) for j in np.flatnonzero(d2 <= r2) if j != i]
            yield pd.DataFrame(rows, columns=["window_start", "qid", "id"])
            return
        ids, xs, ys = state.get if state.exists else ([], [], [])
        ids, xs, ys = list(ids), list(xs), list(ys)
        for part in parts:
            ids, xs, ys = ids + part["id"].tolist(), xs + part["x"].tolist(), ys + part["y"].tolist()
        state.update((ids, xs, ys))
        end = pd.Timestamp(key[0]) + pd.Timedelta(width)
        state.setTimeoutTimestamp(int(end.timestamp() * 1000))
        yield pd.DataFrame([], columns=["window_start", "qid", "id"])

    return keyed.groupBy("window_start").applyInPandasWithState(update, MEMBERS, "ids array<long>, xs array<double>, ys array<double>", "append", GroupStateTimeout.EventTimeTimeout)


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, start, end, n, total): activity sessions of a stream or table."""
    d = events.withWatermark("ts", late) if events.isStreaming else events
    g = d.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return g.select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "n", "total")


def sliding_counts(events: DataFrame, width: str = "1 day", step: str = "6 hours", late: str = "1 hour") -> DataFrame:
    d = events.withWatermark("ts", late) if events.isStreaming else events
    return d.groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


ANSWERS = "qid int, id long, version long"


def standing_queries(points: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, id, version): the members of each standing query, anew after every batch that brings points near it.

    points: a stream (id, x, y) that only grows; queries: a static, bounded table (qid, qx, qy, q_id, k). New points can
    only lower radii, so what a query needs shrinks: once its six sectors hold k points each, its state keeps the points
    within twice the farthest candidate and drops the rest for good. Output mode: update; the largest version counts."""
    near = points.crossJoin(F.broadcast(queries)).where("q_id IS NULL OR id <> q_id")

    def update(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        ids, xs, ys, reach, version = state.get if state.exists else ([], [], [], float("inf"), 0)
        new = pd.concat(list(parts))
        qx, qy, k = float(new["qx"].iloc[0]), float(new["qy"].iloc[0]), int(new["k"].iloc[0])
        ids = np.concatenate([np.array(ids, np.int64), new["id"].to_numpy(np.int64)])
        xy = np.concatenate([np.column_stack([xs, ys]).reshape(-1, 2), new[["x", "y"]].to_numpy(float)])
        ids, first = np.unique(ids, return_index=True)
        xy = xy[first]
        dx, dy = xy[:, 0] - qx, xy[:, 1] - qy
        d = np.hypot(dx, dy)
        keep = d <= reach
        ids, xy, d, dx, dy = ids[keep], xy[keep], d[keep], dx[keep], dy[keep]
        sector = np.where(d == 0, -1, np.floor(np.mod(np.arctan2(dy, dx), 2 * np.pi) / (np.pi / 3)).clip(0, 5))
        cand, full = [np.flatnonzero(sector == -1)], True
        for s in range(6):
            own = np.flatnonzero(sector == s)
            own = own[np.argsort(d[own], kind="stable")]
            # sectors are cut by angle here: one place more for what rounding moves across an edge
            cand.append(own[: k + 1])
            full &= len(own) > k
        cand = np.concatenate(cand)
        if full:
            reach = 2 * float(d[cand].max()) * (1 + 1e-9)
            keep = np.flatnonzero(d <= reach)
        else:
            keep = np.arange(len(ids))
        members = [i for i in cand if int((((xy - xy[i]) ** 2).sum(axis=1)[ids != ids[i]] < dx[i] ** 2 + dy[i] ** 2).sum()) < k]
        state.update((ids[keep].tolist(), xy[keep, 0].tolist(), xy[keep, 1].tolist(), reach, version + 1))
        yield pd.DataFrame({"qid": int(key[0]), "id": ids[members], "version": version + 1})

    return near.groupBy("qid").applyInPandasWithState(update, ANSWERS, "ids array<long>, xs array<double>, ys array<double>, reach double, version long", "update", GroupStateTimeout.NoTimeout)


def maintain_index(changes: DataFrame, path: str, checkpoint: str):
    """Patches the neighbour index at `path` with each micro-batch of (id, x, y, op), op 'add' or 'remove'.

    A batch writes the next version, which readers pin; a batch that is run again overwrites its own."""

    def put(batch: DataFrame, n: int) -> None:
        spark = batch.sparkSession
        index = voronoi.read_index(spark, path, n).select("id", "x", "y", "nbrs")
        fresh = voronoi.patch(index, batch.where("op = 'add'").select("id", "x", "y"), batch.where("op = 'remove'").select("id"))
        voronoi.write_index(cut(fresh.select("id", "x", "y", "nbrs", "deg", "certified")), path, n + 1)

    return changes.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def queries_with_points(queries: DataFrame, points: DataFrame, side: float, within: str = "10 minutes", late: str = "1 hour") -> DataFrame:
    """(qid, id, dist): points that arrive within some time of a query, in its grid cell or one next to it.

    Both streams have watermarks (qt, ts), so state is dropped when no partner can come any more."""
    q = queries.withWatermark("qt", late)
    cx, cy = grid.cell("qx", "qy", side)
    q = q.withColumn("cx", F.explode(F.sequence(cx - 1, cx + 1))).withColumn("cy", F.explode(F.sequence(cy - 1, cy + 1)))
    px, py = grid.cell("x", "y", side)
    p = points.withWatermark("ts", late).withColumns({"px": px, "py": py})
    on = F.expr(f"cx = px AND cy = py AND ts BETWEEN qt AND qt + INTERVAL {within}")
    return q.join(p, on).select("qid", "id", dist("x", "y", "qx", "qy").alias("dist"))
