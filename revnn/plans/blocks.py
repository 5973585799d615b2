"""Neighbours of all points at once, by blocks of about as many locations; nothing of the queries comes to the driver.

Equal locations are one row with a count, so copies don't meet each other. Blocks are strips of x cut along y at
quantiles (even and uneven sets alike). A block answers for its own locations first; a circle that sticks out of it then
asks the blocks that it touches, and no others, so answers are exact whatever the layout."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil, sqrt

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from revnn.plans.cuts import cut

#: Locations of a block, strips at most, cuts of a strip at most, locations that share a task's look.
BLOCK, STRIPS, CUTS, SHARE = 1024, 64, 255, 4096
#: Distances that a task holds at once.
AT_ONCE = 500_000
INF = float("inf")


@dataclass(frozen=True)
class Blocks:
    """Inner bounds of the strips, and of the blocks of each strip; outer ones are infinite."""

    xs: np.ndarray
    ys: list[np.ndarray]

    @property
    def first(self) -> np.ndarray:
        """Number of the first block of each strip."""
        return np.cumsum([0, *(len(y) + 1 for y in self.ys)])

    def of(self, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        strip, out = np.searchsorted(self.xs, x, side="right"), np.empty(len(x), np.int64)
        for s in np.unique(strip):
            here = strip == s
            out[here] = self.first[s] + np.searchsorted(self.ys[s], y[here], side="right")
        return out

    def room(self, block: int, x: np.ndarray, y: np.ndarray) -> np.ndarray:
        """How far it is from places of a block to its nearest side."""
        s = int(np.searchsorted(self.first, block, side="right")) - 1
        bx, by, t = np.r_[-INF, self.xs, INF], np.r_[-INF, self.ys[s], INF], block - self.first[s]
        return np.minimum(np.minimum(x - bx[s], bx[s + 1] - x), np.minimum(y - by[t], by[t + 1] - y))

    def touched(self, x: np.ndarray, y: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(row, block) for every block that may hold a point of a row's disc."""
        bx, rows, found = np.r_[-INF, self.xs, INF], [], []
        r = r * (1 + 1e-9)
        for s, ys in enumerate(self.ys):
            off = np.maximum(np.maximum(bx[s] - x, x - bx[s + 1]), 0.0)
            here = np.flatnonzero(off <= r)
            with np.errstate(invalid="ignore"):
                half = np.where(np.isinf(r[here]), INF, np.sqrt(np.maximum(r[here] ** 2 - off[here] ** 2, 0.0)) + r[here] * 1e-6)
            a, b = np.searchsorted(ys, y[here] - half, side="left"), np.searchsorted(ys, y[here] + half, side="right")
            n = b - a + 1
            rows.append(np.repeat(here, n))
            found.append(np.repeat(self.first[s] + a - np.r_[0, np.cumsum(n)[:-1]], n) + np.arange(n.sum()))
        return np.concatenate(rows), np.concatenate(found)


def locations(p: DataFrame) -> DataFrame:
    """(at, x, y, n, ids) of the places of points (id, x, y); at is the smallest id there."""
    return cut(p.groupBy("x", "y").agg(F.min("id").alias("at"), F.count(F.lit(1)).alias("n"), F.collect_list("id").alias("ids")).select("at", "x", "y", "n", "ids"))


def blocks_of(places: DataFrame, size: int) -> Blocks:
    """A few thousand quantiles come to the driver, whatever the number of places."""
    n = places.count()
    strips = min(STRIPS, ceil(sqrt(max(n, 1) / size)))
    xs = np.unique(places.approxQuantile("x", [i / strips for i in range(1, strips)], 0.1 / strips)) if strips > 1 and n else np.array([])
    strip = pandas_udf(lambda x: pd.Series(np.searchsorted(xs, x, side="right")), "int")
    most = min(CUTS, ceil(n / size))
    ys = [np.array([]) for _ in range(len(xs) + 1)]
    if most > 1:
        at = F.percentile_approx("y", [i / (most + 1) for i in range(1, most + 1)], F.lit(10 * most))
        for r in places.groupBy(strip("x").alias("s")).agg(F.count(F.lit(1)).alias("n"), at.alias("y")).collect():
            cuts = min(most, ceil(r.n / size) - 1)
            ys[r.s] = np.unique([r.y[(i + 1) * (most + 1) // (cuts + 1) - 1] for i in range(cuts)])
    return Blocks(np.asarray(xs, float), [np.asarray(y, float) for y in ys])


def _distances(asks: pd.DataFrame, held: pd.DataFrame):
    """Slices of asks with squared distances to all that a block holds."""
    x, y = held["x"].to_numpy(float), held["y"].to_numpy(float)
    ax, ay = asks["x"].to_numpy(float), asks["y"].to_numpy(float)
    step = max(1, AT_ONCE // max(len(x), 1))
    for i in range(0, len(ax), step):
        dx, dy = x[None] - ax[i : i + step, None], y[None] - ay[i : i + step, None]
        dx *= dx
        dy *= dy
        dx += dy
        yield slice(i, i + step), dx


def nearest(asks: pd.DataFrame, held: pd.DataFrame, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row of asks, squared distance, points there) of the nearest places, as many as can hold k other points."""
    ids, n, rows, far, weight = held["at"].to_numpy(), held["n"].to_numpy(), [], [], []
    m = min(k + 1, len(ids))
    for part, d2 in _distances(asks, held):
        top = np.argpartition(d2, m - 1, axis=1)[:, :m] if m < len(ids) else np.broadcast_to(np.arange(len(ids)), d2.shape)
        rows.append(np.repeat(np.arange(len(asks))[part], m))
        far.append(np.take_along_axis(d2, top, 1).ravel())
        # a point is no neighbour of itself
        weight.append((n[top] - (ids[top] == asks["at"].to_numpy()[part, None])).ravel())
    return (np.concatenate(rows), np.concatenate(far), np.concatenate(weight)) if rows else (np.zeros(0, int), np.zeros(0), np.zeros(0, int))


def kth(asks: pd.DataFrame, held: pd.DataFrame, k: int) -> np.ndarray:
    """Squared distance of the k-th other point among those that a block holds, infinite if there are fewer."""
    n = held["n"].to_numpy()
    if len(n) > k and (n == 1).all() and asks["at"].isin(held["at"]).all():
        # the place itself comes first
        return np.concatenate([np.partition(d2, k, axis=1)[:, k] for _, d2 in _distances(asks, held)] or [np.zeros(0)])
    rows, far, weight = nearest(asks, held, k)
    turn = np.lexsort((far, rows))
    rows, far, weight = rows[turn], far[turn], weight[turn]
    upto = np.cumsum(weight)
    before = np.r_[0, upto][np.searchsorted(rows, rows)]
    out, enough = np.full(len(asks), INF), np.flatnonzero(upto - before >= k)
    first, at = np.unique(rows[enough], return_index=True)
    out[first] = far[enough[at]]
    return out


def _dealt(asks: DataFrame, held: DataFrame, parts: int) -> DataFrame:
    """Asks (bound not null) beside all that their block holds; large blocks' asks are dealt to several tasks."""
    part = F.pmod(F.xxhash64("at"), F.lit(parts)).cast("int")
    copies = held.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).withColumn("bound", F.lit(None).cast("double"))
    cols = ("block", "part", "at", "x", "y", "n", "bound")
    return asks.withColumn("part", part).select(*cols).unionByName(copies.select(*cols))


def _split(f: pd.DataFrame) -> tuple[pd.DataFrame, pd.DataFrame]:
    ask = f["bound"].notna()
    return f[ask].reset_index(drop=True), f[~ask].reset_index(drop=True)


@dataclass(frozen=True)
class Layout:
    """Places in their blocks, and how many tasks share the asks of a block."""

    places: DataFrame
    blocks: Blocks
    parts: int

    def asking(self, asks: DataFrame) -> DataFrame:
        """Asks (at, x, y, n, bound), a row for each block that their discs of squared radius `bound` touch."""
        blocks = self.blocks

        def spread(batches):
            for f in batches:
                row, block = blocks.touched(f["x"].to_numpy(float), f["y"].to_numpy(float), np.sqrt(f["bound"].to_numpy(float)))
                yield f.iloc[row].assign(block=block)

        return asks.mapInPandas(spread, "at long, x double, y double, n long, bound double, block long")


def layout(p: DataFrame, k: int) -> Layout:
    """Blocks of the points (id, x, y) that mostly hold k neighbours of their own places."""
    size = max(BLOCK, 8 * k)
    places = locations(p)
    blocks = blocks_of(places, size)
    of = pandas_udf(lambda x, y: pd.Series(blocks.of(x.to_numpy(), y.to_numpy())), "long")
    return Layout(cut(places.withColumn("block", of("x", "y"))), blocks, ceil(size / SHARE))


def radii(at: Layout, k: int, some: DataFrame | None = None) -> DataFrame:
    """(at, r2): squared distance to the k-th other point of each place (or of those of `some`), infinite if there are fewer."""
    blocks, held = at.blocks, at.places.drop("ids")
    first = (held if some is None else held.join(some.select("at"), "at", "left_semi")).withColumn("bound", F.lit(INF))

    def own(f: pd.DataFrame) -> pd.DataFrame:
        asks, here = _split(f)
        r2 = kth(asks, here, k) if len(asks) else np.zeros(0)
        room = blocks.room(int(f["block"].iloc[0]), asks["x"].to_numpy(float), asks["y"].to_numpy(float))
        return asks.assign(bound=r2, sure=np.sqrt(r2) <= room * (1 - 1e-9))[["at", "x", "y", "n", "bound", "sure"]]

    def other(f: pd.DataFrame) -> pd.DataFrame:
        asks, here = _split(f)
        if asks.empty or here.empty:
            return pd.DataFrame({"at": [], "d2": [], "w": []})
        row, d2, w = nearest(asks, here, k)
        keep = (d2 <= asks["bound"].to_numpy()[row]) & (w > 0)
        return pd.DataFrame({"at": asks["at"].to_numpy()[row[keep]], "d2": d2[keep], "w": w[keep]})

    near = cut(_dealt(first, held, at.parts).groupBy("block", "part").applyInPandas(own, "at long, x double, y double, n long, bound double, sure boolean"))
    open_ = near.where("NOT sure").drop("sure")
    found = _dealt(at.asking(open_), held, at.parts).groupBy("block", "part").applyInPandas(other, "at long, d2 double, w long")
    upto = F.sum("w").over(Window.partitionBy("at").orderBy("d2").rowsBetween(Window.unboundedPreceding, 0))
    r2 = found.withColumn("upto", upto).where(F.col("upto") >= k).groupBy("at").agg(F.min("d2").alias("r2"))
    late = open_.select("at").join(r2, "at", "left").select("at", F.coalesce("r2", F.lit(INF)).alias("r2"))
    return near.where("sure").select("at", F.col("bound").alias("r2")).unionByName(late)


def within(at: Layout, circles: DataFrame) -> DataFrame:
    """(at, other, d2): the places in the circle (at, r2) of each place, itself included."""
    held = at.places.drop("ids")
    asks = at.asking(held.join(circles, "at").select("at", "x", "y", "n", F.col("r2").alias("bound")))

    def pairs(f: pd.DataFrame) -> pd.DataFrame:
        asks, here = _split(f)
        ids, own, bound = here["at"].to_numpy(), asks["at"].to_numpy(), asks["bound"].to_numpy()
        out = []
        for part, d2 in _distances(asks, here):
            a, b = np.nonzero(d2 <= bound[part, None])
            out.append(pd.DataFrame({"at": own[part][a], "other": ids[b], "d2": d2[a, b]}))
        return pd.concat(out) if out else pd.DataFrame({"at": [], "other": [], "d2": []})

    return _dealt(asks, held, at.parts).groupBy("block", "part").applyInPandas(pairs, "at long, other long, d2 double")
