"""How points lie: counts on a grid with dense cells split, small enough for the driver.

Two passes give a few thousand counts whatever the input. They choose each query's first disc (so that one round mostly
suffices on even and uneven sets) and tell beforehand whether a bundle may be too large for one task."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from revnn.plans.grid import box_of

#: Cells of a side, and of a side within a dense cell; the most cells that are split; a dense cell holds DENSE times the mean.
SIDE, INNER, SPLIT, DENSE = 64, 16, 64, 4.0


@dataclass
class Density:
    box: tuple[int, float, float, float, float]
    counts: np.ndarray
    inner: dict[tuple[int, int], np.ndarray]

    @property
    def spans(self) -> tuple[float, float]:
        return max(self.box[3] - self.box[1], 1e-9), max(self.box[4] - self.box[2], 1e-9)

    def _pyramid(self) -> list[np.ndarray]:
        out = [self.counts]
        while out[-1].shape[0] > 1:
            c = out[-1]
            out.append(c.reshape(c.shape[0] // 2, 2, -1, 2).sum(axis=(1, 3)))
        return out

    def around(self, xy: np.ndarray, wanted: np.ndarray) -> np.ndarray:
        """Points for each unit of area near each place, from the smallest cell around it that holds `wanted` of them."""
        (w, h), n = self.spans, max(self.box[0], 1)
        at = np.clip((xy - [self.box[1], self.box[2]]) / [w, h], 0, 1 - 1e-12)
        out, open_ = np.full(len(xy), n / (w * h)), np.ones(len(xy), bool)
        for cell, sub in self.inner.items():
            here = np.flatnonzero((np.floor(at * SIDE).astype(int) == cell).all(axis=1))
            i = np.floor((at[here] * SIDE % 1) * INNER).astype(int)
            enough = sub[i[:, 0], i[:, 1]] >= wanted[here]
            out[here[enough]] = sub[i[enough, 0], i[enough, 1]] * (SIDE * INNER) ** 2 / (w * h)
            open_[here[enough]] = False
        for c in self._pyramid():
            i = np.floor(at * c.shape[0]).astype(int)
            found = c[i[:, 0], i[:, 1]]
            take = open_ & (found >= wanted)
            out[take] = found[take] * c.shape[0] ** 2 / (w * h)
            open_ &= ~take
        return out

    def radius(self, xy: np.ndarray, wanted: np.ndarray) -> np.ndarray:
        """Radius of a disc that should hold `wanted` points; on a (nearly) flat box the points lie on a line."""
        w, h = self.spans
        line = max(w, h) * np.minimum(1.0, wanted / max(self.box[0], 1)) / 2
        return np.maximum(np.sqrt(wanted / (np.pi * self.around(xy, wanted))), line * (min(w, h) < 1e-3 * max(w, h)))


def density(p: DataFrame) -> Density:
    """Counts of the points (id, x, y): at most SIDE**2 + SPLIT * INNER**2 of them come to the driver."""
    box = box_of(p)
    counts, inner = np.zeros((SIDE, SIDE)), {}
    if not box[0]:
        return Density(box, counts, inner)
    w, h = max(box[3] - box[1], 1e-9), max(box[4] - box[2], 1e-9)
    at = lambda side: (F.least(F.floor((F.col("x") - box[1]) / w * side), F.lit(side - 1)).cast("int"), F.least(F.floor((F.col("y") - box[2]) / h * side), F.lit(side - 1)).cast("int"))
    (cx, cy), (fx, fy) = at(SIDE), at(SIDE * INNER)
    for r in p.groupBy(cx.alias("cx"), cy.alias("cy")).count().collect():
        counts[r.cx, r.cy] = r["count"]
    dense = [tuple(map(int, c)) for c in np.argwhere(counts > DENSE * max(1.0, box[0] / SIDE**2))]
    dense = sorted(dense, key=lambda c: -counts[c])[:SPLIT]
    if dense:
        chosen = F.array(*(F.lit(a * SIDE + b) for a, b in dense))
        for a, b in dense:
            inner[a, b] = np.zeros((INNER, INNER))
        for r in p.where(F.array_contains(chosen, cx * SIDE + cy)).groupBy(fx.alias("fx"), fy.alias("fy")).count().collect():
            inner[r.fx // INNER, r.fy // INNER][r.fx % INNER, r.fy % INNER] = r["count"]
    return Density(box, counts, inner)
