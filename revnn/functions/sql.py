"""The scalar functions as SQL functions; bodies are SQL expressions that the optimizer inlines, and two Python ones."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

FUNCTIONS = {
    "revnn_dist(ax DOUBLE, ay DOUBLE, bx DOUBLE, by DOUBLE) RETURNS DOUBLE": "sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by))",
    "revnn_semi(d DOUBLE, r_q DOUBLE) RETURNS BOOLEAN": "d <= r_q / 2",
    "revnn_positive(d_pq DOUBLE, d_pw DOUBLE, d_wq DOUBLE, r_w DOUBLE) RETURNS BOOLEAN": "d_wq <= r_w AND d_pq + d_pw <= r_w * (1 - 1e-12D)",
    "revnn_negative(d_pq DOUBLE, d_pw DOUBLE, d_wq DOUBLE, r_w DOUBLE) RETURNS BOOLEAN": "d_wq > r_w AND d_pq - d_pw > r_w * (1 + 1e-12D)",
    "revnn_cell(x DOUBLE, y DOUBLE, side DOUBLE) RETURNS STRUCT<cx: BIGINT, cy: BIGINT>": "named_struct('cx', CAST(floor(x / side) AS BIGINT), 'cy', CAST(floor(y / side) AS BIGINT))",
    "revnn_sector(dx DOUBLE, dy DOUBLE) RETURNS INT": """CASE WHEN dx = 0 AND dy = 0 THEN -1
        WHEN dy > 0 OR (dy = 0 AND dx > 0) THEN CASE WHEN dx > 0 AND dy - 1.7320508075688772D * dx < 0 THEN 0 WHEN dy > 0 AND dy + 1.7320508075688772D * dx > 0 THEN 1 ELSE 2 END
        WHEN dy = 0 AND dx < 0 THEN 3
        ELSE CASE WHEN dx < 0 AND dy - 1.7320508075688772D * dx > 0 THEN 3 WHEN dy + 1.7320508075688772D * dx < 0 THEN 4 ELSE 5 END END""",
    "revnn_upper_arc(d DOUBLE, angle DOUBLE) RETURNS DOUBLE": "CASE WHEN angle >= pi() / 2 THEN DOUBLE('Infinity') ELSE d / (2 * cos(angle)) END",
    "revnn_lower_arc(d DOUBLE, angle DOUBLE) RETURNS DOUBLE": "CASE WHEN cos(angle) <= 1e-12D THEN DOUBLE('Infinity') ELSE d / (2 * cos(angle)) END",
    # bits of two non-negative cell numbers below 2**20, interleaved: near cells, near keys
    "revnn_zkey(cx BIGINT, cy BIGINT) RETURNS BIGINT": "aggregate(sequence(0, 19), 0L, (z, i) -> z | shiftleft(shiftright(cx, i) & 1L, 2 * i) | shiftleft(shiftright(cy, i) & 1L, 2 * i + 1))",
    "revnn_theory_verified(k INT) RETURNS DOUBLE": "4 * sqrt(pi() * k)",
    "revnn_theory_accessed(k INT) RETURNS DOUBLE": "6 * k + 2 * sqrt(6 * pi() * k)",
}


@udtf(returnType="qid INT, id BIGINT, member BOOLEAN")
class AnswerBundle:
    """revnn_rknn(TABLE(bundle) PARTITION BY qid): members among a query's bundle, which has columns
    (qid, qx, qy, q_id, k, id, x, y) and holds every point that can matter."""

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((row["qid"], row["qx"], row["qy"], row["q_id"], row["k"], row["id"], row["x"], row["y"]))

    def terminate(self):
        if not self.rows:
            return
        qid, qx, qy, q_id, k = self.rows[0][:5]
        ids = np.array([r[5] for r in self.rows])
        xy = np.array([r[6:] for r in self.rows], float)
        for i, place in enumerate(xy):
            if ids[i] != q_id:
                d = xy - place
                d2 = d[:, 0] * d[:, 0] + d[:, 1] * d[:, 1]
                # products: a power of a single number may differ from them in its last bit
                dx, dy = place[0] - qx, place[1] - qy
                closer = int((d2[ids != ids[i]] < dx * dx + dy * dy).sum())
                yield qid, int(ids[i]), closer < k


@udtf(returnType="src BIGINT, dst BIGINT")
class LinkNeighbors:
    """revnn_neighbors(TABLE(points) PARTITION BY ...): Voronoi neighbours within each group of points (id, x, y)."""

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((row["id"], row["x"], row["y"]))

    def terminate(self):
        from revnn.operators.voronoi import clip

        ids = np.array([r[0] for r in self.rows])
        xy = np.array([r[1:] for r in self.rows], float).reshape(-1, 2)
        box = (*xy.min(axis=0), *xy.max(axis=0)) if len(xy) else None
        for i in range(len(xy)):
            other = np.flatnonzero(ids != ids[i])
            _, near, _ = clip(xy[i], xy[other], box, np.inf)
            for j in near:
                yield int(ids[i]), int(ids[other[j]])


def register(spark: SparkSession) -> None:
    """Temporary SQL functions revnn_*, the grouped aggregate revnn_kth and the scalar revnn_ring_area."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")

    @pandas_udf("double")
    def kth(d: pd.Series, k: pd.Series) -> float:
        n = int(k.iloc[0])
        return float(d.nsmallest(n).iloc[-1]) if len(d) >= n else float("inf")

    @pandas_udf("double")
    def ring_area(ring: pd.Series) -> pd.Series:
        def area(r):
            x, y = [p["x"] for p in r], [p["y"] for p in r]
            return abs(sum(x[i - 1] * y[i] - x[i] * y[i - 1] for i in range(len(x)))) / 2

        return ring.map(area)

    spark.udtf.register("revnn_rknn", AnswerBundle)
    spark.udtf.register("revnn_neighbors", LinkNeighbors)
    spark.udf.register("revnn_kth", kth)
    spark.udf.register("revnn_ring_area", ring_area)
