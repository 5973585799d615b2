"""Regions around a query: kNN circle, half-radius circle, ellipse of an accepted and hyperbola of a rejected witness."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from revnn.functions.geometry import MARGIN, col


def in_knn_region(d, r) -> Column:
    """Within the kNN circle, border included: with the point's own radius this is the membership test."""
    return col(d) <= col(r)


def semi_region(d_pq, r_q) -> Column:
    """Within half of the query's kNN radius: surely a member."""
    return col(d_pq) <= col(r_q) / 2


def positive_region(d_pq, d_pw, d_wq, r_w) -> Column:
    """Inside the ellipse with foci query and witness and sum r_w; empty unless the witness is a member."""
    return (col(d_wq) <= col(r_w)) & (col(d_pq) + col(d_pw) <= col(r_w) * (1 - MARGIN))


def negative_region(d_pq, d_pw, d_wq, r_w) -> Column:
    """Beyond the witness's branch of the hyperbola with difference r_w; empty unless the witness is no member."""
    return (col(d_wq) > col(r_w)) & (col(d_pq) - col(d_pw) > col(r_w) * (1 + MARGIN))


def on_conic(value, constant, eps: float = 1e-9) -> Column:
    return F.abs(col(value) - col(constant)) <= eps
