"""Expected counts as functions of k."""

from __future__ import annotations

from math import pi

from pyspark.sql import Column
from pyspark.sql import functions as F

from revnn.functions.geometry import col


def verified(k) -> Column:
    """Expected size of a witness set, at most."""
    return 4 * F.sqrt(pi * col(k))


def accessed(k) -> Column:
    """Expected points read for candidates, uniform data."""
    return 6 * col(k) + 2 * F.sqrt(6 * pi * col(k))


def accessed_max(k) -> Column:
    """What can be read at most within k hops."""
    return (col(k) * col(k) + col(k)) * pi


def result_size(k) -> Column:
    return col(k).cast("double")
