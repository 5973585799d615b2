"""Verifying candidates (qid, id, x, y, d2 with the query's qx, qy, q_id, k) with joins and column rules."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from revnn.functions.geometry import dist
from revnn.functions.regions import in_knn_region, negative_region, positive_region, semi_region
from revnn.operators.knn import knn_exact, knn_grid, knn_radius
from revnn.plans import grid
from revnn.plans.cuts import cut


def with_queries(c: DataFrame, q: DataFrame) -> DataFrame:
    """Candidates with their query's columns; queries are joined by key, broadcast only as Spark's size check allows."""
    return c.join(q.select("qid", "qx", "qy", "q_id", "k"), "qid")


#: Neighbours that the kNN queries of a batch of candidates may make; beyond, radii come from blocks, which keep none.
NEIGHBOURS = 20_000_000


def radii(c: DataFrame, p: DataFrame, method: str = "grid") -> DataFrame:
    """(id, k, r) of each distinct candidate (a point of p) and k: one kNN query for each."""
    ask = cut(c.select("id", "x", "y", "k").distinct())
    if method == "grid":
        rows = {r.k: r.n for r in ask.groupBy("k").agg(F.count(F.lit(1)).alias("n")).collect()}
        if sum(k * n for k, n in rows.items()) > NEIGHBOURS:
            return reduce(DataFrame.unionByName, (knn_radius(p, ask.where(F.col("k") == k).select("id"), k) for k in rows))
    # one kNN run for each k that occurs; keys stay (id, k)
    q = ask.select(F.struct("id", "k").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"), F.col("id").alias("q_id"), "k")
    near = (knn_grid if method == "grid" else knn_exact)(p, q)
    r = near.groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.max("dist").alias("far")).select("qid.id", "qid.k", "n", "far")
    return ask.join(r, ["id", "k"], "left").select("id", "k", F.when(F.coalesce("n", F.lit(0)) >= F.col("k"), F.col("far")).otherwise(F.lit(float("inf"))).alias("r"))


def by_knn(c: DataFrame, p: DataFrame, q: DataFrame, method: str = "grid") -> DataFrame:
    """(qid, id, member, r): one kNN query for each candidate."""
    d = with_queries(c, q)
    d = d.join(radii(d, p, method), ["id", "k"])
    # squared distances decide, so both sides of a tie have the same bits
    return d.select("qid", "id", in_knn_region(F.sqrt("d2"), "r").alias("member"), "r")


def by_range_count(c: DataFrame, p: DataFrame, q: DataFrame) -> DataFrame:
    """(qid, id, member, closer): members have fewer than k other points strictly closer than the query."""
    d = cut(with_queries(c, q).select(F.col("qid").alias("of"), F.col("id").alias("q_id"), F.col("x").alias("qx"), F.col("y").alias("qy"), F.col("d2").alias("limit2"), "k", F.sqrt("d2").alias("_r")))
    n, far = d.agg(F.count(F.lit(1)), F.avg("_r")).first()
    box = grid.box_of(p)
    near = grid.within(p, d, "_r", far or 1.0, n, box).where("id <> q_id AND d2 < limit2")
    closer = near.groupBy("of", "q_id").agg(F.count(F.lit(1)).alias("closer"))
    out = d.join(closer, ["of", "q_id"], "left").withColumn("closer", F.coalesce("closer", F.lit(0)))
    return out.select(F.col("of").alias("qid"), F.col("q_id").alias("id"), (F.col("closer") < F.col("k")).alias("member"), "closer")


def query_radius(c: DataFrame, q: DataFrame, slack: bool = False) -> DataFrame:
    """(qid, r_q): the query's own kNN radius from its candidates (the k nearest are among them); slack: of the (k+1)-th."""
    from pyspark.sql import Window

    w = Window.partitionBy("qid").orderBy("d2", "id")
    nth = F.col("k") + (1 if slack else 0)
    d = with_queries(c, q).withColumn("n", F.row_number().over(w)).where(F.col("n") <= nth)
    d = d.groupBy("qid", "k").agg(F.count(F.lit(1)).alias("n"), F.max("d2").alias("far"))
    return d.select("qid", F.when(F.col("n") >= nth, F.sqrt("far")).otherwise(F.lit(float("inf"))).alias("r_q"))


def by_semi(c: DataFrame, q: DataFrame, slack: bool = False) -> DataFrame:
    """(qid, id, settled): candidates within half of the query's radius are members."""
    d = c.join(query_radius(c, q, slack), "qid")
    return d.select("qid", "id", semi_region(F.sqrt("d2"), "r_q").alias("settled"))


def decides(c: DataFrame, w: DataFrame, kinds=("positive", "negative")) -> DataFrame:
    """(qid, witness_id, id, kind): which witness (qid, witness_id, wx, wy, wd, wr) settles which candidate, and how."""
    d = c.join(w, "qid").where("id <> witness_id")
    args = (F.sqrt("d2"), dist("x", "y", "wx", "wy"), "wd", "wr")
    kind = F.when(positive_region(*args) if "positive" in kinds else F.lit(False), "positive").when(negative_region(*args) if "negative" in kinds else F.lit(False), "negative")
    return d.withColumn("kind", kind).where("kind IS NOT NULL").select("qid", "witness_id", "id", "kind")


def by_positive(c: DataFrame, w: DataFrame) -> DataFrame:
    return decides(c, w, ("positive",))


def by_negative(c: DataFrame, w: DataFrame) -> DataFrame:
    return decides(c, w, ("negative",))


def as_witnesses(c: DataFrame, p: DataFrame, q: DataFrame, method: str = "grid") -> DataFrame:
    """Candidates with their radius, in the form that :func:`decides` takes."""
    d = by_knn(c, p, q, method).join(c, ["qid", "id"])
    return d.select("qid", F.col("id").alias("witness_id"), F.col("x").alias("wx"), F.col("y").alias("wy"), F.sqrt("d2").alias("wd"), F.col("r").alias("wr"))


def undecided(c: DataFrame, w: DataFrame) -> DataFrame:
    """(qid, id): candidates that are no witness and that no witness settles; empty for a valid witness set."""
    rest = c.select("qid", "id").join(w.select("qid", F.col("witness_id").alias("id")), ["qid", "id"], "left_anti")
    return rest.join(decides(c, w), ["qid", "id"], "left_anti")


def is_witness_set(c: DataFrame, w: DataFrame) -> DataFrame:
    """(qid, valid, n_undecided)."""
    left = undecided(c, w).groupBy("qid").agg(F.count(F.lit(1)).alias("n"))
    d = c.select("qid").distinct().join(left, "qid", "left")
    return d.select("qid", F.col("n").isNull().alias("valid"), F.coalesce("n", F.lit(0)).alias("n_undecided"))


def boundary_band(c: DataFrame, p: DataFrame, q: DataFrame, share: float = 0.25) -> DataFrame:
    """(qid, id, member, decision): only candidates near the query's kNN circle become witnesses.

    Those within `share` of its radius get a kNN query of their own; their conics settle what they cover, and what is
    left open gets a kNN query after all, so the answer is exact whatever the band."""
    c = cut(c)
    band = cut(c.join(query_radius(c, q), "qid").where(F.abs(F.sqrt("d2") - F.col("r_q")) <= share * F.col("r_q")).drop("r_q"))
    known = cut(by_knn(band, p, q))
    w = known.join(c, ["qid", "id"]).select("qid", F.col("id").alias("witness_id"), F.col("x").alias("wx"), F.col("y").alias("wy"), F.sqrt("d2").alias("wd"), F.col("r").alias("wr"))
    rest = c.join(known.select("qid", "id"), ["qid", "id"], "left_anti")
    hit = cut(decides(rest, w).groupBy("qid", "id").agg(F.min("kind").alias("decision")))
    open_ = cut(rest.join(hit.select("qid", "id"), ["qid", "id"], "left_anti"))
    out = known.select("qid", "id", "member", F.lit("band").alias("decision"))
    out = out.unionByName(hit.select("qid", "id", (F.col("decision") == "positive").alias("member"), "decision"))
    return out.unionByName(by_knn(open_, p, q).select("qid", "id", "member", F.lit("fallback").alias("decision")))
