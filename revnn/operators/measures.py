"""Cost and accuracy measures."""

from __future__ import annotations

import time
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from revnn.functions import theory
from revnn.operators import baselines, candidates, knn, rknn, verify
from revnn.plans import grid
from revnn.plans.cuts import cut


def timed(run, warm: bool = False, repeats: int = 1) -> float:
    """Milliseconds from calling `run`, which builds a plan (and may run jobs for it), to that plan's end.

    The plan's rows are kept nowhere. warm: one run before the clock starts; of several repeats the median counts."""
    took = []
    for n in range(repeats + warm):
        t = time.perf_counter()
        run().write.format("noop").mode("overwrite").save()
        if n or not warm:
            took.append((time.perf_counter() - t) * 1000)
    return median(took)


def decision_mix(decisions: DataFrame) -> DataFrame:
    """Per query, how many candidates each rule settled."""
    d = decisions.groupBy("qid").pivot("decision", ["semi", "positive", "negative", "knn"]).count()
    return d.select("qid", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("semi", "positive", "negative", "knn")))


def recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(qid, n_true, n_found, n_both, recall, precision) over (qid, id) sets."""
    a, b = truth.select("qid", "id", F.lit(1).alias("t")), found.select("qid", "id", F.lit(1).alias("f"))
    d = a.join(b, ["qid", "id"], "full_outer").groupBy("qid").agg(F.count("t").alias("n_true"), F.count("f").alias("n_found"), F.count(F.expr("t + f")).alias("n_both"))
    share = lambda n: F.when(F.col(n) > 0, F.col("n_both") / F.col(n)).otherwise(F.lit(1.0))
    return d.withColumns({"recall": share("n_true"), "precision": share("n_found")})


def saving(ours: float, other: float) -> float:
    return 1 - ours / other


def loglog_slope(df: DataFrame, k: str, value: str, *by: str) -> DataFrame:
    """Exponent of a power law: slope of log value on log k."""
    return df.groupBy(*by).agg(F.regr_slope(F.log(value), F.log(k)).alias("slope"))


def boundary_points(p: DataFrame, q: DataFrame) -> DataFrame:
    """(qid, n_boundary, area, circumference): points within one mean spacing of the query's kNN circle."""
    q = cut(q)
    n, x0, y0, x1, y1 = box = grid.box_of(p)
    spacing = ((x1 - x0) * (y1 - y0) / max(n, 1)) ** 0.5
    r = knn.knn_grid(p, q).groupBy("qid").agg(F.max("dist").alias("r_q"))
    asked = cut(q.join(r, "qid").withColumn("_r", (F.col("r_q") + spacing) * (1 + 1e-9)))
    m, side = asked.agg(F.count(F.lit(1)), F.max("_r")).first()
    near = grid.within(p, asked, "_r", side or 1.0, m, box).where(knn.OTHER)
    near = near.groupBy("qid", "r_q").agg(F.sum((F.abs(F.sqrt("d2") - F.col("r_q")) <= spacing).cast("long")).alias("n_boundary"))
    return near.select("qid", "n_boundary", (F.pi() * F.col("r_q") * F.col("r_q")).alias("area"), (2 * F.pi() * F.col("r_q")).alias("circumference"))


def unevenness(p: DataFrame, cells: int = 10) -> DataFrame:
    """(n_cells, mean, ratio): variance of counts over their mean on a grid of cells x cells; 1 for a random set."""
    n, x0, y0, x1, y1 = grid.box_of(p)
    at = lambda c, lo, hi: F.least(F.floor((F.col(c) - lo) / max(hi - lo, 1e-300) * cells), F.lit(cells - 1)).cast("int")
    got = p.groupBy(at("x", x0, x1).alias("cx"), at("y", y0, y1).alias("cy")).count()
    every = p.sparkSession.range(cells * cells).select((F.col("id") % cells).cast("int").alias("cx"), F.floor(F.col("id") / cells).cast("int").alias("cy"))
    d = every.join(got, ["cx", "cy"], "left").select(F.coalesce("count", F.lit(0)).alias("n"))
    return d.agg(F.count(F.lit(1)).alias("n_cells"), F.avg("n").alias("mean"), (F.var_pop("n") / F.avg("n")).alias("ratio"))


def region_coverage(c: DataFrame, w: DataFrame) -> DataFrame:
    """(qid, n_candidates, positive, negative, either): shares of candidates that witnesses settle."""
    d = verify.decides(c, w).groupBy("qid", "id").agg(F.max((F.col("kind") == "positive").cast("int")).alias("p"), F.max((F.col("kind") == "negative").cast("int")).alias("n"))
    g = c.select("qid", "id").join(d, ["qid", "id"], "left").groupBy("qid").agg(F.count(F.lit(1)).alias("n_candidates"), F.sum(F.coalesce("p", F.lit(0))).alias("p"), F.sum(F.coalesce("n", F.lit(0))).alias("n"), F.count(F.coalesce("p", "n")).alias("e"))
    return g.select("qid", "n_candidates", (F.col("p") / F.col("n_candidates")).alias("positive"), (F.col("n") / F.col("n_candidates")).alias("negative"), (F.col("e") / F.col("n_candidates")).alias("either"))


def accessed(c: DataFrame, q: DataFrame, index: DataFrame) -> DataFrame:
    """(qid, n_accessed): candidates and their neighbours in the index, each once, without the query itself."""
    near = c.select("qid", "id").join(index.select("id", "nbrs.id").toDF("id", "near"), "id").select("qid", F.explode(F.array_append("near", F.col("id"))).alias("id"))
    near = near.join(q.select("qid", "q_id"), "qid").where("q_id IS NULL OR id <> q_id")
    return near.groupBy("qid").agg(F.count_distinct("id").alias("n_accessed"))


def costs(p: DataFrame, q: DataFrame, index: DataFrame | None = None) -> DataFrame:
    """(algorithm, k, qid, n_candidates, n_verified, n_accessed, n_result) for the engine and its competitors.

    verified: candidates with a check of their own (a kNN query, or for arc bounds a count). accessed: with an index,
    candidates and their neighbours; for arc bounds the points within twice the largest bound. Each algorithm's result
    is its own: six sectors answer by a kNN radius for each candidate, arc bounds by counting."""
    q = cut(q)
    c = cut(candidates.six_sector(p, q))
    n_cand = c.groupBy("qid").agg(F.count(F.lit(1)).alias("n_candidates"))
    n_acc = accessed(c, q, index) if index is not None else n_cand.select("qid", F.lit(None).cast("long").alias("n_accessed"))
    frame = lambda name, f: f.join(q.select("qid", "k"), "qid").select(F.lit(name).alias("algorithm"), "k", "qid", *(F.col(x).cast("long").alias(x) for x in ("n_candidates", "n_verified", "n_accessed", "n_result")))
    members = F.sum(F.col("member").cast("int")).alias("n_result")
    d = rknn.conic_decisions(p, q, candidates=c, match="graph" if index is not None else "exhaustive", index=index)
    ours = d.groupBy("qid").agg(F.sum((F.col("decision") == "knn").cast("int")).alias("n_verified"), members)
    conic = cut(frame("conic", n_cand.join(n_acc, "qid", "left").join(ours, "qid", "left")))
    one = verify.by_knn(c, p, q).groupBy("qid").agg(F.count("r").alias("n_verified"), members)
    six = cut(frame("six_sector", n_cand.join(n_acc, "qid", "left").join(one, "qid", "left")))
    bounds, pruners = baselines.arc_scan(p, q)
    bounds, pruners = cut(bounds), cut(pruners)
    m = baselines.arc_verify(baselines.arc_candidates(bounds, pruners), bounds, pruners, q).groupBy("qid").agg(F.count(F.lit(1)).alias("n_verified"), members)
    top = bounds.groupBy("qid").agg(F.max("bound").alias("top"))
    read = pruners.select("qid", "id", "d2").distinct().join(top, "qid").where("sqrt(d2) <= 2 * top").groupBy("qid").agg(F.count(F.lit(1)).alias("n_accessed"))
    arc = cut(frame("arc_bound", m.join(read, "qid", "left").withColumn("n_candidates", F.col("n_verified"))))
    return conic.unionByName(six).unionByName(arc)


def summary(c: DataFrame) -> DataFrame:
    """Means over queries beside the expected values."""
    d = c.groupBy("algorithm", "k").agg(*(F.round(F.avg(x), 2).alias(x) for x in ("n_candidates", "n_verified", "n_accessed", "n_result")))
    return d.withColumns({"expected_verified": F.round(theory.verified("k"), 2), "expected_accessed": F.round(theory.accessed("k"), 2)})


def spark_metrics(df: DataFrame, name: str = "revnn") -> tuple[dict, float]:
    """Rows of a plan through observe(), and milliseconds."""
    from pyspark.sql import Observation

    o = Observation(name)
    ms = timed(lambda: df.observe(o, F.count(F.lit(1)).alias("rows")))
    return o.get, ms
