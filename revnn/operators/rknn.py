"""Reverse k nearest neighbours: by definition, by the conic engine (bundles or waves), for all points at once.

A point is a member if fewer than k other points are strictly closer to it than the query. Results are (qid, id)."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from revnn.functions.geometry import dist_v
from revnn.operators import cascade, metric, verify
from revnn.operators.candidates import six_sector
from revnn.operators.knn import knn_radius, knn_self
from revnn.plans import grid
from revnn.plans.cuts import cut
from revnn.plans.density import density

DECISIONS = "qid int, id long, member boolean, decision string, witness_id long, r double, visit_ord int"
#: Points of a bundle beyond which a query goes through waves instead of one task.
MAX_BUNDLE = 2_000_000
#: Radius of a bundle in distances of the 3k-th candidate, at most; all candidates of an inner query lie within half of it.
TIGHT = 4.0


def rknn_definition(p: DataFrame, q: DataFrame) -> DataFrame:
    """Every point's radius, then every query against every circle; radii come from blocks, whose answers are exact."""
    ks = [r.k for r in q.select("k").distinct().collect()]
    out = None
    for k in ks:
        r = knn_radius(p, None, k).drop("k")
        from revnn.functions.geometry import dist2

        d = q.where(F.col("k") == k).join(p, F.expr("q_id IS NULL OR id <> q_id")).join(r, "id")
        d = d.where(F.sqrt(dist2("x", "y", "qx", "qy")) <= F.col("r")).select("qid", "id")
        out = d if out is None else out.unionByName(d)
    return out if out is not None else q.join(p, F.lit(False)).select("qid", "id")


def all_points(p: DataFrame, k: int) -> DataFrame:
    """(qid, id) for every point as a query: the kNN self-join read backwards."""
    return knn_self(p, k).select(F.col("id").alias("qid"), F.col("qid").alias("id"))


def conic(p: DataFrame, q: DataFrame, **options) -> DataFrame:
    """(qid, id) of all members."""
    return conic_decisions(p, q, **options).where("member").select("qid", "id")


def conic_decisions(p: DataFrame, q: DataFrame, order: str = "boundary_out", match: str = "exhaustive", rules=cascade.RULES, index: DataFrame | None = None, plan: str = "auto", candidates: DataFrame | None = None, max_bundle: int = MAX_BUNDLE) -> DataFrame:
    """Every candidate with the rule that settled it.

    match='graph' reaches witnesses through visited neighbours of the neighbour index (id, nbrs); 'exhaustive' tries
    all. plan: 'bundle' ships what one query needs to one task, 'wave' joins instead, 'auto' takes waves for queries
    whose bundle may be larger than max_bundle. Waves visit in the standard order and try all witnesses: another order
    or matching changes how many witnesses there are, never the answer.

    Bundles are tightened: they end at TIGHT times the distance of the 3k-th candidate, so that a query at an edge,
    whose emptier sectors look far, ships no more than others. Candidates whose circle sticks out are deferred: conics
    of the others are tried first, and the few that stay open get a kNN query of their own on the grid."""
    rows = grid.bounded(q)
    if rows is None or plan == "wave":
        return _decisions_by_joins(p, q, order, match, rules, index, plan, candidates, max_bundle)
    spread = density(p)
    c = six_sector(p, q, spread=spread, rows=rows) if candidates is None else candidates
    if not rows or not spread.box[0]:
        return c.limit(0).selectExpr("CAST(qid AS INT) AS qid", "id", "false AS member", "'' AS decision", "CAST(NULL AS LONG) AS witness_id", "d2 AS r", "0 AS visit_ord")
    near = F.sort_array(F.collect_list("d2"))
    at = c.join(F.broadcast(grid.local(rows, q).select("qid", "k")), "qid").groupBy("qid", "k").agg(near.alias("d2"))
    nth = lambda n: F.try_element_at("d2", n.cast("int"))
    state = {r.qid: r for r in at.select("qid", F.sqrt(F.array_max("d2")).alias("far"), F.sqrt(F.coalesce(nth(3 * F.col("k")), F.array_max("d2"))).alias("mid"), F.coalesce(F.sqrt(nth(F.col("k"))), F.lit(float("inf"))).alias("r_q")).collect()}
    rows = [r for r in rows if r["qid"] in state]
    reach = [min(2 * state[r["qid"]].far, TIGHT * state[r["qid"]].mid) for r in rows]
    r_q = [state[r["qid"]].r_q for r in rows]
    xy = np.array([(r["qx"], r["qy"]) for r in rows], float).reshape(-1, 2)
    ks = np.array([r["k"] for r in rows], float)
    bundle = grid.within_each(p, rows, q, reach, spread.box).select("qid", "id", "x", "y")
    if plan == "auto" and (np.pi * np.square(reach) * spread.around(xy, ks) > max_bundle / 8).any():
        size = {r.qid: r["count"] for r in bundle.groupBy("qid").count().collect()}
        large = [r for r in rows if size.get(r["qid"], 0) > max_bundle]
        if large:
            rest = [r for r in rows if size.get(r["qid"], 0) <= max_bundle]
            some = lambda part: (grid.local(part, q), c.join(F.broadcast(grid.local(part, q).select("qid")), "qid", "left_semi"))
            out = waves(p, *some(large), rules)
            return out if not rest else conic_decisions(p, some(rest)[0], order, match, rules, index, "bundle", some(rest)[1]).unionByName(out)
    left = c.select("qid", "id", "x", "y").join(F.broadcast(grid.local(rows, q, reach=reach, r_q=r_q)), "qid").select("qid", "id", "x", "y", "qx", "qy", "q_id", "k", "reach", "r_q")
    if all(2 * state[r["qid"]].far <= x for r, x in zip(rows, reach, strict=True)):
        return _settled(left, bundle, order, match, rules, index)
    # deferred candidates: few, and radii need points beyond the bundle
    d = cut(_settled(left, bundle, order, match, rules, index))
    late = cut(d.where("decision = 'deferred'").select("qid", "id").join(c.select("qid", "id", "x", "y", "d2"), ["qid", "id"]).join(F.broadcast(grid.local(rows, q).select("qid", "k")), "qid"))
    if late.isEmpty():
        return d
    r = late.join(verify.radii(late, p), ["id", "k"]).select("qid", "id", "d2", F.col("r").alias("r2_"))
    d = d.join(r, ["qid", "id"], "left")
    here = F.col("decision") == "deferred"
    return d.select("qid", "id", F.when(here, F.sqrt("d2") <= F.col("r2_")).otherwise(F.col("member")).alias("member"), F.when(here, F.lit("knn")).otherwise(F.col("decision")).alias("decision"), "witness_id", F.when(here, F.col("r2_")).otherwise(F.col("r")).alias("r"), "visit_ord")


def _decisions_by_joins(p, q, order, match, rules, index, plan, candidates, max_bundle) -> DataFrame:
    """For batches of queries that no driver should hold, and for waves."""
    box = grid.box_of(p)
    q = cut(q)
    c = cut(six_sector(p, q, box=box) if candidates is None else candidates)
    if plan == "wave":
        return waves(p, q, c, rules)
    reach = c.groupBy("qid").agg((2 * F.sqrt(F.max("d2"))).alias("reach")).join(verify.query_radius(c, q), "qid")
    asked = cut(q.join(reach, "qid"))
    n, side = asked.agg(F.count(F.lit(1)), F.percentile_approx("reach", 0.5)).first()
    bundle = grid.within(p, asked, "reach", max(side or 1.0, 1e-12), n, box).select("qid", "id", "x", "y")
    if plan == "auto":
        size = cut(bundle.groupBy("qid").count())
        large = size.where(F.col("count") > max_bundle).select("qid")
        if not large.isEmpty():
            some = lambda d, how: d.join(large, "qid", how)
            rest = conic_decisions(p, some(q, "left_anti"), order, match, rules, index, "bundle", some(c, "left_anti"))
            return rest.unionByName(waves(p, some(q, "left_semi"), some(c, "left_semi"), rules))
    return _settled(c.select("qid", "id", "x", "y").join(asked.select("qid", "qx", "qy", "q_id", "k", "reach", "r_q"), "qid"), bundle, order, match, rules, index)


def _settled(left: DataFrame, bundle: DataFrame, order: str, match: str, rules, index: DataFrame | None) -> DataFrame:
    """The cascade over candidates (with their query's columns) and bundles, a query at a time."""
    if match == "graph":
        if index is None:
            raise ValueError("match='graph' needs a neighbour index")
        left = left.join(index.select("id", F.transform("nbrs", lambda x: x["id"]).alias("near")), "id", "left")
    else:
        left = left.withColumn("near", F.lit(None).cast("array<bigint>"))

    def settle(cand: pd.DataFrame, points: pd.DataFrame) -> pd.DataFrame:
        if cand.empty:
            return pd.DataFrame(columns=[x.split()[0] for x in DECISIONS.split(", ")])
        one, ids = cand.iloc[0], cand["id"].to_numpy()
        place = {i: n for n, i in enumerate(ids.tolist())}
        near = [[place[j] for j in (x if x is not None else ()) if j in place] for x in cand["near"]] if match == "graph" else None
        o = cascade.run((one.qx, one.qy), one.q_id, int(one.k), cand[["x", "y"]].to_numpy(), ids, points[["x", "y"]].to_numpy(), points["id"].to_numpy(), one.r_q, one.reach, order, match, rules, near)
        turn = np.empty(len(ids), int)
        turn[o.order] = np.arange(len(ids))
        witness = pd.array([ids[w] if w >= 0 else None for w in o.witness], dtype="Int64")
        return pd.DataFrame({"qid": int(one.qid), "id": ids, "member": o.member, "decision": o.rule, "witness_id": witness, "r": np.where(o.rule == "knn", o.radius, np.nan), "visit_ord": turn})

    # renamed, so that the sides share no attribute
    other = bundle.toDF("b_qid", "id", "x", "y")
    return left.toDF(*left.columns).groupBy("qid").cogroup(other.groupBy("b_qid")).applyInPandas(settle, DECISIONS)


def waves(p: DataFrame, q: DataFrame, c: DataFrame, rules=cascade.RULES) -> DataFrame:
    """The cascade by joins, for bundles that no task should hold.

    Each round makes the next candidate of every sector a witness (at most six for a query), computes their radii with
    grid kNN, and settles what their conics cover. Rounds shrink the undecided set; one count each goes to the driver."""
    d = verify.with_queries(c, q).join(verify.query_radius(c, q), "qid")
    inner = F.sqrt("d2") <= F.col("r_q")
    w = Window.partitionBy("qid").orderBy((~inner).cast("int"), F.when(inner, -F.col("d2")).otherwise(F.col("d2")), "id")
    d = d.withColumn("visit_ord", F.row_number().over(w) - 1)
    semi = (F.col("d2") == 0) | (F.sqrt("d2") <= F.col("r_q") / 2 * (1 - 1e-12)) if "semi" in rules else F.col("d2") == 0
    shape = lambda f, member, decision, witness, r: f.select("qid", "id", member.alias("member"), decision.alias("decision"), witness.cast("long").alias("witness_id"), r.alias("r"), "visit_ord")
    none, nan = F.lit(None), F.lit(float("nan"))
    done = [cut(shape(d.where(semi), F.lit(True), F.lit("semi"), none, nan))]
    left = cut(d.where(~semi))
    while not left.isEmpty():
        front = Window.partitionBy("qid", "sector").orderBy("visit_ord")
        wave = cut(left.withColumn("_n", F.row_number().over(front)).where("_n = 1").drop("_n"))
        known = cut(wave.join(verify.radii(wave, p), ["id", "k"]).withColumn("member", F.sqrt("d2") <= F.col("r")))
        done.append(cut(shape(known, F.col("member"), F.lit("knn"), none, F.col("r"))))
        witnesses = known.select("qid", F.col("id").alias("witness_id"), F.col("x").alias("wx"), F.col("y").alias("wy"), F.sqrt("d2").alias("wd"), F.col("r").alias("wr"))
        left = left.join(known.select("qid", "id"), ["qid", "id"], "left_anti")
        kinds = [k for k in ("positive", "negative") if k in rules]
        hit = verify.decides(left, witnesses, kinds).groupBy("qid", "id").agg(F.min(F.struct("witness_id", "kind")).alias("by"))
        settled = cut(left.join(hit, ["qid", "id"]))
        done.append(shape(settled, F.col("by.kind") == "positive", F.col("by.kind"), F.col("by.witness_id"), nan))
        left = cut(left.join(settled.select("qid", "id"), ["qid", "id"], "left_anti"))
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    return out.select(F.col("qid").cast("int").alias("qid"), "id", "member", "decision", "witness_id", "r", F.col("visit_ord").cast("int").alias("visit_ord"))


#: Numbers of a table of vectors up to which it goes to tasks as a whole.
METRIC_NUMBERS = 12_000_000
#: Witnesses of a round of :func:`metric_waves`, at most (they are broadcast).
METRIC_WAVE = 4096
#: Vectors of a packed row, vectors whose radii a task finds at most, tasks that small tables are dealt over, rows of
#: decisions of a task, about.
METRIC_PACK, METRIC_ASKS, METRIC_TASKS, METRIC_ROWS = 4096, 8192, 12, 1_000_000


def conic_metric(v: DataFrame, q_ids: DataFrame, k: int, dims: int | None = None, rules=cascade.RULES, numbers: int = METRIC_NUMBERS) -> DataFrame:
    """The same rules in d dimensions (they use the triangle inequality only): decisions of every point for each query.

    v: (id, v array<double>), q_ids: (qid, q_id), a bounded set. There are no sectors, so every other point is a
    candidate. Tables that fit a task go packed to a few tasks, each for some of the queries, with radii that all queries
    share; larger ones stream past the queries in rounds."""
    v = v.select("id", (F.slice("v", 1, dims) if dims else F.col("v")).alias("v"))
    rows, wide = v.agg(F.count(F.lit(1)), F.max(F.size("v"))).first()
    if rows * (wide or 0) > numbers:
        return metric_waves(v, q_ids, k, rules)
    known = _packed(cut(_metric_radii(v, rows, k)))
    q = cut(q_ids.select("qid", "q_id"))
    asked = max(1, q.count())
    parts = min(asked, max(METRIC_TASKS, -(-asked * rows // METRIC_ROWS)))
    turn = (F.row_number().over(Window.orderBy("qid", "q_id")) - 1) % parts
    own = q.withColumn("part", turn).groupBy("part").agg(F.collect_list(F.struct("qid", "q_id")).alias("q")).select("part", F.col("q.qid").alias("qids"), F.col("q.q_id").alias("q_ids"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for _, f in _by_part(batches):
            ids, x, r, near = _unpacked(f)
            for qid, q_id in zip(f["qids"].iloc[0], f["q_ids"].iloc[0], strict=True):
                yield _metric_one(int(qid), int(q_id), k, ids, x, r, near, rules)

    return _dealt(known, parts).join(F.broadcast(own), "part").mapInPandas(run, DECISIONS)


def _packed(v: DataFrame) -> DataFrame:
    """Rows of many vectors, as bytes: (ids, x) and every column beside id and v. Four bytes a number where no bit is lost."""
    more = [c for c in v.columns if c not in ("id", "v")]

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for i in range(0, len(b), METRIC_PACK):
                f = b.iloc[i : i + METRIC_PACK]
                x = np.stack(f["v"].to_numpy())
                half = x.astype("f4")
                short = bool((half == x).all())
                yield pd.DataFrame({"n": [len(f)], "short": [short], "ids": [f["id"].to_numpy("i8").tobytes()], "x": [(half if short else x).tobytes()]} | {c: [f[c].to_numpy("f8").tobytes()] for c in more})

    return v.select("id", "v", *more).mapInPandas(pack, ", ".join(["n int, short boolean, ids binary, x binary", *(f"{c} binary" for c in more)]))


def _unpacked(f: pd.DataFrame) -> list[np.ndarray]:
    """ids, x and the other packed columns, in the order of the ids."""
    ids = np.concatenate([np.frombuffer(b, "i8") for b in f["ids"]])
    turn = np.argsort(ids, kind="stable")
    x = np.concatenate([np.frombuffer(b, "f4" if short else "f8").astype("f8").reshape(n, -1) for b, short, n in zip(f["x"], f["short"], f["n"], strict=True)])[turn]
    return [ids[turn], x, *(np.concatenate([np.frombuffer(b, "f8") for b in f[c]])[turn] for c in ("r", "near") if c in f)]


def _dealt(packed: DataFrame, parts: int) -> DataFrame:
    """The whole packed table for each part, a partition each."""
    return packed.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).repartitionById(parts, "part")


def _by_part(batches: Iterator[pd.DataFrame]) -> Iterator[tuple[int, pd.DataFrame]]:
    held = list(batches)
    if held:
        yield from pd.concat(held).groupby("part")


def _metric_radii(v: DataFrame, rows: int, k: int) -> DataFrame:
    """(id, v, r, near): each vector's radius and the distance of its nearest other, from one scan of pairs of leaves.

    Each task has the whole table and orders it alike; it answers for every parts-th leaf."""
    parts = max(min(METRIC_TASKS, -(-rows // metric.LEAF)), -(-rows // METRIC_ASKS), 1)

    def look(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part, f in _by_part(batches):
            ids, x = _unpacked(f)
            for own, r, near in metric.radii(x, k, int(part), parts):
                yield pd.DataFrame({"id": ids[own], "v": list(x[own]), "r": r, "near": near})

    return _dealt(cut(_packed(v)), parts).mapInPandas(look, "id long, v array<double>, r double, near double")


def metric_waves(v: DataFrame, q_ids: DataFrame, k: int, rules=cascade.RULES) -> DataFrame:
    """:func:`conic_metric` for any table: each round broadcasts the next witnesses of all queries, finds their radii in
    one pass over the vectors (each task keeps k distances of a witness), and settles what their conics cover.

    Rounds have twice as many witnesses as the one before, so there are few where conics fade."""
    v = cut(v)
    q = cut(q_ids.join(v.withColumnsRenamed({"id": "q_id", "v": "qv"}), "q_id"))
    n_queries = max(1, q.count())
    d = cut(v.join(F.broadcast(q)).where("id <> q_id").select("qid", "id", dist_v("v", "qv").alias("d")))
    first = lambda f, by, key: f.withColumn("_n", F.row_number().over(Window.partitionBy(*by).orderBy(key))).where(F.col("_n") <= k)
    far = lambda f, by, key: first(f, by, key).groupBy(*by).agg(F.when(F.count(F.lit(1)) >= k, F.max(key)).otherwise(F.lit(float("inf"))).alias("far"))
    d = d.join(far(d, ["qid"], "d").withColumnRenamed("far", "r_q"), "qid")
    inner = F.col("d") <= F.col("r_q")
    turn = Window.partitionBy("qid").orderBy((~inner).cast("int"), F.when(inner, -F.col("d")).otherwise(F.col("d")), "id")
    d = cut(d.withColumn("visit_ord", (F.row_number().over(turn) - 1).cast("int")))
    shape = lambda f, member, decision, witness, r: f.select(F.col("qid").cast("int").alias("qid"), "id", member.alias("member"), decision.alias("decision"), witness.cast("long").alias("witness_id"), r.alias("r"), "visit_ord")
    none, nan = F.lit(None), F.lit(float("nan"))
    semi = F.col("d") <= F.col("r_q") / 2 * (1 - 1e-12) if "semi" in rules else F.lit(False)
    done, left, width = [shape(d.where(semi), F.lit(True), F.lit("semi"), none, nan)], cut(d.where(~semi)), 4
    while not left.isEmpty():
        nth = F.row_number().over(Window.partitionBy("qid").orderBy("visit_ord"))
        wave = left.withColumn("_n", nth).where(F.col("_n") <= width).drop("_n")
        w = cut(wave.join(v, "id").select("qid", F.col("id").alias("wid"), F.col("d").alias("wd"), F.col("v").alias("wv"), "visit_ord"))
        meet = v.join(F.broadcast(w.select("wid", "wv").dropDuplicates(["wid"]))).where("id <> wid").select("wid", dist_v("v", "wv").alias("dw"))
        w = cut(w.join(far(meet, ["wid"], "dw").withColumnRenamed("far", "wr"), "wid", "left").withColumn("wr", F.coalesce("wr", F.lit(float("inf")))))
        member = F.col("wd") <= F.col("wr")
        done.append(shape(w.withColumnRenamed("wid", "id"), member, F.lit("knn"), none, F.col("wr")))
        rest = left.join(w.select("qid", F.col("wid").alias("id")), ["qid", "id"], "left_anti")
        open_ = rest.join(v, "id").join(F.broadcast(w.drop("visit_ord")), "qid").withColumn("dw", dist_v("v", "wv"))
        yes = member & (F.col("d") + F.col("dw") <= F.col("wr") * (1 - 1e-12)) if "positive" in rules else F.lit(False)
        no = ~member & (F.col("d") - F.col("dw") > F.col("wr") * (1 + 1e-12)) if "negative" in rules else F.lit(False)
        hit = open_.where(yes | no).groupBy("qid", "id").agg(F.min(F.struct("wid", member.alias("member"))).alias("by"))
        settled = cut(rest.join(hit, ["qid", "id"]))
        done.append(shape(settled, F.col("by.member"), F.when(F.col("by.member"), "positive").otherwise("negative"), F.col("by.wid"), nan))
        left = cut(rest.join(settled.select("qid", "id"), ["qid", "id"], "left_anti"))
        width = min(2 * width, max(4, METRIC_WAVE // n_queries))
    return reduce(DataFrame.unionByName, done)


def _metric_one(qid: int, q_id: int, k: int, ids: np.ndarray, x: np.ndarray, r: np.ndarray, near: np.ndarray, rules) -> pd.DataFrame:
    """Witnesses in the visiting order, each of which settles what is open."""
    own = int(np.flatnonzero(ids == q_id)[0])
    o = metric.run(x, ids, own, k, r, near, rules)
    witness = pd.Series(ids[o.witness], dtype="Int64").mask(o.witness < 0)
    return pd.DataFrame({"qid": qid, "id": ids[o.order], "member": o.member, "decision": o.rule, "witness_id": witness, "r": o.radius, "visit_ord": np.arange(len(o.order))})
