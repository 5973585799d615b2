"""What the second round's findings asked for; each would have failed before."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import revnn.operators_queries  # noqa: F401  (registers queries)
from revnn import queries, workloads
from revnn.functions import sql as sqlfunctions
from revnn.operators import cascade, graph, knn, rknn, verify, voronoi
from revnn.plans.cuts import cut
from revnn.sources import points as S


def test_a_query_at_the_radius_is_no_closer_point():
    """a power of one number and a product may differ in the last bit; the query's own row then shut members out."""
    rng = np.random.default_rng(5)
    rows = []
    for qid in range(30_000):
        x, y, qx, qy = rng.random(4).tolist()
        rows += [(qid, qx, qy, 1, 1, 0, x, y), (qid, qx, qy, 1, 1, 1, qx, qy)]
    udtf = sqlfunctions.AnswerBundle.func
    lost = 0
    for i in range(0, len(rows), 2):
        one = udtf()
        for r in rows[i : i + 2]:
            one.eval(dict(zip(("qid", "qx", "qy", "q_id", "k", "id", "x", "y"), r, strict=True)))
        lost += [(q, p, m) for q, p, m in one.terminate()] != [(rows[i][0], 0, True)]
    assert lost == 0


def layouts():
    rng = np.random.default_rng(3)
    yield "uniform", rng.random((300, 2))
    yield "clustered", np.vstack([rng.normal(0, 1e-3, (200, 2)), rng.random((60, 2)) * 50])
    yield "copies", np.round(rng.random((300, 2)) * 6)
    yield "one place", np.ones((40, 2))
    yield "line", np.column_stack([np.arange(150.0), np.zeros(150)])
    yield "fewer than k", rng.random((4, 2))


def frame(spark, xy):
    return spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(xy)], "id long, x double, y double")


def refuse(*_, **__):
    raise AssertionError("query rows came to the driver, or every pair was made")


def test_radii_of_all_points_by_blocks(spark, monkeypatch):
    """radii of whole tables leave no query rows on the driver and equal the definition."""
    for name, xy in layouts():
        p = frame(spark, xy)
        for k in (1, 5):
            want = {r.id: r.r for r in knn.knn_radius(p, None, k, "exact").collect()}
            with monkeypatch.context() as m:
                m.setattr(knn.blocks, "BLOCK", 24)
                m.setattr(knn.grid, "bounded", refuse)
                assert {r.id: r.r for r in knn.knn_radius(p, None, k).collect()} == want, (name, k)
    some = spark.createDataFrame([(i,) for i in (3, 5, 38)], "id long")
    assert {r.id: r.r for r in knn.knn_radius(p, some, 1).collect()} == {3: pytest.approx(want_radius(p, 3))}


def want_radius(p, i):
    xy = {r.id: (r.x, r.y) for r in p.collect()}
    return min(np.hypot(xy[i][0] - x, xy[i][1] - y) for j, (x, y) in xy.items() if j != i)


def test_neighbours_of_all_points_by_blocks(spark, monkeypatch):
    """all points as queries, ties and copies included."""
    for name, xy in layouts():
        p = frame(spark, xy)
        want = {(r.qid, r.id): (r.dist, r["rank"]) for r in knn.knn_self(p, 3, "exact").collect()}
        with monkeypatch.context() as m:
            m.setattr(knn.blocks, "BLOCK", 24)
            m.setattr(knn.grid, "bounded", refuse)
            assert {(r.qid, r.id): (r.dist, r["rank"]) for r in knn.knn_self(p, 3).collect()} == want, name
            knn.nn_graph(p).collect()


def test_definition_makes_no_pair_of_all_points(spark, monkeypatch):
    """The definition's radii come without every pair."""
    p = frame(spark, dict(layouts())["copies"])
    q = p.where("id < 5").selectExpr("CAST(id AS INT) AS qid", "x AS qx", "y AS qy", "id AS q_id", "4 AS k")
    r = {i.id: i.r for i in knn.knn_radius(p, None, 4, "exact").collect()}
    at = {i.id: (i.x, i.y) for i in p.collect()}
    want = {(a, b) for a in range(5) for b in at if a != b and np.hypot(at[a][0] - at[b][0], at[a][1] - at[b][1]) <= r[b]}
    monkeypatch.setattr(knn, "knn_exact", refuse)
    assert {(i.qid, i.id) for i in rknn.rknn_definition(p, q).collect()} == want


def test_intervals_meet_no_triple_join(spark):
    """the interval form plans no join of pairs with third points, and links what cells link."""
    p = frame(spark, np.random.default_rng(8).random((700, 2)))
    d = voronoi.neighbors_by_intervals(p)
    assert "Join" not in d._jdf.queryExecution().executedPlan().toString()
    assert {tuple(r) for r in d.collect()} == {(r.src, r.dst) for r in voronoi.delaunay_edges(p).collect()}


def test_metric_witnesses_share_radii(spark):
    """radii are found once for all queries; decisions are those of a plain walk over the definition."""
    x = np.random.default_rng(9).normal(size=(90, 8))
    v = spark.createDataFrame([(i, a.tolist()) for i, a in enumerate(x)], "id long, v array<double>")
    q = spark.createDataFrame([(1, 4), (2, 50)], "qid int, q_id long")
    for dims in (2, 8):
        y = x[:, :dims]
        d = np.sqrt(((y[:, None] - y[None]) ** 2).sum(axis=2))
        r = np.sort(d + np.diag([np.inf] * 90), axis=1)[:, 2]
        known = {i.id: i for i in rknn._metric_radii(v.selectExpr("id", f"slice(v, 1, {dims}) AS v"), 90, 3).collect()}
        assert all(known[i].r == pytest.approx(r[i]) for i in range(90))
        got = {(i.qid, i.id): (i.member, i.decision, i.witness_id) for i in rknn.conic_metric(v, q, 3, dims).collect()}
        for qid, own in ((1, 4), (2, 50)):
            walk, seen = [], {}
            for i in cascade.visit_order(d[own], np.arange(90), r[own]):
                if i == own:
                    continue
                if d[own, i] <= r[own] / 2 * (1 - 1e-12):
                    seen[i] = (True, "semi", None)
                    continue
                by = next(((w, yes) for w, yes in walk if (d[own, i] + d[w, i] <= r[w] * (1 - 1e-12) if yes else d[own, i] - d[w, i] > r[w] * (1 + 1e-12))), None)
                if by:
                    seen[i] = (by[1], "positive" if by[1] else "negative", by[0])
                else:
                    seen[i] = (d[own, i] <= r[i], "knn", None)
                    walk.append((i, d[own, i] <= r[i]))
            assert {i: got[qid, i] for i in range(90) if i != own} == seen


def test_experiments_read_given_tables(spark, sf, monkeypatch):
    """Points and values of k come from tables that Spark reads, not from made-up rows."""
    monkeypatch.setattr(workloads.S, "uniform", refuse)
    for f in ("times", "counts", "conic_counts"):
        monkeypatch.setattr(workloads, f, lambda p, *_, **__: p.selectExpr("CAST(id AS STRING) AS algorithm", "1 AS k", "x AS ms"))
    reads = lambda name: {f.rsplit("/", 1)[-1].split(".")[0] for f in queries.QUERIES[name](spark, sf).inputFiles()}
    assert reads("w1_time_vs_n") == {"supplier", "customer", "orders"}
    assert reads("w1_small_n") == {"supplier"}
    assert reads("w3_w4_counts_uniform") == {"customer"}
    for name in ("a06_theory", "w2_time_vs_k_uniform", "w2_time_vs_k_uniform_1000", "w3_verified_uniform_1000000", "w6_savings"):
        assert reads(name) == {"orders"}, name
    assert queries.QUERIES["op_data_source"](spark, sf).collect() == [(S.load(spark, sf, "orders_uniform").count(), 0)]


def test_expansion_of_all_points_needs_no_level_of_joins(spark, monkeypatch):
    """without a limit a query walks in one task, and finds what level after level of joins finds."""
    p = frame(spark, np.random.default_rng(4).random((120, 2)))
    q = S.sample_queries(p, 4, 3)
    index = cut(voronoi.cells(p).select("id", "x", "y", "nbrs"))
    rows = lambda d: sorted(map(tuple, d.collect()))
    cuts = []
    monkeypatch.setattr(graph, "cut", lambda d: cuts.append(1) or cut(d))
    got = [rows(d) for d in graph.delaunay_expand(index, q, max_hops=None, expand="all")]
    assert len(cuts) == 1
    monkeypatch.setattr(graph, "WALK_NUMBERS", 0)
    assert [rows(d) for d in graph.delaunay_expand(index, q, max_hops=None, expand="all")] == got


def test_radii_of_many_neighbours_keep_none(spark, monkeypatch):
    """where candidates have very many neighbours, radii come without rows for these."""
    p = frame(spark, dict(layouts())["uniform"])
    c = p.where("id % 3 = 0").withColumn("k", F.lit(100)).unionByName(p.where("id % 5 = 0").withColumn("k", F.lit(299)))
    want = sorted(map(tuple, verify.radii(c, p).collect()))
    monkeypatch.setattr(verify, "NEIGHBOURS", 1000)
    monkeypatch.setattr(verify, "knn_grid", refuse)
    assert sorted(map(tuple, verify.radii(c, p).collect())) == want
    assert len(want) == 160
