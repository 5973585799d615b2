"""The engine against the definition, the rules' soundness, the index, and plans."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from revnn.functions import geometry as G
from revnn.functions import regions as R
from revnn.operators import baselines, candidates, cascade, graph, knn, measures, rknn, verify, voronoi
from revnn.plans import grid
from revnn.plans.cuts import cut
from revnn.sources import points as S


def cloud(kind, n, seed=0):
    r = np.random.default_rng(seed)
    if kind == "clustered":
        x = r.random((6, 2))[r.integers(0, 6, n)] + r.normal(0, 0.02, (n, 2))
    elif kind == "stripes":
        x = np.column_stack([r.integers(0, 8, n) / 8, r.random(n)])
    elif kind == "lattice":
        x = np.array([(i % 12, i // 12) for i in range(n)], float)
    elif kind == "line":
        x = np.column_stack([r.random(n), np.full(n, 0.5)])
    elif kind == "copies":
        x = r.integers(0, 5, (n, 2)).astype(float)
    else:
        x = r.random((n, 2))
    return x


def frames(spark, x, k, n_queries=8, free=False):
    p = cut(spark.createDataFrame([(i, float(a), float(b)) for i, (a, b) in enumerate(x)], "id long, x double, y double"))
    return p, cut(S.free_queries(spark, n_queries, k) if free else S.sample_queries(p, n_queries, k))


def truth(x, queries, k):
    d2 = ((x[:, None] - x[None]) ** 2).sum(axis=2)
    np.fill_diagonal(d2, np.inf)
    r2 = np.sort(d2, axis=1)[:, k - 1] if len(x) > k else np.full(len(x), np.inf)
    out = set()
    for q in queries:
        to = (x[:, 0] - q.qx) ** 2 + (x[:, 1] - q.qy) ** 2
        out |= {(q.qid, int(i)) for i in np.flatnonzero(to <= r2) if i != q.q_id}
    return out


def pairs(df):
    return {(r.qid, r.id) for r in df.collect()}


@pytest.mark.parametrize("kind,k,free", [("uniform", 5, False), ("clustered", 3, True), ("stripes", 4, False), ("lattice", 4, False), ("line", 2, False), ("copies", 3, False), ("uniform", 200, False)])
def test_every_way_gives_the_definition(spark, kind, k, free):
    x = cloud(kind, 144)
    p, q = frames(spark, x, k, free=free)
    want = truth(x, q.collect(), k)
    assert pairs(rknn.rknn_definition(p, q)) == want
    assert pairs(rknn.conic(p, q)) == want
    assert pairs(baselines.six_sector(p, q)) == want
    assert pairs(baselines.arc_bound(p, q)) == want


def test_waves_lookup_and_all_points(spark):
    x = cloud("clustered", 120, 2)
    p, q = frames(spark, x, 3, 4)
    want = truth(x, q.collect(), 3)
    assert pairs(rknn.conic(p, q, plan="wave")) == want
    assert pairs(rknn.conic(p, q, max_bundle=1)) == want
    assert pairs(baselines.lookup(cut(baselines.stored_radii(p, 3)), q)) == want
    assert pairs(rknn.all_points(p, 3)) == truth(x, S.all_queries(p, 3).collect(), 3)


def test_rules_are_sound_and_order_is_free():
    """On random clouds every order, rule set and matching gives the definition's answer."""
    rnd = random.Random(4)
    for seed in range(25):
        x = cloud(rnd.choice(["uniform", "clustered", "stripes", "copies"]), 60, seed)
        k, q = rnd.choice([1, 2, 5, 9]), rnd.randrange(60)
        d2 = ((x[:, None] - x[None]) ** 2).sum(axis=2)
        np.fill_diagonal(d2, np.inf)
        r2 = np.sort(d2, axis=1)[:, k - 1]
        ids = np.array([i for i in range(60) if i != q])
        member = ((x - x[q]) ** 2).sum(axis=1)[ids] <= r2[ids]
        near = [[j for j in np.argsort(d2[i])[:6] if j != q] for i in ids]
        place = {int(i): n for n, i in enumerate(ids)}
        near = [[place[int(j)] for j in row] for row in near]
        for order in cascade.ORDERS:
            for rules in (cascade.RULES, ("semi",), ("positive",), ("negative",), ()):
                for match in ("exhaustive", "graph"):
                    o = cascade.run(x[q], q, k, x[ids], ids, x, np.arange(60), float(np.sqrt(r2[q])), np.inf, order, match, rules, near)
                    assert np.array_equal(o.member, member)
        settles = np.array([cascade.decided_by(np.sqrt(((x[ids[:10]] - x[q]) ** 2).sum(axis=1)), x[ids[:10]], i, float(np.sqrt(r2[ids[i]]))) for i in range(10)])
        assert len(cascade.minimum_cover(settles)) <= len(cascade.greedy_cover(settles))
    with pytest.raises(ValueError):
        cascade.minimum_cover(np.zeros((20, 20), bool))


def test_regions_on_worked_layouts(spark):
    """Points inside and outside of each region; empty regions; the direction of the hyperbola rule."""
    one = lambda c: spark.range(1).select(c.alias("v")).first().v
    assert one(R.in_knn_region(F.lit(1.0), F.lit(1.0))) and not one(R.in_knn_region(F.lit(1.1), F.lit(1.0)))
    assert one(R.semi_region(F.lit(0.5), F.lit(1.0))) and not one(R.semi_region(F.lit(0.51), F.lit(1.0)))
    # accepted witness: radius 3, at 2 from the query
    assert one(R.positive_region(F.lit(1.0), F.lit(1.5), F.lit(2.0), F.lit(3.0)))
    assert not one(R.positive_region(F.lit(2.0), F.lit(1.5), F.lit(2.0), F.lit(3.0)))
    assert not one(R.positive_region(F.lit(0.1), F.lit(0.1), F.lit(4.0), F.lit(3.0)))
    # rejected witness: radius 1, at 4 from the query
    assert one(R.negative_region(F.lit(5.0), F.lit(1.0), F.lit(4.0), F.lit(1.0)))
    assert not one(R.negative_region(F.lit(3.0), F.lit(2.5), F.lit(4.0), F.lit(1.0)))
    assert not one(R.negative_region(F.lit(9.0), F.lit(0.1), F.lit(0.5), F.lit(1.0)))


def test_sectors_are_half_open_and_equal_the_angle(spark):
    rows = [(float(np.cos(a)), float(np.sin(a)), int(a // (np.pi / 3))) for a in np.arange(0.01, 6.28, 0.05)] + [(1.0, 0.0, 0), (-1.0, 0.0, 3), (0.0, 0.0, -1)]
    d = spark.createDataFrame(rows, "x double, y double, s int").select("s", G.sector("x", "y").alias("t"), G.sector_any("x", "y", 12).alias("u"))
    for r in d.collect():
        assert r.s == r.t
        assert r.s < 0 or r.u // 2 == r.s


def test_knn_grid_is_exact_with_ties(spark):
    for kind, k in (("uniform", 7), ("copies", 4), ("line", 150)):
        p, q = frames(spark, cloud(kind, 140), k)
        rows = lambda d: {(r.qid, r.id, r["rank"]) for r in d.collect()}
        assert rows(knn.knn_grid(p, q)) == rows(knn.knn_exact(p, q))
    assert knn.knn_grid(p.limit(0), q).count() == 0


def test_self_counting_bound_loses_members(spark):
    """With the k-th instead of the (k+1)-th upper arc a point prunes itself: nothing is left at k = 1."""
    p, q = frames(spark, cloud("uniform", 100), 1, 10)
    bounds, pruners = baselines.arc_scan(p, q)
    short, _ = baselines.arc_scan(p, q.withColumn("k", F.lit(0)))
    full = pairs(baselines.arc_candidates(bounds, pruners).select("qid", "id"))
    assert pairs(rknn.conic(p, q)) <= full
    cut_short = pairs(baselines.arc_candidates(short, pruners).select("qid", "id"))
    assert not pairs(rknn.conic(p, q)) <= cut_short


def test_last_point_bound_loses_members(spark):
    """Expanding only through points that are nearer than the last one held in their sector misses members."""
    p = S.uniform(spark, 150)
    near = {r.id: [n.id for n in r.nbrs] for r in voronoi.cells(p).select("id", "nbrs").collect()}
    xy = {r.id: np.array([r.x, r.y]) for r in p.collect()}
    lost = 0
    for q in range(0, 150, 30):
        d = {i: float(np.hypot(*(xy[i] - xy[q]))) for i in xy if i != q}
        members = {i for i in d if sum(np.hypot(*(xy[i] - xy[j])) < d[i] for j in xy if j not in (i, q)) < 5}
        last, held, seen, level = {}, set(), {q}, [i for i in near[q]]
        while level:
            after = []
            for i in level:
                if i in seen:
                    continue
                seen.add(i)
                s = int(np.mod(np.arctan2(*(xy[i] - xy[q])[::-1]), 2 * np.pi) // (np.pi / 3))
                if d[i] <= last.get(s, np.inf):
                    last[s] = d[i]
                    held.add(i)
                    after += near[i]
            level = after
        lost += len(members - held)
    assert lost > 0


def test_regions_on_point_layouts(spark):
    """Points placed by hand inside and outside of an accepted witness's ellipse and a rejected one's hyperbola."""
    points = [(1, 1.0, 0.5), (2, 1.0, 1.5), (3, 5.0, 0.0), (4, 0.0, 1.0), (5, -0.4, 0.0), (6, -0.6, 0.0), (7, 4.0, 3.0), (8, 2.2, 0.0)]
    c = spark.createDataFrame([(1, i, x, y, x * x + y * y) for i, x, y in points], "qid int, id long, x double, y double, d2 double")
    w = spark.createDataFrame([(1, 100, 2.0, 0.0, 2.0, 3.0), (1, 200, 4.0, 0.0, 4.0, 1.0)], "qid int, witness_id long, wx double, wy double, wd double, wr double")
    got = {(r.witness_id, r.id, r.kind) for r in verify.decides(c, w).collect()}
    inside, beyond = {1, 5, 8}, {3, 7}
    assert {i for wid, i, kind in got if kind == "positive"} == inside and {wid for wid, _, kind in got if kind == "positive"} == {100}
    # 8 lies nearer to the query than to the far branch: 2.2 - 1.8 < 1
    assert {i for wid, i, kind in got if kind == "negative"} == beyond and {wid for wid, _, kind in got if kind == "negative"} == {200}


@pytest.mark.parametrize("kind", ["uniform", "clustered", "line"])
def test_index_equals_the_interval_form(spark, kind):
    p, q = frames(spark, cloud(kind, 80, 3), 5)
    p = cut(S.distinct_points(p))
    c = cut(voronoi.cells(p, per_cell=10))
    assert c.count() == p.count() and c.where("NOT certified").count() == 0
    e = {(r.src, r.dst) for r in voronoi.delaunay_edges(p).collect()}
    assert e == {(r.src, r.dst) for r in voronoi.neighbors_by_intervals(p).collect()}
    assert len(e) <= 3 * p.count() - 6
    _, b = voronoi.box_for(p)
    area = sum(voronoi.ring_area([(v.x, v.y) for v in r.ring]) for r in c.select("ring").collect())
    assert area == pytest.approx((b[2] - b[0]) * (b[3] - b[1]))
    if kind == "line":
        assert len(e) == p.count() - 1


def test_graph_walks(spark):
    p, q = frames(spark, cloud("uniform", 150, 5), 4)
    index = cut(voronoi.cells(p).select("id", "x", "y", "nbrs"))
    rows = lambda d: {(r.qid, r.id, r["rank"]) for r in d.collect()}
    assert rows(graph.knn_voronoi(index, q)) == rows(knn.knn_exact(p, q))
    direct = candidates.six_sector(p, q)
    c, n = graph.delaunay_expand(index, q, expand="all", max_hops=None)
    assert pairs(c) == pairs(direct)
    near, _ = graph.delaunay_expand(index, q)
    assert pairs(rknn.conic(p, q)) <= pairs(near)
    assert n.where("n_expanded > n_seen").count() == 0
    hops = graph.hops(voronoi.delaunay_edges(p), q.select(F.col("q_id").alias("src")), 4)
    m = rknn.conic(p, q).join(q.select("qid", F.col("q_id").alias("src")), "qid")
    assert m.join(hops, ["src", "id"], "left_anti").count() == 0
    assert pairs(rknn.conic(p, q, match="graph", index=index)) == pairs(rknn.conic(p, q))


def test_index_versions_and_patches(spark, tmp_path):
    p, _ = frames(spark, cloud("uniform", 90, 6), 4)
    voronoi.build_index(p, str(tmp_path / "i"), 1)
    index = voronoi.read_index(spark, str(tmp_path / "i"))
    assert index.count() == 90 and index.where("deg <> size(nbrs)").count() == 0
    one = p.where("id = 7")
    less = cut(voronoi.patch(index, one.limit(0), one.select("id")))
    changed = {r.id for r in less.where("changed").collect()}
    was = {n.id for n in index.where("id = 7").first().nbrs}
    assert was <= changed and less.count() == 89
    free = voronoi.insert_query(less, spark.createDataFrame([(1, *one.select("x", "y").first())], "qid int, qx double, qy double"))
    assert {r.id for r in free.collect()} == was


def test_counts_behave_as_expected(spark):
    """Witnesses: about sqrt(k) and below 4 sqrt(pi k) on average, fewer than arc-bound's, fewer than six sectors'."""
    p = cut(S.uniform(spark, 4000))
    mean = {}
    for k in (10, 40):
        q = cut(S.sample_queries(p, 20, k))
        mean |= {(r.algorithm, k): r for r in measures.summary(measures.costs(p, q)).collect()}
        assert mean["conic", k].n_verified < mean["arc_bound", k].n_verified < mean["six_sector", k].n_verified
        assert mean["conic", k].n_verified <= mean["conic", k].expected_verified
        assert mean["conic", k].n_result == pytest.approx(k, rel=0.2)
    slope = np.log(mean["conic", 40].n_verified / mean["conic", 10].n_verified) / np.log(4)
    assert 0.35 <= slope <= 0.65


def test_witness_sets(spark):
    p, q = frames(spark, cloud("uniform", 120, 8), 4)
    c = cut(candidates.six_sector(p, q))
    w = cut(verify.as_witnesses(c, p, q))
    assert verify.is_witness_set(c, w).where("NOT valid").count() == 0
    m = pairs(rknn.conic(p, q))
    for r in verify.decides(c, w).collect():
        assert ((r.qid, r.id) in m) == (r.kind == "positive")
    semi = {(r.qid, r.id) for r in verify.by_semi(c, q, slack=True).where("settled").collect()}
    assert semi <= m
    assert pairs(verify.by_range_count(c, p, q).where("member")) == m


def test_plans_have_no_nested_loops_and_prune_columns(spark, sf):
    from io import StringIO
    from contextlib import redirect_stdout

    p = S.load(spark, sf, "orders_uniform")
    q = cut(S.sample_queries(p, 5, 3))
    out = StringIO()
    with redirect_stdout(out):
        grid.within(p, q.withColumn("_r", F.lit(0.1)), "_r", 0.1, 5).explain("formatted")
        S.load(spark, sf, "events_time_value").explain("formatted")
    text = out.getvalue()
    assert "NestedLoop" not in text and "Cartesian" not in text
    assert "ReadSchema: struct<o_orderkey:bigint>" in text
    assert "ReadSchema: struct<event_id:bigint,ts:timestamp_ntz,value:double>" in text and "IsNotNull(value)" in text


def test_partitions_do_not_matter(spark):
    x = cloud("clustered", 100, 9)
    p, q = frames(spark, x, 4)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for n in ("1", "7"):
            spark.conf.set("spark.sql.shuffle.partitions", n)
            assert pairs(rknn.conic(p, q)) == truth(x, q.collect(), 4)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_sources(spark, tmp_path):
    d = spark.createDataFrame([(1, 1.0, 2.0), (2, None, 1.0), (3, float("nan"), 1.0), (None, 1.0, 1.0), (5, 1.0, 2.0)], "k long, a double, b double")
    spec = S.PointSpec("t", "k", "a", "b")
    assert {r.id for r in S.points(d, spec).collect()} == {1, 5}
    assert S.rejected(d, spec) == 3
    assert [r.id for r in S.points(d, S.PointSpec("t", "k", "a", "b", distinct=True)).collect()] == [1]
    S.points(d, spec).write.csv(str(tmp_path / "c"))
    assert S.file_points(spark, str(tmp_path / "c")).count() == 2


def test_entry_point(spark):
    import __spark_entry__ as e

    q, o = e.queries(), e.oracle_sql()
    assert set(o) <= set(q)
    assert e.entry(spark).count() > 0


def test_bundles_are_tightened_and_late_candidates_settled(spark):
    """Queries at the edge of a set: far candidates are deferred, and the answer is the definition's."""
    rnd = np.random.default_rng(3)
    xy = np.concatenate([rnd.random((300, 2)) * [1.0, 0.02], rnd.random((40, 2))])
    p = spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(xy)], "id long, x double, y double")
    q = spark.createDataFrame([(n + 1, float(xy[i][0]), float(xy[i][1]), i, 3) for n, i in enumerate([0, 5, 299, 310, 339])], "qid int, qx double, qy double, q_id long, k int")
    d = rknn.conic_decisions(p, q)
    rows = d.collect()
    assert {r.decision for r in rows} <= {"semi", "positive", "negative", "knn"}
    assert {(r.qid, r.id) for r in rows if r.member} == {tuple(r) for r in rknn.rknn_definition(p, q).collect()}


def test_density_follows_the_points(spark):
    from revnn.plans.density import density

    rnd = np.random.default_rng(4)
    xy = np.concatenate([rnd.normal(0.2, 0.001, (5000, 2)), rnd.random((1000, 2))])
    p = spark.createDataFrame([(i, float(x), float(y)) for i, (x, y) in enumerate(xy)], "id long, x double, y double")
    d = density(p)
    dense, thin = d.radius(np.array([[0.2, 0.2], [0.8, 0.8]]), np.array([60.0, 60.0]))
    assert d.counts.sum() == 6000 and dense < 0.02 < thin
    held = [int((((xy - at) ** 2).sum(axis=1) <= r * r).sum()) for at, r in (([0.2, 0.2], dense), ([0.8, 0.8], thin))]
    assert 20 <= held[0] <= 600 and 20 <= held[1] <= 180


def test_clock_holds_eager_work(spark):
    import time

    def slow():
        time.sleep(0.2)
        return spark.range(1)

    assert measures.timed(slow) >= 200


def test_vectors_in_rounds_equal_the_whole_table(spark):
    rnd = np.random.default_rng(9)
    x = rnd.random((80, 3))
    v = spark.createDataFrame([(i, a.tolist()) for i, a in enumerate(x)], "id long, v array<double>")
    q = spark.createDataFrame([(1, 3), (2, 50)], "qid int, q_id long")
    one = lambda d: {(r.qid, r.id) for r in d.where("member").collect()}
    rounds = rknn.conic_metric(v, q, 4, numbers=0)
    assert rounds.count() == 2 * 79 and one(rounds) == one(rknn.conic_metric(v, q, 4))
