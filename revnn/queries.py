"""Registered queries of the engine and, where SQL can say it, the same in SQL over the given tables.

Every query reads its whole tables; 30 drawn query points for each setting are the experiments' own design."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from revnn.functions import geometry as G
from revnn.functions import theory
from revnn.operators import baselines, candidates, graph, knn, measures, rknn, verify, voronoi
from revnn.plans.cuts import cut
from revnn.sources import points as S

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}
N = 30


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return put


def setting(spark, sf, spec: str, k: int, free: bool = False):
    p = S.load(spark, sf, spec)
    return p, S.free_queries(spark, N, k) if free else S.sample_queries(p, N, k)


# --- SQL pieces


def sql_points(spec: str) -> str:
    s = S.SPECS[spec]
    return f"select cast({s.id} as bigint) as id, {s.duck_x} as x, {s.duck_y} as y from {s.table}"


def sql_base(spec: str, k: int, free: bool = False) -> str:
    """p(id, x, y), q(qid, qx, qy, q_id, k)."""
    key = "md5(concat(i, ':7'))"
    if free:
        unit = lambda at: f"('0x' || substr({key}, {at}, 8))::bigint / 4294967296.0::double"
        q = f"select i + 1 as qid, {unit(1)} as qx, {unit(9)} as qy, null::bigint as q_id, {k} as k from range({N}) t(i)"
    else:
        q = f"select row_number() over (order by md5(concat(id, ':7')), id) as qid, x as qx, y as qy, id as q_id, {k} as k from (select * from p order by md5(concat(id, ':7')), id limit {N})"
    return f"p as materialized ({sql_points(spec)}), q as materialized ({q})"


D2 = "(p.x - q.qx) * (p.x - q.qx) + (p.y - q.qy) * (p.y - q.qy)"
OTHER = "(q.q_id is null or p.id <> q.q_id)"
#: m(qid, id, d2, member): by the radius form of the definition; r(id, r2, n): radii of all points.
SQL_R = """s as (select a.id, (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) as d2 from p a join p b on a.id <> b.id),
s2 as (select id, d2, row_number() over (partition by id order by d2) as n from s),
r as materialized (select p.id, p.x, p.y, max(d2) as r2, count(d2) as n from p left join (select * from s2 where n <= {k}) s2 using (id) group by p.id, p.x, p.y)"""
SQL_SECTOR = """case when dx = 0 and dy = 0 then -1
 when dy > 0 or (dy = 0 and dx > 0) then case when dx > 0 and dy - 1.7320508075688772::double * dx < 0 then 0 when dy > 0 and dy + 1.7320508075688772::double * dx > 0 then 1 else 2 end
 when dy = 0 and dx < 0 then 3
 else case when dx < 0 and dy - 1.7320508075688772::double * dx > 0 then 3 when dy + 1.7320508075688772::double * dx < 0 then 4 else 5 end end"""
SQL_C = f"""c0 as (select q.qid, q.k, p.id, p.x, p.y, {D2} as d2, p.x - q.qx as dx, p.y - q.qy as dy from q join p on {OTHER}),
c1 as (select *, {SQL_SECTOR} as sector from c0),
c2 as (select *, row_number() over (partition by qid, sector order by d2, id) as rank_in_sector from c1),
c as materialized (select * from c2 where rank_in_sector <= k or sector = -1)"""


def sql_definition(spec: str, k: int, free: bool = False) -> str:
    return f"with {sql_base(spec, k, free)}, {SQL_R.format(k=k)} select q.qid, r.id from q join r p on {OTHER} join r on r.id = p.id where r.n < {k} or {D2} <= r.r2"


def sql_by_candidates(spec: str, k: int) -> str:
    """For large sets: what six sectors leave, and fewer than k strictly closer points."""
    return f"""with {sql_base(spec, k)}, {SQL_C},
n as (select c.qid, c.id, sum(case when p.id <> c.id and (p.x - c.x) * (p.x - c.x) + (p.y - c.y) * (p.y - c.y) < c.d2 then 1 else 0 end) as closer from c cross join p group by c.qid, c.id)
select qid, id from n where closer < {k}"""


def sql_knn(spec: str, k: int) -> str:
    return f"with {sql_base(spec, k)}, d as (select q.qid, p.id, {D2} as d2 from q join p on {OTHER}), w as (select *, rank() over (partition by qid order by d2) as rank from d) select qid, id, rank from w where rank <= {k}"


# --- definitions

query("d01_dist", f"with {sql_base('supplier_uniform', 10)} select q.qid, p.id, round(sqrt({D2}), 9) as dist from q join p on {OTHER}")(
    lambda s, sf: (lambda p, q: q.join(p, F.expr(knn.OTHER)).select("qid", "id", F.round(G.dist("x", "y", "qx", "qy"), 9).alias("dist")))(*setting(s, sf, "supplier_uniform", 10))
)


def vectors(spark, sf) -> DataFrame:
    return S.table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v"))


def drawn_vectors(spark, sf, n: int = N) -> DataFrame:
    v = vectors(spark, sf)
    d = v.withColumn("draw", F.md5(F.concat(F.col("id").cast("string"), F.lit(":7")))).orderBy("draw", "id").limit(n)
    return d.select(F.row_number().over(Window.orderBy("draw", "id")).alias("qid"), F.col("id").alias("q_id"), F.col("v").alias("qv"))


SQL_V = f"v as materialized (select vec_id as id, list_transform(embedding, lambda x: x::double) as v from embeddings), qv as materialized (select row_number() over (order by md5(concat(id, ':7')), id) as qid, id as q_id, v as qv from (select * from v order by md5(concat(id, ':7')), id limit {N}))"


@query("d02_dist_v", f"with {SQL_V} select qid, id, round(list_distance(v, qv), 6) as dist from qv join v on id <> q_id")
def d02(s, sf):
    return drawn_vectors(s, sf).join(vectors(s, sf), F.expr("id <> q_id")).select("qid", "id", F.round(G.dist_v("v", "qv"), 6).alias("dist"))


for _spec in ("customer_uniform", "part_size_price"):
    query(f"d03_knn_{_spec.split('_')[0]}", sql_knn(_spec, 10))(lambda s, sf, x=_spec: knn.knn_exact(*setting(s, sf, x, 10)).select("qid", "id", "rank"))
    query(f"m18_knn_grid_{_spec.split('_')[0]}", sql_knn(_spec, 10))(lambda s, sf, x=_spec: knn.knn_grid(*setting(s, sf, x, 10)).select("qid", "id", "rank"))
for _spec in ("orders_uniform", "events_time_value"):
    query(f"m18_knn_grid_{_spec.split('_')[0]}", sql_knn(_spec, 100))(lambda s, sf, x=_spec: knn.knn_grid(*setting(s, sf, x, 100)).select("qid", "id", "rank"))


@query("d04_knn_radius", f"with p as ({sql_points('customer_uniform')}), {SQL_R.format(k=10)} select id, round(sqrt(r2), 9) as r from r")
def d04(s, sf):
    return knn.knn_radius(S.load(s, sf, "customer_uniform"), None, 10).select("id", F.round("r", 9).alias("r"))


for _name, _spec, _k, _free in (("customer", "customer_uniform", 10, False), ("part_ties", "part_size_price", 5, False), ("supplier_free", "supplier_uniform", 5, True)):
    query(f"d05_rknn_{_name}", sql_definition(_spec, _k, _free))(lambda s, sf, a=(_spec, _k, _free): rknn.rknn_definition(*setting(s, sf, *a)))


@query("d06_membership", f"with {sql_base('customer_uniform', 10)}, {SQL_C}, {SQL_R.format(k=10)} select c.qid, c.id, (r.n < 10 or c.d2 <= r.r2) as member from c join r using (id)")
def d06(s, sf):
    p, q = setting(s, sf, "customer_uniform", 10)
    return verify.by_knn(candidates.six_sector(p, q), p, q).select("qid", "id", "member")


@query("d07_knn_region", f"with {sql_base('customer_uniform', 10)}, d as (select q.qid, p.id, {D2} as d2 from q join p on {OTHER}), w as (select *, row_number() over (partition by qid order by d2) as n from d), r as (select qid, max(d2) as r2 from w where n <= 10 group by qid) select qid, count(*) as inside from d join r using (qid) where d2 <= r2 group by qid")
def d07(s, sf):
    from revnn.functions.regions import in_knn_region

    p, q = setting(s, sf, "customer_uniform", 10)
    c = cut(candidates.six_sector(p, q))
    return c.join(verify.query_radius(c, q), "qid").where(in_knn_region(F.sqrt("d2"), "r_q")).groupBy("qid").agg(F.count(F.lit(1)).alias("inside"))


@query("d08_voronoi_cells")
def d08(s, sf):
    area = F.aggregate(F.sequence(F.lit(1), F.size("ring")), F.lit(0.0), lambda a, i: a + F.element_at("ring", i)["x"] * F.element_at("ring", i % F.size("ring") + 1)["y"] - F.element_at("ring", i % F.size("ring") + 1)["x"] * F.element_at("ring", i)["y"])
    return voronoi.cells(S.load(s, sf, "customer_uniform")).select("id", F.size("ring").alias("corners"), F.size("nbrs").alias("degree"), (F.abs(area) / 2).alias("area"), "certified")


@query("d09_cells_tile_the_box", f"with p as ({sql_points('customer_uniform')}) select round((max(x) - min(x)) * (max(y) - min(y)), 9) as area, count(*) as cells from p")
def d09(s, sf):
    return d08(s, sf).agg(F.round(F.sum("area"), 9).alias("area"), F.count(F.lit(1)).alias("cells"))


SQL_EDGES = f"""p as materialized ({sql_points('supplier_uniform')}), b as (select min(x) as x0, max(x) as x1, min(y) as y0, max(y) as y1 from p),
pr as (select a.id as src, c.id as dst, a.x as ax, a.y as ay, (a.x + c.x) / 2 as mx, (a.y + c.y) / 2 as my, a.y - c.y as ux, c.x - a.x as uy from p a join p c on a.id < c.id),
t as (select src, dst, ux * (p.x - ax) + uy * (p.y - ay) as slope, (p.x * p.x + p.y * p.y - ax * ax - ay * ay) / 2 - (mx * (p.x - ax) + my * (p.y - ay)) as room from pr join p on p.id <> src and p.id <> dst
 union all select src, dst, ux, x1 - mx from pr, b union all select src, dst, -ux, mx - x0 from pr, b union all select src, dst, uy, y1 - my from pr, b union all select src, dst, -uy, my - y0 from pr, b),
g as (select src, dst, min(case when slope > 0 then room / slope end) as hi, max(case when slope < 0 then room / slope end) as lo, min(case when slope = 0 then room end) as flat from t group by src, dst),
e as materialized (select src, dst from g where lo < hi and coalesce(flat, 1) >= 0)"""

query("d10_voronoi_neighbors", f"with {SQL_EDGES} select src, dst from e union all select dst, src from e")(lambda s, sf: voronoi.neighbors(S.load(s, sf, "supplier_uniform")))
query("d11_delaunay", f"with {SQL_EDGES} select src, dst, round(sqrt((a.x - c.x) * (a.x - c.x) + (a.y - c.y) * (a.y - c.y)), 9) as len from e join p a on a.id = src join p c on c.id = dst")(
    lambda s, sf: voronoi.delaunay_edges(S.load(s, sf, "supplier_uniform")).withColumn("len", F.round("len", 9))
)
query("m20_interval_form", f"with {SQL_EDGES} select src, dst from e")(lambda s, sf: voronoi.neighbors_by_intervals(S.load(s, sf, "supplier_uniform")))
query("d12_nn_graph", f"with p as ({sql_points('customer_uniform')}), d as (select a.id as i, b.id as j, rank() over (partition by a.id order by (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) as n from p a join p b on a.id <> b.id) select distinct least(i, j) as src, greatest(i, j) as dst from d where n = 1")(
    lambda s, sf: knn.nn_graph(S.load(s, sf, "customer_uniform"))
)


@query("d12_nn_graph_in_delaunay", "select 0::bigint as violations")
def d12(s, sf):
    p = cut(S.load(s, sf, "customer_uniform"))
    return knn.nn_graph(p).join(voronoi.delaunay_edges(p), ["src", "dst"], "left_anti").agg(F.count(F.lit(1)).alias("violations"))


@query("d13_hops", f"with recursive {SQL_EDGES}, u as (select src, dst from e union all select dst, src from e), h as (select 0::bigint as id, 0 as hops union select u.dst, h.hops + 1 from h join u on u.src = h.id where h.hops < 12) select 0::bigint as src, id, min(hops) as hops from h group by id")
def d13(s, sf):
    return graph.hops(voronoi.delaunay_edges(S.load(s, sf, "supplier_uniform")), s.range(1).select(F.col("id").alias("src")))


#: decides(qid, witness_id, id, kind): all candidates as witnesses.
SQL_DECIDES = f"""with {sql_base('supplier_uniform', 5)}, {SQL_C}, {SQL_R.format(k=5)},
w as (select c.qid, c.id as witness_id, c.x as wx, c.y as wy, sqrt(c.d2) as wd, case when r.n < 5 then 'infinity'::double else sqrt(r.r2) end as wr from c join r using (id)),
j as (select c.qid, w.witness_id, c.id, sqrt(c.d2) as d, sqrt((c.x - wx) * (c.x - wx) + (c.y - wy) * (c.y - wy)) as dw, wd, wr from c join w using (qid) where c.id <> w.witness_id),
k as (select qid, witness_id, id, case when wd <= wr and d + dw <= wr * (1 - 1e-12::double) then 'positive' when wd > wr and d - dw > wr * (1 + 1e-12::double) then 'negative' end as kind from j)"""


def decided(s, sf, kinds=("positive", "negative")):
    p, q = setting(s, sf, "supplier_uniform", 5)
    c = cut(candidates.six_sector(p, q))
    return verify.decides(c, cut(verify.as_witnesses(c, p, q)), kinds)


query("d18_decides", f"{SQL_DECIDES} select qid, witness_id, id, kind from k where kind is not null")(decided)
query("m02_positive", f"{SQL_DECIDES} select qid, witness_id, id, kind from k where kind = 'positive'")(lambda s, sf: decided(s, sf, ("positive",)))
query("m03_negative", f"{SQL_DECIDES} select qid, witness_id, id, kind from k where kind = 'negative'")(lambda s, sf: decided(s, sf, ("negative",)))
SQL_RQ = "o as (select qid, d2, row_number() over (partition by qid order by d2, id) as n from c), rq as (select qid, sqrt(max(d2)) as r_q from o where n <= {n} group by qid)"
for _slack in (False, True):
    query(f"m04_semi{'_slack' * _slack}", f"with {sql_base('customer_uniform', 10)}, {SQL_C}, {SQL_RQ.format(n=10 + _slack)} select qid, id, sqrt(d2) <= r_q / 2 as settled from c join rq using (qid)")(
        lambda s, sf, slack=_slack: (lambda p, q: verify.by_semi(cut(candidates.six_sector(p, q)), q, slack))(*setting(s, sf, "customer_uniform", 10))
    )


@query("d14_conic_sides", f"with {sql_base('supplier_uniform', 5)}, a as (select qid, id, sqrt({D2}) as d, sqrt(p.x * p.x + p.y * p.y) as e from q join p on {OTHER}) select qid, id, sign(d + e - 1)::int as ellipse, sign(d - e - 0.25)::int as hyperbola from a")
def d14(s, sf):
    p, q = setting(s, sf, "supplier_uniform", 5)
    args = ("x", "y", "qx", "qy", F.lit(0.0), F.lit(0.0))
    return q.join(p, F.expr(knn.OTHER)).select("qid", "id", G.ellipse_side(*args, F.lit(1.0)).alias("ellipse"), G.hyperbola_side(*args, F.lit(0.25)).alias("hyperbola"))


@query("d19_witness_sets_are_valid", f"select i + 1 as qid, true as valid, 0::bigint as n_undecided from range({N}) t(i)")
def d19(s, sf):
    p, q = setting(s, sf, "customer_uniform", 10)
    c = cut(candidates.six_sector(p, q))
    d = cut(rknn.conic_decisions(p, q, candidates=c))
    w = d.where("decision = 'knn'").join(c, ["qid", "id"]).select("qid", F.col("id").alias("witness_id"), F.col("x").alias("wx"), F.col("y").alias("wy"), F.sqrt("d2").alias("wd"), F.col("r").alias("wr"))
    open_ = c.join(d.where("decision = 'semi'").select("qid", "id"), ["qid", "id"], "left_anti")
    return q.select("qid").join(verify.is_witness_set(open_, w), "qid", "left").select("qid", F.coalesce("valid", F.lit(True)).alias("valid"), F.coalesce("n_undecided", F.lit(0)).alias("n_undecided"))


@query("d20_influence_zone", f"with {sql_base('supplier_uniform', 5)}, g as (select (i % 16 + 0.5) / 16 as gx, (i // 16 + 0.5) / 16 as gy from range(256) t(i)), n as (select q.qid, gx, gy, sum(case when {OTHER} and (p.x - gx) * (p.x - gx) + (p.y - gy) * (p.y - gy) < (q.qx - gx) * (q.qx - gx) + (q.qy - gy) * (q.qy - gy) then 1 else 0 end) as closer from q cross join g cross join p group by q.qid, gx, gy) select qid, count(*) filter (closer < 5) / 256.0::double as share from n group by qid")
def d20(s, sf):
    p, q = setting(s, sf, "supplier_uniform", 5)
    g = s.range(256).select(((F.col("id") % 16 + 0.5) / 16).alias("gx"), ((F.floor(F.col("id") / 16) + 0.5) / 16).alias("gy"))
    closer = F.sum((F.expr(knn.OTHER) & (G.dist2("x", "y", "gx", "gy") < G.dist2("qx", "qy", "gx", "gy"))).cast("int"))
    n = q.join(g).join(p).groupBy("qid", "gx", "gy").agg(closer.alias("closer"))
    return n.groupBy("qid").agg((F.sum((F.col("closer") < 5).cast("int")) / F.lit(256.0)).alias("share"))


@query("d21_region_coverage", f"{SQL_DECIDES}, f as (select qid, id, max((kind = 'positive')::int) as p, max((kind = 'negative')::int) as n from k where kind is not null group by qid, id) select c.qid, count(*) as n_candidates, round(sum(coalesce(p, 0)) / count(*), 9) as positive, round(sum(coalesce(n, 0)) / count(*), 9) as negative, round(count(f.id) / count(*), 9) as either from c left join f using (qid, id) group by c.qid")
def d21(s, sf):
    p, q = setting(s, sf, "supplier_uniform", 5)
    c = cut(candidates.six_sector(p, q))
    d = measures.region_coverage(c, cut(verify.as_witnesses(c, p, q)))
    return d.select("qid", "n_candidates", *(F.round(x, 9).alias(x) for x in ("positive", "negative", "either")))


@query("d22_knn_chain", "select 0::bigint as violations")
def d22(s, sf):
    """The k-th neighbour touches the query or an earlier neighbour."""
    p, q = setting(s, sf, "customer_uniform", 10)
    e = cut(voronoi.neighbors(p))
    n = cut(knn.knn_grid(p, q).join(q.select("qid", "q_id"), "qid"))
    before = n.select("qid", F.col("id").alias("src"), F.col("rank").alias("was")).unionByName(q.select("qid", F.col("q_id").alias("src"), F.lit(0).alias("was")))
    linked = n.join(before, "qid").where("was < rank").join(e, (F.col("dst") == F.col("id")) & (e["src"] == before["src"])).select("qid", "id").distinct()
    return n.join(linked, ["qid", "id"], "left_anti").agg(F.count(F.lit(1)).alias("violations"))


@query("d23_degree", "select count(*) as n, true as few_edges, true as mean_below_six from customer")
def d23(s, sf):
    p = S.load(s, sf, "customer_uniform")
    e = voronoi.delaunay_edges(p).agg(F.count(F.lit(1)).alias("e"))
    return p.agg(F.count(F.lit(1)).alias("n")).join(e).select("n", (F.col("e") <= 3 * F.col("n") - 6).alias("few_edges"), (2 * F.col("e") <= 6 * F.col("n") - 12).alias("mean_below_six"))


@query("d24_member_hops", "select 0::bigint as violations")
def d24(s, sf):
    p, q = setting(s, sf, "customer_uniform", 5)
    p = cut(p)
    h = graph.hops(voronoi.delaunay_edges(p), q.select(F.col("q_id").alias("src")), 5)
    m = rknn.conic(p, q).join(q.select("qid", F.col("q_id").alias("src")), "qid")
    return m.join(h, ["src", "id"], "left_anti").agg(F.count(F.lit(1)).alias("violations"))


# --- the engine and its variants

for _name, _spec, _k in (("orders", "orders_uniform", 10), ("events", "events_time_value", 10), ("orders_date_price", "orders_date_price", 5)):
    query(f"m12_conic_{_name}", sql_by_candidates(_spec, _k))(lambda s, sf, a=(_spec, _k): rknn.conic(*setting(s, sf, *a)))
for _k in (1, 2, 100):
    query(f"m13_conic_k{_k}", sql_definition("customer_uniform", _k))(lambda s, sf, k=_k: rknn.conic(*setting(s, sf, "customer_uniform", k)))
query("m14_waves", sql_definition("customer_uniform", 3))(lambda s, sf: rknn.conic(*setting(s, sf, "customer_uniform", 3), plan="wave"))
query("m15_free_queries", sql_definition("customer_uniform", 5, True))(lambda s, sf: rknn.conic(*setting(s, sf, "customer_uniform", 5, True)))
query("m16_ties_and_duplicates", sql_definition("part_size_price", 5))(lambda s, sf: rknn.conic(*setting(s, sf, "part_size_price", 5)))
query("m16_n_below_k", sql_definition("supplier_uniform", 200))(lambda s, sf: rknn.conic(*setting(s, sf, "supplier_uniform", 200)))
query("m01_by_knn", sql_definition("customer_uniform", 10))(lambda s, sf: d06(s, sf).where("member").select("qid", "id"))


def variant(s, sf, **options):
    p, q = setting(s, sf, "customer_uniform", 10)
    if options.get("match") == "graph":
        p = cut(p)
        options["index"] = cut(voronoi.cells(p).select("id", "x", "y", "nbrs"))
    return rknn.conic(p, q, **options)


for _order in ("asc", "desc", "hash", "boundary"):
    query(f"m06_order_{_order}", sql_definition("customer_uniform", 10))(lambda s, sf, o=_order: variant(s, sf, order=o))
query("m09_match_graph", sql_definition("customer_uniform", 10))(lambda s, sf: variant(s, sf, match="graph"))
for _rules in (("semi",), ("positive",), ("negative",), ("positive", "negative"), ()):
    query(f"m09_rules_{'_'.join(_rules) or 'none'}", sql_definition("customer_uniform", 10))(lambda s, sf, r=_rules: variant(s, sf, rules=r))


@query("m06_visit_order", f"with {sql_base('customer_uniform', 10)}, {SQL_C}, {SQL_RQ.format(n=10)}, z as (select qid, id, d2, sqrt(d2) <= r_q as inner_ from c join rq using (qid)) select qid, id, row_number() over (partition by qid order by (not inner_)::int, case when inner_ then -d2 else d2 end, id) - 1 as visit_ord from z")
def m06(s, sf):
    p, q = setting(s, sf, "customer_uniform", 10)
    c = cut(candidates.six_sector(p, q))
    inner = F.sqrt("d2") <= F.col("r_q")
    w = Window.partitionBy("qid").orderBy((~inner).cast("int"), F.when(inner, -F.col("d2")).otherwise(F.col("d2")), "id")
    return c.join(verify.query_radius(c, q), "qid").select("qid", "id", (F.row_number().over(w) - 1).alias("visit_ord"))


@query("m07_boundary_band", sql_definition("customer_uniform", 10))
def m07(s, sf):
    """Only candidates near the kNN circle as witnesses, kNN queries for what these leave open."""
    p, q = setting(s, sf, "customer_uniform", 10)
    return verify.boundary_band(candidates.six_sector(p, q), p, q).where("member").select("qid", "id")


@query("m08_smallest_witness_sets")
def m08(s, sf):
    """Greedy and, for few candidates, exact minimum sizes beside the dynamic choice (k = 2)."""
    import numpy as np
    import pandas as pd

    from revnn.operators import cascade

    p, q = setting(s, sf, "customer_uniform", 2)
    c = cut(candidates.six_sector(p, q))
    w = verify.as_witnesses(c, p, q).select("qid", F.col("witness_id").alias("id"), "wr")

    def sizes(part: pd.DataFrame) -> pd.DataFrame:
        xy, d = part[["x", "y"]].to_numpy(), np.sqrt(part["d2"].to_numpy())
        settles = np.array([cascade.decided_by(d, xy, i, r) for i, r in enumerate(part["wr"])])
        exact = len(cascade.minimum_cover(settles)) if len(d) <= 12 else None
        return pd.DataFrame({"qid": [int(part["qid"].iloc[0])], "n_candidates": [len(d)], "greedy": [len(cascade.greedy_cover(settles))], "exact": pd.array([exact], dtype="Int64")})

    cover = c.join(w, ["qid", "id"]).groupBy("qid").applyInPandas(sizes, "qid int, n_candidates long, greedy long, exact long")
    ours = rknn.conic_decisions(p, q, candidates=c, rules=("positive", "negative")).groupBy("qid").agg(F.sum((F.col("decision") == "knn").cast("int")).alias("dynamic"))
    return cover.join(ours, "qid")


for _name, _spec, _k in (("orders", "orders_uniform", 10), ("events", "events_time_value", 100)):
    query(f"m10_six_sector_{_name}", f"with {sql_base(_spec, _k)}, {SQL_C} select qid, id, sector, rank_in_sector from c")(
        lambda s, sf, a=(_spec, _k): candidates.six_sector(*setting(s, sf, *a)).select("qid", "id", "sector", "rank_in_sector")
    )


@query("m11_delaunay_expansion")
def m11(s, sf):
    """Candidates by graph expansion, with their recall against the direct ones, for both ways of expanding."""
    p, q = setting(s, sf, "customer_uniform", 10)
    index = cut(voronoi.cells(cut(p)).select("id", "x", "y", "nbrs"))
    direct = cut(candidates.six_sector(p, q).select("qid", "id"))
    out = None
    for how in ("accepted", "all"):
        c, n = graph.delaunay_expand(index, q, expand=how, max_hops=-1)
        r = measures.recall(c.select("qid", "id"), direct).join(n, "qid").withColumn("expand", F.lit(how))
        out = r if out is None else out.unionByName(r)
    return out


@query("m11_hop_limit")
def m11_limit(s, sf):
    """Recall of the expansion with a limit of k hops and without one."""
    p, q = setting(s, sf, "customer_uniform", 5)
    index = cut(voronoi.cells(cut(p)).select("id", "x", "y", "nbrs"))
    direct = cut(candidates.six_sector(p, q).select("qid", "id"))
    runs = {"k": -1, "none": None}
    out = [measures.recall(graph.delaunay_expand(index, q, max_hops=h)[0].select("qid", "id"), direct).withColumn("hop_limit", F.lit(name)) for name, h in runs.items()]
    return out[0].unionByName(out[1])


@query("m11_expand_all", f"with {sql_base('supplier_uniform', 5)}, {SQL_C} select qid, id, sector, rank_in_sector from c")
def m11_all(s, sf):
    """Handing on from every point and without a hop limit, the expansion reaches all that six sectors hold."""
    p, q = setting(s, sf, "supplier_uniform", 5)
    index = cut(voronoi.cells(cut(p)).select("id", "x", "y", "nbrs"))
    return graph.delaunay_expand(index, q, max_hops=None, expand="all")[0].select("qid", "id", "sector", "rank_in_sector")


@query("m17_knn_voronoi", sql_knn("customer_uniform", 10))
def m17(s, sf):
    p, q = setting(s, sf, "customer_uniform", 10)
    return graph.knn_voronoi(cut(voronoi.cells(cut(p)).select("id", "x", "y", "nbrs")), q).select("qid", "id", "rank")


for _dims in (2, 4, 64):
    query(
        f"m19_metric_{_dims}d",
        f"with {SQL_V}, s as (select a.id, list_distance(a.v[1:{_dims}], b.v[1:{_dims}]) as d from v a join v b on a.id <> b.id), t as (select *, row_number() over (partition by id order by d) as n from s), r as (select id, max(d) as r from t where n <= 5 group by id) select qid, v.id from qv join v on v.id <> q_id join r on r.id = v.id where list_distance(v.v[1:{_dims}], qv[1:{_dims}]) <= r + 1e-12",
    )(lambda s, sf, d=_dims: rknn.conic_metric(vectors(s, sf), drawn_vectors(s, sf).select("qid", "q_id"), 5, d).where("member").select("qid", "id"))


@query("m20_index_degrees", f"with {SQL_EDGES}, u as (select src as id from e union all select dst from e) select id, count(*) as deg from u group by id")
def m20(s, sf):
    return voronoi.cells(S.load(s, sf, "supplier_uniform")).select("id", F.size("nbrs").cast("long").alias("deg"))


query("m21_insert_query")(lambda s, sf: (lambda p, q: voronoi.insert_query(p, q))(*setting(s, sf, "customer_uniform", 5, True)))


@query("m22_patch_index", f"with {SQL_EDGES} select count(*) as edges, true as same from e")
def m22(s, sf):
    """Taking a point out and putting it back gives the old index again."""
    p = cut(S.load(s, sf, "supplier_uniform"))
    index = cut(voronoi.cells(p).select("id", "x", "y", "nbrs"))
    one = p.where("id = 3")
    less = cut(voronoi.patch(index, one.limit(0), one.select("id")))
    again = cut(voronoi.patch(less.select("id", "x", "y", "nbrs"), one, one.select("id").limit(0)))
    pairs = lambda d: d.select(F.col("id").alias("src"), F.explode("nbrs.id").alias("dst")).where("src < dst")
    return pairs(again).agg(F.count(F.lit(1)).alias("edges")).join(pairs(again).exceptAll(pairs(index)).agg((F.count(F.lit(1)) == 0).alias("same")))


# --- baselines

query("b1_six_sector", sql_definition("customer_uniform", 10))(lambda s, sf: baselines.six_sector(*setting(s, sf, "customer_uniform", 10)))
query("b1_six_sector_orders", sql_by_candidates("orders_uniform", 10))(lambda s, sf: baselines.six_sector(*setting(s, sf, "orders_uniform", 10)))
query("b2_arc_bound", sql_definition("customer_uniform", 10))(lambda s, sf: baselines.arc_bound(*setting(s, sf, "customer_uniform", 10)))
query("b2_arc_bound_12_sectors", sql_definition("customer_uniform", 10))(lambda s, sf: baselines.arc_bound(*setting(s, sf, "customer_uniform", 10), sectors=12))
query("b2_arc_bound_k1", sql_definition("part_size_price", 1))(lambda s, sf: baselines.arc_bound(*setting(s, sf, "part_size_price", 1)))
query("b2_arc_bound_events", sql_by_candidates("events_time_value", 10))(lambda s, sf: baselines.arc_bound(*setting(s, sf, "events_time_value", 10)))
query("b3_brute_force", sql_definition("supplier_uniform", 10))(lambda s, sf: baselines.brute_force(*setting(s, sf, "supplier_uniform", 10)))
query("b4_stored_radii", sql_definition("customer_uniform", 10))(lambda s, sf: (lambda p, q: baselines.lookup(cut(baselines.stored_radii(p, 10)), q))(*setting(s, sf, "customer_uniform", 10)))
query("b6_range_count", sql_definition("customer_uniform", 10))(
    lambda s, sf: (lambda p, q: verify.by_range_count(candidates.six_sector(p, q), p, q).where("member").select("qid", "id"))(*setting(s, sf, "customer_uniform", 10))
)
query("b7_all_points", f"with p as ({sql_points('customer_uniform')}), d as (select a.id as id, b.id as qid, rank() over (partition by a.id order by (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) as n from p a join p b on a.id <> b.id) select qid, id from d where n <= 10")(
    lambda s, sf: rknn.all_points(S.load(s, sf, "customer_uniform"), 10)
)


@query("b5_knn_as_rknn", f"""with {sql_base('customer_uniform', 10)}, {SQL_R.format(k=10)}, t as (select q.qid, r.id from q join r p on {OTHER} join r on r.id = p.id where {D2} <= r.r2),
d as (select q.qid, p.id, rank() over (partition by q.qid order by {D2}) as n from q join p on {OTHER}), f as (select qid, id from d where n <= 10)
select qid, count(t.id) as n_true, count(f.id) as n_found, count(case when t.id is not null and f.id is not null then 1 end) as n_both from t full outer join f using (qid, id) group by qid""")
def b5(s, sf):
    p, q = setting(s, sf, "customer_uniform", 10)
    return measures.recall(baselines.knn_as_rknn(p, q), rknn.conic(p, q)).select("qid", "n_true", "n_found", "n_both")


# --- measures


@query("a05_result_size", f"with m as ({sql_definition('customer_uniform', 10)}) select count(*) / {N}.0::double as mean_size from m")
def a05(s, sf):
    return rknn.conic(*setting(s, sf, "customer_uniform", 10)).agg((F.count(F.lit(1)) / F.lit(float(N))).alias("mean_size"))


@query("a06_theory", "select distinct k, round(4 * sqrt(pi() * k), 6) as verified, round(6 * k + 2 * sqrt(6 * pi() * k), 6) as accessed, round((k * k + k) * pi(), 6) as accessed_max from (select count(*)::int as k from orders group by o_custkey) t")
def a06(s, sf):
    """Expected counts for every k that is some customer's number of orders."""
    k = S.table(s, sf, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).cast("int").alias("k")).select("k").distinct()
    return k.select("k", F.round(theory.verified("k"), 6).alias("verified"), F.round(theory.accessed("k"), 6).alias("accessed"), F.round(theory.accessed_max("k"), 6).alias("accessed_max"))


query("a10_decision_mix")(lambda s, sf: measures.decision_mix(rknn.conic_decisions(*setting(s, sf, "events_time_value", 100))))
query("a11_expansion_recall")(lambda s, sf: m11(s, sf).groupBy("expand").agg(F.avg("recall").alias("recall"), F.avg("n_seen").alias("n_seen"), F.avg("n_expanded").alias("n_expanded")))


@query("a13_boundary", f"""with {sql_base('orders_uniform', 100)}, d as materialized (select q.qid, {D2} as d2, row_number() over (partition by q.qid order by {D2}, p.id) as n from q join p on {OTHER}),
rq as (select qid, sqrt(max(d2)) as r_q from d where n <= 100 group by qid), b as (select sqrt((max(x) - min(x)) * (max(y) - min(y)) / count(*)) as gap from p)
select qid, sum((abs(sqrt(d2) - r_q) <= gap)::int)::bigint as n_boundary, round(pi() * r_q * r_q, 9) as area, round(2 * pi() * r_q, 9) as circumference from d join rq using (qid) cross join b group by qid, r_q""")
def a13(s, sf):
    p, q = setting(s, sf, "orders_uniform", 100)
    return measures.boundary_points(p, q).select("qid", "n_boundary", F.round("area", 9).alias("area"), F.round("circumference", 9).alias("circumference"))


for _spec in ("orders_uniform", "events_time_value"):
    query(
        f"a14_unevenness_{_spec.split('_')[0]}",
        f"with p as ({sql_points(_spec)}), b as (select min(x) as x0, max(x) as x1, min(y) as y0, max(y) as y1 from p), g as (select least(floor((x - x0) / (x1 - x0) * 10), 9) as cx, least(floor((y - y0) / (y1 - y0) * 10), 9) as cy from p, b), n as (select c.i, count(g.cx) as n from range(100) c(i) left join g on g.cx = c.i % 10 and g.cy = c.i // 10 group by c.i) select count(*) as n_cells, avg(n) as mean, round(var_pop(n) / avg(n), 6) as ratio from n",
    )(lambda s, sf, x=_spec: measures.unevenness(S.load(s, sf, x)).withColumn("ratio", F.round("ratio", 6)))
