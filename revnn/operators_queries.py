"""Scans, windows, set operations and SQL functions around the engine, as registered queries."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from revnn.functions import sql as sqlfunctions
from revnn.operators import baselines, candidates, rknn
from revnn.plans.cuts import cut
from revnn.queries import D2, N, OTHER, SQL_C, SQL_R, query, setting, sql_base, sql_definition, sql_points
from revnn.sources import points as S
from revnn.sources import simulated

for _spec in S.SPECS:
    if not S.SPECS[_spec].distinct:
        query(f"op_points_{_spec}", f"with p as ({sql_points(_spec)}) select id, round(x, 9) as x, round(y, 9) as y from p where x is not null and y is not null")(
            lambda s, sf, x=_spec: S.load(s, sf, x).select("id", F.round("x", 9).alias("x"), F.round("y", 9).alias("y"))
        )


@query("op_points_distinct_lineitem", f"select count(*) as locations, round(sum(x), 4) as sx, round(sum(y), 4) as sy from (select distinct x, y from ({sql_points('lineitem_qty_price')}))")
def distinct_lineitem(s, sf):
    return S.load(s, sf, "lineitem_qty_price").agg(F.count(F.lit(1)).alias("locations"), F.round(F.sum("x"), 4).alias("sx"), F.round(F.sum("y"), 4).alias("sy"))


@query("op_sample_queries", f"with {sql_base('orders_uniform', 10)} select qid, q_id, k from q")
def sample(s, sf):
    return setting(s, sf, "orders_uniform", 10)[1].select("qid", "q_id", "k")


@query("op_window_profile", f"""with {sql_base('customer_uniform', 10)}, {SQL_C}, o as (select qid, id, d2 from c)
select qid, id, rank() over w as rank, dense_rank() over w as dense, ntile(4) over v as quarter, round(percent_rank() over w, 9) as part, round(cume_dist() over w, 9) as cume, round(sqrt(d2) - sqrt(lag(d2) over v), 9) as gap, round(sqrt(nth_value(d2, 10) over (partition by qid order by d2, id rows between unbounded preceding and unbounded following)), 9) as tenth
from o window w as (partition by qid order by d2), v as (partition by qid order by d2, id)""")
def profile(s, sf):
    p, q = setting(s, sf, "customer_uniform", 10)
    w, v = Window.partitionBy("qid").orderBy("d2"), Window.partitionBy("qid").orderBy("d2", "id")
    whole = v.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return candidates.six_sector(p, q).select(
        "qid", "id", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"), F.ntile(4).over(v).alias("quarter"), F.round(F.percent_rank().over(w), 9).alias("part"),
        F.round(F.cume_dist().over(w), 9).alias("cume"), F.round(F.sqrt("d2") - F.sqrt(F.lag("d2").over(v)), 9).alias("gap"), F.round(F.sqrt(F.nth_value("d2", 10).over(whole)), 9).alias("tenth"),
    )


@query("op_rollup_sectors", f"with {sql_base('customer_uniform', 10)}, {SQL_C} select qid, sector, grouping(qid) * 2 + grouping(sector) as level, count(*) as n from c group by rollup (qid, sector)")
def rollup(s, sf):
    c = candidates.six_sector(*setting(s, sf, "customer_uniform", 10))
    return c.rollup("qid", "sector").agg(F.grouping_id().cast("int").alias("level"), F.count(F.lit(1)).alias("n")).select("qid", "sector", "level", "n")


@query("op_cube_sectors", f"with {sql_base('customer_uniform', 10)}, {SQL_C} select sector, rank_in_sector <= 3 as near, count(*) as n from c group by cube (sector, rank_in_sector <= 3)")
def cube(s, sf):
    c = candidates.six_sector(*setting(s, sf, "customer_uniform", 10)).withColumn("near", F.col("rank_in_sector") <= 3)
    return c.cube("sector", "near").agg(F.count(F.lit(1)).alias("n"))


SQL_BOTH = f"with {sql_base('customer_uniform', 10)}, {SQL_R.format(k=10)}, t as (select q.qid, r.id from q join r p on {OTHER} join r on r.id = p.id where {D2} <= r.r2), d as (select q.qid, p.id, rank() over (partition by q.qid order by {D2}) as n from q join p on {OTHER}), f as (select qid, id from d where n <= 10)"


def both(s, sf):
    p, q = setting(s, sf, "customer_uniform", 10)
    p, q = cut(p), cut(q)
    return cut(rknn.conic(p, q)), cut(baselines.knn_as_rknn(p, q))


query("op_intersect", f"{SQL_BOTH} select * from t intersect select * from f")(lambda s, sf: (lambda a, b: a.intersect(b))(*both(s, sf)))
query("op_except", f"{SQL_BOTH} select * from t except select * from f")(lambda s, sf: (lambda a, b: a.subtract(b))(*both(s, sf)))
query("op_union", f"{SQL_BOTH} select * from t union select * from f")(lambda s, sf: (lambda a, b: a.union(b).distinct())(*both(s, sf)))
query("op_answer_arrays", f"with m as ({sql_definition('customer_uniform', 10)}) select qid, string_agg(id::varchar, ',' order by id) as ids from m group by qid")(
    lambda s, sf: rknn.conic(*setting(s, sf, "customer_uniform", 10)).groupBy("qid").agg(F.array_join(F.array_sort(F.collect_list("id")), ",").alias("ids"))
)


@query("op_attribute_filter", f"""with p as materialized (select * from ({sql_points('events_time_value')}) where id in (select event_id from events where event_type = 'click')),
q as materialized (select row_number() over (order by md5(concat(id, ':7')), id) as qid, x as qx, y as qy, id as q_id, 5 as k from (select * from p order by md5(concat(id, ':7')), id limit {N})), {SQL_C},
n as (select c.qid, c.id, sum(case when p.id <> c.id and (p.x - c.x) * (p.x - c.x) + (p.y - c.y) * (p.y - c.y) < c.d2 then 1 else 0 end) as closer from c cross join p group by c.qid, c.id) select qid, id from n where closer < 5""")
def filtered(s, sf):
    """The filter reaches the scan; it changes the set, hence the answer."""
    p = S.points(S.table(s, sf, "events").where("event_type = 'click'"), S.SPECS["events_time_value"])
    return rknn.conic(p, S.sample_queries(p, N, 5))


@query("op_sql_functions", f"with {sql_base('supplier_uniform', 5)} select q.qid, p.id, round(sqrt({D2}), 9) as dist, sqrt({D2}) <= 0.25 as semi, cast(floor(p.x / 0.125) as bigint) as cx from q join p on {OTHER}")
def functions(s, sf):
    sqlfunctions.register(s)
    p, q = setting(s, sf, "supplier_uniform", 5)
    return q.join(p, F.expr("q_id is null or id <> q_id")).selectExpr("qid", "id", "round(revnn_dist(x, y, qx, qy), 9) AS dist", "revnn_semi(revnn_dist(x, y, qx, qy), 0.5D) AS semi", "revnn_cell(x, y, 0.125D).cx AS cx")


@query("op_interval_join", "select a.event_id as id, count(b.event_id) as n from events a left join events b on b.event_id <> a.event_id and a.user_id = b.user_id and b.ts between a.ts - interval 1 hour and a.ts group by a.event_id")
def interval(s, sf):
    """Events of the same user in the hour before each: an equi-join on user with the time range as residual."""
    e = S.table(s, sf, "events").select("event_id", "user_id", "ts")
    b = e.select(F.col("event_id").alias("other"), "user_id", F.col("ts").alias("was"))
    hit = e.join(b, "user_id").where("other <> event_id AND was BETWEEN ts - INTERVAL 1 HOUR AND ts").groupBy("event_id").agg(F.count(F.lit(1)).alias("n"))
    return e.join(hit, "event_id", "left").select(F.col("event_id").alias("id"), F.coalesce("n", F.lit(0)).alias("n"))


@query("op_as_of", "with v as (select (epoch_us(date_trunc('day', ts)) - epoch_us(timestamp '2024-01-01')) // 86400000000 as version, min(ts) as since from events where event_type = 'click' group by 1) select event_id as id, max(version)::bigint as version from events left join v on since <= ts group by event_id")
def as_of(s, sf):
    """The newest index version (a day's first click) at each event's time: union, running last value, no range join."""
    e = S.table(s, sf, "events")
    day = F.expr("CAST(floor(timestampdiff(MICROSECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts) / 86400000000) AS BIGINT)")
    v = e.where("event_type = 'click'").groupBy(day.alias("version")).agg(F.min("ts").alias("ts"))
    rows = e.select("ts", F.col("event_id").alias("id"), F.lit(None).cast("bigint").alias("version"), day.alias("day")).unionByName(v.select("ts", F.lit(None).cast("bigint").alias("id"), "version", F.col("version").alias("day")))
    # within a day a running maximum; a day that begins before its version takes the newest of the days before
    w = Window.partitionBy("day").orderBy("ts", F.col("id").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    d = rows.withColumn("v", F.max("version").over(w)).where("id IS NOT NULL")
    # a row for each day: one window over them all is small
    days = rows.groupBy("day").agg(F.max("version").alias("version"))
    last = days.select("day", F.max("version").over(Window.orderBy("day").rowsBetween(Window.unboundedPreceding, -1)).alias("old"))
    return d.join(last, "day", "left").select("id", F.coalesce("v", "old").alias("version"))


@query("op_grouping_sets", f"with {sql_base('customer_uniform', 10)}, {SQL_C} select qid, sector, count(*) as n, round(max(sqrt(d2)), 9) as far from c group by grouping sets ((qid), (sector), ())")
def grouping_sets(s, sf):
    candidates.six_sector(*setting(s, sf, "customer_uniform", 10)).createOrReplaceTempView("revnn_candidates")
    return s.sql("SELECT qid, sector, count(*) AS n, round(max(sqrt(d2)), 9) AS far FROM revnn_candidates GROUP BY GROUPING SETS ((qid), (sector), ())")


@query("op_pivot_sectors", f"with {sql_base('customer_uniform', 10)}, {SQL_C} select qid, " + ", ".join(f"sum((sector = {i})::int)::bigint as s{i}" for i in range(6)) + " from c group by qid")
def pivot(s, sf):
    c = candidates.six_sector(*setting(s, sf, "customer_uniform", 10)).groupBy("qid").pivot("sector", list(range(6))).count()
    return c.select("qid", *(F.coalesce(F.col(f"`{i}`"), F.lit(0)).alias(f"s{i}") for i in range(6)))


@query("op_band_counts", f"with {sql_base('customer_uniform', 10)}, {SQL_C}, d as (select qid, id, sqrt(d2) as d from c) select qid, id, count(*) over (partition by qid order by d range between 0.01 preceding and 0.01 following) as band from d")
def band_counts(s, sf):
    """Candidates at nearly the same distance: a range frame on the distance."""
    frame = "PARTITION BY qid ORDER BY d RANGE BETWEEN 0.01D PRECEDING AND 0.01D FOLLOWING"
    return candidates.six_sector(*setting(s, sf, "customer_uniform", 10)).select("qid", "id", F.sqrt("d2").alias("d")).selectExpr("qid", "id", f"count(1) OVER ({frame}) AS band")


@query("op_sketch_merge", f"with {sql_base('customer_uniform', 10)}, {SQL_C} select count(distinct id) as exact, true as close from c")
def sketch_merge(s, sf):
    """Distinct candidates over all queries from mergeable sketches, a sketch for each query; within 5 % of the count."""
    c = cut(candidates.six_sector(*setting(s, sf, "customer_uniform", 10)).select("qid", "id"))
    merged = c.groupBy("qid").agg(F.hll_sketch_agg("id", 12).alias("sketch")).agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("n"))
    exact = c.agg(F.count_distinct("id").alias("exact"))
    return exact.crossJoin(merged).select("exact", (F.abs(F.col("n") - F.col("exact")) <= 0.05 * F.col("exact") + 1).alias("close"))


@query("op_candidate_trend", f"with {sql_base('customer_uniform', 10)}, {SQL_C} select sector, round(corr(rank_in_sector, d2), 6) as corr, round(regr_slope(d2, rank_in_sector), 9) as slope, count(distinct id) as ids from c group by sector")
def trend(s, sf):
    """Squared distance grows about linearly with the rank in a sector."""
    c = candidates.six_sector(*setting(s, sf, "customer_uniform", 10))
    return c.groupBy("sector").agg(F.round(F.corr("rank_in_sector", "d2"), 6).alias("corr"), F.round(F.regr_slope("d2", "rank_in_sector"), 9).alias("slope"), F.count_distinct("id").alias("ids"))


@query("op_decision_trace", f"with m as ({sql_definition('customer_uniform', 10)}) select qid, count(*) as members from m group by qid")
def decision_trace(s, sf):
    """A query's decisions as a map id -> rule; members read back from the map and a set of accepted ids."""
    d = rknn.conic_decisions(*setting(s, sf, "customer_uniform", 10))
    t = d.groupBy("qid").agg(F.map_from_entries(F.collect_list(F.struct("id", "decision"))).alias("trace"), F.collect_set(F.when(F.col("member"), F.col("id"))).alias("yes"))
    return t.select("qid", F.size(F.map_filter("trace", lambda i, _: F.array_contains("yes", i))).cast("long").alias("members"))


@query("op_json_filter", f"with {sql_base('customer_uniform', 10)}, d as (select q.qid, p.id, rank() over (partition by q.qid order by {D2}) as n from q join p on {OTHER}) select qid, id from d where n <= 3")
def json_filter(s, sf):
    """Query points from JSON text; the filter on k is read from its path."""
    p, q = setting(s, sf, "customer_uniform", 3)
    text = q.select(F.to_json(F.struct("qid", "qx", "qy", "q_id", F.struct("k").alias("ask"))).alias("j")).where(F.get_json_object("j", "$.ask.k") == "3")
    back = text.select(F.from_json("j", "qid INT, qx DOUBLE, qy DOUBLE, q_id BIGINT, ask STRUCT<k: INT>").alias("v")).select("v.qid", "v.qx", "v.qy", "v.q_id", "v.ask.k")
    return baselines.knn_as_rknn(p, back)


@query("op_arcs_and_keys_sql", f"with {sql_base('supplier_uniform', 5)} select q.qid, p.id, round(sqrt({D2}) / (2 * cos(0.5)), 9) as upper, round(sqrt({D2}) / (2 * cos(0.25)), 9) as lower, (select sum(((cast(floor(p.x * 16) as bigint) >> i) & 1) << (2 * i))::bigint + sum(((cast(floor(p.y * 16) as bigint) >> i) & 1) << (2 * i + 1))::bigint from range(4) t(i)) as z from q join p on {OTHER}")
def arcs_sql(s, sf):
    sqlfunctions.register(s)
    p, q = setting(s, sf, "supplier_uniform", 5)
    return q.join(p, F.expr("q_id is null or id <> q_id")).selectExpr(
        "qid", "id", "round(revnn_upper_arc(revnn_dist(x, y, qx, qy), 0.5D), 9) AS upper", "round(revnn_lower_arc(revnn_dist(x, y, qx, qy), 0.25D), 9) AS lower",
        "revnn_zkey(revnn_cell(x, y, 0.0625D).cx, revnn_cell(x, y, 0.0625D).cy) AS z",
    )


@query("op_table_functions", sql_definition("supplier_uniform", 5))
def table_functions(s, sf):
    """Members by the SQL table function over bundles, a group for each query."""
    sqlfunctions.register(s)
    p, q = setting(s, sf, "supplier_uniform", 5)
    q.join(p).createOrReplaceTempView("revnn_bundles")
    return s.sql("SELECT qid, id FROM revnn_rknn(TABLE(revnn_bundles) PARTITION BY qid) WHERE member")


@query("op_ring_area_and_kth", f"with {sql_base('supplier_uniform', 5)}, d as (select q.qid, sqrt({D2}) as d, row_number() over (partition by q.qid order by {D2}) as n from q join p on {OTHER}) select qid, round(max(d), 9) as kth, 0.5::double as area from d where n <= 5 group by qid")
def aggregates_sql(s, sf):
    sqlfunctions.register(s)
    p, q = setting(s, sf, "supplier_uniform", 5)
    d = q.join(p, F.expr("q_id is null or id <> q_id")).selectExpr("qid", "k", "revnn_dist(x, y, qx, qy) AS d")
    triangle = "array(named_struct('x', 0D, 'y', 0D), named_struct('x', 1D, 'y', 0D), named_struct('x', 0D, 'y', 1D))"
    return d.groupBy("qid").agg(F.expr("revnn_kth(d, k)").alias("kth")).selectExpr("qid", "round(kth, 9) AS kth", f"revnn_ring_area({triangle}) AS area")


@query("op_data_source", "select count(*) as n, 0::bigint as apart from orders")
def data_source(s, sf):
    """The data source gives the points that the digests of a table's keys are: those of all orders, compared bit by bit."""
    simulated.register(s)
    p = S.load(s, sf, "orders_uniform")
    n = (p.agg(F.max("id")).first()[0] or 0) + 1
    a = s.read.format("revnn_uniform").option("n", n).option("partitions", 8 + n // simulated.BATCH).load()
    return p.agg(F.count(F.lit(1)).alias("n")).crossJoin(p.exceptAll(a).agg(F.count(F.lit(1)).alias("apart")))
