"""The experiments, re-expressed on the given tables: counts and times for the engine and its two competitors."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from revnn.functions import theory
from revnn.operators import baselines, measures, rknn, voronoi
from revnn.operators.cascade import ORDERS
from revnn.plans.cuts import cut
from revnn.queries import N, drawn_vectors, query, setting, sql_by_candidates, vectors
from revnn.sources import points as S

ALGORITHMS = {"conic": rknn.conic, "six_sector": baselines.six_sector, "arc_bound": baselines.arc_bound}


#: Tables whose keys' digests stand in for simulated points, from few to many rows, and the values of k that the
#: experiments go through; the largest k runs in bench.py.
UNIFORM, KS = ("supplier_uniform", "customer_uniform", "orders_uniform"), (10, 100, 1_000)


def counts(p: DataFrame, ks, indexed: bool = True, n_queries: int = N) -> DataFrame:
    """algorithm, k and mean counts beside the expected ones, over drawn queries."""
    p = cut(S.distinct_points(p))
    index = cut(voronoi.cells(p).select("id", "x", "y", "nbrs")) if indexed else None
    return reduce(DataFrame.unionByName, (measures.summary(cut(measures.costs(p, S.sample_queries(p, n_queries, k), index))) for k in ks))


def times(p: DataFrame, ks, n_queries: int = N, algorithms=tuple(ALGORITHMS), repeats: int = 1) -> DataFrame:
    """algorithm, n, k, ms for each query: a batch from the call to its last row, all jobs of the algorithm included.

    A run with k = 1 comes before, so that no algorithm pays for compiling what it shares with others."""
    p = cut(p)
    n, rows, spark = p.count(), [], p.sparkSession
    for name in algorithms:
        measures.timed(lambda f=ALGORITHMS[name]: f(p, S.sample_queries(p, 3, 1)))
    for k in ks:
        q = cut(S.sample_queries(p, n_queries, k))
        rows += [(name, n, k, measures.timed(lambda f=ALGORITHMS[name]: f(p, q), repeats=repeats) / n_queries) for name in algorithms]  # noqa: B023
    return spark.createDataFrame(rows, "algorithm string, n long, k int, ms double")


@query("w1_time_vs_n")
def w1(s, sf):
    """Time against n, uniform points of three tables, k = 200."""
    return reduce(DataFrame.unionByName, (times(S.load(s, sf, x), (200,)) for x in UNIFORM))


query("w1_small_n")(lambda s, sf: times(S.load(s, sf, UNIFORM[0]), (10, 200)))
query("w2_time_vs_k_uniform")(lambda s, sf: times(S.load(s, sf, UNIFORM[-1]), (10, 100)))
query("w2_time_vs_k_uniform_1000")(lambda s, sf: times(S.load(s, sf, UNIFORM[-1]), (1_000,), algorithms=("conic", "arc_bound")))
query("w2_time_vs_k_uneven")(lambda s, sf: times(S.uneven(s, sf), (10, 100)))
query("w3_w4_counts_uniform")(lambda s, sf: counts(S.load(s, sf, UNIFORM[1]), (10, 100)))
query("w3_w4_counts_uneven")(lambda s, sf: counts(S.uneven(s, sf), (10, 100)))


def conic_counts(p: DataFrame, ks) -> DataFrame:
    """Verified candidates and results of the engine and candidates of six sectors, which verify all of theirs."""
    p = cut(p)
    one = lambda k: rknn.conic_decisions(p, S.sample_queries(p, N, k)).groupBy("qid").agg(F.count(F.lit(1)).alias("six_sector"), F.sum((F.col("decision") == "knn").cast("int")).alias("conic"), F.sum(F.col("member").cast("int")).alias("result")).agg(*(F.round(F.avg(x), 2).alias(x) for x in ("six_sector", "conic", "result"))).withColumn("k", F.lit(k))
    d = reduce(DataFrame.unionByName, (cut(one(k)) for k in ks))
    return d.withColumn("expected", F.round(theory.verified("k"), 2))


query("w3_verified_uniform_1000000")(lambda s, sf: conic_counts(S.load(s, sf, UNIFORM[-1]), KS))
query("w3_verified_uneven")(lambda s, sf: conic_counts(S.uneven(s, sf), KS))


@query("w5_complexity")
def w5(s, sf):
    """Slopes on log k: of verified candidates about 1/2 for the engine and 1 for the others, and of time."""
    p = S.load(s, sf, "customer_uniform")
    ks = (5, 20, 80)
    n = measures.loglog_slope(counts(p, ks, False), "k", "n_verified", "algorithm").withColumnRenamed("slope", "verified_slope")
    return n.join(measures.loglog_slope(times(p, ks), "k", "ms", "algorithm").withColumnRenamed("slope", "time_slope"), "algorithm")


@query("w6_savings")
def w6(s, sf):
    """Share of time that the engine saves against each competitor, uniform points, k = 200."""
    d = times(S.load(s, sf, UNIFORM[-1]), (200,), repeats=3)
    ours = d.where("algorithm = 'conic'").select("k", F.col("ms").alias("ours"))
    return d.where("algorithm <> 'conic'").join(ours, "k").select("algorithm", "k", (1 - F.col("ours") / F.col("ms")).alias("saving"))


@query("w8_saturation")
def w8(s, sf):
    """From k = n / 6 on, six sectors hold every point: verified candidates of the engine against all of them."""
    p = S.load(s, sf, "supplier_uniform")
    n = p.count()
    return counts(p, (max(1, n // 6), max(1, n // 2)))


@query("w9_ablation")
def w9(s, sf):
    """Mean witnesses for orders, rules and matching."""
    p, q = setting(s, sf, "customer_uniform", 10)
    p = cut(p)
    index = cut(voronoi.cells(p).select("id", "x", "y", "nbrs"))
    runs = {f"order={o}": {"order": o} for o in ORDERS}
    runs |= {"match=graph": {"match": "graph", "index": index}, "rules=conics": {"rules": ("positive", "negative")}, "rules=semi": {"rules": ("semi",)}}
    one = lambda name, o: rknn.conic_decisions(p, q, **o).agg((F.sum((F.col("decision") == "knn").cast("int")) / N).alias("witnesses")).withColumn("variant", F.lit(name))
    return reduce(DataFrame.unionByName, (one(name, o) for name, o in runs.items()))


query("w10_orders_like_this", sql_by_candidates("orders_date_price", 10))(lambda s, sf: rknn.conic(*setting(s, sf, "orders_date_price", 10)))

SQL_REGION = """with c as (select c_custkey as id, c_acctbal / 10000.0::double as y, ('0x' || substr(md5(c_custkey::varchar), 1, 8))::bigint / 4294967296.0::double as x, r_name from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey),
d as (select a.r_name, a.id, b.id as qid, rank() over (partition by a.id order by (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)) as n from c a join c b on a.r_name = b.r_name and a.id <> b.id)
select r_name as region, qid, id from d where n <= 3"""


@query("w10_region_customers", SQL_REGION)
def w10_region(s, sf):
    """All-points answers within each region: customers who count another among their 3 nearest (key digest, balance)."""
    t = lambda n: S.table(s, sf, n)
    c = t("customer").join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    x = S.SPECS["customer_uniform"].x
    c = cut(c.selectExpr("c_custkey AS id", f"{x} AS x", "c_acctbal / 10000.0D AS y", "r_name"))
    names = [r.r_name for r in t("region").select("r_name").distinct().collect()]
    return reduce(DataFrame.unionByName, (rknn.all_points(c.where(F.col("r_name") == n).select("id", "x", "y"), 3).select(F.lit(n).alias("region"), "qid", "id") for n in names))


query("w11_stripes", sql_by_candidates("events_time_value", 5))(lambda s, sf: rknn.conic(*setting(s, sf, "events_time_value", 5), plan="bundle"))


@query("w12_embeddings")
def w12(s, sf):
    """How often the conic rules settle a vector, by dimension: they fade as distances concentrate."""
    v, q = cut(vectors(s, sf)), cut(drawn_vectors(s, sf).select("qid", "q_id"))
    one = lambda d: rknn.conic_metric(v, q, 5, d).groupBy().pivot("decision", ["semi", "positive", "negative", "knn"]).count().withColumn("dims", F.lit(d))
    return reduce(DataFrame.unionByName, map(one, (2, 3, 4, 8, 64)))
