"""Tables as planar points (id, x, y), simulated points, and query points (qid, qx, qy, q_id, k)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PointSpec:
    """How a table becomes points; SQL expressions for Spark and for DuckDB."""

    table: str
    id: str
    x: str
    y: str
    duck_x: str | None = None
    duck_y: str | None = None
    distinct: bool = False


def _md5(key: str, at: int) -> tuple[str, str]:
    return f"CAST(conv(substr(md5(CAST({key} AS STRING)), {at}, 8), 16, 10) AS BIGINT) / 4294967296.0D", f"('0x' || substr(md5({key}::varchar), {at}, 8))::bigint / 4294967296.0::double"


def _uniform(table: str, key: str) -> PointSpec:
    (x, dx), (y, dy) = _md5(key, 1), _md5(key, 9)
    return PointSpec(table, key, x, y, dx, dy)


DAY = 86_400_000_000
SPECS = {
    "orders_uniform": _uniform("orders", "o_orderkey"),
    "customer_uniform": _uniform("customer", "c_custkey"),
    "supplier_uniform": _uniform("supplier", "s_suppkey"),
    # fixed scales, so that both engines see the same bits: 30 days and a value of 600 are one unit
    "events_time_value": PointSpec("events", "event_id", f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'2024-01-01 00:00:00', ts) / {30 * DAY}.0D", "value / 600.0D", f"(epoch_us(ts) - epoch_us(timestamp '2024-01-01')) / {30 * DAY}.0::double", "value / 600.0::double"),
    "orders_date_price": PointSpec("orders", "o_orderkey", f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1995-01-01 00:00:00', o_orderdate) / {2500 * DAY}.0D", "o_totalprice / 500000.0D", f"(epoch_us(o_orderdate) - epoch_us(timestamp '1995-01-01')) / {2500 * DAY}.0::double", "o_totalprice / 500000.0::double"),
    "lineitem_qty_price": PointSpec("lineitem", "l_orderkey * 8 + l_linenumber", "l_quantity / 50.0D", "l_extendedprice / 100000.0D", "l_quantity / 50.0::double", "l_extendedprice / 100000.0::double", True),
    "lineitem_date_price": PointSpec("lineitem", "l_orderkey * 8 + l_linenumber", f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1995-01-01 00:00:00', l_shipdate) / {2500 * DAY}.0D", "l_extendedprice / 100000.0D", f"(epoch_us(l_shipdate) - epoch_us(timestamp '1995-01-01')) / {2500 * DAY}.0::double", "l_extendedprice / 100000.0::double", True),
    "part_size_price": PointSpec("part", "p_partkey", "CAST(p_size AS DOUBLE)", "p_retailprice", "p_size::double", "p_retailprice"),
    "embeddings_xy": PointSpec("embeddings", "vec_id", "CAST(embedding[0] AS DOUBLE)", "CAST(embedding[1] AS DOUBLE)", "embedding[1]::double", "embedding[2]::double"),
    "documents_len_words": PointSpec("documents", "doc_id", "n_chars / 10000.0D", "(length(text) - length(replace(text, ' ', ''))) / 2000.0D", "n_chars / 10000.0::double", "(length(text) - length(replace(text, ' ', ''))) / 2000.0::double"),
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def points(df: DataFrame, spec: PointSpec) -> DataFrame:
    """(id, x, y) of a table: rows without an id or with a null or non-finite coordinate are left out."""
    p = df.selectExpr(f"CAST({spec.id} AS BIGINT) AS id", f"CAST({spec.x} AS DOUBLE) AS x", f"CAST({spec.y} AS DOUBLE) AS y")
    p = p.where("id IS NOT NULL AND x IS NOT NULL AND y IS NOT NULL AND abs(x) < double('Infinity') AND abs(y) < double('Infinity')")
    return distinct_points(p) if spec.distinct else p


def rejected(df: DataFrame, spec: PointSpec) -> int:
    """Rows that :func:`points` leaves out (before de-duplication)."""
    plain = PointSpec(spec.table, spec.id, spec.x, spec.y)
    return df.count() - points(df, plain).count()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Points of a built-in spec."""
    return points(table(spark, sf_dir, SPECS[name].table), SPECS[name])


def distinct_points(p: DataFrame) -> DataFrame:
    """One point for each location: that with the smallest id."""
    return p.groupBy("x", "y").agg(F.min("id").alias("id")).select("id", "x", "y")


def uniform(spark: SparkSession, n: int, seed: int = 0) -> DataFrame:
    """n simulated points of the unit square, from digests of their numbers."""
    key = f"concat(id, ':', {seed})" if seed else "id"
    return spark.range(n).selectExpr("id", f"{_md5(key, 1)[0]} AS x", f"{_md5(key, 9)[0]} AS y")


#: Size of the published uneven set: distinct geographic places.
UNEVEN = 49_601


def uneven(spark: SparkSession, sf_dir: str, n: int = UNEVEN) -> DataFrame:
    """n distinct uneven points: event time and value, those of smallest digest; all of them where there are fewer."""
    p = distinct_points(load(spark, sf_dir, "events_time_value"))
    return p.orderBy(F.md5(p["id"].cast("string")), "id").limit(n)


def file_points(spark: SparkSession, path: str, fmt: str = "csv", **options) -> DataFrame:
    """Points of a csv, json, orc or parquet file with columns id, x, y."""
    return spark.read.format(fmt).options(**options).schema("id LONG, x DOUBLE, y DOUBLE").load(path)


def sample_queries(p: DataFrame, n: int = 30, k: int = 10, seed: int = 7) -> DataFrame:
    """n members of the point set as queries, drawn by digest of the id."""
    from pyspark.sql import Window

    drawn = p.withColumn("draw", F.md5(F.concat(F.col("id").cast("string"), F.lit(f":{seed}")))).orderBy("draw", "id").limit(n)
    q = drawn.withColumn("qid", F.row_number().over(Window.orderBy("draw", "id")))
    return q.select("qid", F.col("x").alias("qx"), F.col("y").alias("qy"), F.col("id").alias("q_id"), F.lit(k).alias("k"))


def free_queries(spark: SparkSession, n: int = 30, k: int = 10, box=(0.0, 0.0, 1.0, 1.0), seed: int = 7) -> DataFrame:
    """n query points that are no member: simulated in the box."""
    q = uniform(spark, n, seed).withColumnRenamed("id", "qid")
    x, y = box[0] + F.col("x") * (box[2] - box[0]), box[1] + F.col("y") * (box[3] - box[1])
    return q.select((F.col("qid") + 1).cast("int").alias("qid"), x.alias("qx"), y.alias("qy"), F.lit(None).cast("long").alias("q_id"), F.lit(k).alias("k"))


def all_queries(p: DataFrame, k: int = 10) -> DataFrame:
    """Every point a query."""
    return p.select(F.col("id").cast("int").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"), F.col("id").alias("q_id"), F.lit(k).alias("k"))
