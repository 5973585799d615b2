"""Streams against batch results."""

import numpy as np
from pyspark.sql import functions as F

from revnn.operators import rknn
from revnn.sources import points as S
from revnn.streaming import streams


def files_by_day(spark, sf, folder):
    e = spark.read.parquet(f"{sf}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "value")
    days = sorted(r.d for r in e.select(F.to_date("ts").alias("d")).distinct().collect())[:4]
    for n, d in enumerate(days):
        e.where(F.to_date("ts") == F.lit(d)).coalesce(1).write.parquet(f"{folder}/{n:02d}")
    return e.where(F.to_date("ts").isin(days)), e.schema, days


def test_query_stream_equals_batch(spark, sf, tmp_path):
    p = S.load(spark, sf, "customer_uniform")
    q = S.free_queries(spark, 9, 3)
    for i in range(3):
        q.where(F.col("qid") % 3 == i).coalesce(1).write.parquet(str(tmp_path / "in" / str(i)))
    stream = spark.readStream.schema(q.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    streams.answer_stream(stream, lambda: p, str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination()
    got = {(r.qid, r.id) for r in spark.read.parquet(str(tmp_path / "out")).collect()}
    assert got == {(r.qid, r.id) for r in rknn.conic(p, q).collect()}


def test_snapshots_equal_batch_per_window(spark, sf, tmp_path):
    e, schema, days = files_by_day(spark, sf, str(tmp_path / "in"))
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    p = stream.select("ts", F.col("event_id").alias("id"), (F.unix_micros("ts") / 8.64e10).alias("x"), F.col("value").alias("y"))
    out = streams.snapshots(p, 3)
    w = out.writeStream.format("memory").queryName("snaps").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).outputMode("append").start()
    w.awaitTermination()
    got = {(str(r.window_start)[:10], r.qid, r.id) for r in spark.table("snaps").collect()}
    closed = {g[0] for g in got}
    assert closed
    want = set()
    for d in days:
        rows = e.where(F.to_date("ts") == F.lit(d)).select("event_id", (F.unix_micros("ts") / 8.64e10).alias("x"), "value").collect()
        ids, x = [r[0] for r in rows], np.array([[r[1], r[2]] for r in rows])
        d2 = ((x[:, None] - x[None]) ** 2).sum(axis=2)
        np.fill_diagonal(d2, np.inf)
        r2 = np.sort(d2, axis=1)[:, 2]
        want |= {(str(d), ids[j], ids[i]) for i in range(len(ids)) for j in np.flatnonzero(d2[i] <= r2[i])}
    assert got == {w for w in want if w[0] in closed}


def test_sessions_and_sliding_windows(spark, sf):
    e = spark.read.parquet(f"{sf}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "value")
    s = streams.sessions(e).collect()
    assert sum(r.n for r in s) == e.count()
    assert sum(r.n for r in streams.sliding_counts(e).collect()) == 4 * e.count()


def test_repeated_rows_count_once(spark, sf, tmp_path):
    e, schema, _ = files_by_day(spark, sf, str(tmp_path / "in"))
    e.limit(5).coalesce(1).write.parquet(str(tmp_path / "in" / "00b"))
    stream = spark.readStream.schema(schema).parquet(str(tmp_path / "in" / "*"))
    w = streams.without_repeats(stream).writeStream.format("memory").queryName("once").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    w.awaitTermination()
    assert spark.table("once").count() == e.count()


def test_standing_queries_follow_the_points(spark, tmp_path):
    p = S.uniform(spark, 400)
    q = S.free_queries(spark, 4, 3)
    for i in range(4):
        p.where(F.col("id") % 4 == i).coalesce(1).write.parquet(str(tmp_path / "in" / str(i)))
    stream = spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in" / "*"))
    out = streams.standing_queries(stream, q)
    w = out.writeStream.format("memory").queryName("standing").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).outputMode("update").start()
    w.awaitTermination()
    rows = spark.table("standing").collect()
    last = {qid: max(r.version for r in rows if r.qid == qid) for qid in {r.qid for r in rows}}
    assert {(r.qid, r.id) for r in rows if r.version == last[r.qid]} == {(r.qid, r.id) for r in rknn.rknn_definition(p, q).collect()}


def test_index_is_kept_up_by_batches(spark, tmp_path):
    from revnn.operators import voronoi

    p = S.uniform(spark, 120)
    path = str(tmp_path / "index")
    voronoi.build_index(p.where("id < 100 OR id > 110"), path, 0)
    change = p.where("id BETWEEN 100 AND 110").withColumn("op", F.lit("add")).unionByName(p.where("id IN (5, 6)").withColumn("op", F.lit("remove")))
    change.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(change.schema).parquet(str(tmp_path / "in"))
    streams.maintain_index(stream, path, str(tmp_path / "cp")).awaitTermination()
    got = voronoi.read_index(spark, path)
    want = voronoi.cells(p.where("id NOT IN (5, 6)"))
    ids = lambda d: {(r.id, tuple(sorted(n.id for n in r.nbrs))) for r in d.select("id", "nbrs").collect()}
    assert got.first().version == 1 and ids(got) == ids(want)


def test_queries_meet_points_in_time(spark, tmp_path):
    t = "timestamp'2024-01-01 00:00:00'"
    q = spark.range(20).selectExpr("id AS qid", f"{t} + make_interval(0,0,0,0,0,CAST(id AS INT)) AS qt", "id / 20D AS qx", "0.5D AS qy")
    p = spark.range(200).selectExpr("id", f"{t} + make_interval(0,0,0,0,0,CAST(id % 60 AS INT)) AS ts", "(id % 20) / 20D AS x", "0.5D AS y")
    for name, d in (("q", q), ("p", p)):
        d.coalesce(1).write.parquet(str(tmp_path / name))
    read = lambda name, d: spark.readStream.schema(d.schema).parquet(str(tmp_path / name))
    out = streams.queries_with_points(read("q", q), read("p", p), 0.1)
    w = out.writeStream.format("memory").queryName("met").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).outputMode("append").start()
    w.awaitTermination()
    want = {(a.qid, b.id) for a in q.collect() for b in p.collect() if 0 <= (b.ts - a.qt).total_seconds() <= 600 and abs(int(b.x / 0.1) - int(a.qx / 0.1)) <= 1}
    assert {(r.qid, r.id) for r in spark.table("met").collect()} == want
