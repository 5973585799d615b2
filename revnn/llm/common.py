"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import re
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Contract characters: words are runs of anything but these ASCII white-space characters.
WORD = r"[^\x20\x09-\x0D]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; only Spark's reader touches the path."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share, as the session names it.

    Only a local session (one process, as in tests) may leave it unset and gets a temporary one."""
    sc = spark.sparkContext
    named = sc.getCheckpointDir() or sc.getConf().get("spark.checkpoint.dir")
    if not named:
        if not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        named = tempfile.mkdtemp(prefix="revnn-checkpoint-")
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(named)
    return named


@contextmanager
def settings(spark: SparkSession, **values: str):
    """Runtime settings (`__` for a dot) for what runs inside."""
    before = {k: spark.conf.get(k, None) for k in (name.replace("__", ".") for name in values)}
    for name, v in values.items():
        spark.conf.set(name.replace("__", "."), v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


#: What is written is not read from shuffle files again, so these go when the write ends; skewed joins are split even
#: where an aggregate by the same key follows and needs an exchange then.
WRITING = {"spark__sql__classic__shuffleDependency__fileCleanup__enabled": "true", "spark__sql__adaptive__forceOptimizeSkewedJoin": "true"}


def cut(df: DataFrame) -> DataFrame:
    """Materialise reliably: later reads survive lost executors and repeat no work."""
    shared_dir(df.sparkSession)
    with settings(df.sparkSession, **WRITING):
        return df.select("*").checkpoint(eager=True)


class Work:
    """Tables of one run in the folder that executors share."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.folder, self.n, self.held = spark, f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}", 0, []

    def keep(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.folder}/{self.n}"
        with settings(self.spark, **WRITING):
            df.write.option("compression", "zstd").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.held.append((out, path))
        return out

    def drop(self, *tables: DataFrame) -> None:
        """Empties kept tables that no plan reads any more."""
        for t, path in [x for x in self.held if any(x[0] is t for t in tables)]:
            self.spark.createDataFrame([], t.schema).write.mode("overwrite").parquet(path)
        self.held = [x for x in self.held if not any(x[0] is t for t in tables)]


def ascii_lower(c):
    """A-Z to a-z and nothing else."""
    return F.translate(c, UPPER, LOWER)


def batches_of(spark: SparkSession, rows: int):
    """Arrow batches of at most `rows` rows for what runs inside: rows that hold texts are large."""
    return settings(spark, spark__sql__execution__arrow__maxRecordsPerBatch=str(rows))


def small(df: DataFrame, limit: int = 100_000) -> DataFrame:
    """`df`, marked for broadcast only if it is shown to have at most `limit` rows; `df` should be cut before."""
    return F.broadcast(df) if df.limit(limit + 1).count() <= limit else df


def bind(c, f):
    """f(c) with c evaluated once for each row, though f uses it many times."""
    return F.transform(F.array(c), f)[0]


def prefix_sums(a, chunk: int = 256):
    """For an array<long>, the sum of what stands before each element; near-linear in its length."""
    total = lambda x: F.aggregate(x, F.lit(0).cast("long"), lambda s, v: s + v)

    def of(a):
        starts = F.sequence(F.lit(0), F.floor((F.size(a) - 1) / chunk).cast("int"))
        part = lambda i: F.slice(a, i * chunk + 1, chunk)
        inside = lambda q: F.transform(q["part"], lambda _, i: q["before"] + total(F.slice(q["part"], F.lit(1), i)))
        sums = F.transform(starts, lambda i: total(part(i)))
        return bind(sums, lambda t: F.flatten(F.transform(starts, lambda i: bind(F.struct(total(F.slice(t, F.lit(1), i)).alias("before"), part(i).alias("part")), inside))))

    return F.when(F.size(a) > 0, bind(a, of)).otherwise(F.array().cast("array<bigint>"))


def spread_join(rows: DataFrame, keyed: DataFrame, key: list[str], by: list[str], how: str = "inner") -> DataFrame:
    """`rows` joined with `keyed` (one row for each key), a key's rows dealt to as many tasks as its column `salts` says.

    Rows of a key are told apart by `by` and by their place in the input. The few keys with several salts are broadcast
    if they are shown to be few."""
    hot = keyed.where("salts > 1").select(*key, "salts")
    d = rows.join(small(hot), key, "left").withColumn("_salt", F.pmod(F.xxhash64(*by, F.monotonically_increasing_id()), F.coalesce("salts", F.lit(1))).cast("int")).drop("salts")
    return d.join(keyed.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("salts"), [*key, "_salt"], how).drop("_salt")


BITMAP = 1 << 15
BITS = 1 << 24


def fixed_filter(keys: DataFrame, *names: str):
    """A test for rows whose `names` may be among `keys`: a bit for each hash, BITS of them whatever the input.

    Returns f(df, flag): df with a boolean column, false only for rows that surely are not among the keys. What is
    broadcast is BITS / 8 bytes at most; with ever more keys the test lets more pass, and stays right."""
    bit = lambda: F.pmod(F.xxhash64(*names), F.lit(BITS))
    rows = keys.select(F.floor(bit() / BITMAP).alias("_bucket"), (bit() % BITMAP).alias("_bit"))
    maps = F.broadcast(cut(rows.groupBy("_bucket").agg(F.bitmap_construct_agg("_bit").alias("_map"))))

    def marked(df: DataFrame, flag: str) -> DataFrame:
        d = df.withColumns({"_bucket": F.floor(bit() / BITMAP), "_bit": (bit() % BITMAP).cast("int")}).join(maps, "_bucket", "left")
        byte = F.conv(F.hex(F.substring("_map", (F.floor(F.col("_bit") / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
        there = F.coalesce(byte.bitwiseAND(F.expr("shiftleft(1, _bit % 8)")) != 0, F.lit(False))
        return d.withColumn(flag, there).drop("_bucket", "_bit", "_map")

    return marked
