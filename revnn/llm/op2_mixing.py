"""Mixing sources to target weights by highest quotients (odd divisors 1, 3, 5, ...).

Every step is a DataFrame expression. Word counts are taken once and cut from the text; what follows works on
rows of a few longs:

1. source sizes -> targets: ``min(cap * size, level * weight)``, the level found by one pass over the sources in
   order of ``cap * size / weight`` (this is where repeated resharing of the excess ends);
2. equal-token blocks -> sources by highest quotients ``target / (2 j + 1)``. Only quotients near the final divisor
   are generated (a few for each source), the rest is known to be won;
3. each source is dealt into shards of a bounded number of words by a seeded hash of the row (equal rows are numbered),
   so that a hot source, or an id that a third of all rows share, is many shards; the source's blocks go to its shards by the same rule: integer quotas for each shard;
4. in a shard documents stand in seeded order and are cut into blocks; whole passes take every block, the rest of
   the quota takes the blocks of smallest seeded hash. A document's share is its overlap with the taken blocks.

Defined cases: null text has size 0 and takes 0; null source is a source, last in order; null or repeated ids are
kept row by row; an empty table gives an empty result. Further columns of the input are ignored.
Cost: shuffles of (id, size) rows only. The windows over sources are over one row each (metadata), those over shards
are bounded by ``SHARD_WORDS``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from revnn.llm.common import WORD, cut, small, table

SEED = 20240607
WEIGHTS = (1.0, 2.0, 3.0)
CAP = 3
#: Words of a block: a millionth of the corpus, between 1 and this.
BLOCK_WORDS = 256
#: Blocks below which a source's target is met word by word.
FEW_BLOCKS = 64
#: Words of a shard: a 256th of the corpus, at most this.
SHARD_WORDS = 1 << 22


def sizes(docs: DataFrame) -> DataFrame:
    """doc_id, source, size (the number of words of the whole text), text_hash."""
    n = F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long")
    return docs.select("doc_id", "source", n.alias("size"), F.xxhash64("text").alias("text_hash"))


def source_targets(sized: DataFrame, weights=WEIGHTS, cap: int = CAP) -> DataFrame:
    """source, source_id, source_size, weight, total, target: the shares of all words, none above cap times its size."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    every = Window.partitionBy()
    s = sized.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    s = s.withColumn("source_id", F.row_number().over(by_name) - 1)
    w = F.element_at(F.array(*map(F.lit, weights)), (F.col("source_id") % len(weights) + 1).cast("int"))
    s = s.withColumns({"weight": w, "top": F.lit(float(cap)) * F.col("source_size")})
    s = s.withColumns({"total": F.sum("source_size").over(every), "order": F.col("top") / F.col("weight")})
    before = Window.orderBy("order", "source_id").rowsBetween(Window.unboundedPreceding, -1)
    after = Window.orderBy("order", "source_id").rowsBetween(0, Window.unboundedFollowing)
    left = F.col("total") - F.coalesce(F.sum("top").over(before), F.lit(0.0))
    s = s.withColumn("level", left / F.sum("weight").over(after))
    # the first source (in this order) whose top lies above its level fixes the level; those before it are full
    s = s.withColumn("level", F.min(F.when(F.col("level") <= F.col("order"), F.struct("order", "source_id", "level"))).over(every)["level"])
    target = F.when(F.col("total") == 0, 0.0).otherwise(F.least(F.col("top"), F.coalesce("level", F.lit(0.0)) * F.col("weight")))
    return s.select("source", "source_id", "source_size", "weight", "total", target.alias("target"))


def highest_quotients(units: DataFrame, key: str, weight: str, seats: str, within: str | None = None) -> DataFrame:
    """Adds ``quota``: `seats` (one number for all units of `within`) go to units by highest quotients weight/(2j+1).

    The final divisor lies between those for seats - n and seats + n rounded quotas (n units), so only the quotients
    between them are generated: about 2 n + 2 for all units together."""
    part = [within] if within else []
    every = Window.partitionBy(*part)
    u = units.withColumns({"_n": F.count(F.lit(1)).over(every), "_sum": F.sum(weight).over(every)})
    share = F.when(F.col("_sum") > 0, F.col(weight) / F.col("_sum")).otherwise(F.lit(0.0))
    u = u.withColumns(
        {
            "_low": F.floor(share * F.greatest(F.col(seats) - F.col("_n"), F.lit(0))).cast("long"),
            "_high": F.when(F.col(weight) > 0, F.ceil(share * (F.col(seats) + F.col("_n"))) + 1).otherwise(F.lit(0)).cast("long"),
        }
    )
    u = u.withColumn("_rest", F.col(seats) - F.sum("_low").over(every))
    q = u.where(F.col("_high") > F.col("_low")).select(*part, key, "_rest", weight, F.explode(F.sequence("_low", F.col("_high") - 1)).alias("_j"))
    order = Window.partitionBy(*part).orderBy((F.col(weight) / (2 * F.col("_j") + 1)).desc(), F.col(key), F.col("_j"))
    won = q.withColumn("_rank", F.row_number().over(order)).where(F.col("_rank") <= F.col("_rest"))
    won = won.groupBy(*part, key).agg(F.count(F.lit(1)).alias("_won"))
    out = u.join(won, [*part, key], "left").withColumn("quota", F.col("_low") + F.coalesce("_won", F.lit(0)))
    return out.drop("_n", "_sum", "_low", "_high", "_rest", "_won")


def mix(docs: DataFrame, weights=WEIGHTS, cap: int = CAP, seed: int = SEED) -> DataFrame:
    """doc_id, size, source_size, target, taken, source for every row of `docs` (doc_id, text, source)."""
    return mix_sized(cut(sizes(docs)), weights, cap, seed).drop("text_hash")


def mix_sized(sized: DataFrame, weights=WEIGHTS, cap: int = CAP, seed: int = SEED) -> DataFrame:
    """As :func:`mix`, from rows (doc_id, source, size); further columns (of types that can be grouped) are kept."""
    kept = [c for c in sized.columns if c not in ("doc_id", "source", "size")]
    # equal rows are counted, then told apart by a number: no key holds them all, and reruns number them alike
    d = sized.select("doc_id", "source", "size", F.struct(F.lit(0).alias("_none"), *(F.col(f"`{c}`") for c in kept)).alias("_kept"))
    d = d.groupBy("doc_id", "source", "size", "_kept").agg(F.count(F.lit(1)).alias("_copies"))
    d = d.withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("long"), "_copies"))).drop("_copies")
    targets = source_targets(sized, weights, cap)
    block = F.least(F.greatest(F.shiftright("total", 20), F.lit(1)), F.lit(BLOCK_WORDS)).cast("long")
    shard = F.least(F.greatest(F.shiftright("total", 8), F.lit(1)), F.lit(SHARD_WORDS)).cast("long")
    targets = targets.withColumns({"block": block, "n_shards": F.greatest(F.ceil(F.col("source_size") / shard), F.lit(1)).cast("long")})
    targets = targets.withColumn("seats", F.round(F.col("total") / F.col("block")).cast("long"))
    targets = highest_quotients(targets, "source_id", "target", "seats").withColumnRenamed("quota", "source_quota")
    # a target of few blocks is met in words
    few = F.col("target") < FEW_BLOCKS * F.col("block")
    targets = cut(targets.withColumn("source_quota", F.when(few, F.round("target").cast("long")).otherwise(F.col("source_quota"))).withColumn("block", F.when(few, F.lit(1)).otherwise(F.col("block")).cast("long")))

    d = d.join(small(targets.select(F.col("source").alias("_source"), "source_id", "source_size", "target", "n_shards", "block")), F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
    name = (F.col("doc_id").cast("string"), "size", "_kept", "_copy")
    d = d.withColumns({"shard": F.pmod(F.xxhash64(F.lit(seed), *name), F.col("n_shards")), "draw": F.xxhash64(F.lit(seed + 1), *name)})
    in_shard = Window.partitionBy("source_id", "shard").orderBy("draw", "doc_id", "size", "_kept", "_copy")
    d = d.withColumns({"nth": F.row_number().over(in_shard), "end": F.sum("size").over(in_shard.rowsBetween(Window.unboundedPreceding, 0))})
    d = cut(d.drop("draw"))

    shards = d.groupBy("source_id", "shard").agg(F.sum("size").alias("shard_size"))
    shards = shards.join(small(targets.select("source_id", "source_quota", "block")), "source_id")
    shards = highest_quotients(shards, "shard", "shard_size", "source_quota", "source_id")
    n_blocks = F.ceil(F.col("shard_size") / F.col("block")).cast("long")
    shards = shards.withColumn("n_blocks", n_blocks).where("n_blocks > 0")
    shards = shards.withColumn("passes", F.least(F.floor(F.col("quota") / F.col("n_blocks")), F.lit(cap)).cast("long"))
    shards = shards.withColumn("rest", F.when(F.col("passes") < cap, F.col("quota") - F.col("passes") * F.col("n_blocks")).otherwise(F.lit(0)))
    shards = cut(shards.select("source_id", "shard", "n_blocks", "passes", "rest"))

    drawn = shards.where("rest > 0").select("source_id", "shard", "rest", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n_blocks") - 1)).alias("nth_block"))
    draw = Window.partitionBy("source_id", "shard").orderBy(F.xxhash64(F.lit(seed + 2), "source_id", "shard", "nth_block"), "nth_block")
    drawn = drawn.withColumn("_rank", F.row_number().over(draw)).where("_rank <= rest").select("source_id", "shard", "nth_block", F.lit(1).alias("hit"))

    # shard quotas are a few hundred to a few rows a shard of millions of words; each document meets its own shard's row
    d = d.join(shards.drop("n_blocks"), ["source_id", "shard"], "left")
    first, last = F.floor((F.col("end") - F.col("size")) / F.col("block")), F.floor((F.col("end") - 1) / F.col("block"))
    spans = F.when((F.col("size") > 0) & (F.col("rest") > 0), F.sequence(first, last))
    parts = d.withColumn("nth_block", F.explode_outer(spans)).join(drawn, ["source_id", "shard", "nth_block"], "left")
    low, high = F.col("nth_block") * F.col("block"), (F.col("nth_block") + 1) * F.col("block")
    overlap = F.when(F.col("hit") == 1, F.least("end", high) - F.greatest(F.col("end") - F.col("size"), low)).otherwise(F.lit(0))
    rows = parts.groupBy("source_id", "shard", "nth").agg(
        *(F.first(c).alias(c) for c in ["doc_id", "source", "size", "source_size", "target", "passes", "_kept"]), F.sum(overlap).alias("extra")
    )
    taken = F.coalesce(F.col("passes") * F.col("size"), F.lit(0)) + F.col("extra")
    return rows.select("doc_id", "size", "source_size", "target", taken.cast("long").alias("taken"), "source", *(F.col("_kept")[c].alias(c) for c in kept))


def op2_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


QUERIES = {"op2_source_mixing": op2_source_mixing}
