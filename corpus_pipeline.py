"""A corpus in five stages: language, near-duplicates, personal data, mixing, tokens.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of documents.
Rows are named by id and text hash, so null or repeated ids with different texts stay different documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from revnn.llm import op2_mixing, op3_bpe, op4_pii, op7_language, op8_minhash
from revnn.llm.common import shared_dir, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: Shingles of the near-duplicate stage, in words.
SHINGLE = 5


def named(df: DataFrame) -> DataFrame:
    """Adds the two columns that name a row: id as text (null-safe) and text hash."""
    return df.withColumns({"_id": F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), "_th": F.xxhash64("text")})


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language (no text, no letters) go; a missing label is filled with the prediction.

    Without one labelled row there is nothing to predict: what has a letter stays, with a null label."""
    docs = docs.select(*COLUMNS)
    model = op7_language.learn(docs)
    if model is None:
        return docs.where(F.rlike("text", F.lit(r"\p{L}")))
    found = op7_language.identify(docs, model).where("lang_pred != 'und'")
    return found.withColumn("lang", F.coalesce("lang", "lang_pred")).select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: that with the smallest id. Texts without words are no group."""
    docs = docs.select(*COLUMNS)
    rows = op8_minhash.near_duplicates(docs, k=SHINGLE).select("doc_id", F.col("th").alias("_th"), "label")
    rows = rows.withColumn("_id", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")))
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "_th", "_id")
    stay = rows.where("label is not null").groupBy("label").agg(F.min(first).alias("one")).select("one._id", "one._th")
    stay = stay.union(rows.where("label is null").select("_id", "_th").distinct())
    # equal rows are one document: the join's own partitioning serves to keep one of them
    return named(docs).join(stay, ["_id", "_th"]).dropDuplicates(["_id", "_th"]).select(*COLUMNS)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Spans are replaced by their kind; every document stays."""
    found = op4_pii.detect(docs.select(*COLUMNS))
    text = F.when(F.size("spans") > 0, op4_pii.redact(F.col("text"), F.col("spans"))).otherwise(F.col("text"))
    return found.withColumn("text", text).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document stands as often as the mix takes it; a fraction is rounded up for its share of seeded draws."""
    docs = named(docs.select(*COLUMNS))
    size = F.coalesce(F.regexp_count("text", F.lit(op2_mixing.WORD)), F.lit(0)).cast("long")
    sized = op2_mixing.cut(docs.select("doc_id", "source", size.alias("size"), "_id", "_th"))
    taken = op2_mixing.mix_sized(sized)
    draw = F.pmod(F.xxhash64(F.lit(op2_mixing.SEED + 3), "_id", "_th"), F.lit(1 << 20)) / (1 << 20)
    times = taken.withColumn("times", F.floor(F.col("taken") / F.greatest("size", F.lit(1)) + draw))
    times = times.groupBy("_id", "_th").agg(F.sum("times").alias("times")).where("times > 0")
    kept = docs.join(times, ["_id", "_th"]).dropDuplicates(["_id", "_th"])
    return kept.withColumn("_n", F.explode(F.sequence(F.lit(1).cast("long"), "times"))).select(*COLUMNS)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens and digests of ids and decoded text."""
    return op3_bpe.digests(docs.select("doc_id", "text"))


STAGES = [
    ("language", language),
    ("near_duplicates", near_duplicates),
    ("personal_data", personal_data),
    ("mixing", mixing),
    ("tokens", tokens),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written to the shared folder and read again."""
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i + 1 < len(STAGES):
            docs.write.parquet(f"{folder}/{i}-{name}")
            docs = spark.read.parquet(f"{folder}/{i}-{name}")
    return docs
