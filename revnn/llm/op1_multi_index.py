"""Approximate nearest neighbours by an inverted multi-index, for inner products.

Both halves of a vector are quantised on their own (K centroids each), so a vector lies in one of K x K cells. A query
sorts both lists of centroids by inner product and walks the pairs in order of their sum with a heap, until the cells
that it has seen hold enough entries; the entries of these cells are then ranked by the exact inner product in double
precision. Equal vectors are one entry with the smallest of their ids, as many as any answer can need, so a vector on a
third of all rows costs no more than another; equal queries are searched once.

Centroids come from a bounded sample (``SAMPLE`` vectors of smallest hash); every row is indexed. How many entries are
enough is measured on the same sample: the smallest share of entries at which the walk finds ``AIM`` of the exact
answers. On vectors without structure that share is large, on clustered ones small; ``share`` can be given instead.
Cells are dealt into buckets of a bounded number of entries (a crowded cell into several) and queries into blocks by
the bucket that their walk begins in; only (bucket, block) pairs meet in a task, and an entry is copied only to blocks
of which some query asks for its bucket.

Defined cases: vectors that are null, zero, of another length than the sample's most frequent one, or that hold null
or non-finite components take no part, nor do rows without an id; a repeated (id, vector) counts once; with fewer
candidates than wanted all are returned; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import heapq
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from revnn.llm.common import cut, small, table

SAMPLE, AIM, NEAREST = 20_000, 0.96, 20
BUCKET_ENTRIES, BLOCK_QUERIES, BLOCK_SCORES = 20_000, 4_000, 256
#: Entries that a cell should hold, for the choice of K (a power of two, at most MOST_CENTROIDS).
CELL_ENTRIES, MOST_CENTROIDS = 12, 1024


def taking_part(vectors: DataFrame) -> DataFrame:
    """vec_id, v (array<double>), k1, k2 (128 bits that name the vector), length."""
    v = F.transform("embedding", lambda x: x.cast("double"))
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("v", lambda x: x != 0)
    d = vectors.select("vec_id", v.alias("v")).where(F.col("vec_id").isNotNull() & F.col("v").isNotNull()).where(fine)
    # -0.0 and 0.0 are one value
    d = d.withColumn("v", F.transform("v", lambda x: x + F.lit(0.0)))
    return d.select("vec_id", "v", F.xxhash64("v").alias("k1"), F.xxhash64(F.lit(1), "v").alias("k2"), F.size("v").alias("length"))


def classes(vectors: DataFrame, keep: int = NEAREST + 1) -> DataFrame:
    """rep, ids (the `keep` smallest, sorted), v: a row for each distinct vector."""
    few = Window.partitionBy("k1", "k2").orderBy("vec_id")
    d = vectors.dropDuplicates(["k1", "k2", "vec_id"]).withColumn("nth", F.row_number().over(few)).where(F.col("nth") <= keep)
    d = d.groupBy("k1", "k2").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"), F.first("v").alias("v"))
    return d.select(F.col("ids")[0].alias("rep"), "ids", "v", "k1", "k2")


def k_means(x: np.ndarray, k: int, rounds: int = 10, seed: int = 3) -> np.ndarray:
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        a = nearest(x, c)
        n = np.bincount(a, minlength=len(c))
        total = np.zeros_like(c)
        np.add.at(total, a, x)
        c = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], c)
    return c


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return np.concatenate([(x[i : i + 4096] @ c.T - 0.5 * (c * c).sum(axis=1)).argmax(axis=1) for i in range(0, len(x), 4096)] or [np.zeros(0, int)])


class Quantiser:
    """Centroids of both halves."""

    def __init__(self, sample: np.ndarray, k: int):
        self.half = sample.shape[1] // 2
        self.first, self.second = k_means(sample[:, : self.half], k), k_means(sample[:, self.half :], k)

    @property
    def n_cells(self) -> int:
        return len(self.first) * len(self.second)

    def cells(self, x: np.ndarray) -> np.ndarray:
        return nearest(x[:, : self.half], self.first) * len(self.second) + nearest(x[:, self.half :], self.second)

    def walk(self, q: np.ndarray) -> Iterator[int]:
        """Cells in order of the summed inner products of their centroids with the query's halves."""
        a, b = self.first @ q[: self.half], self.second @ q[self.half :]
        i, j = np.argsort(-a, kind="stable"), np.argsort(-b, kind="stable")
        a, b, n = a[i].tolist(), b[j].tolist(), len(self.second)
        i, j = (i * n).tolist(), j.tolist()
        heap, row = [(-(a[0] + b[0]), 0, 0)], 1
        while heap:
            _, x, y = heapq.heappop(heap)
            yield i[x] + j[y]
            if y == 0 and row < len(a):  # the next row can't come before its left neighbour's first cell
                heapq.heappush(heap, (-(a[row] + b[0]), row, 0))
                row += 1
            if y + 1 < len(b):
                heapq.heappush(heap, (-(a[x] + b[y + 1]), x, y + 1))

    def probe(self, q: np.ndarray, counts: np.ndarray, enough: int) -> list[int]:
        """The first cells of the walk that hold `enough` entries together; empty cells are left out."""
        found, got = [], 0
        for cell in self.walk(q):
            if n := int(counts[cell]):
                found.append(cell)
                got += n
                if got >= enough:
                    break
        return found


def enough_share(quantiser: Quantiser, sample: np.ndarray, aim: float = AIM, n_queries: int = 200, nearest_n: int = NEAREST) -> float:
    """The share of entries that must be ranked for `aim` of the exact answers, over the sample."""
    cells = quantiser.cells(sample)
    counts = np.bincount(cells, minlength=quantiser.n_cells)
    need = []
    for q in sample[:: max(1, len(sample) // n_queries)]:
        top = np.argsort(-(sample @ q), kind="stable")[: nearest_n + 1]
        order, seen = np.fromiter(quantiser.walk(q), int), np.zeros(quantiser.n_cells)
        seen[order] = np.cumsum(counts[order])
        need.append(seen[cells[top[1:]]] / len(sample))
    if not any(map(len, need)):
        return 1.0
    return float(np.quantile(np.concatenate(need), aim))


def search(vectors: DataFrame, is_query: Column, n: int = NEAREST, share: float | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: for the rows of `vectors` (vec_id, embedding) that are queries, the n nearest others."""
    spark = vectors.sparkSession
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    valid = taking_part(vectors)
    drawn = cut(valid.select("v", "length", F.col("k1").alias("draw")).dropDuplicates(["draw"]).orderBy("draw").limit(SAMPLE)).collect()
    if not drawn:
        return empty
    dims = Counter(r.length for r in drawn).most_common(1)[0][0]
    sample = np.array([r.v for r in drawn if r.length == dims])
    valid = valid.where(F.col("length") == dims)
    entries = cut(classes(valid, n + 1))
    total = entries.count()
    k = min(MOST_CENTROIDS, 1 << max(1, round(np.log2(max(total / CELL_ENTRIES, 4)) / 2)))
    quantiser = Quantiser(sample, k)
    share = enough_share(quantiser, sample) if share is None else share
    shared = spark.sparkContext.broadcast(quantiser)

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = b.column(2).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, dims)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), pa.array(shared.value.cells(x), pa.int64())], names=["rep", "ids", "v", "cell"])

    placed = cut(entries.select("rep", "ids", "v").mapInArrow(encode, "rep long, ids array<long>, v array<double>, cell long"))
    counts = np.zeros(quantiser.n_cells, np.int64)  # MOST_CENTROIDS squared numbers at most
    for r in placed.groupBy("cell").count().collect():
        counts[r["cell"]] = r["count"]
    enough = max(4 * (n + 1), int(np.ceil(share * total)))
    # cells dealt into buckets in order, a crowded cell over several
    bucket_of = (np.cumsum(counts) - 1) // BUCKET_ENTRIES
    parts_of = np.maximum(1, -(-counts // BUCKET_ENTRIES))
    plan = spark.sparkContext.broadcast((counts, bucket_of, parts_of))

    asked = valid.where(is_query).select(F.col("vec_id").alias("query_id"), "k1", "k2").distinct()
    asked = cut(asked.join(entries.select("rep", "k1", "k2", "v"), ["k1", "k2"]).select("query_id", "rep", "v"))
    distinct = asked.groupBy(F.col("rep").alias("q")).agg(F.first("v").alias("qv"))

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, bucket_of, _ = plan.value
        for b in batches:
            for i, q in enumerate(b.column(1).to_pylist()):
                cells = np.array(shared.value.probe(np.array(q), counts, enough))
                buckets = bucket_of[cells]
                here = np.unique(buckets)
                yield pa.RecordBatch.from_arrays(
                    [pa.array([b.column(0)[i].as_py()] * len(here), pa.int64()), pa.array([q] * len(here), pa.list_(pa.float64())), pa.array(here, pa.int64()), pa.array([cells[buckets == x].tolist() for x in here], pa.list_(pa.int64())), pa.array(here == buckets[0])],
                    names=["q", "qv", "bucket", "cells", "best"],
                )

    probes = cut(distinct.mapInArrow(probe, "q long, qv array<double>, bucket long, cells array<long>, best boolean"))
    # queries that begin in the same bucket share blocks, so a block asks for few buckets where vectors have clusters
    begins, before = [], 0
    for r in sorted(probes.where("best").groupBy("bucket").count().collect(), key=lambda r: r.bucket):
        begins.append((r.bucket, before, r["count"]))
        before += r["count"]
    begins = spark.createDataFrame(begins, "bucket long, before long, many long")
    turn = F.floor((F.col("before") + F.pmod(F.xxhash64("q"), F.col("many"))) / BLOCK_QUERIES).alias("block")
    block_of = probes.where("best").select("q", "bucket").join(F.broadcast(begins), "bucket").select("q", turn)
    probes = cut(probes.drop("best").join(block_of, "q"))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        _, bucket_of, parts_of = plan.value
        for b in batches:
            cell = b.column(3).to_numpy()
            part = b.column(0).to_numpy() % parts_of[cell]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(bucket_of[cell]), pa.array(part)], names=[*b.schema.names, "bucket", "part"])

    dealt = placed.mapInArrow(deal, "rep long, ids array<long>, v array<double>, cell long, bucket long, part long")
    # an entry goes to the blocks that ask for its bucket only
    dealt = dealt.join(small(cut(probes.select("bucket", "block").distinct()).toDF("bucket", "block")), "bucket")
    widest = int(parts_of.max())
    probes = probes.withColumn("part", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(widest - 1).cast("long")))) if widest > 1 else probes.withColumn("part", F.lit(0).cast("long"))

    def rank(left: pa.Table, right: pa.Table) -> pa.Table:
        out = {"q": [], "rep": [], "ids": [], "score": []}
        if left.num_rows and right.num_rows:
            cell = left["cell"].to_numpy()
            order = np.argsort(cell, kind="stable")
            cell, reps = cell[order], left["rep"].to_numpy()[order]
            x = left["v"].combine_chunks().flatten().to_numpy().reshape(-1, dims)[order]
            names, first = np.unique(cell, return_index=True)
            spans = dict(zip(names.tolist(), zip(first.tolist(), [*first[1:].tolist(), len(cell)], strict=True), strict=True))
            q, qv, cells = right["q"].to_numpy(), right["qv"].combine_chunks().flatten().to_numpy().reshape(-1, dims), right["cells"].to_pylist()
            ids = left["ids"].to_pylist()
            for lo in range(0, len(q), BLOCK_SCORES):
                some = range(lo, min(lo + BLOCK_SCORES, len(q)))
                asks: dict[int, list[int]] = {}
                for i in some:
                    for c in cells[i]:
                        asks.setdefault(c, []).append(i)
                scores = np.full((len(some), len(cell)), -np.inf)
                for c, who in asks.items():
                    if c in spans:
                        a, b = spans[c]
                        scores[np.array(who)[:, None] - lo, np.arange(a, b)] = qv[who] @ x[a:b].T
                for i in some:
                    s = scores[i - lo]
                    if len(s) > n + 1:
                        least = np.partition(s, len(s) - n - 1)[len(s) - n - 1]
                        at = np.flatnonzero((s >= least) & (s > -np.inf))
                    else:
                        at = np.flatnonzero(s > -np.inf)
                    at = at[np.lexsort((reps[at], -s[at]))][: n + 1]
                    out["q"] += [int(q[i])] * len(at)
                    out["rep"] += reps[at].tolist()
                    out["ids"] += [ids[order[y]] for y in at]
                    out["score"] += (x[at] @ qv[i]).tolist()
        return pa.table({"q": pa.array(out["q"], pa.int64()), "rep": pa.array(out["rep"], pa.int64()), "ids": pa.array(out["ids"], pa.list_(pa.int64())), "score": pa.array(out["score"], pa.float64())})

    keys = ["bucket", "part", "block"]
    found = dealt.groupBy(*keys).cogroup(probes.groupBy(*keys)).applyInArrow(rank, "q long, rep long, ids array<long>, score double")
    best = Window.partitionBy("q").orderBy(F.col("score").desc(), "rep")
    found = found.withColumn("nth", F.row_number().over(best)).where(F.col("nth") <= n + 1)
    # at most n + 1 entries of n + 1 ids for each distinct query
    pairs = F.flatten(F.collect_list(F.transform("ids", lambda i: F.struct((-F.col("score")).alias("s"), i.alias("vec_id")))))
    lists = found.groupBy("q").agg(F.array_sort(pairs).alias("near"))
    own = F.slice(F.filter("near", lambda x: x["vec_id"] != F.col("query_id")), 1, n)
    out = asked.select("query_id", "rep").join(lists, F.col("rep") == F.col("q")).select("query_id", F.posexplode(own).alias("pos", "x"))
    return out.select("query_id", (F.col("pos") + 1).cast("int").alias("rank"), F.col("x.vec_id").alias("vec_id"), (-F.col("x.s") + F.lit(0.0)).alias("score"))


def op1_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return search(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"), F.col("vec_id") % 20 == 0)


QUERIES = {"op1_multi_index": op1_multi_index}
