"""Near-duplicate documents: fast similarity sketches, banding, exact verification, components.

Sketch: rounds of hashing throw every shingle into one of T bins; a bin keeps the smallest value of the first round
that reaches it, and after T rounds a last pass visits the bins one by one, so that every coordinate is filled however
small the set, and the share of equal coordinates is concentrated around the similarity. Bands of four coordinates make
bucket keys; at similarity 0.8 a pair misses all 32 bands with probability 5e-8.

Documents with equal sets are one class from the start (a digest of the sorted set), so copies are never paired. Links
between classes are found without listing the pairs of a bucket:

1. every bucket has a hub; a class is verified against the hub that it shares most buckets with;
2. classes still apart from other hubs of their buckets are verified against these;
3. classes apart from their bucket's commonest label are verified against a few classes drawn from it;
4. what shares a bucket and is apart even then is compared pair by pair, inside the join condition.

A pair is verified only if sizes and parities of the sets allow a link (both are exact bounds, so no link is lost); no
text moves before that test. Classes that are connected already are never compared again. Verification computes both
full sets of shingles and counts 100 * shared >= 80 * union. Components: links contracted to labels, smallest label
spread with pointer jumps. All joins are by bucket key or class id, may be split where skewed, and no bucket is
gathered into one task. Tables that no later step reads are emptied at once, and so are shuffle files.

Defined cases: null text or text without words has an empty set and is its own component; one word is a set of one;
null doc_ids are kept (a component of null ids only has a null id; `kept` is false there unless null-safe equal);
repeated ids with different texts are different documents that share an id; an empty table gives an empty result;
further columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from revnn.llm.common import Work, batches_of, cut, fixed_filter, table

T, BAND = 128, 4
BANDS = T // BAND
#: Classes of a bucket's commonest label that others meet.
DRAWS = 3
WORDS_IN_SHINGLE, PERCENT = 2, 80
#: Bytes of texts that are hashed at once, and rows of an Arrow batch (two texts each).
SLICE, BATCH = 1 << 19, 500
U = np.uint64
BASE = 0x9E3779B97F4A7C15 | 1
PARITY = [f"p{i}" for i in range(16)]
SKETCHES = "doc_id long, th long, n long, gid binary, bands array<long>, " + ", ".join(f"{p} long" for p in PARITY)
#: Copies of a class that one salt takes, at most about.
SALTED = 10_000


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words that spreads every bit."""
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


SEEDS = mix(np.arange(1, 2 * T + 1, dtype=U) * U(BASE))


class Powers:
    """Powers of the base and of its inverse modulo 2**64, for positions in a buffer."""

    def __init__(self):
        self.up = self.down = np.ones(1, U)

    def to(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            for name, base in (("up", BASE), ("down", pow(BASE, -1, 1 << 64))):
                x = np.full(n, base, U)
                x[0] = 1
                setattr(self, name, np.multiply.accumulate(x))
        return self.up[:n], self.down[:n]


POWERS = Powers()


def word_hashes(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Start and 64-bit hash of each word of a buffer of bytes, A-Z lower-cased."""
    raw = np.where((raw >= 65) & (raw <= 90), raw + np.uint8(32), raw)
    gap = np.concatenate([[True], (raw == 32) | ((raw >= 9) & (raw <= 13)), [True]])
    edge = np.flatnonzero(gap[1:] != gap[:-1])
    start, end = edge[::2], edge[1::2]
    up, down = POWERS.to(len(raw) + 1)
    total = np.zeros(len(raw) + 1, U)
    np.cumsum((raw.astype(U) + U(1)) * up[:-1], out=total[1:])
    return start, mix((total[end] - total[start]) * down[start] + (end - start).astype(U) * U(0xD6E8FEB86659FD93))


def pieces(text: bytes) -> Iterator[bytes]:
    """A long text in slices that no word crosses."""
    at = 0
    while len(text) - at > SLICE:
        found = [x for x in (text.rfind(s, at, at + SLICE) for s in (b" ", b"\n")) if x > at]
        if not found:
            found = [min([x for x in (text.find(s, at + SLICE) for s in (b" ", b"\n")) if x >= 0], default=len(text))]
        yield text[at : max(found)]
        at = max(found)
    yield text[at:]


def join_words(words: np.ndarray, k: int = WORDS_IN_SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of all runs of k words; fewer words are one run."""
    if len(words) == 0:
        return words
    k = min(k, len(words))
    h = np.full(len(words) - k + 1, k, U)
    for i in range(k):
        h = mix(h * U(0x9FB21C651E98DF25) + words[i : len(words) - k + 1 + i])
    return np.unique(h)


def sets_of(texts: list[str | None], k: int = WORDS_IN_SHINGLE) -> list[np.ndarray]:
    """The set of shingle hashes of each text; texts share a buffer."""
    out: list = [None] * len(texts)
    held, size = [], 0

    def flush() -> None:
        nonlocal held, size
        if held:
            start, words = word_hashes(np.frombuffer(b"\n".join(t for _, t in held), np.uint8))
            ends = np.cumsum([len(t) + 1 for _, t in held])
            for (i, _), w in zip(held, np.split(words, np.searchsorted(start, ends[:-1])), strict=True):
                out[i] = join_words(w, k)
        held, size = [], 0

    for i, t in enumerate(texts):
        data = (t or "").encode("utf-8", "surrogatepass")
        if len(data) > SLICE:
            out[i] = join_words(np.concatenate([word_hashes(np.frombuffer(p, np.uint8))[1] for p in pieces(data)]), k)
            continue
        held.append((i, data))
        size += len(data)
        if size > SLICE:
            flush()
    flush()
    return out


def sketch(s: np.ndarray) -> np.ndarray:
    """T coordinates of a non-empty set."""
    out, empty = np.zeros(T, U), np.ones(T, bool)
    none = U(0xFFFFFFFFFFFFFFFF)
    for r in range(T):
        h = mix(s ^ SEEDS[r])
        least = np.full(T, none, U)
        np.minimum.at(least, (h & U(T - 1)).astype(np.intp), h >> U(7))
        new = empty & (least != none)
        out[new] = least[new] + (U(r) << U(57))
        empty &= ~new
        if not empty.any():
            return out
    for b in np.flatnonzero(empty):
        out[b] = (mix(s ^ SEEDS[T + b]) >> U(7)).min() + (U(T - 1) << U(57))
    return out


def band_keys(c: np.ndarray) -> np.ndarray:
    h = np.arange(BANDS, dtype=U)
    for i in range(BAND):
        h = mix(h * U(0x9FB21C651E98DF25) + c.reshape(BANDS, BAND)[:, i])
    return h.view(np.int64)


def parity(s: np.ndarray) -> np.ndarray:
    """1024 bits, each the parity of the set's elements that fall on it: sets differ in no fewer elements than bits."""
    return np.packbits(np.bincount((s >> U(20)).astype(np.int64) & 1023, minlength=1024) & 1).view(np.int64)


def digest(s: np.ndarray) -> bytes:
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


def _sketch_rows(k: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in SKETCHES.split(", ")]
        for batch in batches:
            for first in range(0, batch.num_rows, 1024):
                part = batch.slice(first, 1024)
                gids, bands, bits, n = [], [], [], []
                for s in sets_of(part.column(1).to_pylist(), k):
                    n.append(len(s))
                    if len(s):
                        gids.append(digest(s))
                        bands.append(band_keys(sketch(s)))
                        bits.append(parity(s))
                    else:
                        gids.append(None)
                        bands.append(None)
                        bits.append(np.zeros(len(PARITY), np.int64))
                columns = [part.column(0), part.column(2), pa.array(n, pa.int64()), pa.array(gids, pa.binary()), pa.array(bands, pa.list_(pa.int64()))]
                yield pa.RecordBatch.from_arrays([*columns, *(pa.array(x) for x in np.array(bits, np.int64).reshape(-1, len(PARITY)).T.copy())], names=names)

    return run


def with_text_hash(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "text", F.xxhash64("text").alias("th"))


def may_link(a: str, b: str, percent: int) -> Column:
    """False only for pairs that sizes or parities rule out (exact bounds)."""
    n, m = F.col(f"{a}.n"), F.col(f"{b}.n")
    differ = sum((F.bit_count(F.col(f"{a}.{p}").bitwiseXOR(F.col(f"{b}.{p}"))) for p in PARITY), F.lit(0))
    return (100 * F.least(n, m) >= percent * F.greatest(n, m)) & (differ * (100 + percent) <= (100 - percent) * (n + m))


def verify(pairs: DataFrame, texts: DataFrame, k: int, percent: int) -> DataFrame:
    """The pairs (a, b) of class ids whose full sets are similar enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first in range(0, batch.num_rows, 256):
                a, b, x, y = (c.to_pylist() for c in batch.slice(first, 256).columns)
                # a hub meets many classes: its set is made once
                hubs = dict(zip(b, y, strict=True))
                hubs = dict(zip(hubs, sets_of(list(hubs.values()), k), strict=True))
                keep = []
                for i, (p, q) in enumerate(zip(sets_of(x, k), (hubs[i] for i in b), strict=True)):
                    shared = len(np.intersect1d(p, q, assume_unique=True))
                    if 100 * shared >= percent * (len(p) + len(q) - shared):
                        keep.append(i)
                yield pa.RecordBatch.from_arrays([pa.array([a[i] for i in keep], pa.binary()), pa.array([b[i] for i in keep], pa.binary())], names=["a", "b"])

    x, y = texts.select(F.col("gid").alias("a"), F.col("text").alias("x")), texts.select(F.col("gid").alias("b"), F.col("text").alias("y"))
    return pairs.join(x, "a").join(y, "b").select("a", "b", "x", "y").mapInArrow(run, "a binary, b binary")


def contract(links: DataFrame) -> DataFrame:
    """Links (a, b) -> (node, label) for every node of a link: the smallest node of its component."""
    both = cut(links.select("a", "b").union(links.select("b", "a")).where("a != b").distinct())
    labels = both.groupBy(F.col("a").alias("node")).agg(F.least(F.first("a"), F.min("b")).alias("label"))
    while True:
        near = both.join(labels, both["b"] == labels["node"]).groupBy("a").agg(F.min("label").alias("near"))
        new = labels.join(near, labels["node"] == near["a"]).select("node", F.least("label", "near").alias("new"), F.col("label").alias("old"))
        jump = new.select(F.col("node").alias("via"), F.col("new").alias("far"))
        new = cut(new.join(jump, new["new"] == jump["via"], "left").select("node", F.least("new", "far").alias("label"), "old"))
        done = new.where("label != old").isEmpty()
        labels = new.select("node", "label")
        if done:
            return labels


def relabel(labels: DataFrame, links: DataFrame) -> DataFrame:
    """labels (gid, label) after links (a, b) between class ids."""
    if links.isEmpty():
        return labels
    named = links.join(labels.select(F.col("gid").alias("a"), F.col("label").alias("la")), "a").join(labels.select(F.col("gid").alias("b"), F.col("label").alias("lb")), "b")
    moved = contract(named.select(F.col("la").alias("a"), F.col("lb").alias("b")))
    return cut(labels.join(moved, labels["label"] == moved["node"], "left").select("gid", F.coalesce(moved["label"], labels["label"]).alias("label")))


def near_duplicates(docs: DataFrame, k: int = WORDS_IN_SHINGLE, percent: int = PERCENT) -> DataFrame:
    """doc_id, th, n_shingles, component_id, kept, label for every row of `docs` (doc_id, text).

    th is the text's hash, label names the component (null for empty sets)."""
    work = Work(docs.sparkSession, "near-duplicates")
    with batches_of(docs.sparkSession, BATCH):
        rows = work.keep(with_text_hash(docs).mapInArrow(_sketch_rows(k), SKETCHES))
        classes = work.keep(rows.where("gid is not null").groupBy("gid").agg(F.min(F.struct("doc_id", "th")).alias("one"), F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("copies"), *(F.first(c).alias(c) for c in ("bands", "n", *PARITY))))
        rows = rows.select("doc_id", "th", "n", "gid")
        found = components(docs, classes, k, percent, work)
    # only classes with links share a label; the others need no second look
    named = classes.select("gid", "least", "copies").join(found, "gid", "left").withColumn("label", F.coalesce("label", "gid"))
    linked = named.groupBy("label").agg(F.min("least").alias("component"))
    named = work.keep(named.join(linked, "label").select("gid", "component", "label", F.ceil(F.col("copies") / SALTED).cast("int").alias("salts")))
    work.drop(classes)
    # a class of many copies has as many salts as its copies need; the broadcast holds only such classes
    many = F.broadcast(named.where("salts > 1").select("gid", "salts")) if named.where("salts > 1").limit(SALTED + 1).count() <= SALTED else named.where("salts > 1").select("gid", "salts")
    salted = named.select("gid", "component", "label", F.explode(F.sequence(F.lit(0), F.col("salts") - 1)).alias("salt"))
    d = rows.join(many, "gid", "left").withColumn("salt", F.pmod(F.xxhash64("doc_id", "th"), F.coalesce("salts", F.lit(1))).cast("int"))
    d = d.join(salted, ["gid", "salt"], "left").withColumn("component_id", F.when(F.col("gid").isNull(), F.col("doc_id")).otherwise(F.col("component")))
    return d.select("doc_id", "th", F.col("n").alias("n_shingles"), "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(False)).alias("kept"), "label")


def components(docs: DataFrame, classes: DataFrame, k: int, percent: int, work: Work) -> DataFrame:
    """(gid, label) of every class that shares a bucket with another one."""
    bucket = ["band", "key"]
    entries = classes.select("gid", F.posexplode("bands").alias(*bucket))
    # kept before the join, so that both sides are exchanged and a frequent bucket can be split
    size = work.keep(entries.groupBy(*bucket).agg(F.count(F.lit(1)).alias("size"), F.max("gid").alias("hub")).where("size > 1").select(*bucket, "hub"))
    entries = work.keep(entries.join(size, bucket).select(*bucket, "gid", "hub"))
    work.drop(size)
    own = cut(entries.select("gid").distinct())
    texts = work.keep(texts_of(docs, classes.join(own, "gid", "left_semi").select("gid", "one.doc_id", "one.th")))

    look = classes.select("gid", "n", "bands", *PARITY)
    of = lambda side: look.select(F.col("gid").alias(side), F.struct("n", *PARITY).alias(f"{side}_s"))
    possible = lambda pairs: pairs.join(of("a"), "a").join(of("b"), "b").where(may_link("a_s", "b_s", percent)).drop("a_s", "b_s")

    shared = entries.where("gid != hub").groupBy(F.col("gid").alias("a"), F.col("hub").alias("b")).agg(F.count(F.lit(1)).alias("bands"))
    best = possible(shared).withColumn("nth", F.row_number().over(Window.partitionBy("a").orderBy(F.col("bands").desc(), "b")))
    hubs = cut(best.select("a", "b", "nth"))
    links = cut(verify(hubs.where("nth = 1").select("a", "b"), texts, k, percent))
    # a hub is the largest id of its bucket, so these links are a forest; two steps up are near enough to a root here
    up = own.join(links, own["gid"] == links["a"], "left").select("gid", F.coalesce("b", "gid").alias("to"))
    root = up.select(F.col("gid").alias("via"), F.col("to").alias("root"))
    near = up.join(root, up["to"] == root["via"]).select("gid", "root")
    known = lambda side: near.select(F.col("gid").alias(side), F.col("root").alias(f"{side}_root"))
    rest = hubs.where("nth > 1").join(known("a"), "a").join(known("b"), "b").where("a_root != b_root").select("a", "b")
    links = cut(links.union(verify(rest, texts, k, percent)))
    labels = relabel(own.withColumn("label", F.col("gid")), links)

    def still_mixed(seen: DataFrame) -> DataFrame:
        """Entries, with labels, of buckets that hold several."""
        named = work.keep(seen.select(*bucket, "gid").join(labels, "gid"))
        mixed = work.keep(named.groupBy(*bucket).agg(F.min("label").alias("least"), F.max("label").alias("most")).where("least != most").select(*bucket))
        out = work.keep(named.join(mixed, bucket, "left_semi"))
        work.drop(named, mixed)
        return out

    # what is apart from its bucket's commonest label meets a few of that label's classes, drawn anew for each bucket
    named = still_mixed(entries)
    work.drop(entries)
    common = named.groupBy(*bucket, "label").agg(F.count(F.lit(1)).alias("n"), *(F.max_by("gid", F.xxhash64(F.lit(i), "gid", "band")).alias(f"h{i}") for i in range(DRAWS)))
    common = common.groupBy(*bucket).agg(F.max(F.struct("n", "label", F.array(*(f"h{i}" for i in range(DRAWS))).alias("hubs"))).alias("top")).select(*bucket, "top.label", "top.hubs")
    drawn = named.alias("x").join(common.alias("y"), (F.col("x.band") == F.col("y.band")) & (F.col("x.key") == F.col("y.key")) & (F.col("x.label") != F.col("y.label")))
    drawn = drawn.select("x.gid", F.explode("y.hubs").alias("hub")).select(F.least("gid", "hub").alias("a"), F.greatest("gid", "hub").alias("b")).distinct()
    drawn = cut(possible(drawn.join(hubs.select("a", "b"), ["a", "b"], "left_anti")))
    labels = relabel(labels, cut(verify(drawn, texts, k, percent)))

    open_ = still_mixed(named)
    work.drop(named)
    x, y = open_.join(look, "gid").alias("x"), open_.join(look, "gid").alias("y")
    on = (F.col("x.band") == F.col("y.band")) & (F.col("x.key") == F.col("y.key")) & (F.col("x.gid") < F.col("y.gid")) & (F.col("x.label") != F.col("y.label"))
    # a pair is made in the first band that it shares only
    before = lambda side: F.slice(f"{side}.bands", F.lit(1), F.col("x.band"))
    first = ~F.exists(F.zip_with(before("x"), before("y"), lambda p, q: p == q), lambda same: same)
    pairs = x.join(y, on & may_link("x", "y", percent) & first).select(F.col("x.gid").alias("a"), F.col("y.gid").alias("b"))
    done = hubs.select("a", "b").union(drawn)  # a < b: a hub is the largest of its bucket
    pairs = cut(pairs.join(done, ["a", "b"], "left_anti"))
    work.drop(open_)
    labels = relabel(labels, cut(verify(pairs, texts, k, percent)))
    work.drop(texts)
    return labels


def texts_of(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """gid and text of the wanted (gid, doc_id, th)."""
    name = lambda d: d.withColumn("_id", F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))).drop("doc_id")
    wanted = cut(name(wanted))
    # equal rows are equal texts: each task passes on one of them
    source = fixed_filter(wanted, "_id", "th")(name(with_text_hash(docs)), "needed").where("needed")
    return source.groupBy("_id", "th").agg(F.first("text").alias("text")).join(wanted, ["_id", "th"]).select("gid", "text")


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id", "kept")


QUERIES = {"op8_near_duplicates": op8_near_duplicates}
