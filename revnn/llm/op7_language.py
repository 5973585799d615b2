"""Language identification by error-correcting output codes.

Each language has a codeword; one binary classifier for each bit reads hashed byte trigrams of a text and predicts the
bit. A language's loss is the sum of its bits' logistic losses, weighted by how well each classifier did on rows that
it wasn't fitted on; the nearest codeword wins. A small margin to the next codeword flags the text as ambiguous.

Classifiers are fitted on the driver from a bounded sample of ``SAMPLE_ROWS`` different rows, shared evenly over the
languages: rows of smallest hash within each language, what a rare one leaves over goes to the others, and every
language has one row at least. Trigrams of the sample's whole texts are counted on the executors; only rows of BUCKETS
counts reach the driver. Prediction is one pass over the whole texts
with numpy inside Arrow batches (only the text goes in, only the answer comes out), without a shuffle; long texts go through in slices.

Defined cases: null text and text without a letter are ``und`` with score 0; rows without a language, a doc_id or
a letter teach nothing and equal rows teach once; with no labelled rows at all every text is ``und``; a single language is always predicted; repeated rows give
repeated results; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from revnn.llm.common import table

#: Rows of the sample, at most (or one for each language, where there are more of them).
SAMPLE_ROWS = 4000
BUCKETS = 1 << 13
SLICE = 1 << 20
AMBIGUOUS = 0.1


def has_letter(text: str | None) -> bool:
    """Whether some character is of a letter category (L*); numerals that look like letters are not."""
    return any(map(str.isalpha, text or ""))


def trigrams(text: str) -> np.ndarray:
    """Counts of hashed byte trigrams of the lower-cased text with white space as one blank, as BUCKETS floats."""
    counts = np.zeros(BUCKETS, np.int64)
    tail = b" "
    for i in range(0, len(text), SLICE):
        raw = tail + " ".join(re.split(r"[\s\d]+", text[i : i + SLICE].lower())).encode("utf-8", "surrogatepass") + b" " * (i + SLICE >= len(text))
        b = np.frombuffer(raw, np.uint8).astype(np.uint32)
        tail = raw[-2:]
        if len(b) > 2:
            h = (b[:-2] * np.uint32(0x9E3779B1) + b[1:-1] * np.uint32(0x85EBCA77) + b[2:] * np.uint32(0xC2B2AE3D)) * np.uint32(0x27D4EB2F)
            counts += np.bincount((h >> np.uint32(19)).astype(np.int64), minlength=BUCKETS)
    return counts


def row_of(counts: np.ndarray) -> np.ndarray:
    """Damped, unit-length features."""
    x = np.sqrt(counts.astype(np.float64))
    return (x / max(np.sqrt((x * x).sum()), 1e-12)).astype(np.float32)


def codewords(n: int, seed: int = 7) -> np.ndarray:
    """(n, bits) of -1 and 1: all splits of up to 5 languages, else random ones chosen for distance between words."""
    if n <= 1:
        return np.ones((n, 1), np.int8)
    if n <= 5:
        splits = np.arange(1, 2 ** (n - 1))
        return np.array([[1 if i == 0 else (1 if s >> (i - 1) & 1 == 0 else -1) for s in splits] for i in range(n)], np.int8)
    rng, best, far = np.random.default_rng(seed), None, -1
    for _ in range(200):
        c = rng.choice(np.array([-1, 1], np.int8), (n, 10 * int(np.ceil(np.log2(n)))))
        c = c[:, np.abs(c.sum(axis=0)) < n]
        apart = min((c[i] != c[j]).sum() for i in range(n) for j in range(i))
        if apart > far:
            best, far = c, apart
    return best


class Model:
    """Languages, their codewords, classifiers (bits x BUCKETS with bias) and the bits' weights."""

    def __init__(self, langs: list[str], code: np.ndarray, w: np.ndarray, bias: np.ndarray, weight: np.ndarray):
        self.langs, self.code, self.w, self.bias, self.weight = langs, code, w, bias, weight

    def losses(self, x: np.ndarray) -> np.ndarray:
        """Loss of each language, (rows, languages)."""
        f = x @ self.w.T + self.bias
        wrong = np.logaddexp(0, -f[:, None, :] * self.code[None])
        return (wrong * self.weight).sum(axis=2) / self.weight.sum()

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Index, score and margin for each row."""
        loss = self.losses(x) * self.code.shape[1]
        p = np.exp(-(loss - loss.min(axis=1, keepdims=True)))
        p /= p.sum(axis=1, keepdims=True)
        order = np.sort(p, axis=1)
        margin = order[:, -1] - order[:, -2] if p.shape[1] > 1 else order[:, -1]
        return p.argmax(axis=1), order[:, -1], margin


def fit(x: np.ndarray, langs: list[str], n: int, steps: int = 120, rate: float = 20.0) -> Model:
    """Logistic classifiers by accelerated gradient steps on all but the first `n` rows, which weigh the bits."""
    names = sorted(set(langs))
    code = codewords(len(names))
    at = {name: i for i, name in enumerate(names)}
    k = np.array([at[name] for name in langs])
    y = code[k].astype(np.float32)
    xs, ys = x[n:], y[n:]
    share = np.bincount(k[n:], minlength=len(names)).astype(np.float64)
    rare = (1 / share / len(names))[k[n:]].astype(np.float32)[:, None]
    rare /= rare.sum()
    w, bias = np.zeros((code.shape[1], BUCKETS), np.float32), np.zeros(code.shape[1], np.float32)
    v, c = w.copy(), bias.copy()
    for _ in range(steps):
        g = -ys * rare / (1 + np.exp(ys * (xs @ w.T + bias)))
        v = 0.9 * v - rate * (g.T @ xs + 1e-5 * w)
        c = 0.9 * c - rate * g.sum(axis=0)
        w, bias = w + v, bias + c
    right = ((x[:n] @ w.T + bias) * y[:n] > 0).mean(axis=0) if n else np.ones(code.shape[1])
    return Model(names, code, w, bias, np.maximum(right - 0.5, 0.01))


def level_of(sizes: list[int], rows: int) -> int:
    """The most rows of each language such that all together are at most `rows`; at least 1."""
    left, many = rows, len(sizes)
    for size in sorted(sizes):
        if size * many > left:
            return max(left // many, 1)
        left, many = left - size, many - 1
    return max(sizes)


def _count_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        packed = [zlib.compress(trigrams(t.as_py()).astype("<u4").tobytes(), 1) for t in batch.column(2)]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(packed, pa.binary())], names=["lang", "draw", "counts"])


def up_to(rows: DataFrame, last: dict[str, int]) -> DataFrame:
    """Rows whose draw is at most that of their language."""
    bounds = rows.sparkSession.createDataFrame(list(last.items()), "lang string, last long")
    return rows.join(F.broadcast(bounds), "lang").where(F.col("draw") <= F.col("last")).drop("last")


def learn(docs: DataFrame, rows: int = SAMPLE_ROWS) -> Model | None:
    """Fits on rows that aren't held out: in each language those of smallest hash, at most `rows` in all."""
    known = docs.where(F.col("lang").isNotNull() & F.rlike("text", F.lit(r"\p{L}")) & F.col("doc_id").isNotNull() & ~held_out())
    known = known.select("lang", F.xxhash64(F.lit(11), "doc_id", "lang", "text").alias("draw"), "text")
    sizes = {r.lang: r.n for r in known.groupBy("lang").agg(F.approx_count_distinct("draw").alias("n")).collect()}
    if not sizes:
        return None
    level = level_of(list(sizes.values()), rows)
    # draws spread evenly over all longs: twice the rows that are needed and some more come to the driver, as numbers
    wide = {lang: min(-(1 << 63) + (1 << 64) * (2 * level + 20) // n, (1 << 63) - 1) for lang, n in sizes.items()}
    draws = defaultdict(list)
    for r in up_to(known.select("lang", "draw"), wide).distinct().collect():
        draws[r.lang].append(r.draw)
    chosen = {lang: sorted(found)[:level] for lang, found in sorted(draws.items())}
    # every fifth row of a language first: both parts are views of one matrix
    order = sorted(((lang, d, i % 5 != 4) for lang, found in chosen.items() for i, d in enumerate(found)), key=lambda r: r[2])
    at = {(lang, d): i for i, (lang, d, _) in enumerate(order)}
    x = np.zeros((len(order), BUCKETS), np.float32)
    texts = up_to(known, {lang: found[-1] for lang, found in chosen.items()}).dropDuplicates(["lang", "draw"])
    for r in texts.select("lang", "draw", "text").mapInArrow(_count_rows, "lang string, draw long, counts binary").collect():
        x[at[r.lang, r.draw]] = row_of(np.frombuffer(zlib.decompress(r.counts), "<u4"))
    return fit(x, [lang for lang, *_ in order], sum(not late for *_, late in order))


def held_out():
    return F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, F.lit(False))


def identify(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score, ambiguous for every row; further columns of `docs` are kept."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("lang string, score double, ambiguous boolean")
    def tell(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        m = shared.value
        for part in parts:
            out = []
            for t in part:
                if m and has_letter(t):
                    # a row at a time: equal texts give equal sums, whatever stands beside them
                    k, p, gap = m.predict(row_of(trigrams(t))[None])
                    out.append((m.langs[k[0]], float(p[0]), bool(gap[0] < AMBIGUOUS)))
                else:
                    out.append(("und", 0.0, False))
            yield pd.DataFrame(out, columns=["lang", "score", "ambiguous"])

    # only the text goes to Python and only the answer comes back; not deterministic, so that it runs once for a row
    kept = [F.col(f"`{c}`") for c in docs.columns if c not in ("held_out", "lang_pred", "score", "ambiguous")]
    d = docs.select(*kept, held_out().alias("held_out"), tell.asNondeterministic()("text").alias("_told"))
    return d.select(*kept, "held_out", F.col("_told.lang").alias("lang_pred"), F.col("_told.score").alias("score"), F.col("_told.ambiguous").alias("ambiguous"))


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return identify(docs.select("doc_id", "text"), learn(docs)).select("doc_id", "held_out", "lang_pred", "score", "ambiguous")


QUERIES = {"op7_language_id": op7_language_id}
