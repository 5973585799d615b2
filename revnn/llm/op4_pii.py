"""Personal data: exact base spans, high-recall candidates, boosted trees, calibrated thresholds. DataFrame functions only.

All spans of a text are found inside its own row. Hits of an expression and the gaps between them come from the two
functions that share its matching (extract-all and split); starts are running sums of their lengths, in code points.
Expressions never retry inside a run that has failed (possessive runs that begin at a run's first character or where
the last hit ended), so long runs of digits or letters cost linear time.

Beyond the base rules, generous generators propose spans in what the base spans leave over. Trees, written as nested
CASE expressions, score each candidate by format (length, digits, groups, separators, letters) and context (cue words
before it, neighbours); spans at or above the threshold are added. The trees are fitted on the driver from a bounded
sample (``SAMPLE_DOCS`` documents of smallest hash that hold a digit or an @, ``SAMPLE_SPANS`` of their spans): base
spans teach what such data look like, candidates that no base rule accepts are the contrast; what makes the base rules
decisive (the plus sign, check digits, ranges) is no feature. Candidates after a cue word of their kind teach as base
spans do (the cue only labels: it is no feature of the trees, so a format counts by how often cues stand before it).
Other candidates count as unlabelled, not as wrong: a third of
the sample is held out, the mean probability that its labelled spans get tells which share of true spans is
labelled, and the expected count of labelled spans at or above a score, over that share, is the expected count of true ones.
The threshold is the lowest score at which at least ``PRECISION`` of the held-out spans are true by this estimate (it
takes labelled and other true spans to look alike in the features). A kind with few held-out labelled spans takes the
share of all kinds together.

Defined cases: null text is empty: no spans; texts of any length are read whole; if the sample holds no example of
either kind, or fewer than 6 * ``LEAST_LEAF`` spans in all (too few for a leaf on each side and a held-out part), nothing
is added; repeated rows give repeated results; an empty table gives an empty result; further
columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from revnn.llm.common import bind, prefix_sums, table

KINDS = ("email", "ip", "card", "phone")
LOCAL = "[A-Za-z0-9._%+-]"
#: The contract's expressions, written so that no run is tried twice.
BASE = {
    "email": rf"(?:(?<!{LOCAL})|\G){LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Proposals of each kind: spelled-out addresses, other separators, no plus sign. Their counts bound what is proposed as
#: one span (mail's 64 letters before the @ and 63 in a label, groups of digits of usual length), never which part of a
#: text is read; base spans have no such bounds.
LOOSE = {
    "email": rf"(?<!{LOCAL}){LOCAL}{{1,64}}+(?: ?[(\[{{]at[)\]}}] ?| at |@)[A-Za-z0-9-]{{1,63}}+(?:(?: ?[(\[{{]dot[)\]}}] ?| dot |\.)[A-Za-z0-9-]{{1,63}}+){{1,6}}+",
    "ip": r"(?<![0-9])[0-9]{1,3}+(?:(?:\[\.\]|\(\.\)|\[dot\]| \. )[0-9]{1,3}+){3}+(?![0-9])|(?<![0-9A-Za-z:])(?:[0-9A-Fa-f]{1,4}+:){4,7}+:?[0-9A-Fa-f]{1,4}+(?![0-9A-Za-z:])",
    "card": r"(?<![0-9])[0-9]{3,6}+(?:[ ./_-]{1,2}+[0-9]{3,6}+){2,5}+(?![0-9])|(?<![0-9A-Za-z])[0-9]{12,19}+(?![0-9A-Za-z])",
    "phone": r"(?<![0-9A-Za-z])(?:00|\+)?+\(?[0-9]{1,4}+\)?+(?:[ ./-]{1,2}+\(?[0-9]{2,5}+\)?+){1,5}+(?![0-9A-Za-z])",
}
CUES = {"email": r"mail|contact|write to|reach", "ip": r"\bip\b|host|server|addr|from", "card": r"card|visa|credit|master|amex|account|iban", "phone": r"phone|tel|call|fax|mobile|cell|dial|whatsapp"}
#: Characters before a candidate that cue words are looked for in.
CONTEXT = 24
FILL = "￼"
SAMPLE_DOCS, SAMPLE_SPANS, PRECISION = 3000, 30_000, 0.97
TREES, DEPTH, RATE, LEAST_LEAF = 24, 3, 0.3, 10
#: The feature that labels candidates.
CUE = 11
NONE = "array<struct<start:bigint,ord:int,end:bigint,hit:string,before:string,after:string>>"


def digits(hit: Column) -> Column:
    return F.regexp_replace(hit, "[^0-9]", "")


def luhn(d: Column) -> Column:
    """The check-digit rule, for up to 19 digits."""
    padded = F.lpad(d, 19, "0")
    value = lambda i: F.instr(F.when(i % 2 == 0, F.lit("0516273849")).otherwise(F.lit("0123456789")), F.substring(padded, i, F.lit(1))) - 1
    return F.aggregate(F.sequence(F.lit(1), F.lit(19)), F.lit(0), lambda s, i: s + value(i)) % 10 == 0


def valid(kind: str, hit: Column) -> Column:
    if kind == "ip":
        short = lambda p: F.ltrim(p, F.lit("0"))
        return F.forall(F.split(hit, r"\."), lambda p: (F.length(short(p)) < 3) | ((F.length(short(p)) == 3) & (short(p) <= "255")))
    if kind == "card":
        return bind(digits(hit), lambda d: F.when(F.length(d).between(12, 19), luhn(d)).otherwise(F.lit(False)))
    if kind == "phone":
        return F.length(digits(hit)).between(9, 15)
    return F.lit(True)


def hits_of(text: Column, pattern: str) -> Column:
    """struct<hits, gaps>: the matches and the texts around them; one gap more than hits."""
    return F.struct(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hits"), F.split(text, pattern, -1).alias("gaps"))


def spans_of(q: Column, ord_: int) -> Column:
    """Places of the hits with what stands around them."""
    lengths = F.zip_with(q["hits"], F.slice(q["gaps"], F.lit(1), F.size(q["hits"])), lambda h, g: (F.length(h) + F.length(g)).cast("long"))
    one = lambda h, i, at: F.struct(at.alias("start"), F.lit(ord_).alias("ord"), (at + F.length(h)).alias("end"), h.alias("hit"), F.right(q["gaps"][i], F.lit(CONTEXT)).alias("before"), F.left(q["gaps"][i + 1], F.lit(1)).alias("after"))
    return bind(prefix_sums(lengths), lambda p: F.transform(q["hits"], lambda h, i: bind(p[i] + F.length(q["gaps"][i]), lambda at: one(h, i, at))))


def placed(text: Column, pattern: str, ord_: int) -> Column:
    return bind(hits_of(text, pattern), lambda q: spans_of(q, ord_))


def passing(kind: str):
    return lambda s: valid(kind, s["hit"])


def masked(kind: str, text: Column) -> Column:
    """The text with valid hits covered, character for character."""
    return bind(text, lambda t: bind(hits_of(t, BASE[kind]), lambda q: covered(kind, q)))


def covered(kind: str, q: Column) -> Column:
    filled = F.transform(q["hits"], lambda h: F.when(valid(kind, h), F.repeat(F.lit(FILL), F.length(h))).otherwise(h))
    return F.array_join(F.zip_with(q["gaps"], filled, lambda g, h: F.concat(g, F.coalesce(h, F.lit("")))), "")


def gate(kind: str, text: Column) -> Column:
    """False only where the base expression can't match."""
    return {"email": F.contains(text, F.lit("@")), "phone": F.contains(text, F.lit("+"))}.get(kind, F.col("has_digit"))


def base_spans(docs: DataFrame) -> DataFrame:
    """`docs` (with text) and its base spans by kind, b_<kind>, and has_digit."""
    d = docs.withColumn("text", F.coalesce("text", F.lit("")))
    d = d.withColumn("has_digit", F.rlike("text", F.lit("[0-9]")))
    found = {}
    for n, kind in enumerate(KINDS):
        spans = F.filter(placed(F.col("text"), BASE[kind], n), passing(kind))
        found[f"b_{kind}"] = F.when(gate(kind, F.col("text")), spans).otherwise(F.array().cast(NONE))
    return d.withColumns(found)


def candidates(d: DataFrame) -> DataFrame:
    """Adds c_<kind>, the proposals in what base spans leave over; `d` as of :func:`base_spans`."""
    d = d.withColumn("rest", F.col("text"))
    for kind in KINDS:
        d = d.withColumn("rest", F.when(F.size(f"b_{kind}") > 0, masked(kind, F.col("rest"))).otherwise(F.col("rest")))
    maybe = {"email": F.rlike("text", F.lit("@|[(\\[{ ]at[)\\]} ]")), "ip": F.col("has_digit") | F.rlike("text", F.lit("[0-9A-Fa-f]:[0-9A-Fa-f]")), "card": F.col("has_digit"), "phone": F.col("has_digit")}
    return d.withColumns({f"c_{k}": F.when(maybe[k], placed(F.col("rest"), LOOSE[k], n)).otherwise(F.array().cast(NONE)) for n, k in enumerate(KINDS)})


def features(kind: str, s: Column) -> list[Column]:
    """Numbers that describe a span; none of them is what the base rules decide by."""
    hit = s["hit"]
    d, n = F.length(digits(hit)), F.length(hit)
    groups = F.size(F.split(hit, "[^0-9A-Za-z]+"))
    return [
        n.cast("double"), d.cast("double"), (d / F.greatest(n, F.lit(1))).cast("double"), groups.cast("double"),
        F.length(F.regexp_replace(hit, r"[0-9A-Za-z]", "")).cast("double"), F.length(F.regexp_replace(hit, "[^.]", "")).cast("double"),
        F.length(F.regexp_replace(hit, "[^ -]", "")).cast("double"), F.contains(hit, F.lit("(")).cast("double"),
        F.length(F.element_at(F.split(hit, "[^0-9A-Za-z]+"), -1)).cast("double"), F.length(F.element_at(F.split(F.ltrim(hit, F.lit("+")), "[^0-9A-Za-z]+"), 1)).cast("double"),
        F.size(F.array_distinct(F.split(digits(hit), ""))).cast("double"), F.rlike(F.lower(s["before"]), F.lit(CUES[kind])).cast("double"),
        F.rlike(s["before"], F.lit(r"[0-9A-Za-z=\"]$")).cast("double"), F.rlike(s["after"], F.lit(r"[0-9A-Za-z=\"%]")).cast("double"),
        *(F.lit(float(k == kind)) for k in KINDS),
    ]


def sample(docs: DataFrame, n_docs: int = SAMPLE_DOCS, n_spans: int = SAMPLE_SPANS) -> list[tuple[str, tuple, int]]:
    """kind, features, 1 for base spans: at most n_spans spans of at most n_docs documents."""
    d = docs.select("text", F.xxhash64(F.lit(5), "text").alias("draw")).where(F.rlike("text", F.lit("[0-9@]")))
    last = d.select("draw").orderBy("draw").limit(n_docs).agg(F.max("draw")).first()[0]
    if last is None:
        return []
    d = candidates(base_spans(d.where(F.col("draw") <= last).limit(n_docs)))
    example = lambda k, y: lambda s: F.struct(F.lit(k).alias("kind"), F.array(*features(k, s)).alias("x"), F.lit(y).alias("y"))
    told = F.flatten(F.array(*(F.transform(f"{p}_{k}", example(k, y)) for k in KINDS for p, y in (("b", 1), ("c", 0)))))
    rows = d.select(F.explode(told).alias("s")).select("s.*").orderBy(F.xxhash64("kind", "x", "y")).limit(n_spans).collect()
    return [(r.kind, tuple(r.x), r.y) for r in rows]


def grow(x: np.ndarray, g: np.ndarray, h: np.ndarray, depth: int):
    """A regression tree as nested (feature, threshold, below, above) or a number."""
    best = (1e-6, None)
    if depth and len(g) >= 2 * LEAST_LEAF:
        whole = g.sum() ** 2 / (h.sum() + 1)
        for f in range(x.shape[1]):
            for t in np.unique(np.quantile(x[:, f], np.linspace(0.05, 0.95, 15))):
                low = x[:, f] <= t
                if LEAST_LEAF <= low.sum() <= len(g) - LEAST_LEAF:
                    gain = g[low].sum() ** 2 / (h[low].sum() + 1) + g[~low].sum() ** 2 / (h[~low].sum() + 1) - whole
                    if gain > best[0]:
                        best = (gain, (f, float(t)))
    if best[1] is None:
        return float(RATE * g.sum() / (h.sum() + 1))
    f, t = best[1]
    low = x[:, f] <= t
    return f, t, grow(x[low], g[low], h[low], depth - 1), grow(x[~low], g[~low], h[~low], depth - 1)


def value(tree, x: np.ndarray) -> np.ndarray:
    if isinstance(tree, float):
        return np.full(len(x), tree)
    f, t, low, high = tree
    return np.where(x[:, f] <= t, value(low, x), value(high, x))


def fit(spans: list[tuple[str, tuple, int]], precision: float = PRECISION) -> tuple[list, dict[str, float]] | None:
    """Trees over the spans of all kinds and each kind's calibrated threshold; None if one class is missing."""
    if not 0 < sum(b or a[CUE] > 0 for _, a, b in spans) < len(spans) or len(spans) < 6 * LEAST_LEAF:
        return None
    kinds, x = np.array([k for k, *_ in spans]), np.array([a for _, a, _ in spans])
    y = np.array([float(b or a[CUE] > 0) for _, a, b in spans])
    x[:, CUE] = 0
    aside = np.arange(len(y)) % 3 == 2
    f, trees = np.zeros((~aside).sum()), []
    for _ in range(TREES):
        p = 1 / (1 + np.exp(-f))
        tree = grow(x[~aside], y[~aside] - p, p * (1 - p), DEPTH)
        trees.append(tree)
        f += value(tree, x[~aside])
    least = {}
    total = sum(value(t, x) for t in trees)
    chance = 1 / (1 + np.exp(-total))
    for kind in KINDS:
        here = aside & (kinds == kind)
        known = aside & (y > 0)
        if (known & here).sum() >= LEAST_LEAF:
            known = known & here
        score = total[here]
        share = float(chance[known].mean()) if known.any() else 1.0
        order = np.argsort(-score, kind="stable")
        right = np.cumsum(chance[here][order]) / np.arange(1, len(order) + 1) / share
        last = np.append(score[order][1:] < score[order][:-1], True)[: len(order)]  # equal scores stand or fall together
        good = np.flatnonzero((right >= precision) & last)
        if len(good):
            least[kind] = float(score[order][good[-1]])
    return trees, least


def as_column(tree, x: Column) -> Column:
    if isinstance(tree, float):
        return F.lit(tree)
    f, t, low, high = tree
    return F.when(x[f] <= t, as_column(low, x)).otherwise(as_column(high, x))


def accepted(kind: str, spans: Column, model: tuple[list, dict] | None) -> Column:
    if model is None or kind not in model[1]:
        return F.array().cast(NONE)
    trees, least = model
    score = lambda x: sum((as_column(t, x) for t in trees), F.lit(0.0))
    return F.filter(spans, lambda s: bind(F.array(*features(kind, s)), score) >= least[kind])


def detect(docs: DataFrame, model: tuple[list, dict] | None | str = "fit") -> DataFrame:
    """`docs` with n_<kind>, base and spans (arrays of struct<start, ord, end>, sorted) and text ('' for null)."""
    model = fit(sample(docs)) if model == "fit" else model
    plain = lambda a: F.transform(a, lambda s: F.struct(s["start"], s["ord"], s["end"]))
    d = base_spans(docs)
    base = F.array_sort(F.concat(*(plain(F.col(f"b_{k}")) for k in KINDS)))
    if model and model[1]:
        d = candidates(d)
        more = F.concat(*(plain(accepted(k, F.col(f"c_{k}"), model)) for k in KINDS))
    else:
        more = F.array().cast("array<struct<start:bigint,ord:int,end:bigint>>")
    d = d.withColumns({**{f"n_{k}": F.size(f"b_{k}").cast("long") for k in KINDS}, "base": base, "more": more})
    d = d.withColumn("spans", F.array_sort(F.concat("base", "more")))
    return d.select(*docs.columns, *(f"n_{k}" for k in KINDS), "base", "spans")


def listed(spans: Column) -> Column:
    name = lambda o: F.element_at(F.array(*map(F.lit, KINDS)), o + 1)
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", name(s["ord"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(text: Column, spans: Column) -> Column:
    """The text with spans (sorted by start) replaced by their kind in angle brackets; overlapping ones become one."""
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<string>").alias("out"))
    name = lambda o: F.element_at(F.array(*map(F.lit, KINDS)), o + 1)

    def step(acc: Column, s: Column) -> Column:
        kept = F.substring(text, (acc["at"] + 1).cast("int"), (s["start"] - acc["at"]).cast("int"))
        added = F.concat(acc["out"], F.array(kept, F.concat(F.lit("<"), name(s["ord"]), F.lit(">"))))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(s["start"] >= acc["at"], added).otherwise(acc["out"]).alias("out"))

    tail = lambda acc: F.concat(F.array_join(acc["out"], ""), F.substring(text, (acc["at"] + 1).cast("int"), F.length(text)))
    return F.when(F.size(spans) > 0, F.aggregate(spans, start, step, tail)).otherwise(text)


def op4_pii_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = detect(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return d.select("doc_id", *(f"n_{k}" for k in KINDS), F.sha2(listed(F.col("base")), 256).alias("base_sha256"), listed(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"), (F.size("spans") - F.size("base")).cast("long").alias("n_added"))


QUERIES = {"op4_pii_spans": op4_pii_spans}
