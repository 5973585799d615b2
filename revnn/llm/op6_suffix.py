"""Exact removal of long repeated byte strings with a sparse, distributed suffix sort.

Every byte covered by a string of LENGTH bytes that also starts elsewhere is removed. Sorting the suffixes at every
byte would move each text hundreds of times, so only suffixes at *anchors* are sorted: each window of LENGTH bytes
elects its smallest hashed GRAM (leftmost among equals), so equal windows elect the same gram at the same offset, and a
gram found once proves that none of its windows repeats. A gram whose surroundings are equal wherever it stands needs
no comparison either. The rest, anchors near an edge of a repeat, are sorted twice, by what follows the anchor and by
what precedes it (read backwards):

* a task sorts its keys, cuts them at sampled splitters and writes front-coded runs (common prefix with the key before,
  then the rest of the key); each run also carries its nearest keys beyond a splitter, so neighbours are never missed;
* a range's runs meet in a loser tree that keeps, for every head, its common prefix with the last key put out: two
  heads with different prefixes are ordered without a look at their bytes, others are compared from there on.

The longest common prefix with its neighbours bounds how far any repeat of an anchor reaches to that side, and each
neighbour proves an interval of window offsets. Where the proven intervals don't fill the bounds, windows in between
are settled by digests of the windows themselves.

Beside what is removed, the same sorts report passages: a neighbour from another document shares some bytes before and
after the anchor, and if these hold more than PASSAGE words, they are a passage that both documents hold, though it may
be too short to be removed. Passages of LENGTH bytes or more are always met; of shorter ones those with an anchor inside.

Defined cases: null text is empty; texts shorter than LENGTH lose nothing; copies of a text lose all of it; repeated
rows are copies of each other; texts of any length are cut into slices that overlap by LENGTH; an empty table gives an
empty result; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from revnn.llm.common import Work, fixed_filter, small, spread_join, table

LENGTH, GRAM = 400, 64
REACH = LENGTH - GRAM
NEIGHBOURS = 8
SLICE = 1 << 19
RANGE_KEYS, SPLIT_SAMPLE, RUN_KEYS = 8192, 4096, 20_000
#: A byte that no UTF-8 text has: ends the first part of a key.
END = b"\xff"
#: Words that a reported passage has more than, and the fewest bytes that can hold so many.
PASSAGE = 50
LEAST_BYTES = 2 * PASSAGE + 1
#: Bytes of an id in a run: a digest of the surroundings, and which document alone has them (zeros: several do).
IDENT = 24
#: Occurrences of a surrounding, or copies of a text, that a task takes, about.
DEALT = 4096
#: Open windows up to which they are broadcast (36 bytes each).
ASKED = 100_000
U = np.uint64
BASE = 0xD1B54A32D192ED03
ANCHOR = "array<struct<fp:bigint,a:bigint,lo:int,hi:int,ctx:binary>>"


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> U(30))) * U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> U(27))) * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


class _Powers:
    def __init__(self):
        self.up = self.down = np.ones(1, U)

    def to(self, n: int):
        if len(self.up) < n:
            for name, base in (("up", BASE), ("down", pow(BASE, -1, 1 << 64))):
                x = np.full(n, base, U)
                x[0] = 1
                setattr(self, name, np.multiply.accumulate(x))
        return self.up[:n], self.down[:n]


_POWERS = _Powers()


def grams(raw: np.ndarray, k: int = GRAM) -> np.ndarray:
    """A hash of each run of k bytes."""
    n = len(raw)
    up, down = _POWERS.to(n + 1)
    total = np.zeros(n + 1, U)
    np.cumsum((raw.astype(U) + U(1)) * up[:n], out=total[1:])
    return _mix((total[k:] - total[:-k]) * down[: n - k + 1])


def sliding_least(v: np.ndarray, w: int) -> np.ndarray:
    n = len(v)
    full = np.concatenate([v, np.full(-n % w, U(0xFFFFFFFFFFFFFFFF))]).reshape(-1, w)
    ahead = np.minimum.accumulate(full, axis=1).ravel()
    back = np.minimum.accumulate(full[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - w + 1], ahead[w - 1 : n])


def surroundings(text: bytes, a: int) -> tuple[bytes, bytes]:
    """What stands from the anchor on, and what stands before it, as far as a window with this anchor can reach."""
    return text[a : a + LENGTH], text[max(0, a - REACH) : a]


def context_id(text: bytes, a: int) -> bytes:
    ahead, back = surroundings(text, a)
    return hashlib.blake2b(back + END + ahead, digest_size=16).digest()


def anchors(text: bytes) -> list[tuple[int, int, int, int]]:
    """(gram hash, place, smallest and largest offset of the windows that elect it)."""
    out = []
    for first in range(0, len(text) - LENGTH + 1, SLICE):
        raw = np.frombuffer(text, np.uint8)[first : first + SLICE + LENGTH - 1]
        h = grams(raw)
        v = (h & ~U(0xFFFFF)) | np.arange(len(h), dtype=U)
        at = (sliding_least(v, REACH + 1) & U(0xFFFFF)).astype(np.int64)
        start = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]]))
        stop = np.concatenate([start[1:], [len(at)]])
        place = at[start]
        more = list(zip(h[place].view(np.int64).tolist(), (place + first).tolist(), (place - stop + 1).tolist(), (place - start).tolist(), strict=True))
        if out and out[-1][1] == more[0][1]:  # an anchor of windows on both sides of a cut is one anchor
            more[0] = (*more[0][:3], out.pop()[3])
        out += more
    return out


def _anchor_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kind = pa.list_(pa.struct([("fp", pa.int64()), ("a", pa.int64()), ("lo", pa.int32()), ("hi", pa.int32()), ("ctx", pa.binary())]))
    for batch in batches:
        for part in (batch.slice(i, 512) for i in range(0, batch.num_rows, 512)):
            found, sizes = [], []
            for t in part.column(1):
                text = (t.as_py() or "").encode("utf-8", "surrogatepass")
                sizes.append(len(text))
                found.append([{"fp": f, "a": a, "lo": lo, "hi": hi, "ctx": context_id(text, a)} for f, a, lo, hi in anchors(text)])
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(sizes, pa.int64()), pa.array(found, kind)], names=["doc_id", "tkey", "n_bytes", "anchors"])


def common(a: bytes, b: bytes, at: int = 0) -> int:
    """Length of the common prefix, known to be at least `at`."""
    n = min(len(a), len(b))
    while at < n:
        step = min(64, n - at)
        x, y = a[at : at + step], b[at : at + step]
        if x != y:
            d = int.from_bytes(x, "big") ^ int.from_bytes(y, "big")
            return at + step - (d.bit_length() + 7) // 8
        at += step
    return n


def front_coded(keys: list[tuple[bytes, bytes, bool]]) -> bytes:
    """Sorted (key, id, owned) as: common prefix, rest length, owned, id, rest."""
    out, last = bytearray(), b""
    for key, ident, owned in keys:
        n = common(last, key)
        out += struct.pack("<HHB", n, len(key) - n, owned) + ident + key[n:]
        last = key
    return bytes(out)


def decoded(blob: bytes) -> Iterator[tuple[int, bytes, bytes, bool]]:
    """(common prefix with the key before, key, id, owned)."""
    at, last = 0, b""
    while at < len(blob):
        n, m, owned = struct.unpack_from("<HHB", blob, at)
        last = last[:n] + blob[at + 5 + IDENT : at + 5 + IDENT + m]
        yield n, last, blob[at + 5 : at + 5 + IDENT], bool(owned)
        at += 5 + IDENT + m


def merged(runs: list[Iterator[tuple[int, bytes, bytes, bool]]]) -> Iterator[tuple[int, bytes, bytes, bool]]:
    """A loser tree over front-coded runs: (common prefix with what was put out before, key, id, owned) in order."""
    size = 1
    while size < len(runs):
        size *= 2
    heads = [next(r, None) for r in runs] + [None] * (size - len(runs))
    known = [0] * size  # common prefix of a head with the key put out last
    tree = [0] * size

    def play(x: int, y: int) -> tuple[int, int]:
        """(winner, loser); the loser's known prefix becomes that with the winner."""
        if heads[x] is None or heads[y] is None:
            return (y, x) if heads[x] is None else (x, y)
        if known[x] != known[y]:
            return (x, y) if known[x] > known[y] else (y, x)
        a, b = heads[x][1], heads[y][1]
        n = common(a, b, known[x])
        winner, loser = (y, x) if n == len(b) and n < len(a) or n < min(len(a), len(b)) and b[n] < a[n] else (x, y)
        known[loser] = n
        return winner, loser

    level = list(range(size))
    base = size
    while len(level) > 1:
        base //= 2
        after = []
        for i in range(0, len(level), 2):
            w, tree[base + i // 2] = play(level[i], level[i + 1])
            after.append(w)
        level = after
    top = level[0]
    while heads[top] is not None:
        yield known[top], *heads[top][1:]
        heads[top] = next(runs[top], None) if top < len(runs) else None
        known[top] = heads[top][0] if heads[top] else 0
        node = (size + top) // 2
        while node:
            top, tree[node] = play(top, tree[node])
            node //= 2


def forward_key(ahead: bytes, back: bytes) -> bytes:
    return ahead + END + back[::-1] + END


def backward_key(ahead: bytes, back: bytes) -> bytes:
    return (back + ahead[:GRAM])[::-1] + END + ahead[GRAM:] + END


KEYS = {1: forward_key, 2: backward_key}


def overlap(kind: int, a: tuple[int, bytes], b: tuple[int, bytes], shared: int) -> tuple[int, int]:
    """Bytes in common after (from the anchor on) and before it, of two keys with a common prefix of `shared`."""
    (cut_a, x), (cut_b, y) = a, b
    first = min(shared, cut_a, cut_b)
    if shared > cut_a and shared > cut_b:  # equal first parts: the common prefix tells the second
        second = shared - cut_a - 1
    else:
        second = common(x[cut_a + 1 :], y[cut_b + 1 :])
    second = min(second, len(x) - cut_a - 2, len(y) - cut_b - 2)
    return (first, second) if kind == 1 else (GRAM + second, first - GRAM)


def united(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Closed integer intervals, joined where they touch."""
    out: list[list[int]] = []
    for lo, hi in sorted(spans):
        if out and lo <= out[-1][1] + 1:
            out[-1][1] = max(out[-1][1], hi)
        else:
            out.append([lo, hi])
    return [tuple(x) for x in out]


def elsewhere(a: bytes, b: bytes) -> bool:
    """Whether two ids stand for places in different documents."""
    return a[16:] != b[16:] or not any(a[16:])


def neighbours(kind: int, keys: Iterator[tuple[int, bytes, bytes, bool]]) -> Iterator[tuple[bytes, int, list[tuple[int, int]], tuple[int, int]]]:
    """For owned keys: id, most bytes that any key shares on this side, the window offsets that neighbours prove, and
    the longest stretch (bytes after the anchor's begin and before it) shared with another document's neighbour."""
    recent: list[list] = []  # [cut, key, id, owned, most, spans, stretch, common prefix with the key after it so far]
    for n, key, ident, owned in keys:
        me = [key.index(END), key, ident, owned, 0, [], (0, 0)]
        shared = n
        for back, other in enumerate(reversed(recent)):
            if back:
                shared = min(shared, recent[-back][7])
            if shared < GRAM:
                break
            ahead, before = overlap(kind, (me[0], key), (other[0], other[1]), shared)
            span = (LENGTH - ahead, before)
            across = ahead + before >= LEAST_BYTES and elsewhere(ident, other[2])
            for x in (me, other):
                x[4] = max(x[4], ahead if kind == 1 else before + GRAM)
                if span[0] <= span[1]:
                    x[5].append(span)
                if across and ahead + before > sum(x[6]):
                    x[6] = (ahead, before)
        me.append(n)
        recent.append(me)
        if len(recent) > NEIGHBOURS:
            done = recent.pop(0)
            if done[3]:
                yield done[2], done[4], united(done[5]), done[6]
    for done in recent:
        if done[3]:
            yield done[2], done[4], united(done[5]), done[6]


def _make_runs(kind: int, splitters: list[bytes]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[bytes, bytes]] = []

        def flush():
            held.sort()
            names = [k for k, _ in held]
            cuts = [0, *(bisect_left(names, s) for s in splitters), len(held)]
            for part, (lo, hi) in enumerate(zip(cuts, cuts[1:], strict=False)):
                # beyond a splitter, as many keys as neighbours are looked at
                near = held[max(0, lo - NEIGHBOURS) : hi + NEIGHBOURS]
                if near:
                    first = max(0, lo - NEIGHBOURS)
                    blob = front_coded([(k, i, lo <= first + j < hi) for j, (k, i) in enumerate(near)])
                    yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([blob], pa.binary())], names=["part", "run"])
            held.clear()

        for batch in batches:
            for ctx, owner, ahead, back in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                held.append((KEYS[kind](ahead, back), ctx + owner))
                if len(held) == RUN_KEYS:
                    yield from flush()
        yield from flush()

    return run


def _merge_runs(kind: int):
    def merge(t: pa.Table) -> pa.Table:
        out = ([], [], [], [], [])
        for ident, most, spans, (after, before) in neighbours(kind, merged([decoded(x.as_py()) for x in t["run"]])):
            for column, v in zip(out, (ident[:16], most, [{"lo": lo, "hi": hi} for lo, hi in spans], after, before), strict=True):
                column.append(v)
        types = (pa.binary(), pa.int32(), pa.list_(pa.struct([("lo", pa.int32()), ("hi", pa.int32())])), pa.int32(), pa.int32())
        return pa.table([pa.array(c, x) for c, x in zip(out, types, strict=True)], names=["ctx", "most", "spans", "after", "before"])

    return merge


SPANS = "array<struct<lo:int,hi:int>>"


def sorted_sides(contexts: DataFrame, n: int) -> tuple[DataFrame, DataFrame]:
    """For both sorts: ctx, most, spans, after, before."""
    # about SPLIT_SAMPLE keys, whatever n
    sample = contexts.where(F.pmod(F.xxhash64("ctx"), F.lit(max(n, SPLIT_SAMPLE))) < SPLIT_SAMPLE).select("ahead", "back").collect()
    ranges = min(max(1, -(-n // RANGE_KEYS)), max(1, len(sample) // 8))
    found = []
    for kind in (1, 2):
        keys = sorted(KEYS[kind](bytes(r.ahead), bytes(r.back)) for r in sample)
        splitters = sorted({keys[len(keys) * i // ranges] for i in range(1, ranges)})
        runs = contexts.select("ctx", "owner", "ahead", "back").mapInArrow(_make_runs(kind, splitters), "part int, run binary")
        found.append(runs.groupBy("part").applyInArrow(_merge_runs(kind), f"ctx binary, most int, spans {SPANS}, after int, before int"))
    return found[0], found[1]


def _settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """ctx, ahead_most, back_most, spans, lo, hi -> proven intervals and offsets that are still open."""
    kind = pa.list_(pa.struct([("lo", pa.int32()), ("hi", pa.int32())]))
    for batch in batches:
        proven, left = [], []
        for _, ahead, back, spans, lo, hi in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            lo, hi = max(lo, LENGTH - (ahead or 0)), min(hi, (back or 0) - GRAM)
            known = united([(max(lo, s["lo"]), min(hi, s["hi"])) for s in spans or [] if max(lo, s["lo"]) <= min(hi, s["hi"])])
            proven.append([{"lo": a, "hi": b} for a, b in known])
            covered = {x for a, b in known for x in range(a, b + 1)}
            left.append([x for x in range(lo, hi + 1) if x not in covered])
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(proven, kind), pa.array(left, pa.list_(pa.int32()))], names=["ctx", "proven", "open"])


def window_id(ahead: bytes, back: bytes, x: int) -> bytes | None:
    """A digest of the window that begins x bytes before the anchor, if the text has it."""
    return hashlib.blake2b(back[len(back) - x :] + ahead[: LENGTH - x], digest_size=16).digest() if x <= len(back) and LENGTH - x <= len(ahead) else None


def _windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """ctx, fp, ahead, back, offsets -> a digest of each of these windows."""
    for batch in batches:
        out = [(ctx, fp, x, d) for ctx, fp, ahead, back, offsets in zip(*(c.to_pylist() for c in batch.columns), strict=True) for x in offsets if (d := window_id(ahead, back, x))]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True) if out else [()] * 4, (pa.binary(), pa.int64(), pa.int32(), pa.binary()), strict=True)], names=["ctx", "fp", "x", "window"])


def _matches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """ctx, ahead, back, asked (windows of the same gram by offset) -> the asked windows that stand here."""
    for batch in batches:
        out = [(ctx, d) for ctx, ahead, back, asked in zip(*(c.to_pylist() for c in batch.columns), strict=True) for w in asked if (d := window_id(ahead, back, w["x"])) in w["windows"]]
        yield pa.RecordBatch.from_arrays([pa.array(c, pa.binary()) for c in (zip(*out, strict=True) if out else [()] * 2)], names=["ctx", "window"])


def _context_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for t, wanted in zip(batch.column(0), batch.column(1), strict=True):
            text = (t.as_py() or "").encode("utf-8", "surrogatepass")
            rows = [(w["ctx"], w["fp"], w["owner"], *surroundings(text, w["a"])) for w in wanted.as_py()]
            yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(zip(*rows, strict=True), (pa.binary(), pa.int64(), pa.binary(), pa.binary(), pa.binary()), strict=True)], names=["ctx", "fp", "owner", "ahead", "back"])


def words_in(text: bytes, lo: int, hi: int) -> int:
    """Whole words between two places."""
    part = text[lo:hi]
    if lo and not text[lo - 1 : lo].isspace():
        part = _without_first(part)
    if hi < len(text) and not text[hi : hi + 1].isspace():
        part = _without_first(part[::-1])
    return len(part.split())


def _without_first(part: bytes) -> bytes:
    """What follows the first word, if the part begins with one."""
    return part if part[:1].isspace() else (part.split(None, 1) + [b"", b""])[1]


def _result_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = ([], [], [], [], [], [], [])
        for doc_id, t, spans in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist(), strict=True):
            text = (t.as_py() or "").encode("utf-8", "surrogatepass")
            runs = united([(s["s"], s["e"] - 1) for s in spans or [] if not s["passage"]])
            kept, at = hashlib.sha256(), 0
            for lo, hi in runs:
                kept.update(text[at:lo])
                at = hi + 1
            kept.update(text[at:])
            passages = [(max(0, s["s"]), min(len(text), s["e"])) for s in spans or [] if s["passage"]]
            passages = united([(lo, hi - 1) for lo, hi in passages if words_in(text, lo, hi) > PASSAGE])
            n_words = sum(words_in(text, lo, hi + 1) for lo, hi in passages)
            for c, v in zip(out, (doc_id, len(text), sum(hi - lo + 1 for lo, hi in runs), len(runs), kept.hexdigest(), len(passages), n_words), strict=True):
                c.append(v)
        yield pa.RecordBatch.from_arrays([pa.array(c, x) for c, x in zip(out, (*[pa.int64()] * 4, pa.string(), pa.int64(), pa.int64()), strict=True)], names=[x.split()[0] for x in RESULT.split(", ")])


RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, n_passages long, passage_words long"
OWNED = "array<struct<s:bigint,e:bigint,passage:boolean>>"


def with_key(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", "text", F.substring(F.unhex(F.sha2(F.coalesce("text", F.lit("")), 256)), 1, 16).alias("tkey"))


def repeated_spans(docs: DataFrame, work: Work) -> DataFrame:
    """tkey (names a text), copies (rows that have it), spans: array<struct<s, e, passage>>, unmerged.

    Spans that are no passage are what repeated strings of LENGTH bytes cover."""
    rows = work.keep(with_key(docs).mapInArrow(_anchor_rows, f"doc_id long, tkey binary, n_bytes long, anchors {ANCHOR}"))
    every = rows.select("doc_id", "tkey", F.explode("anchors").alias("x")).select("doc_id", "tkey", "x.*")
    twice = every.groupBy("fp").agg(F.count(F.lit(1)).alias("n"), F.min("ctx").alias("one"), F.max("ctx").alias("other")).where("n > 1")
    # kept before the join, so that both sides are exchanged and a frequent gram can be split
    twice = work.keep(twice.select("fp", (F.col("one") != F.col("other")).alias("mixed")))
    found = work.keep(every.join(twice, "fp"))
    by_ctx = found.groupBy("ctx").agg(F.count(F.lit(1)).alias("n"), F.max("mixed").alias("mixed"), F.first("fp").alias("fp"), F.min("lo").alias("lo"), F.max("hi").alias("hi"), F.min(F.struct("tkey", "doc_id", "a")).alias("at"), F.max("tkey").alias("other"))
    by_ctx = work.keep(by_ctx.withColumn("owner", F.when(F.col("at.tkey") == F.col("other"), F.substring("other", 1, 8)).otherwise(F.lit(bytes(8)))).drop("other"))

    wanted = by_ctx.where("mixed").groupBy("at.tkey", "at.doc_id").agg(F.collect_list(F.struct("ctx", "fp", "owner", F.col("at.a").alias("a"))).alias("wanted"))
    wanted = work.keep(wanted)
    needed = fixed_filter(wanted, "tkey", "doc_id")(with_key(docs), "needed").where("needed").withColumn("_id", F.coalesce(F.col("doc_id").cast("string"), F.lit("null")))
    # equal rows are equal texts: each task passes on one of them
    needed = needed.groupBy("tkey", "_id").agg(F.first("text").alias("text"))
    texts = needed.join(wanted.withColumn("_id", F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))), ["tkey", "_id"])
    contexts = work.keep(texts.select("text", "wanted").mapInArrow(_context_rows, "ctx binary, fp long, owner binary, ahead binary, back binary"))
    work.drop(wanted, twice)
    ahead, back = sorted_sides(contexts, contexts.count())
    sides = ahead.withColumn("side", F.lit(1)).unionByName(back.withColumn("side", F.lit(2)))
    stretch = F.max(F.struct((F.col("after") + F.col("before")).alias("both"), "after", "before")).alias("stretch")
    sides = work.keep(sides.groupBy("ctx").agg(F.max(F.when(F.col("side") == 1, F.col("most"))).alias("ahead"), F.max(F.when(F.col("side") == 2, F.col("most"))).alias("back"), F.flatten(F.collect_list("spans")).alias("spans"), stretch))
    alone = by_ctx.where("mixed and n = 1").select("ctx", "lo", "hi", "fp")
    settled = work.keep(sides.join(alone, "ctx").select("ctx", "ahead", "back", "spans", "lo", "hi").mapInArrow(_settle, f"ctx binary, proven {SPANS}, open array<int>"))

    # few windows are left; they are looked for where their gram stands
    still = settled.where(F.size("open") > 0).select("ctx", F.col("open").alias("offsets"))
    still = work.keep(contexts.join(small(still), "ctx").select("ctx", "fp", "ahead", "back", "offsets").mapInArrow(_windows, "ctx binary, fp long, x int, window binary"))
    asked = still.groupBy("fp", "x").agg(F.collect_set("window").alias("windows")).groupBy("fp").agg(F.collect_list(F.struct("x", "windows")).alias("asked"))
    asked = small(asked) if still.count() <= ASKED else asked
    matches = contexts.join(asked, "fp").select("ctx", "ahead", "back", "asked").mapInArrow(_matches, "ctx binary, window binary")
    again = matches.groupBy("window").agg(F.count_distinct("ctx").alias("n")).where("n > 1")
    proven = still.join(again, "window").select("ctx", F.col("x").alias("lo"), F.col("x").alias("hi"))
    proven = proven.unionByName(settled.select("ctx", F.explode("proven").alias("p")).select("ctx", "p.lo", "p.hi"))
    proven = proven.groupBy("ctx").agg(F.collect_list(F.struct("lo", "hi")).alias("spans"))

    # what is known of a surrounding holds wherever it stands; one that stands at several places repeats as a whole
    known = by_ctx.select("ctx", "n", (F.col("owner") == F.lit(bytes(8))).alias("shared")).join(proven, "ctx", "left").join(sides.where("stretch.both > 0").select("ctx", "stretch.after", "stretch.before"), "ctx", "left")
    known = known.where("n > 1 or spans is not null or after is not null").withColumn("salts", F.ceil(F.col("n") / DEALT).cast("int"))
    placed = spread_join(found.select("ctx", "tkey", "a", "lo", "hi"), work.keep(known), ["ctx"], ["tkey", "a"])
    span = lambda s, e, passage: F.struct(s.cast("long").alias("s"), e.cast("long").alias("e"), F.lit(passage).alias("passage"))
    a, lo, hi = F.col("a"), F.col("lo"), F.col("hi")
    some = F.filter(F.transform("spans", lambda p: F.struct(F.greatest(lo, p["lo"]).alias("x"), F.least(hi, p["hi"]).alias("y"))), lambda p: p["x"] <= p["y"])
    removed = F.when(F.col("n") > 1, F.array(span(a - hi, a - lo + LENGTH, False))).otherwise(F.transform(some, lambda p: span(a - p["y"], a - p["x"] + LENGTH, False)))
    passage = F.when((F.col("n") > 1) & F.col("shared"), F.array(span(a - REACH, a + LENGTH, True))).when(F.col("after").isNotNull(), F.array(span(a - F.col("before"), a + F.col("after"), True)))
    none = F.array().cast(OWNED)
    placed = placed.select("tkey", F.explode(F.concat(F.coalesce(removed, none), F.coalesce(passage, none))).alias("span"))
    copies = rows.groupBy("tkey").agg(F.count(F.lit(1)).alias("copies"), F.first("n_bytes").alias("n_bytes")).where("copies > 1 and n_bytes > 0")
    zero, end = F.lit(0), F.col("n_bytes")
    whole = copies.select("tkey", F.explode(F.concat(F.when(end >= LENGTH, F.array(span(zero, end, False))).otherwise(none), F.array(span(zero, end, True)))).alias("span"))
    spans = placed.distinct().unionByName(whole).groupBy("tkey").agg(F.collect_list("span").alias("spans"))
    spans = work.keep(spans.join(copies.select("tkey", "copies"), "tkey", "left").select("tkey", F.coalesce("copies", F.lit(1)).alias("copies"), "spans"))
    work.drop(rows, found, by_ctx, contexts, sides, settled, still)
    return spans


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, n_passages, passage_words for every row."""
    spans = repeated_spans(docs, Work(docs.sparkSession, "suffix"))
    d = fixed_filter(spans, "tkey")(with_key(docs), "maybe")
    keyed = spans.withColumn("salts", F.ceil(F.col("copies") / DEALT).cast("int")).drop("copies")
    some = spread_join(d.where("maybe").select("doc_id", "text", "tkey"), keyed, ["tkey"], ["doc_id"], "left").select("doc_id", "text", "spans")
    # texts that surely lose nothing aren't moved
    d = some.unionByName(d.where("not maybe").select("doc_id", "text", F.lit(None).cast(OWNED).alias("spans")))
    return d.mapInArrow(_result_rows, RESULT)


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"))


QUERIES = {"op6_suffix_dedup": op6_suffix_dedup}
