"""Vectors, audio, suffixes, near-duplicates, archives and the pipeline."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

UPPER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")

# --- vectors


def test_multi_index_recall_ties_and_odd_vectors(spark):
    from pyspark.sql import functions as F

    from revnn.llm.op1_multi_index import search

    rng = np.random.default_rng(1)
    centres = rng.standard_normal((20, 16))
    x = (centres[rng.integers(0, 20, 1500)] + 0.4 * rng.standard_normal((1500, 16))).astype(np.float32)
    x[500:1000] = x[500]  # a vector on a third of all rows
    rows = [(i, v) for i, v in enumerate(x.tolist())]
    rows += [(2000, None), (2020, [0.0] * 16), (2040, [float("nan")] + [1.0] * 15), (2060, [None] + [1.0] * 15), (2080, [1.0] * 3), (None, [1.0] * 16), (20, x[20].tolist())]
    d = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got: dict = {}
    for r in search(d, F.col("vec_id") % 20 == 0).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    assert sorted(got) == list(range(0, 1500, 20))
    x = x.astype(np.float64)
    found = 0
    for q, near in got.items():
        near.sort()
        s = x @ x[q]
        s[q] = -np.inf
        best = np.lexsort((np.arange(1500), -np.round(s, 12)))[:20]
        assert [k for k, *_ in near] == list(range(1, 21))
        assert all(abs(v - s[i]) < 1e-12 for _, i, v in near)
        found += len(set(best.tolist()) & {i for _, i, _ in near})
    assert found / (20 * len(got)) >= 0.9
    assert search(d.where("vec_id = 0"), F.col("vec_id") % 20 == 0).count() == 0
    assert search(d.where("vec_id < 4"), F.col("vec_id") % 20 == 0).count() == 3
    assert search(d.where("false"), F.col("vec_id") % 20 == 0).count() == 0


def test_walk_is_in_order():
    from revnn.llm.op1_multi_index import Quantiser

    rng = np.random.default_rng(0)
    x = rng.standard_normal((300, 8))
    z, q = Quantiser(x, 8), rng.standard_normal(8)
    sums = (z.first @ q[:4])[:, None] + (z.second @ q[4:])[None]
    cells = list(z.walk(q))
    assert sorted(cells) == list(range(z.n_cells))
    assert np.all(np.diff(sums.ravel()[cells]) <= 1e-12)


# --- audio


def test_polyphase_equals_plain_filtering():
    from revnn.llm.op5_audio import polyphase, resample

    x = np.random.default_rng(0).standard_normal(1000)
    for rate, target in ((16000, 8000), (16000, 12000), (8000, 16000), (11025, 8000)):
        up, down, phases = polyphase(rate, target)
        y = resample(x, rate, target)
        z = np.zeros(len(x) * up)
        z[::up] = x
        assert np.allclose(np.convolve(z, phases[:, ::-1].T.reshape(-1))[::down][: len(y)], y)


def test_audio_round_trip_and_tensors(spark, monkeypatch):
    import zlib

    import pyarrow as pa

    from revnn.llm import op5_audio as m
    from revnn.llm.common import Work

    texts = {1: None, 2: "x", 3: "héllo " * 3000, 4: "héllo " * 3000, 5: "a" * 192}
    d = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: r for r in m.media(d).collect()}
    for i, t in texts.items():
        n, payload = m.payload_of(t)
        assert len(payload) % 192 == 0 and len(payload) > 0
        r = got[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (n, len(payload), hashlib.sha256(payload).hexdigest())
        assert r.tail_crc32 == zlib.crc32(payload[-16:])
        assert r.media_sha256 == hashlib.sha256(m.wave_bytes(payload)).hexdigest()
    assert got[3][1:] == got[4][1:]
    work = Work(spark, "audio-test")
    stored = m.store(d, work)
    assert {r.doc_id: bytes(r.media) for r in stored.collect()} == {i: m.wave_bytes(m.payload_of(t)[1]) for i, t in texts.items()}
    featured = m.features(stored, work)
    media = m.wave_bytes(m.payload_of(texts[3])[1])
    whole = m.analyse(media)[0]
    for r in featured.collect():
        tensors = pa.ipc.open_stream(bytes(r.tensors)).read_all()
        assert tensors["logmel"].type.shape == [m.TENSOR_FRAMES, m.MELS] and tensors["active"].type.shape == [m.TENSOR_FRAMES]
        assert all(e > s for s, e in zip(tensors["start_s"].to_pylist(), tensors["end_s"].to_pylist(), strict=True))
        if r.doc_id == 3:
            assert np.array_equal(np.concatenate([x for _, _, x, _ in m.read_stream(bytes(r.tensors))]), whole)
    rows = m.frames(featured).where("doc_id = 3").orderBy("tensor").collect()
    assert np.array_equal(np.concatenate([np.array(r.logmel, np.float32) for r in rows]), whole.reshape(-1))
    monkeypatch.setattr(m, "BLOCK_FRAMES", 7)
    assert np.array_equal(whole, m.analyse(media)[0])


def test_audio_frames_reach_the_end():
    from revnn.llm import op5_audio as m

    for n in (190, 500, 576, 700, 960, 5000):
        text = "word " * (n // 5)
        a, b = (m.wave_bytes(m.payload_of(text + end)[1]) for end in ("aaaa", "~~~~"))
        assert m.digest_of(m.as_stream(a)) != m.digest_of(m.as_stream(b))
    for n in (190, 500, 576, 700, 960, 5000):
        a = m.wave_bytes(m.payload_of("word " * (n // 5))[1])
        mel = m.analyse(a)[0]
        frames = [k for k, *_ in m.tensors_of(a)]
        assert sum(frames) == len(mel) and m.span_of(0, len(mel))[1] >= len(m.wave_samples(a)[1]) / m.RATE
        assert m.digest_of(m.as_stream(a)).startswith(f"frames={len(mel)};")


def test_hysteresis():
    from revnn.llm.op5_audio import segments

    assert segments(np.array([0, 5, 1, -1, -5, 0, 4, 4, 4, 0, -9.0]), 3, -3, 2) == [(1, 4), (6, 10)]
    assert segments(np.array([0.0, 1, 2]), 3, -3, 1) == []


# --- suffixes


def test_loser_tree_merges_front_coded_runs():
    from revnn.llm.op6_suffix import IDENT, common, decoded, front_coded, merged

    rnd = random.Random(5)
    keys = sorted(bytes(rnd.choice(b"ab") for _ in range(rnd.choice([3, 10, 40]))) + b"\xff" for _ in range(2000))
    runs: list = [[] for _ in range(7)]
    for k in keys:
        runs[rnd.randrange(7)].append((k, b"0" * IDENT, True))
    out = list(merged([decoded(front_coded(r)) for r in runs]))
    assert [x[1] for x in out] == keys
    assert all(out[i][0] == common(out[i - 1][1], out[i][1]) for i in range(1, len(out)))


def repeats_of(texts):
    seen = Counter(t[p : p + 400] for t in texts for p in range(len(t) - 399))
    for t in texts:
        gone = np.zeros(len(t), np.int8)
        for p in range(len(t) - 399):
            if seen[t[p : p + 400]] > 1:
                gone[p : p + 400] = 1
        kept = np.frombuffer(t, np.uint8)[gone == 0].tobytes()
        yield len(t), int(gone.sum()), int((np.diff(np.concatenate([[0], gone])) == 1).sum()), hashlib.sha256(kept).hexdigest()


def test_repeats_equal_brute_force(spark, monkeypatch):
    from revnn.llm import op6_suffix as m

    rnd = random.Random(6)
    words = ["".join(rnd.choice("abcdefgh") for _ in range(rnd.randint(1, 8))) for _ in range(100)]
    passages = [" ".join(rnd.choice(words) for _ in range(rnd.randint(40, 300))) for _ in range(8)]

    def edited(t):
        x = t.split(" ")
        for _ in range(rnd.randint(1, 6)):
            x[rnd.randrange(len(x))] = rnd.choice(words) + "é"
        return " ".join(x)

    texts: list = [None, "", "a" * 399, "a" * 400, "a" * 401, "b" * 2000, "ab" * 700, "ab" * 600 + "c" + "ab" * 300]
    for _ in range(90):
        texts.append(" ".join(edited(rnd.choice(passages)) if rnd.random() < 0.6 else rnd.choice(passages) for _ in range(rnd.randint(1, 3))))
    texts += [texts[-rnd.randint(1, 40)] for _ in range(15)]
    monkeypatch.setattr(m, "RANGE_KEYS", 50)
    whole = [m.anchors((t or "").encode()) for t in texts]
    monkeypatch.setattr(m, "SLICE", 300)
    assert [m.anchors((t or "").encode()) for t in texts] == whole
    monkeypatch.undo()
    d = spark.createDataFrame([(i if i % 9 else None, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, spans string").repartition(5)
    rows = m.remove_repeats(d).collect()
    assert Counter(tuple(r)[1:5] for r in rows) == Counter(repeats_of([(t or "").encode() for t in texts]))
    assert m.remove_repeats(d.where("false")).count() == 0
    # passages: runs of 51 words in two documents
    runs = Counter()
    for t in texts:
        w = (t or "").split()
        runs.update({tuple(w[j : j + 51]) for j in range(len(w) - 50)})
    told = Counter()
    for t in texts:
        w = (t or "").split()
        told[any(runs[tuple(w[j : j + 51])] > 1 for j in range(len(w) - 50))] += 1
    caught = sum(r.passage_words > 0 for r in rows)
    assert all((r.n_passages > 0) == (r.passage_words > 50) for r in rows)
    assert 0.95 * told[True] <= caught <= told[True]


def test_short_passages_are_told_though_kept(spark):
    """A passage of 60 short words in several documents is reported, repeats inside one document are not."""
    from revnn.llm import op6_suffix as m

    rnd = random.Random(16)
    words = ["".join(rnd.choice("abcdefgh") for _ in range(rnd.randint(2, 7))) for _ in range(3000)]
    said = lambda n: " ".join(rnd.choice(words) for _ in range(n))
    passage, own = said(60), said(30)
    texts = [f"{said(80)} {passage} {said(50)}" if i < 20 else f"{own} {said(20)} {own} {said(9)} {own} {own}" if i == 20 else said(200) for i in range(60)]
    rows = m.remove_repeats(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    told = {r.doc_id for r in rows if r.n_passages}
    assert told <= set(range(20)) and len(told) >= 17  # a third of a kilobyte: an anchor stands inside in most documents
    assert all(60 <= r.passage_words <= 62 for r in rows if r.n_passages) and all(r.n_removed == 0 for r in rows if r.doc_id != 20)


# --- near-duplicates


def shingles(t, k=2):
    w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(UPPER))
    return frozenset(tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))) if w else frozenset()


def groups(texts, k=2):
    """doc -> smallest linked doc, from all pairs."""
    sets, up = {i: shingles(t, k) for i, t in texts.items()}, {i: i for i in texts}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    ids = sorted(texts)
    for n, i in enumerate(ids):
        for j in ids[n + 1 :]:
            a, b = sets[i], sets[j]
            if a and b and 5 * min(len(a), len(b)) >= 4 * max(len(a), len(b)):
                s = len(a & b)
                if 100 * s >= 80 * (len(a) + len(b) - s):
                    x, y = sorted((root(i), root(j)))
                    up[y] = x
    return {i: root(i) for i in ids}, sets


def test_near_duplicates_equal_all_pairs(spark):
    from revnn.llm.op8_minhash import near_duplicates

    rnd = random.Random(9)
    words = [f"W{i}" for i in range(300)]
    texts: dict = {0: None, 1: "", 2: " \t ", 3: "one", 4: "ONE", 5: "one two", 6: "two one", 7: "one two one two"}
    n = 8
    for _ in range(12):
        base = [rnd.choice(words) for _ in range(rnd.choice([6, 30, 120]))]
        for _ in range(14):
            x = list(base)
            for _ in range(rnd.randint(0, max(1, len(x) // 9))):
                x[rnd.randrange(len(x))] = rnd.choice(words)
            texts[n] = " ".join(x)
            n += 1
    d = spark.createDataFrame([(i, t, "a") for i, t in texts.items()], "doc_id long, text string, label string")
    got = {r.doc_id: r for r in near_duplicates(d).collect()}
    want, sets = groups(texts)
    assert {i: r.component_id for i, r in got.items()} == want
    assert {i: r.n_shingles for i, r in got.items()} == {i: len(s) for i, s in sets.items()}
    assert all(r.kept == (i == want[i]) for i, r in got.items())
    assert near_duplicates(d.where("false")).count() == 0


def test_sketch_estimates_similarity():
    from revnn.llm.op8_minhash import T, mix, sketch

    x = mix(np.arange(1, 2001, dtype=np.uint64))
    a, b = sketch(x[:1500]), sketch(x[300:1800])
    assert abs((a == b).mean() - 1200 / 1800) < 0.15
    for n in (1, 2, 5):
        assert len(sketch(x[:n])) == T


# --- archives


def test_archives_round_trip(spark, sf, tmp_path):
    from revnn.llm import op9_warc as m

    page = "<html>" + "pé" * 600
    rows = [(i, "http://a/b\r\nc", page) for i in range(40)] + [(50, None, None), (51, "u", ""), (52, "u", "short"), (53, "u", "short"), (None, "u", page), (54, "u", "y" * 999), (55, "u", "y" * 999), (56, "u", "z" * 1000), (57, "u", "z" * 1000)]
    d = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    m.write_archives(d, str(tmp_path / "a"))
    got = {r.page_id: r for r in m.read_archives(spark, str(tmp_path / "a")).collect()}
    assert len(got) == len(rows)
    assert [i for i, r in got.items() if i is not None and i < 40 and r.record_type == "response"] == [39]
    assert got[None].refers_to == 39 and got[3].refers_to == 39 and got[39].refers_to is None
    assert got[54].record_type == got[55].record_type == "response"
    assert got[56].refers_to == 57 and got[57].record_type == "response"
    assert got[3].payload_digest == hashlib.sha1(page.encode()).hexdigest()
    assert got[50].payload_bytes == 0
    (tmp_path / "files").mkdir()
    kept = m.write_files(spark.read.parquet(str(tmp_path / "a")), str(tmp_path / "files")).collect()
    assert sum(r.records for r in kept) == len(rows)
    m.write_archives(d.where("false"), str(tmp_path / "b"))
    assert m.read_archives(spark, str(tmp_path / "b")).count() == 0


def test_normaliser_takes_any_member_layout():
    import gzip

    from revnn.llm.op9_warc import normalise, read_member, record

    records = [record(i, "u", "x" * i * 50, "00" * 20, i * 50, None) for i in range(9)]
    for stream in (gzip.compress(b"".join(records)), b"".join(map(gzip.compress, records)), gzip.compress(b"".join(records[:4])) + gzip.compress(b"".join(records[4:]))):
        out = list(normalise(stream[i : i + 7] for i in range(0, len(stream), 7)))
        body = b"".join(x[0] for x in out)
        assert [read_member(body, o, n)[1] for _, _, o, n in out] == [b"x" * i * 50 for i in range(9)]
    with pytest.raises(ValueError):
        list(normalise([gzip.compress(b"".join(records)[:-3])]))


# --- pipeline


def test_pipeline_stages(spark, sf, tmp_path):
    import corpus_pipeline as c

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    extra = spark.createDataFrame([(None, "alpha beta gamma delta epsilon zeta", None, None, 1)] * 3 + [(900, None, "en", "s", 0), (901, "123 456", "en", "s", 7), (902, "mail me at joe@example.com or joe@example.com", "en", "src0", 1)], docs.schema)
    docs = docs.unionByName(extra)
    d, kept = docs, {}
    for name, stage in c.STAGES:
        out = stage(spark, d, sf)
        out.write.parquet(str(tmp_path / name))
        d = spark.read.parquet(str(tmp_path / name))
        if name != "tokens":
            assert d.columns == c.COLUMNS
        kept[name] = d
    lang = {r.doc_id for r in kept["language"].collect()}
    assert 900 not in lang and 901 not in lang and kept["language"].count() == docs.count() - 2
    before = {(r.doc_id, r.text) for r in kept["language"].collect()}
    texts = dict(enumerate(t for _, t in sorted(before, key=str)))
    want, _ = groups(texts, c.SHINGLE)
    assert kept["near_duplicates"].count() == len(set(want.values()))
    pii = kept["personal_data"]
    assert pii.count() == kept["near_duplicates"].count()
    assert pii.where("doc_id = 902").first().text == "mail me at <email> or <email>"
    assert pii.where("n_chars != length(text)").count() == 0
    assert kept["tokens"].count() == kept["mixing"].count() > 0


def test_pipeline_on_empty_unlabelled_and_repeated_rows(spark, sf):
    import corpus_pipeline as c

    d = spark.read.parquet(f"{sf}/documents.parquet")
    empty = d.where("false")
    for _, stage in c.STAGES:
        assert stage(spark, empty, sf).count() == 0
    # nothing labelled: what has letters stays
    bare = d.limit(20).withColumn("lang", F.lit(None).cast("string")).unionByName(d.limit(1).withColumn("text", F.lit("12 34")))
    assert c.language(spark, bare, sf).count() == d.limit(20).where(F.rlike("text", F.lit(r"\p{L}"))).count()
    # one id, two texts: both are documents of their own
    words = " ".join(f"w{i}" for i in range(60))
    twice = spark.createDataFrame([(1, words, "en", "a", 9), (1, words[::-1], "en", "a", 9), (1, words, "en", "a", 9), (None, None, None, None, None)], d.select(*c.COLUMNS).schema)
    kept = c.near_duplicates(spark, twice, sf).collect()
    assert sorted(str(r.text) for r in kept) == sorted([words, words[::-1], "None"])
    mixed = c.mixing(spark, twice, sf)
    assert {r.text for r in mixed.collect()} <= {words, words[::-1]} and set(mixed.columns) == set(c.COLUMNS)
