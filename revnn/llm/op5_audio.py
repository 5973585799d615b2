"""Audio columns: PCM bytes to log-mel frames and speech-like segments, as fixed-shape tensors with time spans.

Samples are unsigned 8-bit PCM in RIFF/WAVE. A polyphase filter resamples by a ratio of small integers (each output
phase has its own short filter, so nothing is computed that is thrown away); overlapped Hann frames go through a real
FFT and triangular mel bands; frame energies pass a two-threshold (hysteresis) segmenter that opens above the upper
and closes below the lower threshold. A recording is worked through in blocks of a fixed number of frames with the
overlap carried (only frames' bands and energies are kept, MELS + 2 numbers for 256 samples), and a block's results depend on its own samples alone: equal
recordings give equal features wherever they are computed.

Recordings are written as a table in the folder that executors share and read from there; so are their features, each
recording's tensors with begin and end in seconds as an Arrow stream of the fixed-shape tensor type.

Defined cases: null text is empty and becomes one block of 192 blanks; the last frame is
filled up with zeros, so every sample is in a frame; repeated rows give repeated results; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache
from math import gcd

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from revnn.llm.common import Work, batches_of, table

RATE = 16_000
TARGET = 8_000
PAD_TO = 192
FRAME, HOP, MELS = 256, 128, 16
#: Frames in a tensor of :func:`features`; blocks of the analysis are a whole number of them.
TENSOR_FRAMES = 64
BLOCK_FRAMES = 64 * TENSOR_FRAMES
OPEN_DB, CLOSE_DB, LEAST_FRAMES = 3.0, -3.0, 3
#: Rows of an Arrow batch of texts or recordings.
BATCH = 1000
RESULT = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
FEATURES = RESULT.replace("feature string", "tensors binary")
TENSORS = "doc_id long, tensor long, start_s double, end_s double, n_frames int, n_mels int, logmel array<float>, active array<boolean>"


def payload_of(text: str | None) -> tuple[int, bytes]:
    """Bytes before padding, and the text as UTF-8 padded with blanks to a positive multiple of PAD_TO."""
    data = (text or "").encode("utf-8", "surrogatepass")
    return len(data), data + b" " * (-len(data) % PAD_TO if data else PAD_TO)


def wave_bytes(samples: bytes, rate: int = RATE) -> bytes:
    """Unsigned 8-bit mono PCM as RIFF/WAVE."""
    body = struct.pack("<4sIHHIIHH", b"fmt ", 16, 1, 1, rate, rate, 1, 8) + struct.pack("<4sI", b"data", len(samples)) + samples + b"\0" * (len(samples) % 2)
    return struct.pack("<4sI4s", b"RIFF", 4 + len(body), b"WAVE") + body


def wave_samples(media: bytes) -> tuple[int, memoryview]:
    """Rate and samples of what :func:`wave_bytes` stored; other chunks are skipped."""
    view, at, rate = memoryview(media), 12, 0
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a RIFF/WAVE file")
    while at + 8 <= len(media):
        kind, n = struct.unpack_from("<4sI", media, at)
        if kind == b"fmt ":
            coding, channels, rate, _, _, bits = struct.unpack_from("<HHIIHH", media, at + 8)
            if (coding, channels, bits) != (1, 1, 8):
                raise ValueError("only mono 8-bit PCM is read")
        elif kind == b"data":
            return rate, view[at + 8 : at + 8 + n]
        at += 8 + n + n % 2
    raise ValueError("no samples")


@lru_cache
def polyphase(rate: int, target: int, taps: int = 8) -> tuple[int, int, np.ndarray]:
    """up, down and the windowed-sinc filter as one row of taps for each output phase."""
    up, down = target // (g := gcd(rate, target)), rate // g
    n = 2 * taps * max(up, down)
    t = np.arange(n) - (n - 1) / 2
    cut = 1 / max(up, down)
    h = np.sinc(t * cut) * cut * np.hanning(n + 2)[1:-1] * up
    width = -(-n // up)
    return up, down, np.pad(h, (0, width * up - n)).reshape(width, up).T[:, ::-1].copy()


def resample(x: np.ndarray, rate: int = RATE, target: int = TARGET) -> np.ndarray:
    """All outputs that `x` (with zeros before it) determines."""
    up, down, phases = polyphase(rate, target)
    width = phases.shape[1]
    n = -(-len(x) * up // down)
    padded = np.concatenate([np.zeros(width - 1), x])
    if up == 1:
        rows = np.lib.stride_tricks.sliding_window_view(padded, width)[::down][:n]
        return rows @ phases[0]
    k = np.arange(n) * down
    rows = np.lib.stride_tricks.sliding_window_view(padded, width)[k // up]
    return np.einsum("ij,ij->i", rows, phases[k % up])


@lru_cache
def mel_bank(rate: int = TARGET, frame: int = FRAME, mels: int = MELS) -> np.ndarray:
    """(bins, mels) triangular weights, equally spaced on the mel scale."""
    to_mel, to_hz = lambda f: 2595 * np.log10(1 + f / 700), lambda m: 700 * (10 ** (m / 2595) - 1)
    edges = to_hz(np.linspace(to_mel(30.0), to_mel(rate / 2), mels + 2))
    f = np.linspace(0, rate / 2, frame // 2 + 1)[:, None]
    return np.maximum(0, np.minimum((f - edges[:-2]) / (edges[1:-1] - edges[:-2]), (edges[2:] - f) / (edges[2:] - edges[1:-1])))


def log_mel(samples: memoryview, rate: int = RATE) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Blocks of (frames, mels) log energies and (frames,) energies in dB."""
    up, down, phases = polyphase(rate, TARGET)
    lead = phases.shape[1] - 1
    lead += -lead % down
    n_out = -(-len(samples) * up // down)
    n_frames = 1 + max(0, -(-(n_out - FRAME) // HOP))
    window, bank = np.hanning(FRAME), mel_bank()
    raw = np.frombuffer(samples, np.uint8)
    for first in range(0, n_frames, BLOCK_FRAMES):
        frames = min(BLOCK_FRAMES, n_frames - first)
        lo, hi = first * HOP * down // up, -(-((first + frames - 1) * HOP + FRAME) * down // up)
        skip = min(lo, lead)
        y = resample((raw[lo - skip : hi].astype(np.float64) - 128) / 128, rate)[skip * up // down :]
        y = np.pad(y, (0, max(0, (frames - 1) * HOP + FRAME - len(y))))
        cut = np.lib.stride_tricks.sliding_window_view(y, FRAME)[::HOP][:frames]
        power = np.abs(np.fft.rfft(cut * window)) ** 2
        yield np.log(power @ bank + 1e-8), 10 * np.log10((cut**2).mean(axis=1) + 1e-8)


def segments(energy: np.ndarray, up: float, down: float, least: int = LEAST_FRAMES) -> list[tuple[int, int]]:
    """[begin, end) of runs that open at >= up, last while >= down, and have `least` frames."""
    state = np.where(energy >= up, 1, np.where(energy < down, -1, 0))
    held = np.maximum.accumulate(np.where(state != 0, np.arange(len(state)), -1))
    active = (held >= 0) & (state[held] == 1)
    edges = np.flatnonzero(np.diff(np.concatenate([[0], active.astype(np.int8), [0]])))
    return [(a, b) for a, b in edges.reshape(-1, 2).tolist() if b - a >= least]


def analyse(media: bytes) -> tuple[np.ndarray, list[tuple[int, int]]]:
    """(frames, mels) float32 and the active segments; thresholds are relative to the mean energy."""
    rate, samples = wave_samples(media)
    blocks = list(log_mel(samples, rate))
    energy = np.concatenate([e for _, e in blocks])
    middle = float(energy.mean())
    return np.concatenate([m.astype(np.float32) for m, _ in blocks]), segments(energy, middle + OPEN_DB, middle + CLOSE_DB)


def tensors_of(media: bytes) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Frames, (TENSOR_FRAMES, MELS) and (TENSOR_FRAMES,) active flags of each tensor, zero-padded."""
    mel, spans = analyse(media)
    active = np.zeros(len(mel), bool)
    for a, b in spans:
        active[a:b] = True
    for first in range(0, len(mel), TENSOR_FRAMES):
        n = min(TENSOR_FRAMES, len(mel) - first)
        yield n, np.pad(mel[first : first + n], ((0, TENSOR_FRAMES - n), (0, 0))), np.pad(active[first : first + n], (0, TENSOR_FRAMES - n))


def span_of(first: int, n: int) -> tuple[float, float]:
    """Seconds from the begin of frame `first` to the end of the n-th frame from there."""
    return first * HOP / TARGET, ((first + n - 1) * HOP + FRAME) / TARGET


def as_stream(media: bytes) -> bytes:
    """The tensors of a recording with their time spans, as an Arrow stream of fixed-shape tensors."""
    n, mel, active = zip(*tensors_of(media), strict=True)
    start, end = zip(*(span_of(i * TENSOR_FRAMES, k) for i, k in enumerate(n)), strict=True)
    flat = pa.FixedSizeListArray.from_arrays(pa.array(np.concatenate(mel).reshape(-1)), TENSOR_FRAMES * MELS)
    flags = pa.FixedSizeListArray.from_arrays(pa.array(np.concatenate(active)), TENSOR_FRAMES)
    out = pa.BufferOutputStream()
    with pa.ipc.new_stream(out, STREAM) as writer:
        writer.write_batch(pa.RecordBatch.from_arrays([pa.array(start), pa.array(end), pa.array(n, pa.int32()), pa.ExtensionArray.from_storage(STREAM.field("logmel").type, flat), pa.ExtensionArray.from_storage(STREAM.field("active").type, flags)], schema=STREAM))
    return out.getvalue().to_pybytes()


STREAM = pa.schema(
    [
        ("start_s", pa.float64()), ("end_s", pa.float64()), ("n_frames", pa.int32()),
        ("logmel", pa.fixed_shape_tensor(pa.float32(), [TENSOR_FRAMES, MELS])), ("active", pa.fixed_shape_tensor(pa.bool_(), [TENSOR_FRAMES])),
    ]
)


def read_stream(stored: bytes) -> Iterator[tuple[float, float, np.ndarray, np.ndarray]]:
    """Begin and end in seconds, (n, MELS) log energies and (n,) active flags of each stored tensor."""
    t = pa.ipc.open_stream(stored).read_all().combine_chunks()
    mel = t["logmel"].combine_chunks().storage.flatten().to_numpy().reshape(-1, TENSOR_FRAMES, MELS)
    active = t["active"].combine_chunks().storage.flatten().to_numpy(zero_copy_only=False).reshape(-1, TENSOR_FRAMES)
    for i, (a, b, n) in enumerate(zip(*(t[c].to_pylist() for c in ("start_s", "end_s", "n_frames")), strict=True)):
        yield a, b, mel[i, :n], active[i, :n]


def digest_of(stored: bytes) -> str:
    """Counts, mean and deviation of bands, and active spans and end in time, of stored tensors."""
    n, total, squares, active, runs, before, last = 0, np.zeros(MELS), np.zeros(MELS), 0, 0, False, 0.0
    for _, last, mel, on in read_stream(stored):  # noqa: B007
        mel = mel.astype(np.float64)
        n, total, squares = n + len(mel), total + mel.sum(axis=0), squares + (mel**2).sum(axis=0)
        active, runs, before = active + int(on.sum()), runs + int((on & ~np.append(before, on[:-1])).sum()), bool(on[-1])
    mean = total / n
    spread = np.sqrt(np.maximum(squares / n - mean**2, 0))
    short = lambda x: ",".join(f"{v:.3f}" for v in np.round(x, 3) + 0.0)
    return f"frames={n};segments={runs};active={active};end={last:.3f};mean={short(mean)};std={short(spread)}"


def _media_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in (batch.slice(i, 256) for i in range(0, batch.num_rows, 256)):
            n, payload = zip(*(payload_of(t.as_py()) for t in part.column(1)), strict=True)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n, pa.int64()), pa.array(map(wave_bytes, payload), pa.binary())], names=["doc_id", "n_bytes", "media"])


def _feature_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for part in (batch.slice(i, 64) for i in range(0, batch.num_rows, 64)):
            out = []
            for media in part.column(2):
                media = media.as_py()
                back = wave_samples(media)[1]
                out.append((len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-16:]), len(media), hashlib.sha256(media).hexdigest(), as_stream(media)))
            types = (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary())
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *(pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True))], names=[x.split()[0] for x in FEATURES.split(", ")])


def _digest_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [x.split()[0] for x in RESULT.split(", ")]
    for batch in batches:
        yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array([digest_of(x.as_py()) for x in batch.column(batch.num_columns - 1)], pa.string())], names=names)


def _tensor_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for doc_id, stored in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            for i, (start, end, mel, active) in enumerate(read_stream(stored.as_py())):
                yield pa.RecordBatch.from_arrays(
                    [pa.array([doc_id], pa.int64()), pa.array([i], pa.int64()), pa.array([start]), pa.array([end]), pa.array([len(mel)], pa.int32()), pa.array([MELS], pa.int32()), pa.array([mel.reshape(-1).tolist()], pa.list_(pa.float32())), pa.array([active.tolist()], pa.list_(pa.bool_()))],
                    names=[x.split()[0] for x in TENSORS.split(", ")],
                )


def store(docs: DataFrame, work: Work) -> DataFrame:
    """doc_id, n_bytes and media (RIFF/WAVE) of every row of `docs` (doc_id, text), read from the table that was written."""
    with batches_of(docs.sparkSession, BATCH):
        return work.keep(docs.select("doc_id", "text").mapInArrow(_media_rows, "doc_id long, n_bytes long, media binary"))


def features(stored: DataFrame, work: Work) -> DataFrame:
    """Measures of the stored bytes and `tensors`, an Arrow stream of fixed-shape log-mel tensors with their time spans
    (:func:`read_stream`), for every row of :func:`store`, read from the table that was written."""
    with batches_of(stored.sparkSession, BATCH):
        return work.keep(stored.mapInArrow(_feature_rows, FEATURES))


def frames(featured: DataFrame) -> DataFrame:
    """A row for each stored tensor: its time span, n_frames x MELS log energies and active flags."""
    return featured.select("doc_id", "tensors").mapInArrow(_tensor_rows, TENSORS)


def digests(featured: DataFrame) -> DataFrame:
    """Contract columns, with the feature text read from the stored tensors."""
    return featured.mapInArrow(_digest_rows, RESULT)


def media(docs: DataFrame) -> DataFrame:
    """Recordings stored, read back, turned into stored tensors, and the digests of both."""
    work = Work(docs.sparkSession, "audio")
    stored = store(docs, work)
    featured = features(stored, work)
    work.drop(stored)  # digests need the recordings no more; store() and features() keep them for who does
    return digests(featured)


def op5_audio_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media(table(spark, sf_dir, "documents"))


QUERIES = {"op5_audio_features": op5_audio_features}
