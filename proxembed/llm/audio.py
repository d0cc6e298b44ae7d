"""Audio features of media columns: polyphase resampling, log-mel filterbanks, hysteresis energy segments.

A payload is stored losslessly as an 8-bit PCM WAVE, read back from the stored bytes, and resampled by a windowed-sinc
polyphase filter (each output phase is one short dot product). Overlapping Hann frames give log-mel vectors; frame energy
with two thresholds gives segments: one opens above the high threshold and closes below the low one.

A text's features are stored as an Arrow stream: a row for each block of BLOCK frames with its time span, how many of its
frames count, and the tensor, of the fixed-shape type BLOCK x MELS (the last block is padded with the floor value); and in
the stream's metadata the segments. Spark has no such type, so the stream is a binary column; `read_tensors` gives it back,
and `feature_tensors` has a row for each block with the tensor as a list and its shape beside it. The query's `feature` is
made from the stream as read back: frames, blocks, all segments, the mean log-mel vector and a checksum of the tensors.

Defined cases: null text is the empty payload, padded to one unit of 64 zero bytes; equal texts give equal values, for
each is computed alone; repeated rows and null ids are rows like others; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from proxembed.llm.common import spread, table

RATE, TARGET_RATE = 16_000, 8_000
FRAME, HOP, FFT, MELS = 200, 80, 256, 20
BLOCK = 98
UNIT = 64


def wave_bytes(payload: bytes, rate: int = RATE) -> bytes:
    """A mono 8-bit PCM file of the payload."""
    pad = len(payload) & 1
    head = struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(payload) + pad, b"WAVE", b"fmt ", 16, 1, 1, rate, rate, 1, 8, b"data", len(payload))
    return head + payload + b"\0" * pad


def wave_samples(stored: bytes) -> tuple[int, bytes]:
    """(rate, 8-bit samples) of a mono 8-bit PCM file; other chunks are skipped."""
    if stored[:4] != b"RIFF" or stored[8:12] != b"WAVE":
        raise ValueError("not a WAVE file")
    at, rate = 12, 0
    while at + 8 <= len(stored):
        kind, size = stored[at : at + 4], struct.unpack_from("<I", stored, at + 4)[0]
        if kind == b"fmt ":
            rate = struct.unpack_from("<I", stored, at + 12)[0]
        elif kind == b"data":
            return rate, stored[at + 8 : at + 8 + size]
        at += 8 + size + (size & 1)
    raise ValueError("no data chunk")


@lru_cache(maxsize=8)
def _phases(up: int, down: int, half: int = 8) -> np.ndarray:
    """Row p: the taps of output phase p, a Hann-windowed sinc cut off at the lower of both rates."""
    cut = min(1.0, up / down)
    taps = np.arange(-half, half + 1)
    rows = []
    for p in range(up):
        t = taps - (p * down % up) / up
        row = cut * np.sinc(cut * t) * (0.5 + 0.5 * np.cos(np.pi * t / (half + 1)))
        rows.append(row / row.sum())
    return np.array(rows, dtype=np.float32)


def resample(x: np.ndarray, rate: int, target: int) -> np.ndarray:
    """Polyphase resampling; edges see zeros."""
    g = int(np.gcd(rate, target))
    up, down = target // g, rate // g
    taps = _phases(up, down)
    half = taps.shape[1] // 2
    n = -(-len(x) * up // down)
    padded = np.concatenate((np.zeros(half, dtype=np.float32), x.astype(np.float32), np.zeros(half + down + 1, dtype=np.float32)))
    out = np.zeros(n, dtype=np.float32)
    for p in range(up):
        k = np.arange(p, n, up)
        base = k * down // up
        if not len(base):
            continue
        step = down
        acc = np.zeros(len(base), dtype=np.float32)
        for t in range(taps.shape[1]):
            acc += taps[p, t] * padded[base[0] + t : base[0] + t + step * (len(base) - 1) + 1 : step]
        out[k] = acc
    return out


@lru_cache(maxsize=4)
def mel_filters(rate: int = TARGET_RATE, fft: int = FFT, mels: int = MELS) -> np.ndarray:
    """Triangles equally spaced in mel, as (fft / 2 + 1, mels)."""
    mel = lambda f: 2595 * np.log10(1 + f / 700)
    edges = 700 * (10 ** (np.linspace(0, mel(rate / 2), mels + 2) / 2595) - 1)
    f = np.arange(fft // 2 + 1) * rate / fft
    low, mid, high = edges[:-2], edges[1:-1], edges[2:]
    return np.maximum(0, np.minimum((f[:, None] - low) / (mid - low), (high - f[:, None]) / (high - mid))).astype(np.float32)


def log_mel(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(frames, MELS) log energies and each frame's log energy; a short signal is one zero-padded frame."""
    n = 1 + max(0, -(-(len(x) - FRAME) // HOP)) if len(x) else 0
    if not n:
        return np.zeros((0, MELS), dtype=np.float32), np.zeros(0, dtype=np.float32)
    padded = np.concatenate((x, np.zeros(max(0, FRAME + (n - 1) * HOP - len(x)), dtype=np.float32)))
    frames = np.lib.stride_tricks.sliding_window_view(padded, FRAME)[::HOP][:n]
    window = np.hanning(FRAME).astype(np.float32)
    mels, energy = [], []
    for a in range(0, n, 4096):
        part = frames[a : a + 4096] * window
        power = np.abs(np.fft.rfft(part, FFT, axis=1)).astype(np.float32) ** 2
        mels.append(np.log(power @ mel_filters() + np.float32(1e-6)))
        energy.append(np.log(np.einsum("ij,ij->i", part, part) + np.float32(1e-6)))
    return np.concatenate(mels), np.concatenate(energy)


def segments(energy: np.ndarray, above: float = 0.5, below: float = -0.5) -> list[tuple[int, int]]:
    """[from, to) frames: opened where energy passes mean + above * deviation, closed where it falls under mean + below * deviation."""
    if not len(energy):
        return []
    mean, deviation = float(energy.mean(dtype=np.float64)), float(energy.std(dtype=np.float64))
    state = np.where(energy >= mean + above * deviation, 1, np.where(energy < mean + below * deviation, -1, 0))
    known = np.flatnonzero(state)
    if not len(known):
        return []
    last = np.searchsorted(known, np.arange(len(state)), side="right") - 1
    on = np.where(last >= 0, state[known[np.maximum(last, 0)]], -1) > 0
    edge = np.flatnonzero(np.diff(np.concatenate(([0], on.astype(np.int8), [0]))))
    return list(zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True))


def analyse(stored: bytes) -> tuple[np.ndarray, list[tuple[int, int]], bytes]:
    """(log-mel frames, segments in milliseconds, samples read back) of a stored file."""
    rate, raw = wave_samples(stored)
    x = (np.frombuffer(raw, dtype=np.uint8).astype(np.float32) - np.float32(128)) / np.float32(128)
    mels, energy = log_mel(resample(x, rate, TARGET_RATE))
    ms = lambda frame: frame * HOP * 1000 // TARGET_RATE
    return mels, [(ms(a), ms(b - 1) + FRAME * 1000 // TARGET_RATE) for a, b in segments(energy)], raw


def payload_of(text: str | None) -> tuple[int, bytes]:
    """(bytes before padding, payload): UTF-8, zero bytes up to a positive multiple of 64."""
    data = (text or "").encode("utf-8")
    return len(data), data + b"\0" * (-len(data) % UNIT if data else UNIT)


FLOOR = np.log(np.float32(1e-6))
TENSOR = pa.fixed_shape_tensor(pa.float32(), (BLOCK, MELS))
STREAM = pa.schema([("from_ms", pa.int64()), ("to_ms", pa.int64()), ("frames", pa.int32()), ("tensor", TENSOR)])


def tensor_stream(mels: np.ndarray, spans: list[tuple[int, int]]) -> bytes:
    """Frames in blocks of fixed shape with their time spans, and segments, as an Arrow stream."""
    n = -(-len(mels) // BLOCK)
    full = np.full((n * BLOCK, MELS), FLOOR, dtype=np.float32)
    full[: len(mels)] = mels
    k = np.arange(n)
    used = np.minimum(BLOCK, len(mels) - k * BLOCK)
    ms = HOP * 1000 // TARGET_RATE
    tensors = pa.ExtensionArray.from_storage(TENSOR, pa.FixedSizeListArray.from_arrays(pa.array(full.reshape(-1)), BLOCK * MELS))
    batch = pa.RecordBatch.from_arrays([pa.array(k * BLOCK * ms), pa.array((k * BLOCK + used - 1) * ms + FRAME * 1000 // TARGET_RATE), pa.array(used, pa.int32()), tensors], names=STREAM.names)
    batch = batch.replace_schema_metadata({"segments": ",".join(f"{a}-{b}" for a, b in spans)})
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema) as writer:
        writer.write_batch(batch)
    return sink.getvalue().to_pybytes()


def read_tensors(stream: bytes) -> tuple[pa.Table, list[tuple[int, int]]]:
    """(blocks, segments) of a tensor stream."""
    blocks = pa.ipc.open_stream(stream).read_all()
    said = (blocks.schema.metadata or {}).get(b"segments", b"").decode()
    return blocks, [tuple(map(int, x.split("-"))) for x in said.split(",") if x]


#: Tensor blocks of a media column: fixed shape, with the time span each covers.
TENSOR_SCHEMA = "doc_id long, block int, from_ms long, to_ms long, frames int, shape array<int>, tensor array<float>"


def feature_tensors(docs: DataFrame) -> DataFrame:
    """(doc_id, text) -> TENSOR_SCHEMA, a row for each block of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                mels, spans, _ = analyse(wave_bytes(payload_of(text.as_py())[1]))
                blocks, _ = read_tensors(tensor_stream(mels, spans))
                n, tensors = len(blocks), blocks["tensor"].combine_chunks()
                yield pa.RecordBatch.from_arrays([
                    pa.array([doc] * n, pa.int64()), pa.array(np.arange(n), pa.int32()), *(blocks[c].combine_chunks() for c in ("from_ms", "to_ms", "frames")),
                    pa.array([list(tensors.type.shape)] * n, pa.list_(pa.int32())), tensors.storage.cast(pa.list_(pa.float32())),
                ], names=[c.split()[0] for c in TENSOR_SCHEMA.split(", ")])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, TENSOR_SCHEMA)


def describe(stream: bytes) -> str:
    """frames x mels; blocks; segments in milliseconds; mean log-mel vector; checksum of the tensors."""
    blocks, spans = read_tensors(stream)
    used = blocks["frames"].to_numpy()
    tensors = blocks["tensor"].combine_chunks().to_numpy_ndarray()
    frames = tensors.reshape(-1, MELS)[: int(used.sum())]
    mean = frames.mean(axis=0, dtype=np.float64) if len(frames) else np.zeros(MELS)
    return ";".join([f"{len(frames)}x{MELS}", str(len(blocks)), ",".join(f"{a}-{b}" for a, b in spans), ",".join(f"{v + 0.0:.3f}" for v in mean), f"{zlib.crc32(tensors.tobytes()):08x}"])


FEATURES = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, tensors binary"


def media_features(docs: DataFrame) -> DataFrame:
    """FEATURES of each text: digests of the payload read back and of the stored form, the features and their tensors."""
    names = [c.split()[0] for c in FEATURES.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, size = [], 0
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                n, payload = payload_of(text.as_py())
                stored = wave_bytes(payload)
                mels, spans, back = analyse(stored)
                stream = tensor_stream(mels, spans)
                rows.append((doc, n, len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-UNIT:]), len(stored), hashlib.sha256(stored).hexdigest(), describe(stream), stream))
                size += len(stream)
                if size > 8 << 20:
                    yield _batch(rows, names)
                    rows, size = [], 0
            if rows:
                yield _batch(rows, names)

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, FEATURES)


def _batch(rows: list[tuple], names: list[str]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c) if k else pa.array(c, pa.int64()) for k, c in enumerate(zip(*rows, strict=True))], names=names)


def op6_audio_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_features(spread(table(spark, sf_dir, "documents")))
