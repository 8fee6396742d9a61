"""Audio features of 8-bit samples: polyphase resampling, log-mel frames, energy segments, fixed-shape tensors.

Samples are kept in a WAV container (mono, unsigned 8 bits), read back from its bytes and resampled by ``UP / DOWN``
with the branches of one windowed-sinc filter, so no zero-stuffed signal is ever made. Overlapped Hann frames give
log-mel values; frame energies are cut into segments by two thresholds: a segment opens above the upper one and stays
open until the energy falls below the lower one. Frames are padded to whole tensors of ``FRAMES x MELS`` float32, each
with the span of time it covers; ``store`` keeps them as an Arrow stream with a fixed-shape tensor column, and the query
reads its features back from there.

Null and empty payloads become one block of zero bytes. A result depends on the payload only.
"""

from __future__ import annotations

import hashlib
import math
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from privq.llm.common import table, text_or_empty, tidy

RATE, UP, DOWN, TAPS = 16_000, 1, 2, 16
WINDOW, HOP, MELS, FRAMES = 256, 128, 20, 64
OPEN_DB, CLOSE_DB = -12.0, -15.0
BLOCK = 64
#: Frames that are transformed at a time, for bounded memory.
AT_A_TIME = 4096


def padded(payload: bytes) -> bytes:
    return payload + bytes(-len(payload) % BLOCK or (0 if payload else BLOCK))


def to_wav(samples: bytes, rate: int = RATE) -> bytes:
    """Mono 8-bit PCM in a RIFF container."""
    odd = len(samples) % 2
    head = struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(samples) + odd, b"WAVE", b"fmt ", 16, 1, 1, rate, rate, 1, 8, b"data", len(samples))
    return head + samples + b"\0" * odd


def from_wav(media: bytes) -> tuple[bytes, int]:
    """Samples and rate, found by walking the chunks."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a RIFF WAVE container")
    at, rate = 12, 0
    while at + 8 <= len(media):
        name, size = struct.unpack_from("<4sI", media, at)
        if name == b"fmt ":
            rate = struct.unpack_from("<I", media, at + 12)[0]
        elif name == b"data":
            return media[at + 8 : at + 8 + size], rate
        at += 8 + size + size % 2
    raise ValueError("no data chunk")


def low_pass(up: int, down: int, taps: int) -> np.ndarray:
    """Hann-windowed sinc for the narrower of both rates, ``taps`` for each branch, gain ``up``."""
    n = taps * up
    x = np.arange(n) - (n - 1) / 2
    cut = 1.0 / max(up, down)
    h = cut * np.sinc(cut * x) * np.hanning(n + 2)[1:-1]
    return (h / h.sum() * up).astype(np.float32)


def resample(x: np.ndarray, up: int = UP, down: int = DOWN, taps: int = TAPS) -> np.ndarray:
    """Output k uses branch ``k * down % up`` of the filter at input ``k * down // up``."""
    h = low_pass(up, down, taps)
    n_out = -(-len(x) * up // down)
    line = np.concatenate([np.zeros(taps - 1, x.dtype), x])
    out = np.empty(n_out, np.float32)
    for first in range(up):  # outputs first, first + up, ... share a branch and step by `down` inputs
        k = np.arange(first, n_out, up)
        if not len(k):
            continue
        branch, start = h[first * down % up :: up], first * down // up
        acc = np.zeros(len(k), np.float32)
        for t, weight in enumerate(branch):
            lo = start + taps - 1 - t
            acc += weight * line[lo : lo + (len(k) - 1) * down + 1 : down]
        out[first::up] = acc
    return out


def mel_bank(rate: int, window: int, mels: int) -> np.ndarray:
    """Triangles evenly spaced in mel, as a matrix of spectrum bins x mels."""
    top = 2595 * math.log10(1 + rate / 2 / 700)
    edges = 700 * (10 ** (np.linspace(0, top, mels + 2) / 2595) - 1)
    bins = np.arange(window // 2 + 1) * rate / window
    rise = (bins[:, None] - edges[None, :-2]) / (edges[1:-1] - edges[:-2])
    fall = (edges[None, 2:] - bins[:, None]) / (edges[2:] - edges[1:-1])
    return np.maximum(0, np.minimum(rise, fall)).astype(np.float32)


_HANN = np.hanning(WINDOW + 1)[:-1].astype(np.float32)
_BANK = mel_bank(RATE * UP // DOWN, WINDOW, MELS)


def log_mel(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Log-mel frames and each frame's energy in dB; the last frame is padded with zeros."""
    n = max(1, -(-max(0, len(x) - WINDOW) // HOP) + 1)
    x = np.concatenate([x, np.zeros((n - 1) * HOP + WINDOW - len(x), np.float32)]) if len(x) < (n - 1) * HOP + WINDOW else x
    frames = np.lib.stride_tricks.sliding_window_view(x, WINDOW)[::HOP][:n]
    mel, energy = np.empty((n, MELS), np.float32), np.empty(n, np.float32)
    for lo in range(0, n, AT_A_TIME):
        part = frames[lo : lo + AT_A_TIME]
        spectrum = np.fft.rfft(part * _HANN, axis=1)
        power = (spectrum.real**2 + spectrum.imag**2).astype(np.float32)
        mel[lo : lo + AT_A_TIME] = np.log10(power @ _BANK + 1e-6)
        energy[lo : lo + AT_A_TIME] = 10 * np.log10((part * part).mean(axis=1) + 1e-10)
    return mel, energy


def segments(energy: np.ndarray, open_db: float = OPEN_DB, close_db: float = CLOSE_DB) -> list[tuple[int, int]]:
    """Frame ranges between a rise above ``open_db`` and the next fall below ``close_db``."""
    says = np.where(energy > open_db, 1, np.where(energy < close_db, 0, -1))
    last = np.maximum.accumulate(np.where(says >= 0, np.arange(len(says)), -1))
    state = np.where(last >= 0, says[np.maximum(last, 0)], 0)
    turns = np.flatnonzero(np.diff(np.concatenate([[0], state, [0]])))
    return list(zip(turns[::2].tolist(), turns[1::2].tolist(), strict=True))


def analyse(media: bytes) -> tuple[np.ndarray, list[tuple[float, float]], list[tuple[float, float]]]:
    """Tensors (n x FRAMES x MELS), the span of each in seconds, and the spans of the energy segments."""
    samples, rate = from_wav(media)
    x = (np.frombuffer(samples, np.uint8).astype(np.float32) - 128.0) / 128.0
    mel, energy = log_mel(resample(x))
    step, seconds = HOP * DOWN / UP / rate, len(samples) / rate
    n = -(-len(mel) // FRAMES)
    tensor = np.zeros((n, FRAMES, MELS), np.float32)
    tensor.reshape(-1, MELS)[: len(mel)] = mel
    spans = [(k * FRAMES * step, min(seconds, (k + 1) * FRAMES * step)) for k in range(n)]
    return tensor, spans, [(lo * step, min(seconds, hi * step)) for lo, hi in segments(energy)]


def to_fixed_shape(flat: pa.Array) -> pa.Array:
    """List column of flat tensors as an Arrow column of fixed-shape tensors."""
    values = flat.flatten().cast(pa.float32())
    return pa.ExtensionArray.from_storage(pa.fixed_shape_tensor(pa.float32(), (FRAMES, MELS)), pa.FixedSizeListArray.from_arrays(values, FRAMES * MELS))


_SPANS = pa.list_(pa.struct([("start_s", pa.float64()), ("end_s", pa.float64())]))


def tensor_rows(media: bytes) -> pa.RecordBatch:
    """One row per tensor: its time span, the energy segments that it touches, and the tensor (fixed shape)."""
    tensor, spans, voiced = analyse(media)
    near = [[{"start_s": a, "end_s": b} for a, b in voiced if a < hi and b > lo] for lo, hi in spans]
    flat = pa.FixedSizeListArray.from_arrays(pa.array(tensor.ravel()), FRAMES * MELS).cast(pa.list_(pa.float32()))
    return pa.RecordBatch.from_arrays([pa.array([s[0] for s in spans]), pa.array([s[1] for s in spans]), pa.array(near, _SPANS), to_fixed_shape(flat)], ["start_s", "end_s", "voiced", "tensor"])


def store(rows: pa.RecordBatch) -> bytes:
    """Tensor rows as an Arrow stream, which keeps their fixed-shape type."""
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, rows.schema) as writer:
        writer.write_batch(rows)
    return sink.getvalue().to_pybytes()


def load(stored: bytes) -> tuple[np.ndarray, list[tuple[float, float]], list[tuple[float, float]]]:
    """Tensors, their spans and the energy segments of a stored stream."""
    rows = pa.ipc.open_stream(stored).read_all().combine_chunks()
    spans = list(zip(rows["start_s"].to_pylist(), rows["end_s"].to_pylist(), strict=True))
    voiced = sorted({(v["start_s"], v["end_s"]) for near in rows["voiced"].to_pylist() for v in near})
    return rows["tensor"].chunk(0).to_numpy_ndarray(), spans, voiced


def _tensor_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = ["media_id", "chunk", "start_s", "end_s", "voiced", "tensor"]
    for batch in batches:
        for media_id, payload in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            rows = tensor_rows(to_wav(padded(payload or b"")))
            n = rows.num_rows
            yield pa.RecordBatch.from_arrays([pa.array([media_id] * n, batch.column(0).type), pa.array(range(n), pa.int32()), *rows.columns[:3], rows.column(3).storage.cast(pa.list_(pa.float32()))], names)


def audio_tensors(df: DataFrame, id_column: str, payload_column: str) -> DataFrame:
    """One row per tensor: its place, time span, the segments it touches, and FRAMES * MELS values."""
    body = df.select(df[id_column].cast("long").alias("media_id"), df[payload_column].cast("binary").alias("payload"))
    return body.mapInArrow(tidy(_tensor_batches), "media_id bigint, chunk int, start_s double, end_s double, voiced array<struct<start_s: double, end_s: double>>, tensor array<float>")


def _media_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for lo in range(0, batch.num_rows, 64):
            part = batch.slice(lo, 64)
            media = [to_wav(padded(x.as_buffer().to_pybytes() if x.is_valid else b"")) for x in part.column(1)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(media, pa.binary()), pa.array([store(tensor_rows(m)) for m in media], pa.binary())], ["media_id", "media", "tensors"])


def media_columns(df: DataFrame, id_column: str, payload_column: str) -> DataFrame:
    """One row per payload: the WAV bytes, and its fixed-shape tensors with spans as an Arrow stream (see ``load``)."""
    body = df.select(df[id_column].cast("long").alias("media_id"), df[payload_column].cast("binary").alias("payload"))
    return body.mapInArrow(tidy(_media_batches), "media_id bigint, media binary, tensors binary")


def digest(payload: bytes | None) -> tuple:
    """Row of the query for one payload; features are read back from the stored tensors."""
    raw = payload or b""
    media = to_wav(padded(raw))
    back, _ = from_wav(media)
    tensor, spans, voiced = load(store(tensor_rows(media)))
    seen = hashlib.sha256(tensor.tobytes() + np.array([*spans, *voiced], np.float64).tobytes()).hexdigest()
    feature = f"logmel={tensor.shape[0]}x{FRAMES}x{MELS};seconds={spans[-1][1]:.6f};segments={len(voiced)};voiced={sum(b - a for a, b in voiced):.6f};sha256={seen}"
    return len(raw), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-BLOCK:]), len(media), hashlib.sha256(media).hexdigest(), feature


_DIGEST = [("n_bytes", pa.int64()), ("payload_bytes", pa.int64()), ("payload_sha256", pa.string()), ("tail_crc32", pa.int64()), ("media_bytes", pa.int64()), ("media_sha256", pa.string()), ("feature", pa.string())]


def _digest_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        rows = [digest(x.as_buffer().to_pybytes() if x.is_valid else None) for x in batch.column(1)]
        columns = zip(*rows, strict=True) if rows else [[] for _ in _DIGEST]
        yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, t) for c, (_, t) in zip(columns, _DIGEST, strict=True))], ["doc_id", *(n for n, _ in _DIGEST)])


def op6_audio_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole texts of ``documents`` as 8-bit samples, their stored form and features."""
    docs = table(spark, sf_dir, "documents").select("doc_id", text_or_empty().cast("binary").alias("payload"))
    return docs.mapInArrow(tidy(_digest_batches), "doc_id bigint, n_bytes bigint, payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string")
