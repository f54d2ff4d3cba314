"""Media columns: bytes as 8-bit audio, and features of the audio.

`to_wav` stores any payload as the samples of a mono WAV file, `from_wav` reads it back, `audio_features` resamples with a
polyphase filter, takes overlapped log-mel frames and finds active segments by energy with hysteresis. Frames are
stored as Arrow fixed-shape tensors of (frames, bands), one for each block of frames, with the block's time span;
the last block is padded with the floor value and `n_frames` tells how many rows are real.

Each row is computed by itself, so that equal payloads give equal results whatever else a batch holds. Edge cases:
null text counts as empty; an empty text is one block of padding; null or broken media give null features; memory is
bounded by the longest single text.
"""

from __future__ import annotations

import struct
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

RATE, UP, DOWN = 12_000, 2, 3
FRAME, HOP, BANDS, BLOCK = 256, 128, 16, 64
FLOOR = 1e-6


def wav_bytes(samples: bytes, rate: int = RATE) -> bytes:
    """A RIFF file of unsigned 8-bit mono samples (of an even number, so that chunks need no padding)."""
    form = struct.pack("<4sIHHIIHH", b"fmt ", 16, 1, 1, rate, rate, 1, 8)
    return struct.pack("<4sI4s", b"RIFF", 4 + len(form) + 8 + len(samples), b"WAVE") + form + struct.pack("<4sI", b"data", len(samples)) + samples


def wav_samples(media: bytes) -> tuple[bytes, int]:
    """The samples and the rate of a WAV file."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, rate = 12, 0
    while at + 8 <= len(media):
        name, size = struct.unpack_from("<4sI", media, at)
        if name == b"fmt ":
            rate = struct.unpack_from("<I", media, at + 12)[0]
        elif name == b"data":
            return media[at + 8 : at + 8 + size], rate
        at += 8 + size + size % 2
    raise ValueError("no samples")


def padded(text: bytes, to: int = 64) -> bytes:
    """text and bytes 0 up to a positive multiple of `to`."""
    return text + bytes(-len(text) % to if text else to)


@lru_cache(maxsize=4)
def _filter(up: int, down: int, taps: int = 16) -> np.ndarray:
    """(up, taps): the windowed-sinc low-pass of each phase, newest sample last."""
    n = np.arange(up * taps) - (up * taps - 1) / 2
    wide = max(up, down)
    h = np.sinc(n / wide) * np.hamming(up * taps) * up / wide
    return np.stack([h[p::up][::-1] for p in range(up)]).astype(np.float32)


def resample(x: np.ndarray, up: int, down: int) -> np.ndarray:
    """Rational resampling: each output is one phase of the filter over the input; no zeros are multiplied."""
    taps = _filter(up, down)
    n = -(-len(x) * up // down)
    seen = np.lib.stride_tricks.sliding_window_view(np.concatenate([np.zeros(taps.shape[1] - 1, np.float32), x, np.zeros(down, np.float32)]), taps.shape[1])
    out = np.empty(n, np.float32)
    for k in range(min(up, n)):  # outputs k, k + up, ... share the phase and step by `down` inputs
        own = -(-(n - k) // up)
        out[k::up] = seen[k * down // up :: down][:own] @ taps[k * down % up]
    return out


@lru_cache(maxsize=2)
def _mel(rate: float) -> np.ndarray:
    """(FRAME / 2 + 1, BANDS) triangles, evenly spaced on the mel scale."""
    mel = lambda f: 2595 * np.log10(1 + f / 700)
    edges = 700 * (10 ** (np.linspace(mel(60), mel(rate / 2), BANDS + 2) / 2595) - 1)
    f = np.fft.rfftfreq(FRAME, 1 / rate)[:, None]
    return np.clip(np.minimum((f - edges[:-2]) / (edges[1:-1] - edges[:-2]), (edges[2:] - f) / (edges[2:] - edges[1:-1])), 0, None).astype(np.float32)


_WINDOW = np.hanning(FRAME).astype(np.float32)


def log_mel(x: np.ndarray, rate: float) -> np.ndarray:
    """(frames, BANDS) of frames that overlap by half; at least one."""
    n = max(1, -(-max(0, len(x) - FRAME) // HOP) + 1)
    x = np.concatenate([x, np.zeros((n - 1) * HOP + FRAME - len(x), np.float32)])
    out = np.empty((n, BANDS), np.float32)
    for at in range(0, n, 4096):
        frames = np.lib.stride_tricks.sliding_window_view(x, FRAME)[at * HOP :: HOP][: min(4096, n - at)]
        out[at : at + len(frames)] = np.log(np.abs(np.fft.rfft(frames * _WINDOW, axis=1)) ** 2 @ _mel(rate) + FLOOR)
    return out


def segments(energy: np.ndarray, on: float, off: float) -> list[tuple[int, int]]:
    """Half-open runs of frames: one starts where the energy exceeds `on` and lasts until it falls below `off`."""
    mark = np.where(energy > on, 1, np.where(energy < off, 0, -1))
    mark[0] = max(mark[0], 0)
    last = np.maximum.accumulate(np.where(mark >= 0, np.arange(len(mark)), 0))
    state = np.concatenate([[0], mark[last], [0]])
    step = np.diff(state)
    return list(zip(np.flatnonzero(step == 1).tolist(), np.flatnonzero(step == -1).tolist(), strict=True))


def features_of(media: bytes) -> tuple[bytes, int, bytes, list[tuple[float, float]]]:
    """payload read back, number of frames, tensors as an Arrow stream, active spans in seconds."""
    payload, rate = wav_samples(media)
    x = (np.frombuffer(payload, np.uint8).astype(np.float32) - 128) / 128
    y, new_rate = resample(x, UP, DOWN), rate * UP / DOWN
    mel = log_mel(y, new_rate)
    energy = mel.mean(axis=1)
    middle = float(np.median(energy))
    active = [(a * HOP / new_rate, ((b - 1) * HOP + FRAME) / new_rate) for a, b in segments(energy, middle + 0.2, middle)]
    blocks = -(-len(mel) // BLOCK)
    full = np.full((blocks * BLOCK, BANDS), np.log(FLOOR), np.float32)
    full[: len(mel)] = mel
    return payload, len(mel), tensor_stream(full.reshape(blocks, BLOCK, BANDS), len(mel), new_rate), active


def tensor_stream(blocks: np.ndarray, n_frames: int, rate: float) -> bytes:
    """An Arrow stream of columns t_start, t_end, n_frames and logmel, the last of type fixed_shape_tensor(float32, (BLOCK, BANDS))."""
    start = np.arange(len(blocks)) * BLOCK
    real = np.minimum(BLOCK, n_frames - start)
    batch = pa.record_batch(
        [pa.array(start * HOP / rate), pa.array(((start + real - 1) * HOP + FRAME) / rate), pa.array(real.astype(np.int32)), pa.FixedShapeTensorArray.from_numpy_ndarray(blocks)],
        ["t_start", "t_end", "n_frames", "logmel"],
    )
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema) as writer:
        writer.write_batch(batch)
    return sink.getvalue().to_pybytes()


def read_tensors(stream: bytes) -> tuple[np.ndarray, list[dict]]:
    """The blocks of tensor_stream and their spans."""
    table = pa.ipc.open_stream(stream).read_all()
    return table.column("logmel").combine_chunks().to_numpy_ndarray(), table.select(["t_start", "t_end", "n_frames"]).to_pylist()


def to_wav(text: Column | str, to: int = 64) -> Column:
    """The padded UTF-8 bytes of each text as a WAV file."""

    @F.arrow_udf("binary")
    def media(column: pa.Array) -> pa.Array:
        return pa.array([wav_bytes(padded((t.as_py() or "").encode(), to)) for t in column], pa.binary())

    return media(text)



def audio_features(media: Column | str) -> Column:
    """struct of payload (read back), n_frames, tensors (see tensor_stream) and active (spans in seconds)."""
    kind = pa.struct([("payload", pa.binary()), ("n_frames", pa.int32()), ("tensors", pa.binary()), ("active", pa.list_(pa.struct([("t_start", pa.float64()), ("t_end", pa.float64())])))])

    @F.arrow_udf("struct<payload: binary, n_frames: int, tensors: binary, active: array<struct<t_start: double, t_end: double>>>")
    def features(column: pa.Array) -> pa.Array:
        rows = []
        for m in column:
            try:
                payload, n, tensors, active = features_of(m.as_py())
                rows.append({"payload": payload, "n_frames": n, "tensors": tensors, "active": [{"t_start": a, "t_end": b} for a, b in active]})
            except (TypeError, ValueError, struct.error):
                rows.append(None)
        return pa.array(rows, kind)

    return features(media)
