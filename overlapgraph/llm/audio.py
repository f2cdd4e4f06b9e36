"""Audio features: polyphase resampling, log-mel filterbanks and energy segments.

Sound is kept as an 8-bit PCM WAV file in a binary column. Features are computed from the
bytes read back: the samples are resampled by a rational factor (one short filter per phase),
cut into overlapping windows whose power spectra pass a mel filterbank, and the frame
energies are segmented with hysteresis (a segment opens above one level and closes below a lower
one). The log-mel frames of each segment are stored as tensors of a fixed shape with their time spans.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textvec as tv
from .common import text_batches, text_of

ALIGN = 64


@dataclass(frozen=True)
class AudioParams:
    rate: int = 16_000
    up: int = 3
    down: int = 5
    taps: int = 12  # filter taps of one phase
    window: int = 240  # 25 ms at 9.6 kHz
    hop: int = 120
    fft: int = 256
    mels: int = 32
    open_db: float = 6.0
    close_db: float = 3.0
    floor_quantile: float = 0.1
    min_frames: int = 3
    tensor_frames: int = 64

    @property
    def out_rate(self) -> float:
        return self.rate * self.up / self.down


def wav_bytes(samples: bytes, rate: int) -> bytes:
    """A mono 8-bit PCM WAV file (fixed layout); odd lengths get the format's pad byte."""
    pad = b"\0" * (len(samples) % 2)
    head = struct.pack("<4sI4s4sIHHIIHH4sI", b"RIFF", 36 + len(samples) + len(pad), b"WAVE", b"fmt ", 16, 1, 1, rate, rate, 1, 8, b"data", len(samples))
    return head + samples + pad


def read_wav(media: bytes) -> tuple[bytes, int]:
    """(samples, rate) of a mono 8-bit PCM WAV file, whatever other chunks it has."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, rate = 12, None
    while at + 8 <= len(media):
        kind, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if kind == b"fmt ":
            form, channels, rate, _, _, bits = struct.unpack_from("<HHIIHH", media, at + 8)
            if (form, channels, bits) != (1, 1, 8):
                raise ValueError("not mono 8-bit PCM")
        elif kind == b"data":
            if rate is None:
                raise ValueError("no format chunk before the data")
            return media[at + 8 : at + 8 + size], rate
        at += 8 + size + size % 2
    raise ValueError("no data chunk")


@lru_cache
def _phases(up: int, down: int, taps: int) -> np.ndarray:
    """Low-pass filter (windowed sinc) split into one row of taps for each phase."""
    n = np.arange(up * taps) - (up * taps - 1) / 2
    cut = 1.0 / max(up, down)
    h = cut * np.sinc(cut * n) * np.hamming(len(n)) * up
    return np.ascontiguousarray(h.reshape(taps, up).T.astype(np.float32))


def resample(x: np.ndarray, up: int, down: int, taps: int) -> np.ndarray:
    """Samples at up/down times the rate; ceil(n * up / down) of them, the filter's delay removed."""
    h = _phases(up, down, taps)
    n_out = -(-len(x) * up // down)
    out = np.zeros(n_out, np.float32)
    half = taps // 2
    padded = np.concatenate([np.zeros(taps - 1, np.float32), x.astype(np.float32), np.zeros(taps + down, np.float32)])
    view = np.lib.stride_tricks.sliding_window_view(padded, taps)
    for first in range(min(up, n_out)):
        count = len(range(first, n_out, up))
        start, phase = divmod(first * down, up)
        rows = view[start + half : start + half + (count - 1) * down + 1 : down]
        out[first::up] = rows @ h[phase][::-1]
    return out


@lru_cache
def _mel_bank(mels: int, fft: int, rate: float) -> np.ndarray:
    to_mel = lambda f: 2595.0 * np.log10(1.0 + f / 700.0)
    edges = 700.0 * (10.0 ** (np.linspace(to_mel(20.0), to_mel(rate / 2), mels + 2) / 2595.0) - 1.0)
    f = np.arange(fft // 2 + 1) * rate / fft
    lo, mid, hi = edges[:-2, None], edges[1:-1, None], edges[2:, None]
    return np.maximum(0.0, np.minimum((f - lo) / (mid - lo), (hi - f) / (hi - mid))).astype(np.float32)


def log_mel(x: np.ndarray, p: AudioParams) -> tuple[np.ndarray, np.ndarray]:
    """(frames x mels in decibels, frame energies in decibels); at least one frame."""
    if len(x) < p.window:
        x = np.concatenate([x, np.zeros(p.window - len(x), np.float32)])
    view = np.lib.stride_tricks.sliding_window_view(x, p.window)[:: p.hop]
    bank, taper = _mel_bank(p.mels, p.fft, p.out_rate).T, np.hanning(p.window).astype(np.float32)
    mel, energy = np.empty((len(view), p.mels), np.float32), np.empty(len(view), np.float32)
    for a in range(0, len(view), 2048):
        frames = view[a : a + 2048]
        spectrum = np.fft.rfft(frames * taper, p.fft)
        power = spectrum.real**2 + spectrum.imag**2
        mel[a : a + 2048] = 10.0 * np.log10(power @ bank + 1e-6)
        energy[a : a + 2048] = 10.0 * np.log10(np.einsum("ij,ij->i", frames, frames) / p.window + 1e-9)
    return mel, energy


def segments(energy: np.ndarray, p: AudioParams) -> list[tuple[int, int]]:
    """Frame ranges [start, end) that open above one level and close below a lower one."""
    floor = float(np.quantile(energy, p.floor_quantile))
    event = np.where(energy >= floor + p.open_db, 1, np.where(energy < floor + p.close_db, -1, 0))
    last = np.maximum.accumulate(np.where(event != 0, np.arange(len(event)), -1))
    on = (last >= 0) & (event[np.maximum(last, 0)] == 1)
    edge = np.diff(np.concatenate([[0], on.astype(np.int8), [0]]))
    return [(int(a), int(b)) for a, b in zip(np.flatnonzero(edge == 1), np.flatnonzero(edge == -1), strict=True) if b - a >= p.min_frames]


def analyse(media: bytes, p: AudioParams) -> dict:
    """Features of one file: frames, segments, tensors of shape (tensor_frames, mels) with spans."""
    raw, rate = read_wav(media)
    p = p if rate == p.rate else AudioParams(**{**p.__dict__, "rate": rate})
    x = (np.frombuffer(raw, np.uint8).astype(np.float32) - 128.0) / 128.0
    mel, energy = log_mel(resample(x, p.up, p.down, p.taps), p)
    cuts = segments(energy, p)
    return {"raw": raw, "mel": mel, "segments": cuts, "seconds": len(raw) / rate, "params": p}


def tensors(found: dict) -> Iterator[tuple[float, float, int, np.ndarray]]:
    """(start, end in seconds, frames in use, tensor) of each piece of each segment; zeros fill the last."""
    p = found["params"]
    for a, b in found["segments"]:
        for at in range(a, b, p.tensor_frames):
            n = min(p.tensor_frames, b - at)
            out = np.zeros((p.tensor_frames, p.mels), np.float32)
            out[:n] = found["mel"][at : at + n]
            yield at * p.hop / p.out_rate, ((at + n - 1) * p.hop + p.window) / p.out_rate, n, out


@lru_cache
def tensor_schema(p: AudioParams) -> pa.Schema:
    kind = pa.fixed_shape_tensor(pa.float32(), [p.tensor_frames, p.mels])
    return pa.schema([("start_s", pa.float64()), ("end_s", pa.float64()), ("frames", pa.int32()), ("values", kind)])


def store_tensors(found: dict) -> bytes:
    """The pieces of one file as an Arrow stream: time spans, and a column of tensors of one fixed shape.

    Spark has no type of fixed shape, so the column travels as these bytes; any Arrow reader gets the tensors back.
    """
    p = found["params"]
    rows = list(tensors(found))
    flat = np.concatenate([t.reshape(-1) for *_, t in rows]) if rows else np.zeros(0, np.float32)
    schema = tensor_schema(p)
    values = pa.ExtensionArray.from_storage(schema.field("values").type, pa.FixedSizeListArray.from_arrays(pa.array(flat), p.tensor_frames * p.mels))
    cols = [pa.array([r[0] for r in rows], pa.float64()), pa.array([r[1] for r in rows], pa.float64()), pa.array([r[2] for r in rows], pa.int32()), values]
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, schema) as out:
        out.write_batch(pa.RecordBatch.from_arrays(cols, schema=schema))
    return sink.getvalue().to_pybytes()


def load_tensors(stored: bytes) -> pa.Table:
    """Columns start_s, end_s, frames, and values of the fixed-shape tensor type."""
    return pa.ipc.open_stream(stored).read_all()


def feature_text(found: dict, stored: bytes) -> str:
    """The file in one line, the voiced part of it read from the stored tensors."""
    mel, table = found["mel"], load_tensors(stored)
    line = f"frames={len(mel)};mels={mel.shape[1]};segments={len(found['segments'])};mean_db={mel.mean(dtype=np.float64):.1f};max_db={mel.max():.1f};tensors={len(table)}"
    if not len(table):
        return line
    used = table["frames"].to_numpy()
    values = table["values"].combine_chunks().to_numpy_ndarray()
    voiced = values.sum(axis=(1, 2), dtype=np.float64).sum() / (used.sum() * values.shape[2])
    return f"{line};voiced={used.sum()};voiced_db={voiced:.1f};from_s={table['start_s'][0].as_py():.4f};to_s={table['end_s'][-1].as_py():.4f}"


def as_payload(text: str) -> tuple[bytes, int]:
    """UTF-8 bytes, filled with zeros to a positive multiple of 64; and the length before."""
    raw = text.encode("utf-8")
    return raw + b"\0" * (-len(raw) % ALIGN if raw else ALIGN), len(raw)


def encode_media(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", params: AudioParams = AudioParams()) -> DataFrame:
    """(id, n_bytes, media): the bytes of a text as the samples of a WAV file. Null counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tv.pieces(batches):
            made = [as_payload(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([n for _, n in made], pa.int64()), pa.array([wav_bytes(b, params.rate) for b, _ in made], pa.binary())], ["id", "n_bytes", "media"]
            )

    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("n_bytes", T.LongType()), T.StructField("media", T.BinaryType())])
    return text_batches(docs).select(F.col(id_col).cast("long").alias("id"), text_of(text_col).alias("text")).mapInArrow(run, schema)


_FEATURES = (
    ("payload_bytes", pa.int64(), T.LongType()), ("payload_sha256", pa.string(), T.StringType()), ("tail_crc32", pa.int64(), T.LongType()), ("media_bytes", pa.int64(), T.LongType()),
    ("media_sha256", pa.string(), T.StringType()), ("feature", pa.string(), T.StringType()), ("n_tensors", pa.int64(), T.LongType()), ("tensors", pa.binary(), T.BinaryType()),
)


def media_features(media: DataFrame, params: AudioParams = AudioParams(), keep_tensors: bool = True) -> DataFrame:
    """Features of each row (id, n_bytes, media) of ``encode_media``.

    Adds payload_bytes, payload_sha256, tail_crc32 (of the samples read back), media_bytes,
    media_sha256, feature, n_tensors and tensors: an Arrow stream (``load_tensors``) with the time spans and the tensors, all of one
    fixed shape, of the file's segments. The tensors are always made and stored, and the feature is read from them;
    ``keep_tensors=False`` only leaves their column out of the result. Equal media give equal rows; a file that
    is not mono 8-bit WAV raises an error.
    """
    out = _FEATURES if keep_tensors else _FEATURES[:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in tv.pieces(batches):
            rows = []
            for blob in batch.column(2):
                stored = blob.as_py()
                found = analyse(stored, params)
                raw, kept = found["raw"], store_tensors(found)
                pieces = sum(-(-(b - a) // params.tensor_frames) for a, b in found["segments"])
                rows.append((len(raw), hashlib.sha256(raw).hexdigest(), zlib.crc32(raw[-ALIGN:]), len(stored), hashlib.sha256(stored).hexdigest(), feature_text(found, kept), pieces, kept if keep_tensors else None))
            arrays = [pa.array([r[i] for r in rows], t) for i, (_, t, _) in enumerate(out)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *arrays], ["id", "n_bytes", *[n for n, _, _ in out]])

    schema = T.StructType([T.StructField("id", T.LongType()), T.StructField("n_bytes", T.LongType()), *[T.StructField(n, t) for n, _, t in out]])
    return text_batches(media).mapInArrow(run, schema)


def audio_features(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", params: AudioParams = AudioParams(), keep_tensors: bool = True) -> DataFrame:
    """Store each text as sound, read it back and compute its features; one row per input row.

    Null counts as empty text, whose payload is 64 zero bytes. Repeated rows give equal rows; only the id and text are
    read, so other names cannot clash. An empty table gives no row.
    """
    return media_features(encode_media(docs, id_col, text_col, params), params, keep_tensors).withColumnRenamed("id", id_col)
