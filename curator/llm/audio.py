"""Audio features of stored samples: polyphase resampling, log-mel filterbanks, hysteresis segments.

A payload is stored without loss as an 8-bit mono WAV file, read back from the file's bytes, resampled by a rational
factor with a polyphase windowed-sinc filter, cut into overlapping frames, and turned into log-mel energies.  Frames
whose energy passes the upper threshold open a segment, which lasts until the energy falls under the lower one.
Log-mel frames are stored as an Arrow stream of fixed-shape tensors (``TENSOR_FRAMES`` x ``MELS``) with the time span of each.

Every text is handled by itself, in blocks of frames, so equal texts give equal values wherever they stand and a
very long one needs no more memory than a block beyond its own bytes.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from curator.llm import flat

RATE, UP, DOWN = 16000, 3, 4
#: Filter taps of one phase.
TAPS = 16
FRAME, HOP, MELS = 256, 128, 40
UPPER_DB, LOWER_DB = 1.0, 0.3
TENSOR_FRAMES = 64
BLOCK = 2048


def payload_of(text: bytes) -> bytes:
    """The text's bytes with bytes 0 up to a positive multiple of 64."""
    return text + b"\0" * (64 - len(text) % 64 if len(text) % 64 or not text else 0)


def to_wav(payload: bytes, rate: int = RATE) -> bytes:
    """An 8-bit mono PCM WAV file of the payload (of even length)."""
    fmt = struct.pack("<4sIHHIIHH", b"fmt ", 16, 1, 1, rate, rate, 1, 8)
    return struct.pack("<4sI4s", b"RIFF", 36 + len(payload), b"WAVE") + fmt + struct.pack("<4sI", b"data", len(payload)) + payload


def from_wav(stored: bytes) -> tuple[bytes, int]:
    """Samples and rate of an 8-bit mono WAV file, chunk by chunk."""
    if stored[:4] != b"RIFF" or stored[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, rate = 12, 0
    while at + 8 <= len(stored):
        name, size = struct.unpack_from("<4sI", stored, at)
        if name == b"fmt ":
            kind, channels, rate, _, _, bits = struct.unpack_from("<HHIIHH", stored, at + 8)
            if (kind, channels, bits) != (1, 1, 8):
                raise ValueError("only 8-bit mono samples are read")
        elif name == b"data":
            return stored[at + 8 : at + 8 + size], rate
        at += 8 + size + size % 2
    raise ValueError("no samples")


@lru_cache(maxsize=8)
def _phases(up: int, down: int, taps: int = TAPS) -> np.ndarray:
    """Taps of each phase of the interpolating low-pass filter: (up, taps)."""
    n = up * taps
    cutoff = 1 / max(up, down)
    t = np.arange(n) - (n - 1) / 2
    h = np.sinc(t * cutoff) * np.kaiser(n, 7.0)
    h *= up / h.sum()
    return np.ascontiguousarray(h.reshape(taps, up).T[:, ::-1]).astype(np.float32)


def resample(x: np.ndarray, up: int, down: int, taps: int = TAPS) -> np.ndarray:
    """Output m is filtered at position m * down / up of the input; only the phase that m needs is computed."""
    h = _phases(up, down, taps)
    n = -(-len(x) * up // down)
    padded = np.concatenate([np.zeros(taps - 1, dtype=np.float32), x, np.zeros(taps, dtype=np.float32)])
    views = np.lib.stride_tricks.sliding_window_view(padded, taps)
    m = np.arange(n)
    out = np.empty(n, dtype=np.float32)
    for p in range(min(up, n)):
        mine = m[p::up]
        phase = int(mine[0]) * down % up
        first, step = int(mine[0]) * down // up, down
        rows = views[first : first + step * len(mine) : step]
        for a in range(0, len(mine), 1 << 16):
            out[p + a * up : p + (a + len(rows[a : a + (1 << 16)])) * up : up] = np.einsum("ij,j->i", rows[a : a + (1 << 16)], h[phase])
    return out


@lru_cache(maxsize=4)
def _mel_bank(rate: int) -> np.ndarray:
    """Triangles on the mel scale: (bins, mels)."""
    to_mel, to_hz = (lambda f: 2595 * np.log10(1 + f / 700)), (lambda m: 700 * (10 ** (m / 2595) - 1))
    edges = to_hz(np.linspace(to_mel(20.0), to_mel(rate / 2), MELS + 2))
    bins = np.linspace(0, rate / 2, FRAME // 2 + 1)
    rise = (bins[:, None] - edges[None, :-2]) / (edges[1:-1] - edges[:-2])
    fall = (edges[None, 2:] - bins[:, None]) / (edges[2:] - edges[1:-1])
    return np.maximum(0, np.minimum(rise, fall)).astype(np.float32)


_window = np.hanning(FRAME + 1)[:-1].astype(np.float32)


def log_mel(x: np.ndarray, rate: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Blocks of (log-mel energies, frame energy in dB) of overlapping frames; the last frame is padded with zeros."""
    n = max(1, -(-(len(x) - FRAME) // HOP) + 1)
    padded = np.zeros((n - 1) * HOP + FRAME, dtype=np.float32)
    padded[: len(x)] = x[: len(padded)]
    frames = np.lib.stride_tricks.sliding_window_view(padded, FRAME)[::HOP]
    bank = _mel_bank(rate)
    for a in range(0, n, BLOCK):
        spectrum = np.fft.rfft(frames[a : a + BLOCK] * _window, axis=1)
        power = (spectrum.real**2 + spectrum.imag**2).astype(np.float32)
        yield np.log(power @ bank + np.float32(1e-6)), 10 * np.log10(power.mean(axis=1) + np.float32(1e-9))


def segments(energy: np.ndarray, floor: float, upper: float = UPPER_DB, lower: float = LOWER_DB) -> list[tuple[int, int]]:
    """Runs of frames that start above floor + upper and end before one at or below floor + lower."""
    high, low = energy > floor + upper, energy <= floor + lower
    mark = np.where(high, 1, np.where(low, -1, 0))
    at = np.flatnonzero(mark)
    state = np.zeros(len(energy), dtype=np.int8)
    if len(at):
        last = np.maximum.accumulate(np.where(mark != 0, np.arange(len(mark)), -1))
        state = np.where(last >= 0, mark[last] > 0, False).astype(np.int8)
    turn = np.flatnonzero(np.diff(np.concatenate([[0], state, [0]])))
    return [(int(a), int(b)) for a, b in zip(turn[::2], turn[1::2], strict=True)]


class Analysis:
    """Features of one payload."""

    def __init__(self, payload: bytes, rate: int = RATE, keep: bool = False):
        x = (np.frombuffer(payload, dtype=np.uint8).astype(np.float32) - 128) / 128
        self.rate = rate * UP // DOWN
        y = resample(x, UP, DOWN)
        mels, energy, total = [], [], np.zeros(MELS)
        for block, db in log_mel(y, self.rate):
            total += block.sum(axis=0, dtype=np.float64)
            energy.append(db)
            if keep:
                mels.append(block)
        energy = np.concatenate(energy)
        self.frames = len(energy)
        self.mean = total / self.frames
        self.segments = segments(energy, float(np.median(energy)))
        self.mels = np.concatenate(mels) if keep else None

    def feature(self) -> str:
        """Frames, segments, frames within them, and ten band means in steps of a tenth."""
        inside = sum(b - a for a, b in self.segments)
        bands = self.mean.reshape(10, -1).mean(axis=1)
        return f"{self.frames};{len(self.segments)};{inside};" + ",".join(f"{round(float(b), 1) + 0.0:.1f}" for b in bands)

    def tensors(self) -> list[tuple[float, float, np.ndarray]]:
        """(begin s, end s, TENSOR_FRAMES x MELS) pieces, the last padded with its floor."""
        out = []
        for a in range(0, self.frames, TENSOR_FRAMES):
            part = self.mels[a : a + TENSOR_FRAMES]
            full = np.full((TENSOR_FRAMES, MELS), np.float32(np.log(1e-6)), dtype=np.float32)
            full[: len(part)] = part
            out.append((a * HOP / self.rate, ((a + len(part) - 1) * HOP + FRAME) / self.rate, full))
        return out


#: Arrow type of one tensor, and what is stored of a document: its tensors and the time that each spans.
TENSOR = pa.fixed_shape_tensor(pa.float32(), (TENSOR_FRAMES, MELS), dim_names=["frame", "mel"])
STORED = pa.schema([("tensor", TENSOR), ("begin", pa.float64()), ("end", pa.float64())])


def write_tensors(pieces: list[tuple[float, float, np.ndarray]]) -> bytes:
    """An Arrow stream of the pieces' fixed-shape tensors and spans."""
    values = pa.FixedSizeListArray.from_arrays(pa.array(np.concatenate([p[2].reshape(-1) for p in pieces])), TENSOR_FRAMES * MELS)
    columns = [pa.ExtensionArray.from_storage(TENSOR, values), pa.array([p[0] for p in pieces]), pa.array([p[1] for p in pieces])]
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, STORED) as writer:
        writer.write_batch(pa.RecordBatch.from_arrays(columns, schema=STORED))
    return sink.getvalue().to_pybytes()


def read_tensors(stored: bytes) -> tuple[np.ndarray, np.ndarray]:
    """The tensors (pieces, TENSOR_FRAMES, MELS) and spans (pieces, 2) of such a stream."""
    table = pa.ipc.open_stream(stored).read_all().combine_chunks()
    return table["tensor"].chunk(0).to_numpy_ndarray(), np.stack([table["begin"].to_numpy(), table["end"].to_numpy()], axis=1)


def _run(with_media: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = flat.buffers(batch.column(1))
            for i, j in flat.slices(offsets, 1 << 20):
                cols: list[list] = [[] for _ in range(11)]
                for d in range(i, j):
                    text = data[offsets[d] : offsets[d + 1]].tobytes()
                    stored = to_wav(payload_of(text))
                    back, rate = from_wav(stored)
                    seen = Analysis(back, rate, keep=with_media)
                    row = [len(text), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(stored), hashlib.sha256(stored).hexdigest(), seen.feature()]
                    if with_media:
                        pieces = seen.tensors()
                        row += [stored, write_tensors(pieces), [{"begin": p[0], "end": p[1]} for p in pieces], [{"first": a, "stop": b} for a, b in seen.segments]]
                    for c, value in zip(cols, row, strict=False):
                        c.append(value)
                types = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
                names = ["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
                if with_media:
                    span = pa.struct([("begin", pa.float64()), ("end", pa.float64())])
                    types += [pa.binary(), pa.binary(), pa.list_(span), pa.list_(pa.struct([("first", pa.int32()), ("stop", pa.int32())]))]
                    names += ["media", "tensors", "spans", "segments"]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, j - i), *[pa.array(c, t) for c, t in zip(cols, types, strict=False)]], names=["doc_id", *names])

    return run


def audio_features(docs: DataFrame, with_media: bool = True) -> DataFrame:
    """documents -> digests, feature string and, if asked, the stored file, tensors, their spans and segments; map-only.

    Null reads as empty: a payload of 64 zero bytes.  ``tensors`` is an Arrow stream of TENSOR_FRAMES x MELS fixed-shape
    tensors with their spans in seconds, which :func:`read_tensors` reads; ``segments`` are runs of frames.  Every row
    is handled by itself: repeated rows give repeated results, and other columns are ignored.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    if with_media:
        schema += ", media binary, tensors binary, spans array<struct<begin:double,end:double>>, segments array<struct<first:int,stop:int>>"
    return rows.mapInArrow(_run(with_media), schema)
