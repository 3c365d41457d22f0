"""Audio features over 8-bit samples: polyphase resampling, overlapped log-mel filterbanks, energy segments.

Media are WAV files (8-bit mono PCM), written first. Features are computed from stored bytes only: samples are
resampled by a rational factor, cut into overlapping frames, put through a mel filterbank, and laid out as
patches of one fixed shape (frames x bands, 8-bit numbers in half decibels). Patches and their time spans are
stored as an Arrow record batch with a fixed-shape tensor column, one serialised batch a medium; what is said
about a medium is read from there. Segments are runs of frames that rise over a high threshold of energy and
stay over a low one.

Defined cases: null text is an empty payload, which becomes one padding unit; other columns are ignored; an
empty table gives an empty result; equal bytes give equal features, since each medium is worked on alone; rows
that repeat an id are media of their own. Long media are worked on in fixed stretches of frames, so memory
holds one stretch besides the samples.
"""

from __future__ import annotations

import hashlib
import math
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..sources.io import stage
from .texts import pieces

UNIT = 192
RATE, UP, DOWN = 16_000, 3, 4
FRAME, HOP, MELS, PATCH = 256, 128, 24, 32
HIGH_DB, LOW_DB = -3.0, -6.0
_WAV = struct.Struct("<4sI4s4sIHHIIHH4sI")


def to_wav(payload: bytes, rate: int = RATE) -> bytes:
    """8-bit mono PCM; an odd length takes the pad byte that the format asks for."""
    head = _WAV.pack(b"RIFF", 36 + len(payload) + len(payload) % 2, b"WAVE", b"fmt ", 16, 1, 1, rate, rate, 1, 8, b"data", len(payload))
    return head + payload + b"\0" * (len(payload) % 2)


def from_wav(media: bytes) -> tuple[bytes, int]:
    """(payload, rate) of a file of to_wav, by walking through its chunks."""
    if media[:4] != b"RIFF" or media[8:12] != b"WAVE":
        raise ValueError("not a WAV file")
    at, rate = 12, 0
    while at + 8 <= len(media):
        kind, size = media[at : at + 4], struct.unpack_from("<I", media, at + 4)[0]
        if kind == b"fmt ":
            code, channels, rate, _, _, bits = struct.unpack_from("<HHIIHH", media, at + 8)
            if (code, channels, bits) != (1, 1, 8):
                raise ValueError("8-bit mono PCM only")
        elif kind == b"data":
            return media[at + 8 : at + 8 + size], rate
        at += 8 + size + size % 2
    raise ValueError("no samples")


def padded(raw: bytes, unit: int = UNIT) -> bytes:
    return raw + b" " * (max(unit, -(-len(raw) // unit) * unit) - len(raw))


def resampling_matrix(up: int, down: int, half: int = 8) -> tuple[np.ndarray, int]:
    """(K, lead): `up` outputs from a window of inputs are window @ K; the window starts `lead` samples early.

    The windowed-sinc prototype is split into its phases, one a column.
    """
    cutoff = 1 / max(up, down)
    reach = half * max(up, down)
    t = np.arange(-reach, reach + 1)
    h = np.sinc(t * cutoff) * cutoff * np.kaiser(len(t), 6.0) * up
    lead = reach // up
    width = lead + (down * (up - 1) + reach) // up + 1
    k = np.zeros((width, up))
    for r in range(up):
        for j in range(width):
            place = r * down - (j - lead) * up  # distance, on the fine grid, of input j from output r
            if -reach <= place <= reach:
                k[j, r] = h[place + reach]
    return k.astype(np.float32), lead


def resample(x: np.ndarray, up: int = UP, down: int = DOWN) -> np.ndarray:
    k, lead = _kernel(up, down)
    groups = -(-len(x) // down)
    wide = np.zeros(lead + groups * down + len(k), np.float32)
    wide[lead : lead + len(x)] = x
    windows = np.lib.stride_tricks.sliding_window_view(wide, len(k))[: groups * down : down]
    return (np.ascontiguousarray(windows) @ k).ravel()[: -(-len(x) * up // down)]


_cache: dict = {}


def _kernel(up: int, down: int) -> tuple[np.ndarray, int]:
    if (up, down) not in _cache:
        _cache[up, down] = resampling_matrix(up, down)
    return _cache[up, down]


def mel_filters(rate: float, frame: int = FRAME, bands: int = MELS) -> np.ndarray:
    """Triangles equally spaced on the mel scale: (frame/2 + 1, bands)."""
    mel = lambda f: 2595 * np.log10(1 + f / 700)
    edges = 700 * (10 ** (np.linspace(0, mel(rate / 2), bands + 2) / 2595) - 1)
    f = np.linspace(0, rate / 2, frame // 2 + 1)[:, None]
    rise = (f - edges[:-2]) / (edges[1:-1] - edges[:-2])
    fall = (edges[2:] - f) / (edges[2:] - edges[1:-1])
    return np.maximum(0, np.minimum(rise, fall)).astype(np.float32)


def log_mel(x: np.ndarray, rate: float, stretch: int = 4096) -> tuple[np.ndarray, np.ndarray]:
    """(log-mel [frames, bands] in dB, energy [frames] in dB); the last frame is filled with silence."""
    if ("mel", rate) not in _cache:
        _cache["mel", rate] = (mel_filters(rate), np.hanning(FRAME).astype(np.float32))
    filters, window = _cache["mel", rate]
    n = 1 + max(0, -(-(len(x) - FRAME) // HOP))
    wide = np.zeros((n - 1) * HOP + FRAME, np.float32)
    wide[: len(x)] = x[: len(wide)]
    frames = np.lib.stride_tricks.sliding_window_view(wide, FRAME)[::HOP]
    mels, energy = [], []
    for at in range(0, n, stretch):
        f = frames[at : at + stretch] * window
        spectrum = np.fft.rfft(f, axis=1)
        power = (spectrum.real**2 + spectrum.imag**2).astype(np.float32)
        mels.append(10 * np.log10(power @ filters + 1e-6))
        energy.append(10 * np.log10((f * f).mean(axis=1) + 1e-9))
    return np.concatenate(mels), np.concatenate(energy)


def segments(energy: np.ndarray, high: float, low: float) -> np.ndarray:
    """(first, last + 1) frames of runs that start at `high` or more and end below `low`."""
    mark = np.where(energy >= high, 1, np.where(energy < low, -1, 0))
    at = np.maximum.accumulate(np.where(mark != 0, np.arange(len(mark)), -1))
    on = (at >= 0) & (mark[np.maximum(at, 0)] == 1)
    edge = np.diff(np.concatenate(([0], on.view(np.int8), [0])))
    return np.stack([np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)], axis=1)


TENSOR = pa.fixed_shape_tensor(pa.int8(), [PATCH, MELS])
#: Schema of a serialised batch: where a patch begins and ends in its medium, and its log-mel values in half decibels.
STORED = pa.schema([("start_ms", pa.float64()), ("end_ms", pa.float64()), ("log_mel", TENSOR)])
SILENCE = -120


def features(media: bytes) -> dict:
    """Patches [n, frames, bands] in half decibels with spans in ms, segments in ms, of one stored medium."""
    payload, rate = from_wav(media)
    x = (np.frombuffer(payload, np.uint8).astype(np.float32) - 128) / 128
    x = resample(x - x.mean() if len(x) else x)
    at_rate = rate * UP / DOWN
    mel, energy = log_mel(x, at_rate)
    n = len(mel)
    patches = -(-n // PATCH)
    tensor = np.full((patches * PATCH, MELS), SILENCE, np.int8)
    tensor[:n] = np.clip(np.round(mel * 2), SILENCE, 127)  # half a decibel: the last bits of a product are no feature
    ms = 1000 * HOP / at_rate
    starts = np.arange(patches) * PATCH
    spans = np.stack([starts * ms, np.minimum(starts + PATCH, n) * ms], axis=1)
    top = float(np.median(energy))
    runs = segments(energy, top - HIGH_DB, top + LOW_DB)
    return {"frames": n, "tensor": tensor.reshape(patches, PATCH, MELS), "spans": spans, "segments": runs * ms, "energy": energy}


def stored(f: dict) -> bytes:
    """Patches with their spans as a serialised Arrow batch of the schema STORED."""
    cells = pa.FixedSizeListArray.from_arrays(pa.array(f["tensor"].ravel()), PATCH * MELS)
    batch = pa.RecordBatch.from_arrays([pa.array(f["spans"][:, 0]), pa.array(f["spans"][:, 1]), pa.ExtensionArray.from_storage(TENSOR, cells)], schema=STORED)
    return batch.serialize().to_pybytes()


def loaded(raw) -> pa.RecordBatch:
    """The batch that stored() wrote."""
    return pa.ipc.read_record_batch(pa.py_buffer(raw), STORED)


MEDIA = "doc_id long, n_bytes long, media binary"


def media_of(docs: DataFrame, unit: int = UNIT) -> DataFrame:
    """(doc_id, n_bytes, media): whole texts, filled up with spaces to whole units, as WAV files."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch):
                raw = [b"" if t is None else t.encode() for t in part.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([len(r) for r in raw], pa.int64()), pa.array([to_wav(padded(r, unit)) for r in raw], pa.binary())], names=["doc_id", "n_bytes", "media"])

    return docs.select("doc_id", "text").mapInArrow(run, MEDIA)


TENSORS = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, frames long, segments array<double>, tensors binary"
#: Media are worked on so many at a time, and fewer if their bytes pass the other number.
ROWS, BYTES = 256, 4 << 20


def media_tensors(media: DataFrame) -> DataFrame:
    """One row a medium: checksums of what is stored, frames, segments (ms, begin and end in turn), patches as stored()."""
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.list_(pa.float64()), pa.binary()]

    def made(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=[x.split()[0] for x in TENSORS.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, held = [], 0
            for k in range(batch.num_rows):
                m = batch.column("media")[k].as_py()
                payload, f = from_wav(m)[0], features(m)
                rows.append((batch.column("doc_id")[k].as_py(), batch.column("n_bytes")[k].as_py(), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), len(m), hashlib.sha256(m).hexdigest(), f["frames"], f["segments"].ravel(), stored(f)))
                held += len(m)
                if len(rows) >= ROWS or held >= BYTES:
                    yield made(rows)
                    rows, held = [], 0
            if rows:
                yield made(rows)

    return media.select("doc_id", "n_bytes", "media").mapInArrow(run, TENSORS)


def media_patches(tensors: DataFrame) -> DataFrame:
    """Stored tensors to one row a patch: (doc_id, start_ms, end_ms, log_mel), log_mel in decibels, PATCH rows of MELS behind each other."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc_id, raw in zip(batch.column("doc_id").to_pylist(), batch.column("tensors"), strict=True):
                one = loaded(raw.as_buffer())
                values = one.column("log_mel").to_numpy_ndarray().reshape(one.num_rows, -1).astype(np.float32) / 2
                yield pa.RecordBatch.from_arrays([pa.array([doc_id] * one.num_rows, pa.int64()), one.column("start_ms"), one.column("end_ms"), pa.array(list(values), pa.list_(pa.float32()))], names=["doc_id", "start_ms", "end_ms", "log_mel"])

    return tensors.select("doc_id", "tensors").mapInArrow(run, "doc_id long, start_ms double, end_ms double, log_mel array<float>")


def describe(frames: int, segments: np.ndarray, raw) -> str:
    """A line about a medium's stored features: sizes, segments, and a checksum of the tensor column."""
    batch = loaded(raw)
    n, values = batch.num_rows, batch.column("log_mel").storage.flatten()
    active = float((segments[1::2] - segments[::2]).sum())
    crc = zlib.crc32(np.asarray(values).tobytes())
    return f"frames={frames};patches={n}x{PATCH}x{MELS};span_ms={math.floor(batch.column('end_ms')[n - 1].as_py())};segments={len(segments) // 2};active_ms={math.floor(active)};log_mel_crc32={crc:08x}"


DIGEST = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def digest(tensors: DataFrame) -> DataFrame:
    """One row a medium: its checksums, and a line about the features read from the stored tensors."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lines = [describe(n, np.asarray(runs.as_py(), np.float64), raw.as_buffer()) for n, runs, raw in zip(batch.column("frames").to_pylist(), batch.column("segments"), batch.column("tensors"), strict=True)]
            keep = [x.split()[0] for x in DIGEST.split(", ")][:-1]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in keep), pa.array(lines, pa.string())], names=[*keep, "feature"])

    return tensors.mapInArrow(run, DIGEST)


def op2_audio_features(spark, sf_dir: str) -> DataFrame:
    """All documents as WAV files, written and read back; their tensors, written and read back; a line about each."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return digest(stage(media_tensors(stage(media_of(docs), "media", compression="zstd")), "tensors", compression="zstd"))
