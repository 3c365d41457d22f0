"""Texts of an Arrow batch as flat byte arrays, and vectorised words and hashes over them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Bytes of text worked on at once inside a batch; one longer text is worked on alone.
PIECE = 2 << 20
_U = np.uint64
_held: dict[tuple, object] = {}


def held(key: tuple, make: Callable[[], object]) -> object:
    """The one large object a worker keeps between tasks; another operator's takes its place, so they do not add up."""
    if key not in _held:
        _held.clear()
        _held[key] = make()
    return _held[key]


SPACES = np.zeros(256, bool)
SPACES[[32, *range(9, 14)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def pieces(batch: pa.RecordBatch, most: int = PIECE) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose texts (column `text`) hold about `most` bytes; rows are never split."""
    sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column("text")), 0), dtype=np.int64)
    ends, at = np.cumsum(sizes), 0
    while at < len(sizes):
        base = ends[at - 1] if at else 0
        stop = max(at + 1, int(np.searchsorted(ends, base + most, side="right")))
        yield batch.slice(at, stop - at)
        at = stop


def flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets): all texts of a string column behind each other; null is empty."""
    if column.null_count:
        column = pc.fill_null(column, "")
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    at = np.frombuffer(offsets, np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data is not None else np.zeros(0, np.uint8)
    return raw, at - at[0]


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads 64 bits, one to one."""
    x = x ^ (x >> _U(30))
    x *= _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x *= _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


_KEEP = np.array([(1 << 8 * n) - 1 for n in range(9)], _U)
_PLACE, _SIZE = _U(0x9E3779B97F4A7C15), _U(0xD6E8FEB86659FD93)
#: Spans worked on at once.
_SPANS = 1 << 18


def padded(raw: np.ndarray) -> np.ndarray:
    """A row of bytes as one 8-byte number from each place on (zeros follow the last)."""
    wide = np.zeros(len(raw) + 8, np.uint8)
    wide[: len(raw)] = raw
    return np.ndarray((len(raw) + 1,), "<u8", wide, strides=(1,))


def chunks(numbers: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(8-byte chunks of all spans, first chunk of each span, chunks of each span); an empty span has one chunk, 0."""
    sizes = ends - starts
    n = np.maximum((sizes + 7) >> 3, 1)
    last = np.cumsum(n)
    first = last - n
    at = np.arange(last[-1] if len(last) else 0)
    values = numbers[np.minimum(np.repeat(starts - 8 * first, n) + 8 * at, len(numbers) - 1)]
    values[last - 1] &= _KEEP[sizes - 8 * (n - 1)]
    return values, first, n


def chunk_hashes(values: np.ndarray, first: np.ndarray, n: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """64-bit hash of each span from its chunks: every chunk is mixed with its place before they are added up."""
    place = np.arange(len(values)) - np.repeat(first, n)
    return mix(np.add.reduceat(mix(values + place.astype(_U) * _PLACE), first) + sizes.astype(_U) * _SIZE) if len(first) else np.zeros(0, _U)


def span_hashes(values: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of each span of a flat array, whatever its place. Two different spans share one with a chance of 2^-64."""
    width = values.dtype.itemsize
    numbers, out = padded(np.ascontiguousarray(values).view(np.uint8)), np.empty(len(starts), _U)
    for at in range(0, len(starts), _SPANS):
        a, b = starts[at : at + _SPANS] * width, ends[at : at + _SPANS] * width
        out[at : at + _SPANS] = chunk_hashes(*chunks(numbers, a, b), b - a)
    return out


def words(raw: np.ndarray, offsets: np.ndarray, spaces: np.ndarray = SPACES) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(starts, ends, words before each text): maximal runs of bytes outside `spaces`, cut at text borders."""
    if not len(raw):
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(len(offsets), np.int64)
    inside = ~spaces[raw]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    last = inside.copy()
    last[:-1] &= ~inside[1:]
    borders = offsets[1:-1]
    borders = borders[borders < len(raw)]
    first[borders] = inside[borders]
    borders = borders[borders > 0]
    last[borders - 1] = inside[borders - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    return starts, ends, np.searchsorted(starts, offsets)
