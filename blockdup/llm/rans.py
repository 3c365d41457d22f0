"""Range asymmetric numeral systems over token ids: one static table, independent blocks, interleaved lanes.

A block's ids are dealt over lanes row by row; all lanes take a step together, so numpy carries the coder.
Blocks hold checkpoints (state of all lanes before a row, the place in the word stream, and a checksum of the
ids up to the next one). A reader can start at any of them, so the segments between them decode in parallel;
a whole block has two checksums of its own (of the ids and of everything stored).
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

MAGIC = b"RANB"
BITS = 20
LANES = 2048
ROWS_BETWEEN_CHECKPOINTS = 32
_U = np.uint64
_LOW = _U(1 << 31)
_HEAD = struct.Struct("<4sIIIII")  # magic, ids, lanes, words, checkpoints, crc of the ids
_MARK = struct.Struct("<III")  # row, words used before it, crc of the ids up to the next checkpoint


def frequency_table(counts: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Frequencies of all symbols that sum to 2^bits; a symbol that occurs keeps at least 1."""
    seen = np.flatnonzero(counts)
    out = np.zeros(len(counts), np.int64)
    if not len(seen):
        return out
    if len(seen) > 1 << bits:
        raise ValueError("more symbols than the table has room for")
    scaled = np.maximum(1, counts[seen].astype(np.float64) * ((1 << bits) / counts.sum())).astype(np.int64)
    excess = int(scaled.sum()) - (1 << bits)
    order = np.argsort(-scaled, kind="stable")
    while excess > 0:
        room = scaled[order] - 1
        take = np.minimum(room, np.ceil(room * (excess / max(1, room.sum()))).astype(np.int64))
        over = np.cumsum(take) - excess
        take -= np.clip(over, 0, take)
        scaled[order] -= take
        excess = int(scaled.sum()) - (1 << bits)
    scaled[order[0]] -= excess
    out[seen] = scaled
    return out


class Coder:
    """Encoder and decoder for one frequency table."""

    def __init__(self, freq: np.ndarray, bits: int = BITS):
        self.bits = _U(bits)
        self.freq = freq.astype(_U)
        self.base = (np.cumsum(freq) - freq).astype(_U)
        self.of_slot = np.repeat(np.arange(len(freq), dtype=np.uint16), freq)
        self.mask = _U((1 << bits) - 1)
        self.full = self.freq << _U(63 - bits)

    def encode(self, ids: np.ndarray, lanes: int = LANES) -> bytes:
        """One block. `ids` are unsigned 16-bit."""
        n = len(ids)
        lanes = max(1, min(lanes, n))
        rows = -(-n // lanes)
        x = np.full(lanes, _LOW, _U)
        words, marks, written = [], [], 0
        for r in range(rows - 1, -1, -1):
            s = ids[r * lanes : (r + 1) * lanes]
            y, f = x[: len(s)], self.freq[s]
            out = y >= self.full[s]
            if out.any():
                spilt = y[out].astype(np.uint32)
                words.append(spilt)
                written += len(spilt)
                y = np.where(out, y >> _U(32), y)
            q = y // f
            x[: len(s)] = (q << self.bits) + (y - q * f) + self.base[s]
            if r and r % ROWS_BETWEEN_CHECKPOINTS == 0:
                marks.append((r, written, x.astype("<u8").tobytes()))
        stream = np.concatenate(words[::-1]).astype("<u4") if words else np.zeros(0, "<u4")
        segment = lanes * ROWS_BETWEEN_CHECKPOINTS
        crc = lambda r: zlib.crc32(ids[r * lanes : r * lanes + segment].astype("<u2").tobytes())
        body = [_MARK.pack(0, 0, crc(0)) + x.astype("<u8").tobytes(), *(_MARK.pack(r, written - w, crc(r)) + state for r, w, state in reversed(marks)), stream.tobytes()]
        head = _HEAD.pack(MAGIC, n, lanes, len(stream), len(marks), zlib.crc32(ids.astype("<u2").tobytes()))
        whole = head + b"".join(body)
        return whole + struct.pack("<I", zlib.crc32(whole))

    def decode(self, block: bytes) -> np.ndarray:
        """All ids of a block."""
        magic, n, lanes, _, _, crc = _HEAD.unpack_from(block)
        if magic != MAGIC or zlib.crc32(memoryview(block)[:-4]) != struct.unpack_from("<I", block, len(block) - 4)[0]:
            raise ValueError("the block is damaged")
        out = self._rows(block, 0, -(-n // lanes))
        if zlib.crc32(out.astype("<u2").tobytes()) != crc:
            raise ValueError("the ids do not match their checksum")
        return out

    def decode_segment(self, block: bytes, k: int) -> np.ndarray:
        """The ids from checkpoint k (0: the start) up to the next one, with no other part of the block decoded or checked."""
        magic, n, lanes, _, _, _ = _HEAD.unpack_from(block)
        if magic != MAGIC:
            raise ValueError("the block is damaged")
        out = self._rows(block, k, min(ROWS_BETWEEN_CHECKPOINTS, -(-n // lanes) - k * ROWS_BETWEEN_CHECKPOINTS))
        if zlib.crc32(out.astype("<u2").tobytes()) != _MARK.unpack_from(block, _HEAD.size + k * (_MARK.size + 8 * lanes))[2]:
            raise ValueError("the ids do not match their checksum")
        return out

    def _rows(self, block: bytes, k: int, rows: int) -> np.ndarray:
        """So many rows of ids from checkpoint k on."""
        _, n, lanes, n_words, n_marks, _ = _HEAD.unpack_from(block)
        step = _MARK.size + 8 * lanes
        at, words_at = _HEAD.size + k * step, _HEAD.size + (n_marks + 1) * step
        row, used, _ = _MARK.unpack_from(block, at)
        x = np.frombuffer(block, "<u8", lanes, at + _MARK.size).astype(_U)
        stream = np.frombuffer(block, "<u4", n_words, words_at)
        first, last = row * lanes, row + rows
        out = np.empty(min(n, last * lanes) - first, np.uint16)
        for r in range(row, last):
            m = min(lanes, n - r * lanes)
            y = x[:m]
            slot = y & self.mask
            s = self.of_slot[slot]
            out[r * lanes - first : r * lanes - first + m] = s
            y = self.freq[s] * (y >> self.bits) + slot - self.base[s]
            low = np.flatnonzero(y < _LOW)
            y[low] = (y[low] << _U(32)) | stream[used : used + len(low)]
            used += len(low)
            x[:m] = y
        return out


def segments(block: bytes) -> int:
    """Parts of a block that can be decoded by themselves."""
    return _HEAD.unpack_from(block)[4] + 1
