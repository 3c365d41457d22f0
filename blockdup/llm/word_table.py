"""Distinct words as numbers: a hash table in numpy that compares the words themselves on every hit."""

from __future__ import annotations

import numpy as np

from .texts import chunk_hashes, chunks, padded


class Grown:
    """An array that is appended to."""

    def __init__(self, kind, room: int = 1 << 16):
        self.data, self.used = np.zeros(room, kind), 0

    def extend(self, values: np.ndarray) -> None:
        need = self.used + len(values)
        if need > len(self.data):
            wide = np.zeros(max(need, 2 * len(self.data)), self.data.dtype)
            wide[: self.used] = self.data[: self.used]
            self.data = wide
        self.data[self.used : need] = values
        self.used = need


class WordTable:
    """Words (spans of a byte array) to entries 0, 1, 2, ...

    `keep` bounds the entries, `most_chunks` their 8-byte chunks: a table that has passed either is emptied
    before the next look-up, so entries hold until then only. Hits are compared byte by byte. Words that share
    a 64-bit hash with another one are kept in a dictionary.
    """

    def __init__(self, keep: int = 1_000_000, most_chunks: int = 8_000_000):
        self.keep, self.most_chunks = keep, most_chunks
        self.clear()

    def clear(self) -> None:
        self.slots = np.full(1 << 16, -1, np.int32)
        self.hashes, self.sizes, self.first, self.pool = Grown(np.uint64), Grown(np.int64), Grown(np.int64), Grown(np.uint64)
        self.odd: dict[bytes, int] = {}

    @property
    def full(self) -> bool:
        return self.hashes.used > self.keep or self.pool.used > self.most_chunks

    def _probe(self, h: np.ndarray) -> np.ndarray:
        """Entry with each hash, or -1."""
        mask, known = len(self.slots) - 1, self.hashes.data
        slot = (h & np.uint64(mask)).astype(np.int64)
        entry = self.slots[slot]
        left = np.flatnonzero((entry >= 0) & (known[entry] != h))
        while len(left):
            slot[left] = (slot[left] + 1) & mask
            entry[left] = self.slots[slot[left]]
            e = entry[left]
            left = left[(e >= 0) & (known[e] != h[left])]
        return entry

    def _seat(self, h: np.ndarray, entries: np.ndarray) -> None:
        """Give each hash a free slot; hashes are distinct."""
        mask = len(self.slots) - 1
        slot, left = (h & np.uint64(mask)).astype(np.int64), np.arange(len(h))
        while len(left):
            s = slot[left]
            free = self.slots[s] < 0
            self.slots[s[free]] = entries[left[free]]  # of several that want one slot, one gets it
            left = left[self.slots[s] != entries[left]]
            slot[left] = (slot[left] + 1) & mask

    def _add(self, h: np.ndarray, sizes: np.ndarray, values: np.ndarray, n: np.ndarray) -> None:
        entries = np.arange(self.hashes.used, self.hashes.used + len(h), dtype=np.int32)
        self.hashes.extend(h)
        self.sizes.extend(sizes)
        self.first.extend(self.pool.used + np.cumsum(n) - n)
        self.pool.extend(values)
        if 4 * self.hashes.used > len(self.slots):
            room = len(self.slots)
            while 4 * self.hashes.used > room:
                room *= 2
            self.slots = np.full(room, -1, np.int32)
            h, entries = self.hashes.data[: self.hashes.used], np.arange(self.hashes.used, dtype=np.int32)
            plain = np.ones(len(h), bool)
            plain[list(self.odd.values())] = False
            h, entries = h[plain], entries[plain]
        self._seat(h, entries)

    def find(self, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(entry of each span, spans that made the new entries, in the order of these)."""
        if not len(starts):
            return np.zeros(0, np.int32), np.zeros(0, np.int64)
        sizes = ends - starts
        values, first, n = chunks(padded(raw), starts, ends)
        h = chunk_hashes(values, first, n, sizes)
        entry, made = self._probe(h), []
        missing = np.flatnonzero(entry < 0)
        if len(missing):
            new, place = np.unique(h[missing], return_index=True)
            spans = missing[place]
            size = n[spans]
            self._add(new, sizes[spans], values[np.repeat(first[spans] - (np.cumsum(size) - size), size) + np.arange(size.sum())], size)
            entry[missing] = self._probe(h[missing])
            made.append(spans)
        same = self.sizes.data[entry] == sizes
        at = np.repeat(np.where(same, self.first.data[entry], 0) - first, n) + np.arange(len(values))
        equal = self.pool.data[np.minimum(at, self.pool.used - 1)] == values
        for k in np.flatnonzero(~(same & np.logical_and.reduceat(equal, first))).tolist():
            word = raw[starts[k] : ends[k]].tobytes()
            if word not in self.odd:
                self.odd[word] = self.hashes.used
                for grown, value in ((self.hashes, h[k]), (self.sizes, sizes[k]), (self.first, self.pool.used)):
                    grown.extend(np.array([value], grown.data.dtype))
                self.pool.extend(values[first[k] : first[k] + n[k]])
                made.append(np.array([k]))
            entry[k] = self.odd[word]
        return entry, np.concatenate(made) if made else np.zeros(0, np.int64)
