"""Detection in cells of sizes: blocks that can match by size meet in one task, as bags, and only once.

Nothing but bags of token hashes is shuffled: a block goes to the cell of its own size band and, as a query, to the
cells of the bands its smaller partners may lie in. A cell indexes the rarest part of its blocks, counts what a query
shares with each, and verifies candidates on whole bags. Candidates, postings and copies of blocks are never written.
Sizes are looked up within an element's postings, so no match of a wrong size is formed. The bound from positions is
left out here: at 0.7 it took 0.3 % of the matches on prose, and candidates share many elements anyway.
"""

from __future__ import annotations

import hashlib
import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pandas._libs.hashtable import Int64Factorizer
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import similarity as sim
from ..functions.tokens import token_array
from ..sources.io import stage, unstage

#: Counters of token frequency: a table of fixed size, whatever the vocabulary. Tokens that share one only come later in the order.
SLOTS, PIECE = 1 << 22, 1 << 16
#: Steps of the order for each doubling of a frequency; a token that occurs once has the step ONCE.
STEPS = 6
#: Ratio of the largest to the smallest size of a band.
BAND = 1.195
#: Distinct tokens that a cell holds at most (4 bytes each, and its frequency); larger cells are split on both sides.
HELD = 32_000_000
#: Tokens that are given numbers at a time.
NUMBERED = 2_000_000
#: Ids of copies that are told to the readers of texts at most; further copies are collapsed in their cells.
TOLD = 1_000_000
#: Elements that candidates share, and that sub-blocks hold beyond what one shared element needs.
SHARED = 16
#: Words of a block for each of them, at least.
SHORT = 12
#: Postings of an index, of a group of queries, and matches at a time.
INDEXED, ASKED, MATCHED = 1_000_000, 200_000, 400_000
#: Tokens of a candidate that are read before it is first looked at whether it is decided; twice as many each time after.
PACE = 32
#: Queries and blocks that are compared at a time, where every pair is.
ROWS, COLUMNS = 16, 2048
#: Postings of an element that are tried whatever their sizes.
FEW = 6
#: A token's hash is cut to 56 bits: two blocks of 300 words each share one by chance once in 10^12 pairs.
MASK = np.int64((1 << 56) - 1)
BAG = "cell int, role int, block_id long, n int, digest binary, tokens binary, freqs binary, codes binary"
#: Tokens with a code of two bytes on the way to cells, found among the first SEEN tokens of at most TELLING tasks, NAMED of each; all others go with their hash.
CODED, TELLING, SEEN, NAMED = 1 << 16, 64, 1_000_000, 16_384
FOUND = pa.schema([("b", pa.int64()), ("c", pa.int64()), ("n_b", pa.int32()), ("n_c", pa.int32()), ("overlap", pa.int32())])


def hashed(blocks: DataFrame, profile: str = "prose") -> DataFrame:
    """(block_id, project_id, codes): each token a hash, in reading order."""
    return blocks.select("block_id", "project_id", F.transform(token_array(F.col("text"), profile), lambda t: F.xxhash64(t)).alias("codes"))


def _bags(batch: pa.RecordBatch) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(row, tokens, frequencies) of each row that has tokens; tokens ascend."""
    column = batch.column("codes")
    at, values = column.offsets.to_numpy(), column.values.to_numpy()
    for row in range(batch.num_rows):
        one = values[at[row] : at[row + 1]]
        if len(one):
            yield row, *np.unique(one & MASK, return_counts=True)


def edges(ratio: float = BAND, top: int = 1 << 31) -> np.ndarray:
    """Smallest size of each band."""
    out = [1]
    while out[-1] < top:
        out.append(max(out[-1] + 1, int(out[-1] * ratio)))
    return np.array(out)


def least(n: np.ndarray, theta_pm: int, measure: str) -> np.ndarray:
    """least_partner() on arrays."""
    share, scale = (theta_pm * theta_pm, 1_000_000) if measure == "cosine" else (theta_pm, 1000)
    return -(-n * share // scale)


def meets(o: np.ndarray, a: np.ndarray, b: np.ndarray, theta_pm: int, measure: str, strict: bool = False) -> np.ndarray:
    """similarity.meets() on arrays of long."""
    if measure == "overlap":
        need = np.maximum(a, b) * theta_pm
        return o > -(-need // 1000) if strict else o * 1000 >= need
    left, right = (o * (1000 + theta_pm), (a + b) * theta_pm) if measure == "jaccard" else (o * o * 1_000_000, a * b * (theta_pm * theta_pm))
    return left > right if strict else left >= right


def _survey(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counters by piece, tokens by size band (piece -1), the digest of each bag (piece -2), and common tokens (piece -3)."""
    counts, sizes, lows = np.zeros(SLOTS, np.int64), np.zeros(256, np.int64), edges()
    some, left = [], SEEN if TaskContext.get().partitionId() < TELLING else 0
    schema = pa.schema([("piece", pa.int32()), ("body", pa.binary()), ("block_id", pa.int64()), ("project_id", pa.string()), ("n", pa.int32())])
    for batch in batches:
        rows: list[list] = [[], [], [], []]
        ids, projects = batch.column("block_id").to_pylist(), batch.column("project_id").to_pylist()
        for row, tokens, freqs in _bags(batch):
            n = int(freqs.sum())
            if left > 0:
                some.append(tokens)
                left -= len(tokens)
            np.add.at(counts, tokens & (SLOTS - 1), freqs)
            sizes[np.searchsorted(lows, n, "right") - 1] += len(tokens)
            digest = hashlib.blake2b(tokens.tobytes() + freqs.astype("<i4").tobytes(), digest_size=16).digest()
            for to, x in zip(rows, (digest, ids[row], projects[row], n), strict=True):
                to.append(x)
        yield pa.RecordBatch.from_arrays([pa.array([-2] * len(rows[0]), pa.int32()), *(pa.array(x, t.type) for x, t in zip(rows, list(schema)[1:], strict=True))], schema=schema)
    made = [(-1, sizes.tobytes())]
    if some:
        known, times = np.unique(np.concatenate(some), return_counts=True)
        top = np.argsort(-times, kind="stable")[:NAMED]
        made.append((-3, np.stack((known[top], times[top])).astype("<i8").tobytes()))
    for k in range(SLOTS // PIECE):
        part = counts[k * PIECE : (k + 1) * PIECE]
        at = np.flatnonzero(part)
        if len(at):
            made.append((k, zlib.compress(at.astype("<u2").tobytes() + part[at].astype("<i8").reshape(-1, 1).view(np.uint8).reshape(-1, 8).T.tobytes(), 1)))
    none = [None] * len(made)
    yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in made], pa.int32()), pa.array([x[1] for x in made], pa.binary()), *(pa.array(none, t.type) for t in list(schema)[2:])], schema=schema)


def _levels(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counters of a piece added up, as steps of the order in one byte each; sizes added up; the commonest tokens of those named."""
    total: dict[int, np.ndarray] = {}
    for batch in batches:
        for piece, body in zip(batch.column("piece").to_pylist(), batch.column("body").to_pylist(), strict=True):
            if piece == -1:
                total[piece] = total.get(piece, 0) + np.frombuffer(body, np.int64)
                continue
            if piece == -3:
                known, times = np.concatenate((total.get(piece, np.zeros((2, 0), np.int64)), np.frombuffer(body, "<i8").reshape(2, -1)), axis=1)
                known, of = np.unique(known, return_inverse=True)
                total[piece] = np.stack((known, np.bincount(of, weights=times, minlength=len(known)).astype(np.int64)))
                continue
            raw = zlib.decompress(body)
            m = len(raw) // 10
            at, planes = np.frombuffer(raw, "<u2", m), np.frombuffer(raw, np.uint8, offset=2 * m).reshape(8, m)
            total.setdefault(piece, np.zeros(PIECE, np.int64))[at] += np.ascontiguousarray(planes.T).view("<i8").ravel()
    if -3 in total:
        known, times = total[-3]
        total[-3] = known[np.argsort(-times, kind="stable")[:CODED]]
    out = [(k, x.tobytes() if k < 0 else np.floor(STEPS * np.log2(x + 1)).astype(np.uint8).tobytes()) for k, x in total.items()]
    yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int32()), pa.array([x[1] for x in out], pa.binary())], names=["piece", "body"])


def survey(codes: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray, DataFrame]:
    """(step of the order for each counter, distinct tokens for each size band, common tokens in the order, (rep, block_id, project_id, n)).

    Blocks with equal bags have one representative, the smallest id. What comes to the driver has a fixed size.
    """
    seen = stage(codes.mapInArrow(_survey, "piece int, body binary, block_id long, project_id string, n int"), "survey")
    parts = seen.where("piece <> -2").select("piece", "body").repartition(16, "piece").mapInArrow(_levels, "piece int, body binary").collect()
    levels, sizes, common = np.zeros(SLOTS, np.uint8), np.zeros(256, np.int64), np.zeros(0, np.int64)
    for piece, body in parts:
        if piece == -3:
            common = np.sort(np.frombuffer(bytes(body), np.int64))
        elif piece < 0:
            sizes += np.frombuffer(bytes(body), np.int64)
        else:
            levels[piece * PIECE : (piece + 1) * PIECE] = np.frombuffer(bytes(body), np.uint8)
    bags = seen.where("piece = -2").select(F.col("body").alias("digest"), "block_id", "project_id", "n")
    reps = bags.groupBy("digest").agg(F.min("block_id").alias("rep"))
    members = stage(bags.join(reps, "digest").select("rep", "block_id", "project_id", "n"), "members")
    unstage(seen)
    return levels, sizes, common[np.argsort(levels[common & (SLOTS - 1)], kind="stable")], members


class Cells:
    """Which cells there are and where a block of a size goes."""

    def __init__(self, sizes: np.ndarray, theta_pm: int, measure: str, held: int = HELD):
        self.lows, self.theta_pm, self.measure = edges(), theta_pm, measure
        self.split, self.first, count = {}, {}, 0
        for band in np.flatnonzero(sizes):
            reach = sum(int(sizes[x]) for x in range(band, min(len(self.lows), len(sizes))) if self.floor(int(self.lows[x])) <= band)
            s = max(1, math.ceil(2 * int(sizes[band]) / held)) if sizes[band] + reach > held else 1
            t = max(1, math.ceil(2 * reach / held)) if sizes[band] + reach > held else 1
            self.split[int(band)], self.first[int(band)] = (s, t), count
            count += s * t
        self.count = count

    def floor(self, n: int) -> int:
        """The lowest band of a partner of n."""
        return int(np.searchsorted(self.lows, int(least(np.int64(n), self.theta_pm, self.measure)), "right") - 1)

    def of(self, n: int, digest: bytes) -> Iterator[tuple[int, int]]:
        """(cell, role) for a block: role has 1 for a block of the cell's index and 2 for a query."""
        own, x, y = int(np.searchsorted(self.lows, n, "right") - 1), digest[0] << 8 | digest[1], digest[2] << 8 | digest[3]
        for band in range(self.floor(n), own + 1):
            if band not in self.split:
                continue
            s, t = self.split[band]
            for i in range(s):
                for j in range(t):
                    role = (1 if band == own and x % s == i else 0) | (2 if y % t == j else 0)
                    if role:
                        yield self.first[band] + i * t + j, role


def _dealt(levels: np.ndarray, cells: Cells, copies: np.ndarray, common: np.ndarray):
    """Bags for their cells: tokens from the rarest on, 7 bytes each; of common ones a code of 2, and a bit for which they are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([("cell", pa.int32()), ("role", pa.int32()), ("block_id", pa.int64()), ("n", pa.int32()), ("digest", pa.binary()), ("tokens", pa.binary()), ("freqs", pa.binary()), ("codes", pa.binary())])
        code = np.full(SLOTS, -1, np.int32)
        code[common & (SLOTS - 1)] = np.arange(len(common))  # one of those that share a counter
        for batch in batches:
            ids, rows, size = batch.column("block_id").to_numpy(), [], 0
            at = np.minimum(np.searchsorted(copies, ids), max(len(copies) - 1, 0))
            copy = copies[at] == ids if len(copies) else np.zeros(len(ids), bool)
            for row, tokens, freqs in _bags(batch):
                if copy[row]:
                    continue
                digest = hashlib.blake2b(tokens.tobytes() + freqs.astype("<i4").tobytes(), digest_size=16).digest()
                turn = np.argsort(levels[tokens & (SLOTS - 1)], kind="stable")
                tokens = tokens[turn]
                of = code[tokens & (SLOTS - 1)]
                coded = of >= 0
                coded[coded] = common[of[coded]] == tokens[coded]
                body = tokens[~coded].astype("<i8").view(np.uint8).reshape(-1, 8)[:, :7].tobytes()
                short = of[coded].astype("<u2").view(np.uint8).reshape(-1, 2).T.tobytes()  # codes ascend: their high bytes are alike
                short = zlib.compress(short + np.packbits(coded).tobytes(), 1)
                times = zlib.compress(freqs[turn].astype("<i4").tobytes(), 1)
                n = int(freqs.sum())
                for cell, role in cells.of(n, digest):
                    rows.append((cell, role, int(ids[row]), n, digest, body, times, short))
                    size += len(body) + len(short)
                if size > 8_000_000:
                    yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
                    rows, size = [], 0
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)

    return run


class Held:
    """The distinct bags of one cell, as numbers given to its tokens: four bytes each, and tables by number need no search."""

    def __init__(self, common: np.ndarray | None = None) -> None:
        self.common = common
        self.place: dict[bytes, int] = {}
        self.id: list[int] = []
        self.n: list[int] = []
        self.role: list[int] = []
        self.raw: list[tuple[bytes, bytes, bytes]] = []
        self.waiting = 0
        self.numbers = Int64Factorizer(1 << 16)
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []
        self.at = np.zeros(1, np.int64)
        self.tokens, self.freqs = np.zeros(0, np.int32), np.zeros(0, np.uint8)

    def add(self, role: int, block_id: int, n: int, digest: bytes, tokens: bytes, freqs: bytes, codes: bytes = b"") -> None:
        k = self.place.setdefault(digest, len(self.id))
        if k < len(self.id):
            self.id[k] = min(self.id[k], block_id)
        else:
            for to, x in ((self.id, block_id), (self.n, n), (self.role, role), (self.raw, (tokens, freqs, codes))):
                to.append(x)
            self.waiting += len(tokens) // 7 + len(codes) // 2
            if self.waiting > NUMBERED:
                self._number()

    def _number(self) -> None:
        body = np.frombuffer(b"".join(t for t, _, _ in self.raw), np.uint8).reshape(-1, 7)
        wide = np.zeros((len(body), 8), np.uint8)
        wide[:, :7] = body
        parts = [zlib.decompress(f) for _, f, _ in self.raw]
        of = np.array([len(f) // 4 for f in parts])
        freqs, tokens = np.frombuffer(b"".join(parts), "<i4"), wide.view("<i8").ravel()
        if self.common is not None:
            tokens = self._decoded(tokens, of)
        self.parts.append((self.numbers.factorize(tokens).astype(np.int32), freqs.astype(np.min_scalar_type(int(freqs.max(initial=0))))))
        self.at = np.append(self.at, self.at[-1] + np.cumsum(of))
        self.raw, self.waiting = [], 0

    def _decoded(self, uncoded: np.ndarray, of: np.ndarray) -> np.ndarray:
        """Tokens of the waiting bags, `of` in each, with those that came as codes in their places."""
        codes, coded = [], []
        for (_, _, short), many in zip(self.raw, of.tolist(), strict=True):
            short = zlib.decompress(short)
            bits = len(short) - -(-many // 8)
            codes.append(np.frombuffer(short, np.uint8, bits).reshape(2, -1).T.ravel())
            coded.append(np.unpackbits(np.frombuffer(short, np.uint8, offset=bits), count=many))
        at, out = np.concatenate(coded).view(bool), np.empty(int(of.sum()), np.int64)
        out[at], out[~at] = self.common[np.concatenate(codes).view("<u2")], uncoded
        return out

    def close(self) -> None:
        """No more blocks come."""
        if self.raw:
            self._number()
        if self.parts:
            self.tokens, self.freqs = np.empty(self.at[-1], np.int32), np.empty(self.at[-1], np.result_type(*(f for _, f in self.parts)))
            done = len(self.tokens)
            while self.parts:  # from the end, so that nothing is held twice
                t, f = self.parts.pop()
                self.tokens[done - len(t) : done], self.freqs[done - len(t) : done] = t, f
                done -= len(t)

    def rows(self, blocks: np.ndarray, skip: int = 0, most: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(places of their tokens one after the other, how many tokens each has); without the first `skip` of each, and so many at most."""
        start, of = self.at[blocks] + skip, self.at[blocks + 1] - self.at[blocks] - skip
        if most is not None:
            of = np.minimum(of, most)
        at = np.arange(int(of.sum()), dtype=np.int32 if self.at[-1] < 1 << 31 else np.int64)
        at += np.repeat((start - (np.cumsum(of) - of)).astype(at.dtype), of)
        return at, of

    def postings(self, blocks: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(element, place in `blocks`) of the first `length` elements of each; a token's k-th occurrence is an element with a number."""
        at, of = self.rows(blocks)
        f, where = self.freqs[at].astype(np.int64), np.repeat(np.arange(len(blocks), dtype=np.int32), of)
        before = np.cumsum(f) - f
        left = (length[blocks] + before[np.cumsum(of) - of])[where] - before  # elements of the sub-block from this token on
        del before
        keep = left > 0
        t, where, f = self.tokens[at[keep]].astype(np.int64), where[keep], np.minimum(f, left)[keep]
        again = f > 1
        if not again.any():
            return t, where
        more = f[again] - 1
        k = np.arange(int(more.sum())) - np.repeat(np.cumsum(more) - more, more) + 1
        named = self.numbers.factorize(-1 - (np.repeat(t[again], more) << 31 | k))  # below zero: no token's hash
        return np.concatenate((t, named)), np.concatenate((where, np.repeat(where[again], more)))


def _search(held: Held, theta_pm: int, measure: str, strict: bool, shared: int, given: bool = False, early: bool = False) -> Iterator[pa.RecordBatch]:
    """Pairs of a query and an indexed block of one cell that meet the threshold, each once: b is the larger."""
    held.close()
    ids, n, role = np.array(held.id, np.int64), np.array(held.n, np.int64), np.array(held.role, np.int64)
    low = least(n, theta_pm, measure)
    shared = np.full(len(n), shared) if given else np.clip(n // SHORT, 1, shared)  # short blocks would be indexed whole
    length = np.minimum(n, n - low + shared)
    share, scale = (theta_pm * theta_pm, 1_000_000) if measure == "cosine" else (theta_pm, 1000)
    mark = np.zeros(int(held.tokens.max(initial=-1)) + 1, held.freqs.dtype)

    def groups(blocks: np.ndarray, most: int) -> list[np.ndarray]:
        cuts = np.cumsum(length[blocks]) // most
        return np.split(blocks, np.flatnonzero(np.diff(cuts)) + 1) if len(blocks) else []

    fewest = int(np.minimum(shared, low).min(initial=1 << 30))
    queries = groups(np.flatnonzero(role & 2), ASKED)
    for homes in groups(np.flatnonzero(role & 1), INDEXED):
        homes = homes[np.argsort(n[homes], kind="stable")]
        element, where = held.postings(homes, length)
        many = np.bincount(element)
        first = np.concatenate(([0], np.cumsum(many)))  # of an element's postings; the last is of those that are not there
        turn = np.lexsort((where, element))
        where = where[turn]
        sized = element[turn] << 32 | n[homes][where]  # element and size, ascending
        del element, turn
        top = int(np.max(n[homes] * scale // share)) + 1
        for asked in queries:
            asked = asked[n[asked] <= top]
            if not len(asked):
                continue
            q, q_of = held.postings(asked, length)
            hit = np.flatnonzero(q < len(many))
            hit = hit[many[q[hit]] > 0]
            q, q_of = q[hit], q_of[hit]
            start, times = first[q], many[q]
            long = np.flatnonzero(times > FEW)  # partners of fitting sizes stand together; few are as well tried
            long = long[np.argsort(q[long])]  # places looked up in turn are near in memory
            at, of = q[long] << 32, asked[q_of[long]]
            start[long] = np.searchsorted(sized, at + low[of], "left")
            times[long] = np.searchsorted(sized, at + n[of], "right") - start[long]
            turn = np.argsort(q_of, kind="stable")  # queries stay whole
            q_of, start, times = q_of[turn], start[turn], times[turn]
            ends = np.searchsorted(q_of, np.arange(len(asked)), "right")
            total = np.concatenate(([0], np.cumsum(times)))[ends]
            cuts = np.flatnonzero(np.diff(total // MATCHED)) + 1
            picked_b, picked_c = [], []
            kind = np.int32 if len(asked) * len(homes) < 1 << 31 else np.int64
            for a, z in zip(np.append(0, ends[cuts - 1]), np.append(ends[cuts - 1], ends[-1]), strict=True):
                rep = times[a:z]
                j = np.arange(int(rep.sum())) + np.repeat(start[a:z] - (np.cumsum(rep) - rep), rep)
                key = np.repeat((q_of[a:z] * kind(len(homes))).astype(kind), rep) + where[j].astype(kind)
                if not len(key):
                    continue
                key.sort()
                fresh = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
                seen, key = np.diff(np.append(fresh, len(key))), key[fresh]
                enough = seen >= fewest
                seen, key = seen[enough], key[enough]
                b, c = asked[key // len(homes)], homes[key % len(homes)]
                ok = ((n[b] > n[c]) | ((n[b] == n[c]) & (ids[b] < ids[c]))) & (n[c] >= low[b])
                ok &= (seen >= np.minimum(shared[b], shared[c])) | meets(seen, n[b], n[c], theta_pm, measure)
                picked_b.append(b[ok]), picked_c.append(c[ok])
            yield from _verify(held, mark, ids, n, np.concatenate(picked_b or [asked[:0]]), np.concatenate(picked_c or [asked[:0]]), theta_pm, measure, strict, early)


def _verify(held: Held, mark: np.ndarray, ids: np.ndarray, n: np.ndarray, b: np.ndarray, c: np.ndarray, theta_pm: int, measure: str, strict: bool, early: bool = False) -> Iterator[pa.RecordBatch]:
    """Overlaps on whole bags, the candidates of one query at a time: `mark` holds the query's frequencies by token.

    early: each candidate is read only until it is decided; the overlap of an accepted one is a lower bound.
    """
    if not len(b):
        return
    overlap = np.zeros(len(b), np.int64)
    starts = np.flatnonzero(np.concatenate(([True], b[1:] != b[:-1])))
    for a, z in zip(starts.tolist(), np.append(starts[1:], len(b)).tolist(), strict=True):
        own = slice(held.at[b[a]], held.at[b[a] + 1])
        mark[held.tokens[own]] = held.freqs[own]
        for lo in range(a, z, 256):
            if early:
                overlap[lo : min(lo + 256, z)] = _decided(held, mark, n, int(b[a]), c[lo : min(lo + 256, z)], theta_pm, measure, strict)
                continue
            at, of = held.rows(c[lo : min(lo + 256, z)])
            both = np.minimum(mark[held.tokens[at]], held.freqs[at])
            overlap[lo : lo + len(of)] = np.add.reduceat(both, np.cumsum(of) - of, dtype=np.int64)
        mark[held.tokens[own]] = 0
    ok = meets(overlap, n[b], n[c], theta_pm, measure, strict)
    b, c, overlap = b[ok], c[ok], overlap[ok]
    yield pa.RecordBatch.from_arrays([pa.array(x, t.type) for x, t in zip((ids[b], ids[c], n[b], n[c], overlap), FOUND, strict=True)], schema=FOUND)


def needed(a: np.ndarray, b: np.ndarray, theta_pm: int, measure: str, strict: bool = False) -> np.ndarray:
    """Least overlap that meets the threshold."""
    if measure == "overlap":
        o = np.maximum(a, b) * theta_pm // 1000
    else:
        o = (a + b) * theta_pm // (1000 + theta_pm) if measure == "jaccard" else (np.sqrt(a * b) * (theta_pm / 1000)).astype(np.int64)
    o = np.maximum(o - 1, 0)
    for _ in range(4):
        o = o + ~meets(o, a, b, theta_pm, measure, strict)
    return o


def _decided(held: Held, mark: np.ndarray, n: np.ndarray, b: int, c: np.ndarray, theta_pm: int, measure: str, strict: bool) -> np.ndarray:
    """Overlaps with the query of `mark` as far as they were counted: until a candidate has enough, or too little is left of it."""
    out, live, passed, skip, most = np.zeros(len(c), np.int64), np.arange(len(c)), np.zeros(len(c), np.int64), 0, PACE
    need = needed(np.full(len(c), n[b]), n[c], theta_pm, measure, strict)
    while len(live):
        at, of = held.rows(c[live], skip, most)
        first = np.cumsum(of) - of
        f = held.freqs[at]
        out[live] += np.add.reduceat(np.minimum(mark[held.tokens[at]], f), first, dtype=np.int64)
        passed[live] += np.add.reduceat(f, first, dtype=np.int64)
        live = live[(out[live] < need[live]) & (out[live] + n[c[live]] - passed[live] >= need[live])]
        skip, most = skip + most, 2 * most
    return out


def _bits(held: Held, n: np.ndarray, blocks: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray]:
    """(words x blocks: a bit for each element, by hash; elements of each block beyond its bits)."""
    out, done = np.empty((words, len(blocks)), np.uint64), 0
    for part in np.split(blocks, np.flatnonzero(np.diff(np.cumsum(n[blocks]) // ASKED)) + 1) if len(blocks) else []:
        at, of = held.rows(part)
        f = held.freqs[at].astype(np.int64)
        where = np.repeat(np.repeat(np.arange(len(part)), of), f)
        k = np.arange(len(where)) - np.repeat(np.cumsum(f) - f, f)
        h = np.repeat(held.tokens[at].astype(np.uint64), f) * np.uint64(0x9E3779B97F4A7C15) + k.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F)
        h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
        flags = np.zeros((len(part), 64 * words), bool)
        flags[where, (h >> np.uint64(33)).astype(np.int64) % (64 * words)] = True
        out[:, done : done + len(part)] = np.packbits(flags, axis=1).view(np.uint64).T
        done += len(part)
    return out, n[blocks] - np.bitwise_count(out).sum(axis=0, dtype=np.int64)


def _compare(held: Held, theta_pm: int, measure: str, strict: bool) -> Iterator[pa.RecordBatch]:
    """As _search, without an index: every query with every block of the cell, by size, by a bound on the overlap, whole.

    The bound: elements in common have bits in common, except as many as either side has elements beyond its bits.
    """
    held.close()
    ids, n, role = np.array(held.id, np.int64), np.array(held.n, np.int64), np.array(held.role, np.int64)
    low = least(n, theta_pm, measure)
    mark = np.zeros(int(held.tokens.max(initial=-1)) + 1, held.freqs.dtype)
    homes, queries = (x[np.argsort(n[x], kind="stable")] for x in (np.flatnonzero(role & 1), np.flatnonzero(role & 2)))
    if not len(homes) or not len(queries):
        return
    sizes = n[homes]
    words = max(1, math.ceil(2 * int(sizes[-1]) / 64))
    (of_c, more_c), (of_b, more_b) = _bits(held, n, homes, words), _bits(held, n, queries, words)
    for a in range(0, len(queries), ROWS):
        asked, b_bits = queries[a : a + ROWS], of_b[:, a : a + ROWS, None]
        picked_b, picked_c = [asked[:0]], [asked[:0]]
        for lo in range(int(np.searchsorted(sizes, low[asked[0]])), int(np.searchsorted(sizes, n[asked[-1]], "right")), COLUMNS):
            c_bits = of_c[:, None, lo : lo + COLUMNS]
            both = np.empty((len(asked), c_bits.shape[2]), np.uint64)
            times, seen = np.empty(both.shape, np.uint8), np.zeros(both.shape, np.uint16 if words < 1000 else np.int32)
            for w in range(words):
                np.bitwise_and(b_bits[w], c_bits[w], out=both)
                np.bitwise_count(both, out=times)
                np.add(seen, times, out=seen)
            i, j = np.nonzero(seen + np.minimum(more_b[a : a + ROWS, None], more_c[None, lo : lo + COLUMNS]) >= low[asked][:, None])
            b, c = asked[i], homes[lo + j]
            ok = ((n[b] > n[c]) | ((n[b] == n[c]) & (ids[b] < ids[c]))) & (n[c] >= low[b])
            picked_b.append(b[ok]), picked_c.append(c[ok])
        b, c = np.concatenate(picked_b), np.concatenate(picked_c)
        turn = np.argsort(b, kind="stable")
        yield from _verify(held, mark, ids, n, b[turn], c[turn], theta_pm, measure, strict)


def find(blocks: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, profile: str = "prose", strict: bool = False, shared: int | None = None, held: int = HELD, every: bool = False, early: bool = False) -> tuple[DataFrame, DataFrame]:
    """(pairs of representatives (b, c, n_b, n_c, overlap), membership (rep, block_id, project_id, n)), both written.

    every: all blocks of a cell are compared with each other, without an index of rare elements. early: verification stops
    as soon as a pair is decided, so overlaps are lower bounds.
    """
    sim.check(theta_pm, measure)
    codes = hashed(blocks, profile)
    levels, sizes, common, members = survey(codes)
    if members.groupBy("block_id").count().where("count > 1").limit(1).count():  # rows of one id are one block
        codes = codes.groupBy("block_id", "project_id").agg(F.flatten(F.collect_list("codes")).alias("codes"))
        unstage(members)
        levels, sizes, common, members = survey(codes)
    cells = Cells(sizes, theta_pm, measure, held)
    told = [r.block_id for r in members.where("block_id <> rep").select("block_id").limit(TOLD + 1).collect()]
    copies = np.array(sorted(told) if len(told) <= TOLD else [], np.int64)

    def search(now: Held) -> Iterator[pa.RecordBatch]:
        return _compare(now, theta_pm, measure, strict) if every else _search(now, theta_pm, measure, strict, shared or SHARED, shared is not None, early)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, now = None, Held(common)
        for batch in batches:
            for of, *row in zip(*(batch.column(k).to_pylist() for k in range(8)), strict=True):
                if of != cell:
                    yield from search(now)
                    cell, now = of, Held(common)
                now.add(*row)
        yield from search(now)

    dealt = codes.mapInArrow(_dealt(levels, cells, copies, common), BAG).repartitionById(max(1, cells.count), F.col("cell"))
    pairs = dealt.mapInArrow(run, "b long, c long, n_b int, n_c int, overlap int")
    return stage(pairs, "pairs"), members
