"""Sub-blocks in the exact order of corpus frequency, and their candidates, in cells of sizes.

Tokens are counted once. Those of high frequency, a table of bounded size, have their place in it; only the others,
few of all occurrences but the rarest of each block, are joined with their counts. Blocks then go to cells (`cells.Cells`) as
their sub-blocks, and a cell forms its candidates by itself: neither postings nor candidates are ever shuffled or written.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pandas._libs.hashtable import Int64Factorizer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import similarity as sim
from ..functions.order import MARK
from ..functions.tokens import token_array
from ..sources.io import stage, unstage
from . import cells

#: Tokens in the table at most; the rarer ones are joined with their counts.
TABLE = 1 << 19
#: Tokens of sub-blocks that a cell holds at most; larger cells are split on both sides.
HELD = 5_000_000
#: Elements of queries, and matches, at a time.
ASKED, MATCHED = 200_000, 500_000
#: Elements of whole blocks that a cell holds at most, and tokens of sets of them: 4 bytes each.
WHOLE, SETS = 14_000_000, 12_000_000
#: Elements that a walk reads beyond those a candidate can lose.
PACE = 32
#: Blocks that have a bit in a row of bits, and blocks of them that a token needs to have such a row.
BITS, DENSE = 1 << 14, 128
#: Rows of a batch that are taken apart at a time.
SLICE = 2_500
#: Added to the numbers of tokens outside the table: they come before those of the table, as they are rarer.
RARER = -(1 << 62)
#: Postings of an element that are tried whatever their sizes.
FEW = 6
SENT = "cell int, role int, block_id long, project_id string, n int, tokens binary, freqs binary"
CANDIDATE = "b long, c long, n_b int, n_c int, seen int, last_b int, last_c int"


def prefix(n: np.ndarray, theta_pm: int, measure: str) -> np.ndarray:
    """similarity.prefix_length() on arrays."""
    return np.minimum(n, n - cells.least(n, theta_pm, measure) + 1)


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        seen = batch.column("tokens").flatten().value_counts()
        yield pa.RecordBatch.from_arrays([seen.field("values"), seen.field("counts")], names=["token", "f"])


def _bags(common: pa.Array, length: Callable[[np.ndarray], np.ndarray]) -> Callable:
    """Bags of blocks: tokens outside the table as they are, then places in the table as far as `length` elements reach."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(lo, SLICE) for whole in batches for lo in range(0, whole.num_rows, SLICE)):
            column = batch.column("tokens")
            coded = column.flatten().dictionary_encode()
            words, rows = coded.dictionary, batch.num_rows
            place = pc.fill_null(pc.index_in(words, value_set=common), -1).to_numpy().astype(np.int64)
            width = len(words) + len(common) + 1
            turn = np.where(place < 0, np.arange(len(words)), place + len(words))
            of = pc.fill_null(pc.list_value_length(column), 0).to_numpy()
            key, f = np.unique(np.repeat(np.arange(rows, dtype=np.int64), of) * width + turn[coded.indices.to_numpy()], return_counts=True)
            row, key = key // width, key % width
            n = np.bincount(row, weights=f, minlength=rows).astype(np.int64)
            rare = key < len(words)
            lists = np.concatenate(([0], np.cumsum(np.bincount(row[rare], minlength=rows)))).astype(np.int32)
            # rare tokens come first in every order of theirs: what is left is for the table
            left = length(n) - np.bincount(row[rare], weights=f[rare], minlength=rows).astype(np.int64)
            row, key, f, rare_key, rare_f = row[~rare], key[~rare] - len(words), f[~rare], key[rare], f[rare]
            before = np.cumsum(f) - f
            many = np.bincount(row, minlength=rows)
            starts = np.concatenate(([0], np.cumsum(many)))[:-1]
            left = np.maximum(left, 0)[row] - (before - np.repeat(before[starts[many > 0]], many[many > 0]))
            keep = left > 0
            row, key, f = row[keep], key[keep], np.minimum(f, left)[keep]
            ends = (4 * np.concatenate(([0], np.cumsum(np.bincount(row, minlength=rows))))).astype(np.int32)
            packed = lambda x: pa.BinaryArray.from_buffers(pa.binary(), rows, [None, pa.py_buffer(ends), pa.py_buffer(x.astype("<i4"))])  # noqa: E731, B023
            yield pa.RecordBatch.from_arrays(
                [batch.column("block_id"), batch.column("project_id"), pa.array(n.astype(np.int32)), packed(key), packed(f), pa.ListArray.from_arrays(lists, words.take(pa.array(rare_key))), pa.ListArray.from_arrays(lists, pa.array(rare_f.astype(np.int32)))],
                names=["block_id", "project_id", "n", "tokens", "freqs", "rare", "rare_f"])

    return run


def token_lists(blocks: DataFrame, profile: str = "prose") -> DataFrame:
    """(block_id, project_id, tokens): rows of one id are one block."""
    docs = blocks.select("block_id", "project_id", token_array(F.col("text"), profile).alias("tokens"))
    if blocks.groupBy("block_id", "project_id").count().where("count > 1").limit(1).count():
        docs = docs.groupBy("block_id", "project_id").agg(F.flatten(F.collect_list("tokens")).alias("tokens"))
    return docs


def _occurring(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        column = batch.column("tokens")
        coded = column.flatten().dictionary_encode()
        at, width, df = coded.indices.to_numpy(), len(coded.dictionary), 0
        ends = np.concatenate(([0], np.cumsum(pc.fill_null(pc.list_value_length(column), 0).to_numpy())))
        for lo in range(0, batch.num_rows, SLICE):
            of = ends[lo : lo + SLICE + 1]
            row = np.repeat(np.arange(len(of) - 1, dtype=np.int64), np.diff(of))
            df = df + np.bincount(np.unique(row * width + at[of[0] : of[-1]]) % max(width, 1), minlength=width)
        if width:
            yield pa.RecordBatch.from_arrays([coded.dictionary, pa.array(np.bincount(at, minlength=width).astype(np.int64)), pa.array(df.astype(np.int64))], names=["token", "gf", "df"])


def token_frequencies(blocks: DataFrame, profile: str = "prose") -> DataFrame:
    """order.global_token_frequency() of blocks: tokens are counted where they are read, only counts are shuffled."""
    return token_lists(blocks, profile).mapInArrow(_occurring, "token string, gf long, df long").groupBy("token").agg(F.sum("gf").alias("gf"), F.sum("df").alias("df"))


def _elements(common: pa.Array) -> Callable:
    """(block_id, project_id, n, elements) of bags: rare tokens as they are, then those of the table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for lo in range(0, whole.num_rows, 500):
                batch = whole.slice(lo, 500)
                rare, of = batch.column("rare").flatten(), pc.list_value_length(batch.column("rare")).to_numpy()
                places, freqs = ([np.frombuffer(x, "<i4") for x in batch.column(c).to_pylist()] for c in ("tokens", "freqs"))
                rows = np.arange(batch.num_rows)
                row = np.concatenate((np.repeat(rows, of), np.repeat(rows, [len(x) for x in places])))
                turn = np.argsort(row, kind="stable")
                token = np.concatenate((np.arange(len(rare)), *(x + len(rare) for x in places)))[turn]
                f = np.concatenate((batch.column("rare_f").flatten().to_numpy(), *freqs))[turn].astype(np.int64)
                k = np.arange(1, int(f.sum()) + 1) - np.repeat(np.cumsum(f) - f, f)
                names = pa.concat_arrays([rare, common]).take(pa.array(np.repeat(token, f)))
                named = pc.binary_join_element_wise(names, pa.array(k).cast(pa.string()), MARK)
                ends = np.concatenate(([0], np.cumsum(batch.column("n").to_numpy()))).astype(np.int32)
                yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("block_id", "project_id", "n")), pa.ListArray.from_arrays(ends, named)], names=["block_id", "project_id", "n", "elements"])

    return run


def ordered(blocks: DataFrame, frequencies: DataFrame, profile: str = "prose") -> DataFrame:
    """order.ordered_blocks() by token frequency: occurrences are not shuffled, but for those of tokens outside the table.

    Tokens without a frequency come first.
    """
    common, least, every = table_of(frequencies)
    made = token_lists(blocks, profile).mapInArrow(_bags(common, lambda n: n), "block_id long, project_id string, n int, tokens binary, freqs binary, rare array<string>, rare_f array<int>").where("n > 0")
    bags = stage(made.withColumn("row", F.monotonically_increasing_id()), "bags")
    each = bags.select("row", F.explode(F.arrays_zip("rare", "rare_f")).alias("s")).select("row", F.col("s.rare").alias("token"), F.col("s.rare_f").alias("f"))
    known = each.withColumn("gf", F.lit(0)) if every else each.join(frequencies.where(F.col("gf") < least).select("token", "gf"), "token", "left")
    known = known.groupBy("row").agg(F.sort_array(F.collect_list(F.struct(F.coalesce("gf", F.lit(0)).alias("gf"), "token", "f"))).alias("s"))
    known = known.select("row", F.col("s.token").alias("named"), F.col("s.f").alias("fs"))
    joined = bags.drop("rare", "rare_f").join(known, "row", "left").select("block_id", "project_id", "n", "tokens", "freqs", F.coalesce("named", F.array().cast("array<string>")).alias("rare"), F.coalesce("fs", F.array().cast("array<int>")).alias("rare_f"))
    out = stage(joined, "inorder")
    unstage(bags)
    done = out.mapInArrow(_elements(common), "block_id long, project_id string, n int, elements array<string>")
    done._blockdup_path = out._blockdup_path
    return done


def table_of(counts: DataFrame) -> tuple[pa.Array, int, bool]:
    """(the most frequent tokens of (token, gf), in the order; the least frequency of one; whether these are all)."""
    by_gf = sorted(((r.gf, r.many) for r in counts.groupBy("gf").agg(F.count("*").alias("many")).collect()), reverse=True)
    total, least = 0, 1 << 62
    for gf, many in by_gf:
        if total + many > TABLE:
            break
        total, least = total + many, gf
    top = counts.where(F.col("gf") >= least).select("gf", "token").toArrow()
    common = top.sort_by([("gf", "ascending"), ("token", "ascending")]).column("token").combine_chunks()
    return common, least, total == sum(many for _, many in by_gf)


def sub_blocks(blocks: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, profile: str = "prose", whole: bool = False) -> tuple[DataFrame, dict[int, int]]:
    """(block_id, project_id, n, tokens, freqs, rare, rare_f), with the number of blocks of each size.

    whole: blocks are not cut to their sub-blocks, and the ids of rare tokens ascend in the order, too.

    A sub-block is its `rare` tokens, in order and by ids, as far as it reaches, and then `tokens` by their places in
    the table; each stands for as many elements as its frequency says. The order is that of ordered_blocks().
    """
    sim.check(theta_pm, measure)
    docs = token_lists(blocks, profile)
    counts = docs.select("tokens").mapInArrow(_counted, "token string, f long").groupBy("token").agg(F.sum("f").alias("gf"))
    counts = stage((counts.orderBy("gf", "token") if whole else counts).withColumn("id", F.monotonically_increasing_id()), "counts")
    common, least, every = table_of(counts)
    made = docs.mapInArrow(_bags(common, (lambda n: n) if whole else lambda n: prefix(n, theta_pm, measure)), "block_id long, project_id string, n int, tokens binary, freqs binary, rare array<string>, rare_f array<int>").where("n > 0")
    bags = stage(made.withColumn("row", F.monotonically_increasing_id()), "bags")
    sizes = {r.n: r.many for r in bags.groupBy("n").agg(F.count("*").alias("many")).collect()}
    if every:
        unstage(counts)
        return bags.select("block_id", "project_id", "n", "tokens", "freqs", F.array().cast("array<long>").alias("rare"), "rare_f"), sizes
    each = bags.select("row", F.explode(F.arrays_zip("rare", "rare_f")).alias("s")).select("row", F.col("s.rare").alias("token"), F.col("s.rare_f").alias("f"))
    known = each.join(counts.where(F.col("gf") < least), "token")
    known = known.groupBy("row").agg(F.sort_array(F.collect_list(F.struct("gf", "token", "id", "f"))).alias("s"))
    known = known.select("row", F.col("s.id").alias("ids"), F.col("s.f").alias("fs"))
    joined = bags.drop("rare", "rare_f").join(known, "row", "left").select("block_id", "project_id", "n", "tokens", "freqs", F.coalesce("ids", F.array().cast("array<long>")).alias("rare"), F.coalesce("fs", F.array().cast("array<int>")).alias("rare_f"))
    out = stage(joined, "subblocks")
    unstage(bags, counts)
    return out, sizes


def _dealt(cells_of: Callable, length: Callable[[np.ndarray], np.ndarray]) -> Callable:
    """Sub-blocks for their cells: tokens and frequencies, cut to their length."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            out: list[tuple] = []
            rare, rare_f = (batch.column(c).flatten().to_numpy() for c in ("rare", "rare_f"))
            at = batch.column("rare").offsets.to_numpy()
            at = at - at[0]
            for k, (block_id, project, n, tokens, freqs) in enumerate(zip(*(batch.column(c).to_pylist() for c in ("block_id", "project_id", "n", "tokens", "freqs")), strict=True)):
                t = np.concatenate((rare[at[k] : at[k + 1]] + RARER, np.frombuffer(tokens, "<i4")))
                f = np.concatenate((rare_f[at[k] : at[k + 1]], np.frombuffer(freqs, "<i4"))).astype(np.int64)
                left = int(length(np.int64(n))) - (np.cumsum(f) - f)
                keep = left > 0
                t, f = t[keep], np.minimum(f, left)[keep]
                body = zlib.compress(t.astype("<i8").view(np.uint8).reshape(-1, 8).T.tobytes(), 1), zlib.compress(f.astype("<i4").tobytes(), 1)
                out += [(cell, role, block_id, project, n, *body) for cell, role in cells_of(n, zlib.crc32(np.int64(block_id).tobytes()).to_bytes(4, "big"))]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), TYPES, strict=True)], names=NAMES)

    return run


NAMES = [x.split()[0] for x in SENT.split(", ")]
TYPES = [pa.int32(), pa.int32(), pa.int64(), pa.string(), pa.int32(), pa.binary(), pa.binary()]


class Cell:
    """The sub-blocks of one cell, as elements given numbers."""

    def __init__(self) -> None:
        self.rows: list[tuple] = []

    def add(self, *row) -> None:
        self.rows.append(row)

    def close(self, within: bool) -> None:
        """No more blocks come. within: an element of another project is another element."""
        self.role, self.id, project, self.n = (np.array([r[k] for r in self.rows], t) for k, t in ((0, np.int64), (1, np.int64), (2, object), (3, np.int64)))
        self.projects, of_project = np.unique([p or "" for p in project], return_inverse=True)
        self.project = of_project
        freqs = [np.frombuffer(zlib.decompress(r[5]), "<i4") for r in self.rows]
        many = np.array([len(x) for x in freqs], np.int64)
        t, done = np.empty(int(many.sum()), np.int64), 0
        for r, m in zip(self.rows, many.tolist(), strict=True):
            t.view(np.uint8).reshape(-1, 8)[done : done + m] = np.frombuffer(zlib.decompress(r[4]), np.uint8).reshape(8, m).T
            done += m
        self.rows = []
        t = Int64Factorizer(1 << 16).factorize(t)  # once for all: each call costs as much as all numbers given so far
        f = np.concatenate([np.zeros(0, np.int32), *freqs]).astype(np.int64)
        of = np.repeat(np.arange(len(many), dtype=np.int32), many)
        ends = np.cumsum(f)
        e = np.arange(int(f.sum()))
        e -= np.repeat(ends - f, f)
        e += np.repeat(t * (int(f.max(initial=0)) + 1), f)
        self.of = np.repeat(of, f)
        del t, f, of, ends, freqs
        if within:
            e = e * len(self.projects) + of_project[self.of]
        self.element = Int64Factorizer(1 << 16).factorize(e).astype(np.int32)
        del e
        self.at = np.concatenate(([0], np.cumsum(np.bincount(self.of, minlength=len(many)))))
        self.pos = np.arange(1, len(self.of) + 1, dtype=np.int32) - self.at[self.of].astype(np.int32)

    def pairs(self, theta_pm: int, measure: str, posting: bool = False, ties: bool | None = None) -> Iterator[tuple[np.ndarray, ...]]:
        """(b, c, seen, last_b, last_c) of each pair of a query and an indexed block that fit in size and share an element.

        posting: shared elements that fail filters.posting_filter() by themselves are not seen. ties: whether blocks
        of one size are a pair, without it only in the order of their ids. All pairs of a query come at once.
        """
        n, low = self.n, cells.least(self.n, theta_pm, measure)
        held = np.flatnonzero(self.role[self.of] & 1)
        queries = np.flatnonzero(self.role & 2)
        if not len(held) or not len(queries):
            return
        sized = self.element[held].astype(np.int64) << 32 | n[self.of[held]]
        turn = np.argsort(sized, kind="stable")
        sized, held = sized[turn], held[turn]
        block, place = self.of[held], self.pos[held]
        del turn
        many = np.bincount(self.element[held], minlength=int(self.element.max()) + 1)
        first = np.concatenate(([0], np.cumsum(many)))[:-1]
        bits_c = int(place.max()).bit_length()
        sub = np.diff(self.at)
        for asked in np.split(queries, np.flatnonzero(np.diff(np.cumsum(sub[queries]) // ASKED)) + 1):
            at = np.concatenate([np.arange(self.at[x], self.at[x + 1]) for x in asked])
            at = at[many[self.element[at]] > 0]
            e, of = self.element[at].astype(np.int64), self.of[at]
            start, times = first[e], many[e]
            long = np.flatnonzero(times > FEW)
            long = long[np.argsort(e[long])]  # places looked up in turn are near in memory
            start[long] = np.searchsorted(sized, (e[long] << 32) + low[of[long]], "left")
            times[long] = np.searchsorted(sized, (e[long] << 32) + n[of[long]], "right") - start[long]
            ends = np.searchsorted(of, asked, "right")
            total = np.concatenate(([0], np.cumsum(times)))[ends]
            cuts = np.flatnonzero(np.diff(total // MATCHED)) + 1
            bits = bits_c + int(sub[asked].max()).bit_length()
            for a, z in zip(np.append(0, ends[cuts - 1]), np.append(ends[cuts - 1], ends[-1]), strict=True):
                rep = times[a:z]
                if not rep.sum():
                    continue
                j = np.arange(int(rep.sum())) + np.repeat(start[a:z] - (np.cumsum(rep) - rep), rep)
                base = int(of[a])
                key = np.repeat((of[a:z].astype(np.int64) - base) * len(n) << bits | self.pos[at[a:z]].astype(np.int64) << bits_c, rep)
                key += (block[j].astype(np.int64) << bits) + place[j]
                if posting:
                    n_b, n_c, pos_b, pos_c = np.repeat(n[of[a:z]], rep), n[block[j]], np.repeat(self.pos[at[a:z]], rep), place[j]
                    key = key[cells.meets(np.minimum(pos_b, pos_c) + np.minimum(n_b - pos_b, n_c - pos_c), n_b, n_c, theta_pm, measure)]
                    if not len(key):
                        continue
                key.sort()
                pair = key >> bits
                last = np.flatnonzero(np.concatenate((pair[1:] != pair[:-1], [True])))
                seen, pair, key = np.diff(np.append(-1, last)), pair[last], key[last] & ((1 << bits) - 1)
                b, c = pair // len(n) + base, pair % len(n)
                ok = ((n[b] > n[c]) | ((n[b] == n[c]) & (self.id[b] < self.id[c] if ties is None else ties))) & (n[c] >= low[b])
                yield b[ok], c[ok], seen[ok], key[ok] >> bits_c, key[ok] & ((1 << bits_c) - 1)


class Whole(Cell):
    """The whole blocks of one cell: elements numbered in the order, and of them the sub-blocks as in any cell."""

    def __init__(self, length: Callable[[np.ndarray], np.ndarray]) -> None:
        super().__init__()
        self.length = length

    def close(self, within: bool = False) -> None:
        self.role, self.id, self.n = (np.array([r[k] for r in self.rows], np.int64) for k in (0, 1, 3))
        freqs = [np.frombuffer(zlib.decompress(r[5]), "<i4") for r in self.rows]
        freqs = [x.astype(np.min_scalar_type(int(x.max(initial=0)))) for x in freqs]
        many = np.array([len(x) for x in freqs], np.int64)
        numbers, parts = Int64Factorizer(1 << 16), []
        for lo in range(0, len(many), 1000):
            t, done = np.empty(int(many[lo : lo + 1000].sum()), np.int64), 0
            for r, m in zip(self.rows[lo : lo + 1000], many[lo : lo + 1000].tolist(), strict=True):
                t.view(np.uint8).reshape(-1, 8)[done : done + m] = np.frombuffer(zlib.decompress(r[4]), np.uint8).reshape(8, m).T
                done += m
            parts.append(numbers.factorize(t).astype(np.int32))
        self.rows = []
        t, f = np.concatenate([np.zeros(0, np.int32), *parts]), np.concatenate([np.zeros(0, np.uint8), *freqs])
        known = numbers.uniques.to_array()
        del parts, freqs, numbers
        turn = np.argsort(known)
        most = np.zeros(len(known), np.int64)
        np.maximum.at(most, t, f)
        first = np.zeros(len(known), np.int32)
        first[turn] = np.cumsum(most[turn]) - most[turn]
        start = first[t]
        del t, first, most, turn, known
        start -= np.cumsum(f, dtype=np.int32) - f  # a cell has fewer than 2^31 elements
        self.whole = np.arange(int(self.n.sum()), dtype=np.int32)
        self.whole += np.repeat(start, f)
        del f, start
        self.whole_at = np.concatenate(([0], np.cumsum(self.n)))
        sub = self.length(self.n)
        self.of = np.repeat(np.arange(len(sub), dtype=np.int32), sub)
        self.at = np.concatenate(([0], np.cumsum(sub)))
        self.pos = np.arange(1, len(self.of) + 1, dtype=np.int32) - self.at[self.of].astype(np.int32)
        self.element = self.whole[self.whole_at[self.of] + self.pos - 1]

    def read(self, own: np.ndarray, c: np.ndarray, start: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(which c, how many elements of it from `start` on with this one, elements of `own` before it, whether `own` has it) of `of` elements each."""
        row = np.repeat(np.arange(len(c)), of)
        k = np.arange(1, len(row) + 1) - (np.cumsum(of) - of)[row]
        e = self.whole[(self.whole_at[c] + start - 1)[row] + k]
        before = np.searchsorted(own, e)
        return row, k, before, own[np.minimum(before, len(own) - 1)] == e

    def own(self, b: int) -> np.ndarray:
        return self.whole[self.whole_at[b] : self.whole_at[b + 1]]


def _first(flags: np.ndarray, row: np.ndarray) -> np.ndarray:
    """Places of the first flag of each row."""
    at = np.flatnonzero(flags)
    return at[np.flatnonzero(np.concatenate(([True], row[at[1:]] != row[at[:-1]])))] if len(at) else at


def _so_far(hit: np.ndarray, of: np.ndarray, matched: np.ndarray) -> np.ndarray:
    """Matches of each row up to each of its elements."""
    run = np.concatenate(([0], np.cumsum(hit)))
    return run[1:] + np.repeat(matched - run[np.cumsum(of) - of], of)


def merged(cell: Whole, b: int, c: np.ndarray, seen: np.ndarray, last_b: np.ndarray, last_c: np.ndarray, need: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Comparisons of detect.merge() of b with each c from the last elements seen on, and those if it accepts early.

    Two cursors compare once for each element of either block, in order, until one block ends or has lost more elements
    than it can; so they are counted from c's elements and from how many of b come before each.
    """
    own, n_b, n_c = cell.own(b), int(cell.n[b]), cell.n[c]
    spare_b, spare_c = seen + n_b - last_b - need, seen + n_c - last_c - need
    plain, early = np.zeros(len(c), np.int64), np.where(seen >= need, 0, -1)
    done, matched, lost, live = np.zeros(len(c), np.int64), np.zeros(len(c), np.int64), np.zeros(len(c), np.int64), np.arange(len(c))
    while True:
        over = done[live] == (n_c - last_c)[live]
        plain[live[over]] = (done + lost)[live[over]]
        live = live[~over]
        if not len(live):
            break
        of = np.minimum((n_c - last_c - done)[live], np.maximum(spare_c - (done - matched), done)[live] + PACE)
        row, k, before, hit = cell.read(own, c[live], (last_c + done)[live], of)
        at = live[row]
        k += done[at]
        now = _so_far(hit, of, matched[live])
        gone = before - last_b[at] - (now - hit)  # of b alone, before this one
        ended = (gone > spare_b[at]) | (before >= n_b)
        stop = _first(ended | (~hit & (k - now > spare_c[at])), row)
        plain[at[stop]] = np.where(ended[stop], k[stop] - 1 + np.minimum(spare_b[at[stop]] + 1, gone[stop]), k[stop] + gone[stop])
        until = np.full(len(live), len(row))
        until[row[stop]] = stop
        won = _first(hit & (now + seen[at] == need[at]), row)
        won = won[(won < until[row[won]]) & (early[at[won]] < 0)]
        early[at[won]] = k[won] + gone[won]
        last = np.cumsum(of) - 1
        done[live], matched[live], lost[live] = k[last], now[last], gone[last]
        live = live[until == len(row)]
    return plain, np.where(early < 0, plain, early)


def within(cell: Whole, b: int, c: np.ndarray, seen: np.ndarray, last_b: np.ndarray, last_c: np.ndarray, need: np.ndarray) -> np.ndarray:
    """Which c still meet the bound from positions after all elements they share with b; it falls from each to the next."""
    own, n_b, n_c = cell.own(b), int(cell.n[b]), cell.n[c]
    ok, done, matched, live = np.ones(len(c), bool), np.zeros(len(c), np.int64), np.zeros(len(c), np.int64), np.arange(len(c))
    while True:
        live = live[ok[live] & (done < n_c - last_c)[live]]
        if not len(live):
            return ok
        of = np.minimum((n_c - last_c - done)[live], np.maximum(done[live], 2 * PACE))
        row, k, before, hit = cell.read(own, c[live], (last_c + done)[live], of)
        at = live[row]
        k += done[at]
        now = _so_far(hit, of, matched[live])
        fails = hit & (seen[at] + now + np.minimum(n_b - before - 1, n_c[at] - last_c[at] - k) < need[at])
        ok[at[fails]] = False
        last = np.cumsum(of) - 1
        done[live], matched[live] = k[last], now[last]


def by_query(cell: Whole, pairs: Iterator[tuple], theta_pm: int, measure: str) -> Iterator[tuple]:
    """(b, c, seen, last_b, last_c, need) of the pairs within the bound from positions, one query at a time."""
    for b, c, seen, last_b, last_c in pairs:
        ok = bounded(seen, last_b, last_c, cell.n[b], cell.n[c], theta_pm, measure)
        b, c, seen, last_b, last_c = (x[ok] for x in (b, c, seen, last_b, last_c))
        need = cells.needed(cell.n[b], cell.n[c], theta_pm, measure)
        cuts = np.flatnonzero(np.diff(b)) + 1
        for a, z in zip([0, *cuts.tolist()], [*cuts.tolist(), len(b)], strict=True):
            if z > a:
                yield int(b[a]), *(x[a:z] for x in (c, seen, last_b, last_c, need))


def bounded(seen: np.ndarray, last_b: np.ndarray, last_c: np.ndarray, n_b: np.ndarray, n_c: np.ndarray, theta_pm: int, measure: str) -> np.ndarray:
    """filters.position_filter() on arrays."""
    return cells.meets(seen + np.minimum(n_b - last_b, n_c - last_c), n_b, n_c, theta_pm, measure)


def in_cells(sub: DataFrame, sizes: dict[int, int], theta_pm: int, measure: str, each: Callable, schema: str, *, within: bool = False, held: int = HELD, whole: bool = False, posting: bool = False) -> DataFrame:
    """What `each` makes of the pairs of a cell of sub_blocks(): each(cell, pairs) gives record batches of `schema`.

    whole: blocks come whole, the pairs are still those of their sub-blocks.
    """
    sub_block = lambda n: prefix(n, theta_pm, measure)
    length = (lambda n: n) if whole else sub_block
    bands, lows = np.zeros(256, np.int64), cells.edges()
    for n, many in sizes.items():
        bands[np.searchsorted(lows, n, "right") - 1] += many * int(length(np.int64(n)))
    grid = cells.Cells(bands, theta_pm, measure, held)

    def closed(now: Cell) -> Iterator[pa.RecordBatch]:
        if now.rows:
            now.close(within)
            yield from each(now, now.pairs(theta_pm, measure, posting))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        new = (lambda: Whole(sub_block)) if whole else Cell
        cell, now = None, new()
        for batch in batches:
            for of, *row in zip(*(batch.column(k).to_pylist() for k in range(7)), strict=True):
                if of != cell:
                    yield from closed(now)
                    cell, now = of, new()
                now.add(*row)
        yield from closed(now)

    sub = sub.where("project_id is not null") if within else sub
    return sub.mapInArrow(_dealt(grid.of, length), SENT).repartitionById(max(1, grid.count), F.col("cell")).mapInArrow(run, schema)


def candidates(blocks: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, profile: str = "prose", position: bool = False, within: bool = False, held: int = HELD) -> DataFrame:
    """(b, c, n_b, n_c, seen, last_b, last_c) as detect.candidates() of partial indexes by sizes; position: that also meet the bound from positions."""

    def each(cell: Cell, pairs: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        for b, c, seen, last_b, last_c in pairs:
            ok = bounded(seen, last_b, last_c, cell.n[b], cell.n[c], theta_pm, measure) if position else slice(None)
            row = (cell.id[b], cell.id[c], *(x.astype(np.int32) for x in (cell.n[b], cell.n[c], seen, last_b, last_c)))
            yield pa.RecordBatch.from_arrays([pa.array(x[ok]) for x in row], names=[x.split()[0] for x in CANDIDATE.split(", ")])

    return in_cells(*sub_blocks(blocks, theta_pm, measure, profile=profile), theta_pm, measure, each, CANDIDATE, within=within, held=held)


def comparisons(blocks: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, profile: str = "prose", held: int = HELD) -> DataFrame:
    """(project_id, blocks, f1, f1f3): the blocks of each project, its candidates by sub-blocks and sizes, and of them those within the bound from positions; counted in the cells."""
    sub, sizes = sub_blocks(blocks, theta_pm, measure, profile=profile)

    def each(cell: Cell, pairs: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        made = np.zeros((2, len(cell.projects)), np.int64)
        for b, c, seen, last_b, last_c in pairs:
            ok = bounded(seen, last_b, last_c, cell.n[b], cell.n[c], theta_pm, measure)
            made += [np.bincount(cell.project[x], minlength=made.shape[1]) for x in (b, b[ok])]
        yield pa.RecordBatch.from_arrays([pa.array(cell.projects.tolist(), pa.string()), *map(pa.array, made)], names=["project_id", "f1", "f1f3"])

    found = in_cells(sub, sizes, theta_pm, measure, each, "project_id string, f1 long, f1f3 long", within=True, held=held)
    found = found.groupBy("project_id").agg(F.sum("f1").alias("f1"), F.sum("f1f3").alias("f1f3"))
    return sub.groupBy("project_id").agg(F.count("*").alias("blocks")).join(found, "project_id", "left").fillna(0, ["f1", "f1f3"])


def token_comparisons(blocks: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, profile: str = "prose", held: int = WHOLE) -> DataFrame:
    """(compared, early, nested, candidates), a row or more a cell: sums over the candidates of detect.candidates() with all its filters.

    Each is compared as by detect.merge(), without and with early acceptance; nested is every element with every other.
    """

    def each(cell: Whole, pairs: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        total = [0, 0, 0, 0]
        for b, c, seen, last_b, last_c, need in by_query(cell, pairs, theta_pm, measure):
            plain, early = merged(cell, b, c, seen, last_b, last_c, need)
            total = [x + int(y) for x, y in zip(total, (plain.sum(), early.sum(), cell.n[b] * cell.n[c].sum(), len(c)), strict=True)]
        if total[3]:
            yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in total], names=["compared", "early", "nested", "candidates"])

    sub, sizes = sub_blocks(blocks, theta_pm, measure, profile=profile, whole=True)
    return in_cells(sub, sizes, theta_pm, measure, each, "compared long, early long, nested long, candidates long", held=held, whole=True, posting=True)


def _sets(groups: int) -> Callable:
    """Blocks as sets of tokens for the cells of all pairs of groups."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rare, at, out = batch.column("rare").flatten().to_numpy(), batch.column("rare").offsets.to_numpy(), []
            at = at - at[0]
            for k, (block_id, tokens) in enumerate(zip(batch.column("block_id").to_pylist(), batch.column("tokens").to_pylist(), strict=True)):
                t = np.sort(np.concatenate((rare[at[k] : at[k + 1]] + RARER, np.frombuffer(tokens, "<i4"))))
                body, g = zlib.compress(np.diff(t, prepend=0).astype("<i8").view(np.uint8).reshape(-1, 8).T.tobytes(), 1), zlib.crc32(np.int64(block_id).tobytes()) % groups
                out += [(min(g, h) * groups + max(g, h), g, body) for h in range(groups)]
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), (pa.int32(), pa.int32(), pa.binary()), strict=True)], names=["cell", "side", "body"])

    return run


def _meeting(side: np.ndarray, bodies: list[bytes]) -> int:
    """Pairs of blocks that share a token: of different groups or, if there is but one, of that group."""
    at, parts, numbers = [0], [], Int64Factorizer(1 << 16)
    for lo in range(0, len(bodies), 1000):
        some = []
        for body in bodies[lo : lo + 1000]:
            raw = np.frombuffer(zlib.decompress(body), np.uint8).reshape(8, -1)
            some.append(np.cumsum(np.ascontiguousarray(raw.T).view("<i8").ravel()))
            at.append(at[-1] + len(some[-1]))
        parts.append(numbers.factorize(np.concatenate(some)).astype(np.int32))
    t, at = np.concatenate(parts), np.array(at)
    bodies.clear()
    del parts, numbers
    one = side.min() == side.max()
    left, right = (np.flatnonzero(side == side.min()), np.flatnonzero(side == side.max()))
    many, pairs = np.zeros(int(t.max()) + 1, np.int64), 0
    for lo in range(0, len(right), BITS):
        some = right[lo : lo + BITS]
        place = np.concatenate([np.arange(at[y], at[y + 1]) for y in some])
        e, of = t[place], np.repeat(np.arange(len(some), dtype=np.int32), at[some + 1] - at[some])
        turn = np.argsort(e, kind="stable")
        e, of = e[turn], of[turn]
        many[:] = np.bincount(e, minlength=len(many))
        start = np.cumsum(many) - many
        dense = np.full(len(many), -1, np.int32)
        common = np.flatnonzero(many >= DENSE)
        dense[common] = np.arange(len(common))
        rows = np.zeros((len(common), -(-len(some) // 64)), np.uint64)
        for k in range(0, len(common), 4000):  # flags of a byte each are made for some tokens at a time
            flags = np.zeros((min(4000, len(common) - k), 64 * rows.shape[1]), bool)
            for j, x in enumerate(common[k : k + 4000].tolist()):
                flags[j, of[start[x] : start[x] + many[x]]] = True
            rows[k : k + 4000] = np.packbits(flags, axis=1, bitorder="little").view(np.uint64)
        met = np.zeros(64 * rows.shape[1], bool)
        for x in left.tolist():
            mine = t[at[x] : at[x + 1]]
            mine = mine[many[mine] > 0]
            d = dense[mine]
            few = mine[d < 0]
            met[:] = False
            if len(few):
                times = many[few]
                met[of[np.arange(int(times.sum())) + np.repeat(start[few] - (np.cumsum(times) - times), times)]] = True
            bits = np.packbits(met, bitorder="little").view(np.uint64)
            d = d[d >= 0]
            for k in range(0, len(d), 256):
                bits = bits | np.bitwise_or.reduce(rows[d[k : k + 256]], axis=0)
            pairs += int(np.bitwise_count(bits).sum(dtype=np.int64))
    return (pairs - len(left)) // 2 if one else pairs


def sharing(sub: DataFrame, held: int = SETS) -> DataFrame:
    """(pairs), a row a cell: pairs of blocks of sub_blocks(whole=True) that share an element, whatever their sizes.

    They are counted, not made: all blocks of a group with one of a token are a row of bits, and a block's rows are joined.
    """
    total = sub.agg(F.sum(F.octet_length("tokens") / 4 + F.size("rare"))).first()[0] or 0
    groups = max(4, -(-2 * int(total) // held))

    def counted(cell: int | None, side: list[int], bodies: list[bytes]) -> Iterator[pa.RecordBatch]:
        if bodies and (cell // groups == cell % groups or len(set(side)) == 2):  # else one of the two groups is empty
            yield pa.RecordBatch.from_arrays([pa.array([_meeting(np.array(side), bodies)], pa.int64())], names=["pairs"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, side, bodies = None, [], []
        for batch in batches:
            for of, g, body in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                if of != cell:
                    yield from counted(cell, side, bodies)
                    cell, side, bodies = of, [], []
                side.append(g)
                bodies.append(body)
        yield from counted(cell, side, bodies)

    return sub.mapInArrow(_sets(groups), "cell int, side int, body binary").repartitionById(groups * groups, F.col("cell")).mapInArrow(run, "pairs long")


def position_alone(blocks: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, profile: str = "prose", held: int = WHOLE, sets: int = SETS) -> DataFrame:
    """(pairs, within_bound), a row or more a cell: pairs that share an element, and those within the bound from positions after all of them.

    Pairs within the bound fit in size and share an element of their sub-blocks: else the bound at the first one shared is too low.
    """

    def each(cell: Whole, pairs: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
        total = sum(int(within(cell, *row).sum()) for row in by_query(cell, pairs, theta_pm, measure))
        yield pa.RecordBatch.from_arrays([pa.array([0], pa.int64()), pa.array([total], pa.int64())], names=["pairs", "within_bound"])

    sub, sizes = sub_blocks(blocks, theta_pm, measure, profile=profile, whole=True)
    found = stage(in_cells(sub, sizes, theta_pm, measure, each, "pairs long, within_bound long", held=held, whole=True), "bounded")  # one shuffle of blocks after the other
    return found.unionByName(stage(sharing(sub, sets).select("pairs", F.lit(0).cast("long").alias("within_bound")), "sharing"))


def _coded(common: pa.Array) -> Callable:
    """Ordered blocks as what sub_blocks(whole=True) gives: rare tokens, which come first, by a hash of 61 bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(lo, SLICE) for whole in batches for lo in range(0, whole.num_rows, SLICE)):
            column, rows = batch.column("elements"), batch.num_rows
            coded = column.flatten().dictionary_encode()
            of, words = pd.factorize(np.array([x.rsplit(MARK, 1)[0] for x in coded.dictionary.to_pylist()], dtype=object))
            place = pc.fill_null(pc.index_in(pa.array(words, pa.string()), value_set=common), -1).to_numpy().astype(np.int64)
            number = np.where(place < 0, (pd.util.hash_array(words) & np.uint64((1 << 61) - 1)).astype(np.int64) if len(words) else place, place)
            row = np.repeat(np.arange(rows, dtype=np.int64), pc.list_value_length(column).to_numpy())
            t = of[coded.indices.to_numpy()]
            start = np.flatnonzero(np.concatenate((np.ones(min(1, len(t)), bool), (t[1:] != t[:-1]) | (row[1:] != row[:-1]))))  # a token's elements stand together
            f, row, t = np.diff(np.append(start, len(t))), row[start], t[start]
            rare, number = place[t] < 0, number[t]
            lists, ends = (np.concatenate(([0], np.cumsum(np.bincount(row[x], minlength=rows)))).astype(np.int32) for x in (rare, ~rare))
            packed = lambda x: pa.BinaryArray.from_buffers(pa.binary(), rows, [None, pa.py_buffer(4 * ends), pa.py_buffer(x[~rare].astype("<i4"))])  # noqa: E731, B023
            yield pa.RecordBatch.from_arrays(
                [*(batch.column(c) for c in ("block_id", "project_id", "n")), packed(number), packed(f), pa.ListArray.from_arrays(lists, pa.array(number[rare])), pa.ListArray.from_arrays(lists, pa.array(f[rare].astype(np.int32)))],
                names=["block_id", "project_id", "n", "tokens", "freqs", "rare", "rare_f"])

    return run


class Sides(cells.Cells):
    """Cells of two sides: a held block goes to the cells of its own band only, and one asked for to all bands that partners may lie in."""

    def __init__(self, held: np.ndarray, asked: np.ndarray, theta_pm: int, measure: str, most: int):
        self.lows, self.theta_pm, self.measure = cells.edges(), theta_pm, measure
        self.split, self.first, self.count = {}, {}, 0
        for band in np.flatnonzero(held):
            reach = sum(int(asked[x]) for x in range(self.floor(int(self.lows[band])), self.top(int(self.lows[band + 1])) + 1))
            s, t = (max(1, -(-2 * int(x) // most)) for x in (held[band], reach))
            self.split[int(band)], self.first[int(band)] = (s, t), self.count
            self.count += s * t

    def top(self, n: int) -> int:
        """The highest band of a partner of n."""
        return int(np.searchsorted(cells.least(self.lows, self.theta_pm, self.measure), n, "right") - 1)

    def of_held(self, n: int, digest: bytes) -> Iterator[tuple[int, int]]:
        band, x = int(np.searchsorted(self.lows, n, "right") - 1), digest[0] << 8 | digest[1]
        s, t = self.split[band]
        for j in range(t):
            yield self.first[band] + x % s * t + j, 1

    def of_asked(self, n: int, digest: bytes) -> Iterator[tuple[int, int]]:
        y = digest[2] << 8 | digest[3]
        for band in range(self.floor(n), self.top(n) + 1):
            s, t = self.split.get(band, (0, 1))
            for i in range(s):
                yield self.first[band] + i * t + y % t, 2


def matches(asked: DataFrame, held: DataFrame, frequencies: DataFrame, theta_pm: int = 700, measure: str = "overlap", most: int = WHOLE) -> DataFrame:
    """(b, c, n_b, n_c, overlap): blocks asked for (b) and held ones (c), ordered by these frequencies, that meet the threshold.

    Held blocks are sent once, and those asked for to the cells their partners may be in; candidates, from sub-blocks and
    the bound from positions, are verified there on whole blocks. Neither postings nor candidates are shuffled.
    """
    common, lows = table_of(frequencies)[0], cells.edges()
    bands = []
    for side in (held, asked):
        bands.append(np.zeros(len(lows) + 1, np.int64))
        for n, many in side.groupBy("n").count().collect():
            bands[-1][np.searchsorted(lows, n, "right") - 1] += n * many
    grid = Sides(*bands, theta_pm, measure, most)
    code = _coded(common)

    def sent(side: DataFrame, cells_of: Callable) -> DataFrame:
        dealt = _dealt(cells_of, lambda n: n)
        return side.select("block_id", "project_id", "n", "elements").mapInArrow(lambda batches: dealt(code(batches)), SENT)

    def found(cell: Whole) -> Iterator[pa.RecordBatch]:
        cell.close()
        mark, sides = np.zeros(int(cell.whole.max(initial=-1)) + 1, bool), cell.role
        for turned in (False, True):  # the larger block is the one asked for, or the held one
            cell.role = 3 - sides if turned else sides
            out: list[tuple] = []
            for b, c, seen, _, last_c, need in by_query(cell, cell.pairs(theta_pm, measure, ties=not turned), theta_pm, measure):
                mark[cell.own(b)] = True
                for lo in range(0, len(c), 256):
                    some, after = c[lo : lo + 256], last_c[lo : lo + 256]
                    of = cell.n[some] - after
                    row = np.repeat(np.arange(len(some)), of)
                    at = np.arange(len(row)) + np.repeat(cell.whole_at[some] + after - (np.cumsum(of) - of), of)
                    overlap = seen[lo : lo + 256] + np.bincount(row, weights=mark[cell.whole[at]], minlength=len(some)).astype(np.int64)
                    ok = overlap >= need[lo : lo + 256]
                    out += [(cell.id[x], cell.id[y], cell.n[x], cell.n[y], o) for x, y, o in ((z, b, o) if turned else (b, z, o) for z, o in zip(some[ok].tolist(), overlap[ok].tolist(), strict=True))]
                mark[cell.own(b)] = False
                if len(out) > 10_000:
                    yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32()), strict=True)], names=["b", "c", "n_b", "n_c", "overlap"])
                    out = []
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out, strict=True), (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32()), strict=True)], names=["b", "c", "n_b", "n_c", "overlap"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, now = None, Whole(lambda n: prefix(n, theta_pm, measure))
        for batch in batches:
            for of, *row in zip(*(batch.column(k).to_pylist() for k in range(7)), strict=True):
                if of != cell:
                    yield from found(now) if now.rows else ()
                    cell, now = of, Whole(now.length)
                now.add(*row)
        yield from found(now) if now.rows else ()

    dealt = sent(held, grid.of_held).unionByName(sent(asked, grid.of_asked))
    return dealt.repartitionById(max(1, grid.count), F.col("cell")).mapInArrow(run, "b long, c long, n_b int, n_c int, overlap int")
