"""Stand-ins for the classes of technique the method is compared with; none claims to be a given program."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.similarity import meets
from ..functions.tokens import normalize_t1, normalize_t2, normalized_lines, token_array
from .detect import _accept, candidates
from .index import full_index

PRESETS = {
    "scale": {"min_lines": 6, "theta_pm": 700}, "mutant": {"min_lines": 15, "theta_pm": 700}, "large": {"min_lines": 10, "theta_pm": 700},
    "token_runs": {"min_tokens": 50, "min_types": 12}, "vectors": {"min_tokens": 50, "sim_pm": 850, "step": 2}, "vectors_mutant": {"min_tokens": 100, "sim_pm": 850, "step": 4},
    "gapped_runs": {"min_tokens": 50, "min_block": 20}, "line_lcs": {"min_lines": 6, "sim_pm": 700},
    "gapped_runs_mutant": {"min_tokens": 100, "min_block": 20}, "line_lcs_mutant": {"min_lines": 15, "sim_pm": 700},
}


#: Rows of a group of an all-pairs reference.
ROWS = 500


def _all(left: DataFrame, right: DataFrame, key_left: str, key_right: str, n: int, rows: int) -> DataFrame:
    """Every row of `left` with every row of `right`, both of about n rows: an equi-join on pairs of groups, so no side is sent whole to a task."""
    groups = max(1, -(-n // rows))
    each = F.explode(F.sequence(F.lit(0), F.lit(groups - 1)))
    group = lambda key: F.pmod(F.xxhash64(key), F.lit(groups)).cast("int")
    x = left.withColumn("group_l", group(key_left)).withColumn("group_r", each)
    y = right.withColumn("group_r2", group(key_right)).withColumn("group_l2", each)
    return x.join(y.hint("merge"), (F.col("group_l") == F.col("group_l2")) & (F.col("group_r") == F.col("group_r2"))).drop("group_l", "group_r", "group_l2", "group_r2")


def all_pairs(ordered: DataFrame, theta_pm: int = 700, rows: int = ROWS) -> DataFrame:
    """Every pair of blocks compared: the quadratic reference. Groups of about `rows` blocks meet each other, so memory is bounded; time is not."""
    b = ordered.select(F.col("block_id").alias("b"), F.col("n").alias("n_b"), F.col("elements").alias("of_b"))
    c = ordered.select(F.col("block_id").alias("c"), F.col("n").alias("n_c"), F.col("elements").alias("of_c"))
    turn = (F.col("n_b") > F.col("n_c")) | ((F.col("n_b") == F.col("n_c")) & (F.col("b") < F.col("c")))
    return _accept(_all(b, c, "b", "c", ordered.count(), rows).where(turn).withColumn("overlap", F.size(F.array_intersect("of_b", "of_c"))), theta_pm, "overlap", False)


def full_index_join(ordered: DataFrame, theta_pm: int = 700) -> DataFrame:
    """The usual inverted index over all elements: overlaps are exact, candidates are many."""
    postings = full_index(ordered)
    found = candidates(postings, postings, theta_pm, filters=frozenset())
    return _accept(found.withColumn("overlap", F.col("seen")), theta_pm, "overlap", False)


def normalized_hash(blocks: DataFrame, level: str = "t1", profile: str = "prose") -> DataFrame:
    """(b, c), b < c, of equal texts after normalisation: scales, but finds no edited copy."""
    norm = normalize_t1(F.col("text"), profile) if level == "t1" else normalize_t2(F.col("text"), profile)
    keyed = blocks.select("block_id", F.sha2(norm, 256).alias("key"))
    x, y = keyed.select(F.col("block_id").alias("b"), "key"), keyed.select(F.col("block_id").alias("c"), F.col("key").alias("key_c"))
    return x.join(y, (F.col("key") == F.col("key_c")) & (F.col("b") < F.col("c"))).select("b", "c")


def _positions(blocks: DataFrame, profile: str, window: int) -> DataFrame:
    """(block_id, project_id, pos, key, kinds): hash of each run of `window` normalised tokens."""
    tokens = blocks.select("block_id", "project_id", token_array(normalize_t2(F.col("text"), profile)).alias("t")).where(F.size("t") >= window)
    at = F.sequence(F.lit(1), F.size("t") - window + 1)
    return tokens.select("block_id", "project_id", "t", F.explode(at).alias("pos")).select("block_id", "project_id", "pos", F.xxhash64(F.slice("t", F.col("pos"), window)).alias("key"), F.size(F.array_distinct(F.slice("t", F.col("pos"), window))).alias("kinds"))


def _apart(across: bool):
    """Condition of a join of sides `project_b` and `project_c`: with `across`, only blocks of different projects meet."""
    return ~F.col("project_b").eqNullSafe(F.col("project_c")) if across else F.lit(True)


def token_spans(blocks: DataFrame, window: int, min_types: int = 0, profile: str = "prose", across: bool = False) -> DataFrame:
    """(b, c, at_b, at_c, tokens): maximal equal runs, by gaps and islands on the diagonals of pairs."""
    p = _positions(blocks, profile, window).where(F.col("kinds") >= min_types)
    x = p.select(F.col("block_id").alias("b"), F.col("project_id").alias("project_b"), F.col("pos").alias("p_b"), "key")
    y = p.select(F.col("block_id").alias("c"), F.col("project_id").alias("project_c"), F.col("pos").alias("p_c"), F.col("key").alias("key_c"))
    hits = x.join(y, (F.col("key") == F.col("key_c")) & (F.col("b") < F.col("c")) & _apart(across)).withColumn("diagonal", F.col("p_b") - F.col("p_c"))
    lane = Window.partitionBy("b", "c", "diagonal").orderBy("p_b")
    island = hits.withColumn("island", F.col("p_b") - F.row_number().over(lane))
    return island.groupBy("b", "c", "diagonal", "island").agg(F.min("p_b").alias("at_b"), F.min("p_c").alias("at_c"), (F.count("*") + window - 1).cast("int").alias("tokens")).drop("diagonal", "island")


def token_runs(blocks: DataFrame, min_tokens: int = 50, min_types: int = 12, profile: str = "prose") -> DataFrame:
    """Equal normalised token runs: exact and renamed copies only."""
    return token_spans(blocks, min_tokens, min_types, profile).groupBy("b", "c").agg(F.max("tokens").alias("longest"), F.count("*").alias("runs"))


def gapped_spans(blocks: DataFrame, min_tokens: int = 50, min_block: int = 20, max_gap: int = 20, profile: str = "prose", across: bool = False) -> DataFrame:
    """(b, c, at_b, end_b, at_c, end_c, tokens): runs of `min_block` tokens joined across gaps of up to `max_gap`; ends are the last tokens."""
    runs = token_spans(blocks, min_block, 0, profile, across)
    lane = Window.partitionBy("b", "c").orderBy("at_b", "at_c")
    end_b, end_c = F.lag(F.col("at_b") + F.col("tokens")).over(lane), F.lag(F.col("at_c") + F.col("tokens")).over(lane)
    fresh = end_b.isNull() | (F.col("at_b") - end_b > max_gap) | (F.abs(F.col("at_c") - end_c) > max_gap)
    chained = runs.withColumn("new", fresh.cast("int")).withColumn("chain", F.sum("new").over(lane.rowsBetween(Window.unboundedPreceding, 0)))
    ends = (F.max(F.col(f"at_{s}") + F.col("tokens") - 1).alias(f"end_{s}") for s in "bc")
    spans = chained.groupBy("b", "c", "chain").agg(F.min("at_b").alias("at_b"), F.min("at_c").alias("at_c"), *ends, F.sum("tokens").alias("tokens"))
    return spans.where(F.col("tokens") >= min_tokens).drop("chain")


def gapped_runs(blocks: DataFrame, min_tokens: int = 50, min_block: int = 20, max_gap: int = 20, profile: str = "prose") -> DataFrame:
    """The longest chain of runs of each pair; fails when gaps are many."""
    return gapped_spans(blocks, min_tokens, min_block, max_gap, profile).groupBy("b", "c").agg(F.max("tokens").cast("int").alias("longest"))


def lcs_length(a: list[str], b: list[str]) -> int:
    """Length of the longest common subsequence, a row of the table at a time."""
    codes: dict[str, int] = {}
    y = np.array([codes.setdefault(x, len(codes)) for x in b])
    row = np.zeros(len(b) + 1, np.int32)
    for x in a:
        hit = np.concatenate(([0], np.where(y == codes.get(x, -1), row[:-1] + 1, row[1:]))) if len(b) else row
        row = np.maximum.accumulate(np.maximum(hit, row))
    return int(row[-1])


def line_lcs(blocks: DataFrame, min_lines: int = 6, sim_pm: int = 700, profile: str = "prose", across: bool = False) -> DataFrame:
    """Pairs whose normalised lines share a long enough common subsequence; candidates share a line and fit in size."""
    lines = blocks.select("block_id", "project_id", normalized_lines(F.col("text"), profile).alias("lines")).where(F.size("lines") >= min_lines)
    each = lines.select("block_id", "project_id", F.explode(F.array_distinct("lines")).alias("line"), F.size("lines").alias("n"))
    x, y = each.select(F.col("block_id").alias("b"), F.col("project_id").alias("project_b"), "line", F.col("n").alias("n_b")), each.select(F.col("block_id").alias("c"), F.col("project_id").alias("project_c"), F.col("line").alias("line_c"), F.col("n").alias("n_c"))
    fits = meets(F.least("n_b", "n_c"), F.col("n_b"), F.col("n_c"), sim_pm)
    pairs = x.join(y, (F.col("line") == F.col("line_c")) & (F.col("b") < F.col("c")) & fits & _apart(across)).select("b", "c").distinct()
    rows = pairs.join(lines.select(F.col("block_id").alias("b"), F.col("lines").alias("of_b")), "b").join(lines.select(F.col("block_id").alias("c"), F.col("lines").alias("of_c")), "c")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = [(r.b, r.c, len(r.of_b), len(r.of_c), lcs_length(list(r.of_b), list(r.of_c))) for r in batch.itertuples(index=False)]
            yield pd.DataFrame(out, columns=["b", "c", "n_b", "n_c", "lcs"])

    return rows.mapInPandas(run, "b long, c long, n_b int, n_c int, lcs int").where(meets(F.col("lcs"), F.col("n_b"), F.col("n_c"), sim_pm))


def vector_hits(blocks: DataFrame, min_tokens: int = 50, sim_pm: int = 850, step: int = 2, tables: int = 8, profile: str = "prose", dimensions: int = 32, across: bool = False) -> DataFrame:
    """(b, c, at_b, at_c), one row a table in which two windows meet: count vectors of sliding windows, near in vector
    space by random hyperplanes; an exact cosine decides. Places are of the first token, from 1."""
    tokens = blocks.select("block_id", "project_id", token_array(normalize_t2(F.col("text"), profile)).alias("t")).where(F.size("t") >= min_tokens)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        planes = np.random.default_rng(17).normal(size=(tables, 16, dimensions))
        for batch in batches:
            out = []
            for block_id, project_id, t in zip(batch.block_id, batch.project_id, batch.t, strict=True):
                codes = pd.util.hash_array(np.asarray(t, dtype=object)) % dimensions
                one = np.zeros((len(codes) + 1, dimensions))
                np.cumsum(np.eye(dimensions)[codes], axis=0, out=one[1:])
                starts = np.arange(0, len(codes) - min_tokens + 1, step)
                v = one[starts + min_tokens] - one[starts]
                v = v - v.mean(axis=1, keepdims=True)
                bits = (np.einsum("thd,nd->nth", planes, v) > 0) @ (1 << np.arange(16))
                out += [(block_id, project_id, int(s) + 1, k << 16 | int(b), list(x)) for s, x, row in zip(starts, v, bits, strict=True) for k, b in enumerate(row)]
            yield pd.DataFrame(out, columns=["block_id", "project_id", "at", "bucket", "v"])

    w = tokens.mapInPandas(run, "block_id long, project_id string, at int, bucket long, v array<double>")
    x = w.select(F.col("block_id").alias("b"), F.col("project_id").alias("project_b"), F.col("at").alias("at_b"), "bucket", F.col("v").alias("v_b"))
    y = w.select(F.col("block_id").alias("c"), F.col("project_id").alias("project_c"), F.col("at").alias("at_c"), F.col("bucket").alias("bucket_c"), F.col("v").alias("v_c"))
    return x.join(y, (F.col("bucket") == F.col("bucket_c")) & (F.col("b") < F.col("c")) & _apart(across) & (cosine(F.col("v_b"), F.col("v_c")) >= sim_pm / 1000)).select("b", "c", "at_b", "at_c")


def vector_windows(blocks: DataFrame, **options) -> DataFrame:
    """(b, c, windows): meetings of windows for each pair."""
    return vector_hits(blocks, **options).groupBy("b", "c").agg(F.count("*").alias("windows"))


def vector_spans(blocks: DataFrame, min_tokens: int = 50, step: int = 2, **options) -> DataFrame:
    """(b, c, at_b, end_b, at_c, end_c): near windows joined while one begins within the one before it on both sides."""
    hits = vector_hits(blocks, min_tokens=min_tokens, step=step, **options).distinct()
    shift = F.round((F.col("at_b") - F.col("at_c")) / min_tokens)  # near windows of one passage keep about one distance
    lane = Window.partitionBy("b", "c", "shift").orderBy("at_b", "at_c")
    fresh = F.coalesce(F.col("at_b") - F.lag("at_b").over(lane) > min_tokens, F.lit(True))
    chained = hits.withColumn("shift", shift).withColumn("new", fresh.cast("int")).withColumn("chain", F.sum("new").over(lane.rowsBetween(Window.unboundedPreceding, 0)))
    ends = (F.max(F.col(f"at_{s}") + min_tokens - 1).alias(f"end_{s}") for s in "bc")
    return chained.groupBy("b", "c", "shift", "chain").agg(F.min("at_b").alias("at_b"), F.min("at_c").alias("at_c"), *ends).drop("shift", "chain")


def dot(a, b):
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a, b):
    return dot(a, b) / (F.sqrt(dot(a, a)) * F.sqrt(dot(b, b)))


def embedding_cosine(vectors: DataFrame, threshold: float, rows: int = ROWS) -> DataFrame:
    """All pairs of dense vectors, a reference, by groups of about `rows` vectors."""
    x = vectors.select(F.col("vec_id").alias("b"), F.col("embedding").alias("v_b"))
    y = vectors.select(F.col("vec_id").alias("c"), F.col("embedding").alias("v_c"))
    return _all(x, y, "b", "c", vectors.count(), rows).where((F.col("b") < F.col("c")) & (cosine(F.col("v_b"), F.col("v_c")) >= threshold)).select("b", "c")
