"""Detection: candidates from an equi-join of postings, one aggregate, one bound, exact verification.

The search for candidates accumulates, for each pair, the shared sub-block elements and the last place of
one on either side. A single hash aggregate does this: the bound from positions never rises from one match
to the next, so it is enough to test it after the last.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import filters as flt
from ..functions import order as orders
from ..functions import similarity as sim
from ..functions.tokens import bag_of_tokens, tokenize
from ..sources.io import stage
from . import cells
from .index import full_index, partial_index

ALL = flt.FILTERS
PAIR = ("b", "c", "n_b", "n_c", "overlap", "similarity")


def _after(n_b: Column, b: Column, n_c: Column, c: Column) -> Column:
    """Each pair once: b is the larger block; among equals the smaller id comes first."""
    return (n_b > n_c) | ((n_b == n_c) & (b < c))


#: An element with more postings than this is split over several tasks on one side of the join.
HOT = 20_000


def size_bits(n: Column) -> Column:
    """Binary digits of a size: blocks within a factor of two differ by one at most."""
    return F.length(F.bin(n))


def _reach(theta_pm: int, measure: str) -> int:
    """Steps of size_bits that a partner can lie away."""
    share, steps = (theta_pm / 1000) ** (2 if measure == "cosine" else 1), 0
    while share < 1:
        share, steps = share * 2, steps + 1
    return steps


def spread_hot(b: DataFrame, c: DataFrame, hot: int) -> tuple[DataFrame, DataFrame, list[str]]:
    """Postings with a column `salt`: those of a hot element of `c` are dealt over parts, those of `b` go to each of its parts.

    A hot element's rows then meet in as many tasks as it has parts, whatever their output. Elements are hot by
    their own number of postings; the table of them is no longer than the postings over `hot`.
    """
    many = c.groupBy("element").agg(F.count("*").alias("times")).where(F.col("times") > hot).select("element", F.ceil(F.col("times") / hot).cast("int").alias("parts"))
    many = stage(many, "hot")
    if not many.limit(1).count():
        return b, c, []
    dealt = c.join(many, "element", "left").withColumn("salt", F.pmod(F.xxhash64("c"), F.coalesce("parts", F.lit(1))).cast("int")).drop("parts")
    sent = b.join(many, "element", "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.coalesce("parts", F.lit(1)) - 1))).drop("parts")
    return sent, dealt, ["salt"]


def candidates(
    left: DataFrame, right: DataFrame, theta_pm: int = 700, measure: str = "overlap", *,
    between: bool = False, within: bool = False, filters: frozenset[str] = ALL, min_shared: int = 1, hot: int | None = HOT,
) -> DataFrame:
    """(b, c, n_b, n_c, seen, last_b, last_c) from two sets of postings.

    between: the sides are different repositories, so both orders of size are possible. within: only pairs
    of one project. The join key is the element, the binary digits of the size (with the size filter) and, for
    elements of more than `hot` postings, a part of them: popular elements are split three ways at once.
    """
    b = left.select("element", F.col("block_id").alias("b"), F.col("project_id").alias("project_b"), F.col("pos").alias("pos_b"), F.col("n").alias("n_b"))
    c = right.select("element", F.col("block_id").alias("c"), F.col("project_id").alias("project_c"), F.col("pos").alias("pos_c"), F.col("n").alias("n_c"))
    n_b, n_c, pos_b, pos_c = (F.col(x) for x in ("n_b", "n_c", "pos_b", "pos_c"))
    keys = ["element"]
    if hot:
        b, c, more = spread_hot(b, c, hot)
        keys += more
    if "size" in filters:
        steps = _reach(theta_pm, measure)
        c = c.withColumn("bits", size_bits(n_c))
        b = b.withColumn("bits", F.explode(F.sequence(size_bits(n_b) - steps, size_bits(n_b) + (steps if between else 0))))
        keys.append("bits")
    c = c.select(*(F.col(k).alias(f"{k}_c") if k in keys else F.col(k) for k in c.columns))
    on = F.lit(True)
    for k in keys:
        on = on & (F.col(k) == F.col(f"{k}_c"))
    if within:
        on = on & (F.col("project_b") == F.col("project_c"))
    if not between:
        on = on & _after(n_b, F.col("b"), n_c, F.col("c"))
    if "size" in filters:
        on = on & flt.size_filter(F.greatest(n_b, n_c), F.least(n_b, n_c), theta_pm, measure)
    if "position" in filters:
        on = on & flt.posting_filter(pos_b, pos_c, n_b, n_c, theta_pm, measure)
    found = b.join(c, on).groupBy("b", "c", "n_b", "n_c").agg(
        F.count("*").cast("int").alias("seen"), F.max("pos_b").alias("last_b"), F.max("pos_c").alias("last_c"))
    if min_shared > 1:
        found = found.where(F.col("seen") >= F.least(F.lit(min_shared), sim.required_overlap(n_b, n_c, theta_pm, measure)))
    if "position" in filters:
        found = found.where(flt.position_filter(F.col("seen"), F.col("last_b"), F.col("last_c"), n_b, n_c, theta_pm, measure))
    return found


def _accept(df: DataFrame, theta_pm: int, measure: str, strict: bool) -> DataFrame:
    kept = df.where(sim.meets(F.col("overlap"), F.col("n_b"), F.col("n_c"), theta_pm, measure, strict))
    return kept.withColumn("similarity", sim.similarity(F.col("overlap"), F.col("n_b"), F.col("n_c"), measure)).select(*PAIR)


def _with_elements(found: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    b = left.select(F.col("block_id").alias("b"), F.col("elements").alias("of_b"))
    c = right.select(F.col("block_id").alias("c"), F.col("elements").alias("of_c"))
    return found.join(b, "b").join(c, "c")


def _rest(e: Column, last: Column) -> Column:
    return F.slice(e, last + 1, F.greatest(F.size(e) - last, F.lit(0)))


def verify_array(found: DataFrame, left: DataFrame, right: DataFrame, theta_pm: int, measure: str = "overlap", strict: bool = False) -> DataFrame:
    """Resume after the last elements seen; the rest by a hashed set intersection inside the JVM.

    Candidates carry what is left of a block as 64-bit hashes, cut before it is sent on; the few that pass are
    counted once more on the elements themselves. Only a hash shared by two elements of one block could hide a
    pair: a chance of n * n / 2^65.
    """
    codes = F.transform("elements", lambda e: F.xxhash64(e))
    b = left.select(F.col("block_id").alias("b"), codes.alias("of_b"))
    c = right.select(F.col("block_id").alias("c"), codes.alias("of_c"))
    half = found.join(b, "b").withColumn("of_b", _rest(F.col("of_b"), F.col("last_b")))
    tail = F.size(F.array_intersect("of_b", _rest(F.col("of_c"), F.col("last_c"))))
    likely = half.join(c, "c").withColumn("overlap", F.col("seen") + tail).where(sim.meets(F.col("overlap"), F.col("n_b"), F.col("n_c"), theta_pm, measure, strict))
    exact = _with_elements(likely.select("b", "c", "n_b", "n_c"), left, right).withColumn("overlap", F.size(F.array_intersect("of_b", "of_c")))
    return _accept(exact, theta_pm, measure, strict)


def verify_join(found: DataFrame, left: DataFrame, right: DataFrame, theta_pm: int, measure: str = "overlap", strict: bool = False) -> DataFrame:
    """The same by joins of element rows."""
    b = left.select(F.col("block_id").alias("b"), F.explode("elements").alias("e"))
    c = right.select(F.col("block_id").alias("c"), F.explode("elements").alias("e"))
    counted = found.select("b", "c", "n_b", "n_c").join(b, "b").join(c, ["c", "e"]).groupBy("b", "c", "n_b", "n_c").agg(F.count("*").cast("int").alias("overlap"))
    return _accept(counted, theta_pm, measure, strict)


MERGED = "b long, c long, n_b int, n_c int, overlap int, compared int, outcome string"


def merge(of_b: list[tuple], of_c: list[tuple], i: int, j: int, seen: int, need: int, early_accept: bool) -> tuple[int, int, str]:
    """(overlap, comparisons, outcome) by two cursors over blocks in one common order.

    The cursor at the lower element moves on; both do after a match. What is left on the shorter side bounds the
    overlap from above and ends a lost cause; early_accept ends a won one.
    """
    n_b, n_c, compared = len(of_b), len(of_c), 0
    while i < n_b and j < n_c and seen + min(n_b - i, n_c - j) >= need and not (early_accept and seen >= need):
        compared += 1
        x, y = of_b[i], of_c[j]
        seen += x == y
        i, j = i + (x <= y), j + (y <= x)
    return seen, compared, "accepted" if seen >= need else "rejected"


def verify_merge(found: DataFrame, left: DataFrame, right: DataFrame, theta_pm: int, measure: str = "overlap", early_accept: bool = False) -> DataFrame:
    """Verification that stops as soon as the bound decides, with its cost; overlap is a lower bound if it accepts early.

    `left` and `right` hold the sort keys of their elements beside them (`keys`, see ordered_blocks).
    """
    b = left.select(F.col("block_id").alias("b"), F.col("elements").alias("of_b"), F.col("keys").alias("keys_b"))
    c = right.select(F.col("block_id").alias("c"), F.col("elements").alias("of_c"), F.col("keys").alias("keys_c"))
    rows = found.join(b, "b").join(c, "c").withColumn("need", sim.required_overlap(F.col("n_b"), F.col("n_c"), theta_pm, measure))

    def ordered(keys, elements) -> list[tuple]:
        parts = (e.split(orders.MARK) for e in elements)
        return [(key, token, int(k)) for key, (token, k) in zip(keys.tolist(), parts, strict=True)]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = [(r.b, r.c, r.n_b, r.n_c, *merge(ordered(r.keys_b, r.of_b), ordered(r.keys_c, r.of_c), r.last_b, r.last_c, r.seen, r.need, early_accept)) for r in batch.itertuples(index=False)]
            yield pd.DataFrame(out, columns=["b", "c", "n_b", "n_c", "overlap", "compared", "outcome"])

    return rows.mapInPandas(run, MERGED)


VERIFIERS = {"array": verify_array, "join": verify_join}


def collapse_copies(ordered: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(one block a distinct bag, (block_id, project_id, rep, n)): equal bags have equal neighbours, so nothing is lost."""
    marked = ordered.withColumn("bag_key", F.sha2(F.array_join("elements", "\u0002"), 256))
    reps = marked.groupBy("bag_key").agg(F.min("block_id").alias("rep"))
    # hash-only columns are joined back: the arrays stay out of this shuffle
    members = marked.select("bag_key", "block_id", "project_id", "n").join(reps, "bag_key").drop("bag_key")
    return ordered.join(reps.select(F.col("rep").alias("block_id")), "block_id", "left_semi"), members


def expand_copies(pairs: DataFrame, members: DataFrame, theta_pm: int, measure: str, strict: bool) -> DataFrame:
    """Pairs of representatives to pairs of blocks; copies of one bag pair up among themselves."""
    m = members.select(F.col("rep"), F.col("block_id"), F.col("project_id"))
    left = pairs.join(m.select(F.col("rep").alias("b"), F.col("block_id").alias("x"), F.col("project_id").alias("p_x")), "b")
    both = left.join(m.select(F.col("rep").alias("c"), F.col("block_id").alias("y"), F.col("project_id").alias("p_y")), "c")
    swap = (F.col("n_b") == F.col("n_c")) & (F.col("x") > F.col("y"))
    across = both.select(
        F.when(swap, F.col("y")).otherwise(F.col("x")).alias("b"), F.when(swap, F.col("x")).otherwise(F.col("y")).alias("c"), "n_b", "n_c", "overlap", "similarity",
        F.when(swap, F.col("p_y")).otherwise(F.col("p_x")).alias("project_b"), F.when(swap, F.col("p_x")).otherwise(F.col("p_y")).alias("project_c"))
    u = members.select("rep", F.col("block_id").alias("b"), F.col("n").alias("n_b"), F.col("project_id").alias("project_b"))
    v = members.select(F.col("rep").alias("rep_c"), F.col("block_id").alias("c"), F.col("n").alias("n_c"), F.col("project_id").alias("project_c"))
    inside = u.join(v, (u["rep"] == v["rep_c"]) & (F.col("b") < F.col("c"))).withColumn("overlap", F.col("n_b"))
    inside = _accept_keep(inside, theta_pm, measure, strict)
    return across.unionByName(inside.select(*across.columns))


def _accept_keep(df: DataFrame, theta_pm: int, measure: str, strict: bool) -> DataFrame:
    kept = df.where(sim.meets(F.col("overlap"), F.col("n_b"), F.col("n_c"), theta_pm, measure, strict))
    return kept.withColumn("similarity", sim.similarity(F.col("overlap"), F.col("n_b"), F.col("n_c"), measure))


#: Sub-blocks hold so many elements less one more than a shared element needs, and candidates share as many: on prose a
#: twentieth of the candidates for a fortieth more of postings. 1 is the shortest sub-block.
MIN_SHARED = 4


def detect_representatives(ordered: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, min_shared: int = MIN_SHARED) -> tuple[DataFrame, DataFrame]:
    """(pairs of representatives (b, c, n_b, n_c, overlap, similarity), membership (rep, block_id, project_id, n)).

    Blocks with equal bags have one representative, the smallest id. Nothing is expanded: m copies are m rows, not
    m(m-1)/2 pairs; every pair of blocks follows from a pair of representatives or from a common one.
    """
    sim.check(theta_pm, measure)
    ordered = stage(ordered.where("n > 0"), "ordered")
    reps, members = collapse_copies(ordered)
    reps, members = stage(reps, "reps"), stage(members, "members")
    postings = partial_index(reps, theta_pm, measure, min_shared)
    found = candidates(postings, postings, theta_pm, measure, min_shared=min_shared)
    return verify_array(found, reps, reps, theta_pm, measure), members


def detect_ordered(
    ordered: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, locality: str = "any", strict: bool = False,
    filters: frozenset[str] = ALL, min_shared: int = MIN_SHARED, verifier: str = "array", collapse: bool = True, staged: bool = True, hot: int | None = HOT,
) -> DataFrame:
    """Clone pairs of ordered blocks: (b, c, n_b, n_c, overlap, similarity, project_b, project_c)."""
    sim.check(theta_pm, measure)
    if locality not in ("any", "intra", "inter"):
        raise ValueError("locality is any, intra or inter")
    ordered = ordered.where("n > 0")
    if staged:
        ordered = stage(ordered, "ordered")
    members = None
    reps = ordered.drop("keys")
    if collapse:
        reps, members = collapse_copies(ordered)
        if staged:
            reps, members = stage(reps, "reps"), stage(members, "members")
    within = locality == "intra" and not collapse
    postings = partial_index(reps, theta_pm, measure, min_shared) if "prefix" in filters else full_index(reps)
    found = candidates(postings, postings, theta_pm, measure, within=within, filters=filters, min_shared=min_shared if "prefix" in filters else 1, hot=hot)
    pairs = VERIFIERS[verifier](found, reps, reps, theta_pm, measure, strict)
    if collapse:
        out = expand_copies(pairs, members, theta_pm, measure, strict)
    else:
        of = reps.select("block_id", "project_id")
        out = pairs.join(of.select(F.col("block_id").alias("b"), F.col("project_id").alias("project_b")), "b").join(of.select(F.col("block_id").alias("c"), F.col("project_id").alias("project_c")), "c")
    if locality != "any":
        same = F.col("project_b").eqNullSafe(F.col("project_c"))
        out = out.where(same if locality == "intra" else ~same)
    return out.select(*PAIR, "project_b", "project_c")


def order_of(blocks: DataFrame, profile: str = "prose", order: str = "token_frequency") -> DataFrame:
    return orders.ordered_blocks(bag_of_tokens(tokenize(blocks, profile)), order)


def representatives(blocks: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, profile: str = "prose", strict: bool = False, min_shared: int | None = None, every: bool = False, early_accept: bool = False) -> tuple[DataFrame, DataFrame]:
    """As detect_representatives(), from blocks, in cells of sizes: bags are all that is shuffled.

    every: no index, all pairs are compared. early_accept: verification stops when a pair is decided; overlaps are lower bounds.
    """
    if every and early_accept:
        raise ValueError("early_accept is for the search by an index")
    found, members = cells.find(blocks, theta_pm, measure, profile=profile, strict=strict, shared=min_shared, every=every, early=early_accept)
    return found.withColumn("similarity", sim.similarity(F.col("overlap"), F.col("n_b"), F.col("n_c"), measure)).select(*PAIR), members


#: What detection in cells knows; other options (other orders, filters left out, no collapse) go the way of joins.
IN_CELLS = {"strict", "min_shared", "locality", "every", "early_accept"}


def detect_clones(blocks: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, order: str = "token_frequency", profile: str = "prose", **options) -> DataFrame:
    """The whole way from blocks (block_id, project_id, text) to clone pairs: a self-join of the repository."""
    if order == "token_frequency" and options.keys() <= IN_CELLS:
        locality = options.pop("locality", "any")
        if locality not in ("any", "intra", "inter"):
            raise ValueError("locality is any, intra or inter")
        pairs, members = representatives(blocks, theta_pm, measure, profile=profile, **options)
        out = expand_copies(pairs, members, theta_pm, measure, options.get("strict", False))
        same = F.col("project_b").eqNullSafe(F.col("project_c"))
        return (out if locality == "any" else out.where(same if locality == "intra" else ~same)).select(*PAIR, "project_b", "project_c")
    return detect_ordered(order_of(blocks, profile, order), theta_pm, measure, **options)


def detect_within(blocks: DataFrame, **options) -> DataFrame:
    return detect_clones(blocks, locality="intra", **options)


def detect_across(blocks: DataFrame, **options) -> DataFrame:
    return detect_clones(blocks, locality="inter", **options)


def detect_between(left: DataFrame, right: DataFrame, theta_pm: int = 700, measure: str = "overlap", *, order: str = "token_frequency", profile: str = "prose", strict: bool = False) -> DataFrame:
    """Pairs of a block of one repository (b) and one of another (c); the order is that of both together."""
    sim.check(theta_pm, measure)
    bags = [bag_of_tokens(tokenize(x, profile)) for x in (left, right)]
    both = bags[0].unionByName(bags[1])
    known = orders.element_frequency(both) if order == "element_frequency" else orders.global_token_frequency(both)
    known = stage(known, "frequencies")
    x, y = (stage(orders.ordered_blocks(b, order, known), "ordered") for b in bags)
    found = candidates(partial_index(x, theta_pm, measure), partial_index(y, theta_pm, measure), theta_pm, measure, between=True)
    return verify_array(found, x, y, theta_pm, measure, strict)


def detect_partitioned(blocks: DataFrame, parts: int = 4, theta_pm: int = 700, measure: str = "overlap", *, profile: str = "prose") -> DataFrame:
    """Every pair of parts by itself, k(k+1)/2 small joins: the way to scale a tool that cannot. Each part is one restart unit."""
    ordered = stage(order_of(blocks, profile).withColumn("part", F.pmod(F.xxhash64("block_id"), F.lit(parts)).cast("int")), "parts", partition_by=["part"])
    out = None
    for i in range(parts):
        one = ordered.where(F.col("part") == i).drop("part")
        for j in range(i, parts):
            two = ordered.where(F.col("part") == j).drop("part")
            found = candidates(partial_index(one, theta_pm, measure), partial_index(two, theta_pm, measure), theta_pm, measure, between=i != j)
            pairs = verify_array(found, one, two, theta_pm, measure)
            turn = ~_after(F.col("n_b"), F.col("b"), F.col("n_c"), F.col("c"))
            pairs = pairs.select(
                F.when(turn, F.col("c")).otherwise(F.col("b")).alias("b"), F.when(turn, F.col("b")).otherwise(F.col("c")).alias("c"),
                F.when(turn, F.col("n_c")).otherwise(F.col("n_b")).alias("n_b"), F.when(turn, F.col("n_b")).otherwise(F.col("n_c")).alias("n_c"), "overlap", "similarity")
            out = pairs if out is None else out.unionByName(pairs)
    return out
