"""Clone types and bands of a pair of blocks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.order import MARK
from ..functions.tokens import normalize_t1, normalize_t2, normalized_lines, token_array
from ..sources.io import stage

BANDS = ("T1", "T2", "VST3", "ST3", "MT3", "WT3/T4")


def numbered(lists: DataFrame, column: str) -> DataFrame:
    """(block_id, column): a list column as a set of numbered occurrences, counted by a shuffle and not within the row."""
    bag = lists.select("block_id", F.explode(column).alias("x")).groupBy("block_id", "x").agg(F.count("*").cast("int").alias("f"))
    each = F.transform(F.sequence(F.lit(1), F.col("f")), lambda k: F.concat("x", F.lit(MARK), k.cast("string")))
    return bag.groupBy("block_id").agg(F.flatten(F.collect_list(each)).alias(column))


def share_pm(a: Column, b: Column) -> Column:
    """Multiset overlap of two numbered lists over the longer, per mille; two empty lists are equal."""
    longer = F.greatest(F.size(a), F.size(b))
    return F.when(longer == 0, 1000).otherwise((F.size(F.array_intersect(a, b)) * 1000 / longer).cast("int"))


def classify(pairs: DataFrame, blocks: DataFrame, profile: str = "prose") -> DataFrame:
    """Pairs (b, c) with line_pm, token_pm, sim_pm (the smaller) and clone_type.

    T1: equal texts but for layout and comments. T2: equal after normalisation of names and literals. T3 bands
    by the smaller similarity of lines and of tokens after normalisation; likeness of 1000 without equality
    (reordered lines) counts as the highest band.
    """
    named = pairs.select(F.explode(F.array("b", "c")).alias("block_id")).distinct()
    wanted = blocks.join(named, "block_id", "left_semi").select("block_id", "text")
    t2 = normalize_t2(F.col("text"), profile)
    made = wanted.select("block_id", F.sha2(normalize_t1(F.col("text"), profile), 256).alias("t1"), F.sha2(t2, 256).alias("t2"))
    made = made.join(numbered(wanted.select("block_id", normalized_lines(F.col("text"), profile).alias("lines")), "lines"), "block_id", "left")
    made = made.join(numbered(wanted.select("block_id", token_array(t2).alias("tokens")), "tokens"), "block_id", "left")
    none = F.array().cast("array<string>")
    made = stage(made.withColumns({"lines": F.coalesce("lines", none), "tokens": F.coalesce("tokens", none)}), "normalised")
    side = lambda s: made.select(F.col("block_id").alias(s), *(F.col(c).alias(f"{c}_{s}") for c in ("t1", "t2", "lines", "tokens")))
    both = pairs.join(side("b"), "b").join(side("c"), "c")
    both = both.withColumns({"line_pm": share_pm(F.col("lines_b"), F.col("lines_c")), "token_pm": share_pm(F.col("tokens_b"), F.col("tokens_c"))})
    sim = F.least("line_pm", "token_pm")
    kind = F.when(F.col("t1_b") == F.col("t1_c"), "T1").when(F.col("t2_b") == F.col("t2_c"), "T2").when(sim >= 900, "VST3").when(sim >= 700, "ST3").when(sim >= 500, "MT3").otherwise("WT3/T4")
    return both.select(*pairs.columns, "line_pm", "token_pm", sim.alias("sim_pm"), kind.alias("clone_type"))


def locality(project_b: Column, project_c: Column) -> Column:
    return F.when(project_b.eqNullSafe(project_c), "intra").otherwise("inter")
