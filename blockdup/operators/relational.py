"""Relational operators around the detector that Spark has no single function for."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.tokens import bag_map, bag_of_tokens, tokenize
from ..sources.io import stage
from .groups import connected_components

#: Ids that are told to the readers of texts at most; with more of them texts are joined.
TOLD = 1_000_000
#: Bags of one side of a tile.
TILE = 2_000


def asof_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """Each left row with the value of the latest right row of its key at or before it: one union, one window."""
    a = left.select(*left.columns, F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    b = right.select(*(F.col(c) if c in (key, at) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns), F.col(value).alias("_v"), F.lit(0).alias("_side"))
    w = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(f"asof_{value}", F.last("_v", ignorenulls=True).over(w)).where("_side = 1").drop("_v", "_side")


def interval_join(left: DataFrame, right: DataFrame, key: str, at: str, seconds: int) -> DataFrame:
    """Pairs (l, r) of one key whose times differ by at most so many seconds: an equi-join on key and time cell."""
    cell = lambda c: F.floor(F.unix_timestamp(c) / seconds)
    a = left.select(*(F.col(c).alias(f"l_{c}") for c in left.columns)).withColumn("cell", F.explode(F.sequence(cell(F.col(f"l_{at}")) - 1, cell(F.col(f"l_{at}")) + 1)))
    b = right.select(*(F.col(c).alias(f"r_{c}") for c in right.columns)).withColumn("cell_r", cell(F.col(f"r_{at}")))
    gap = F.abs(F.unix_timestamp(f"l_{at}") - F.unix_timestamp(f"r_{at}"))
    return a.join(b, (F.col(f"l_{key}") == F.col(f"r_{key}")) & (F.col("cell") == F.col("cell_r")) & (gap <= seconds)).drop("cell", "cell_r")


def size_band_join(sizes: DataFrame, theta_pm: int) -> DataFrame:
    """Pairs of blocks whose sizes allow a match: logarithmic cells make the range an equi-join on two cells."""
    step = F.log(F.lit(1000 / theta_pm))
    cell = F.floor(F.log("n") / step).cast("int")
    b = sizes.select(F.col("block_id").alias("b"), F.col("n").alias("n_b"), F.explode(F.array(cell, cell - 1, cell - 2)).alias("cell"))
    c = sizes.select(F.col("block_id").alias("c"), F.col("n").alias("n_c"), cell.alias("cell_c"))
    turn = (F.col("n_b") > F.col("n_c")) | ((F.col("n_b") == F.col("n_c")) & (F.col("b") < F.col("c")))
    return b.join(c, (F.col("cell") == F.col("cell_c")) & turn & (F.col("n_c").cast("long") * 1000 >= F.col("n_b").cast("long") * theta_pm)).select("b", "c", "n_b", "n_c")


def size_band_counts(sizes: DataFrame, theta_pm: int) -> DataFrame:
    """(block_id, n, partners): how many other blocks have a size that allows a match; pairs are counted by size, not formed."""
    many = sizes.groupBy("n").agg(F.count("*").alias("blocks"))
    step = F.log(F.lit(1000 / theta_pm))
    cell = F.floor(F.log("n") / step).cast("int")
    x = many.select(F.col("n").alias("n"), F.explode(F.array(*(cell + k for k in range(-2, 3)))).alias("cell"))
    y = many.select(F.col("n").alias("m"), F.col("blocks"), cell.alias("cell_m"))
    fits = F.least("n", "m").cast("long") * 1000 >= F.greatest("n", "m").cast("long") * theta_pm
    total = x.join(y, (F.col("cell") == F.col("cell_m")) & fits).groupBy("n").agg((F.sum("blocks") - 1).alias("partners"))
    return sizes.join(total, "n").select("block_id", "n", "partners")


def best_match(pairs: DataFrame) -> DataFrame:
    """For each block its most similar partner, ties to the smaller id."""
    both = pairs.select(F.col("b").alias("block_id"), F.col("c").alias("partner"), "similarity").unionByName(pairs.select(F.col("c").alias("block_id"), F.col("b").alias("partner"), "similarity"))
    w = Window.partitionBy("block_id").orderBy(F.desc("similarity"), "partner")
    return both.withColumn("r", F.row_number().over(w)).where("r = 1").drop("r")


def without_items(docs: DataFrame, items: DataFrame, id: str = "doc_id", text: str = "text", item: str = "text", words: int = 8) -> DataFrame:
    """Ids of documents that contain no item word for word.

    A document that contains an item contains the item's inner words in a row (its first and last word may be cut
    from longer ones). Runs of `words` of these are joined by hash, and only documents that share an item's first
    run are compared with it letter by letter. Items with fewer inner words are compared by their rarest way
    left: their longest inner word, or every document if they have none. Null items are in no document; null
    documents hold no item.
    """
    pattern = F.lit(r"([\p{L}\p{N}_]+)")
    d = docs.select(F.col(id).alias("doc"), F.col(text).alias("body"))
    known = items.select(F.col(item).alias("item")).where("item is not null").distinct()
    known = known.withColumn("w", F.regexp_extract_all("item", pattern, F.lit(1))).withColumn("inner", F.slice("w", 2, F.greatest(F.size("w") - 2, F.lit(0))))
    run = lambda w, at, n: F.xxhash64(F.array_join(F.slice(w, at, n), " "))
    long = known.where(F.size("inner") >= words).select("item", run("inner", F.lit(1), words).alias("key"))
    longest = F.element_at(F.array_sort(F.transform("inner", lambda x: F.struct(-F.length(x), x.alias("x")))), 1)["x"]
    short = known.where((F.size("inner") < words) & (F.size("inner") > 0)).select("item", F.xxhash64(longest).alias("key"))
    bare = known.where(F.size("inner") == 0).select("item")
    tokens = d.select("doc", F.regexp_extract_all("body", pattern, F.lit(1)).alias("w"))
    # all items have the same kinds of key, so only documents' keys that some item has are kept, before any text moves
    runs = tokens.where(F.size("w") >= words).select("doc", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - words + 1), lambda k: run("w", k, words)))).alias("key"))
    single = tokens.select("doc", F.explode(F.array_distinct(F.transform("w", lambda x: F.xxhash64(x)))).alias("key"))
    pairs = runs.join(long, "key").select("doc", "item").unionByName(single.join(short, "key").select("doc", "item")).distinct()
    hit = pairs.join(d, "doc").where(F.contains("body", "item")).select("doc")
    if bare.limit(1).count():  # signs and single words: nothing to join on
        hit = hit.unionByName(d.join(bare, F.contains(F.col("body"), F.col("item"))).select("doc"))
    return d.select("doc").join(hit.distinct(), "doc", "left_anti").select(F.col("doc").alias(id))


def with_ids(blocks: DataFrame, ids: DataFrame) -> DataFrame:
    """Blocks whose block_id is among `ids` (block_id, no id twice); up to TOLD ids are told to the readers, and no text is shuffled."""
    told = [r[0] for r in ids.select("block_id").limit(TOLD + 1).collect()]
    if len(told) > TOLD:
        return blocks.join(ids.select("block_id"), "block_id", "left_semi")
    wanted = np.array(sorted(told), np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(np.isin(batch.column("block_id").to_numpy(zero_copy_only=False), wanted)))

    named = blocks.where("block_id is not null")
    return named.mapInArrow(run, named.schema)


def overlaps_of_maps(blocks: DataFrame, pairs: DataFrame, tile: int = TILE) -> DataFrame:
    """`pairs` with their overlap counted from bags held as maps.

    A bag goes once to each tile of its component and not once for each pair; a tile has about `tile` bags on a side,
    so what a task holds does not grow with the component.
    """
    classes = stage(connected_components(pairs.select("b", "c")).select("root", F.col("node").alias("block_id")), "classes")
    parts = classes.groupBy("root").agg(F.ceil(F.count("*") / tile).cast("int").alias("parts"))
    placed = stage(classes.join(parts, "root").withColumn("part", F.pmod(F.xxhash64("block_id"), F.col("parts")).cast("int")), "placed")
    bags = bag_map(bag_of_tokens(tokenize(with_ids(blocks, placed)))).select("block_id", "bag").join(placed, "block_id")
    every = F.explode(F.sequence(F.lit(0), F.col("parts") - 1))
    across = bags.withColumn("other", every)
    sent = across.select("root", F.col("part").alias("i"), F.col("other").alias("j"), "block_id", "bag").unionByName(
        across.where("part <> other").select("root", F.col("other").alias("i"), F.col("part").alias("j"), "block_id", "bag"))
    side = lambda x, i: placed.select(F.col("block_id").alias(x), *([F.col("root").alias("root_of")] if x == "b" else []), F.col("part").alias(i))
    asked = pairs.join(side("b", "i"), "b").join(side("c", "j"), "c").select("root_of", "i", "j", *pairs.columns)

    columns = pairs.columns

    def run(asked: pd.DataFrame, sent: pd.DataFrame) -> pd.DataFrame:
        bag = {k: dict(x) for k, x in zip(sent["block_id"], sent["bag"], strict=True)}
        made = []
        for b, c in zip(asked["b"], asked["c"], strict=True):
            x, y = bag[b], bag[c]
            made.append(sum(min(x[t], y[t]) for t in x.keys() & y.keys()))
        return asked[columns].assign(overlap=made)

    return asked.groupBy("root_of", "i", "j").cogroup(sent.groupBy("root", "i", "j")).applyInPandas(run, pairs.schema)
