"""Grouping of pairs: stars, connected components, strict classes, and statistics of classes."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.io import stage, unstage


def _all_stars(edges: DataFrame) -> bool:
    """Whether every v has one u, and no u is a v of another edge."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("v").alias("node"), F.lit(1).alias("leaf"), F.lit(0).alias("centre")), F.struct(F.col("u").alias("node"), F.lit(0).alias("leaf"), F.lit(1).alias("centre")))).alias("e")).select("e.*")
    return not ends.groupBy("node").agg(F.sum("leaf").alias("leaf"), F.max("centre").alias("centre")).where("leaf + centre > 1").limit(1).count()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) for every node with an edge; root is the smallest node of its component.

    `edges` has two columns of one orderable type. Alternating stars: first every node tells its larger
    neighbours its smallest one, then every node links its smaller neighbours and itself to the smallest.
    Edges only shrink; each round is a written table. The smallest neighbours are aggregated map-side and written
    too, so that what they are joined with comes straight from an exchange and the edges of a hub can be split.
    """
    x, y = edges.columns
    now = edges.select(F.greatest(x, y).alias("v"), F.least(x, y).alias("u")).where("v is not null and u is not null and v <> u").distinct()
    now = stage(now, "edges")
    for _ in range(max_rounds):
        if _all_stars(now):
            break
        both = now.select(F.col("v").alias("a"), F.col("u").alias("b")).unionByName(now.select(F.col("u").alias("a"), F.col("v").alias("b")))
        low = stage(both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m")), "low")
        large = stage(now.select(F.col("u").alias("a"), "v").join(low, "a").select("v", F.col("m").alias("u")).distinct(), "large")
        least = stage(large.groupBy("v").agg(F.min("u").alias("m")), "least")
        small = large.join(least, "v").select(F.explode(F.array(F.struct(F.col("v").alias("v"), F.col("m").alias("u")), F.struct(F.col("u").alias("v"), F.col("m").alias("u")))).alias("e")).select("e.v", "e.u").where("v <> u").distinct()
        last, now = now, stage(small, "edges")
        unstage(last, low, large, least)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    leaves = now.select(F.col("v").alias("node"), F.col("u").alias("root"))
    return leaves.unionByName(leaves.select(F.col("root").alias("node"), "root").distinct())


def clone_map(pairs: DataFrame) -> DataFrame:
    """(block_id, clones): for each block all its clones, in both directions, sorted."""
    both = pairs.select(F.col("b").alias("block_id"), F.col("c").alias("other")).unionByName(pairs.select(F.col("c").alias("block_id"), F.col("b").alias("other")))
    return both.groupBy("block_id").agg(F.sort_array(F.collect_set("other")).alias("clones"))


def clone_components(pairs: DataFrame) -> DataFrame:
    """(class_id, block_id): transitive closure of the pairs; class_id is the smallest block."""
    return connected_components(pairs.select("b", "c")).select(F.col("root").alias("class_id"), F.col("node").alias("block_id"))


def components_of(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """(class_id, block_id) from pairs of representatives and their membership, without a pair of copies being formed."""
    roots = connected_components(pairs.select("b", "c")).withColumnRenamed("node", "rep")
    placed = members.select("rep", "block_id").join(roots, "rep", "left").withColumn("root", F.coalesce("root", "rep"))
    several = placed.groupBy("root").agg(F.count("*").alias("m"), F.min("block_id").alias("class_id")).where("m > 1")
    return placed.join(several, "root").select("class_id", "block_id")


def _greedy(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Strict classes of components whose links come ordered by (component, high, low).

    A block may join a class if as many of its lower neighbours are in it as it has members. What is kept is the
    class of each block of one component and the sizes of its classes; links are read once and not kept.
    """
    component = block = None
    home: dict[int, int] = {}
    sizes: dict[int, int] = {}
    met: dict[int, int] = {}

    def place(x: int) -> tuple[int, int]:
        of = min((g for g, n in met.items() if sizes[g] == n), default=x)
        home[x], sizes[of] = of, sizes.get(of, 0) + 1
        met.clear()
        return of, x

    for batch in batches:
        made = []
        for of, high, low in zip(batch["component"].tolist(), batch["high"].tolist(), batch["low"].tolist(), strict=True):
            if (of, high) != (component, block):
                if met:
                    made.append(place(block))
                if of != component:
                    home.clear()
                    sizes.clear()
                component, block = of, high
            if low not in home:  # no lower neighbour: the first of a class
                home[low], sizes[low] = low, 1
                made.append((low, low))
            met[home[low]] = met.get(home[low], 0) + 1
        yield pd.DataFrame(made, columns=["class_id", "block_id"])
    if met:
        yield pd.DataFrame([place(block)], columns=["class_id", "block_id"])


def clone_classes(pairs: DataFrame) -> DataFrame:
    """(class_id, block_id, is_complete): classes in which every two blocks are a pair.

    A component with all its m(m-1)/2 pairs is a class as it stands. Others are split greedily from the
    lowest block on, each block joining the first class all of whose members it matches. That choice depends on
    all before it, so one component is one task; its links are sorted (and spilled) by the shuffle and read as a
    stream, so the task's memory grows with the blocks of one component and not with their links, at any size.
    """
    links = stage(pairs.where("b <> c").select(F.least("b", "c").cast("long").alias("low"), F.greatest("b", "c").cast("long").alias("high")).distinct(), "links")
    comp = stage(connected_components(links).select(F.col("root").alias("component"), F.col("node").alias("block_id")), "components")
    sizes = comp.groupBy("component").agg(F.count("*").alias("m"))
    placed = links.join(comp.withColumnRenamed("block_id", "low"), "low")
    full = stage(placed.groupBy("component").agg(F.count("*").alias("links")).join(sizes, "component").select("component", (F.col("links") * 2 == F.col("m") * (F.col("m") - 1)).alias("is_complete")), "complete")
    whole = comp.join(full.where("is_complete"), "component").select(F.col("component").alias("class_id"), "block_id", "is_complete")
    rest = placed.join(full.where("not is_complete").select("component"), "component", "left_semi").select("component", "high", "low")
    parts = rest.repartition("component").sortWithinPartitions("component", "high", "low").mapInPandas(_greedy, "class_id long, block_id long")
    return whole.unionByName(parts.withColumn("is_complete", F.lit(False)))


def class_stats(classes: DataFrame, blocks: DataFrame) -> DataFrame:
    """(class_id, size, projects): how large classes are and over how many projects they spread."""
    return classes.join(blocks.select("block_id", "project_id"), "block_id").groupBy("class_id").agg(F.count("*").alias("size"), F.count_distinct("project_id").alias("projects"))
