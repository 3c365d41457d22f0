"""The partial index: postings of the rarest elements of each block, in memory or on disk, and look-ups in it."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import similarity as sim
from ..sources.io import freed, setting, stage, unstage
from . import subblocks

#: Elements asked for at once that are pushed down to the files.
FEW = 1_000
#: Rows of a batch sent to Python: whole texts or blocks, of which many are large.
BATCH = ("spark.sql.execution.arrow.maxRecordsPerBatch", "1000")
POSTINGS = ("element", "block_id", "project_id", "pos", "n")


def partial_index(ordered: DataFrame, theta_pm: int = 700, measure: str = "overlap", min_shared: int = 1) -> DataFrame:
    """(element, block_id, project_id, pos, n): the sub-block of each block, positions from 1."""
    sub = F.slice("elements", F.lit(1), sim.prefix_length(F.col("n"), theta_pm, measure, min_shared))
    return ordered.where("n > 0").select("block_id", "project_id", "n", F.posexplode(sub).alias("at", "element")).select("element", "block_id", "project_id", (F.col("at") + 1).alias("pos"), "n")


def full_index(ordered: DataFrame) -> DataFrame:
    """Postings of all elements, the usual inverted index."""
    return ordered.select("block_id", "project_id", "n", F.posexplode("elements").alias("at", "element")).select("element", "block_id", "project_id", (F.col("at") + 1).alias("pos"), "n")


@dataclass(frozen=True)
class Manifest:
    """What an index was built with; a look-up must agree with it."""

    theta_pm: int
    measure: str
    order: str
    min_shared: int
    profile: str
    buckets: int


class IndexedRepository:
    """A stored index: postings by bucket of element, ordered blocks by bucket of block, frozen frequencies. A look-up reads only the buckets its elements and candidates fall into."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path
        text = spark.read.text(f"{path}/manifest").first()
        self.manifest = Manifest(**json.loads(text[0]))

    def _read(self, name: str, buckets: list[int] | None = None) -> DataFrame:
        """A part of the index; `buckets` are a partition filter, so folders of other buckets are not listed as input."""
        df = self.spark.read.parquet(f"{self.path}/{name}")
        return df if buckets is None else df.where(F.col("bucket").isin(buckets))

    def _buckets(self, ids: DataFrame, id: str) -> list[int]:
        """Buckets that some id falls into: as many at most as the index has, a fixed number."""
        return sorted(r[0] for r in ids.select(F.pmod(F.xxhash64(id), F.lit(self.manifest.buckets)).cast("int")).distinct().collect())

    @property
    def postings(self) -> DataFrame:
        return self._read("postings")

    @property
    def blocks(self) -> DataFrame:
        return self._read("blocks")

    @property
    def frequencies(self) -> DataFrame:
        return self._read("frequencies")

    @staticmethod
    def build(blocks: DataFrame, path: str, theta_pm: int = 700, measure: str = "overlap", order: str = "token_frequency", min_shared: int = 1, profile: str = "prose", buckets: int = 16) -> IndexedRepository:
        sim.check(theta_pm, measure)
        if order != "token_frequency":
            raise ValueError("a stored index keeps token frequencies; other orders are for runs in memory")
        spark = blocks.sparkSession
        with freed(spark), setting(spark, *BATCH):
            subblocks.token_frequencies(blocks, profile).write.mode("overwrite").parquet(f"{path}/frequencies")
        made = Manifest(theta_pm, measure, order, min_shared, profile, buckets)
        spark.createDataFrame([(json.dumps(asdict(made)),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")
        repo = IndexedRepository(spark, path)
        repo._add(repo._order(blocks), "overwrite")
        return repo

    def _add(self, ordered: DataFrame, mode: str) -> None:
        m = self.manifest
        by_block = ordered.withColumn("bucket", F.pmod(F.xxhash64("block_id"), F.lit(m.buckets)).cast("int"))
        with freed(self.spark), setting(self.spark, *BATCH):
            by_block.repartition(m.buckets, "bucket").write.mode(mode).partitionBy("bucket").parquet(f"{self.path}/blocks")
            if mode == "overwrite":  # what was written is all that is there
                unstage(ordered)
                ordered = self.spark.read.schema(ordered.schema).parquet(f"{self.path}/blocks").drop("bucket")
            postings = partial_index(ordered, m.theta_pm, m.measure, m.min_shared).withColumn("bucket", F.pmod(F.xxhash64("element"), F.lit(m.buckets)).cast("int"))
            postings.repartition(m.buckets, "bucket").sortWithinPartitions("element").write.mode(mode).partitionBy("bucket").parquet(f"{self.path}/postings")
        unstage(ordered)

    def _order(self, blocks: DataFrame) -> DataFrame:
        with setting(self.spark, *BATCH):
            return subblocks.ordered(blocks, self.frequencies, self.manifest.profile)

    def append(self, blocks: DataFrame) -> None:
        """Add blocks under the frozen order; it stays correct, only less sharp as the corpus drifts."""
        self._add(self._order(blocks), "append")

    def query(self, blocks: DataFrame, theta_pm: int | None = None) -> DataFrame:
        """Indexed blocks that match the given ones: (query_id, block_id, n_query, n_block, overlap, similarity).

        Up to FEW elements are looked up in the postings; blocks with more meet the indexed ones in cells of sizes.
        """
        from .detect import _accept, candidates, verify_array

        m = self.manifest
        theta = m.theta_pm if theta_pm is None else theta_pm
        if theta < m.theta_pm:
            raise ValueError(f"the index was built for {m.theta_pm} per mille and cannot answer a lower threshold")
        inorder = self._order(blocks)
        asked = stage(inorder, "asked")
        unstage(inorder)
        probes = stage(partial_index(asked, theta, m.measure, m.min_shared), "probes")
        some = probes.select("element").distinct().limit(FEW + 1).collect()
        if len(some) > FEW:
            out = stage(_accept(subblocks.matches(asked, self.blocks, self.frequencies, theta, m.measure), theta, m.measure, False), "matches")
            unstage(asked, probes)
            return _answers(out)
        # an interactive look-up: the files' statistics leave out most of each bucket too
        postings = self._read("postings", self._buckets(probes, "element")).where(F.col("element").isin([r.element for r in some]))
        found = stage(candidates(probes, postings, theta, m.measure, between=True, min_shared=m.min_shared, hot=None), "found")
        held = self._read("blocks", self._buckets(found, "c")).drop("bucket")
        return _answers(verify_array(found, asked, held, theta, m.measure))


def _answers(out: DataFrame) -> DataFrame:
    return out.select(F.col("b").alias("query_id"), F.col("c").alias("block_id"), F.col("n_b").alias("n_query"), F.col("n_c").alias("n_block"), "overlap", "similarity")
