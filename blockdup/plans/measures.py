"""Cost and accuracy measures."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.detect import candidates
from ..operators.index import partial_index


def comparisons_by_project(ordered: DataFrame, theta_pm: int = 700) -> DataFrame:
    """Within each project: blocks, x(x-1)/2, candidates of the sub-block filter, and of both filters."""
    postings = partial_index(ordered, theta_pm)
    of = ordered.select(F.col("block_id").alias("b"), "project_id")
    count = lambda filters, name: candidates(postings, postings, theta_pm, within=True, filters=frozenset(filters)).join(of, "b").groupBy("project_id").agg(F.count("*").alias(name))
    blocks = ordered.groupBy("project_id").agg(F.count("*").alias("blocks")).withColumn("quadratic", (F.col("blocks") * (F.col("blocks") - 1) / 2).cast("long"))
    out = blocks.join(count({"prefix", "size"}, "f1"), "project_id", "left").join(count({"prefix", "size", "position"}, "f1f3"), "project_id", "left")
    return out.fillna(0, ["f1", "f1f3"])


def growth_slope(points: DataFrame, x: str, y: str) -> DataFrame:
    """Slope of log y over log x: the power with which a cost grows."""
    return points.where((F.col(x) > 0) & (F.col(y) > 0)).agg(F.regr_slope(F.log(y), F.log(x)).alias("slope"))


def index_ratio(ordered: DataFrame, theta_pm: int = 700) -> DataFrame:
    """Postings of the partial and of the full index."""
    return ordered.agg(F.sum(F.size("elements")).cast("long").alias("full")).crossJoin(partial_index(ordered, theta_pm).agg(F.count("*").alias("partial")))


def coverage(pairs: DataFrame, blocks: DataFrame) -> DataFrame:
    """Blocks, and those in at least one pair."""
    named = pairs.select(F.explode(F.array("b", "c")).alias("block_id")).distinct()
    return blocks.select("block_id").join(named.withColumn("in_pair", F.lit(1)), "block_id", "left").agg(F.count("*").alias("blocks"), F.coalesce(F.sum("in_pair"), F.lit(0)).cast("long").alias("covered"))


def false_candidates(found: DataFrame, pairs: DataFrame) -> DataFrame:
    """Candidates that are no clones, by query block."""
    return found.join(pairs.select("b", "c"), ["b", "c"], "left_anti").groupBy("b").agg(F.count("*").alias("false_candidates"))


def sample_size(reports: int | None = None, z: float = 1.96, half_width: float = 0.05) -> int:
    """Judged reports needed for a proportion, at worst one half; with the finite correction if their number is given."""
    n = z * z * 0.25 / half_width**2
    return math.ceil(n if reports is None else n / (1 + (n - 1) / reports))


def sample_sizes(reports: Column, z: float = 1.96, half_width: float = 0.05) -> Column:
    """sample_size() of each row's number of reports."""
    n = round(z * z * 0.25 / half_width**2, 9)
    return F.ceil(F.lit(n) / (1 + F.lit(round(n - 1, 9)) / reports)).cast("int")


def interval(hits: int, n: int, z: float = 1.96) -> dict[str, float]:
    """Share with its Wald and Wilson intervals."""
    p = hits / n
    wald = z * math.sqrt(p * (1 - p) / n)
    centre, spread = (p + z * z / (2 * n)) / (1 + z * z / n), z / (1 + z * z / n) * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n))
    return {"p": p, "wald_low": p - wald, "wald_high": p + wald, "wilson_low": centre - spread, "wilson_high": centre + spread}


def judged_sample(pairs: DataFrame, n: int = 390, judges: int = 3) -> DataFrame:
    """A fixed pseudo-random sample of reports, split among judges."""
    key = F.md5(F.concat_ws("-", "b", "c"))
    return pairs.select("b", "c", key.alias("k")).orderBy("k").limit(n).select("b", "c", F.pmod(F.conv(F.substring("k", 1, 4), 16, 10).cast("int"), F.lit(judges)).alias("judge"))


def nested_samples(blocks: DataFrame, shares: tuple[int, ...] = (1, 10, 100, 1000)) -> DataFrame:
    """(share_pm, block_id): samples by hash of the id; larger ones hold smaller ones."""
    bound = F.conv(F.substring(F.md5(F.col("block_id").cast("string")), 1, 8), 16, 10).cast("long")
    return blocks.select("block_id", F.explode(F.array(*(F.lit(s) for s in shares))).alias("share_pm"), bound.alias("h")).where(F.col("h") * 1000 < F.col("share_pm") * 4294967296).select("share_pm", "block_id")


def detected(references: DataFrame, reports: DataFrame, cover_pm: int = 700) -> DataFrame:
    """References with `detected`: some report covers that share of the lines of both fragments and the edited lines.

    references: ref_id, file_1, start_1, end_1, file_2, start_2, end_2, edit_start, edit_end (in file 2);
    reports: file_1, start_1, end_1, file_2, start_2, end_2, in either order.
    """
    flip = reports.select(*(F.col(f"{a}_{2 if s == 1 else 1}").alias(f"{a}_{s}") for s in (1, 2) for a in ("file", "start", "end")))
    r = reports.select(*flip.columns).unionByName(flip).distinct().toDF(*(f"r_{c}" for c in flip.columns))
    shared = lambda s: F.greatest(F.lit(0), F.least(f"end_{s}", f"r_end_{s}") - F.greatest(f"start_{s}", f"r_start_{s}") + 1)
    enough = lambda s: shared(s) * 1000 >= (F.col(f"end_{s}") - F.col(f"start_{s}") + 1) * cover_pm
    on = (F.col("file_1") == F.col("r_file_1")) & (F.col("file_2") == F.col("r_file_2")) & enough(1) & enough(2) & (F.col("r_start_2") <= F.col("edit_start")) & (F.col("r_end_2") >= F.col("edit_end"))
    hit = references.join(r, on, "left_semi").select("ref_id").distinct().withColumn("hit", F.lit(True))
    return references.join(hit, "ref_id", "left").withColumn("detected", F.coalesce("hit", F.lit(False))).drop("hit")


def recall(found: DataFrame, *by: str) -> DataFrame:
    """Detected over all references for each group and each roll-up of them."""
    return found.rollup(*by).agg(F.count("*").alias("references"), F.sum(F.col("detected").cast("long")).alias("found")).withColumn("recall", F.col("found") / F.col("references"))
