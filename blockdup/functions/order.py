"""Global orders of elements. Any fixed total order is correct; it only decides how many candidates there are.

The order is a sort key inside a struct (key, token, k); no dense rank over the vocabulary is ever computed,
since that would be a window without partitions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ORDERS = ("token_frequency", "element_frequency", "alphabetical", "length", "popular_first")
#: Separates a token from its occurrence number in an element; no token pattern lets it through.
MARK = "\u0001"


def global_token_frequency(bag: DataFrame) -> DataFrame:
    """(token, gf, df): occurrences and blocks of each token over the corpus."""
    return bag.groupBy("token").agg(F.sum("freq").cast("long").alias("gf"), F.count("*").cast("long").alias("df"))


def element_frequency(bag: DataFrame) -> DataFrame:
    """(token, k, gf): in how many blocks the token occurs at least k times."""
    return bag.select("token", F.explode(F.sequence(F.lit(1), F.col("freq"))).alias("k")).groupBy("token", "k").agg(F.count("*").cast("long").alias("gf"))


def _gather(keyed: DataFrame, expand: bool, keys: bool) -> DataFrame:
    """Rows (block, key, token, freq or k) to one row a block, its elements in the order of (key, token, k)."""
    # names are made before rows are gathered and sorting needs no lambda: both stay in generated code
    first = F.concat("token", F.lit(f"{MARK}1"))
    if expand:  # k holds the frequency: occurrences of a token stand next to each other
        every = F.transform(F.sequence(F.lit(1), F.col("k")), lambda k: F.concat("token", F.lit(MARK), k.cast("string")))
        named = keyed.withColumn("names", F.when(F.col("k") == 1, F.array(first)).otherwise(every))
    else:
        named = keyed.withColumn("names", F.array(F.concat("token", F.lit(MARK), F.col("k").cast("string"))))
    rows = named.groupBy("block_id", "project_id").agg(F.sort_array(F.collect_list(F.struct("key", "token", "k", "names"))).alias("sorted"))
    made = F.flatten(F.col("sorted.names"))
    more = [F.flatten(F.transform("sorted", lambda s: F.array_repeat(s["key"].cast("long"), s["k"] if expand else F.lit(1)))).alias("keys")] if keys else []
    return rows.select("block_id", "project_id", made.alias("elements"), *more).select("block_id", "project_id", F.size("elements").alias("n"), "elements", *(["keys"] if keys else []))


def ordered_blocks(bag: DataFrame, order: str = "token_frequency", frequencies: DataFrame | None = None, keys: bool = False) -> DataFrame:
    """(block_id, project_id, n, elements[, keys]) sorted by a global order; keys: what elements are sorted by before token and occurrence.

    `frequencies` is a frozen (token, gf) table, e.g. that of a stored index; tokens it does not know take 0,
    which puts them first, in every block alike.
    """
    if order not in ORDERS:
        raise ValueError(f"order is one of {ORDERS}")
    if order == "element_frequency":
        known = element_frequency(bag) if frequencies is None else frequencies
        spread = bag.select("block_id", "project_id", "token", F.explode(F.sequence(F.lit(1), F.col("freq"))).alias("k"))
        return _gather(spread.join(known, ["token", "k"], "left").withColumn("key", F.coalesce("gf", F.lit(0))), False, keys)
    named = bag.withColumnRenamed("freq", "k")
    if order in ("token_frequency", "popular_first"):
        known = global_token_frequency(bag) if frequencies is None else frequencies
        key = F.coalesce("gf", F.lit(0)) * (1 if order == "token_frequency" else -1)
        keyed = named.join(known.select("token", "gf"), "token", "left").withColumn("key", key)
    else:
        keyed = named.withColumn("key", F.lit(0) if order == "alphabetical" else -F.length("token"))
    return _gather(keyed, True, keys)


def zipf_profile(bag: DataFrame) -> DataFrame:
    """(gf, tokens, rank): how many tokens have a frequency, and the rank of the first of them."""
    by_gf = global_token_frequency(bag).groupBy("gf").agg(F.count("*").alias("tokens"))
    above = Window.orderBy(F.desc("gf")).rowsBetween(Window.unboundedPreceding, -1)  # distinct frequencies only: a small aggregate
    return by_gf.select("gf", "tokens", (F.coalesce(F.sum("tokens").over(above), F.lit(0)) + 1).cast("long").alias("rank"))


def zipf_slope(bag: DataFrame) -> DataFrame:
    """Slope of log frequency over log rank; near -1 for natural vocabularies."""
    return zipf_profile(bag).agg(F.regr_slope(F.log("gf"), F.log("rank")).alias("slope"))
