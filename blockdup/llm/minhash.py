"""Near-duplicate documents by SuperMinHash signatures, banding, exact verification and components.

A document's set is that of its distinct shingles of `width` words. A shingle is held as a 64-bit hash of its
words (two different ones share it with a chance of 2^-64); documents with the same set (128-bit fingerprint
of all of it) are one class and are compared once.

Defined cases: a null or empty text has the empty set, links with nothing, and is its own component; fewer
words than a shingle make one shingle of all of them. Rows that repeat an id are documents of their own: each
has the component of its own text, named by the smallest id in it, so that rows of one id may differ. A null
id is kept, with component null unless a document of its component has an id. Columns besides `id` and `text`
are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.groups import connected_components
from ..sources.io import stage, unstage
from .texts import LOWER, flat, held, mix, pieces, span_hashes, words

_U = np.uint64
_STEP = _U(0x9E3779B97F4A7C15)
_ARMS = [_U(x) for x in (0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3, 0x1D8E4E27C47D124F, 0xEB44ACCAB455D165, 0x9C6E6877736C46E3, 0xC13FA9A902A6328F)]


def shingles(raw: np.ndarray, offsets: np.ndarray, width: int = 5) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    low = LOWER[raw]
    starts, ends, before = words(low, offsets)
    h = span_hashes(low, starts, ends)
    runs = np.zeros(len(h), _U)
    for k in range(width):
        if len(h) > k:
            runs[: len(h) - k] += h[k:] * _ARMS[k % 8] if k < 8 else mix(h[k:] + _U(k))
    runs = mix(runs)
    out = []
    for a, b in zip(before[:-1].tolist(), before[1:].tolist(), strict=True):
        if b - a >= width:
            mine = np.sort(runs[a : b - width + 1])
            keep = np.ones(len(mine), bool)
            keep[1:] = mine[1:] != mine[:-1]
            out.append(mine[keep])
        elif b > a:
            short = (h[a:b] * np.array([_ARMS[k % 8] for k in range(b - a)], _U)).sum(dtype=_U) + _U(b - a)
            out.append(mix(mix(np.array([short], _U)) ^ _STEP))
        else:
            out.append(np.zeros(0, _U))
    return out


def super_minhash(elements: np.ndarray, slots: int, chunk: int = 8192) -> np.ndarray:
    """Signature of a set: slot k holds the least (level, fraction) any element gives it.

    Each element walks through its own random permutation of the slots; its step j offers a value in
    [j, j + 1). All elements take a step together, and the walk ends as soon as no slot can still improve.
    Because one element's offers are the ranks of a permutation, slots are correlated in the way that
    lowers the variance of the estimate.
    """
    best = np.full(slots, np.iinfo(np.uint64).max, _U)
    steps = np.arange(1, slots + 1, dtype=_U) * _STEP
    for at in range(0, len(elements), chunk):
        x = elements[at : at + chunk]
        places = np.tile(np.arange(slots, dtype=np.uint16), (len(x), 1))
        row = np.arange(len(x))
        worst = int(best.max())
        for j in range(slots):
            if worst < (j << 32):
                break
            r = mix(x + steps[j])
            k = j + ((r >> _U(32)) % _U(slots - j)).astype(np.intp)
            slot = places[row, k]
            places[row, k] = places[:, j]
            np.minimum.at(best, slot, (r & _U(0xFFFFFFFF)) | _U(j << 32))
            worst = int(best.max())
    return best


def estimate(a: np.ndarray, b: np.ndarray) -> float:
    """Similarity of two sets as the share of equal slots."""
    return float((a == b).mean())


def fingerprint(elements: np.ndarray) -> bytes:
    """128 bits of the whole set."""
    return np.array([mix(elements).sum(dtype=_U), mix(elements ^ _U(0x5851F42D4C957F2D)).sum(dtype=_U) + _U(len(elements))], _U).tobytes()


def _bands(signature: np.ndarray, bands: int) -> np.ndarray:
    rows = signature.reshape(bands, -1)
    key = np.arange(bands, dtype=_U) * _STEP
    for k in range(rows.shape[1]):
        key = mix(key ^ rows[:, k])
    return key.view(np.int64)


def signatures(docs: DataFrame, width: int = 5, bands: int = 32, rows: int = 4) -> DataFrame:
    """(doc_id, text_key, n_shingles, set_key, bands): sizes, fingerprints and band keys of whole texts. No shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held(("minhash",), dict)  # another operator's large object goes
        for batch in batches:
            for part in pieces(batch, 1 << 20):
                sets = shingles(*flat(part.column("text")), width)
                keys = [_bands(super_minhash(s, bands * rows), bands) if len(s) else np.zeros(0, np.int64) for s in sets]
                at = np.concatenate(([0], np.cumsum([len(k) for k in keys]))).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(at), pa.array(np.concatenate(keys) if keys else np.zeros(0, np.int64)))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("text_key"), pa.array([len(s) for s in sets], pa.int64()), pa.array([fingerprint(s) for s in sets], pa.binary()), lists], names=["doc_id", "text_key", "n_shingles", "set_key", "bands"])

    return docs.select("doc_id", F.xxhash64("text").alias("text_key"), "text").mapInArrow(run, "doc_id long, text_key long, n_shingles long, set_key binary, bands array<long>")


def full_sets(docs: DataFrame, width: int = 5) -> DataFrame:
    """(set_key, elements): the sets themselves, for the documents given."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held(("minhash",), dict)  # another operator's large object goes
        for batch in batches:
            for part in pieces(batch, 1 << 20):
                sets = shingles(*flat(part.column("text")), width)
                yield pa.RecordBatch.from_arrays([pa.array([fingerprint(s) for s in sets], pa.binary()), pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], names=["set_key", "elements"])

    return docs.mapInArrow(run, "set_key binary, elements array<long>")


#: The order of rows; one without an id comes last.
FIRST = "struct(doc_id is null as no_id, doc_id, text_key)"


def grouped(rows_in: DataFrame, percent: int, width: int = 5, bands: int = 32, rows: int = 4) -> tuple[DataFrame, DataFrame]:
    """(signatures of all rows, (set_key, first) of each class with the first row of its whole group) of (doc_id, text).

    Two passes over the band buckets. The first compares every member of a bucket with its first and its
    last; for a group of copies that already joins nearly all. The second takes the buckets whose members
    are still in more than one component and compares members of different components, so no link between
    components is lost and no pair inside one is formed. With 32 bands of 4 slots a pair at 0.85 escapes
    all buckets with a chance of 6e-11, at 0.8 of 5e-8. All links are confirmed on the whole sets.
    """
    signed = stage(signatures(rows_in, width, bands, rows), "signatures")
    classes = signed.where("n_shingles > 0").groupBy("set_key").agg(F.min(F.expr(FIRST)).alias("first"), F.first("n_shingles").alias("n"), F.first("bands").alias("bands"))
    # classes are numbered once and written, so that buckets, pairs and labels are plain numbers
    classes = stage(classes.withColumn("node", F.monotonically_increasing_id()), "classes")
    places = classes.select("node", "n", F.explode("bands").alias("bucket"))
    end = F.struct("node", "n")
    ends = places.groupBy("bucket").agg(F.count("*").alias("size"), F.min(end).alias("low"), F.max(end).alias("high")).where("size > 1").drop("size")
    shared = stage(places.join(ends, "bucket"), "buckets")

    # the texts of classes in a shared bucket are read once more, those of their first rows alone
    wanted = classes.join(shared.select("node").distinct(), "node", "left_semi").select("node", "set_key", "first.doc_id")
    named = rows_in.join(wanted.where("doc_id is not null").select("doc_id").distinct(), "doc_id", "left_semi").unionByName(rows_in.where("doc_id is null"))
    # an id that is repeated, or null, may bring in sets nobody asked for, or one set twice
    sets = stage(full_sets(named, width).join(wanted.select("node", "set_key"), "set_key").groupBy("node").agg(F.first("elements").alias("elements")), "sets")

    def confirm(found: DataFrame) -> DataFrame:
        """(a, b) of the candidates (a, b) that are links, on the whole sets."""
        x = sets.select(F.col("node").alias("a"), F.col("elements").alias("of_a"))
        y = sets.select(F.col("node").alias("b"), F.col("elements").alias("of_b"))
        common = found.join(x, "a").join(y, "b").select("a", "b", (F.size("of_a") + F.size("of_b")).cast("long").alias("both"), F.size(F.array_intersect("of_a", "of_b")).cast("long").alias("common"))
        return stage(common.where((F.col("common") * 100 >= (F.col("both") - F.col("common")) * percent)).select("a", "b"), "confirmed")

    def ordered(frame: DataFrame, x: str, y: str) -> DataFrame:
        return frame.where(F.col(x) != F.col(y)).select(F.least(x, y).alias("a"), F.greatest(x, y).alias("b"))

    # each member with the two ends of its bucket, where their sizes let them link
    able = shared.select("node", "n", F.explode(F.array("low", "high")).alias("end")).where((F.col("node") != F.col("end.node")) & (F.least("n", "end.n") * 100 >= F.greatest("n", "end.n") * percent))
    first = confirm(ordered(able.select("node", F.col("end.node").alias("other")), "node", "other").distinct())
    roots = stage(connected_components(first), "roots")
    placed = shared.select("bucket", "node").join(roots, "node", "left").select("bucket", "node", F.coalesce("root", "node").alias("root"))
    split = placed.groupBy("bucket").agg(F.min("root").alias("r0"), F.max("root").alias("r1"), F.count("*").alias("size")).where("r0 <> r1 and size > 2")
    open_ = stage(placed.join(split.select("bucket"), "bucket", "left_semi"), "open")
    # A shingle no other open document has is lost to every pair: what is left bounds the common part.
    mine = sets.join(open_.select("node").distinct(), "node", "left_semi")
    lone = mine.select("node", F.explode("elements").alias("e")).groupBy("e").agg(F.count("*").alias("c"), F.min("node").alias("node")).where("c = 1").groupBy("node").agg(F.count("*").alias("lone"))
    # 32 bits an element decide inside the join, so that only likely links become rows; they are confirmed on full sets.
    short = F.transform("elements", lambda e: F.try_mod(e, F.lit(2**31 - 1)).cast("int"))
    likely = mine.join(lone, "node", "left").select("node", F.size("elements").cast("long").alias("n"), (F.size("elements") - F.coalesce("lone", F.lit(0))).alias("most"), short.alias("short")).where(F.col("most") * 100 >= F.col("n") * percent)
    members = open_.join(likely.join(classes.select("node", "bands"), "node"), "node")
    x = members.select("bucket", "node", "n", "root", "most", "bands", "short")
    y = members.select(F.col("bucket").alias("bucket_y"), *(F.col(c).alias(f"{c}_y") for c in ("node", "n", "root", "most", "bands", "short")))
    reach = lambda common: common * 100 >= (F.col("n") + F.col("n_y") - common) * percent
    cross = x.join(y, (F.col("bucket") == F.col("bucket_y")) & (F.col("node") < F.col("node_y")) & (F.col("root") != F.col("root_y")) & reach(F.least("most", "most_y"))
                   & (F.get(F.array_intersect("bands", "bands_y"), F.lit(0)) == F.col("bucket"))  # a pair is compared in the first bucket it shares
                   & reach(F.size(F.array_intersect("short", "short_y")) + F.size("short") - F.size(F.array_distinct("short"))))
    second = confirm(ordered(cross, "node", "node_y"))
    links = first.unionByName(second)
    unstage(shared, sets, open_, roots)
    roots = stage(connected_components(links), "roots")
    unstage(first, second)
    own = classes.select("node", "set_key", "first").join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    least = own.groupBy("root").agg(F.min("first").alias("first"))
    return signed, own.drop("first").join(least, "root").select("set_key", "first")


def _rows(docs: DataFrame, id: str, text: str) -> DataFrame:
    return docs.select(F.col(id).cast("long").alias("doc_id"), F.col(text).alias("text"))


def near_duplicates(docs: DataFrame, percent: int = 80, width: int = 5, bands: int = 32, rows: int = 4, id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row: links at 100 * common >= percent * union."""
    signed, classes = grouped(_rows(docs, id, text), percent, width, bands, rows)
    out = signed.select("doc_id", "n_shingles", "set_key").join(classes, "set_key", "left")
    own = F.when(F.col("n_shingles") > 0, F.col("first.doc_id")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", own.alias("component_id")).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def one_of_each(docs: DataFrame, percent: int = 80, width: int = 5, bands: int = 32, rows: int = 4) -> DataFrame:
    """The rows of docs (doc_id, text, ...), one of each group of near-duplicates, with their own columns.

    Rows are told apart by id and text, so different texts of one id are judged by themselves. The row with
    the smallest id stays (null last), of like ids the one with the smallest hash of its text; of rows alike in
    id and text the one that sorts first as JSON. Rows without a word stay.
    """
    signed, classes = grouped(_rows(docs, "doc_id", "text"), percent, width, bands, rows)
    stay = classes.select("first.doc_id", "first.text_key").distinct()
    stay = stay.unionByName(signed.where("n_shingles = 0").select("doc_id", "text_key").distinct()).select(F.col("doc_id").alias("stay_id"), F.col("text_key").alias("stay_text"))
    keyed = docs.withColumn("text_key__", F.xxhash64("text"))
    kept = keyed.join(stay, F.col("doc_id").cast("long").eqNullSafe(F.col("stay_id")) & (F.col("text_key__") == F.col("stay_text")), "left_semi")
    again = signed.where("n_shingles > 0").groupBy("doc_id", "text_key").agg(F.count("*").alias("times")).where("times > 1").select(F.col("doc_id").alias("again_id"), F.col("text_key").alias("again_text"))
    if not again.limit(1).count():
        return kept.select(*docs.columns)
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("again_id")) & (F.col("text_key__") == F.col("again_text"))
    once = kept.join(again, same, "left_anti").select(*docs.columns)
    whole = F.struct(*docs.columns)
    some = kept.join(again, same, "left_semi").groupBy("doc_id", "text_key__").agg(F.min_by(whole, F.to_json(whole)).alias("row__"))
    return once.unionByName(some.select("row__.*"))


def op4_super_minhash(spark, sf_dir: str) -> DataFrame:
    """All documents, links at 0.85 on shingles of five words."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return near_duplicates(docs, percent=85)
