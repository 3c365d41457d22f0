"""Structured Streaming: windows over events, deduplication, state per user, and look-ups of new blocks in a stored index."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.blocks import document_blocks
from ..operators.index import IndexedRepository
from ..sources.io import SCHEMAS, shared_folder, table


def events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of its files; the schema is declared."""
    return spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "*.parquet").parquet(_folder(spark, sf_dir))


def _folder(spark: SparkSession, sf_dir: str) -> str:
    """A folder that holds the events alone: file streams read folders."""
    path = f"{shared_folder(spark)}/events-{uuid.uuid4().hex}"
    table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props").write.parquet(path)
    return path


def events_with_late_rows(spark: SparkSession, sf_dir: str, files: int = 4) -> DataFrame:
    """The events, then those of the last day once more, then those of the first day: too late, as its windows are closed.

    The rows a batch may still bring are judged by the watermark the batch before it started with, hence the one between.
    """
    path, events = f"{shared_folder(spark)}/events-{uuid.uuid4().hex}", table(spark, sf_dir, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")
    events.repartition(files).write.parquet(path)
    first, last = events.agg(F.date_trunc("day", F.min("ts")), F.date_trunc("day", F.max("ts"))).first()
    events.where(F.col("ts") >= F.lit(last)).repartition(files).write.mode("append").parquet(path)
    events.where(F.col("ts") < F.lit(first) + F.expr("INTERVAL 1 DAY")).repartition(files).write.mode("append").parquet(path)
    return spark.readStream.schema(SCHEMAS["events"]).option("pathGlobFilter", "*.parquet").option("maxFilesPerTrigger", files).parquet(path)


def finish(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all there is, into Parquet (append) or memory (complete, update), and give its result."""
    spark, name = stream.sparkSession, f"stream_{uuid.uuid4().hex}"
    where = f"{shared_folder(spark)}/{name}"
    writer = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{where}-checkpoint").outputMode(mode)
    if mode == "append":
        writer.format("parquet").option("path", where).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(where)
    writer.format("memory").queryName(name).start().awaitTermination()
    return spark.table(name)


def tumbling(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"))
    return w.select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "1 day", step: str = "12 hours", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n"))
    return w.select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    s = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("s.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")


def clicks_and_purchases(events: DataFrame, within: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """(click, purchase) of one user at most `within` apart: watermarks on both sides bound the state kept."""
    side = lambda kind: events.where(F.col("event_type") == kind).withWatermark("ts", late).select(F.col("event_id").alias(kind), F.col("user_id").alias(f"{kind}_user"), F.col("ts").alias(f"{kind}_ts"))
    near = F.expr(f"purchase_ts BETWEEN click_ts - INTERVAL {within} AND click_ts + INTERVAL {within}")
    return side("click").join(side("purchase"), (F.col("click_user") == F.col("purchase_user")) & near).select("click", "purchase")


def user_bags(events: DataFrame) -> DataFrame:
    """Running bag of event types of each user, kept as state; every batch emits the bags it changed."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        bag = dict(zip(*state.get, strict=True)) if state.exists else {}
        for batch in batches:
            for kind, n in batch.event_type.value_counts().items():
                bag[kind] = bag.get(kind, 0) + int(n)
        names = sorted(bag)
        state.update((names, [bag[x] for x in names]))
        yield pd.DataFrame({"user_id": [key[0]] * len(names), "event_type": names, "n": [bag[x] for x in names]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, event_type string, n long", "names array<string>, counts array<long>", "update", "NoTimeout")


def lookup_stream(spark: SparkSession, sf_dir: str, theta_pm: int = 700) -> DataFrame:
    """Documents of one source arrive as a stream and are looked up in an index of the others, batch by batch."""
    docs = table(spark, sf_dir, "documents")
    base = f"{shared_folder(spark)}/lookup-{uuid.uuid4().hex}"
    repo = IndexedRepository.build(document_blocks(docs.where("source <> 'src0'")), f"{base}/index", theta_pm)
    docs.where("source = 'src0'").select("doc_id", "text", "lang", "source", "n_chars").write.parquet(f"{base}/new")
    stream = spark.readStream.schema(SCHEMAS["documents"]).parquet(f"{base}/new")

    def look(batch: DataFrame, number: int) -> None:
        repo.query(document_blocks(batch)).write.mode("overwrite").parquet(f"{base}/found/batch={number}")

    stream.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{base}/checkpoint").foreachBatch(look).start().awaitTermination()
    return spark.read.parquet(f"{base}/found").drop("batch")
