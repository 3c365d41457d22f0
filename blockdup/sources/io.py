"""Tables in and out, and staging of intermediate results in the folder all executors share."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

SCHEMAS = {
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "benchmark": "item_id long, text string",
    "pages": "page_id long, url string, html string",
    "conversations": "conv_id long, turn long, role string, text string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "events": "event_id long, ts timestamp, user_id long, event_type string, value double, props string",
}

_staged: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; declared schemas are used where the table has one, never inference by value."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir of the session; a temporary folder only where it is unset (local tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that every executor can reach")
    made = getattr(spark.sparkContext, "_blockdup_folder", None)
    if made is None:
        made = spark.sparkContext._blockdup_folder = tempfile.mkdtemp(prefix="blockdup-")
    return made


#: With it, Spark removes the shuffles of a command when it has ended.
FREED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextlib.contextmanager
def setting(spark: SparkSession, key: str, value: str) -> Iterator[None]:
    """A setting of the session for what runs in here."""
    before = spark.conf.get(key, None)
    spark.conf.set(key, value)
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def freed(spark: SparkSession):
    """Shuffles of what is written in here are removed with the end of each write, not when the driver's memory is cleaned some time."""
    return setting(spark, FREED, "true")


def stage(df: DataFrame, name: str = "stage", partition_by: list[str] | None = None, compression: str | None = None) -> DataFrame:
    """Write `df` as Parquet in the shared folder and read it back: lineage is cut and a lost executor costs nothing."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/blockdup-{name}-{uuid.uuid4().hex}"
    writer = df.write.mode("error")
    if compression:
        writer = writer.option("compression", compression)
    with freed(spark):
        (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
    _staged.append((spark, path))
    made = spark.read.schema(df.schema).parquet(path) if not partition_by else spark.read.parquet(path)
    made._blockdup_path = path
    return made


def delete(spark: SparkSession, path: str) -> None:
    """Remove a folder through Spark's own file systems; one that is gone already is no error."""
    try:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session may be gone; files in a checkpoint folder are scratch
        pass


def unstage(*frames: DataFrame) -> None:
    """Remove what stage() wrote for frames that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_blockdup_path", None)
        if path is not None:
            _staged[:] = [x for x in _staged if x[1] != path]
            delete(df.sparkSession, path)


def staged() -> int:
    """How many results stage() has written and not removed: a mark for drop_staged."""
    return len(_staged)


def drop_staged(before: int = 0) -> None:
    """Delete what stage() wrote, from the given position of its list on."""
    while len(_staged) > before:
        delete(*_staged.pop())


atexit.register(drop_staged)


def write_bands(pairs: DataFrame, path: str) -> None:
    """Pairs as Parquet, one folder a clone type, so that readers of one band prune the others."""
    pairs.write.mode("overwrite").partitionBy("clone_type").parquet(path)


def round_trip(df: DataFrame, fmt: str, **options) -> DataFrame:
    """Write and read back in a format (parquet, json, csv, orc); the schema is declared, not inferred."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/blockdup-{fmt}-{uuid.uuid4().hex}"
    df.write.format(fmt).options(**options).save(path)
    _staged.append((spark, path))
    return spark.read.format(fmt).options(**options).schema(df.schema).load(path)


def text_files(spark: SparkSession, path: str) -> DataFrame:
    """Whole text files as documents: (file_path, text)."""
    return spark.read.text(path, wholetext=True).select(F.input_file_name().alias("file_path"), F.col("value").alias("text"))


def empty(spark: SparkSession, ddl: str) -> DataFrame:
    """An empty frame of a declared schema."""
    return spark.createDataFrame([], T._parse_datatype_string(ddl))
