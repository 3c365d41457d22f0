"""Packing by concatenating all tokens and cutting every `length` of them.

The first pass encodes each partition and notes each document's place within it; the prefix sum of the
partitions' totals gives each document its place in the whole; the second pass cuts documents at the borders
of the windows and writes one record a piece. No token is moved between tasks: pieces know their sequence.

Defined cases: null text is empty and gives the end id alone; a null id stays null; rows that repeat an id are
documents of their own; other columns are ignored; an empty table gives no piece. Only the last sequence of
all is not full.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.io import stage
from .texts import pieces
from .words_bpe import encoder

ENCODED = "part int, at long, doc_id long, n long, ids binary"


def encoded(docs: DataFrame, path: str, kind: str = "word", end_id: int = 2) -> DataFrame:
    """(part, at, doc_id, n, ids): each document's ids and its place among the tokens of its partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, at = TaskContext.get().partitionId(), 0
        for batch in batches:
            for piece in pieces(batch, 3 << 20):
                found, before = encoder(path, kind).encode_column(piece.column("text"))
                codes = np.insert(found, before[1:], end_id).astype("<u2")  # the end id behind each document
                ends = before[1:] + np.arange(1, len(before))
                starts = np.concatenate(([0], ends[:-1]))
                ids = pa.Array.from_buffers(pa.large_binary(), len(ends), [None, pa.py_buffer(np.concatenate(([0], 2 * ends)).astype(np.int64)), pa.py_buffer(codes)])
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ends), part, np.int32)), pa.array(at + starts), piece.column("doc_id"), pa.array(ends - starts), ids.cast(pa.binary())], names=["part", "at", "doc_id", "n", "ids"])
                at += int(ends[-1])

    return docs.mapInArrow(run, ENCODED)


PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def cut_pieces(first: int, n: int, length: int) -> Iterator[tuple[int, int]]:
    """(start, size) of the pieces of a document that begins at token `first` of the whole."""
    start = 0
    while start < n:
        size = min(n - start, length - (first + start) % length)
        yield start, size
        start += size


def pack(docs: DataFrame, path: str, kind: str = "word", end_id: int = 2, length: int = 4096, with_ids: bool = False) -> DataFrame:
    """One row a piece: (doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset[, ids])."""
    rows = stage(encoded(docs.select(F.col("doc_id").cast("long"), "text"), path, kind, end_id), "encoded")
    totals = rows.groupBy("part").agg(F.max(F.col("at") + F.col("n")).alias("total"))
    # one row a task of the first pass
    base = totals.select("part", (F.sum("total").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("total")).alias("base"))
    placed = rows.join(F.broadcast(base), "part").select((F.col("base") + F.col("at")).alias("first"), "doc_id", "ids")
    schema = PIECES + ", ids array<int>" * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in range(8)]
            for first, doc_id, code in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                ids = np.frombuffer(code.as_buffer(), "<u2").astype("<u4")
                raw = memoryview(ids.tobytes())
                for start, size in cut_pieces(first, len(ids), length):
                    g = first + start
                    for column, value in zip(out, (doc_id, start, size, zlib.crc32(raw[4 * start : 4 * (start + size)]), len(ids), g // length, g % length), strict=False):
                        column.append(value)
                    if with_ids:
                        out[7].append(ids[start : start + size].astype(np.int32))
            arrays = [pa.array(c, pa.int64()) for c in out[:7]] + [pa.array(out[7], pa.list_(pa.int32()))] * with_ids
            yield pa.RecordBatch.from_arrays(arrays, names=[c.split()[0] for c in schema.split(", ")])

    return placed.mapInArrow(run, schema)


def sequences(packed: DataFrame) -> DataFrame:
    """Pieces with ids to rows of a training set: (sequence_id, n_tokens, ids, boundaries of documents)."""
    piece = F.struct("offset", "length", "doc_id", "start", "ids")
    rows = packed.groupBy("sequence_id").agg(F.array_sort(F.collect_list(piece)).alias("p"))
    return rows.select("sequence_id", F.aggregate("p", F.lit(0).cast("long"), lambda a, x: a + x["length"]).alias("n_tokens"), F.flatten(F.transform("p", lambda x: x["ids"])).alias("ids"), F.transform("p", lambda x: F.struct(x["offset"].alias("offset"), x["doc_id"].alias("doc_id"), x["start"].alias("start"))).alias("boundaries"))


def op10_concatenate_and_cut(spark, sf_dir: str) -> DataFrame:
    """All documents in sequences of 4096 tokens of the word vocabulary, end id 2."""
    import public_tokenizers

    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("word_bpe_49k.json"))
