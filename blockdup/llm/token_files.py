"""Token ids as files of entropy-coded blocks in the order of document ids.

Two passes over tokens. The first cuts documents, in order of id, into blocks of whole documents and writes
them plainly; their counts, over all documents, make the one static table. The second codes block by block.
A block row holds its part (place in the order of parts), its number and first token within the part, ids and
lengths of its documents, and the coded payload. Offsets over the whole corpus need the totals of the parts only.

Defined cases: null text is empty and gives the end id alone; a null id sorts first and stays null; rows that
repeat an id follow each other in the order of a hash of their texts; other columns are ignored; an empty
table gives empty files. A document is never split over blocks, so a very long one makes a long block.
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
from .rans import BITS, LANES, ROWS_BETWEEN_CHECKPOINTS, Coder, frequency_table, segments
from .texts import pieces
from .words_bpe import encoder

BLOCK_TOKENS = 1 << 17
PLAIN = "part int, block int, first long, doc_ids array<long>, lengths array<int>, payload binary, seen array<int>, times array<long>"
SYMBOLS = 1 << 16


def in_order(docs: DataFrame) -> DataFrame:
    """Range-partitioned and sorted by id; a hash of the text breaks ties, so that one id cannot fill a task."""
    tied = docs.select("doc_id", "text", F.xxhash64("text").alias("tie"))
    return tied.repartitionByRange("doc_id", "tie").sortWithinPartitions("doc_id", "tie").select("doc_id", "text")


def token_blocks(docs: DataFrame, path: str, kind: str = "byte", end_id: int = 2, block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """Documents in order to rows of plain blocks (payload: ids as unsigned 16-bit)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, block, first = TaskContext.get().partitionId(), 0, 0
        ids, lengths, codes, held = [], [], [], 0
        end = np.array([end_id], "<u2").tobytes()
        total = np.zeros(SYMBOLS, np.int64)

        def row(last: bool = False) -> pa.RecordBatch:
            """The block in hand; the last one of a part brings the part's counts along."""
            nonlocal total
            payload = b"".join(codes)
            total += np.bincount(np.frombuffer(payload, "<u2"), minlength=SYMBOLS)
            seen = np.flatnonzero(total) if last else np.zeros(0, np.int64)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([block], pa.int32()), pa.array([first], pa.int64()), pa.array([ids], pa.list_(pa.int64())), pa.array([lengths], pa.list_(pa.int32())), pa.array([payload], pa.binary()), pa.array([seen.astype(np.int32)], pa.list_(pa.int32())), pa.array([total[seen]], pa.list_(pa.int64()))], names=["part", "block", "first", "doc_ids", "lengths", "payload", "seen", "times"])

        for batch in batches:
            for piece in pieces(batch, 3 << 20):
                found, before = encoder(path, kind).encode_column(piece.column("text"))
                code = memoryview(found.astype("<u2").tobytes())
                for doc_id, a, b in zip(piece.column("doc_id").to_pylist(), before[:-1].tolist(), before[1:].tolist(), strict=True):
                    ids.append(doc_id)
                    lengths.append(b - a + 1)
                    codes += (code[2 * a : 2 * b], end)
                    held += b - a + 1
                    if held >= block_tokens:
                        yield row()
                        block, first, held = block + 1, first + held, 0
                        ids, lengths, codes = [], [], []
        if block or ids:
            yield row(last=True)

    return docs.mapInArrow(run, PLAIN)


def token_counts(blocks: DataFrame) -> np.ndarray:
    """Occurrences of each id over all blocks; at most one row an id comes to the driver."""
    pairs = blocks.select(F.explode(F.arrays_zip("seen", "times")).alias("x")).select(F.col("x.seen").alias("id"), F.col("x.times").alias("n"))
    rows = pairs.groupBy("id").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(SYMBOLS, np.int64)
    out[rows.id.to_numpy(np.int64)] = rows.n.to_numpy(np.int64)
    return out


_coders: dict[bytes, Coder] = {}


def _coder(freq: bytes) -> Coder:
    if freq not in _coders:
        _coders.clear()
        _coders[freq] = Coder(np.frombuffer(zlib.decompress(freq), "<i4").astype(np.int64))
    return _coders[freq]


CODED = "part int, block int, first long, doc_ids array<long>, lengths array<int>, payload binary"


def code_blocks(plain: DataFrame, freq: bytes) -> DataFrame:
    """Plain blocks to coded ones, each by itself."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                one = batch.slice(k, 1)
                yield one.set_column(5, "payload", pa.array([_coder(freq).encode(np.frombuffer(one.column(5)[0].as_buffer(), "<u2"))], pa.binary()))

    return plain.select(*(c.split()[0] for c in CODED.split(", "))).mapInArrow(run, CODED)


def write_token_files(docs: DataFrame, path: str, kind: str = "byte", end_id: int = 2) -> tuple[DataFrame, DataFrame]:
    """(table of coded blocks, its frequency table), both written; see read_token_files."""
    plain = stage(token_blocks(in_order(docs), path, kind, end_id), "tokens")
    freq = zlib.compress(frequency_table(token_counts(plain), BITS).astype("<i4").tobytes())
    # the table has one entry an id of the vocabulary, a fixed size
    table = docs.sparkSession.createDataFrame([(bytearray(freq),)], "freq binary")
    return stage(code_blocks(plain, freq), "token-files"), stage(table, "token-table")


def read_token_files(coded: DataFrame, table: DataFrame) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32, ids) of each document, decoded from the files."""
    freq = bytes(table.first()[0])
    totals = coded.groupBy("part").agg(F.max(F.col("first") + F.aggregate("lengths", F.lit(0).cast("long"), lambda a, x: a + x)).alias("total"))
    # one row a part of the file: the number of tasks that wrote it, whatever their size
    base = totals.select("part", (F.sum("total").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, 0)) - F.col("total")).alias("base"))
    placed = coded.join(F.broadcast(base), "part").select((F.col("base") + F.col("first")).alias("start"), "doc_ids", "lengths", "payload")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, doc_ids, lengths, payload in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3), strict=True):
                ids = _coder(freq).decode(payload.as_py()).astype("<u4")
                sizes = np.asarray(lengths.values, np.int64)  # the last block of a part can be empty
                ends = np.cumsum(sizes)
                starts = ends - sizes
                raw = memoryview(ids.tobytes())
                crcs = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(doc_ids, pa.int64()), pa.array(start + starts, pa.int64()), pa.array(ends - starts, pa.int64()), pa.array(crcs, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return placed.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def read_segments(coded: DataFrame, table: DataFrame) -> DataFrame:
    """(part, block, segment, first, ids): the token stream decoded from all checkpoints side by side; first is the place within the part."""
    freq = bytes(table.first()[0])

    def cuts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = [segments(p.as_buffer()) for p in batch.column("payload")]
            yield batch.append_column("segments", pa.array(n, pa.int32()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, block, first, segment, payload in zip(*(batch.column(k).to_pylist() for k in range(4)), batch.column("payload"), strict=True):
                ids = _coder(freq).decode_segment(payload.as_py(), segment).astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([block], pa.int32()), pa.array([segment], pa.int32()), pa.array([first + segment * ROWS_BETWEEN_CHECKPOINTS * LANES], pa.int64()), pa.array([ids], pa.list_(pa.int32()))], names=["part", "block", "segment", "first", "ids"])

    kinds = "part int, block int, first long, payload binary, segments int"
    marked = coded.select("part", "block", "first", "payload").mapInArrow(cuts, kinds)
    each = marked.select("part", "block", "first", F.explode(F.sequence(F.lit(0), F.col("segments") - 1)).alias("segment"), "payload")
    return each.repartition("part", "block", "segment").mapInArrow(run, "part int, block int, segment int, first long, ids array<int>")


def op3_token_files(spark, sf_dir: str) -> DataFrame:
    """All documents, byte-level vocabulary, end id 2, written as coded blocks and read back."""
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return read_token_files(*write_token_files(docs, public_tokenizers.path("byte_bpe_50k.json")))
