"""Blocks: what is compared. Every maker returns (block_id, project_id, file_id, start_line, end_line, text)."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.tokens import PROFILES, bag_of_tokens, count_loc, token_array

COLUMNS = "block_id long, project_id string, file_id long, start_line int, end_line int, text string"


def document_blocks(df: DataFrame, id: str = "doc_id", text: str = "text", project: str | None = "source") -> DataFrame:
    """One row, one block. Null texts are no blocks."""
    of = F.col(project).cast("string") if project else F.lit("all")
    return df.where(F.col(text).isNotNull() & F.col(id).isNotNull()).select(
        F.col(id).cast("long").alias("block_id"), of.alias("project_id"), F.col(id).cast("long").alias("file_id"),
        F.lit(1).alias("start_line"), F.size(F.split(text, "\n")).alias("end_line"), F.col(text).alias("text"))


def _numbered(df: DataFrame, file_id: str, start: str) -> DataFrame:
    """block_id from file and first line, in 20 bits: no shuffle, no global counter."""
    return df.withColumn("block_id", F.col(file_id) * (1 << 20) + F.col(start)).select("block_id", "project_id", "file_id", "start_line", "end_line", "text")


def line_blocks(df: DataFrame, id: str = "doc_id", text: str = "text", project: str | None = "source") -> DataFrame:
    """Each line a block."""
    docs = document_blocks(df, id, text, project)
    lines = docs.select("project_id", "file_id", F.posexplode(F.split("text", "\n")).alias("at", "text"))
    return _numbered(lines.withColumns({"start_line": F.col("at") + 1, "end_line": F.col("at") + 1}), "file_id", "start_line")


def window_blocks(df: DataFrame, width: int, step: int, id: str = "doc_id", text: str = "text", project: str | None = "source") -> DataFrame:
    """Sliding windows of `width` lines every `step`; the last one is cut short at the end of the file."""
    docs = document_blocks(df, id, text, project).withColumn("lines", F.split("text", "\n"))
    last = F.least(F.size("lines"), F.greatest(F.size("lines") - width + step, F.lit(1)))  # no line behind the last window
    starts = F.sequence(F.lit(1), last, F.lit(step))
    cut = docs.select("project_id", "file_id", "lines", F.explode(starts).alias("start_line"))
    cut = cut.withColumn("end_line", F.least(F.col("start_line") + width - 1, F.size("lines")))
    return _numbered(cut.withColumn("text", F.array_join(F.slice("lines", F.col("start_line"), width), "\n")), "file_id", "start_line")


def line_group_blocks(df: DataFrame, group: int = 15, id: str = "doc_id", text: str = "text", project: str | None = "source") -> DataFrame:
    """Fixed groups of lines, a stand-in for functions in prose."""
    return window_blocks(df, group, group, id, text, project) if group > 1 else line_blocks(df, id, text, project)


def blocks_from_boundaries(df: DataFrame, bounds: DataFrame, id: str = "doc_id", text: str = "text", project: str | None = "source") -> DataFrame:
    """Blocks at given (file_id, start_line, end_line)."""
    docs = document_blocks(df, id, text, project).select("project_id", "file_id", F.split("text", "\n").alias("lines"))
    cut = bounds.select("file_id", "start_line", "end_line").join(docs, "file_id")
    return _numbered(cut.withColumn("text", F.array_join(F.slice("lines", F.col("start_line"), F.col("end_line") - F.col("start_line") + 1), "\n")), "file_id", "start_line")


_LEXER = re.compile(r"(?s)/\*.*?\*/|//[^\n]*|\"(?:[^\"\\\n]|\\.)*\"|'(?:[^'\\\n]|\\.)*'|[{}]|\n")
_HEADER = re.compile(r"[\w\]>]\s*\([^;{}]*\)\s*(?:throws\s+[\w.,\s]+)?$")
_CONTROL = re.compile(r"\b(?:if|for|while|switch|catch|foreach|using|lock|synchronized)\s*\([^{}]*\)\s*$")


def brace_spans(code: str) -> list[tuple[int, int]]:
    """(first line, last line) of each method-like brace block, found outside comments and literals."""
    spans, opened, line, since = [], [], 1, 0
    for m in _LEXER.finditer(code):
        piece = m.group()
        if piece == "{":
            head = re.sub(r"(?s)/\*.*?\*/|//[^\n]*", " ", code[since : m.start()]).rsplit(";", 1)[-1].strip()
            is_method = bool(_HEADER.search(head)) and not _CONTROL.search(head)
            opened.append((line - code[m.start() - len(code[since : m.start()].rsplit(";", 1)[-1].lstrip()) : m.start()].count("\n") if is_method else line, is_method))
            since = m.end()
        elif piece == "}":
            if opened:
                start, is_method = opened.pop()
                if is_method:
                    spans.append((start, line))
            since = m.end()
        line += piece.count("\n")
    return sorted(spans)


def brace_blocks(df: DataFrame, id: str = "doc_id", text: str = "text", project: str | None = "source") -> DataFrame:
    """Methods of brace languages. Nesting needs a stack, which no built-in has: the one Python lexer."""
    docs = document_blocks(df, id, text, project).select("project_id", "file_id", "text")

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows = []
            for project_id, file_id, code in batch.itertuples(index=False):
                lines = code.split("\n")
                rows += [(file_id * (1 << 20) + a, project_id, file_id, a, b, "\n".join(lines[a - 1 : b])) for a, b in brace_spans(code)]
            yield pd.DataFrame(rows, columns=["block_id", "project_id", "file_id", "start_line", "end_line", "text"])

    return docs.mapInPandas(cut, COLUMNS)


def relation_blocks(df: DataFrame, block: str, token: str, project: str | None = None) -> DataFrame:
    """A bag from any relation of blocks and tokens: (block_id, project_id, token, freq)."""
    of = F.col(project).cast("string") if project else F.lit("all")
    rows = df.select(F.col(block).cast("long").alias("block_id"), of.alias("project_id"), F.col(token).cast("string").alias("token"))
    return rows.where("block_id is not null and token is not null").groupBy("block_id", "project_id", "token").agg(F.count("*").cast("int").alias("freq"))


def session_blocks(events: DataFrame, gap: str = "1 hour") -> DataFrame:
    """A bag a user session: tokens are event types."""
    per = events.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.collect_list("event_type").alias("types"))
    each = per.select(F.xxhash64("user_id", "s.start").alias("block_id"), F.col("user_id").cast("string").alias("project_id"), F.explode("types").alias("token"))
    return bag_of_tokens(each)


def size_limits(blocks: DataFrame, profile: str = "prose", min_lines: int = 0, max_lines: int | None = None, min_tokens: int = 0, max_tokens: int | None = None) -> DataFrame:
    """Blocks within limits of lines (blank and comment lines not counted) and tokens."""
    if profile not in PROFILES:
        raise ValueError(f"profile is one of {sorted(PROFILES)}")
    keep = F.lit(True)
    if min_lines or max_lines is not None:
        loc = count_loc(F.col("text"), profile)
        keep = keep & (loc >= min_lines) & (loc <= max_lines if max_lines is not None else F.lit(True))
    if min_tokens or max_tokens is not None:
        n = F.size(token_array(F.col("text"), profile))
        keep = keep & (n >= min_tokens) & (n <= max_tokens if max_tokens is not None else F.lit(True))
    return blocks.where(keep)


def renamed_prose(docs: DataFrame, keep: int = 100, id: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """(doc_id, token), one row an occurrence: of each language's words all but the `keep` commonest become ID."""
    words = docs.select(F.col(id).alias("doc_id"), F.col(lang).alias("lang"), F.explode(token_array(F.col(text))).alias("token"))
    turn = F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "token"))
    common = words.groupBy("lang", "token").agg(F.count("*").alias("n")).withColumn("r", turn).where(F.col("r") <= keep).select(F.col("lang").alias("its"), F.col("token").alias("common"))
    named = words.join(common, words["lang"].eqNullSafe(F.col("its")) & (F.col("token") == F.col("common")), "left")
    return named.select("doc_id", F.coalesce("common", F.lit("ID")).alias("token"))
