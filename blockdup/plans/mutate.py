"""Mutation operators: copies of a fragment with one edit each, seeded by the fragment's id."""

from __future__ import annotations

import random
import re
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_WORD = re.compile(r"[^\W\d_]\w*")


def _line_edit(f):
    """An operator on one word-bearing line away from both ends."""

    def run(lines: list[str], r: random.Random, margin: float) -> tuple[list[str], int, int]:
        edge = max(1, round(len(lines) * margin))
        places = [k for k in range(edge, len(lines) - edge) if _WORD.search(lines[k])] or list(range(len(lines)))
        at = r.choice(places)
        made = f(lines[at], r)
        first = at if made else max(0, at - 1)  # what is gone lies between two lines, and both are the edit
        return lines[:at] + made + lines[at + 1 :], first, max(at, at + len(made) - 1)

    return run


def _swap_word(line: str, r: random.Random, new: str) -> str:
    spots = list(_WORD.finditer(line))
    if not spots:
        return line + " " + new
    m = r.choice(spots)
    return line[: m.start()] + new + line[m.end() :]


def _halves(line: str, r: random.Random) -> list[str]:
    words = line.split(" ")
    k = r.randrange(1, len(words)) if len(words) > 1 else 1
    return [" ".join(words[:k]), " ".join(words[k:])] if len(words) > 1 else [line, ""]


def _rename(lines: list[str], r: random.Random, margin: float, everything: bool) -> tuple[list[str], int, int]:
    edge = max(1, round(len(lines) * margin))
    names = sorted({w for x in lines[edge : len(lines) - edge] for w in _WORD.findall(x)}) or ["x"]
    table = {n: f"v{k}q" for k, n in enumerate(names)} if everything else {r.choice(names): "renamedq"}
    out = [_WORD.sub(lambda m: table.get(m.group(), m.group()), x) for x in lines]
    touched = [k for k, (a, b) in enumerate(zip(lines, out, strict=True)) if a != b] or [0]
    return out, touched[0], touched[-1]


def _join(lines: list[str], r: random.Random, margin: float) -> tuple[list[str], int, int]:
    edge = max(1, round(len(lines) * margin))
    at = r.randrange(edge, max(edge + 1, len(lines) - edge - 1))
    return lines[:at] + [" ".join(lines[at : at + 2])] + lines[at + 2 :], at, at


#: name -> (type, operator). Copies differ from their fragment by one edit.
OPERATORS = {
    "spaces_added": ("T1", _line_edit(lambda x, r: [x.replace(" ", "   ", 1) if " " in x else x + "  "])),
    "spaces_removed": ("T1", _line_edit(lambda x, r: [x.strip() if x != x.strip() else re.sub(r"([^\w\s]) ", r"\1", x, count=1)])),
    "line_break_added": ("T1", _line_edit(_halves)),
    "line_break_removed": ("T1", _join),
    "note_inserted": ("T1", _line_edit(lambda x, r: [x + " /* noted */"])),
    "one_name_everywhere": ("T2", lambda lines, r, m: _rename(lines, r, m, False)),
    "one_name_once": ("T2", _line_edit(lambda x, r: [_swap_word(x, r, "otherq")])),
    "all_names": ("T2", lambda lines, r, m: _rename(lines, r, m, True)),
    "number_changed": ("T2", _line_edit(lambda x, r: [re.sub(r"\d+", "4711", x, count=1) if re.search(r"\d", x) else x + " 4711"])),
    "phrase_changed": ("T2", _line_edit(lambda x, r: [x + ' "quoted anew"'])),
    "inserted_in_line": ("T3", _line_edit(lambda x, r: [x + " addedq wordsq"])),
    "deleted_in_line": ("T3", _line_edit(lambda x, r: [_swap_word(x, r, "")])),
    "line_inserted": ("T3", _line_edit(lambda x, r: [x, "whole newq lineq"])),
    "line_deleted": ("T3", _line_edit(lambda x, r: [])),
    "line_replaced": ("T3", _line_edit(lambda x, r: ["anotherq lineq insteadq"])),
}


def mutants(fragments: DataFrame, places: int = 1, margin: float = 0.15) -> DataFrame:
    """(fragment_id, lang, operator, clone_type, copy, text, edit_start, edit_end) of each fragment (fragment_id, lang, text)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            out = []
            for fragment_id, lang, text in batch.itertuples(index=False):
                lines = text.split("\n")
                for name, (kind, f) in OPERATORS.items():
                    for copy in range(places):
                        made, a, b = f(lines, random.Random(f"{fragment_id}-{name}-{copy}"), margin)
                        out.append((fragment_id, lang, name, kind, copy, "\n".join(made), a + 1, b + 1))
            yield pd.DataFrame(out, columns=["fragment_id", "lang", "operator", "clone_type", "copy", "text", "edit_start", "edit_end"])

    return fragments.select("fragment_id", "lang", "text").mapInPandas(run, "fragment_id long, lang string, operator string, clone_type string, copy int, text string, edit_start int, edit_end int")


def edited_copies(fragments: DataFrame, rates: tuple[int, ...] = (5, 20, 40, 60)) -> DataFrame:
    """(fragment_id, rate, text): copies in which about `rate` percent of the words are replaced."""
    words = F.split("text", " ")
    cut = F.transform(words, lambda w, i: F.when(F.pmod(F.xxhash64(F.col("fragment_id"), F.col("rate"), i), F.lit(100)) < F.col("rate"), F.concat(F.lit("q"), F.pmod(F.xxhash64(F.col("fragment_id"), i), F.lit(100000)).cast("string"))).otherwise(w))
    return fragments.withColumn("rate", F.explode(F.array(*(F.lit(r) for r in rates)))).select("fragment_id", "rate", F.array_join(cut, " ").alias("text"))
