"""Language identification with hyperdimensional profiles.

Every letter has a random vector of +1 and -1. A trigram is its letters' vectors, each rotated by its place,
multiplied together; a document is the sum of its trigrams; a language is the sum of its documents, each at
unit length. Documents take the language of the largest cosine.

Learned from a sample of labelled rows outside fold 0, of about SAMPLE rows; texts are read whole. Defined
cases: null text, or one without a letter, is `und` with score 0; a label of null teaches nothing; without any
usable label everything is `und`; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .folds import bounded, held_out, trainable
from .texts import held, pieces

SAMPLE = 20_000
DIMENSIONS = 1024
SYMBOLS = 128
GRAM = 3
HAS_LETTER = re.compile(r"[^\W\d_]")


def _symbols() -> np.ndarray:
    """Symbol of each character: 0 for what is no letter, 1..26 for a..z, the rest hashed over the others."""
    table = np.zeros(0x110000, np.uint8)
    points = np.arange(0x80, 0x110000, dtype=np.uint64)
    table[0x80:] = 27 + ((points * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(40)) % np.uint64(SYMBOLS - 27)
    table[ord("a") : ord("z") + 1] = np.arange(1, 27)
    table[ord("A") : ord("Z") + 1] = np.arange(1, 27)
    for lo, hi in ((0x80, 0xBF), (0xD7, 0xD7), (0xF7, 0xF7), (0x2000, 0x206F), (0x3000, 0x303F)):
        table[lo : hi + 1] = 0
    return table


class Profiles:
    """Vectors of letters, trigrams and documents. Trigrams' vectors are bound when first met and kept: there are at most SYMBOLS^3."""

    def __init__(self, seed: int = 7, most: int = 30_000):
        letters = np.random.default_rng(seed).integers(0, 2, (SYMBOLS, DIMENSIONS), dtype=np.int8) * 2 - 1
        self.letters = [np.roll(letters, GRAM - 1 - k, axis=1) for k in range(GRAM)]
        self.symbols, self.most = _symbols(), most
        self._forget()

    def _forget(self) -> None:
        self.row = np.full(SYMBOLS**GRAM, -1, np.int32)
        self.grams = np.zeros((4096, DIMENSIONS), np.float32)
        self.used = 0

    def _bind(self, codes: np.ndarray) -> None:
        fresh = codes[self.row[codes] < 0]
        if not len(fresh):
            return
        if self.used + len(fresh) > self.most:
            self._forget()
            fresh = codes
        made = self.letters[GRAM - 1][fresh % SYMBOLS].copy()
        for k in range(1, GRAM):
            made *= self.letters[GRAM - 1 - k][fresh // SYMBOLS**k % SYMBOLS]
        while self.used + len(fresh) > len(self.grams):
            self.grams = np.concatenate([self.grams, np.zeros_like(self.grams)])
        self.grams[self.used : self.used + len(fresh)] = made
        self.row[fresh] = np.arange(self.used, self.used + len(fresh))
        self.used += len(fresh)

    def document(self, text: str) -> np.ndarray | None:
        """Bundle of a text's trigrams; None if it has no letter."""
        if not HAS_LETTER.search(text):
            return None
        points = np.frombuffer(text.lower().encode("utf-32-le"), np.uint32)
        s = self.symbols[points].astype(np.int32)
        keep = np.ones(len(s), bool)
        keep[1:] = (s[1:] != 0) | (s[:-1] != 0)  # runs of what is no letter count once
        s = np.concatenate(([0], s[keep], [0]))
        codes, n = np.unique((s[:-2] * SYMBOLS + s[1:-1]) * SYMBOLS + s[2:], return_counts=True)
        self._bind(codes)
        return n.astype(np.float32) @ self.grams[self.row[codes]]


def profiles() -> Profiles:
    return held(("profiles",), Profiles)


def fit(docs: DataFrame, sample: int = SAMPLE) -> tuple[list[str], np.ndarray]:
    """(languages, unit prototypes) from labelled rows outside fold 0."""
    usable = docs.where(trainable() & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "text", "lang")
    parts = max(1, sample // 2500)
    rows = bounded(usable, sample).select("text", "lang").repartition(parts)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for batch in batches:
            for text, lang in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                v = profiles().document(text)
                if v is not None:
                    sums[lang] = sums.get(lang, 0) + v / np.linalg.norm(v).clip(1e-9)
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.string()), pa.array([v.astype(np.float64).tobytes() for v in sums.values()], pa.binary())], names=["lang", "v"])

    # a bounded sample in a fixed number of tasks: so many vectors a language at most
    total: dict[str, np.ndarray] = {}
    for lang, v in sorted(map(tuple, rows.mapInArrow(run, "lang string, v binary").collect())):
        total[lang] = total.get(lang, 0) + np.frombuffer(v)
    langs = sorted(total)
    if not langs:
        return [], np.zeros((0, DIMENSIONS), np.float32)
    protos = np.stack([total[x] / np.linalg.norm(total[x]).clip(1e-9) for x in langs])
    return langs, protos.astype(np.float32)


def predict(docs: DataFrame, langs: list[str], protos: np.ndarray) -> DataFrame:
    """The columns of docs with lang_pred and score (the cosine, 0 if below) added."""
    fields = docs.drop("lang_pred", "score")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch):
                names, scores = [], []
                for text in part.column("text").to_pylist():
                    v = profiles().document(text) if text and langs else None
                    if v is None:
                        names.append("und")
                        scores.append(0.0)
                        continue
                    c = protos @ v / max(float(np.linalg.norm(v)), 1e-9)
                    k = int(c.argmax())
                    names.append(langs[k])
                    scores.append(min(1.0, max(0.0, float(c[k]))))
                out = part.append_column("lang_pred", pa.array(names, pa.string()))
                yield out.append_column("score", pa.array(scores, pa.float64()))

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in fields.schema)
    return fields.mapInArrow(run, f"{schema}, lang_pred string, score double")


#: Documents under this cosine are in no language that was learned: five standard deviations of chance.
LEAST_SCORE = 5 / DIMENSIONS**0.5


def keep_known(docs: DataFrame, least: float = LEAST_SCORE) -> DataFrame:
    """Documents in one of the languages learned, with their own columns only."""
    found = predict(docs, *fit(docs))
    return found.where((F.col("lang_pred") != "und") & (F.col("score") >= least)).select(*docs.columns)


def op9_hyperdimensional(spark, sf_dir: str) -> DataFrame:
    """All documents: (doc_id, held_out, lang_pred, score)."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return predict(docs.select("doc_id", "text"), *fit(docs)).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
