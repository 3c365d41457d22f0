"""Encoding and decoding of whole texts by a trie of distinct words whose shared prefixes are encoded once.

Defined cases: null text is empty (no ids, hash of nothing); strings of special tokens in a text become those
tokens, as the library does by default; rows that repeat an id are documents of their own; other columns are
ignored; an empty table gives an empty result. Words remembered are bounded; results do not depend on it.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from tokenizers import Tokenizer

from .bpe import PrefixTrie, Vocabulary, byte_letters
from .texts import held, pieces
from .words_bpe import cut, plain

KEEP = 400_000


class TrieCodec:
    """ids of texts and back. The library only normalises and cuts texts of unusual scripts; it encodes nothing."""

    def __init__(self, path: str, kind: str):
        self.kind, self.v = kind, Vocabulary(path)
        self.trie, self.library = PrefixTrie(self.v), Tokenizer.from_file(path)
        self.letters = byte_letters()
        self.ids: dict[str | bytes, bytes] = {}
        self.said: dict[str | bytes, str] = {}
        self.names = [self.v.names.get(k, "") for k in range(max(self.v.names) + 1)]
        self.special = re.compile("(" + "|".join(map(re.escape, self.v.special)) + ")") if self.v.special else None

    def words(self, text: str) -> list[str | bytes]:
        """Words to encode: str for those that are their own UTF-8, bytes for words of the library's cutting, which come apart from it."""
        if plain(text) and "İ" not in text:
            return cut(text, self.kind)
        out: list[str | bytes] = []
        for k, part in enumerate(self.special.split(text) if self.special else [text]):
            if k % 2:
                out.append(b"\0special " + part.encode())
            elif part:
                clean = self.library.normalizer.normalize_str(part) if self.library.normalizer else part
                out += [b"\0word " + bytes(self.letters[c] for c in w) for w, _ in self.library.pre_tokenizer.pre_tokenize_str(clean)]
        return out

    def learn(self, words: set[str | bytes]) -> None:
        fresh = words.difference(self.ids)
        if not fresh:
            return
        if len(self.ids) + len(fresh) > KEEP:
            self.ids.clear()
            self.said.clear()
            fresh = words
        raw = {w: w.encode() if isinstance(w, str) else w.split(b" ", 1)[1] for w in fresh}
        special = {w for w in fresh if isinstance(w, bytes) and w.startswith(b"\0special ")}
        codes = self.trie.encode(list({r for w, r in raw.items() if w not in special}))
        for w, r in raw.items():
            ids = [self.v.special[r.decode()]] if w in special else codes[r]
            self.ids[w] = np.array(ids, "<u2").tobytes()
            self.said[w] = " ".join([self.names[t] for t in ids])

    def encode(self, texts: list[str]) -> Iterator[tuple[np.ndarray, str]]:
        """(ids, decoded text) of each; this vocabulary has no decoder, so decoding joins token names by spaces."""
        lists = [self.words(t) for t in texts]
        self.learn(set().union(*lists))
        for words in lists:
            yield np.frombuffer(b"".join(map(self.ids.__getitem__, words)), "<u2"), " ".join(map(self.said.__getitem__, words))

    def decode(self, ids: np.ndarray) -> str:
        return " ".join([self.names[t] for t in ids.tolist()])


def codec(path: str, kind: str) -> TrieCodec:
    return held(("trie", path, kind), lambda: TrieCodec(path, kind))


CODES = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def encode_digests(docs: DataFrame, path: str, kind: str = "word") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sha = lambda x: hashlib.sha256(x).hexdigest()
        for batch in batches:
            for part in pieces(batch):
                done = [(len(ids), sha(ids.astype("<u4").tobytes()), sha(said.encode())) for ids, said in codec(path, kind).encode(["" if t is None else t for t in part.column("text").to_pylist()])]
                n, a, b = zip(*done, strict=True)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, CODES)


def encode_ids(docs: DataFrame, path: str, kind: str = "word") -> DataFrame:
    """(doc_id, ids): the ids themselves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch):
                ids = [i.astype(np.int32) for i, _ in codec(path, kind).encode(["" if t is None else t for t in part.column("text").to_pylist()])]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, ids array<int>")


def op8_prefix_trie(spark, sf_dir: str) -> DataFrame:
    """All documents with the word vocabulary."""
    import public_tokenizers

    return encode_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("word_bpe_49k.json"))
