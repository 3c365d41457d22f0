"""Token counts by finite-state transducers.

Two machines. The first reads characters and marks where words begin; its transitions carry the marks. A text
is cut into chunks, each chunk becomes a map from states to states, and the maps compose by a parallel prefix
scan, so all chunks are then run at once from their right states. The second reads the bytes of a word; its
transitions carry how many tokens the step adds to the count of the encoding (a step can merge tokens, so the
number may be negative), and its states are the last tokens of the prefixes that a later token can still
reach back to. It is compiled state by state as words need them.

Defined cases: null text is empty, with no token; strings of special tokens count as one token each, as the
library does by default; rows that repeat an id are documents of their own; other columns are ignored; an
empty table gives an empty result. Machine tables and words remembered are bounded; results are not.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from tokenizers import Tokenizer

from .bpe import Vocabulary
from .texts import held, pieces
from .word_table import Grown, WordTable

# Classes of characters.
LETTER, SHORT, R, V, L, E, NUMBER, SPACE, WHITE, QUOTE, OTHER, END = range(12)
# States: what has been read of the current word.
START, IN_L, IN_N, IN_O, ONE_S, ONE_W, MORE_S, MORE_W, APO, APO_R, APO_V, APO_L, DONE = range(13)
N_STATES, N_CLASSES = 13, 12
HERE, BEFORE = 1, 2
CHUNK = 1024


def _step(state: int, c: int) -> tuple[int, int]:
    """(next state, marks): HERE a word begins at this character, BEFORE one begins at the character before."""
    letter = c <= E
    white = c in (SPACE, WHITE)
    begin = IN_L if letter else {NUMBER: IN_N, SPACE: ONE_S, WHITE: ONE_W, QUOTE: APO, OTHER: IN_O, END: START}[c]
    here = 0 if c == END else HERE
    if state in (START, DONE):
        return begin, here
    if state in (APO_R, APO_V, APO_L):
        if c == (L if state == APO_L else E):
            return DONE, 0
        return (IN_L, BEFORE) if letter else (begin, BEFORE | here)
    if state == APO:
        if c in (SHORT, R, V, L):
            return {SHORT: DONE, R: APO_R, V: APO_V, L: APO_L}[c], 0
        return (IN_O, 0) if c in (QUOTE, OTHER) else (begin, here)
    if state in (ONE_S, ONE_W, MORE_S, MORE_W):
        if white:
            return (MORE_S if c == SPACE else MORE_W), 0
        if c == END:
            return START, 0
        marks = BEFORE if state in (MORE_S, MORE_W) else 0
        if state in (ONE_S, MORE_S):  # a space joins the word it stands before
            return (IN_L if letter else IN_N if c == NUMBER else IN_O), marks
        return begin, marks | HERE
    same = letter if state == IN_L else c == NUMBER if state == IN_N else c in (QUOTE, OTHER)
    return (state, 0) if same else (begin, here)


NEXT = np.array([[_step(s, c)[0] for c in range(N_CLASSES)] for s in range(N_STATES)], np.uint8).ravel()
MARKS = np.array([[_step(s, c)[1] for c in range(N_CLASSES)] for s in range(N_STATES)], np.uint8).ravel()


def scan(maps: np.ndarray) -> np.ndarray:
    """Prefix compositions of state maps [chunks, states]: row k leads from before chunk 0 to behind chunk k."""
    out, reach = maps.copy(), 1
    while reach < len(out):
        out[reach:] = np.take_along_axis(out[reach:], out[:-reach].astype(np.intp), axis=1)
        reach *= 2
    return out


def chunk_maps(lanes: np.ndarray, settle: int = 24) -> np.ndarray:
    """State map of each chunk; `lanes` is [characters, chunks] of classes. Most chunks forget where they came from soon."""
    n = lanes.shape[1]
    states = np.repeat(np.arange(N_STATES, dtype=np.uint16)[:, None], n, axis=1)
    for c in lanes[:settle]:
        states = NEXT[states * N_CLASSES + c].astype(np.uint16)
    one = (states == states[0]).all(axis=0)
    single, rest = states[0, one], states[:, ~one]
    left, right = np.ascontiguousarray(lanes[settle:, one]), np.ascontiguousarray(lanes[settle:, ~one])
    for c in left:
        single = NEXT[single * N_CLASSES + c].astype(np.uint16)
    if rest.shape[1]:
        for c in right:
            rest = NEXT[rest * N_CLASSES + c].astype(np.uint16)
    out = np.empty((n, N_STATES), np.uint8)
    out[one] = single[:, None]
    out[~one] = rest.T
    return out


def word_starts(classes: np.ndarray, chunk: int = CHUNK) -> np.ndarray:
    """Places where words begin in a row of classes that holds an END behind each text."""
    n = -(-len(classes) // chunk)
    lanes = np.full(n * chunk, END, np.uint8)
    lanes[: len(classes)] = classes
    lanes = np.ascontiguousarray(lanes.reshape(n, chunk).T)
    after = scan(chunk_maps(lanes))[:, START]
    state = np.concatenate(([START], after[:-1])).astype(np.uint16)
    marks = np.empty((chunk, n), np.uint8)
    for k, c in enumerate(lanes):
        at = state * N_CLASSES + c
        marks[k] = MARKS[at]
        state = NEXT[at].astype(np.uint16)
    marks = marks.T.ravel()
    begins = (marks & HERE) != 0
    begins[:-1] |= (marks[1:] & BEFORE) != 0
    return np.flatnonzero(begins[: len(classes)])


class CountTransducer:
    """Bytes of a word to the number of its tokens. States are made on demand; `most` bounds the transitions kept."""

    def __init__(self, vocabulary: Vocabulary, most: int = 300_000):
        self.v, self.most = vocabulary, most
        self.alive = {t[:k] for t in vocabulary.inner for k in range(1, len(t))}
        self._reset()

    def _reset(self) -> None:
        first = (b"", (-1,), (0,))
        self.states, self.number, self.steps = [first], {first: 0}, {}

    def _compile(self, state: int, byte: int) -> tuple[int, int]:
        """A state is (the longest suffix read that a token goes on from, last tokens and counts at its places)."""
        suffix, last, counts = self.states[state]
        text = suffix + bytes([byte])
        for begin in range(len(text)):
            token = self.v.inner.get(text[begin:])
            if token is not None and (last[begin] < 0 or self.v.neighbours(last[begin], token)):
                break
        else:
            raise ValueError("a byte is not in the vocabulary")
        added = counts[begin] + 1  # counts are relative to the place just before this byte
        keep = next((k for k in range(len(text)) if text[k:] in self.alive), len(text))
        after = (text[keep:], (*last[keep:], token), (*(c - added for c in counts[keep:]), 0))
        if after not in self.number:
            self.number[after] = len(self.states)
            self.states.append(after)
        made = self.steps[state << 8 | byte] = (self.number[after], added)
        return made

    def count(self, word: bytes) -> int:
        if len(self.steps) > self.most:
            self._reset()
        state, total, known = 0, 0, self.steps.get
        for byte in word:
            step = known(state << 8 | byte)
            state, added = step if step is not None else self._compile(state, byte)
            total += added
        return total


class TokenCounter:
    """Token counts of whole texts of a byte-level vocabulary."""

    def __init__(self, path: str, keep: int = 500_000):
        self.library = Tokenizer.from_file(path)
        vocabulary = Vocabulary(path)
        self.words, self.table, self.known = CountTransducer(vocabulary), WordTable(keep), Grown(np.int64)
        self.special = re.compile("|".join(map(re.escape, vocabulary.special))) if vocabulary.special else None
        self.classes = np.full(0x110000, 255, np.uint8)

    def _class(self, c: str) -> int:
        """Asked of the library's own cutting, so that its tables of characters hold."""
        if c in "stmd":
            return SHORT
        if c in "rvle' ":
            return {"r": R, "v": V, "l": L, "e": E, "'": QUOTE, " ": SPACE}[c]
        pieces_of = lambda t: len(self.library.pre_tokenizer.pre_tokenize_str(t))
        if pieces_of("a" + c) == 1:
            return LETTER
        if pieces_of("1" + c) == 1:
            return NUMBER
        return OTHER if pieces_of("." + c) == 1 else WHITE

    def counts(self, texts: list[str]) -> np.ndarray:
        extra = np.zeros(len(texts), np.int64)
        parts, of = [], []
        for k, text in enumerate(texts):
            if self.special is not None and "<|" in text and self.special.search(text):
                split = self.special.split(text)
                extra[k] = len(split) - 1
                parts += split
                of += [k] * len(split)
            else:
                parts.append(text)
                of.append(k)
        # a character no text can hold stands behind each part
        codes = np.frombuffer("".join([x for p in parts for x in (p, "\0")]).encode("utf-32-le"), np.uint32)
        ends = np.cumsum(np.array([len(p) + 1 for p in parts])) - 1
        classes = self.classes[codes]
        if (classes == 255).any():
            for c in np.unique(codes[classes == 255]).tolist():
                self.classes[c] = self._class(chr(c))
            classes = self.classes[codes]
        classes[ends] = END
        starts = word_starts(classes)
        part = np.searchsorted(ends, starts)
        stops = np.minimum(np.append(starts[1:], len(codes)), ends[part])
        out = extra
        if len(starts):
            n = self._known(codes, starts, stops)
            out += np.bincount(np.array(of)[part], n, len(out)).astype(np.int64)
        return out

    def _known(self, codes: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
        """Tokens of each word. Words met before are known by their characters, not by a hash alone."""
        if self.table.full:
            self.table.clear()
            self.known = Grown(np.int64)
        entry, fresh = self.table.find(codes.view(np.uint8), 4 * starts, 4 * stops)
        count = self.words.count
        self.known.extend(np.array([count(codes[starts[k] : stops[k]].tobytes().decode("utf-32-le").encode()) for k in fresh.tolist()], np.int64))
        return self.known.data[entry]


def counter(path: str) -> TokenCounter:
    return held(("counts", path), lambda: TokenCounter(path))


def token_counts(docs: DataFrame, path: str, limit: int = 1024) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, 1 << 20):
                texts = ["" if t is None else t for t in part.column("text").to_pylist()]
                n = counter(path).counts(texts)
                sizes = pa.array([len(t.encode()) for t in texts], pa.int64())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), sizes, pa.array(n), pa.array(n > limit)], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")


def op6_token_counts(spark, sf_dir: str) -> DataFrame:
    """All documents with the byte-level vocabulary, against a limit of 1024 tokens."""
    import public_tokenizers

    return token_counts(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_50k.json"))
