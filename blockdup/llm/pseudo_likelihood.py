"""Documents scored by masked pseudo-likelihood under a bidirectional window network in numpy.

Every word is predicted from the words on both sides of it, itself masked: window embeddings, one hidden
layer, and a softmax in two levels (a class of words, then the word in its class). A document's score is the
sum of the conditional log-probabilities of its words. Words outside the vocabulary are spelled: to the
network's log-probability of "some other word" comes that of each byte given the two before it, and of the
end, by counts over all such words of all documents. So every word has a probability of its own; only as
neighbours do these words look alike.

The vocabulary is counted over all documents. Training covers all documents too: in each round every task
starts from the shared network, learns from its share of the words of each of its documents, and returns its
network; over the rounds every word is a target once. Networks are averaged with the words seen as weights, in
two steps, so the driver gets PARTIALS of them at most. Defined cases: null or empty text has no word and the score 0; a byte never met in spelling has a small
share; rows that repeat an id are documents of their own; other columns are ignored; an empty
table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .texts import LOWER, flat, pieces, span_hashes, words

CLASSES, PER_CLASS = 48, 48
VOCABULARY = CLASSES * PER_CLASS
SIDE, EMBED, HIDDEN = 2, 12, 24
ROUNDS, BATCH, RATE = 2, 2048, 0.15
PARTIALS = 8
#: Bytes and the border of a word; the second byte back by its low bits, which tell letters apart, and the border.
SIGNS, BACK = 257, 33
#: Spelling counts are mixed with those of shorter contexts, which weigh as so many.
WEIGHT = 16.0
SHAPES = {
    "embed": (VOCABULARY + 1, EMBED), "mix": (2 * SIDE, EMBED, HIDDEN), "hidden": (HIDDEN,), "top": (HIDDEN, CLASSES), "top_bias": (CLASSES,),
    "low": (CLASSES, HIDDEN, PER_CLASS), "low_bias": (CLASSES, PER_CLASS),
}
#: Stands beside the first and last words of a text.
EDGE = VOCABULARY


def count_words(docs: DataFrame) -> DataFrame:
    """(word, n): hashes of all lower-case words of all documents with their counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in pieces(batch, 8 << 20):
                raw, offsets = flat(part.column(0))
                low = LOWER[raw]
                starts, ends, _ = words(low, offsets)
                keys, n = np.unique(span_hashes(low, starts, ends).view(np.int64), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(keys), pa.array(n, pa.int64())], names=["word", "n"])

    return docs.select("text").mapInArrow(run, "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))


def vocabulary(docs: DataFrame) -> np.ndarray:
    """Hashes of the most common words, by rank; place 0 is for all others."""
    rows = count_words(docs).orderBy(F.desc("n"), "word").limit(VOCABULARY - 1).collect()
    return np.array([r.word for r in rows], np.int64)


def ids_of(raw: np.ndarray, offsets: np.ndarray, vocab: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(word ids, words before each text)."""
    return read_words(raw, offsets, vocab)[:2]


def read_words(raw: np.ndarray, offsets: np.ndarray, vocab: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(word ids, words before each text, spelling of the words with id 0, signs before each of these)."""
    low = LOWER[raw]
    starts, ends, before = words(low, offsets)
    h = span_hashes(low, starts, ends).view(np.int64)
    if len(vocab):
        order = np.argsort(vocab)
        at = np.minimum(np.searchsorted(vocab, h, sorter=order), len(vocab) - 1)
        rank = order[at]
        ids = np.where(vocab[rank] == h, rank + 1, 0)
    else:
        ids = np.zeros(len(h), np.int64)
    rare = ids == 0
    return ids, before, *spelled(low, starts[rare], ends[rare])


def spelled(low: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(codes, signs before each word): each byte of each word and its end, with the two signs before it."""
    n = ends - starts + 1
    borders = np.zeros(len(n) + 1, np.int64)
    np.cumsum(n, out=borders[1:])
    first, last = borders[:-1], borders[1:] - 1
    at = np.arange(borders[-1])
    at += np.repeat(starts - first, n)
    at[last] = 0
    sign = low[at].astype(np.int32) if len(low) else np.zeros(0, np.int32)
    sign[last] = SIGNS - 1
    one = np.empty_like(sign)
    one[1:] = sign[:-1]
    one[first] = SIGNS - 1
    two = np.empty_like(sign)
    two[1:] = one[:-1]
    two &= 31
    two[one == SIGNS - 1] = BACK - 1
    second = first + 1
    two[second] = BACK - 1  # a word has a byte and its end at least
    return (two * SIGNS + one) * SIGNS + sign, borders


def spelling(counts: np.ndarray) -> np.ndarray:
    """log p(sign | two signs before) for each code, from counts of codes."""
    three = counts.reshape(BACK, SIGNS, SIGNS).astype(np.float64)
    two = three.sum(0)
    one = (two.sum(0) + 1) / (two.sum() + SIGNS)
    two = (two + WEIGHT * one) / (two.sum(1, keepdims=True) + WEIGHT)
    three = (three + WEIGHT * two) / (three.sum(2, keepdims=True) + WEIGHT)
    return np.log(three).astype("<f4").ravel()


def contexts(ids: np.ndarray, before: np.ndarray, places: np.ndarray) -> np.ndarray:
    """[places, 2 SIDE] ids on both sides, EDGE beyond a text."""
    of = np.searchsorted(before, places, side="right") - 1
    out = np.full((len(places), 2 * SIDE), EDGE, np.int64)
    for k, step in enumerate([*range(-SIDE, 0), *range(1, SIDE + 1)]):
        at = places + step
        ok = (at >= before[of]) & (at < before[of + 1])
        out[ok, k] = ids[at[ok]]
    return out


def initial(seed: int = 5) -> dict[str, np.ndarray]:
    r = np.random.default_rng(seed)
    return {k: (np.zeros(s) if "bias" in k or k == "hidden" else r.normal(0, (0.3 if k == "embed" else s[-2] ** -0.5 * 0.5), s)).astype(np.float32) for k, s in SHAPES.items()}


def packed(p: dict[str, np.ndarray]) -> bytes:
    return b"".join(p[k].astype("<f4").tobytes() for k in SHAPES)


def unpacked(raw) -> dict[str, np.ndarray]:
    out, at = {}, 0
    for k, s in SHAPES.items():
        n = int(np.prod(s))
        out[k] = np.frombuffer(raw, "<f4", n, 4 * at).reshape(s).copy()
        at += n
    return out


def unpacked_spelling(raw) -> np.ndarray:
    """The log-probabilities of signs, which stand behind the network."""
    return np.frombuffer(raw, "<f4", offset=4 * sum(int(np.prod(s)) for s in SHAPES.values()))


def tables(p: dict[str, np.ndarray]) -> np.ndarray:
    """What each word adds to the hidden layer at each place of the window: [places, words, hidden]."""
    return np.einsum("ve,keh->kvh", p["embed"], p["mix"])


def hidden_layer(p: dict, context: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hidden layer, embeddings of the whole window side by side)."""
    e = p["embed"][context].reshape(len(context), 2 * SIDE * EMBED)
    return np.tanh(e @ p["mix"].reshape(-1, HIDDEN) + p["hidden"]), e


def class_of(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words of like rank are spread over the classes."""
    return ids % CLASSES, ids // CLASSES


def by_class(target: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[tuple[int, int, int]]]:
    """(order, classes, words in them, (class, from, to) of each class met): rows of one class behind each other."""
    c, w = class_of(target)
    order = np.argsort(c.astype(np.uint8), kind="stable")
    c = c[order]
    cuts = np.searchsorted(c, np.arange(CLASSES + 1)).tolist()
    return order, c, w[order], [(k, a, b) for k, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)) if b > a]


def inner_logits(p: dict, h: np.ndarray, c: np.ndarray, runs: list[tuple[int, int, int]]) -> np.ndarray:
    """Logits of the words of each row's class, rows in order of classes."""
    z = np.empty((len(h), PER_CLASS), np.float32)
    for k, a, b in runs:
        np.matmul(h[a:b], p["low"][k], out=z[a:b])
    z += p["low_bias"][c]
    return z


def _exp(z: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(sum, most) of each row; z becomes its exponentials after the largest is taken off."""
    most = z.max(axis=1, keepdims=True)
    z -= most
    np.exp(z, out=z)
    return z @ np.ones(z.shape[1], np.float32), most[:, 0]


def log_probabilities(p: dict, context: np.ndarray, target: np.ndarray) -> np.ndarray:
    """log p(word | both sides) for each row."""
    order, c, w, runs = by_class(target)
    h, rows = hidden_layer(p, context[order])[0], np.arange(len(order))
    logs = np.zeros(len(order))
    for z, y in ((h @ p["top"] + p["top_bias"], c), (inner_logits(p, h, c, runs), w)):
        chosen = z[rows, y]
        total, most = _exp(z)
        logs += chosen - most - np.log(total)
    out = np.empty(len(order))
    out[order] = logs
    return out


def learn(p: dict, context: np.ndarray, target: np.ndarray, rate: float) -> None:
    """One step of gradient descent over a batch, in place."""
    n = len(target)
    order, c, w, runs = by_class(target)
    context, rows = context[order], np.arange(n)
    h, e = hidden_layer(p, context)
    top, low = h @ p["top"] + p["top_bias"], inner_logits(p, h, c, runs)
    for z, y in ((top, c), (low, w)):
        z /= _exp(z)[0][:, None]
        z[rows, y] -= 1
    back, inner = top @ p["top"].T, np.empty_like(h)
    p["top"] -= rate / n * (h.T @ top)
    p["top_bias"] -= rate / n * top.sum(0)
    scale = rate * (CLASSES / 4) / n  # a class sees a share of the batch
    for k, a, b in runs:
        np.matmul(low[a:b], p["low"][k].T, out=inner[a:b])
        p["low"][k] -= scale * (h[a:b].T @ low[a:b])
    p["low_bias"][[k for k, _, _ in runs]] -= scale * np.add.reduceat(low, [a for _, a, _ in runs], axis=0)
    d = (back + inner) * (1 - h * h)
    p["hidden"] -= rate / n * d.sum(0)
    mixed = p["mix"].reshape(-1, HIDDEN)
    grad = d @ mixed.T
    mixed -= rate / n * (e.T @ d)
    at = (context[:, :, None] * EMBED + np.arange(EMBED)).ravel()
    p["embed"] -= np.bincount(at, grad.ravel() * (rate * 8 / n), (VOCABULARY + 1) * EMBED).reshape(-1, EMBED).astype(np.float32)


def targets(before: np.ndarray, turn: int, rounds: int) -> np.ndarray:
    """Places learned from in one round: in each text from word `turn` on every rounds-th, whatever task it is in."""
    n = np.diff(before)
    return np.flatnonzero((np.arange(n.sum()) - np.repeat(before[:-1], n)) % rounds == turn)


def _rounds(docs: DataFrame, vocab: np.ndarray, shared: bytes, rate: float, turn: int, rounds: int) -> tuple[bytes, np.ndarray]:
    """One round: (weighted mean of the networks trained in all tasks, counts of spelling codes, made in the first round)."""
    schema, codes = "n double, p binary, code binary, times binary", BACK * SIGNS * SIGNS

    def made(n: float, p: bytes, counts: np.ndarray) -> pa.RecordBatch:
        met = np.flatnonzero(counts)
        return pa.RecordBatch.from_arrays([pa.array([n]), *(pa.array([x], pa.binary()) for x in (p, met.astype("<i4").tobytes(), counts[met].astype("<i8").tobytes()))], names=["n", "p", "code", "times"])

    def add(counts: np.ndarray, code, times) -> None:
        counts[np.frombuffer(code, "<i4")] += np.frombuffer(times, "<i8")

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, seen, counts = unpacked(shared), 0, np.zeros(codes, np.int64)
        for batch in batches:
            for part in pieces(batch):
                ids, before, signs, _ = read_words(*flat(part.column(0)), vocab)
                if turn == 0:
                    counts += np.bincount(signs, minlength=codes)
                places = targets(before, turn, rounds)
                context, target, steps = contexts(ids, before, places), ids[places], -(-len(places) // BATCH)
                for k in range(steps):  # each batch is spread over the piece
                    learn(p, context[k::steps], target[k::steps], rate)
                seen += len(places)
        if seen:
            yield made(float(seen), packed(p), counts)

    def mean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total, counts = 0.0, None, np.zeros(codes, np.int64)
        for batch in batches:
            for k in range(batch.num_rows):
                m, p = batch.column(0)[k].as_py(), np.frombuffer(batch.column(1)[k].as_buffer(), "<f4").astype(np.float64)
                total = p * m if total is None else total + p * m
                n += m
                add(counts, batch.column(2)[k].as_buffer(), batch.column(3)[k].as_buffer())
        if n:
            yield made(n, (total / n).astype("<f4").tobytes(), counts)

    rows = docs.select("text").mapInArrow(local, schema).repartition(PARTIALS).mapInArrow(mean, schema).collect()
    counts = np.zeros(codes, np.int64)
    if not rows:
        return shared, counts
    for r in rows:
        add(counts, bytes(r.code), bytes(r.times))
    n = sum(r.n for r in rows)
    return sum(np.frombuffer(bytes(r.p), "<f4").astype(np.float64) * (r.n / n) for r in rows).astype("<f4").tobytes(), counts


def fit(docs: DataFrame, rounds: int = ROUNDS) -> tuple[np.ndarray, bytes]:
    """(vocabulary, network with the spelling behind it)."""
    vocab, shared, counts = vocabulary(docs), packed(initial()), 0
    for k in range(rounds):
        shared, met = _rounds(docs, vocab, shared, RATE / (k + 1), k, rounds)
        counts = counts + met
    return vocab, shared + spelling(counts).tobytes()


def score(docs: DataFrame, vocab: np.ndarray, network: bytes) -> DataFrame:
    """(doc_id, n_words, log_likelihood, per_word): sums over all words of whole texts; per_word is null without words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, letters = unpacked(network), unpacked_spelling(network)
        for batch in batches:
            for part in pieces(batch, 1 << 20):
                ids, before, signs, borders = read_words(*flat(part.column("text")), vocab)
                logs = np.empty(len(ids))
                for at in range(0, len(ids), 1 << 13):
                    places = np.arange(at, min(len(ids), at + (1 << 13)))
                    logs[places] = log_probabilities(p, contexts(ids, before, places), ids[places])
                if len(signs):
                    logs[ids == 0] += np.add.reduceat(letters[signs].astype(np.float64), borders[:-1])
                sums = np.array([logs[a:b].sum() for a, b in zip(before[:-1].tolist(), before[1:].tolist(), strict=True)])
                n = np.diff(before)
                per = pa.array(sums / np.maximum(n, 1), mask=n == 0)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(n, pa.int64()), pa.array(sums), per], names=["doc_id", "n_words", "log_likelihood", "per_word"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_words long, log_likelihood double, per_word double")


def op7_pseudo_likelihood(spark, sf_dir: str) -> DataFrame:
    """All documents: (doc_id, n_words, log_likelihood, per_word)."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return score(docs, *fit(docs))
