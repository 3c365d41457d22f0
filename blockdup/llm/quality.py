"""Quality by positive-unlabelled learning with the non-negative risk estimator.

A small network is trained on trusted positives (label 1) and unlabelled web text (all documents), both from
outside fold 0; no label 0 is used. With class prior p and loss l, the risk is
p E_P[l(+)] + max(0, E_U[l(-)] - p E_P[l(-)]); when the second part falls below zero the step goes against it,
which keeps the network from memorising U. The prior is estimated between rounds: the share of U over a cut,
over the share of P there, at the cut where the upper bound of that ratio is least. Raw output 0, where the
estimated risk sees both classes alike, becomes the score THRESHOLD.

Features are of the text alone: trigrams of character classes, and shapes of words and lines. They are written
once for all documents outside fold 0; means, scales, training and the prior read all of them there. In each
round every task starts from the shared network and works through its rows; networks are averaged with the
rows as weights. Positives are a bounded sample (POSITIVES ids). Defined cases: null text counts as empty, and
empty texts get a score as any other; null labels teach nothing, nor does an id with both labels; of the rows
of a repeated id one text counts as positive; without a positive or any text every score is 0.5; other columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.io import stage, unstage
from .folds import bounded, held_out, trainable
from .texts import LOWER, flat, held, pieces, span_hashes, words

POSITIVES = 6_000
THRESHOLD = 0.3
ROUNDS, EPOCHS, STEPS, BATCH, RATE, DECAY = 3, 8, 60, 512, 5e-3, 1e-2
#: Rows of a training task at least, where there are as many; rows of features made at once.
TASK_ROWS = 4096
#: Networks, sums and counts reach the driver in so many parts.
PARTIALS = 8
HIDDEN = 24
_KINDS = 8
_CLASS = np.full(256, 7, np.uint8)  # other symbols
_CLASS[128:] = 2
for _k, _chars in ((0, "abcdefghijklmnopqrstuvwxyz"), (1, "ABCDEFGHIJKLMNOPQRSTUVWXYZ"), (3, "0123456789"), (4, " \t\r"), (5, "\n"), (6, ".,;:'\"!?-()")):
    _CLASS[[ord(c) for c in _chars]] = _k
SHAPES = 12
WIDTH = _KINDS**3 + SHAPES


def _distinct(keys: np.ndarray, before: np.ndarray) -> np.ndarray:
    """Distinct keys in each run of a row of keys."""
    return np.array([len(np.unique(keys[a:b])) for a, b in zip(before[:-1].tolist(), before[1:].tolist(), strict=True)], np.float64)


def features(raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """[texts, WIDTH] for flat texts."""
    n, sizes = len(offsets) - 1, np.diff(offsets)
    out = np.zeros((n, WIDTH), np.float32)
    if not n:
        return out
    kinds = _CLASS[raw].astype(np.int64)
    of = np.repeat(np.arange(n), sizes)
    if len(raw) > 2:
        same = of[:-2] == of[2:]
        code = (of[:-2] * _KINDS + kinds[:-2]) * _KINDS * _KINDS + kinds[1:-1] * _KINDS + kinds[2:]
        grams = np.bincount(code[same], minlength=n * _KINDS**3).reshape(n, -1)
        out[:, : _KINDS**3] = np.sqrt(grams / np.maximum(1, sizes - 2)[:, None])
    low = LOWER[raw]
    starts, ends, before = words(low, offsets)
    h = span_hashes(low, starts, ends)
    count = np.maximum(1, np.diff(before)).astype(np.float64)
    total = lambda x: np.diff(np.concatenate(([0], np.cumsum(x)))[before])
    again = np.zeros(len(h))
    again[1:] = h[1:] == h[:-1]
    tail = np.zeros(len(h))
    if len(h):
        tail = (_CLASS[raw[ends - 1]] == 7).astype(float)
    line = np.zeros(256, bool)
    line[10] = True
    ls, le, lb = words(raw, offsets, line)
    lines = np.maximum(1, np.diff(lb)).astype(np.float64)
    per = lambda k: np.bincount(of, weights=kinds == k, minlength=n) / np.maximum(1, sizes)
    shapes = [
        total(again) / count, _distinct(h, before) / np.sqrt(count), _distinct(h, before) / count, total(ends - starts) / count, total(tail) / count, np.log1p(sizes),
        np.log1p(count), _distinct(span_hashes(raw, ls, le), lb) / lines, np.log1p(lines), per(1), per(7), per(3),
    ]
    out[:, _KINDS**3 :] = np.stack(shapes, axis=1)
    return out


def feature_rows(docs: DataFrame) -> DataFrame:
    """(doc_id, x) of documents: features as 16-bit numbers, null text as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held(("quality",), dict)  # another operator's large object goes
        for batch in batches:
            for part in pieces(batch, 1 << 20):
                x = features(*flat(part.column("text"))).astype(np.float16)
                cells = pa.FixedSizeBinaryArray.from_buffers(pa.binary(2 * WIDTH), len(x), [None, pa.py_buffer(x.tobytes())]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), cells], names=["doc_id", "x"])

    kind = dict(docs.dtypes)["doc_id"]
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, x binary")


def matrix(column: pa.Array) -> np.ndarray:
    """Feature cells to numbers, [rows, WIDTH]."""
    return np.frombuffer(b"".join([c.as_buffer() for c in column]), np.float16).reshape(-1, WIDTH).astype(np.float32)


def initial(width: int = WIDTH, hidden: int = HIDDEN, seed: int = 11) -> list[np.ndarray]:
    """One hidden layer, tanh, one output."""
    r = np.random.default_rng(seed)
    return [a.astype(np.float32) for a in (r.normal(0, width**-0.5, (width, hidden)), np.zeros(hidden), r.normal(0, hidden**-0.5, hidden), np.zeros(1))]


def forward(p: list[np.ndarray], x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    h = np.tanh(x @ p[0] + p[1])
    return h, h @ p[2] + p[3][0]


def packed(p: list[np.ndarray]) -> bytes:
    return b"".join(a.astype("<f4").tobytes() for a in p)


def unpacked(raw, width: int = WIDTH, hidden: int = HIDDEN) -> list[np.ndarray]:
    v = np.frombuffer(raw, "<f4")
    ends = np.cumsum([width * hidden, hidden, hidden, 1])
    return [v[: ends[0]].reshape(width, hidden).copy(), *(v[a:b].copy() for a, b in zip(ends[:-1], ends[1:], strict=True))]


class Descent:
    """A network with the moving means that its steps go by."""

    def __init__(self, p: list[np.ndarray]):
        self.p = [a.copy() for a in p]
        self.m = [[np.zeros_like(a), np.zeros_like(a)] for a in p]
        self.t = 0

    def gradient(self, x: np.ndarray, h: np.ndarray, d: np.ndarray) -> list[np.ndarray]:
        d = d.astype(np.float32)
        back = d[:, None] * self.p[2] * (1 - h * h)
        return [x.T @ back, back.sum(0), h.T @ d, np.array([d.sum()], np.float32)]

    def step(self, g: list[np.ndarray], rate: float) -> None:
        self.t += 1
        for a, b, m in zip(self.p, g, self.m, strict=True):
            b = b + DECAY * a
            m[0] = 0.9 * m[0] + 0.1 * b
            m[1] = 0.999 * m[1] + 0.001 * b * b
            a -= (rate * (m[0] / (1 - 0.9**self.t)) / (np.sqrt(m[1] / (1 - 0.999**self.t)) + 1e-8)).astype(np.float32)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def risk(zp: np.ndarray, zu: np.ndarray, prior: float) -> tuple[float, float]:
    """(positive part, negative part) of the unbiased risk with the sigmoid loss l(z, y) = sigmoid(-y z)."""
    return prior * sigmoid(-zp).mean(), sigmoid(zu).mean() - prior * sigmoid(zp).mean()


def learn(net: Descent, positive: np.ndarray, unlabelled: np.ndarray, prior: float, steps: int, rate: float, r: np.random.Generator, batch: int = BATCH) -> None:
    """Steps down the non-negative risk over mini-batches, in place."""
    slope = lambda z: sigmoid(z) * (1 - sigmoid(z))
    at, order = 0, r.permutation(len(unlabelled))
    for _ in range(steps):
        if at >= len(order):
            at, order = 0, r.permutation(len(unlabelled))
        u = unlabelled[order[at : at + batch]]
        p = positive[r.integers(0, len(positive), min(batch, len(positive)))]
        at += batch
        (hp, zp), (hu, zu) = forward(net.p, p), forward(net.p, u)
        if risk(zp, zu, prior)[1] >= 0:
            dp, du = -2 * prior * slope(zp) / len(p), slope(zu) / len(u)
        else:  # walk back: the negative part alone, upwards
            dp, du = prior * slope(zp) / len(p), -slope(zu) / len(u)
        net.step([a + b for a, b in zip(net.gradient(p, hp, dp), net.gradient(u, hu, du), strict=True)], rate)


#: Cuts of raw outputs at which unlabelled rows are counted.
CUTS = np.linspace(-12, 12, 481)


def estimated_prior(zp: np.ndarray, counts: np.ndarray, least: float = 0.05) -> float:
    """Share of positives in U, from raw outputs of P and the number of rows of U between the CUTS (under the first one, ..., over the last)."""
    n = counts.sum()
    over_u = (n - np.cumsum(counts)[:-1]) / n
    over_p = 1 - np.searchsorted(np.sort(zp), CUTS) / len(zp)
    doubt = lambda k: np.sqrt(np.log(40) / (2 * k))
    ratio = (over_u + doubt(n)) / np.maximum(over_p - doubt(len(zp)), 1e-6)
    ratio[over_p < least] = np.inf
    k = int(np.argmin(ratio))
    return float(np.clip(over_u[k] / max(over_p[k], 1e-6), 0.01, 0.99))


def _summed(rows: DataFrame, make, schema: str = "n double, v binary") -> list[tuple[float, np.ndarray]]:
    """make(batches) gives one (weight, numbers) a task; (weight, sum) of at most PARTIALS groups of tasks."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held(("quality",), dict)
        n, v = make(batches)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([float(n)]), pa.array([v.astype("<f8").tobytes()], pa.binary())], names=["n", "v"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, total = 0.0, 0.0
        for batch in batches:
            for k in range(batch.num_rows):
                n, total = n + batch.column(0)[k].as_py(), total + np.frombuffer(batch.column(1)[k].as_buffer(), "<f8")
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([total.tobytes()], pa.binary())], names=["n", "v"])

    parts = rows.select("x").mapInArrow(each, schema).repartition(PARTIALS).mapInArrow(add, schema).collect()
    return [(r.n, np.frombuffer(bytes(r.v), "<f8")) for r in parts]


def positives(rows: DataFrame, labels: DataFrame, most: int) -> np.ndarray:
    """Features of about `most` documents of label 1, one row an id, in the order of ids."""
    marks = labels.where(trainable() & F.col("quality").isin(0, 1)).groupBy("doc_id").agg(F.min("quality").alias("a"), F.max("quality").alias("b"))
    # at most about `most` ids, a documented bound: small enough to go to every task
    ids = bounded(marks.where("a = 1 and b = 1").select("doc_id"), most)
    known = rows.join(F.broadcast(ids), "doc_id").groupBy("doc_id").agg(F.min("x").alias("x")).collect()
    return matrix(pa.array([bytes(r.x) for r in sorted(known)], pa.binary())) if known else np.zeros((0, WIDTH), np.float32)


def fit(docs: DataFrame, labels: DataFrame, most: int = POSITIVES, rounds: int = ROUNDS) -> dict:
    """Everything scoring needs: mean, scale, network, prior."""
    rows = rows_of = stage(feature_rows(docs.where(trainable())), "features")
    known = positives(rows, labels, most)

    def moments(batches: Iterator[pa.RecordBatch]) -> tuple[int, np.ndarray]:
        n, total = 0, np.zeros((2, WIDTH))
        for batch in batches:
            x = matrix(batch.column(0)).astype(np.float64)
            n, total = n + len(x), total + [x.sum(0), (x * x).sum(0)]
        return n, total.ravel()

    sums = _summed(rows, moments)
    n = sum(k for k, _ in sums)
    if not n or not len(known):
        return {"prior": 0.5, "net": None}
    mean, square = (sum(v for _, v in sums) / n).reshape(2, WIDTH)
    scale = np.sqrt(np.maximum(0, square - mean**2)) + 0.02
    mean, scale = mean.astype(np.float32), scale.astype(np.float32)
    known = clean(known, mean, scale)
    sent = docs.sparkSession.sparkContext.broadcast(known)
    rows = rows.coalesce(max(1, int(n) // TASK_ROWS))
    net, prior = initial(), 0.5
    for k in range(rounds):

        def train(batches: Iterator[pa.RecordBatch], net=net, prior=prior, rate=RATE / (k + 1), seed=k) -> tuple[int, np.ndarray]:
            mine, seen, r = Descent(net), 0, np.random.default_rng(seed)
            for batch in batches:
                u = clean(matrix(batch.column(0)), mean, scale)
                if len(u):
                    learn(mine, sent.value, u, prior, min(STEPS, EPOCHS * -(-len(u) // BATCH)), rate, r)
                seen += len(u)
            return seen, np.frombuffer(packed(mine.p), "<f4") * float(seen)

        def count(batches: Iterator[pa.RecordBatch]) -> tuple[int, np.ndarray]:
            total = np.zeros(len(CUTS) + 1)
            for batch in batches:
                z = forward(net, clean(matrix(batch.column(0)), mean, scale))[1]  # noqa: B023  used before the next round
                total += np.bincount(np.searchsorted(CUTS, z, side="right"), minlength=len(total))
            return int(total.sum()), total

        net = unpacked((sum(v for _, v in _summed(rows, train)) / n).astype("<f4").tobytes())
        prior = estimated_prior(forward(net, known)[1], sum(v for _, v in _summed(rows, count)))
    sent.destroy()
    unstage(rows_of)
    return {"prior": prior, "net": net, "mean": mean, "scale": scale}


def clean(x: np.ndarray, mean: np.ndarray, scale: np.ndarray) -> np.ndarray:
    return np.clip((x - mean) / scale, -6, 6)


def scores(model: dict, x: np.ndarray) -> np.ndarray:
    if model["net"] is None:
        return np.full(len(x), model["prior"])
    z = forward(model["net"], clean(x, model["mean"], model["scale"]))[1].astype(np.float64)
    return np.where(z >= 0, np.maximum(THRESHOLD, sigmoid(z / 2 + _CENTRE)), np.minimum(_BELOW, sigmoid(z / 2 + _CENTRE)))


#: Puts a raw output of 0 at the threshold; the largest score under it.
_CENTRE, _BELOW = float(np.log(THRESHOLD / (1 - THRESHOLD))), float(np.nextafter(THRESHOLD, 0))


def score(docs: DataFrame, model: dict) -> DataFrame:
    """The columns of docs with score and predicted added."""
    fields = docs.drop("score", "predicted")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in fields.schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held(("quality",), dict)  # another operator's large object goes
        for batch in batches:
            for part in pieces(batch, 1 << 20):
                s = scores(model, features(*flat(part.column("text"))).astype(np.float16).astype(np.float32))
                yield part.append_column("score", pa.array(s)).append_column("predicted", pa.array((s >= THRESHOLD).astype(np.int32)))

    return fields.mapInArrow(run, f"{schema}, score double, predicted int")


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Documents predicted to be of quality, with their own columns only."""
    return score(docs, fit(docs, labels)).where("predicted = 1").select(*docs.columns)


def op1_positive_unlabelled(spark, sf_dir: str) -> DataFrame:
    """All documents: (doc_id, held_out, score, predicted)."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs.select("doc_id", "text"), model).select("doc_id", held_out().alias("held_out"), "score", "predicted")
