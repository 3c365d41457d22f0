"""Detection in cells against every pair by brute force."""

import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockdup.operators import cells, detect


def corpus(seed: int, rows: int = 120) -> list[tuple[int, str, str]]:
    r = random.Random(seed)
    words = [f"w{k}" for k in range(400)]
    texts: list[list[str]] = []
    for _ in range(rows):
        if texts and r.random() < 0.6:
            t = list(r.choice(texts))
            for _ in range(r.randrange(0, max(1, len(t) // 3) + 1)):
                if t and r.random() < 0.5:
                    t.pop(r.randrange(len(t)))
                else:
                    t.insert(r.randrange(len(t) + 1), r.choice(words))
        else:
            t = [words[min(399, int(r.paretovariate(0.6)) - 1)] for _ in range(r.choice((0, 1, 2, 5, 9, 30, 80, 200)))]
        texts.append(t)
    return [(k + 1, f"p{k % 3}", " ".join(t)) for k, t in enumerate(texts)]


def brute(rows, theta, measure, strict=False):
    bags, out = {i: Counter(t.split()) for i, _, t in rows}, set()
    for b, x in bags.items():
        for c, y in bags.items():
            n_b, n_c, o = x.total(), y.total(), (x & y).total()
            if b == c or not o or (n_b, -b) < (n_c, -c):
                continue
            if measure == "overlap":
                ok = o > -(-n_b * theta // 1000) if strict else o * 1000 >= n_b * theta
            elif measure == "jaccard":
                ok = o * (1000 + theta) >= (n_b + n_c) * theta
            else:
                ok = o * o * 1_000_000 >= n_b * n_c * theta * theta
            if ok:
                out.add((b, c, n_b, n_c, o))
    return out


@pytest.mark.parametrize("theta, measure, options", [
    (700, "overlap", {}), (500, "overlap", {}), (1000, "overlap", {}), (700, "jaccard", {}), (700, "cosine", {}), (300, "cosine", {}),
    (700, "overlap", {"strict": True}), (700, "overlap", {"min_shared": 1}), (700, "overlap", {"min_shared": 8})])
def test_as_brute_force(spark, theta, measure, options):
    rows = corpus(theta)
    got = detect.detect_clones(spark.createDataFrame(rows, "block_id long, project_id string, text string"), theta, measure, **options)
    assert {tuple(r)[:5] for r in got.collect()} == brute(rows, theta, measure, options.get("strict", False))


@pytest.mark.parametrize("held, told", [(200, 1_000_000), (900, 0)])
def test_split_cells_and_untold_copies_lose_nothing(spark, monkeypatch, held, told):
    rows = corpus(5)
    rows += [(1000 + k, "q", rows[k % 7 + 60][2]) for k in range(40)]
    monkeypatch.setattr(cells, "TOLD", told)
    blocks = spark.createDataFrame(rows, "block_id long, project_id string, text string")
    pairs, members = cells.find(blocks, held=held)
    reps = {r.block_id: r.rep for r in members.collect()}
    assert set(reps) == {i for i, _, t in rows if t}
    want = {p for p in brute(rows, 700, "overlap") if reps[p[0]] == p[0] and reps[p[1]] == p[1]}
    found = [tuple(r) for r in pairs.collect()]
    assert len(found) == len(set(found)) and set(found) == want
    assert all(reps[b] == reps[c] for b, c, n, m, o in brute(rows, 1000, "overlap") if n == m == o)


def test_rows_of_one_id_are_one_block(spark):
    blocks = spark.createDataFrame([(1, "p", "a b c d"), (1, "p", "e f g h"), (2, "p", "a b c d e f g x"), (3, None, "")], "block_id long, project_id string, text string")
    assert [tuple(r)[:5] for r in detect.detect_clones(blocks).collect()] == [(1, 2, 8, 8, 7)]


def test_pairs_shuffle_no_postings(spark):
    rows = corpus(9)
    pairs, _ = cells.find(spark.createDataFrame(rows, "block_id long, project_id string, text string"))
    assert "Exchange" not in pairs._jdf.queryExecution().toString()
    assert pairs.where(F.col("overlap") > F.col("n_c")).count() == 0


@pytest.mark.parametrize("most", [1, 60, 10_000])
def test_groups_of_any_length_find_the_same(monkeypatch, most):
    for name in ("INDEXED", "ASKED", "MATCHED"):
        monkeypatch.setattr(cells, name, most)
    rows, held = corpus(3), cells.Held()
    for block_id, _, text in rows:
        bag = sorted(Counter(text.split()).items())
        if bag:
            tokens = np.array([int(t[1:]) for t, _ in bag], "<i8").view(np.uint8).reshape(-1, 8)[:, :7].tobytes()
            held.add(3, block_id, sum(f for _, f in bag), repr(bag).encode(), tokens, zlib.compress(np.array([f for _, f in bag], "<i4").tobytes()))
    kept = [(i, p, t) for i, p, t in rows if i in held.id]
    found = [tuple(r.values()) for batch in cells._search(held, 700, "overlap", False, 16) for r in batch.to_pylist()]
    assert len(found) == len(set(found)) and set(found) == brute(kept, 700, "overlap")


def test_bags_are_kept_by_number(monkeypatch):
    monkeypatch.setattr(cells, "NUMBERED", 3)  # numbers are given in many steps
    held, bags = cells.Held(), [{5: 1, 9: 300}, {9: 2, 7: 1}, {5: 70_000}]
    for k, bag in enumerate(bags):
        tokens = np.array(list(bag), "<i8").view(np.uint8).reshape(-1, 8)[:, :7].tobytes()
        held.add(3, k, sum(bag.values()), bytes([k]), tokens, zlib.compress(np.array(list(bag.values()), "<i4").tobytes()))
    held.close()
    assert held.tokens.tolist() == [0, 1, 1, 2, 0] and held.freqs.tolist() == [1, 300, 2, 1, 70_000] and held.tokens.itemsize == 4
    element, where = held.postings(np.array([0, 1]), np.array([3, 2, 0]))
    assert sorted(zip(where.tolist(), element.tolist(), strict=True)) == [(0, 0), (0, 1), (0, 3), (1, 1), (1, 3)]


@pytest.mark.parametrize("theta, measure, strict", [(700, "overlap", False), (700, "overlap", True), (500, "jaccard", False), (300, "cosine", False)])
def test_every_pair_is_compared_in_cells(spark, monkeypatch, theta, measure, strict):
    monkeypatch.setattr(cells, "ROWS", 3)
    monkeypatch.setattr(cells, "COLUMNS", 7)
    monkeypatch.setattr(cells, "ASKED", 50)
    rows = corpus(theta + strict)
    held = cells.Held()
    for block_id, _, text in rows:
        bag = sorted(Counter(text.split()).items())
        if bag:
            tokens = np.array([int(t[1:]) for t, _ in bag], "<i8").view(np.uint8).reshape(-1, 8)[:, :7].tobytes()
            held.add(3, block_id, sum(f for _, f in bag), repr(bag).encode(), tokens, zlib.compress(np.array([f for _, f in bag], "<i4").tobytes()))
    kept = [(i, p, t) for i, p, t in rows if i in held.id]
    found = [tuple(r.values()) for batch in cells._compare(held, theta, measure, strict) for r in batch.to_pylist()]
    assert len(found) == len(set(found)) and set(found) == brute(kept, theta, measure, strict)
    pairs = detect.detect_clones(spark.createDataFrame(rows, "block_id long, project_id string, text string"), theta, measure, strict=strict, every=True)
    assert {tuple(r)[:5] for r in pairs.collect()} == brute(rows, theta, measure, strict)


@pytest.mark.parametrize("coded", [0, 40, 1 << 16])
def test_common_tokens_travel_as_codes_and_come_back(monkeypatch, coded):
    r = np.random.default_rng(coded)
    tokens = np.unique(r.integers(0, 1 << 56, 300))
    tokens[1] = tokens[0] + cells.SLOTS  # these share a counter
    tokens = np.unique(tokens)
    levels = np.zeros(cells.SLOTS, np.uint8)
    levels[tokens & (cells.SLOTS - 1)] = r.integers(0, 200, len(tokens))
    common = tokens[:coded][np.argsort(levels[tokens[:coded] & (cells.SLOTS - 1)], kind="stable")]
    bags = [np.sort(r.choice(tokens, k, replace=False)) for k in (1, 7, 8, 200)]
    batch = cells.pa.RecordBatch.from_pydict({"block_id": [0, 1, 2, 3], "codes": cells.pa.array([b.tolist() for b in bags], cells.pa.list_(cells.pa.int64()))})
    sizes = np.zeros(256, np.int64)
    for b in bags:
        sizes[np.searchsorted(cells.edges(), len(b), "right") - 1] += len(b)
    held, width = cells.Held(common), 0
    for out in cells._dealt(levels, cells.Cells(sizes, 700, "overlap"), np.zeros(0, np.int64), common)([batch]):
        for _, *row in zip(*(out.column(k).to_pylist() for k in range(8)), strict=True):
            held.add(*row)
            width += len(row[4])
    held.close()
    seen = held.numbers.uniques.to_array()[held.tokens]
    got = dict(zip(held.id, np.split(seen, held.at[1:-1]), strict=True))
    assert {k: got[k].tolist() for k in got} == {k: b[np.argsort(levels[b & (cells.SLOTS - 1)], kind="stable")].tolist() for k, b in enumerate(bags)}
    assert (width <= 7 * 4) if coded > 300 else width > 7 * 100  # of two tokens that share a counter one has no code


@pytest.mark.parametrize("theta, measure, strict", [(700, "overlap", False), (700, "overlap", True), (500, "jaccard", False), (700, "cosine", False)])
def test_early_acceptance_decides_the_same_and_reads_less(spark, monkeypatch, theta, measure, strict):
    monkeypatch.setattr(cells, "PACE", 2)
    rows, held, read = corpus(theta + 1), cells.Held(), [0]
    for block_id, _, text in rows:
        bag = sorted(Counter(text.split()).items())
        if bag:
            tokens = np.array([int(t[1:]) for t, _ in bag], "<i8").view(np.uint8).reshape(-1, 8)[:, :7].tobytes()
            held.add(3, block_id, sum(f for _, f in bag), repr(bag).encode(), tokens, zlib.compress(np.array([f for _, f in bag], "<i4").tobytes()))
    want = {p[:4]: p[4] for p in brute([x for x in rows if x[0] in held.id], theta, measure, strict)}
    given = held.rows

    def counted(blocks, *part):
        at, of = given(blocks, *part)
        read[0] += len(at)
        return at, of

    held.rows = counted
    found = [tuple(r.values()) for batch in cells._search(held, theta, measure, strict, 1, True, True) for r in batch.to_pylist()]
    lazy, read[0] = read[0], 0
    assert len(found) == len(want) and all(cells.meets(*(np.array([x], np.int64) for x in (o, n, m)), theta, measure, strict)[0] and o <= want[b, c, n, m] for b, c, n, m, o in found)
    assert len(list(cells._search(held, theta, measure, strict, 1, True))) and lazy < read[0]
    pairs = detect.detect_clones(spark.createDataFrame(rows, "block_id long, project_id string, text string"), theta, measure, strict=strict, early_accept=True)
    assert {tuple(r)[:4] for r in pairs.collect()} == {p[:4] for p in brute(rows, theta, measure, strict)}


def test_the_survey_names_common_tokens_in_the_order(spark):
    blocks = spark.createDataFrame(corpus(11), "block_id long, project_id string, text string")
    levels, _, common, _ = cells.survey(cells.hashed(blocks))
    words = {w for _, _, t in corpus(11) for w in t.split()}
    assert len(common) == len(set(common.tolist())) == len(words)
    assert (np.diff(levels[common & (cells.SLOTS - 1)].astype(int)) >= 0).all()
