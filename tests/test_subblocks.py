"""Candidates of sub-blocks in cells against the join of postings."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockdup.functions.filters import position_filter
from blockdup.functions.order import global_token_frequency, ordered_blocks
from blockdup.functions.tokens import bag_of_tokens, tokenize
from blockdup.operators import cells, detect, index, subblocks
from blockdup.operators.index import full_index, partial_index
from blockdup.sources.io import FREED, stage
from test_cells import corpus

SCHEMA = "block_id long, project_id string, text string"


def blocks_of(spark, seed: int):
    rows = corpus(seed)
    rows += [(1000 + k, "q", rows[k % 7 + 60][2]) for k in range(20)] + [(2000, "p1", "a a a b ab"), (2000, "p1", "b c"), (2001, None, "a b b c"), (2002, None, "a b b c"), (2003, "p1", "b c a a")]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.mark.parametrize("theta, measure, table, held", [(700, "overlap", 1 << 19, 8_000_000), (700, "overlap", 20, 300), (500, "jaccard", 0, 8_000_000), (800, "cosine", 100, 500), (1000, "overlap", 20, 300)])
def test_candidates_as_by_joins(spark, monkeypatch, theta, measure, table, held):
    monkeypatch.setattr(subblocks, "TABLE", table)
    blocks = blocks_of(spark, theta + table)
    postings = partial_index(detect.order_of(blocks), theta, measure)
    want = {tuple(r) for r in detect.candidates(postings, postings, theta, measure, filters=frozenset({"prefix", "size"})).collect()}
    found = [tuple(r) for r in subblocks.candidates(blocks, theta, measure, held=held).collect()]
    assert len(found) == len(set(found)) and set(found) == want and want
    bound = {x for x in want if cells.meets(*(np.array([v], np.int64) for v in (x[4] + min(x[2] - x[5], x[3] - x[6]), x[2], x[3])), theta, measure)[0]}
    assert {tuple(r) for r in subblocks.candidates(blocks, theta, measure, position=True, held=held).collect()} == bound


def test_candidates_are_not_shuffled(spark):
    plan = subblocks.candidates(blocks_of(spark, 3))._jdf.queryExecution().toString().split("== Physical Plan ==")[1]
    assert plan.count("Exchange") == 1 and "Join" not in plan and plan.index("Exchange") > plan.index("MapInArrow")  # sub-blocks alone are sent


@pytest.mark.parametrize("table, held", [(1 << 19, 8_000_000), (20, 300)])
def test_comparisons_are_counted_by_project(spark, monkeypatch, table, held):
    monkeypatch.setattr(subblocks, "TABLE", table)
    blocks = blocks_of(spark, 8)
    ordered = detect.order_of(blocks)
    postings = partial_index(ordered)
    found = detect.candidates(postings, postings, within=True, filters=frozenset({"prefix", "size"})).join(ordered.select(F.col("block_id").alias("b"), "project_id"), "b").collect()
    near = [r.project_id for r in found if (r.seen + min(r.n_b - r.last_b, r.n_c - r.last_c)) * 1000 >= r.n_b * 700]
    f1, f1f3, of = Counter(r.project_id for r in found), Counter(near), Counter(r.project_id for r in ordered.collect())
    assert {tuple(r) for r in subblocks.comparisons(blocks, held=held).collect()} == {(p, of[p], f1[p], f1f3[p]) for p in of}
    assert sum(f1.values()) > sum(f1f3.values()) > 0


WAYS = [(700, "overlap", 1 << 19, 8_000_000), (700, "overlap", 20, 600), (500, "jaccard", 0, 8_000_000), (900, "cosine", 100, 900)]


@pytest.mark.parametrize("theta, measure, table, held", WAYS)
def test_token_comparisons_as_by_merging(spark, monkeypatch, theta, measure, table, held):
    monkeypatch.setattr(subblocks, "TABLE", table)
    monkeypatch.setattr(subblocks, "PACE", 3)
    blocks = blocks_of(spark, theta + table)
    ordered = ordered_blocks(bag_of_tokens(tokenize(blocks)), keys=True)
    postings = partial_index(ordered, theta, measure)
    want = []
    for early in (False, True):
        rows = detect.verify_merge(detect.candidates(postings, postings, theta, measure), ordered, ordered, theta, measure, early_accept=early).collect()
        want.append((sum(r.compared for r in rows), sum(r.n_b * r.n_c for r in rows), len(rows)))
    rows = subblocks.token_comparisons(blocks, theta, measure, held=held).collect()
    got = {c: sum(r[c] for r in rows) for c in ("compared", "early", "nested", "candidates")}
    assert [(got[c], got["nested"], got["candidates"]) for c in ("compared", "early")] == want and want[0][0] > want[1][0] > 0


@pytest.mark.parametrize("theta, measure, table, held", WAYS)
def test_position_bound_alone_as_by_joins(spark, monkeypatch, theta, measure, table, held):
    for name, value in (("TABLE", table), ("PACE", 3), ("BITS", 64 if held < 1000 else 1 << 14), ("DENSE", 10)):
        monkeypatch.setattr(subblocks, name, value)
    blocks = blocks_of(spark, theta + table)
    every = full_index(detect.order_of(blocks))
    found = detect.candidates(every, every, theta, measure, filters=frozenset(), hot=None)
    ok = position_filter(*(F.col(c) for c in ("seen", "last_b", "last_c", "n_b", "n_c")), theta, measure)
    want = found.agg(F.count("*"), F.count(F.when(ok, 1))).first()
    rows = subblocks.position_alone(blocks, theta, measure, held=held, sets=held).collect()
    assert (sum(r.pairs for r in rows), sum(r.within_bound for r in rows)) == tuple(want) and want[0] > want[1] > 0


def test_no_blocks_no_comparisons(spark):
    none = spark.createDataFrame([(1, "p", ""), (2, "p", None)], SCHEMA)
    assert not subblocks.token_comparisons(none).collect() and not any(sum(r) for r in subblocks.position_alone(none).collect())


def test_costs_send_whole_blocks_alone(spark):
    plan = subblocks.token_comparisons(blocks_of(spark, 3))._jdf.queryExecution().toString().split("== Physical Plan ==")[1]
    assert plan.count("Exchange") == 1 and "Join" not in plan


def test_staged_frames_leave_no_shuffle(spark):
    shuffles = lambda: spark._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker().shuffleStatuses().size()
    before = shuffles()
    stage(spark.range(1000).repartition(3, "id"), "kept")
    assert shuffles() == before and spark.conf.get(FREED) == "false"


@pytest.mark.parametrize("theta, measure, table, most", [(700, "overlap", 1 << 19, 8_000_000), (700, "overlap", 20, 600), (500, "jaccard", 0, 900), (800, "cosine", 100, 8_000_000)])
def test_many_blocks_are_looked_up_in_cells(spark, monkeypatch, tmp_path, theta, measure, table, most):
    monkeypatch.setattr(subblocks, "TABLE", table)
    monkeypatch.setattr(subblocks, "matches", lambda *a, f=subblocks.matches: f(*a, most=most))
    blocks = blocks_of(spark, theta + table).where("block_id <> 2000 or project_id = 'p1'")
    repo = index.IndexedRepository.build(blocks.where("project_id = 'p1'"), str(tmp_path / "index"), theta, measure)
    repo.append(blocks.where("project_id = 'p2'"))
    asked = blocks.where("project_id in ('p0', 'q')")
    answers = {}
    for few in (0, 1_000_000):
        monkeypatch.setattr(index, "FEW", few)
        rows = [tuple(r) for r in repo.query(asked).collect()]
        answers[few] = sorted(rows)
        assert len(rows) == len({r[:2] for r in rows})
    assert answers[0] == answers[1_000_000] and any(r[2] > r[3] for r in answers[0]) and any(r[2] < r[3] for r in answers[0])


@pytest.mark.parametrize("table", [1 << 19, 20, 0])
def test_ordered_blocks_as_by_joins(spark, monkeypatch, table):
    monkeypatch.setattr(subblocks, "TABLE", table)
    blocks = blocks_of(spark, 5)
    bag = bag_of_tokens(tokenize(blocks))
    rows = lambda df: sorted((tuple(r) for r in df.collect()), key=str)
    assert rows(subblocks.token_frequencies(blocks)) == rows(global_token_frequency(bag))
    known = subblocks.token_frequencies(blocks.where("project_id = 'p1'"))
    assert rows(subblocks.ordered(blocks, known)) == rows(ordered_blocks(bag, frequencies=known))
    empty = blocks.where("false")
    assert rows(subblocks.ordered(blocks, subblocks.token_frequencies(empty))) == rows(ordered_blocks(bag, frequencies=known.where("false"))) and not rows(subblocks.ordered(empty, known))
