"""The further queries against DuckDB on the smallest tables, and what SQL cannot say."""

import duckdb
import pandas as pd
import pytest

import __spark_entry__ as e
from blockdup.operators import blocks, relational
from blockdup.plans import queries as library
from blockdup.plans import surfaces, workloads

SF = "/root/testdata/sf0.001"
NAMES = [n for n, f in library.QUERIES.items() if n in library.ORACLES and f.__module__ in (workloads.__name__, surfaces.__name__)]


def plain(df: pd.DataFrame) -> list[tuple]:
    df = df[sorted(df.columns)]
    return sorted((tuple(None if pd.isna(x) else round(x, 9) if isinstance(x, float) else x for x in r) for r in df.itertuples(index=False)), key=str)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", NAMES)
def test_oracle(spark, duck, name):
    assert plain(e.queries()[name](spark, SF).toPandas()) == plain(duck.execute(e.oracle_sql()[name]).df())


def test_windows_reach_the_last_line(spark):
    docs = spark.createDataFrame([(1, "\n".join("abcdefg"), "s"), (2, "x", "s")], "doc_id long, text string, source string")
    spans = lambda df: sorted((r.file_id, r.start_line, r.end_line) for r in df.collect())
    assert spans(blocks.line_group_blocks(docs, 3)) == [(1, 1, 3), (1, 4, 6), (1, 7, 7), (2, 1, 1)]
    assert spans(blocks.window_blocks(docs, 3, 2)) == [(1, 1, 3), (1, 3, 5), (1, 5, 7), (2, 1, 1)]
    assert spans(blocks.window_blocks(docs, 2, 5)) == [(1, 1, 2), (1, 6, 7), (2, 1, 1)]


def test_near_misses(spark):
    got = {(r.kind, r.detector): r.detected for r in e.queries()["near_miss_kinds"](spark, SF).collect()}
    assert all(got[k, "bag"] for k, d in got if d == "bag")
    assert not got["statements_swapped", "token_runs"] and not got["loop_rewritten", "token_runs"]


@pytest.mark.parametrize("name", ["whole_repository_seconds", "lookup_latency", "approximate_by_source"])
def test_rows(spark, name):
    assert e.queries()[name](spark, SF).count() > 0


def test_sizes_are_counted_without_pairs(spark):
    sizes = [(k, n) for k, n in enumerate([1, 1, 9, 10, 10, 11, 90, 100, 111, 112, 1000])]
    got = {r.block_id: r.partners for r in relational.size_band_counts(spark.createDataFrame(sizes, "block_id long, n int"), 900).collect()}
    assert got == {k: sum(j != k and min(n, m) * 1000 >= max(n, m) * 900 for j, m in sizes) for k, n in sizes}


def test_sample_sizes_read_the_table(spark, duck):
    got = e.queries()["sample_size"](spark, SF)
    assert plain(got.toPandas()) == plain(duck.execute(e.oracle_sql()["sample_size"]).df())
    assert {r.reports for r in got.where("blocks <= 10").collect()} <= set(range(1, 11))


def test_near_misses_are_made_of_every_part(spark):
    parts = spark.read.parquet(f"{SF}/part.parquet").count()
    assert all(r.parts == parts for r in e.queries()["near_miss_kinds"](spark, SF).collect())


@pytest.mark.parametrize("tile, told", [(2_000, 1_000_000), (1, 1)])
def test_overlaps_of_maps_by_tiles(spark, monkeypatch, tile, told):
    monkeypatch.setattr(relational, "TOLD", told)
    texts = ["a a b c", "a a a b", "a b c d", "x y", "x y y", "z"]
    docs = spark.createDataFrame([(k, "p", t) for k, t in enumerate(texts)], "block_id long, project_id string, text string")
    pairs = spark.createDataFrame([(0, 1, 0), (0, 2, 0), (1, 2, 0), (4, 3, 0)], "b long, c long, overlap int")
    got = {tuple(r) for r in relational.overlaps_of_maps(docs, pairs, tile).collect()}
    assert got == {(0, 1, 3), (0, 2, 3), (1, 2, 2), (4, 3, 2)}
    assert sorted(r.block_id for r in relational.with_ids(docs, pairs.select(pairs.c.alias("block_id")).distinct()).collect()) == [1, 2, 3]
