"""Worked examples, edge cases and random blocks against brute force."""

import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from blockdup.functions import filters, order, similarity
from blockdup.functions.tokens import bag_of_tokens, normalize_t2, token_array, tokenize
from blockdup.operators import detect, groups
from blockdup.operators.blocks import brace_spans
from blockdup.operators.index import IndexedRepository, partial_index
from blockdup.plans import measures


def blocks(spark, texts, project=None):
    rows = [(k, (project or ["p"] * len(texts))[k], t) for k, t in enumerate(texts)]
    return spark.createDataFrame(rows, "block_id long, project_id string, text string")


def brute(texts, theta, measure="overlap", strict=False):
    bags = [Counter(t.split()) for t in texts]
    out = set()
    for x in range(len(bags)):
        for y in range(x + 1, len(bags)):
            o, a, b = sum((bags[x] & bags[y]).values()), sum(bags[x].values()), sum(bags[y].values())
            if not a or not b:
                continue
            if measure == "overlap":
                hit = o > -(-max(a, b) * theta // 1000) if strict else o * 1000 >= theta * max(a, b)
            elif measure == "jaccard":
                hit = o * (1000 + theta) >= theta * (a + b)
            else:
                hit = o * o * 10**6 >= theta * theta * a * b
            if hit:
                out.add((x, y))
    return out


def found(df):
    return {tuple(sorted(r)) for r in df.select("b", "c").collect()}


def test_five_tokens(spark):
    b = blocks(spark, ["a b c d e", "b c d e f"])
    assert found(detect.detect_clones(b, 800, order="alphabetical")) == {(0, 1)}
    assert found(detect.detect_clones(b, 800, order="alphabetical", strict=True)) == set()


def test_four_against_five_is_no_candidate(spark):
    o = detect.order_of(blocks(spark, ["a b c d", "b c d e f"]), order="alphabetical")
    p = partial_index(o, 800)
    assert {(r.block_id, r.element[0]) for r in p.collect()} == {(0, "a"), (1, "b"), (1, "c")}
    assert detect.candidates(p, p, 800).count() == 0
    one = spark.range(1).select(filters.upper_bound(*(F.lit(x) for x in (1, 2, 1, 4, 5))).alias("u"))
    assert one.first().u == 3


def test_multiset_overlap_counts_the_smaller_frequency(spark):
    pairs = detect.detect_clones(blocks(spark, ["x x a b c", "x x x a b c"]), 500).collect()
    assert [(r.overlap, r.n_b, r.n_c) for r in pairs] == [(5, 6, 5)]


def test_integer_ceilings(spark):
    row = spark.range(1).select(similarity.required_overlap(F.lit(100), F.lit(100), 550).alias("o")).first()
    assert row.o == 55


@pytest.mark.parametrize("measure", similarity.MEASURES)
@pytest.mark.parametrize("theta", [500, 700, 1000])
def test_random_blocks(spark, measure, theta):
    r = random.Random(theta)
    texts = [" ".join(r.choice("abcdefgh") for _ in range(r.randrange(0, 9))) for _ in range(40)] + ["a", "", "a b", "a b"]
    b = blocks(spark, texts)
    want = brute(texts, theta, measure)
    assert found(detect.detect_clones(b, theta, measure)) == want
    assert found(detect.detect_clones(b, theta, measure, min_shared=3, collapse=False)) == want


@pytest.mark.parametrize("name", order.ORDERS)
def test_any_order_gives_the_same(spark, name):
    r = random.Random(1)
    texts = [" ".join(r.choice("abcdef") for _ in range(r.randrange(1, 8))) for _ in range(30)]
    assert found(detect.detect_clones(blocks(spark, texts), 600, order=name)) == brute(texts, 600)


def test_merge_verifier_agrees(spark):
    r = random.Random(2)
    texts = [" ".join(r.choice("abcdefghij") for _ in range(r.randrange(4, 12))) for _ in range(40)]
    for name in ("token_frequency", "element_frequency", "popular_first"):
        o = order.ordered_blocks(bag_of_tokens(tokenize(blocks(spark, texts))), name, keys=True)
        p = partial_index(o, 600)
        done = detect.verify_merge(detect.candidates(p, p, 600), o, o, 600)
        assert found(done.where("outcome = 'accepted'")) == brute(texts, 600)
    early = detect.verify_merge(detect.candidates(p, p, 600), o, o, 600, early_accept=True)
    pairs = lambda df: {(r.b, r.c) for r in df.where("outcome = 'accepted'").collect()}
    assert pairs(early) == pairs(done)
    cost = lambda df: sum(r.compared for r in df.collect())
    assert cost(early) < cost(done) < sum(r.n_b * r.n_c for r in done.collect())


def test_merge_is_the_plain_walk():
    b, c = [(1, "a", 1), (2, "b", 1), (2, "b", 2), (5, "x", 1)], [(1, "b", 9), (2, "b", 2), (5, "x", 1)]
    assert detect.merge(b, c, 0, 0, 0, 1, False) == (2, 5, "accepted")
    assert detect.merge(b, c, 0, 0, 0, 1, True)[0] == 1
    assert detect.merge(b, c, 0, 0, 0, 4, False) == (0, 0, "rejected")


def test_hot_elements_are_split_without_loss(spark):
    r = random.Random(7)
    texts = ["same " + " ".join(r.choice("abcdefgh") for _ in range(r.randrange(1, 6))) for _ in range(60)]
    assert found(detect.detect_clones(blocks(spark, texts), 500, order="popular_first", hot=3, min_shared=1)) == brute(texts, 500)
    pairs, members = detect.detect_representatives(detect.order_of(blocks(spark, texts)), 500)
    rep = {x.block_id: x.rep for x in members.collect()}
    near = {frozenset((x.b, x.c)) for x in pairs.collect()}
    whole = {frozenset((x[0], x[1])) for x in brute(texts, 500)}
    assert whole == {frozenset((x, y)) for x in rep for y in rep if x != y and (rep[x] == rep[y] or frozenset((rep[x], rep[y])) in near)}


def test_items_word_for_word(spark):
    from blockdup.operators.relational import without_items

    items = ["one two three four five six seven eight nine ten eleven", "short item here", "!?", "two words", None]
    texts = [f"xx {items[0]}yy", "a short item here.", "a shorts item here", "what!?", "two wordsmith", "none", None, "one two three four five six seven eight nine ten", "re" + items[0]]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {x.doc_id for x in without_items(docs, spark.createDataFrame([(x,) for x in items], "text string")).collect()}
    assert got == {k for k, t in enumerate(texts) if not any(t is not None and x is not None and x in t for x in items)}


def test_partitions_localities_and_empty(spark):
    texts, projects = ["a b c", "a b c", "a b d", "z"], ["p", "q", "p", "p"]
    b = blocks(spark, texts, projects)
    assert found(detect.detect_partitioned(b, 3, 600)) == brute(texts, 600)
    assert found(detect.detect_within(b, theta_pm=600)) == {(0, 2)}
    assert found(detect.detect_across(b, theta_pm=600)) == {(0, 1), (1, 2)}
    assert detect.detect_clones(b.where("false")).count() == 0


def test_stored_index_with_unseen_tokens_and_append(spark, tmp_path):
    stored, asked = ["a b c d", "e f g h", "a b c x"], ["a b c new", "e f g h"]
    repo = IndexedRepository.build(blocks(spark, stored), str(tmp_path / "i"), 700)
    got = {(r.query_id, r.block_id) for r in repo.query(blocks(spark, asked)).collect()}
    assert got == {(0, 0), (0, 2), (1, 1)}
    repo.append(spark.createDataFrame([(9, "p", "e f g new")], "block_id long, project_id string, text string"))
    assert {(r.query_id, r.block_id) for r in repo.query(blocks(spark, asked)).collect()} == got | {(1, 9)}
    with pytest.raises(ValueError):
        repo.query(blocks(spark, asked), 500)


def test_components_and_classes(spark):
    pairs = spark.createDataFrame([(1, 2), (2, 3), (5, 4)], "b long, c long")
    assert {(r.class_id, r.block_id) for r in groups.clone_components(pairs).collect()} == {(1, 1), (1, 2), (1, 3), (4, 4), (4, 5)}
    assert {(r.class_id, r.block_id, r.is_complete) for r in groups.clone_classes(pairs).collect()} == {(1, 1, False), (1, 2, False), (3, 3, False), (4, 4, True), (4, 5, True)}
    chain = spark.createDataFrame([(k, k + 1) for k in range(40)], "b long, c long")
    assert {r.class_id for r in groups.clone_components(chain).collect()} == {0}


def test_strict_classes_as_by_hand(spark):
    import random

    r, links = random.Random(11), set()
    for first, m, share in ((0, 40, 0.8), (100, 60, 0.5), (300, 5, 1.0), (400, 200, 0.04)):
        links |= {(a, b) for a in range(first, first + m) for b in range(a + 1, first + m) if r.random() < share}
    pairs = spark.createDataFrame([p if r.random() < 0.5 else p[::-1] for p in links], "b long, c long").repartition(3)
    near: dict[int, set[int]] = {}
    for a, b in links:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    made: list[list[int]] = []
    for x in sorted(near):
        home = next((g for g in made if near[x].issuperset(g)), None)
        made.append([x]) if home is None else home.append(x)
    got = groups.clone_classes(pairs).collect()
    assert {(r.class_id, r.block_id) for r in got} == {(g[0], x) for g in made for x in g} and len(got) == len(near)
    assert {r.block_id for r in got if r.is_complete} == set(range(300, 305))


def test_strict_classes_of_a_large_component(spark):
    hub = spark.range(1, 20_001).select(F.lit(0).cast("long").alias("b"), F.col("id").alias("c"))
    assert {(r.class_id, r.n) for r in groups.clone_classes(hub).groupBy("class_id").agg(F.count("*").alias("n")).where("n > 1").collect()} == {(0, 2)}


def test_lexing(spark):
    one = spark.range(1).select(token_array(F.lit('x = "alpha beta" + 3; // note\n/* y */ z'), "java").alias("t"), normalize_t2(F.lit("int a = b + a;"), "java", "consistent").alias("n"))
    row = one.first()
    assert row.t == ["x", "alpha", "beta", "3", "z"] and row.n == "int ID1 = ID2 + ID1 ;"
    assert bag_of_tokens(tokenize(blocks(spark, ["", "a"]))).count() == 1
    assert brace_spans("class A {\n int f(int x) {\n  if (x > 0) { return 1; }\n  return 2;\n }\n}\n") == [(2, 5)]


def test_measures(spark):
    assert measures.sample_size() == 385
    got = measures.interval(355, 390)
    assert round(got["p"], 4) == 0.9103 and round(got["p"] - got["wald_low"], 4) == 0.0284
    refs = spark.createDataFrame([(1, 1, 11, 20, 2, 11, 20, 15, 15)], "ref_id int, file_1 int, start_1 int, end_1 int, file_2 int, start_2 int, end_2 int, edit_start int, edit_end int")
    for first, hit in ((14, True), (15, False)):
        rep = spark.createDataFrame([(1, first, 20, 2, first, 20)], "file_1 int, start_1 int, end_1 int, file_2 int, start_2 int, end_2 int")
        assert measures.detected(refs, rep).first().detected is hit


def test_plans_push_filters_and_have_no_cartesian_product(spark):
    from blockdup.sources.io import table

    docs = table(spark, "/root/testdata/sf0.001", "documents").where("lang = 'en'").select("doc_id")
    plan = docs._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(lang), EqualTo(lang,en)]" in plan
    p = partial_index(detect.order_of(blocks(spark, ["a b", "a b"])))
    plan = detect.candidates(p, p)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan and "Python" not in plan


def test_reference_counts(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 27
    assert e.queries()["clones_overlap_700"](spark, "/root/testdata/sf0.01").count() == 189


def test_vector_windows_meet_at_any_even_distance(spark, tmp_path):
    import random

    from blockdup.plans.queries import QUERIES

    r = random.Random(3)
    word = lambda: "".join(r.choices("abcdefghijklmnop", k=6))
    passage = [word() for _ in range(60)]
    texts = [" ".join([*(word() for _ in range(front)), *passage, *(word() for _ in range(70))]) for front in (0, 18)]
    rows = [(k, t, "en", "s", len(t)) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    assert {(r.b, r.c) for r in QUERIES["vector_windows"](spark, str(tmp_path)).collect()} == {(0, 1)}


def test_all_pairs_references_run_beyond_two_thousand_rows(spark):
    from blockdup.operators import baselines

    ordered = spark.range(2_100).select(F.col("id").alias("block_id"), F.lit("p").alias("project_id"), F.array(F.concat(F.lit("t"), (F.col("id") % 1_050).cast("string"))).alias("elements"), F.lit(1).alias("n"))
    assert {(r.b, r.c) for r in baselines.all_pairs(ordered).select("b", "c").collect()} == {(k, k + 1_050) for k in range(1_050)}
    at = F.col("id") % 1_050 * (3.1 / 1_050)
    vectors = spark.range(2_100).select(F.col("id").alias("vec_id"), F.array(F.cos(at), F.sin(at)).alias("embedding"))
    got = baselines.embedding_cosine(vectors, 0.999999, rows=300)
    assert {(r.b, r.c) for r in got.collect()} == {(k, k + 1_050) for k in range(1_050)}
