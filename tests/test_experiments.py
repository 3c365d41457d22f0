"""Injected mutants: where they stand, what a report must cover, and which detector finds which type."""

from pyspark.sql import functions as F

from blockdup.plans import experiments, mutate


def corpus(spark):
    word = lambda d, k: "w" + "".join(chr(97 + (d * 7919 + k * 31 + k // 26 + s * (k + d)) % 26) for s in range(5))
    rows = [(d, "\n".join(" ".join(word(d, line * 8 + k) for k in range(8)) for line in range(n)), "xx") for d, n in ((1, 20), (2, 24), (3, 5))]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("source", F.lit("s"))


def test_mutants_stand_in_their_hosts(spark):
    docs = corpus(spark)
    made = mutate.mutants(experiments.fragments(docs), places=2)
    texts = {r.doc_id: r.text for r in docs.collect()}
    own = {(r.fragment_id, r.operator, r.copy): r for r in made.collect()}
    placed = experiments.inject(made, experiments.subject_system(docs)).collect()
    assert len(placed) == len(own) == len({r.ref_id for r in placed}) == 2 * 15 * 2
    for r in placed:
        lines = r.text.split("\n")
        mutant, host = "\n".join(lines[r.start_2 - 1 : r.end_2]), "\n".join(lines[: r.start_2 - 1] + lines[r.end_2 :])
        assert len(lines) == r.lines and host in texts.values()
        match = [x for (f, o, _), x in own.items() if f == r.fragment_id and o == r.operator and x.text == mutant]
        assert any((x.edit_start + r.start_2 - 1, min(x.edit_end, len(mutant.split("\n"))) + r.start_2 - 1) == (r.edit_start, r.edit_end) for x in match)
        assert r.start_2 <= r.edit_start <= r.edit_end <= r.end_2


def test_spans_of_tokens_as_lines(spark):
    files = spark.createDataFrame([(2, "a b\n\nc, 12 d\ne"), (3, "x\ny z")], "block_id long, text string")
    spans = spark.createDataFrame([(2, 3, 1, 3, 1, 1), (2, 3, 4, 6, 2, 3)], "b long, c long, at_b int, end_b int, at_c int, end_c int")
    got = {tuple(r) for r in experiments.in_lines(spans, files).select("file_1", "start_1", "end_1", "file_2", "start_2", "end_2").collect()}
    assert got == {(2, 1, 3, 3, 1, 1), (2, 3, 4, 3, 2, 2)}


def test_recall_of_injected_mutants(spark):
    rows = experiments.mutant_recall(spark, corpus(spark), detectors=("bag", "token_runs")).where("lang = 'xx' and clone_type is not null").collect()
    found = {(r.detector, r.operator): (r.found, r.references) for r in rows}
    assert all(found["bag", o] == (2, 2) for o in mutate.OPERATORS if o not in ("all_names",))
    assert found["bag", "all_names"] == (0, 2)
    assert found["token_runs", "spaces_added"] == (2, 2) and found["token_runs", "line_break_added"] == (2, 2)
    assert found["token_runs", "line_deleted"] == found["token_runs", "all_names"] == (0, 2)
