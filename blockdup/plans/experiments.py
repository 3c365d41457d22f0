"""The experiments, on the given tables: recall on mutants and on edited copies, competitors, sweeps, look-ups."""

from __future__ import annotations

import re
import time

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.order import ORDERS
from ..functions.tokens import normalize_t2
from ..operators import baselines, detect
from ..operators.blocks import blocks_from_boundaries, document_blocks, size_limits
from ..operators.index import IndexedRepository, partial_index
from ..operators.types import classify, locality
from ..sources.io import shared_folder, stage
from . import mutate
from .measures import detected, recall


#: Fragments a language, as published; the published experiment injects each mutant at 10 places.
FRAGMENTS = 250


def fragments(docs: DataFrame, per_lang: int = FRAGMENTS) -> DataFrame:
    """(fragment_id, lang, text): documents of 15-200 lines and 100-2,000 tokens, at most so many a language by hash of the id."""
    limited = size_limits(document_blocks(docs, project="lang"), min_lines=15, max_lines=200, min_tokens=100, max_tokens=2000)
    turn = F.row_number().over(Window.partitionBy("project_id").orderBy(F.md5(F.col("block_id").cast("string"))))
    return limited.withColumn("turn", turn).where(F.col("turn") <= per_lang).select(F.col("block_id").alias("fragment_id"), F.col("project_id").alias("lang"), "text")


DETECTORS = ("bag", "token_runs", "gapped_runs", "line_lcs", "vectors")


def reports(blocks: DataFrame, detector: str, theta_pm: int = 700) -> DataFrame:
    """(b, c) of one detector, both orders of ids."""
    runs = {
        "bag": lambda: detect.detect_clones(blocks, theta_pm), "token_runs": lambda: baselines.token_runs(blocks), "gapped_runs": lambda: baselines.gapped_runs(blocks),
        "line_lcs": lambda: baselines.line_lcs(blocks, **baselines.PRESETS["line_lcs"]), "vectors": lambda: baselines.vector_windows(blocks, **baselines.PRESETS["vectors"]),
    }
    found = runs[detector]().select("b", "c")
    return found.unionByName(found.select(F.col("c").alias("b"), F.col("b").alias("c"))).distinct()


def subject_system(docs: DataFrame, hosts: int = 50) -> DataFrame:
    """(lang, hosts, seat, host): the documents of each language that mutants are injected into, at most `hosts`."""
    named = docs.where("text is not null and lang is not null").select("lang", "doc_id")
    turn = Window.partitionBy("lang").orderBy(F.desc(F.md5(F.col("doc_id").cast("string"))), "doc_id")
    kept = named.withColumn("seat", F.row_number().over(turn)).where(F.col("seat") <= hosts)
    kept = kept.join(kept.groupBy("lang").agg(F.count("*").alias("hosts")), "lang")
    return kept.join(docs.select("doc_id", F.col("text").alias("host")), "doc_id").drop("doc_id")


def inject(made: DataFrame, subject: DataFrame) -> DataFrame:
    """Mutants in copies of documents of their language: adds ref_id (odd), the file's text, its `lines`, and start_2, end_2 and the edit in it.

    One file holds one mutant, at a line border chosen by hash of fragment, operator and copy. A mutant whose
    language has no document to hold it is not in the result; fragments come from documents, so there is one.
    """
    turn = F.create_map(*(F.lit(x) for k, name in enumerate(mutate.OPERATORS) for x in (name, k)))[F.col("operator")]
    most = 1 << 8  # copies of one mutant that get numbers of their own
    keyed = made.withColumn("ref_id", ((F.col("fragment_id") * len(mutate.OPERATORS) + turn) * most + F.col("copy")) * 2 + 1)
    counts = subject.groupBy("lang").agg(F.max("hosts").alias("hosts"))
    placed = keyed.join(counts, "lang").withColumn("seat", (F.pmod(F.xxhash64("ref_id"), F.col("hosts")) + 1).cast("int"))
    placed = placed.join(subject.select("lang", "seat", F.split("host", "\n").alias("around")), ["lang", "seat"])
    placed = placed.withColumns({"at": F.pmod(F.xxhash64("ref_id", F.lit("place")), F.size("around") + 1).cast("int"), "own": F.split("text", "\n")})
    whole = F.concat(F.slice("around", F.lit(1), F.col("at")), F.col("own"), F.slice("around", F.col("at") + 1, F.size("around")))
    return placed.select(
        "ref_id", "fragment_id", "lang", "operator", "clone_type", F.array_join(whole, "\n").alias("text"), (F.size("around") + F.size("own")).alias("lines"), (F.col("at") + 1).alias("start_2"),
        (F.col("at") + F.size("own")).alias("end_2"), (F.col("edit_start") + F.col("at")).alias("edit_start"), (F.least(F.col("edit_end"), F.size("own")) + F.col("at")).alias("edit_end"))


def in_lines(spans: DataFrame, files: DataFrame) -> DataFrame:
    """Reports by lines (file_1, start_1, end_1, file_2, start_2, end_2) of spans of tokens (b, c, at_b, end_b, at_c, end_c) in files."""
    count = lambda x: F.size(F.filter(F.split(normalize_t2(x), " "), lambda t: t != ""))
    of_token = F.flatten(F.transform(F.split("text", "\n"), lambda x, i: F.array_repeat(i + 1, count(x))))
    lines = stage(files.select(F.col("block_id").alias("file"), of_token.alias("lines")), "lines")
    line = lambda side, at: F.element_at(f"lines_{side}", F.col(at).cast("int"))
    both = spans.join(lines.toDF("b", "lines_b"), "b").join(lines.toDF("c", "lines_c"), "c")
    ends = (line(s, f"{w}_{s}").alias(f"{n}_{k}") for s, k in (("b", 1), ("c", 2)) for w, n in (("at", "start"), ("end", "end")))
    return both.select(F.col("b").alias("file_1"), F.col("c").alias("file_2"), *ends)


def span_reports(files: DataFrame, bounds: DataFrame, detector: str) -> DataFrame:
    """Reports by lines between files of different projects: block detectors see the blocks at `bounds`, the others whole files."""
    preset = baselines.PRESETS
    if detector == "token_runs":
        runs = baselines.token_spans(files, preset["token_runs"]["min_tokens"], preset["token_runs"]["min_types"], across=True)
        return in_lines(runs.withColumns({f"end_{s}": F.col(f"at_{s}") + F.col("tokens") - 1 for s in "bc"}), files)
    if detector == "gapped_runs":
        return in_lines(baselines.gapped_spans(files, **preset["gapped_runs_mutant"], across=True), files)
    if detector == "vectors":
        return in_lines(baselines.vector_spans(files, **preset["vectors_mutant"], across=True), files)
    cut = stage(blocks_from_boundaries(files.select("block_id", "project_id", "text"), bounds, id="block_id", project="project_id"), "blocks")
    if detector == "bag":
        kept = size_limits(cut, min_lines=preset["mutant"]["min_lines"])
        pairs = detect.detect_between(kept.where("project_id = 'original'"), kept.where("project_id = 'injected'"), preset["mutant"]["theta_pm"])
    elif detector == "line_lcs":
        pairs = baselines.line_lcs(cut, **preset["line_lcs_mutant"], across=True)
    else:
        raise ValueError(f"detector is one of {DETECTORS}")
    of = cut.select("block_id", "file_id", "start_line", "end_line")
    return pairs.select("b", "c").join(of.toDF("b", "file_1", "start_1", "end_1"), "b").join(of.toDF("c", "file_2", "start_2", "end_2"), "c").drop("b", "c")


def mutant_recall(
    spark: SparkSession, docs: DataFrame, per_lang: int = FRAGMENTS, places: int = 1, detectors: tuple[str, ...] = ("bag", "token_runs", "gapped_runs", "line_lcs"), hosts: int = 50,
) -> DataFrame:
    """(detector, lang, clone_type, operator, references, found, recall) with roll-ups: fragments against their mutants.

    Each mutant stands in a copy of a document of its language. A report counts if it covers 70 % of the lines of
    the fragment and of the mutant and all lines of the edit (`measures.detected`), for every detector alike.
    Mutant files are compared with fragments only, as each would be in a run of its own.
    """
    if places > 256:
        raise ValueError("at most 256 places a mutant")
    original = stage(fragments(docs.where("lang is not null"), per_lang), "fragments")
    placed = stage(inject(mutate.mutants(original, places), subject_system(docs, hosts)), "injected")
    files = original.select((F.col("fragment_id") * 2).alias("block_id"), F.lit("original").alias("project_id"), "text").unionByName(placed.select(F.col("ref_id").alias("block_id"), F.lit("injected").alias("project_id"), "text"))
    files = stage(files, "files")
    size = F.size(F.split("text", "\n"))
    cuts = F.array(F.struct(F.lit(1).alias("start_line"), (F.col("start_2") - 1).alias("end_line")), F.struct(F.col("start_2").alias("start_line"), F.col("end_2").alias("end_line")), F.struct((F.col("end_2") + 1).alias("start_line"), F.col("lines").alias("end_line")))
    bounds = placed.select(F.col("ref_id").alias("file_id"), F.explode(cuts).alias("s")).select("file_id", "s.*").where("start_line <= end_line")
    whole = original.select((F.col("fragment_id") * 2).alias("file_id"), F.lit(1).alias("start_line"), size.alias("end_line"))
    references = placed.join(original.select("fragment_id", size.alias("end_1")), "fragment_id").withColumns({"file_1": F.col("fragment_id") * 2, "file_2": F.col("ref_id"), "start_1": F.lit(1)})
    out = None
    for name in detectors:
        judged = detected(references, span_reports(files, bounds.unionByName(whole), name))
        rows = stage(recall(judged, "lang", "clone_type", "operator").withColumn("detector", F.lit(name)), "recall")
        out = rows if out is None else out.unionByName(rows)
    return out


def band_recall(docs: DataFrame, per_lang: int = FRAGMENTS, theta_pm: int = 700, detector: str = "bag") -> DataFrame:
    """(band, locality, references, found, recall): edited copies at four rates, half of them in the fragment's own project."""
    original = stage(fragments(docs, per_lang), "fragments")
    made = mutate.edited_copies(original).withColumn("copy_id", F.xxhash64("fragment_id", "rate"))
    same = F.pmod("copy_id", F.lit(2)) == 0
    a = original.select(F.col("fragment_id").alias("block_id"), F.col("fragment_id").cast("string").alias("project_id"), "text")
    b = made.select(F.col("copy_id").alias("block_id"), F.when(same, F.col("fragment_id").cast("string")).otherwise("elsewhere").alias("project_id"), "text")
    blocks = stage(a.unionByName(b), "blocks")
    references = classify(made.select(F.col("fragment_id").alias("b"), F.col("copy_id").alias("c")), blocks)
    projects = blocks.select("block_id", "project_id")
    references = references.join(projects.toDF("b", "project_b"), "b").join(projects.toDF("c", "project_c"), "c")
    hit = reports(blocks, detector, theta_pm).withColumn("hit", F.lit(True))
    judged = references.join(hit, ["b", "c"], "left").withColumns({"detected": F.coalesce("hit", F.lit(False)), "locality": locality(F.col("project_b"), F.col("project_c"))})
    return recall(judged, "clone_type", "locality")


def order_ablation(blocks: DataFrame, theta_pm: int = 700) -> DataFrame:
    """(order, postings, candidates) for each global order, by sub-blocks and sizes."""
    out = None
    for name in ORDERS:
        ordered = stage(detect.order_of(blocks, order=name), "ordered")
        postings = partial_index(ordered, theta_pm)
        found = detect.candidates(postings, postings, theta_pm, filters=frozenset({"prefix", "size"}))
        row = postings.agg(F.count("*").alias("postings")).crossJoin(found.agg(F.count("*").alias("candidates"))).withColumn("order", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out


def lookup(spark: SparkSession, stored: DataFrame, asked: DataFrame, theta_pm: int = 700) -> DataFrame:
    """Matches of query blocks in a stored index built for the occasion."""
    path = f"{shared_folder(spark)}/index-{time.time_ns()}"
    return IndexedRepository.build(stored, path, theta_pm).query(asked)


def scaling(spark: SparkSession, docs: DataFrame, shares: tuple[int, ...] = (100, 1000)) -> list[dict]:
    """Seconds, lines and pairs on nested samples."""
    from .measures import nested_samples

    blocks = document_blocks(docs)
    out = []
    for share in shares:
        part = stage(blocks.join(nested_samples(blocks, (share,)).select("block_id"), "block_id", "left_semi"), "sample")
        began = time.time()
        pairs = detect.detect_clones(part).count()
        out.append({"share_pm": share, "blocks": part.count(), "lines": part.agg(F.sum("end_line")).first()[0] or 0, "pairs": pairs, "seconds": time.time() - began})
    return out


def lookup_latency(spark: SparkSession, blocks: DataFrame, theta_pm: int = 700) -> list[tuple]:
    """(source, matches, seconds): the blocks of three sources looked up in one stored index of all the others."""
    path, asked = f"{shared_folder(spark)}/index-{time.time_ns()}", ("src0", "src1", "src2")
    repo = IndexedRepository.build(blocks.where(~F.col("project_id").isin(*asked)), path, theta_pm)
    out = []
    for source in asked:
        began = time.time()
        matches = repo.query(blocks.where(F.col("project_id") == source)).count()
        out.append((source, matches, time.time() - began))
    return out


def whole_repository(blocks: DataFrame, theta_pm: int = 700) -> dict:
    """Counts and seconds of each stage over all blocks within the limits for whole repositories."""
    from .measures import coverage

    seconds, began = {}, time.time()

    def lap(name: str) -> None:
        nonlocal began
        seconds[f"{name}_seconds"], began = time.time() - began, time.time()

    limited = size_limits(blocks, min_lines=baselines.PRESETS["large"]["min_lines"])
    ordered = stage(detect.order_of(limited), "ordered")
    lap("order")
    postings = partial_index(ordered, theta_pm).count()
    lap("index")
    pairs = stage(detect.detect_ordered(ordered, theta_pm, staged=False), "pairs")
    lap("detect")
    covered = coverage(pairs, ordered).first()
    return {"blocks": covered.blocks, "postings": postings, "pairs": pairs.count(), "covered": covered.covered, **seconds}


def band_recall_detectors(docs: DataFrame, detectors: tuple[str, ...] = ("bag", "token_runs", "gapped_runs", "line_lcs")) -> DataFrame:
    """Recall by band and locality of each detector on the same edited copies."""
    out = None
    for name in detectors:
        rows = band_recall(docs, detector=name).withColumn("detector", F.lit(name))
        out = rows if out is None else out.unionByName(rows)
    return out


def scale_table(spark: SparkSession, docs: DataFrame, shares: tuple[int, ...] = (10, 100, 1000), detectors: tuple[str, ...] = DETECTORS, seconds: float = 300.0) -> DataFrame:
    """(detector, share_pm, lines, pairs, seconds, status) on nested inputs, each larger one holding the smaller ones.

    A detector that takes longer than `seconds` on one input is not run on larger ones (status `not run`, after
    `over time`); one that fails has the kind of its failure there. The limit is a parameter of the experiment.
    """
    from .measures import nested_samples

    blocks, rows = size_limits(document_blocks(docs), min_lines=baselines.PRESETS["scale"]["min_lines"]), []
    parts = []
    for share in shares:
        part = stage(blocks.join(nested_samples(blocks, (share,)).select("block_id"), "block_id", "left_semi"), "sample")
        parts.append((share, part, int(part.agg(F.sum("end_line")).first()[0] or 0)))
    for name in detectors:
        status = "done"
        for share, part, lines in parts:
            if status != "done":
                rows.append((name, share, lines, None, None, "not run"))
                continue
            began, pairs = time.time(), None
            try:
                pairs = reports(part, name).where("b < c").count()
            except Exception as why:  # the table reports failures, it does not hide them
                status = "memory" if "OutOfMemory" in str(why) else type(why).__name__
            took = time.time() - began
            if status == "done" and took > seconds:
                status = "over time"
            rows.append((name, share, lines, pairs, took, status))
    return spark.createDataFrame(rows, "detector string, share_pm int, lines long, pairs long, seconds double, status string")


def index_bytes(spark: SparkSession, blocks: DataFrame, theta_pm: int = 700) -> DataFrame:
    """(part, bytes) of a stored index of all blocks."""
    path = f"{shared_folder(spark)}/index-{time.time_ns()}"
    IndexedRepository.build(blocks, path, theta_pm)
    jvm, out = spark._jvm, []
    for part in ("postings", "blocks", "frequencies"):
        where = jvm.org.apache.hadoop.fs.Path(f"{path}/{part}")
        out.append((part, where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(where).getLength()))
    return spark.createDataFrame(out, "part string, bytes long")


def near_miss_code() -> dict[str, str]:
    """A function, and copies of it that do the same or nearly the same with other statements; @ stands for the ending of its names."""
    names = [chr(97 + k) for k in range(16)]
    work = [f"  a{x}@ = b{x}@ + c{x}@ * d{x}@;" for x in names]
    tests = ["  if (n@ > 3) {", "    n@ = n@ - 1;", "  }", "  if (n@ < 9) {", "    n@ = n@ + 2;", "  }"]
    loop = ["  for (i@ = 0; i@ < n@; i@++) { total@ += i@; }"]
    whole = lambda *parts: "\n".join(["int work@(int n@) {", *(x for p in parts for x in p), "}"])
    return {
        "original": whole(work, tests, loop),
        "statements_swapped": whole(work[:7], [work[8], work[7]], work[9:], tests, loop),
        "conditions_joined": whole(work[:8], ["  if (n@ > 3 && n@ < 9) {", "    n@ = n@ - 1;", "    n@ = n@ + 2;", "  }"], work[8:], loop),
        "operators_changed": whole([x.replace("+", "-") for x in work], tests, loop),
        "loop_rewritten": whole(work[:8], ["  i@ = 0;", "  while (i@ < n@) { total@ += i@; i@++; }"], work[8:], tests),
    }


def near_misses(parts: DataFrame) -> DataFrame:
    """(kind, detector, detected, parts): a function a part with names of its own, and whether it is reported with each
    of its copies; equal runs count if they span the copy."""
    made = near_miss_code()
    kinds = [k for k in made if k != "original"]
    text = F.array(*(F.struct(F.lit(k).alias("copy"), F.lit("copy" if k else "original").alias("project_id"), F.lit(made[kind]).alias("code")) for k, kind in enumerate(["original", *kinds])))
    ending = F.translate(F.col("p_partkey").cast("string"), "0123456789", "qrstuvwxyz")  # digits would be normalised away
    each = parts.select("p_partkey", ending.alias("ending"), F.explode(text).alias("s"))
    blocks = stage(each.select((F.col("p_partkey") * 8 + F.col("s.copy")).alias("block_id"), "s.project_id", F.expr("replace(s.code, '@', ending)").alias("text")), "functions")
    tokens = len(re.findall(r"\w+", made["original"].replace("@", "q")))
    found = {
        "bag": detect.detect_clones(blocks, 700, profile="java"),
        "token_runs": baselines.token_runs(blocks).where(F.col("longest") * 1000 >= tokens * 990),
        "gapped_runs": baselines.gapped_runs(blocks),
    }
    named = parts.select("p_partkey", F.explode(F.array(*(F.struct((F.lit(k + 1)).cast("long").alias("copy"), F.lit(kind).alias("kind")) for k, kind in enumerate(kinds)))).alias("s")).select("p_partkey", "s.*")
    out = None
    for name, pairs in found.items():
        low, high = F.least("b", "c"), F.greatest("b", "c")
        hit = pairs.where((low % 8 == 0) & (high - low < 8)).select(F.floor(low / 8).alias("p_partkey"), (high % 8).alias("copy"), F.lit(True).alias("hit")).distinct()
        row = named.join(hit, ["p_partkey", "copy"], "left").groupBy("kind", F.coalesce("hit", F.lit(False)).alias("detected")).agg(F.count("*").alias("parts")).select("kind", F.lit(name).alias("detector"), "detected", "parts")
        out = row if out is None else out.unionByName(row)
    return out
