"""More named queries: ways to make blocks, ablations, whole-repository runs, near misses, SQL and UDF surfaces, joined streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.filters import position_filter
from ..functions.order import zipf_slope
from ..functions.tokens import WORD, bag_of_tokens, normalize_t2, token_array, token_kind, tokenize
from ..operators import blocks, detect, relational
from ..operators.index import full_index, partial_index
from ..operators.types import classify
from ..sources.io import shared_folder, stage, table, write_bands
from ..streaming import streams
from . import experiments, measures
from .queries import CL7, DOCS, ELEMENTS, TYPED, _typed, at, bags, clone_sql, clones7, docs_of, ordered_docs, overlaps, pair, query

# ---------------------------------------------------------------- blocks
LINES = "string_split(text, chr(10))"


def _cut_sql(width: int, step: int) -> str:
    """Blocks of `width` lines every `step`, down to the last line of each document."""
    last = f"least(len({LINES}), greatest(len({LINES}) - {width} + {step}, 1))"
    return f"SELECT doc_id * 1048576 + st AS block_id, source AS project_id, st::INT AS start_line, least(st + {width - 1}, len(ls))::INT AS end_line, array_to_string(ls[st:st + {width - 1}], chr(10)) AS text FROM (SELECT doc_id, source, {LINES} AS ls, unnest(range(1, {last} + 1, {step})) AS st FROM documents)"


def _tokens_sql(cut: str) -> str:
    return rf"SELECT block_id, project_id, unnest(regexp_extract_all(text, '[\p{{L}}\p{{N}}_]+')) AS token FROM ({cut})"


def _digest(df: DataFrame) -> DataFrame:
    return df.select("block_id", "project_id", "start_line", "end_line", F.md5("text").alias("digest"))


_DIGEST = "SELECT block_id, project_id, start_line, end_line, md5(text) AS digest FROM "
query(f"{_DIGEST}({_cut_sql(15, 15)})", "blocks_line_groups")(lambda s, d: _digest(blocks.line_group_blocks(table(s, d, "documents"), 15)))
query(f"{_DIGEST}({_cut_sql(10, 5)})", "blocks_line_windows")(lambda s, d: _digest(blocks.window_blocks(table(s, d, "documents"), 10, 5)))
query(clone_sql(at(700), _tokens_sql(_cut_sql(15, 15))), "clones_line_groups")(lambda s, d: pair(detect.detect_clones(blocks.line_group_blocks(table(s, d, "documents"), 15))))
query(clone_sql(at(800), _tokens_sql(_cut_sql(10, 5))), "clones_line_windows")(lambda s, d: pair(detect.detect_clones(blocks.window_blocks(table(s, d, "documents"), 10, 5), 800)))


@query(f"SELECT doc_id * 1048576 + 1 AS block_id, source AS project_id, 1 AS start_line, e::INT AS end_line, md5(array_to_string(ls[1:e], chr(10))) AS digest FROM (SELECT doc_id, source, {LINES} AS ls, (len({LINES}) + 1) // 2 AS e FROM documents)")
def blocks_given_boundaries(spark, d):
    """The first half of each document, cut at boundaries that a relation gives."""
    half = docs_of(spark, d).select("file_id", F.lit(1).alias("start_line"), F.floor((F.col("end_line") + 1) / 2).cast("int").alias("end_line"))
    return _digest(blocks.blocks_from_boundaries(table(spark, d, "documents"), half))


@query("WITH e AS (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 6 HOUR, TRUE) AS fresh FROM events), g AS (SELECT *, sum(fresh::INT) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS s FROM e) SELECT project_id, count(*)::BIGINT AS sessions, sum(kinds)::BIGINT AS kinds, sum(n)::BIGINT AS events FROM (SELECT user_id::VARCHAR AS project_id, s, count(DISTINCT event_type) AS kinds, count(*) AS n FROM g GROUP BY ALL) GROUP BY 1")
def blocks_of_sessions(spark, d):
    """Sessions of each user as bags of event types."""
    per = blocks.session_blocks(table(spark, d, "events"), "6 hours").groupBy("project_id", "block_id").agg(F.count("*").alias("k"), F.sum("freq").alias("n"))
    return per.groupBy("project_id").agg(F.count("*").alias("sessions"), F.sum("k").alias("kinds"), F.sum("n").alias("events"))


# ---------------------------------------------------------------- code, generated from parts
def code_files(spark: SparkSession, d: str) -> DataFrame:
    """(doc_id, text, source): a small class a part, with two methods and one nested block."""
    p = table(spark, d, "part")
    body = F.format_string("class P%s {\n int size() { return %s; }\n int price(int n) {\n  if (n > %s) { return n; }\n  return %s;\n }\n}\n", F.col("p_partkey").cast("string"), *(F.col("p_size").cast("string") for _ in range(3)))
    return p.select(F.col("p_partkey").alias("doc_id"), body.alias("text"), F.col("p_brand").alias("source"))


query("SELECT p_partkey AS file_id, unnest([2, 3])::INT AS start_line, unnest([2, 6])::INT AS end_line FROM part", "blocks_of_braces")(lambda s, d: blocks.brace_blocks(code_files(s, d)).select("file_id", "start_line", "end_line"))
query("SELECT unnest(['keyword', 'identifier', 'literal']) AS kind, unnest([8 * count(*), 6 * count(*), 3 * count(*)])::BIGINT AS n FROM part", "token_kinds_code")(
    lambda s, d: code_files(s, d).select(F.explode(token_array(F.col("text"), "java")).alias("t")).groupBy(token_kind(F.col("t"), "java").alias("kind")).agg(F.count("*").alias("n")))
query("SELECT count(*)::BIGINT AS files, 1::BIGINT AS blind, 1::BIGINT AS consistent FROM part", "normalized_code")(
    lambda s, d: code_files(s, d).agg(F.count("*").alias("files"), *(F.count_distinct(normalize_t2(F.col("text"), "java", m)).alias(m) for m in ("blind", "consistent"))))


# ---------------------------------------------------------------- ablations and measures
_CP = ", cp AS (SELECT x.block_id AS b, y.block_id AS c, x.n AS n_b, y.n AS n_c, count(*) AS seen, max(x.pos) AS last_b, max(y.pos) AS last_c FROM post x JOIN post y ON x.token = y.token AND x.k = y.k AND (x.n > y.n OR (x.n = y.n AND x.block_id < y.block_id)) GROUP BY ALL), fits AS (SELECT * FROM cp WHERE n_c * 1000 >= n_b * 700), ov AS (SELECT DISTINCT x.block_id AS b, y.block_id AS c FROM bag x JOIN bag y ON x.token = y.token AND x.block_id < y.block_id)"


@query(ELEMENTS + _CP + " SELECT 'quadratic' AS stage, (count(*) * (count(*) - 1) // 2)::BIGINT AS comparisons FROM sz UNION ALL SELECT 'all_elements', count(*) FROM ov UNION ALL SELECT 'prefix', count(*) FROM cp UNION ALL SELECT 'prefix_size', count(*) FROM fits UNION ALL SELECT 'prefix_size_position', count(*) FROM fits WHERE (seen + least(n_b - last_b, n_c - last_c)) * 1000 >= n_b * 700")
def comparisons_by_stage(spark, d):
    """Pairs left to compare with no filter and with one filter more each time."""
    o = ordered_docs(spark, d)
    every, some = full_index(o), partial_index(o)
    fits = detect.candidates(some, some, filters=frozenset({"prefix", "size"}))
    stages = {
        "all_elements": detect.candidates(every, every, filters=frozenset()), "prefix": detect.candidates(some, some, filters=frozenset({"prefix"})), "prefix_size": fits,
        "prefix_size_position": fits.where(position_filter(*(F.col(c) for c in ("seen", "last_b", "last_c", "n_b", "n_c")), 700, "overlap")),
    }
    out = o.agg((F.count("*") * (F.count("*") - 1) / 2).cast("long").alias("comparisons")).withColumn("stage", F.lit("quadratic"))
    for name, found in stages.items():
        out = out.unionByName(found.agg(F.count("*").alias("comparisons")).withColumn("stage", F.lit(name)))
    return out


@query(f"WITH {overlaps()} SELECT unnest(['overlap', 'jaccard', 'cosine']) AS measure, unnest([count(*) FILTER ({at(700)}), count(*) FILTER (overlap * 1700 >= (n_b + n_c) * 700), count(*) FILTER (overlap * overlap * 1000000 >= n_b * n_c * 490000)])::BIGINT AS pairs FROM pr")
def similarity_ablation(spark, d):
    """Pairs that each similarity finds at 0.7."""
    o, out = ordered_docs(spark, d), None
    for m in ("overlap", "jaccard", "cosine"):
        row = detect.detect_ordered(o, 700, m).agg(F.count("*").alias("pairs")).withColumn("measure", F.lit(m))
        out = row if out is None else out.unionByName(row)
    return out


@query(TYPED + ", s AS (SELECT * FROM cls ORDER BY md5(b || '-' || c) LIMIT 390) SELECT count(*)::BIGINT AS judged, count(*) FILTER (clone_type <> 'WT3/T4')::BIGINT AS clones FROM s")
def precision_by_band(spark, d):
    """Sampled reports, and those that line and token similarity call a clone: a stand-in for human judges."""
    judged = classify(measures.judged_sample(clones7(spark, d)).select("b", "c"), docs_of(spark, d))
    return judged.agg(F.count("*").alias("judged"), F.count(F.when(F.col("clone_type") != "WT3/T4", 1)).alias("clones"))


_LONG = rf"{DOCS} WHERE len(list_filter({LINES}, lambda x: trim(regexp_replace(x, '\s+', ' ', 'g')) <> '')) >= 10"


@query(ELEMENTS.replace(DOCS, _LONG) + f", {overlaps(_LONG).split('sz AS', 1)[1].split('), ', 1)[1]}, cl AS (SELECT * FROM pr WHERE {at(700)}), named AS (SELECT b FROM cl UNION SELECT c FROM cl) SELECT (SELECT count(*) FROM sz)::BIGINT AS blocks, (SELECT count(*) FROM post)::BIGINT AS postings, (SELECT count(*) FROM cl)::BIGINT AS pairs, (SELECT count(*) FROM named)::BIGINT AS covered")
def whole_repository(spark, d):
    """The whole table at 10 lines or more: blocks, postings, pairs, and blocks in a pair."""
    return spark.createDataFrame([experiments.whole_repository(docs_of(spark, d))]).select("blocks", "postings", "pairs", "covered")


query(name="whole_repository_seconds")(lambda s, d: s.createDataFrame([experiments.whole_repository(docs_of(s, d))]))
query(name="lookup_latency")(lambda s, d: s.createDataFrame(experiments.lookup_latency(s, docs_of(s, d)), "source string, matches long, seconds double"))
query(name="recall_by_band_detectors")(lambda s, d: experiments.band_recall_detectors(table(s, d, "documents")))
query(clone_sql(at(700)), "clones_partitioned_2")(lambda s, d: pair(detect.detect_partitioned(docs_of(s, d), 2)))
query(f"WITH {bags()}, gtf AS (SELECT token, sum(f)::BIGINT AS gf FROM bag GROUP BY token), g AS (SELECT gf, count(*) AS m FROM gtf GROUP BY gf), r AS (SELECT gf, coalesce(sum(m) OVER (ORDER BY gf DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + 1 AS rank FROM g) SELECT round(regr_slope(ln(gf), ln(rank)), 6) AS slope FROM r", "zipf_slope")(
    lambda s, d: zipf_slope(bag_of_tokens(tokenize(docs_of(s, d)))).select(F.round("slope", 6).alias("slope")))


@query(f"WITH {CL7} SELECT b, c, overlap::BIGINT AS overlap FROM cl")
def map_overlap(spark, d):
    """The overlap of reported pairs once more, from bags held as maps; copies have that of their representatives."""
    docs = docs_of(spark, d)
    pairs, members = detect.representatives(docs)
    counted = stage(relational.overlaps_of_maps(docs, pairs), "counted")
    return detect.expand_copies(counted, members, 700, "overlap", False).select("b", "c", F.col("overlap").cast("long").alias("overlap"))


# ---------------------------------------------------------------- SQL and UDF surfaces, sinks
@query(f"WITH {CL7} SELECT b, c, ((n_b * 700 + 999) // 1000)::BIGINT AS needed, round(overlap::DOUBLE / n_b, 9) AS likeness FROM cl")
def sql_surface(spark, d):
    """Views and SQL functions over the detector's results."""
    clones7(spark, d).createOrReplaceTempView("pairs")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION required_overlap(x INT, y INT, theta_pm INT) RETURNS BIGINT RETURN (greatest(x, y) * CAST(theta_pm AS BIGINT) + 999) DIV 1000")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION overlap_similarity(o INT, x INT, y INT) RETURNS DOUBLE RETURN o / greatest(x, y)")
    return spark.sql("SELECT b, c, required_overlap(n_b, n_c, 700) AS needed, round(overlap_similarity(overlap, n_b, n_c), 9) AS likeness FROM pairs WHERE overlap >= required_overlap(n_b, n_c, 700)")


class _Words:
    def eval(self, text: str):
        import regex

        for word in regex.findall(WORD, text or ""):
            yield (word,)


@query(f"SELECT block_id AS doc_id, count(*)::BIGINT AS tokens FROM ({DOCS}) GROUP BY 1")
def udtf_words(spark, d):
    """The lexer as a table function; `tokenize` is its built-in twin and the one to use."""
    spark.udtf.register("words_of", F.udtf(_Words, returnType="word string"))
    table(spark, d, "documents").select("doc_id", "text").createOrReplaceTempView("texts")
    return spark.sql("SELECT doc_id, count(*) AS tokens FROM texts, LATERAL words_of(text) GROUP BY doc_id")


@query(TYPED + " SELECT clone_type, count(*)::BIGINT AS pairs FROM cls GROUP BY 1")
def sink_bands(spark, d):
    """Pairs written in a folder a band, and read back."""
    path = f"{shared_folder(spark)}/bands-{uuid.uuid4().hex}"
    write_bands(_typed(spark, d).select("b", "c", "clone_type"), path)
    return spark.read.schema("b long, c long, clone_type string").parquet(path).groupBy("clone_type").agg(F.count("*").alias("pairs"))


# ---------------------------------------------------------------- around the detector
query("SELECT doc_id, 'quality' AS label, quality::INT AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic::INT FROM labels", "unpivot_labels")(
    lambda s, d: table(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "label", "value"))
query("SELECT d.doc_id IS NOT NULL AS in_documents, l.doc_id IS NOT NULL AS in_labels, count(*)::BIGINT AS n FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY 1, 2", "full_outer_labels")(
    lambda s, d: table(s, d, "documents").select(F.col("doc_id").alias("x")).join(table(s, d, "labels").select(F.col("doc_id").alias("y")), F.col("x") == F.col("y"), "full").groupBy(F.col("x").isNotNull().alias("in_documents"), F.col("y").isNotNull().alias("in_labels")).agg(F.count("*").alias("n")))
query(f"WITH {bags()}, t AS (SELECT project_id, token, sum(f)::BIGINT AS n FROM bag GROUP BY ALL) SELECT project_id, token, n, r::INT AS r FROM (SELECT *, row_number() OVER (PARTITION BY project_id ORDER BY n DESC, token) AS r FROM t) WHERE r <= 3", "top_tokens_by_source")(
    lambda s, d: bag_of_tokens(tokenize(docs_of(s, d))).groupBy("project_id", "token").agg(F.sum("freq").alias("n")).withColumn("r", F.row_number().over(Window.partitionBy("project_id").orderBy(F.desc("n"), "token"))).where("r <= 3"))
query("SELECT regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, count(*)::BIGINT AS pages FROM pages GROUP BY 1", "pages_by_host")(
    lambda s, d: table(s, d, "pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count("*").alias("pages")))
query(name="approximate_by_source")(lambda s, d: docs_of(s, d).groupBy("project_id").agg(F.approx_count_distinct("text").alias("texts"), F.approx_percentile(F.length("text"), 0.5).alias("middle")))


# ---------------------------------------------------------------- joined streams
query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts - INTERVAL 1 HOUR AND a.ts + INTERVAL 1 HOUR", "stream_stream_join")(
    lambda s, d: streams.finish(streams.clicks_and_purchases(streams.events_stream(s, d))))
query("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey", "stream_static_join")(
    lambda s, d: streams.finish(streams.events_stream(s, d).join(table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "c_mktsegment")))
