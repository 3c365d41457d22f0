"""Named queries on what stands around the detector: sources, windows, dates, JSON, UDFs, hints, samples, late rows, plans,
lexers of code, live bounds and costs, growth, orders, stored indexes."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.order import ORDERS, ordered_blocks
from ..functions.tokens import token_array, token_kind, tokenize
from ..operators import blocks, detect, subblocks
from ..operators.index import IndexedRepository, partial_index
from ..sources.io import shared_folder, stage, table, text_files
from ..streaming import streams
from . import experiments, measures
from .queries import CL7, DOCS, ELEMENTS, ORACLES, at, bags, clone_sql, clones7, docs_of, ordered_docs, pair, query
from .queries import _between_sql, _line_sql

# ---------------------------------------------------------------- sources
query("SELECT md5(text || chr(10)) AS digest, count(*)::BIGINT AS files FROM benchmark GROUP BY 1", "source_text_files")(lambda s, d: _written_items(s, d).groupBy(F.md5("text").alias("digest")).agg(F.count("*").alias("files")))


def _written_items(spark, d) -> DataFrame:
    """Benchmark items as text files, one each, read back whole."""
    path = f"{shared_folder(spark)}/items-{uuid.uuid4().hex}"
    table(spark, d, "benchmark").select("item_id", "text").write.partitionBy("item_id").text(path)
    return text_files(spark, f"{path}/*/*.txt")


# ---------------------------------------------------------------- windows
@query("SELECT doc_id, rank() OVER w AS r, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr, ntile(4) OVER (PARTITION BY source ORDER BY n_chars, doc_id) AS q FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars)")
def ranking_windows(spark, d):
    w, total = Window.partitionBy("source").orderBy("n_chars"), Window.partitionBy("source").orderBy("n_chars", "doc_id")
    long = lambda c: c.cast("long")
    return table(spark, d, "documents").select("doc_id", long(F.rank().over(w)).alias("r"), long(F.dense_rank().over(w)).alias("dr"), F.round(F.percent_rank().over(w), 9).alias("pr"), long(F.ntile(4).over(total)).alias("q"))


@query("SELECT event_id, first_value(event_id) OVER w AS opened, last_value(event_id) OVER w AS closed, coalesce(nth_value(event_id, 2) OVER w, -1) AS second, coalesce(lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id), -1) AS following FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def analytic_windows(spark, d):
    o = Window.partitionBy("user_id").orderBy("ts", "event_id")
    w = o.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.first("event_id").over(w).alias("opened"), F.last("event_id").over(w).alias("closed"), F.coalesce(F.nth_value("event_id", 2).over(w), F.lit(-1)).alias("second"), F.coalesce(F.lead("event_id").over(o), F.lit(-1)).alias("following"))


query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts))::BIGINT RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)::BIGINT AS in_a_day FROM events", "range_frames")(
    lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(F.unix_timestamp("ts")).rangeBetween(-86400, 0)).alias("in_a_day")))

# ---------------------------------------------------------------- dates, JSON
query("SELECT o_orderkey, year(o_orderdate)::INT AS y, quarter(o_orderdate)::INT AS q, (dayofweek(o_orderdate) + 1)::INT AS dow, date_diff('day', DATE '1990-01-01', o_orderdate::DATE)::INT AS days, last_day(o_orderdate::DATE)::VARCHAR AS month_end, (o_orderdate::DATE + INTERVAL 1 MONTH)::DATE::VARCHAR AS later FROM orders", "date_functions")(
    lambda s, d: table(s, d, "orders").withColumn("day", F.to_date("o_orderdate")).select("o_orderkey", F.year("day").alias("y"), F.quarter("day").alias("q"), F.dayofweek("day").alias("dow"), F.datediff("day", F.lit("1990-01-01").cast("date")).alias("days"), F.last_day("day").cast("string").alias("month_end"), F.add_months("day", 1).cast("string").alias("later")))
query("SELECT event_id, json_extract_string(props, '$.k') AS k FROM events", "json_struct")(lambda s, d: table(s, d, "events").select("event_id", F.from_json("props", "k string")["k"].alias("k")))

# ---------------------------------------------------------------- UDFs, hints, samples


@query(f"SELECT CASE WHEN regexp_matches(token, '^\\p{{N}}') THEN 'literal' ELSE 'identifier' END AS kind, count(*)::BIGINT AS n FROM ({DOCS}) GROUP BY 1")
def udf_token_kind(spark, d):
    """Kinds of tokens by a vectorised scalar UDF; `token_kind` is its built-in twin and the one to use."""

    def kind_of(token: pd.Series) -> pd.Series:
        return token.str[:1].map(lambda c: "literal" if c.isnumeric() else "identifier")

    kind = F.pandas_udf(kind_of, "string")
    return tokenize(docs_of(spark, d)).groupBy(kind("token").alias("kind")).agg(F.count("*").alias("n"))


@query("SELECT source, round(exp(avg(ln(n_chars + 1))), 6) AS middle FROM documents GROUP BY 1")
def udaf_geometric_mean(spark, d):
    """A grouped-aggregate UDF, of one number a document."""

    def middle_of(n: pd.Series) -> float:
        import numpy as np

        return float(np.exp(np.log1p(n).mean()))

    middle = F.pandas_udf(middle_of, "double")
    return table(spark, d, "documents").groupBy("source").agg(middle("n_chars").alias("middle")).select("source", F.round("middle", 6).alias("middle"))


for _hint in ("shuffle_hash", "merge"):
    query("SELECT source, quality::INT AS quality, count(*)::BIGINT AS n FROM documents JOIN labels USING (doc_id) GROUP BY ALL", f"join_hint_{_hint}")(
        lambda s, d, h=_hint: table(s, d, "documents").join(table(s, d, "labels").hint(h), "doc_id").groupBy("source", F.col("quality").cast("int").alias("quality")).agg(F.count("*").alias("n")))


@query("SELECT lang, count(*)::BIGINT AS n FROM documents WHERE lang IN ('en', 'de') GROUP BY 1")
def sample_strata(spark, d):
    """Strata sampled whole or not at all, which fixes the result; other shares go the same way."""
    return table(spark, d, "documents").sampleBy("lang", {"en": 1.0, "de": 1.0, "fr": 0.0}, seed=3).groupBy("lang").agg(F.count("*").alias("n"))


@query("SELECT count(*)::BIGINT AS whole FROM documents")
def sample_table(spark, d):
    table(spark, d, "documents").createOrReplaceTempView("sampled")
    return spark.sql("SELECT count(*) AS whole FROM sampled TABLESAMPLE (100 PERCENT) REPEATABLE (7)")


# ---------------------------------------------------------------- late rows of a stream
query(ORACLES["stream_tumbling"], "stream_late_rows")(lambda s, d: streams.finish(streams.tumbling(streams.events_with_late_rows(s, d))))


# ---------------------------------------------------------------- plans
@query("SELECT unnest(['pushed_filter', 'pruned_columns', 'no_cartesian_product', 'no_python']) AS fact, unnest([true, true, true, true]) AS holds")
def plan_facts(spark, d):
    """What the plans of a scan and of the detector's candidates must show."""
    scan = _plan(table(spark, d, "documents").where("lang = 'en'").select("doc_id"))
    p = partial_index(ordered_docs(spark, d))
    found = _plan(detect.candidates(p, p))
    facts = {"pushed_filter": "EqualTo(lang,en)" in scan, "pruned_columns": "ReadSchema: struct<doc_id:bigint,lang:string>" in scan, "no_cartesian_product": "CartesianProduct" not in found and "NestedLoop" not in found, "no_python": not any(x in found for x in ("Python", "Arrow", "Pandas"))}
    return spark.createDataFrame(list(facts.items()), "fact string, holds boolean")


def _plan(df: DataFrame) -> str:
    return df._jdf.queryExecution().toString()


# ---------------------------------------------------------------- lexers of code
def _code(spark, d, body: str) -> DataFrame:
    return table(spark, d, "part").select(F.concat(F.lit(body), F.col("p_partkey").cast("string"), F.lit(";")).alias("text"))


C_BODY = "/* sizes */ static int size_of(struct part *p) { unsigned n = 40; return sizeof(n); } // end\nint k = "
CSHARP_BODY = "public override string Name(int n) { foreach (var x in items) { n += 7; } return base.Name(n); } /* end */ int k = "
for _name, _body, _profile, _counts in (("c", C_BODY, "c", (7, 6, 2)), ("csharp", CSHARP_BODY, "csharp", (9, 9, 2))):
    query(f"SELECT unnest(['keyword', 'identifier', 'literal']) AS kind, unnest([{', '.join(f'{k} * count(*)' for k in _counts)}])::BIGINT AS n FROM part", f"token_kinds_{_name}")(
        lambda s, d, b=_body, p=_profile: _code(s, d, b).select(F.explode(token_array(F.col("text"), p)).alias("t")).groupBy(token_kind(F.col("t"), p).alias("kind")).agg(F.count("*").alias("n")))


_RANKED = "SELECT lang, token, row_number() OVER (PARTITION BY lang ORDER BY count(*) DESC, token) AS r FROM w GROUP BY lang, token"


@query(rf"WITH w AS (SELECT doc_id, lang, unnest(regexp_extract_all(text, '[\p{{L}}\p{{N}}_]+')) AS token FROM documents), top AS (SELECT * FROM ({_RANKED}) WHERE r <= 100) SELECT doc_id, count(*)::BIGINT AS tokens, (count(*) - count(top.token))::BIGINT AS renamed FROM w LEFT JOIN top USING (lang, token) GROUP BY doc_id")
def prose_blind(spark, d):
    """Blind renaming of prose: of each language's words all but the 100 commonest become one name."""
    docs = table(spark, d, "documents")
    return blocks.renamed_prose(docs).groupBy("doc_id").agg(F.count("*").alias("tokens"), F.sum((F.col("token") == "ID").cast("long")).alias("renamed"))


# ---------------------------------------------------------------- live bounds and costs
query(f"WITH {CL7} SELECT b, c FROM cl", "verify_early_accept")(lambda s, d: detect.detect_clones(docs_of(s, d), early_accept=True).select("b", "c"))


@query(name="token_comparisons")
def token_comparisons(spark, d):
    """Comparisons of elements in verification: every element with every other, two cursors, two cursors that accept early."""
    made = stage(subblocks.token_comparisons(docs_of(spark, d)), "comparisons")
    rows = [made.agg(F.sum(c).alias("comparisons"), F.sum("nested").alias("nested"), F.coalesce(F.sum("candidates"), F.lit(0)).alias("candidates")).withColumn("early_accept", F.lit(early)) for early, c in ((False, "compared"), (True, "early"))]
    return rows[0].unionByName(rows[1])


@query(ELEMENTS + ", ca AS (SELECT x.block_id AS b, y.block_id AS c, x.n AS n_b, y.n AS n_c, count(*) AS seen, max(x.pos) AS last_b, max(y.pos) AS last_c FROM pos x JOIN pos y ON x.token = y.token AND x.k = y.k AND (x.n > y.n OR (x.n = y.n AND x.block_id < y.block_id)) GROUP BY ALL) SELECT count(*)::BIGINT AS pairs, count(*) FILTER ((seen + least(n_b - last_b, n_c - last_c)) * 1000 >= n_b * 700)::BIGINT AS within_bound FROM ca")
def position_filter_alone(spark, d):
    """The bound from positions without sub-blocks: all elements indexed, pairs it leaves."""
    return subblocks.position_alone(docs_of(spark, d)).agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("pairs", "within_bound")))


@query(f"WITH {CL7} SELECT b, c, (('0x' || substr(md5(b || '-' || c), 1, 4))::BIGINT % 3)::INT AS judge FROM cl ORDER BY md5(b || '-' || c) LIMIT 390")
def precision_judges(spark, d):
    """The sample split among three judges."""
    return measures.judged_sample(clones7(spark, d)).select("b", "c", F.col("judge").cast("int").alias("judge"))


_GROWN = ORACLES["comparisons_by_source"]
_SLOPE = "round(regr_slope(ln({0}), ln(blocks)) FILTER ({0} > 0), 6) AS {0}"


@query(f"SELECT {', '.join(_SLOPE.format(c) for c in ('quadratic', 'f1', 'f1f3'))} FROM ({_GROWN})")
def comparisons_growth(spark, d):
    """Powers of the number of blocks with which comparisons grow from project to project: no filter, one, both."""
    points = stage(subblocks.comparisons(docs_of(spark, d)).withColumn("quadratic", (F.col("blocks") * (F.col("blocks") - 1) / 2).cast("long")), "points")
    out = None
    for c in ("quadratic", "f1", "f1f3"):
        row = measures.growth_slope(points, "blocks", c).select(F.round("slope", 6).alias(c))
        out = row if out is None else out.crossJoin(row)  # one row each
    return out


_SORTS = {"token_frequency": "gf, token, k", "element_frequency": "ef, token, k", "alphabetical": "token, k", "length": "-length(token), token, k", "popular_first": "-gf, token, k"}
_ORDER = "SELECT '{name}' AS \"order\", (SELECT count(*) FROM p{i})::BIGINT AS postings, (SELECT count(*) FROM (SELECT DISTINCT x.block_id, y.block_id FROM p{i} x JOIN p{i} y ON x.token = y.token AND x.k = y.k AND (x.n > y.n OR (x.n = y.n AND x.block_id < y.block_id)) AND y.n * 1000 >= x.n * 700))::BIGINT AS candidates"
_PLACES = "p{i} AS (SELECT * FROM (SELECT ek.block_id, token, k, n, row_number() OVER (PARTITION BY ek.block_id ORDER BY {sort}) AS pos FROM ek JOIN sz USING (block_id)) WHERE pos <= n - (n * 700 + 999) // 1000 + 1)"
query(
    f"WITH {bags()}, gtf AS (SELECT token, sum(f)::BIGINT AS gf FROM bag GROUP BY token), el AS (SELECT block_id, token, gf, unnest(range(1, f + 1)) AS k FROM bag JOIN gtf USING (token)), ef AS (SELECT token, k, count(*) AS ef FROM el GROUP BY ALL), ek AS (SELECT el.*, ef FROM el JOIN ef USING (token, k)), "
    + ", ".join(_PLACES.format(i=i, sort=_SORTS[name]) for i, name in enumerate(ORDERS)) + " " + " UNION ALL ".join(_ORDER.format(i=i, name=name) for i, name in enumerate(ORDERS)),
    "order_ablation")(lambda s, d: experiments.order_ablation(docs_of(s, d)))


# ---------------------------------------------------------------- representatives, stored indexes, other bags
_SIG = "sg AS (SELECT block_id, string_agg(token || ':' || f, ' ' ORDER BY token) AS s FROM bag GROUP BY 1), rp AS (SELECT block_id, min(block_id) OVER (PARTITION BY s) AS rep FROM sg)"


@query(f"WITH {CL7}, {_SIG} SELECT b, c, overlap::INT AS overlap FROM cl JOIN rp x ON b = x.block_id AND x.rep = b JOIN rp y ON c = y.block_id AND y.rep = c")
def clones_of_representatives(spark, d):
    """Pairs of distinct bags only; copies are told by the membership beside it."""
    return detect.representatives(docs_of(spark, d))[0].select("b", "c", "overlap")


@query(f"WITH {bags()}, {_SIG} SELECT rep, count(*)::BIGINT AS copies FROM rp GROUP BY 1")
def copies_of_representatives(spark, d):
    return detect.representatives(docs_of(spark, d))[1].groupBy("rep").agg(F.count("*").alias("copies"))


def _named(found: DataFrame) -> DataFrame:
    return found.select(F.col("query_id").alias("b"), F.col("block_id").alias("c"), F.col("n_query").alias("n_b"), F.col("n_block").alias("n_c"), "overlap", "similarity")


@query(_between_sql(DOCS + " WHERE source = 'src0'", DOCS + " WHERE source <> 'src0'"))
def lookup_after_append(spark, d):
    """An index of some projects, the others appended under its frozen order, one project looked up."""
    b = docs_of(spark, d)
    repo = IndexedRepository.build(b.where("project_id not in ('src0', 'src1', 'src2')"), f"{shared_folder(spark)}/index-{uuid.uuid4().hex}")
    repo.append(b.where("project_id in ('src1', 'src2')"))
    return _named(repo.query(b.where("project_id = 'src0'")))


@query(_between_sql(_line_sql("benchmark", "item_id", 6), _line_sql("documents", "doc_id", 6)))
def lookup_benchmark_lines(spark, d):
    """Lines of benchmark items looked up in a stored index of document lines."""
    asked = blocks.size_limits(blocks.line_blocks(table(spark, d, "benchmark"), id="item_id", project=None), min_tokens=6)
    lines = blocks.size_limits(blocks.line_blocks(table(spark, d, "documents")), min_tokens=6)
    return _named(IndexedRepository.build(lines, f"{shared_folder(spark)}/index-{uuid.uuid4().hex}").query(asked))


query(clone_sql(at(250), "SELECT l_suppkey AS block_id, 'all' AS project_id, l_partkey::VARCHAR AS token FROM lineitem"), "clones_supplier_parts")(
    lambda s, d: pair(detect.detect_ordered(ordered_blocks(blocks.relation_blocks(table(s, d, "lineitem").select("l_suppkey", F.col("l_partkey").cast("string").alias("part")), "l_suppkey", "part")), 250)))

#: Which of the near misses each technique reports, on a generated function a part.
_MISSES = {"bag": (True,) * 4, "gapped_runs": (True,) * 4, "token_runs": (False, False, True, False)}
query("SELECT kind, detector, detected, count(*)::BIGINT AS parts FROM part, (" + " UNION ALL ".join(f"SELECT unnest(['statements_swapped', 'conditions_joined', 'operators_changed', 'loop_rewritten']) AS kind, '{k}' AS detector, unnest([{', '.join(map(str, v))}]) AS detected" for k, v in _MISSES.items()) + ") GROUP BY ALL", "near_miss_kinds")(
    lambda s, d: experiments.near_misses(table(s, d, "part")))
query(name="scale_table")(lambda s, d: experiments.scale_table(s, table(s, d, "documents")))
query(name="index_bytes")(lambda s, d: experiments.index_bytes(s, docs_of(s, d)))
