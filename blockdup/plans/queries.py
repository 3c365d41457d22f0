"""The registry of named queries and of their DuckDB oracles.

Oracles are independent: multiset overlaps by brute force, never the filter pipeline again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import order as orders
from ..functions.tokens import bag_map, bag_of_tokens, count_loc, tokenize
from ..operators import baselines, blocks, detect, groups, relational, subblocks, types
from ..operators.index import full_index, partial_index
from ..sources.io import round_trip, stage, table
from ..streaming import streams
from . import experiments, measures

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if oracle:
            ORACLES[name or f.__name__] = oracle
        return f

    return add


# ---------------------------------------------------------------- pieces of oracles
DOCS = r"SELECT doc_id AS block_id, source AS project_id, unnest(regexp_extract_all(text, '[\p{L}\p{N}_]+')) AS token FROM documents"


def bags(tokens: str = DOCS) -> str:
    return f"tok AS ({tokens}), bag AS (SELECT block_id, project_id, token, count(*)::BIGINT AS f FROM tok GROUP BY ALL), sz AS (SELECT block_id, project_id, sum(f)::BIGINT AS n FROM bag GROUP BY ALL)"


def overlaps(tokens: str = DOCS, least: int = 0) -> str:
    """pr: all pairs with a common token, larger block first."""
    keep = f" JOIN sz USING (block_id) WHERE n >= {least}" if least else ""
    return (
        f"{bags(tokens)}, kept AS (SELECT bag.block_id, token, f FROM bag{keep}), "
        "ov AS (SELECT a.block_id AS x, b.block_id AS y, sum(least(a.f, b.f))::BIGINT AS o FROM kept a JOIN kept b ON a.token = b.token AND a.block_id < b.block_id GROUP BY 1, 2), "
        "pr AS (SELECT CASE WHEN s.n >= t.n THEN x ELSE y END AS b, CASE WHEN s.n >= t.n THEN y ELSE x END AS c, greatest(s.n, t.n) AS n_b, least(s.n, t.n) AS n_c, o AS overlap, "
        "CASE WHEN s.n >= t.n THEN s.project_id ELSE t.project_id END AS project_b, CASE WHEN s.n >= t.n THEN t.project_id ELSE s.project_id END AS project_c FROM ov JOIN sz s ON x = s.block_id JOIN sz t ON y = t.block_id)"
    )


PAIR_SQL = "SELECT b, c, n_b::INT AS n_b, n_c::INT AS n_c, overlap::INT AS overlap, overlap::DOUBLE / n_b AS similarity FROM pr"


def clone_sql(where: str, tokens: str = DOCS, least: int = 0, select: str = PAIR_SQL) -> str:
    return f"WITH {overlaps(tokens, least)} {select} WHERE {where}"


def at(theta_pm: int) -> str:
    return f"overlap * 1000 >= n_b * {theta_pm}"


CL7 = f"{overlaps()}, cl AS (SELECT * FROM pr WHERE {at(700)})"


def docs_of(spark: SparkSession, d: str) -> DataFrame:
    return blocks.document_blocks(table(spark, d, "documents"))


def pair(df: DataFrame) -> DataFrame:
    return df.select(*detect.PAIR)


def ordered_docs(spark: SparkSession, d: str, order: str = "token_frequency") -> DataFrame:
    return stage(detect.order_of(docs_of(spark, d), order=order), "ordered")


def clones7(spark: SparkSession, d: str) -> DataFrame:
    return stage(detect.detect_clones(docs_of(spark, d)), "pairs")


# ---------------------------------------------------------------- pairs
for _t in (500, 600, 700, 800, 900, 1000):
    query(clone_sql(at(_t)), f"clones_overlap_{_t}")(lambda s, d, t=_t: pair(detect.detect_clones(docs_of(s, d), t)))
query(clone_sql("overlap > (n_b * 700 + 999) // 1000"), "clones_strict_700")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), strict=True)))
query(clone_sql("overlap * 1700 >= (n_b + n_c) * 700", select=PAIR_SQL.replace("overlap::DOUBLE / n_b", "overlap::DOUBLE / (n_b + n_c - overlap)")), "clones_jaccard_700")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), 700, "jaccard")))
query(clone_sql("overlap * overlap * 1000000 >= n_b * n_c * 490000", select=PAIR_SQL.replace("overlap::DOUBLE / n_b", "overlap::DOUBLE / sqrt((n_b * n_c)::DOUBLE)")), "clones_cosine_700")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), 700, "cosine")))
query(clone_sql(f"{at(700)} AND project_b = project_c"), "clones_intra_source")(lambda s, d: pair(detect.detect_within(docs_of(s, d))))
query(clone_sql(f"{at(700)} AND project_b <> project_c"), "clones_inter_source")(lambda s, d: pair(detect.detect_across(docs_of(s, d))))
query(clone_sql(at(700)), "clones_partitioned_4")(lambda s, d: pair(detect.detect_partitioned(docs_of(s, d), 4)))
query(clone_sql(at(700)), "clones_longer_prefix")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), min_shared=8)))
query(clone_sql(at(700)), "clones_shortest_prefix")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), min_shared=1)))
query(clone_sql(at(700)), "clones_split_hot")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), hot=8)))
query(clone_sql(at(700)), "clones_without_collapse")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), collapse=False)))
query(clone_sql(at(700)), "verify_join")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), verifier="join")))
query(clone_sql(at(700)), "full_index_join")(lambda s, d: pair(baselines.full_index_join(ordered_docs(s, d))))
query(clone_sql(at(700)), "all_pairs")(lambda s, d: pair(detect.detect_clones(docs_of(s, d), every=True)))
for _o in orders.ORDERS:
    query(clone_sql(at(700)), f"order_{_o}")(lambda s, d, o=_o: pair(detect.detect_clones(docs_of(s, d), order=o)))


def _between_sql(left: str, right: str, theta: int = 700) -> str:
    size = lambda k, q: f"{k}t AS ({q}), {k}b AS (SELECT block_id, token, count(*)::BIGINT AS f FROM {k}t GROUP BY ALL), {k}s AS (SELECT block_id, sum(f)::BIGINT AS n FROM {k}b GROUP BY ALL)"
    return f"WITH {size('l', left)}, {size('r', right)}, ov AS (SELECT x.block_id AS b, y.block_id AS c, sum(least(x.f, y.f))::BIGINT AS o FROM lb x JOIN rb y USING (token) GROUP BY 1, 2) SELECT b, c, ls.n::INT AS n_b, rs.n::INT AS n_c, o::INT AS overlap, o::DOUBLE / greatest(ls.n, rs.n) AS similarity FROM ov JOIN ls ON b = ls.block_id JOIN rs ON c = rs.block_id WHERE o * 1000 >= greatest(ls.n, rs.n) * {theta}"


@query(_between_sql(DOCS + " WHERE source = 'src0'", DOCS + " WHERE source <> 'src0'"))
def clones_one_source_vs_rest(spark, d):
    b = docs_of(spark, d)
    return detect.detect_between(b.where("project_id = 'src0'"), b.where("project_id <> 'src0'"))


def _line_sql(name: str, id: str, least: int) -> str:
    lines = f"SELECT {id} AS file, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS ln FROM {name}"
    return f"SELECT file * 1048576 + ln AS block_id, 'x' AS project_id, unnest(regexp_extract_all(line, '[\\p{{L}}\\p{{N}}_]+')) AS token FROM ({lines}) WHERE len(regexp_extract_all(line, '[\\p{{L}}\\p{{N}}_]+')) >= {least}"


@query(_between_sql(_line_sql("benchmark", "item_id", 6), _line_sql("documents", "doc_id", 6)))
def clones_benchmark_lines(spark, d):
    one = blocks.size_limits(blocks.line_blocks(table(spark, d, "benchmark"), id="item_id", project=None), min_tokens=6)
    two = blocks.size_limits(blocks.line_blocks(table(spark, d, "documents")), min_tokens=6)
    return detect.detect_between(one, two)


@query(clone_sql(at(700), _line_sql("documents", "doc_id", 6)))
def clones_line_blocks(spark, d):
    return pair(detect.detect_clones(blocks.size_limits(blocks.line_blocks(table(spark, d, "documents")), min_tokens=6)))


HTML = r"SELECT page_id AS block_id, 'x' AS project_id, unnest(regexp_extract_all(html, '[\p{L}\p{N}_]+')) AS token FROM pages"


@query(clone_sql(at(700), HTML))
def clones_pages_html(spark, d):
    return pair(detect.detect_clones(blocks.document_blocks(table(spark, d, "pages"), "page_id", "html", None)))


@query(clone_sql(at(700), HTML.replace("html,", "regexp_replace(html, '(?s)<!--.*?-->|<script\\b.*?</script>|<style\\b.*?</style>|<[^>]*>', ' ', 'g'),")))
def clones_pages_lexed(spark, d):
    return pair(detect.detect_clones(blocks.document_blocks(table(spark, d, "pages"), "page_id", "html", None), profile="html"))


@query(clone_sql(at(700), "SELECT user_id AS block_id, 'all' AS project_id, event_type AS token FROM events"))
def clones_user_event_types(spark, d):
    bag = blocks.relation_blocks(table(spark, d, "events"), "user_id", "event_type")
    return pair(detect.detect_ordered(orders.ordered_blocks(bag)))


PARTS = "SELECT p_partkey AS block_id, 'all' AS project_id, token FROM (SELECT p_partkey, unnest([p_brand, p_type, p_name]) AS token FROM part)"


@query(clone_sql(at(700), PARTS))
def clones_part_attributes(spark, d):
    parts = table(spark, d, "part").select("p_partkey", F.explode(F.array("p_brand", "p_type", "p_name")).alias("token"))
    return pair(detect.detect_ordered(orders.ordered_blocks(blocks.relation_blocks(parts, "p_partkey", "token"))))


TURNS = r"SELECT conv_id * 1000 + turn AS block_id, 'x' AS project_id, unnest(regexp_extract_all(text, '[\p{L}\p{N}_]+')) AS token FROM conversations"


@query(clone_sql("TRUE", TURNS) + " ORDER BY overlap DESC, b, c LIMIT 20")
def conversation_turns_overlap_top(spark, d):
    turns = table(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), "text")
    o = stage(detect.order_of(blocks.document_blocks(turns, "id", "text", None)), "ordered")
    p = full_index(o)
    found = detect.candidates(p, p, filters=frozenset(), hot=None)
    return found.select("b", "c", "n_b", "n_c", F.col("seen").alias("overlap"), (F.col("seen") / F.col("n_b")).alias("similarity")).orderBy(F.desc("overlap"), "b", "c").limit(20)


# ---------------------------------------------------------------- internals
query(f"WITH {bags()} SELECT block_id, project_id, token, f::INT AS freq FROM bag", "bag_of_tokens")(lambda s, d: bag_of_tokens(tokenize(docs_of(s, d))))
GTF = "gtf AS (SELECT token, sum(f)::BIGINT AS gf, count(*)::BIGINT AS df FROM bag GROUP BY token)"
query(f"WITH {bags()}, {GTF} SELECT * FROM gtf", "global_token_frequency")(lambda s, d: orders.global_token_frequency(bag_of_tokens(tokenize(docs_of(s, d)))))
query(f"WITH {bags()}, {GTF}, g AS (SELECT gf, count(*)::BIGINT AS tokens FROM gtf GROUP BY gf) SELECT gf, tokens, (coalesce(sum(tokens) OVER (ORDER BY gf DESC ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) + 1)::BIGINT AS rank FROM g", "zipf_profile")(lambda s, d: orders.zipf_profile(bag_of_tokens(tokenize(docs_of(s, d)))))
ELEMENTS = f"WITH {bags()}, {GTF}, el AS (SELECT block_id, token, gf, unnest(range(1, f + 1)) AS k FROM bag JOIN gtf USING (token)), pos AS (SELECT el.block_id, token, k, n, row_number() OVER (PARTITION BY el.block_id ORDER BY gf, token, k) AS pos FROM el JOIN sz USING (block_id)), post AS (SELECT * FROM pos WHERE pos <= n - (n * 700 + 999) // 1000 + 1)"
query(ELEMENTS + " SELECT block_id, token || chr(1) || k AS element, pos::INT AS pos, n::INT AS n FROM post", "partial_index")(lambda s, d: partial_index(ordered_docs(s, d)).select("block_id", "element", "pos", "n"))
query(ELEMENTS + " SELECT block_id, count(*)::BIGINT AS sub_block, min(token || chr(1) || k) FILTER (pos = 1) AS rarest FROM post GROUP BY block_id", "ordered_sub_blocks")(lambda s, d: ordered_docs(s, d).select("block_id", (F.col("n") - F.floor((F.col("n").cast("long") * 700 + 999) / 1000) + 1).cast("long").alias("sub_block"), F.col("elements")[0].alias("rarest")))
query(ELEMENTS + " SELECT (SELECT count(*) FROM el)::BIGINT AS postings", "full_index_size")(lambda s, d: full_index(ordered_docs(s, d)).agg(F.count("*").alias("postings")))
CANDIDATES = ELEMENTS + ", ca AS (SELECT x.block_id AS b, y.block_id AS c, x.n AS n_b, y.n AS n_c, count(*) AS seen, max(x.pos) AS last_b, max(y.pos) AS last_c FROM post x JOIN post y ON x.token = y.token AND x.k = y.k AND (x.n > y.n OR (x.n = y.n AND x.block_id < y.block_id)) AND y.n * 1000 >= x.n * 700 GROUP BY ALL) SELECT b, c, n_b::INT AS n_b, n_c::INT AS n_c, seen::INT AS seen, last_b::INT AS last_b, last_c::INT AS last_c FROM ca"


def _candidates(spark, d, filters):
    p = partial_index(ordered_docs(spark, d))
    return detect.candidates(p, p, filters=frozenset(filters))


query(CANDIDATES, "candidates_prefix")(lambda s, d: subblocks.candidates(docs_of(s, d)))


@query(CANDIDATES + " WHERE (seen + least(n_b - last_b, n_c - last_c)) * 1000 >= n_b * 700")
def candidates_position(spark, d):
    """The bound after the last element in common alone; a test at every posting as well can let further pairs through."""
    return subblocks.candidates(docs_of(spark, d), position=True)


@query(f"WITH {CL7} SELECT b, c, overlap::INT AS overlap FROM cl")
def verify_merge(spark, d):
    return merged(spark, d).where("outcome = 'accepted'").select("b", "c", "overlap")


def merged(spark: SparkSession, d: str, early_accept: bool = False) -> DataFrame:
    """All candidates at 0.7 through the merge verifier."""
    o = stage(orders.ordered_blocks(bag_of_tokens(tokenize(docs_of(spark, d))), keys=True), "ordered")
    p = partial_index(o)
    return detect.verify_merge(detect.candidates(p, p), o, o, 700, early_accept=early_accept)


@query(f"WITH {bags()} SELECT block_id, count(*)::BIGINT AS kinds, max(f)::INT AS most FROM bag GROUP BY block_id")
def bag_maps(spark, d):
    m = bag_map(bag_of_tokens(tokenize(docs_of(spark, d))))
    return m.select("block_id", F.size("bag").cast("long").alias("kinds"), F.array_max(F.map_values("bag")).alias("most"))


# ---------------------------------------------------------------- measures
@query(
    ELEMENTS + ", pj AS (SELECT doc_id AS block_id, source AS project_id FROM documents), ca AS (SELECT x.block_id AS b, y.block_id AS c, p.project_id, any_value(x.n) AS n_b, any_value(y.n) AS n_c, count(*) AS seen, max(x.pos) AS last_b, max(y.pos) AS last_c FROM post x JOIN post y ON x.token = y.token AND x.k = y.k AND (x.n > y.n OR (x.n = y.n AND x.block_id < y.block_id)) AND y.n * 1000 >= x.n * 700 JOIN pj p ON x.block_id = p.block_id JOIN pj q ON y.block_id = q.block_id AND p.project_id = q.project_id GROUP BY 1, 2, 3), "
    "bl AS (SELECT project_id, count(*)::BIGINT AS blocks FROM sz GROUP BY 1) SELECT bl.project_id, blocks, (blocks * (blocks - 1) // 2)::BIGINT AS quadratic, count(b)::BIGINT AS f1, count(*) FILTER ((seen + least(n_b - last_b, n_c - last_c)) * 1000 >= n_b * 700)::BIGINT AS f1f3 FROM bl LEFT JOIN ca USING (project_id) GROUP BY 1, 2, 3"
)
def comparisons_by_source(spark, d):
    return measures.comparisons_by_project(ordered_docs(spark, d))


query(ELEMENTS + ' SELECT (SELECT count(*) FROM el)::BIGINT AS "full", (SELECT count(*) FROM post)::BIGINT AS "partial"', "index_ratio")(lambda s, d: measures.index_ratio(ordered_docs(s, d)))
query(f"WITH {CL7}, named AS (SELECT b AS id FROM cl UNION SELECT c FROM cl) SELECT (SELECT count(*) FROM sz)::BIGINT AS blocks, (SELECT count(*) FROM named)::BIGINT AS covered", "clone_coverage")(lambda s, d: measures.coverage(clones7(s, d), ordered_docs(s, d)))


@query(CANDIDATES.replace(") SELECT b, c, n_b", "), " + f"{overlaps().split('sz AS', 1)[1].split('), ', 1)[1]} SELECT ca.b, count(*)::BIGINT AS false_candidates FROM ca LEFT JOIN pr ON ca.b = pr.b AND ca.c = pr.c AND pr.overlap * 1000 >= pr.n_b * 700 WHERE pr.b IS NULL GROUP BY ca.b --", 1))
def false_positive_candidates(spark, d):
    return measures.false_candidates(_candidates(spark, d, {"prefix", "size"}), clones7(spark, d))


query(f"WITH {CL7} SELECT b, c FROM cl ORDER BY md5(b || '-' || c) LIMIT 390", "precision_sample_390")(lambda s, d: measures.judged_sample(clones7(s, d)).select("b", "c"))


@query("SELECT source, count(*)::BIGINT AS blocks, ceil(384.16 / (1 + 383.16 / count(*)))::INT AS reports FROM documents WHERE text IS NOT NULL AND doc_id IS NOT NULL GROUP BY source")
def sample_size(spark, d):
    """Blocks of each source to judge for a proportion within 0.05, with the finite correction for its number of blocks."""
    blocks_of = docs_of(spark, d).groupBy(F.col("project_id").alias("source")).agg(F.count("*").alias("blocks"))
    return blocks_of.withColumn("reports", measures.sample_sizes(F.col("blocks")))


query(r"SELECT source, sum(len(list_filter(string_split(text, chr(10)), lambda x: trim(regexp_replace(x, '\s+', ' ', 'g')) <> '')))::BIGINT AS loc FROM documents GROUP BY source", "loc_by_source")(lambda s, d: table(s, d, "documents").groupBy("source").agg(F.sum(count_loc(F.col("text"))).alias("loc")))
query("SELECT share_pm::INT AS share_pm, doc_id AS block_id FROM documents, (SELECT unnest([1, 10, 100, 1000]) AS share_pm) WHERE ('0x' || substr(md5(doc_id::VARCHAR), 1, 8))::BIGINT * 1000 < share_pm * 4294967296", "nested_samples")(lambda s, d: measures.nested_samples(docs_of(s, d)))


@query(f"WITH {overlaps()}, t AS (SELECT unnest([500, 600, 700, 800, 900, 1000])::INT AS theta_pm) SELECT theta_pm, count(*)::BIGINT AS pairs FROM t JOIN pr ON overlap * 1000 >= n_b * theta_pm GROUP BY 1")
def threshold_sweep(spark, d):
    """Pairs at each threshold; one run at the lowest finds all."""
    low = stage(detect.detect_clones(docs_of(spark, d), 500), "pairs")
    t = low.withColumn("theta_pm", F.explode(F.array(*(F.lit(x) for x in (500, 600, 700, 800, 900, 1000)))))
    return t.where(F.col("overlap").cast("long") * 1000 >= F.col("n_b").cast("long") * F.col("theta_pm")).groupBy("theta_pm").agg(F.count("*").alias("pairs"))


# ---------------------------------------------------------------- types and groups
T1SQL, T2SQL = r"trim(regexp_replace(text, '\s+', ' ', 'g'))", r"trim(regexp_replace(regexp_replace(lower(text), '\p{N}+', 'NUM', 'g'), '[^\p{L}\p{N}_]+', ' ', 'g'))"
T2TOK = rf"SELECT doc_id AS block_id, 'x' AS project_id, unnest(regexp_extract_all({T2SQL}, '[\p{{L}}\p{{N}}_]+')) AS token FROM documents"
_MS = "{p}b AS (SELECT block_id, token, count(*) AS f FROM {p}t WHERE token <> '' GROUP BY ALL), {p}s AS (SELECT block_id, sum(f) AS n FROM {p}b GROUP BY 1), {p}o AS (SELECT cl.b, cl.c, (sum(least(x.f, y.f)) * 1000 // greatest(any_value(u.n), any_value(v.n)))::INT AS pm FROM cl JOIN {p}b x ON cl.b = x.block_id JOIN {p}b y ON cl.c = y.block_id AND x.token = y.token JOIN {p}s u ON cl.b = u.block_id JOIN {p}s v ON cl.c = v.block_id GROUP BY 1, 2)"
T2LINE = T2SQL.replace("text", "line")
TYPED = (
    f"WITH {CL7}, kt AS ({T2TOK}), {_MS.format(p='k')}, lt AS (SELECT doc_id AS block_id, {T2LINE} AS token FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)), {_MS.format(p='l')}, "
    f"norm AS (SELECT doc_id, {T1SQL} AS t1, {T2SQL} AS t2 FROM documents), ty AS (SELECT cl.b, cl.c, project_b, project_c, coalesce(lo.pm, 0) AS line_pm, coalesce(ko.pm, 0) AS token_pm, p.t1 = q.t1 AS same1, p.t2 = q.t2 AS same2 FROM cl LEFT JOIN lo ON cl.b = lo.b AND cl.c = lo.c LEFT JOIN ko ON cl.b = ko.b AND cl.c = ko.c JOIN norm p ON cl.b = p.doc_id JOIN norm q ON cl.c = q.doc_id), "
    "cls AS (SELECT b, c, project_b, project_c, line_pm, token_pm, least(line_pm, token_pm)::INT AS sim_pm, CASE WHEN same1 THEN 'T1' WHEN same2 THEN 'T2' WHEN least(line_pm, token_pm) >= 900 THEN 'VST3' WHEN least(line_pm, token_pm) >= 700 THEN 'ST3' WHEN least(line_pm, token_pm) >= 500 THEN 'MT3' ELSE 'WT3/T4' END AS clone_type FROM ty)"
)


def _typed(spark, d):
    pairs = clones7(spark, d).select("b", "c", "project_b", "project_c")
    return types.classify(pairs, docs_of(spark, d))


query(TYPED + " SELECT b, c, line_pm, token_pm, sim_pm, clone_type FROM cls", "clone_types")(lambda s, d: _typed(s, d).drop("project_b", "project_c"))
query(TYPED + " SELECT clone_type, CASE WHEN project_b = project_c THEN 'intra' ELSE 'inter' END AS locality, count(*)::BIGINT AS pairs FROM cls GROUP BY ALL", "bands_by_locality")(lambda s, d: _typed(s, d).groupBy("clone_type", types.locality(F.col("project_b"), F.col("project_c")).alias("locality")).agg(F.count("*").alias("pairs")))
BOTH = "bo AS (SELECT b AS u, c AS v FROM cl UNION ALL SELECT c, b FROM cl)"
query(f"WITH {CL7}, {BOTH} SELECT u AS block_id, count(*)::BIGINT AS clones, min(v) AS first_clone FROM bo GROUP BY u", "clone_map")(lambda s, d: groups.clone_map(clones7(s, d)).select("block_id", F.size("clones").cast("long").alias("clones"), F.col("clones")[0].alias("first_clone")))
COMP = f"WITH RECURSIVE {CL7}, {BOTH}, reach AS (SELECT u AS block_id, u AS r FROM bo UNION SELECT reach.block_id, v FROM reach JOIN bo ON r = u), co AS (SELECT min(r) AS class_id, block_id FROM reach GROUP BY block_id)"
query(COMP + " SELECT * FROM co", "clone_components")(lambda s, d: groups.components_of(*detect.representatives(docs_of(s, d))))
query(COMP + ", si AS (SELECT class_id, count(*) AS m FROM co GROUP BY 1), li AS (SELECT class_id, count(*) AS l FROM cl JOIN co ON b = block_id GROUP BY 1) SELECT class_id, block_id FROM co JOIN si USING (class_id) JOIN li USING (class_id) WHERE l * 2 = m * (m - 1)", "clone_classes_complete")(lambda s, d: groups.clone_classes(clones7(s, d)).where("is_complete").select("class_id", "block_id"))
query(name="clone_classes")(lambda s, d: groups.clone_classes(clones7(s, d)))
query(COMP + " SELECT class_id, count(*)::BIGINT AS size, count(DISTINCT source)::BIGINT AS projects FROM co JOIN documents ON doc_id = block_id GROUP BY 1", "class_stats")(lambda s, d: groups.class_stats(groups.components_of(*detect.representatives(docs_of(s, d))), docs_of(s, d)))

# ---------------------------------------------------------------- baselines
for _l, _sql in (("t1", T1SQL), ("t2", T2SQL)):
    query(f"WITH n AS (SELECT doc_id, {_sql} AS t FROM documents) SELECT x.doc_id AS b, y.doc_id AS c FROM n x JOIN n y ON x.t = y.t AND x.doc_id < y.doc_id", f"normalized_hash_{_l}")(lambda s, d, level=_l: baselines.normalized_hash(docs_of(s, d), level))
query(name="token_runs")(lambda s, d: baselines.token_runs(docs_of(s, d)))
query(name="gapped_runs")(lambda s, d: baselines.gapped_runs(docs_of(s, d)))
query(name="line_lcs")(lambda s, d: baselines.line_lcs(docs_of(s, d)))
query(name="vector_windows")(lambda s, d: baselines.vector_windows(docs_of(s, d), **baselines.PRESETS["vectors"]))
query("SELECT x.vec_id AS b, y.vec_id AS c FROM embeddings x JOIN embeddings y ON x.vec_id < y.vec_id AND list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]) >= 0.6", "embedding_cosine")(lambda s, d: baselines.embedding_cosine(table(s, d, "embeddings"), 0.6))

# ---------------------------------------------------------------- experiments
query(name="mutant_recall")(lambda s, d: experiments.mutant_recall(s, table(s, d, "documents"), detectors=("bag", "line_lcs")))
query(name="mutant_recall_runs")(lambda s, d: experiments.mutant_recall(s, table(s, d, "documents"), detectors=("token_runs", "gapped_runs")))
query(name="recall_by_band")(lambda s, d: experiments.band_recall(table(s, d, "documents")))
query(_between_sql(DOCS + " WHERE source = 'src0'", DOCS + " WHERE source <> 'src0'"), "lookup_stored_index")(
    lambda s, d: experiments.lookup(s, docs_of(s, d).where("project_id <> 'src0'"), docs_of(s, d).where("project_id = 'src0'")).select(F.col("query_id").alias("b"), F.col("block_id").alias("c"), F.col("n_query").alias("n_b"), F.col("n_block").alias("n_c"), "overlap", "similarity"))


@query()
def scaling_curve(spark, d):
    return spark.createDataFrame(experiments.scaling(spark, table(spark, d, "documents")))


# ---------------------------------------------------------------- around the detector
@query("SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM benchmark b WHERE contains(d.text, b.text))")
def decontaminate_anti(spark, d):
    """Documents that hold no benchmark item word for word."""
    return relational.without_items(table(spark, d, "documents"), table(spark, d, "benchmark"))


query("SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)", "labelled_semi")(lambda s, d: table(s, d, "documents").join(table(s, d, "labels").where("quality = 1"), "doc_id", "left_semi").select("doc_id", "source"))
query(f"WITH {CL7}, bo AS (SELECT b AS u, c AS v, overlap::DOUBLE / n_b AS s FROM cl UNION ALL SELECT c, b, overlap::DOUBLE / n_b FROM cl) SELECT u AS block_id, v AS partner, s AS similarity FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY s DESC, v) AS r FROM bo) WHERE r = 1", "best_match_per_block")(lambda s, d: relational.best_match(clones7(s, d)))
query(f"WITH {CL7} SELECT b, c, overlap::INT AS overlap FROM cl ORDER BY overlap DESC, b, c LIMIT 10", "top_pairs")(lambda s, d: clones7(s, d).select("b", "c", "overlap").orderBy(F.desc("overlap"), "b", "c").limit(10))
query("SELECT lang, source, count(*)::BIGINT AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY ROLLUP (lang, source)", "rollup_lang_source")(lambda s, d: table(s, d, "documents").rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars")))
query(TYPED + ", k AS (SELECT clone_type, CASE WHEN project_b = project_c THEN 'intra' ELSE 'inter' END AS locality FROM cls) SELECT clone_type, locality, count(*)::BIGINT AS pairs FROM k GROUP BY CUBE (clone_type, locality)", "cube_band_locality")(lambda s, d: _typed(s, d).withColumn("locality", types.locality(F.col("project_b"), F.col("project_c"))).cube("clone_type", "locality").agg(F.count("*").alias("pairs")))


@query("SELECT l_returnflag, l_linestatus, count(*)::BIGINT AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")
def grouping_sets_flags(spark, d):
    table(spark, d, "lineitem").createOrReplaceTempView("lineitem")
    return spark.sql("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY l_returnflag, l_linestatus GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")


query(TYPED + " SELECT project_b, count(*) FILTER (clone_type = 'T1')::BIGINT AS \"T1\", count(*) FILTER (clone_type = 'VST3')::BIGINT AS \"VST3\" FROM cls GROUP BY 1", "pivot_bands")(lambda s, d: _typed(s, d).groupBy("project_b").pivot("clone_type", ["T1", "VST3"]).count().fillna(0, ["T1", "VST3"]))
query(clone_sql(f"{at(700)} AND NOT (overlap * 1000 >= n_b * 800)", select="SELECT b, c FROM pr"), "set_ops_runs")(lambda s, d: detect.detect_clones(docs_of(s, d), 700).select("b", "c").exceptAll(detect.detect_clones(docs_of(s, d), 800).select("b", "c")))
query("SELECT a.event_id, b.value AS asof_value FROM events a ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY ALL) b ON a.user_id = b.user_id AND a.ts >= b.ts WHERE a.event_type = 'click'", "asof_events")(
    lambda s, d: relational.asof_join(table(s, d, "events").where("event_type = 'click'").select("event_id", "user_id", "ts"), table(s, d, "events").where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("value").alias("value")), "user_id", "ts", "value").select("event_id", "asof_value"))
query("SELECT a.event_id AS l_event_id, b.event_id AS r_event_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND abs(epoch(date_trunc('second', a.ts)) - epoch(date_trunc('second', b.ts))) <= 3600", "interval_events")(
    lambda s, d: relational.interval_join(table(s, d, "events").where("event_type = 'click'").select("event_id", "user_id", "ts"), table(s, d, "events").where("event_type = 'purchase'").select("event_id", "user_id", "ts"), "user_id", "ts", 3600).select("l_event_id", "r_event_id"))
query(f"WITH {bags()} SELECT x.block_id, x.n::INT AS n, (count(y.block_id) - 1)::BIGINT AS partners FROM sz x JOIN sz y ON least(x.n, y.n) * 1000 >= greatest(x.n, y.n) * 900 GROUP BY ALL", "range_sizes")(lambda s, d: relational.size_band_counts(bag_of_tokens(tokenize(docs_of(s, d))).groupBy("block_id").agg(F.sum("freq").cast("int").alias("n")), 900))
query("SELECT event_id, sum(value) OVER w AS running, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)", "window_frames_events")(
    lambda s, d: table(s, d, "events").select("event_id", F.sum("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)).alias("running"), F.lag("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("before")))
query("SELECT json_extract_string(props, '$.k') AS k, count(*)::BIGINT AS n FROM events GROUP BY 1", "json_props")(lambda s, d: table(s, d, "events").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n")))
query("SELECT date_trunc('month', o_orderdate)::DATE AS month, count(*)::BIGINT AS n FROM orders GROUP BY 1", "date_buckets_orders")(lambda s, d: table(s, d, "orders").groupBy(F.trunc("o_orderdate", "month").alias("month")).agg(F.count("*").alias("n")))
query("SELECT doc_id, length(text)::INT AS chars, lower(substr(text, 1, 10)) AS head, md5(text) AS digest, len(string_split(text, chr(10)))::INT AS lines FROM documents", "string_profile")(lambda s, d: table(s, d, "documents").select("doc_id", F.length("text").alias("chars"), F.lower(F.substring("text", 1, 10)).alias("head"), F.md5("text").alias("digest"), F.size(F.split("text", "\n")).alias("lines")))
query("SELECT doc_id, lang, source, n_chars FROM documents WHERE lang = 'en'", "scan_pushdown")(lambda s, d: table(s, d, "documents").where("lang = 'en'").select("doc_id", "lang", "source", "n_chars"))
for _f in ("json", "orc", "csv"):
    query("SELECT doc_id, lang, source, n_chars FROM documents", f"round_trip_{_f}")(lambda s, d, f=_f: round_trip(table(s, d, "documents").select("doc_id", "lang", "source", "n_chars"), f))
query("SELECT n_name, r_name, count(*)::BIGINT AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2", "broadcast_hierarchy")(
    lambda s, d: table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("n_name", "r_name").agg(F.count("*").alias("customers"), F.round(F.sum("c_acctbal"), 2).alias("balance")))
query("SELECT source, median(n_chars) AS middle, quantile_cont(n_chars, 0.9) AS high, count(DISTINCT lang)::BIGINT AS langs FROM documents GROUP BY 1", "percentiles_by_source")(lambda s, d: table(s, d, "documents").groupBy("source").agg(F.percentile("n_chars", F.lit(0.5)).alias("middle"), F.percentile("n_chars", F.lit(0.9)).alias("high"), F.count_distinct("lang").alias("langs")))


# ---------------------------------------------------------------- streaming
query("SELECT date_trunc('day', ts) AS start, event_type, count(*)::BIGINT AS n FROM events WHERE date_trunc('day', ts) + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY 1, 2", "stream_tumbling")(lambda s, d: streams.finish(streams.tumbling(streams.events_stream(s, d))))
query("WITH w AS (SELECT unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS start FROM events) SELECT start, count(*)::BIGINT AS n FROM w WHERE start + INTERVAL 1 DAY <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY 1", "stream_sliding")(lambda s, d: streams.finish(streams.sliding(streams.events_stream(s, d))))
query("WITH e AS (SELECT *, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 6 HOUR, TRUE) AS fresh FROM events), g AS (SELECT *, sum(fresh::INT) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e) SELECT user_id, min(ts) AS start, count(*)::BIGINT AS n FROM g GROUP BY user_id, s HAVING max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR", "stream_session")(lambda s, d: streams.finish(streams.sessions(streams.events_stream(s, d))))
query("SELECT event_id, any_value(user_id) AS user_id FROM events GROUP BY event_id", "stream_dedupe")(lambda s, d: streams.finish(streams.deduplicated(streams.events_stream(s, d))))
query("SELECT user_id, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2", "stream_user_bags")(lambda s, d: streams.finish(streams.user_bags(streams.events_stream(s, d)), "update"))
query(_between_sql(DOCS + " WHERE source = 'src0'", DOCS + " WHERE source <> 'src0'"), "stream_lookup")(lambda s, d: streams.lookup_stream(s, d).select(F.col("query_id").alias("b"), F.col("block_id").alias("c"), F.col("n_query").alias("n_b"), F.col("n_block").alias("n_c"), "overlap", "similarity"))
