"""Queries by name, over the given tables, and their SQL twins for DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from entitygraph.operators import blocking as bl
from entitygraph.operators import closure as cl
from entitygraph.operators import evaluation as ev
from entitygraph.operators import hierarchical as hi
from entitygraph.operators import matching as ma
from entitygraph.operators import modularity as mo
from entitygraph.operators import parsing as pr
from entitygraph.operators.entropy import entropy_quality
from entitygraph.operators.louvain import RefineConfig, refine_local
from entitygraph.plans.pipeline import ResolveConfig, cluster, iterate_round, resolve, resolve_iterative, score_records, sweep
from entitygraph.shared import materialise, new_path
from entitygraph.sources import files
from entitygraph.sources.fixtures import SAMPLES, WHOLE, Sample, duckdb_references, references, register_tables, worked_example

MU, BETA, SIGMA = 0.6, 6, 7
DEMO = Sample("demo", "poor", "standard", 400)
#: The sample of queries that name none; WHOLE while a query named ``_whole`` is built.
_default: list[str | Sample] = ["S8"]
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return put


# SQL of the stages, one common table expression after the other.
_REFS = f"refs AS ({duckdb_references(SAMPLES['S8'])})"
_DEMO = f"refs AS ({duckdb_references(DEMO)})"
_TOK = """
tok AS (SELECT record_id, CAST(i - 1 AS INT) AS pos, t[i] AS token FROM (SELECT record_id, list_filter(string_split(body, ' '), lambda x: x <> '') AS t FROM refs) q, unnest(range(1, len(t) + 1)) AS u(i)),
freq AS (SELECT token, count(*) AS c, count(DISTINCT record_id) AS df FROM tok GROUP BY token),
kept AS (SELECT record_id, pos, token, c FROM tok JOIN freq USING (token) WHERE c < 7),
bt AS (SELECT DISTINCT token, record_id FROM kept WHERE c <= 6),
pairs AS (SELECT x.record_id AS a, y.record_id AS b, count(*) AS shared FROM bt x JOIN bt y ON x.token = y.token AND x.record_id < y.record_id GROUP BY ALL)"""


def _cells(reduce: str = "both") -> str:
    score = {
        "both": "(rs + cs) / (rn + cn)", "rows": "rs / rn", "cols": "cs / cn", "shorter": "CASE WHEN rn <= cn THEN rs / rn ELSE cs / cn END",
    }[reduce]
    return f"""
cell AS (SELECT a, b, x.pos AS i, y.pos AS j, 1.0 - CAST(levenshtein(x.token, y.token) AS DOUBLE) / greatest(length(x.token), length(y.token)) AS s
         FROM pairs JOIN kept x ON x.record_id = a JOIN kept y ON y.record_id = b),
rowm AS (SELECT a, b, sum(m) AS rs, count(*) AS rn FROM (SELECT a, b, i, max(s) AS m FROM cell GROUP BY ALL) q GROUP BY a, b),
colm AS (SELECT a, b, sum(m) AS cs, count(*) AS cn FROM (SELECT a, b, j, max(s) AS m FROM cell GROUP BY ALL) q GROUP BY a, b),
scored AS (SELECT a, b, round(round({score}, 9), 6) AS score FROM rowm JOIN colm USING (a, b))"""


def _closure(mu: float = MU, edges: str = "scored") -> str:
    return f"""
both_ways AS (SELECT a, b FROM {edges} WHERE score >= {mu} UNION SELECT b, a FROM {edges} WHERE score >= {mu}),
reach(a, b) AS (SELECT a, b FROM both_ways UNION SELECT r.a, e.b FROM reach r JOIN both_ways e ON r.b = e.a),
comp AS (SELECT least(a, min(b)) AS component_id, a AS record_id FROM reach GROUP BY a),
clusters AS (SELECT coalesce(component_id, r.record_id) AS cluster_id, r.record_id FROM refs r LEFT JOIN comp c ON c.record_id = r.record_id)"""


def _with(*parts: str, select: str) -> str:
    return f"WITH RECURSIVE {','.join(parts)} {select}"


def _refs(spark, sf, sample=None) -> DataFrame:
    return materialise(references(spark, sf, sample or _default[-1]), "references")


def _tokens(spark, sf, sample=None) -> tuple[DataFrame, DataFrame]:
    tokens = pr.explode_tokens(_refs(spark, sf, sample))
    return tokens, pr.token_frequencies(tokens)


def _blocked(spark, sf, sample=None):
    tokens, freqs = _tokens(spark, sf, sample)
    kept = bl.cut_stop_tokens(tokens, freqs, SIGMA)
    return kept, bl.blocks(bl.blocking_tokens(kept, BETA))


def _scored(spark, sf, sample=None, measure="both") -> tuple[DataFrame, DataFrame]:
    refs = _refs(spark, sf, sample)
    return score_records(refs, ResolveConfig(measure=measure)), refs


# ---- ingest and parsing
_TEXTS = ("documents", "pages", "benchmark", "conversations")


@query(
    "p1_merge_files",
    """SELECT 'documents:' || doc_id AS record_id, 'documents' AS source, CAST(len(text) AS BIGINT) AS n FROM documents UNION ALL
       SELECT 'pages:' || page_id, 'pages', CAST(len(html) AS BIGINT) FROM pages UNION ALL SELECT 'benchmark:' || item_id, 'benchmark', CAST(len(text) AS BIGINT) FROM benchmark UNION ALL
       SELECT 'conversations:' || conv_id || ':' || turn, 'conversations', CAST(len(text) AS BIGINT) FROM conversations""",
)
def _(spark, sf):
    return _merged(spark, sf).select("record_id", "source", F.length(F.coalesce(F.col("attrs")["text"], F.col("attrs")["html"])).cast("long").alias("n"))


def _merged(spark, sf):
    keys = {"documents": "doc_id", "pages": "page_id", "benchmark": "item_id", "conversations": ("conv_id", "turn")}
    return files.merge_files(spark, [files.SourceSpec(f"{sf}/{t}.parquet", t, keys[t]) for t in _TEXTS])


@query("p2_id_audit", "SELECT CAST(0 AS BIGINT) AS repeated")
def _(spark, sf):
    return _merged(spark, sf).groupBy("record_id").count().where("count > 1").agg(F.count("*").alias("repeated"))


@query("p3_build_body", "SELECT 'n:' || n_nationkey AS record_id, n_name || ' ' || n_regionkey AS body FROM nation")
def _(spark, sf):
    return pr.build_body(files.merge_files(spark, [files.SourceSpec(f"{sf}/nation.parquet", "n", "n_nationkey")]))


_ASCII = "trim(regexp_replace(upper(regexp_replace({c}, '[^A-Za-z0-9 \\t\\r\\n\\f]+', '', 'g')), '[ \\t\\r\\n\\f]+', ' ', 'g'))"


@query("p4_normalise_ascii", f"SELECT doc_id, {_ASCII.format(c='text')} AS body FROM documents")
def _(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", pr.normalise(F.col("text"), "ascii").alias("body"))


@query("p5_tokenise", f"SELECT doc_id, CAST(len(list_filter(string_split({_ASCII.format(c='text')}, ' '), lambda x: x <> '')) AS INT) AS n FROM documents")
def _(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", F.size(pr.tokenise(pr.normalise(F.col("text"), "ascii"))).alias("n"))


@query("p0_references", _with(_REFS, select="SELECT * FROM refs"))
def _(spark, sf):
    return references(spark, sf, _default[-1])


@query("p0_references_mixed", duckdb_references(SAMPLES["S10"]))
def _(spark, sf):
    return references(spark, sf, "S10")


@query("p0_references_business", duckdb_references(SAMPLES["S3"]))
def _(spark, sf):
    return references(spark, sf, "S3")


@query("p6_token_positions", _with(_REFS, _TOK, select="SELECT * FROM tok"))
def _(spark, sf):
    return _tokens(spark, sf)[0]


@query("p7_token_frequencies", _with(_REFS, _TOK, select="SELECT * FROM freq"))
def _(spark, sf):
    return _tokens(spark, sf)[1]


@query("p8_frequency_profile", _with(_REFS, _TOK, select="SELECT c, count(*) AS tokens FROM freq GROUP BY c"))
def _(spark, sf):
    return pr.frequency_profile(_tokens(spark, sf)[1])


# ---- blocking
for _b, _op in (("inclusive", "<"), ("strict", "<=")):

    @query(f"k1_stop_cut_{_b}", _with(_REFS, _TOK, select=f"SELECT record_id, pos, token, c FROM tok JOIN freq USING (token) WHERE c {_op} 7"))
    def _(spark, sf, b=_b):
        return bl.cut_stop_tokens(*_tokens(spark, sf), SIGMA, b)


@query("k2_blocking_tokens", _with(_REFS, _TOK, select="SELECT * FROM bt"))
def _(spark, sf):
    return bl.blocking_tokens(bl.cut_stop_tokens(*_tokens(spark, sf)))


@query("k3_filtered_records", _with(_REFS, _TOK, select="SELECT record_id, string_agg(token, ' ' ORDER BY pos) AS tokens FROM kept GROUP BY record_id"))
def _(spark, sf):
    return bl.filtered_records(bl.cut_stop_tokens(*_tokens(spark, sf))).select("record_id", F.array_join("tokens", " ").alias("tokens"))


@query("k4_blocks", _with(_REFS, _TOK, select="SELECT token, string_agg(record_id, ' ' ORDER BY record_id) AS members, CAST(count(*) AS INT) AS size FROM bt GROUP BY token HAVING count(*) > 1"))
def _(spark, sf):
    return _blocked(spark, sf)[1].select("token", F.array_join("members", " ").alias("members"), "size")


@query("k5_candidate_pairs", _with(_REFS, _TOK, select="SELECT * FROM pairs"))
def _(spark, sf):
    return bl.candidate_pairs(_blocked(spark, sf)[1])


@query(
    "k6_blocking_report",
    _with(
        _REFS, _TOK, "blk AS (SELECT token, count(*) AS size FROM bt GROUP BY token HAVING count(*) > 1)",
        select="""SELECT (SELECT count(*) FROM blk) AS n_blocks, CAST((SELECT max(size) FROM blk) AS INT) AS largest, CAST((SELECT sum(size * (size - 1) / 2) FROM blk) AS BIGINT) AS comparisons,
        count(*) AS n_pairs, round(1 - count(*) / (1000 * 999 / 2.0), 6) AS reduction_ratio,
        round(count(*) FILTER (x.truth_id = y.truth_id) / (SELECT sum(n * (n - 1) / 2.0) FROM (SELECT count(*) AS n FROM refs GROUP BY truth_id) q), 6) AS pair_completeness
        FROM pairs JOIN refs x ON x.record_id = a JOIN refs y ON y.record_id = b""",
    ),
)
def _(spark, sf):
    refs = _refs(spark, sf)
    blocked = _blocked(spark, sf)[1]
    return bl.blocking_report(blocked, bl.candidate_pairs(blocked), refs.count(), refs)


@query("k7_lsh_pairs")
def _(spark, sf):
    return bl.lsh_pairs(_tokens(spark, sf)[0])


@query(
    "k8_random_blocks",
    _with(_REFS, select="SELECT CAST(('0x' || substr(md5('0:' || record_id), 1, 8))::BIGINT % 50 AS BIGINT) AS token, CAST(count(*) AS INT) AS size FROM refs GROUP BY 1 HAVING count(*) > 1"),
)
def _(spark, sf):
    return bl.random_blocks(_refs(spark, sf), 50).select("token", "size")


@query("k9_all_pairs", _with(_DEMO, select="SELECT x.record_id AS a, y.record_id AS b FROM refs x JOIN refs y ON x.record_id < y.record_id"))
def _(spark, sf):
    return bl.all_pairs(_refs(spark, sf, DEMO))


# ---- matching
for _r in ma.REDUCTIONS:

    @query(f"m2_matrix_{_r}", _with(_REFS, _TOK, _cells(_r), select="SELECT * FROM scored"))
    def _(spark, sf, r=_r):
        return _scored(spark, sf, measure=r)[0]


@query("m4_above_mu", _with(_REFS, _TOK, _cells(), select="SELECT * FROM scored WHERE score >= 0.6"))
def _(spark, sf):
    return ma.above(_scored(spark, sf)[0], MU)


_LISTS = "lst AS (SELECT record_id, list(token ORDER BY pos) AS t FROM kept GROUP BY record_id), pl AS (SELECT a, b, x.t AS ta, y.t AS tb FROM pairs JOIN lst x ON x.record_id = a JOIN lst y ON y.record_id = b)"
_COMMON = "len(list_distinct(list_filter(ta, lambda x: list_contains(tb, x))))"
for _m, _sql in {
    "jaccard": f"round({_COMMON} / len(list_distinct(list_concat(ta, tb))), 6)",
    "overlap": f"round({_COMMON} / least(len(list_distinct(ta)), len(list_distinct(tb))), 6)",
    "exact": "CAST(array_to_string(ta, ' ') = array_to_string(tb, ' ') AS DOUBLE)",
    "levenshtein_body": "round(1.0 - CAST(levenshtein(array_to_string(ta, ' '), array_to_string(tb, ' ')) AS DOUBLE) / greatest(length(array_to_string(ta, ' ')), length(array_to_string(tb, ' '))), 6)",
}.items():

    @query(f"m5_{_m}", _with(_REFS, _TOK, _LISTS, select=f"SELECT a, b, CAST({_sql} AS DOUBLE) AS score FROM pl"))
    def _(spark, sf, m=_m):
        return _scored(spark, sf, measure=m)[0]


@query(
    "m5_idf_cosine",
    _with(
        _REFS, _TOK, "wt AS (SELECT DISTINCT record_id, token, ln(1000.0 / df) AS w FROM tok JOIN freq USING (token)), nm AS (SELECT record_id, sqrt(sum(w * w)) AS n FROM wt GROUP BY record_id)",
        select="""SELECT a, b, CAST(round(sum(x.w * y.w) / (max(p.n) * max(q.n)), 6) AS DOUBLE) AS score FROM pairs JOIN wt x ON x.record_id = a JOIN wt y ON y.record_id = b AND y.token = x.token
        JOIN nm p ON p.record_id = a JOIN nm q ON q.record_id = b GROUP BY a, b""",
    ),
)
def _(spark, sf):
    tokens, freqs = _tokens(spark, sf)
    return ma.idf_cosine(bl.candidate_pairs(_blocked(spark, sf)[1]), tokens, freqs, _refs(spark, sf).count()).select("a", "b", F.round("score", 6).alias("score"))


@query("m7_rule_pairs", _with(_REFS, _TOK, _LISTS, select=f"SELECT a, b FROM pl WHERE {_COMMON} >= 3"))
def _(spark, sf):
    kept, blocked = _blocked(spark, sf)
    return ma.rule_pairs(bl.candidate_pairs(blocked), bl.filtered_records(kept))


# ---- closure
_SCORED = (_REFS, _TOK, _cells())


@query("c1_stars", _with(*_SCORED, select="SELECT a AS center, b AS member FROM scored WHERE score >= 0.6 UNION SELECT a, a FROM scored WHERE score >= 0.6"))
def _(spark, sf):
    return cl.stars(ma.above(_scored(spark, sf)[0], MU))


for _m in cl.METHODS:

    @query(f"c2_closure_{_m}", _with(*_SCORED, _closure(), select="SELECT component_id, record_id FROM comp"))
    def _(spark, sf, m=_m):
        return cl.closure(_scored(spark, sf)[0], MU, m)


@query("c3_resolve_closure_only", _with(*_SCORED, _closure(), select="SELECT cluster_id, record_id FROM clusters"))
def _(spark, sf):
    return resolve(_refs(spark, sf), ResolveConfig(mu=MU, clusterer="closure"))


_COPURCHASE = """bought AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem WHERE l_orderkey % 40 = 1 AND l_partkey % 7 < 3),
scored AS (SELECT lpad(CAST(x.l_partkey AS VARCHAR), 12, '0') AS a, lpad(CAST(y.l_partkey AS VARCHAR), 12, '0') AS b, CAST(count(*) AS DOUBLE) AS score FROM bought x JOIN bought y USING (l_orderkey) WHERE x.l_partkey < y.l_partkey GROUP BY ALL)"""


def _copurchase(spark, sf, only="true"):
    """Parts of one order, weighted by the orders that hold both: a graph with hubs, given by parts, whose components are far from records."""
    bought = spark.read.parquet(f"{sf}/lineitem.parquet").where(only).where("l_orderkey is not null and l_partkey is not null").select("l_orderkey", F.lpad(F.col("l_partkey").cast("string"), 12, "0").alias("p")).distinct()
    left, right = bought.withColumnRenamed("p", "a"), bought.withColumnRenamed("p", "b")
    return left.join(right, "l_orderkey").where("a < b").groupBy("a", "b").agg(F.count("*").cast("double").alias("score"))


@query("w9_copurchase_slice", _with(_COPURCHASE, "refs AS (SELECT DISTINCT a AS record_id FROM scored)", _closure(0.0), select="SELECT component_id, record_id FROM comp"))
def _(spark, sf):
    """A named slice of the orders, small enough for the recursive SQL to follow; the workload is w9_copurchase_components."""
    return cl.closure(_copurchase(spark, sf, "l_orderkey % 40 = 1 and l_partkey % 7 < 3"), 0.0)


@query("w9_copurchase_components")
def _(spark, sf):
    """All orders and parts, which make one giant component; no SQL twin, as recursion holds a row for each pair that is reached."""
    return cl.closure(_copurchase(spark, sf), 0.0)


# ---- refinement
_SOFT = (*_SCORED, _closure(), "inside AS (SELECT p.component_id, a AS u, b AS v, score AS w FROM scored JOIN comp p ON p.record_id = a JOIN comp q ON q.record_id = b WHERE p.component_id = q.component_id)")
#: A partition that both engines can name: the planted truth inside each soft cluster.
_ASSIGN = "asg AS (SELECT component_id, c.record_id, CAST(truth_id AS VARCHAR) AS community FROM comp c JOIN refs r ON r.record_id = c.record_id)"
_MODULARITY = """tot AS (SELECT component_id, sum(w) AS total FROM inside GROUP BY component_id),
pl2 AS (SELECT i.component_id, x.community AS cu, y.community AS cv, w FROM inside i JOIN asg x ON x.record_id = u JOIN asg y ON y.record_id = v),
com AS (SELECT component_id, c, sum(ins) AS ins, sum(d) AS d FROM (SELECT component_id, cu AS c, CASE WHEN cu = cv THEN w ELSE 0 END AS ins, w AS d FROM pl2 UNION ALL SELECT component_id, cv, 0, w FROM pl2) q GROUP BY ALL),
md AS (SELECT component_id, round(sum(ins / total - power(d / (2 * total), 2)), 6) + 0.0 AS m FROM com JOIN tot USING (component_id) GROUP BY component_id)"""


def _soft(spark, sf):
    scored, refs = _scored(spark, sf)
    components = materialise(cl.closure(scored, MU), "soft")
    edges = materialise(mo.component_edges(scored, components), "inside")
    assign = components.join(refs.select("record_id", F.col("truth_id").cast("string").alias("community")), "record_id")
    return scored, refs, components, edges, assign


@query("c4_component_edges", _with(*_SOFT, select="SELECT component_id, u, v, w FROM inside"))
def _(spark, sf):
    return _soft(spark, sf)[3]


@query("c5_isolated_nodes", _with(*_SOFT, select="SELECT component_id, record_id FROM comp WHERE record_id NOT IN (SELECT u FROM inside WHERE w >= 0.8 UNION SELECT v FROM inside WHERE w >= 0.8)"))
def _(spark, sf):
    _, _, components, edges, _ = _soft(spark, sf)
    return hi.isolated_nodes(components, edges.where("w >= 0.8")).select("component_id", "record_id")


@query("c6_modularity_of_truth", _with(*_SOFT, _ASSIGN, _MODULARITY, select="SELECT component_id, m FROM md"))
def _(spark, sf):
    _, _, _, edges, assign = _soft(spark, sf)
    return mo.modularity(edges, assign).select("component_id", (F.round("m", 6) + 0.0).alias("m"))


@query("c6_modularity_dense", _with(*_SOFT, _ASSIGN, _MODULARITY, select="SELECT component_id, m FROM md"))
def _(spark, sf):
    _, _, _, edges, assign = _soft(spark, sf)
    return mo.modularity_dense(edges, assign).select("component_id", (F.round("m", 6) + 0.0).alias("m"))


@query("c6_modularity_unweighted", _with(*_SOFT[:-1], _SOFT[-1].replace("score AS w", "1.0::DOUBLE AS w"), _ASSIGN, _MODULARITY, select="SELECT component_id, m FROM md"))
def _(spark, sf):
    _, _, _, edges, assign = _soft(spark, sf)
    return mo.modularity(edges, assign, weighted=False).select("component_id", (F.round("m", 6) + 0.0).alias("m"))


@query(
    "c7_move_gain",
    _with(
        *_SOFT, _ASSIGN.replace("CAST(truth_id AS VARCHAR)", "c.record_id"), _MODULARITY,
        "one AS (SELECT component_id, min(u) AS x FROM inside GROUP BY component_id), two AS (SELECT component_id, min(v) AS y FROM inside JOIN one USING (component_id) WHERE u = x GROUP BY component_id)",
        "deg AS (SELECT component_id, n, sum(w) AS k FROM (SELECT component_id, u AS n, w FROM inside UNION ALL SELECT component_id, v, w FROM inside) q GROUP BY ALL)",
        select="""SELECT component_id, round(w / total - (power((p.k + q.k) / (2 * total), 2) - power(p.k / (2 * total), 2) - power(q.k / (2 * total), 2)), 6) + 0.0 AS gain
        FROM one JOIN two USING (component_id) JOIN tot USING (component_id) JOIN inside i USING (component_id) JOIN deg p USING (component_id) JOIN deg q USING (component_id)
        WHERE i.u = x AND i.v = y AND p.n = x AND q.n = y""",
    ),
)
def _(spark, sf):
    """The gain of joining each component's least node to its least neighbour, from single nodes, against modularity after less before."""
    _, _, _, edges, _ = _soft(spark, sf)
    first = edges.groupBy("component_id").agg(F.min(F.struct("u", "v", "w")).alias("e")).select("component_id", "e.*")
    k = mo.degrees(edges)
    total = edges.groupBy("component_id").agg(F.sum("w").alias("total"))
    ends = first.join(k.select("component_id", F.col("record_id").alias("u"), F.col("k").alias("ku")), ["component_id", "u"]).join(k.select("component_id", F.col("record_id").alias("v"), F.col("k").alias("kv")), ["component_id", "v"])
    gain = mo.move_gain(F.col("ku"), F.col("w"), F.col("kv"), F.lit(0.0), F.lit(0.0), F.col("total"))
    return ends.join(total, "component_id").select("component_id", (F.round(gain, 6) + 0.0).alias("gain"))


@query(
    "c9_contract",
    _with(*_SOFT, _ASSIGN, select="""SELECT i.component_id, least(x.community, y.community) AS u, greatest(x.community, y.community) AS v, round(sum(w), 6) AS w
          FROM inside i JOIN asg x ON x.record_id = u JOIN asg y ON y.record_id = v GROUP BY ALL"""),
)
def _(spark, sf):
    _, _, _, edges, assign = _soft(spark, sf)
    return mo.contract(edges, assign).withColumn("w", F.round("w", 6))


@query(
    "c11_accept_or_collapse",
    _with(*_SOFT, _ASSIGN, _MODULARITY, select="SELECT component_id, record_id, CASE WHEN m > 0 THEN community ELSE component_id END AS community FROM asg JOIN md USING (component_id)"),
)
def _(spark, sf):
    _, _, _, edges, assign = _soft(spark, sf)
    return hi.accept_or_collapse(assign.join(mo.modularity(edges, assign).withColumn("m", F.round("m", 6)), "component_id"))


@query("c12_rename_to_least", _with(*_SOFT, _ASSIGN, select="SELECT min(record_id) OVER (PARTITION BY component_id, community) AS cluster_id, record_id FROM asg"))
def _(spark, sf):
    return hi.rename_to_least(_soft(spark, sf)[4])


@query("c13_link_index")
def link_index_query(spark, sf):
    return resolve(_refs(spark, sf, "S2"), ResolveConfig(mu=MU))


@query("c13_hierarchical_invariants", "SELECT CAST(1000 AS BIGINT) AS records, CAST(1000 AS BIGINT) AS distinct_records, CAST(0 AS BIGINT) AS not_least, CAST(0 AS BIGINT) AS across")
def _(spark, sf):
    """Every record once, clusters named by their least member, none across soft clusters."""
    scored, refs = _scored(spark, sf)
    return invariants(cluster(scored, refs, ResolveConfig(mu=MU)), cl.closure(scored, MU))


def invariants(found: DataFrame, soft: DataFrame) -> DataFrame:
    found, soft = materialise(found, "clusters"), soft.select("record_id", "component_id")
    least = found.groupBy("cluster_id").agg(F.min("record_id").alias("m"))
    joined = found.join(soft, "record_id", "left").groupBy("cluster_id").agg(F.count_distinct(F.coalesce("component_id", "record_id")).alias("n"))
    counts = found.agg(F.count("*").alias("records"), F.count_distinct("record_id").alias("distinct_records"))
    return counts.crossJoin(least.where("m != cluster_id").agg(F.count("*").alias("not_least"))).crossJoin(joined.where("n > 1").agg(F.count("*").alias("across")))


@query("c8_refine_invariants", "SELECT CAST(0 AS BIGINT) AS falling, CAST(0 AS BIGINT) AS differing")
def _(spark, sf):
    """Modularity rises from level to level, and what the kernel reports is the modularity of its partition."""
    _, _, _, edges, _ = _soft(spark, sf)
    levels = materialise(refine_local(edges, all_levels=True), "levels")
    by = Window.partitionBy("component_id").orderBy("level")
    each = levels.select("component_id", "level", "m").distinct()
    falling = each.withColumn("before", F.lag("m").over(by)).where("m < before").agg(F.count("*").alias("falling"))
    last = levels.join(levels.groupBy("component_id").agg(F.max("level").alias("level")), ["component_id", "level"])
    told = last.select("component_id", "m").distinct().withColumnRenamed("m", "told")
    differing = mo.modularity(edges, last).join(told, "component_id").where("abs(m - told) > 1e-6").agg(F.count("*").alias("differing"))
    return falling.crossJoin(differing)


for _n, _cfg in {
    "c8_first_gain": ResolveConfig(mu=MU, refine=RefineConfig(move="first_gain")),
    "c8_one_pass": ResolveConfig(mu=MU, refine=RefineConfig(passes="one")),
    "c8_unweighted": ResolveConfig(mu=MU, refine=RefineConfig(weighted=False)),
    "c10_distributed": ResolveConfig(mu=0.5, refine=RefineConfig(local_edge_cap=30)),
    "c14_modularity_only": ResolveConfig(mu=MU, clusterer="modularity"),
    "w12_above_mu": ResolveConfig(mu=MU, refine_edges="above_mu"),
    "w12_strict_bounds": ResolveConfig(mu=MU, bounds="strict"),
    "w12_two_phase": ResolveConfig(mu=MU, two_phase=True),
}.items():

    @query(_n)
    def _(spark, sf, cfg=_cfg):
        return resolve(_refs(spark, sf), cfg)


@query("c15_dendrogram")
def _(spark, sf):
    return refine_local(_soft(spark, sf)[3], all_levels=True)


@query(
    "c16_graph_profile",
    _with(
        *_SOFT, "ends AS (SELECT component_id, u AS x FROM inside UNION ALL SELECT component_id, v FROM inside), dg AS (SELECT component_id, x, count(*) AS d FROM ends GROUP BY ALL)",
        "tri AS (SELECT p.component_id, count(*) AS t FROM inside p JOIN inside q ON q.u = p.v AND q.component_id = p.component_id JOIN inside r ON r.u = p.u AND r.v = q.v AND r.component_id = p.component_id GROUP BY ALL)",
        select="""SELECT n.component_id, nodes, edges, round(2 * edges / (nodes * (nodes - 1)), 6) AS density, max_degree, coalesce(t, 0) AS triangles
        FROM (SELECT component_id, count(*) AS nodes, max(d) AS max_degree FROM dg GROUP BY ALL) n JOIN (SELECT component_id, count(*) AS edges FROM inside GROUP BY ALL) e USING (component_id) LEFT JOIN tri USING (component_id)""",
    ),
)
def _(spark, sf):
    return mo.graph_profile(_soft(spark, sf)[3])


# ---- baseline
_QUALITY = """ct AS (SELECT cluster_id, token, count(*) AS c FROM clusters JOIN tok USING (record_id) GROUP BY ALL),
sm AS (SELECT cluster_id, CAST(sum(c) AS DOUBLE) AS t, sum(c * log2(c)) AS x FROM ct GROUP BY cluster_id), sz AS (SELECT cluster_id, count(*) AS n FROM clusters GROUP BY cluster_id),
eq AS (SELECT cluster_id, n, round(log2(t) - x / t, 6) AS entropy, round(CASE WHEN n = 1 THEN 1.0 ELSE greatest(0, least(1, 1 - ((log2(t) - x / t) - log2(t / n)) / (log2(t) - log2(t / n)))) END, 6) AS quality FROM sz JOIN sm USING (cluster_id))"""


@query("b2_entropy_quality", _with(*_SCORED, _closure(), _QUALITY, select="SELECT cluster_id, n, abs(entropy) AS entropy, quality FROM eq"))
def _(spark, sf):
    scored, refs = _scored(spark, sf)
    return entropy_quality(cluster(scored, refs, ResolveConfig(mu=MU, clusterer="closure")), pr.explode_tokens(refs)).withColumn("entropy", F.abs("entropy"))


@query("b1_first_round", _with(*_SCORED, _closure(), _QUALITY, select="SELECT cluster_id, record_id, quality FROM clusters JOIN eq USING (cluster_id)"))
def _(spark, sf):
    return iterate_round(_refs(spark, sf), MU, 0.6, ResolveConfig())[0]


@query("b1_requeued_records", _with(*_SCORED, _closure(), _QUALITY, select="SELECT record_id FROM clusters JOIN eq USING (cluster_id) WHERE quality < 0.6"))
def _(spark, sf):
    return iterate_round(_refs(spark, sf), MU, 0.6, ResolveConfig())[1].select("record_id")


@query("b1_resolve_iterative")
def _(spark, sf):
    return resolve_iterative(_refs(spark, sf), MU, 0.6)[0]


@query(
    "b7_all_pairs_closure",
    _with(_DEMO, _TOK.rsplit("pairs AS", 1)[0] + "pairs AS (SELECT x.record_id AS a, y.record_id AS b FROM refs x JOIN refs y ON x.record_id < y.record_id)", _cells(), _closure(0.8), select="SELECT cluster_id, record_id FROM clusters"),
)
def _(spark, sf):
    return resolve(_refs(spark, sf, DEMO), ResolveConfig(mu=0.8, clusterer="closure", blocking="none"))


# ---- measures
@query("e1_link_index_roundtrip", _with(*_SCORED, _closure(), select="SELECT cluster_id, record_id FROM clusters"))
def _(spark, sf):
    path = new_path(spark, "link-index")
    files.write_link_index(resolve(_refs(spark, sf), ResolveConfig(mu=MU, clusterer="closure")), path, "csv")
    return files.read_link_index(spark, path, "csv")


_CELLS = "cells AS (SELECT cluster_id, truth_id, count(*) AS n FROM clusters JOIN refs USING (record_id) GROUP BY ALL)"
_CONFUSION = """g AS (SELECT CAST(coalesce((SELECT sum(n * (n - 1) / 2) FROM cells), 0) AS DECIMAL(38, 0)) AS tp,
    CAST((SELECT sum(n * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM cells GROUP BY cluster_id) q) AS DECIMAL(38, 0)) AS p,
    CAST((SELECT sum(n * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM cells GROUP BY truth_id) q) AS DECIMAL(38, 0)) AS t,
    CAST((SELECT sum(n) * (sum(n) - 1) / 2 FROM cells) AS DECIMAL(38, 0)) AS al),
cf AS (SELECT tp, CAST(p - tp AS DECIMAL(38, 0)) AS fp, CAST(t - tp AS DECIMAL(38, 0)) AS fn, CAST(al - p - t + tp AS DECIMAL(38, 0)) AS tn FROM g)"""


def _metrics_sql(bal: str) -> str:
    d = lambda x: f"CAST({x} AS DOUBLE)"
    return f"""SELECT tp, fp, fn, tn, round({d('tp')} / {d('tp + fp')}, 6) AS precision, round({d('tp')} / {d('tp + fn')}, 6) AS recall,
    round(2 * {d('tp')} / {d('2 * tp + fp + fn')}, 6) AS f1, round({bal.format(a=f"{d('tp')} / {d('tp + fn')}", b=f"{d('tn')} / {d('tn + fp')}")}, 6) AS bal_acc FROM cf"""


def _judged(spark, sf):
    refs = _refs(spark, sf)
    return materialise(resolve(refs, ResolveConfig(mu=MU, clusterer="closure")), "clusters"), refs


@query("e2_contingency", _with(*_SCORED, _closure(), _CELLS, select="SELECT * FROM cells"))
def _(spark, sf):
    return ev.contingency(*_judged(spark, sf))


for _n, _f in (("e3_pair_confusion", ev.pair_confusion), ("e3_pair_confusion_enumerated", ev.pair_confusion_enumerated)):

    @query(_n, _with(*_SCORED, _closure(), _CELLS, _CONFUSION, select="SELECT tp, fp, fn, tn FROM cf"))
    def _(spark, sf, f=_f):
        return f(*_judged(spark, sf))


@query("e4_pair_metrics", _with(*_SCORED, _closure(), _CELLS, _CONFUSION, select=_metrics_sql("({a} + {b}) / 2")))
def _(spark, sf):
    return ev.pair_metrics(ev.pair_confusion(*_judged(spark, sf)))


@query("e5_balanced_accuracy_literal", _with(*_SCORED, _closure(), _CELLS, _CONFUSION, select=_metrics_sql("{a} + {b}")))
def _(spark, sf):
    return ev.pair_metrics(ev.pair_confusion(*_judged(spark, sf)), literal=True)


@query("e15_cluster_report", _with(*_SCORED, _closure(), _CELLS, select="""SELECT size, count(*) AS clusters, CAST(sum(CASE WHEN parts = 1 AND size = ts THEN 1 ELSE 0 END) AS BIGINT) AS exact
    FROM (SELECT cluster_id, CAST(sum(n) AS BIGINT) AS size, count(*) AS parts, max(truth_id) AS truth_id FROM cells GROUP BY ALL) a JOIN (SELECT truth_id, sum(n) AS ts FROM cells GROUP BY ALL) b USING (truth_id) GROUP BY size"""))  # fmt: skip
def _(spark, sf):
    return ev.cluster_report(*_judged(spark, sf))


# A run log of the orders table: nations are samples, urgent orders are the truth, and an order is found where a digit of its key reaches mu (in the baseline another one epsilon, too).
# Samples are odd in number, in all and by quality, so that no mean of measures of six places lies half way between two of six places.
_LOG = """SELECT 'S' || s AS sample, CASE region WHEN 0 THEN 'good' WHEN 1 THEN 'moderate' ELSE 'poor' END AS quality, CASE WHEN s % 2 = 0 THEN 'standard' ELSE 'mixed' END AS layout, n AS n_rows, algo,
    m / 10.0{D} AS mu, e / 10.0{D} AS epsilon, CASE WHEN tp + fp = 0 THEN 0.0{D} ELSE round(tp * 1.0{D} / (tp + fp), 6) END AS precision, CASE WHEN tp + fn = 0 THEN 0.0{D} ELSE round(tp * 1.0{D} / (tp + fn), 6) END AS recall,
    CASE WHEN tp + fp + fn = 0 THEN 0.0{D} ELSE round(2.0{D} * tp / (2 * tp + fp + fn), 6) END AS f1,
    CASE WHEN tp + fn = 0 OR n = tp + fn THEN 0.0{D} ELSE round((tp * 1.0{D} / (tp + fn) + (n - tp - fn - fp) * 1.0{D} / (n - tp - fn)) / 2, 6) END AS bal_acc, n * (CASE WHEN e = 0 THEN 1 ELSE 10 - m END) / 1000.0{D} AS seconds
    FROM (SELECT s, region, algo, m, e, CAST(sum(n) AS BIGINT) AS n, CAST(sum(CASE WHEN found AND urgent THEN n ELSE 0 END) AS BIGINT) AS tp, CAST(sum(CASE WHEN found AND NOT urgent THEN n ELSE 0 END) AS BIGINT) AS fp,
        CAST(sum(CASE WHEN urgent AND NOT found THEN n ELSE 0 END) AS BIGINT) AS fn
        FROM (SELECT h.*, algo, m, e, x >= m AND y >= e AS found
            FROM (SELECT n_nationkey AS s, n_regionkey AS region, o_orderkey * 7 % 11 AS x, o_orderkey * 5 % 13 AS y, o_orderpriority IN ('1-URGENT', '2-HIGH') AS urgent, count(*) AS n
                FROM orders JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey GROUP BY 1, 2, 3, 4, 5) h
            CROSS JOIN (SELECT 1 AS m UNION ALL SELECT 2 UNION ALL SELECT 3 UNION ALL SELECT 4 UNION ALL SELECT 5 UNION ALL SELECT 6 UNION ALL SELECT 7 UNION ALL SELECT 8 UNION ALL SELECT 9) mm
            CROSS JOIN (SELECT 'two_step' AS algo, 0 AS e UNION ALL SELECT 'entropy_iterated', 3 UNION ALL SELECT 'entropy_iterated', 6 UNION ALL SELECT 'entropy_iterated', 9) aa) f
        GROUP BY s, region, algo, m, e) g"""
_LOG_DUCK = f"log AS ({_LOG.format(D='::DOUBLE')})"
_BEST = f"{_LOG_DUCK}, best AS (SELECT * EXCLUDE (r) FROM (SELECT *, row_number() OVER (PARTITION BY sample, algo ORDER BY f1 DESC, mu, seconds, epsilon) AS r FROM log) q WHERE r = 1)"
_SUMMARY = f"{_BEST}, smry AS (SELECT algo, round(avg(precision), 6) AS precision, round(avg(recall), 6) AS recall, round(avg(f1), 6) AS f1, round(avg(bal_acc), 6) AS bal_acc, round(avg(seconds), 6) AS seconds FROM best GROUP BY algo)"


def _log(spark, sf):
    register_tables(spark, sf, "orders", "customer", "nation")
    return spark.sql(_LOG.format(D="D"))


@query("e8_best_run", f"WITH {_BEST} SELECT * FROM best")
def _(spark, sf):
    return ev.best_run(_log(spark, sf))


@query("e9_macro_average", f"WITH {_SUMMARY} SELECT * FROM smry")
def _(spark, sf):
    return ev.summarise(ev.best_run(_log(spark, sf)))


@query("e10_compare", f"""WITH {_SUMMARY} SELECT round(x.precision - y.precision, 6) AS precision_gain, round(x.recall - y.recall, 6) AS recall_gain, round(x.f1 - y.f1, 6) AS f1_gain, round(x.bal_acc - y.bal_acc, 6) AS bal_acc_gain,
    round(y.seconds / x.seconds, 6) AS speed_up FROM smry x, smry y WHERE x.algo = 'two_step' AND y.algo = 'entropy_iterated'""")  # fmt: skip
def _(spark, sf):
    return ev.compare(ev.summarise(ev.best_run(_log(spark, sf))))


@query("e11_best_by_sample", f"WITH {_BEST} SELECT sample, algo, mu, f1 FROM best")
def _(spark, sf):
    return ev.best_run(_log(spark, sf)).select("sample", "algo", "mu", "f1")


@query("e12_sensitivity", f"""WITH {_LOG_DUCK} SELECT algo, mu, round(avg(f1) FILTER (sample = 'S1'), 6) AS "S1", round(avg(f1) FILTER (sample = 'S2'), 6) AS "S2" FROM log GROUP BY ALL""")
def _(spark, sf):
    return ev.sensitivity(_log(spark, sf), ["S1", "S2"])


@query("e13_dominance", f"""WITH {_LOG_DUCK}, b AS (SELECT sample, quality, mu, algo, max(f1) AS f1 FROM log GROUP BY ALL) SELECT x.quality, x.mu, round(avg(x.f1 - y.f1), 6) AS gain, count(*) AS n
    FROM b x JOIN b y USING (sample, quality, mu) WHERE x.algo = 'two_step' AND y.algo = 'entropy_iterated' GROUP BY ROLLUP (x.quality, x.mu)""")  # fmt: skip
def _(spark, sf):
    return ev.dominance(_log(spark, sf))


# ---- workloads
@query("w5_worked_example", "SELECT CASE WHEN i < 5 THEN 'X000001' ELSE 'X000005' END AS cluster_id, 'X00000' || i AS record_id FROM range(1, 7) t(i)")
def _(spark, sf):
    return resolve(worked_example(spark), ResolveConfig(mu=0.8))


def _mu_sweep_sql() -> str:
    runs = " UNION ALL ".join(f"SELECT {m / 10} AS mu, * FROM ({_with(*_SCORED, _closure(m / 10), _CELLS, _CONFUSION, select=_metrics_sql('({a} + {b}) / 2'))}) q{m}" for m in range(1, 10))
    return f"SELECT CAST(mu AS DOUBLE) AS mu, precision, recall, f1, bal_acc FROM ({runs}) z"


@query("w1_closure_mu_sweep", _mu_sweep_sql())
def _(spark, sf):
    refs = _refs(spark, sf)
    return sweep(spark, [(SAMPLES["S8"], refs)], clusterers=("closure",)).select("mu", "precision", "recall", "f1", "bal_acc")


_DOCS_SQL = f"refs AS (SELECT lpad(CAST(doc_id AS VARCHAR), 12, '0') AS record_id, list_distinct(list_filter(string_split({_ASCII.format(c='text')}, ' '), lambda x: x <> '')) AS t FROM documents)"


@query(
    "w6_document_copies",
    _with(
        _DOCS_SQL, "tk AS (SELECT record_id, unnest(t) AS token, len(t) AS n FROM refs), fr AS (SELECT token FROM tk GROUP BY token HAVING count(*) BETWEEN 2 AND 6)",
        "cand AS (SELECT DISTINCT x.record_id AS a, y.record_id AS b FROM tk x JOIN fr USING (token) JOIN tk y USING (token) WHERE x.record_id < y.record_id)",
        "scored AS (SELECT a, b, CAST(len(list_intersect(x.t, y.t)) AS DOUBLE) / (len(x.t) + len(y.t) - len(list_intersect(x.t, y.t))) AS score FROM cand JOIN refs x ON x.record_id = a JOIN refs y ON y.record_id = b)",
        _closure(0.5), select="SELECT component_id, record_id FROM comp",
    ),
)
def _(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    refs = docs.select(F.lpad(F.col("doc_id").cast("string"), 12, "0").alias("record_id"), F.array_distinct(pr.tokenise(pr.normalise(F.col("text"), "ascii"))).alias("tokens"))
    tokens = refs.select("record_id", F.explode("tokens").alias("token"))
    rare = tokens.groupBy("token").agg(F.count("*").alias("c")).where("c between 2 and 6")
    pairs = bl.candidate_pairs(bl.blocks(tokens.join(rare, "token").select("token", "record_id")))
    left, right = (refs.select(F.col("record_id").alias(c), F.col("tokens").alias(f"t{c}")) for c in ("a", "b"))
    common = F.size(F.array_intersect("ta", "tb"))
    score = common.cast("double") / (F.size("ta") + F.size("tb") - common)
    return cl.connected_components(pairs.join(left, "a").join(right, "b").where(score >= 0.5).select("a", "b"))


@query(
    "w8_embedding_graph",
    _with(
        "e AS (SELECT lpad(CAST(vec_id AS VARCHAR), 12, '0') AS id, label, CAST(embedding AS DOUBLE[]) AS v FROM embeddings)",
        "scored AS (SELECT x.id AS a, y.id AS b, list_dot_product(x.v, y.v) / sqrt(list_dot_product(x.v, x.v) * list_dot_product(y.v, y.v)) AS score FROM e x JOIN e y ON x.label = y.label AND x.id < y.id)",
        "refs AS (SELECT id AS record_id FROM e)", _closure(0.35), select="SELECT component_id, record_id FROM comp",
    ),
)
def _(spark, sf):
    """The clusterer on a graph that is not of text: cosine edges between vectors of a label (its members are few at this size)."""
    e = spark.read.parquet(f"{sf}/embeddings.parquet").select(F.lpad(F.col("vec_id").cast("string"), 12, "0").alias("id"), "label", F.col("embedding").cast("array<double>").alias("v"))
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, z: s + z)
    e = e.withColumn("n", F.sqrt(dot(F.col("v"), F.col("v"))))
    left, right = (e.select("label", F.col("id").alias(c), F.col("v").alias(f"v{c}"), F.col("n").alias(f"n{c}")) for c in ("a", "b"))
    pairs = left.join(right, "label").where("a < b").select("a", "b", (dot(F.col("va"), F.col("vb")) / (F.col("na") * F.col("nb"))).alias("score"))
    return cl.closure(pairs, 0.35)


# ---- the operators over all references: those above that take the default sample, without SQL twins, which are too slow at that size
def _over_all(f):
    def build(spark, sf):
        _default.append(WHOLE)
        try:
            return f(spark, sf)
        finally:
            _default.pop()

    return build


_ON_DEFAULT = ("p0_references", "p6_", "p7_", "p8_", *(f"k{i}_" for i in range(1, 9)), "m2_", "m3_", "m4_", "m5_", "m7_", *(f"c{i}_" for i in range(1, 17) if i != 10), "b1_", "b2_", *(f"e{i}_" for i in range(1, 6)), "e15_", "w12_two_phase", "w12_above_mu", "w12_strict_bounds")
_OTHER = ("p0_references_mixed", "p0_references_business", "c13_link_index")  # samples of their own


def add_whole_forms() -> None:
    for name, f in list(QUERIES.items()):
        if name.startswith(_ON_DEFAULT) and name not in _OTHER and not name.endswith(("_whole", "_invariants", "_communities", "_to_local")):
            QUERIES[f"{name}_whole"] = _over_all(f)
