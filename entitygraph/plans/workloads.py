"""The experiment, its tables and series, ablations, and the clusterer on other tables, as queries."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entitygraph.operators import blocking as bl
from entitygraph.operators import closure as cl
from entitygraph.operators import evaluation as ev
from entitygraph.operators import matching as ma
from entitygraph.operators import modularity as mo
from entitygraph.operators import parsing as pr
from entitygraph.operators.hierarchical import accept_or_collapse, refine, rename_to_least
from entitygraph.operators.louvain import RefineConfig, refine_distributed, refine_large, refine_local
from entitygraph.plans import catalogue as cat
from entitygraph.plans import experiment as ex
from entitygraph.plans.catalogue import _ASCII, _CELLS, _CONFUSION, _REFS, _SCORED, _SOFT, _TOK, MU, QUERIES, _cells, _closure, _metrics_sql, _refs, _scored, _soft, _tokens, _with, query
from entitygraph.plans.pipeline import ResolveConfig, cluster, resolve
from entitygraph.shared import materialise

FOUR = ("f1", "precision", "recall", "bal_acc")


# ---- further operators
@query("p7_record_frequencies", _with(_REFS, _TOK, select="SELECT token, df FROM freq"))
def _(spark, sf):
    return _tokens(spark, sf)[1].select("token", "df")


@query("m2_matrix_greedy")
def _(spark, sf):
    return _scored(spark, sf, measure="greedy")[0]


@query("m2_monge_elkan", _with(_REFS, _TOK, _cells("rows"), select="SELECT * FROM scored"))
def _(spark, sf):
    return _scored(spark, sf, measure="monge_elkan")[0]


@query("m3_match_pairs", _with(_REFS, _TOK, _cells(), select="SELECT * FROM scored"))
def _(spark, sf):
    kept, blocked = cat._blocked(spark, sf)
    return ma.match_pairs(bl.candidate_pairs(blocked), bl.filtered_records(kept))


@query("e5_balanced_accuracy", _with(*_SCORED, _closure(), _CELLS, _CONFUSION, select=f"SELECT bal_acc FROM ({_metrics_sql('({a} + {b}) / 2')}) q"))
def _(spark, sf):
    return ev.pair_metrics(ev.pair_confusion(*cat._judged(spark, sf))).select("bal_acc")


_MOVED = """asg AS (SELECT component_id, c.record_id, CAST(truth_id AS VARCHAR) AS community FROM comp c JOIN refs r ON r.record_id = c.record_id),
mover AS (SELECT component_id, min(record_id) AS x FROM asg GROUP BY 1), home AS (SELECT component_id, x, community AS own FROM mover JOIN asg USING (component_id) WHERE record_id = x),
goal AS (SELECT component_id, min(community) AS target FROM asg JOIN home USING (component_id) WHERE community <> own GROUP BY 1),
moved AS (SELECT a.component_id, record_id, CASE WHEN record_id = x THEN target ELSE community END AS community FROM asg a JOIN home USING (component_id) JOIN goal USING (component_id))"""


def _modularity_sql(assign: str, name: str) -> str:
    return f"""{name}_ends AS (SELECT i.component_id, x.community AS cu, y.community AS cv, w FROM inside i JOIN {assign} x ON x.record_id = u JOIN {assign} y ON y.record_id = v),
    {name}_com AS (SELECT component_id, c, sum(ins) AS ins, sum(d) AS d FROM (SELECT component_id, cu AS c, CASE WHEN cu = cv THEN w ELSE 0 END AS ins, w AS d FROM {name}_ends UNION ALL SELECT component_id, cv, 0, w FROM {name}_ends) q GROUP BY ALL),
    {name} AS (SELECT component_id, sum(ins / total - power(d / (2 * total), 2)) AS m FROM {name}_com JOIN tot USING (component_id) GROUP BY component_id)"""


@query(
    "c7_move_gain_communities",
    _with(
        *_SOFT, _MOVED, "tot AS (SELECT component_id, sum(w) AS total FROM inside GROUP BY component_id)", _modularity_sql("asg", "before"), _modularity_sql("moved", "after"),
        select="SELECT component_id, round(a.m - b.m, 6) + 0.0 AS gain FROM after a JOIN before b USING (component_id)",
    ),
)
def _(spark, sf):
    """The gain of moving each component's least record out of its true cluster into the least other one, by the formula, against modularity after less before."""
    _, _, _, edges, assign = _soft(spark, sf)
    assign = materialise(assign.select("component_id", "record_id", "community"), "assign")
    home = assign.groupBy("component_id").agg(F.min(F.struct("record_id", "community")).alias("h")).select("component_id", F.col("h.record_id").alias("x"), F.col("h.community").alias("own"))
    goal = assign.join(home, "component_id").where("community != own").groupBy("component_id").agg(F.min("community").alias("target"))
    k = mo.degrees(edges)
    degree = k.join(assign, ["component_id", "record_id"]).groupBy("component_id", "community").agg(F.sum("k").alias("d"))
    both = edges.select("component_id", F.col("u").alias("x"), F.col("v").alias("record_id"), "w").union(edges.select("component_id", F.col("v").alias("x"), F.col("u").alias("record_id"), "w"))
    links = both.join(home.select("component_id", "x"), ["component_id", "x"]).join(assign, ["component_id", "record_id"]).groupBy("component_id", "community").agg(F.sum("w").alias("links"))
    side = lambda c, s: degree.join(links, ["component_id", "community"], "left").select("component_id", F.col("community").alias(c), F.col("d").alias(f"d{s}"), F.coalesce("links", F.lit(0.0)).alias(f"k{s}"))
    one = home.join(goal, "component_id").join(side("own", "o"), ["component_id", "own"]).join(side("target", "t"), ["component_id", "target"])
    one = one.join(k.select("component_id", F.col("record_id").alias("x"), "k"), ["component_id", "x"]).join(edges.groupBy("component_id").agg(F.sum("w").alias("total")), "component_id")
    gain = mo.move_gain(F.col("k"), F.col("kt"), F.col("dt"), F.col("ko"), F.col("do") - F.col("k"), F.col("total"))
    return one.select("component_id", (F.round(gain, 6) + 0.0).alias("gain"))


_INVARIANT = "SELECT CAST(1000 AS BIGINT) AS records, CAST(1000 AS BIGINT) AS distinct_records, CAST(0 AS BIGINT) AS not_least, CAST(0 AS BIGINT) AS across"
for _n, _cfg in {
    "c8_first_gain": ResolveConfig(mu=MU, refine=RefineConfig(move="first_gain")),
    "c8_one_pass": ResolveConfig(mu=MU, refine=RefineConfig(passes="one")),
    "c8_unweighted": ResolveConfig(mu=MU, refine=RefineConfig(weighted=False)),
    "c8_resolution": ResolveConfig(mu=MU, refine=RefineConfig(resolution=1.5)),
    "c8_seed": ResolveConfig(mu=MU, refine=RefineConfig(seed=7)),
    "c14_modularity_only": ResolveConfig(mu=MU, clusterer="modularity"),
    "w12_above_mu": ResolveConfig(mu=MU, refine_edges="above_mu"),
    "w12_greedy": ResolveConfig(mu=MU, measure="greedy"),
}.items():
    if _n not in QUERIES:

        @query(_n)
        def _(spark, sf, cfg=_cfg):
            return resolve(_refs(spark, sf), cfg)

    @query(f"{_n}_invariants", _INVARIANT)
    def _(spark, sf, cfg=_cfg):
        """Every record once, clusters named by their least member, none across the components of the pairs above mu."""
        scored, refs = _scored(spark, sf, measure=cfg.measure)
        return cat.invariants(cluster(scored, refs, cfg), cl.closure(scored, MU))


@query("w12_two_phase_invariants", "SELECT CAST(0 AS BIGINT) AS other_pairs")
def _(spark, sf):
    """Scoring in two phases against scoring all pairs: records whose cluster differs under closure."""
    refs = _refs(spark, sf)
    one, two = (resolve(refs, ResolveConfig(mu=MU, clusterer="closure", two_phase=t)) for t in (False, True))
    return one.exceptAll(two).agg(F.count("*").alias("other_pairs"))


@query("c10_close_to_local", "SELECT true AS close, true AS positive")
def _(spark, sf):
    """The distributed form against the kernel on every component of a low threshold with ten edges or more: the sum of modularity is within two hundredths."""
    scored, _ = _scored(spark, sf)
    edges = materialise(mo.component_edges(scored, materialise(cl.closure(scored, 0.5), "soft")), "inside")
    large = edges.groupBy("component_id").agg(F.count("*").alias("n")).where("n >= 10").select("component_id")
    edges = materialise(edges.join(large, "component_id"), "inside")
    total = lambda x: x.select("component_id", "m").distinct().agg(F.sum("m").alias("m"))
    near = total(refine_distributed(edges)).select(F.col("m").alias("far")).crossJoin(total(refine_local(edges)))  # one row each
    return near.select((F.col("far") >= 0.98 * F.col("m")).alias("close"), (F.col("far") > 0).alias("positive"))


@query("c15_levels_found")
def _(spark, sf):
    """How many components were refined in how many levels, and their records."""
    levels = refine_local(_soft(spark, sf)[3], all_levels=True)
    per = levels.groupBy("component_id").agg(F.max("level").alias("levels"), F.count_distinct("record_id").alias("records"))
    return per.groupBy("levels").agg(F.count("*").alias("components"), F.sum("records").alias("records"))


# ---- the experiment: 18 samples, 9 thresholds, and 81 runs of the baseline for each
_logs: dict[tuple, DataFrame] = {}


def _log_of(spark, sf: str, names: tuple[str, ...] | None = None, algos=("two_step", "entropy_iterated"), cfg: ResolveConfig = ResolveConfig()) -> DataFrame:
    """The run log, each algorithm's made once a session (a table in the shared folder)."""
    parts = []
    for algo in algos:
        key = (spark.sparkContext.applicationId, sf, names, algo, cfg)
        if key not in _logs:
            _logs[key] = ex.run_log(spark, sf, list(names) if names else None, cfg=cfg, algos=(algo,), records=_records_of(spark, sf, names))
        parts.append(_logs[key])
    return reduce(DataFrame.unionByName, parts)


def _records_of(spark, sf: str, names: tuple[str, ...] | None) -> DataFrame:
    key = (spark.sparkContext.applicationId, sf, names)
    if key not in _logs:
        _logs[key] = ex.sample_records(spark, sf, list(names) if names else None)
    return _logs[key]


@query("w1_two_step_runs")
def _(spark, sf):
    return _log_of(spark, sf, algos=("two_step",))


@query("w2_baseline_runs")
def _(spark, sf):
    return _log_of(spark, sf, algos=("entropy_iterated",))


@query("w3_table_of_best_runs")
def _(spark, sf):
    """Means over the best runs of all samples, with rounds, comparisons and matrix cells."""
    return ex.table_of_best_runs(_log_of(spark, sf))


@query("w3_gains")
def _(spark, sf):
    """What the two-step method gains over the baseline, and how many times the baseline's comparisons and rounds are its own."""
    t = ex.table_of_best_runs(_log_of(spark, sf))
    x, y = (t.where(F.col("algo") == a).select(*[F.col(c).alias(f"{c}_{s}") for c in t.columns]) for a, s in (("two_step", "x"), ("entropy_iterated", "y")))
    gains = [F.round(F.col(f"{c}_x") - F.col(f"{c}_y"), 6).alias(f"{c}_gain") for c in FOUR]
    times = [F.round(F.col(f"{c}_y") / F.col(f"{c}_x"), 3).alias(f"{c}_ratio") for c in ("rounds", "comparisons", "cells", "all_comparisons")]
    return x.crossJoin(y).select(*gains, *times)  # one row each


@query("w4_best_by_sample")
def _(spark, sf):
    return ex.best_runs(_log_of(spark, sf)).select("sample", "quality", "layout", "n_rows", "algo", "mu", "epsilon", *FOUR, "rounds", "comparisons")


@query("w4_sensitivity")
def _(spark, sf):
    """F1, precision, recall and balanced accuracy by mu on four samples of unlike quality, size and layout."""
    return ev.sensitivity(_log_of(spark, sf, algos=("two_step",)), ["S1", "S2", "S6", "S18"], FOUR)


@query("w4_dominance")
def _(spark, sf):
    return ev.dominance(_log_of(spark, sf))


_ABLATED = ("S4", "S8", "S10")


@query("w12_ablations")
def _(spark, sf):
    """Best runs of the hybrid, the graph alone, closure alone, and the hybrid with one choice changed, on three samples."""
    base = ResolveConfig()
    changed = {
        "hybrid": base, "refine_above_mu": replace(base, refine_edges="above_mu"), "unweighted": replace(base, refine=RefineConfig(weighted=False)), "first_gain": replace(base, refine=RefineConfig(move="first_gain")),
        "matrix_rows": replace(base, measure="rows"), "matrix_shorter": replace(base, measure="shorter"), "matrix_greedy": replace(base, measure="greedy"), "strict_bounds": replace(base, bounds="strict"),
    }
    parts = [_log_of(spark, sf, _ABLATED, ("graph_only", "closure")).withColumn("variant", F.col("algo"))]
    parts += [_log_of(spark, sf, _ABLATED, ("two_step",), cfg).withColumn("variant", F.lit(n)) for n, cfg in changed.items()]
    log = reduce(DataFrame.unionByName, parts).withColumn("algo", F.col("variant"))
    return ex.best_runs(log).select("sample", "variant", "mu", *FOUR, "comparisons", "cells")


@query("e16_beta_sigma_grid")
def _(spark, sf):
    """The two cuts of blocking against each other: best two-step run of two samples for each."""
    parts = []
    for beta, sigma in ((4, 5), (4, 7), (6, 7), (6, 11), (10, 11), (10, 15)):
        log = _log_of(spark, sf, ("S8", "S10"), ("two_step",), ResolveConfig(beta=beta, sigma=sigma))
        parts.append(ex.best_runs(log).withColumn("beta", F.lit(beta)).withColumn("sigma", F.lit(sigma)))
    return reduce(DataFrame.unionByName, parts).select("beta", "sigma", "sample", "mu", *FOUR, "comparisons", "cells")


# ---- the clusterer on other tables
_MERGED_SQL = " UNION ALL ".join(
    f"SELECT '{t}:' || {key} AS record_id, {_ASCII.format(c=text)} AS body FROM {t}"
    for t, key, text in (
        ("documents", "doc_id", "text"), ("pages", "page_id", "regexp_replace(html, '<[^>]*>', ' ', 'g')"), ("benchmark", "item_id", "text"), ("conversations", "conv_id || ':' || turn", "text"),
    )
)
_OVERLAP = f"scored AS (SELECT a, b, round(CAST({cat._COMMON} AS DOUBLE) / least(len(list_distinct(ta)), len(list_distinct(tb))), 6) AS score FROM pl)"


def _merged_records(spark, sf) -> DataFrame:
    merged = cat._merged(spark, sf)
    a = F.col("attrs")
    body = pr.normalise(F.coalesce(a["text"], F.regexp_replace(a["html"], "<[^>]*>", " ")), "ascii")
    return materialise(merged.select("record_id", body.alias("body")), "merged")


_CROSS = ResolveConfig(mu=0.5, measure="overlap")


@query("w7_cross_file_closure", _with(f"refs AS ({_MERGED_SQL})", _TOK, cat._LISTS, _OVERLAP, _closure(0.5), select="SELECT cluster_id, record_id FROM clusters"))
def _(spark, sf):
    """Texts of four tables of unlike layout as one record set, resolved by their rare tokens."""
    return resolve(_merged_records(spark, sf), replace(_CROSS, clusterer="closure"))


@query("w7_cross_file_two_step")
def _(spark, sf):
    """How many clusters of the two-step method hold records of which tables."""
    found = resolve(_merged_records(spark, sf), _CROSS)
    tables = found.groupBy("cluster_id").agg(F.array_join(F.array_sort(F.collect_set(F.substring_index("record_id", ":", 1))), "+").alias("tables"), F.count("*").alias("size"))
    return tables.where("size > 1").groupBy("tables").agg(F.count("*").alias("clusters"), F.sum("size").alias("records"))


def _nearest(k: int):
    """Of one cell's vectors (role 0 against role 1): the k nearest of each by cosine."""

    def run(rows: pa.Table) -> pa.Table:
        rows = rows.combine_chunks()
        data = np.array(rows.column("v").to_pylist(), float)
        role, ids = rows.column("role").to_numpy(), np.array(rows.column("id").to_pylist(), object)
        left, right = np.flatnonzero(role == 0), np.flatnonzero(role == 1)
        a, b, score = [], [], []
        for at in range(0, len(left), 512):
            some = left[at : at + 512]
            dots = data[some] @ data[right].T
            dots[ids[some][:, None] == ids[right][None]] = -np.inf
            best = np.argsort(-dots, axis=1, kind="stable")[:, :k]
            a += np.repeat(ids[some], best.shape[1]).tolist()
            b += ids[right][best].ravel().tolist()
            score += np.take_along_axis(dots, best, axis=1).ravel().tolist()
        keep = [i for i, s in enumerate(score) if s > -np.inf]
        return pa.table({"a": pa.array([a[i] for i in keep], pa.string()), "b": pa.array([b[i] for i in keep], pa.string()), "score": pa.array([score[i] for i in keep], pa.float64())})

    return run


def nearest_edges(vectors: DataFrame, k: int = 10, cell: int = 2000) -> DataFrame:
    """a < b, score: each vector (id, v) and its k nearest by cosine, of positive score. Exact: all vectors meet, in cells of two parts of about ``cell`` vectors each."""
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    unit = vectors.select("id", F.transform("v", lambda x: x / norm).alias("v"))
    parts = max(1, -(-vectors.count() // cell))
    dealt = unit.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int"))
    every = F.sequence(F.lit(0), F.lit(parts - 1))
    left = dealt.select(F.col("part").alias("i"), F.explode(every).alias("j"), F.lit(0).alias("role"), "id", "v")
    right = dealt.select(F.explode(every).alias("i"), F.col("part").alias("j"), F.lit(1).alias("role"), "id", "v")
    near = left.union(right).groupBy("i", "j").applyInArrow(_nearest(k), "a string, b string, score double")
    best = near.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("score"), "b"))).where(F.col("r") <= k)
    return best.where("score > 0").groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.round(F.max("score"), 6).alias("score"))


def _vectors(spark, sf) -> DataFrame:
    e = spark.read.parquet(f"{sf}/embeddings.parquet").where("embedding is not null")
    return e.select(F.lpad(F.col("vec_id").cast("string"), 12, "0").alias("id"), "label", F.col("embedding").cast("array<double>").alias("v"))


_KNN = """e AS (SELECT lpad(CAST(vec_id AS VARCHAR), 12, '0') AS id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings WHERE embedding IS NOT NULL),
near AS (SELECT x.id AS a, y.id AS b, list_dot_product(x.v, y.v) / sqrt(list_dot_product(x.v, x.v) * list_dot_product(y.v, y.v)) AS score FROM e x JOIN e y ON x.id <> y.id),
knn AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY score DESC, b) AS r FROM near) q WHERE r <= 10 AND score > 0)"""


@query("w8_nearest_edges", f"WITH {_KNN} SELECT least(a, b) AS a, greatest(a, b) AS b, round(max(score), 6) AS score FROM knn GROUP BY 1, 2")
def _(spark, sf):
    return nearest_edges(_vectors(spark, sf).select("id", "v"))


@query("w8_embedding_two_step")
def _(spark, sf):
    """Closure and refinement of the graph of nearest vectors against their labels: precision, recall, F1 and balanced accuracy of each."""
    vectors = materialise(_vectors(spark, sf), "vectors")
    scored = materialise(nearest_edges(vectors.select("id", "v")), "edges")
    return _by_threshold(scored, vectors.select(F.col("id").alias("record_id"), F.col("label").cast("long").alias("truth_id")), (0.2, 0.3, 0.4))


def _by_threshold(scored: DataFrame, truth: DataFrame, mus: tuple) -> DataFrame:
    """mu, clusterer and the measures of closure and of both steps. All thresholds go through one closure and one refinement together, told apart by the names of their runs."""
    grid = ex._grid(scored.sparkSession, mu=mus)
    named = lambda c: F.concat(F.lit("all|"), F.col(c)).alias(c)
    records = materialise(truth.select(named("record_id"), "truth_id"), "records")
    each = ex._in_runs(records.select("record_id"), grid, "record_id")
    every = materialise(ex._in_runs(scored.select(named("a"), named("b"), "score"), grid, "a", "b").select("a", "b", "score", "mu"), "runs")
    soft = materialise(cl.connected_components(every.where("score >= mu").select("a", "b")), "soft")
    edges = materialise(mo.component_edges(every.select("a", "b", "score"), soft), "inside")
    # the search visits nodes in the order of a hash of their names, so they go by their own
    plain = refine(edges.withColumns({x: ex.plain_of(x) for x in "uv"})).withColumns({x: ex._named(ex.run_of("component_id"), F.col(x)) for x in ("record_id", "community")})
    refined = materialise(accept_or_collapse(plain), "refined")
    rest = soft.join(refined.select("record_id"), "record_id", "left_anti").select("component_id", "record_id", F.col("component_id").alias("community"))
    found = {"closure": soft.select(F.col("component_id").alias("cluster_id"), "record_id"), "two_step": rename_to_least(refined.unionByName(rest))}
    out = [ex.measures_by_run(ex._singletons(clusters, each), records).select(F.split("run", ";")[1].cast("double").alias("mu"), F.lit(name).alias("clusterer"), *FOUR) for name, clusters in found.items()]
    return materialise(reduce(DataFrame.unionByName, out), "measures")


@query("w9_copurchase_two_step")
def _(spark, sf):
    """The communities of the giant component of parts bought together: how many parts and communities, their largest, and the modularity."""
    scored = materialise(cat._copurchase(spark, sf), "copurchase")
    soft = materialise(cl.closure(scored, 0.0), "soft")
    edges = materialise(mo.component_edges(scored, soft), "inside")
    sizes = materialise(edges.groupBy("component_id").agg(F.count("*").alias("n_edges")), "sizes")
    cfg = RefineConfig()
    large = sizes.where(F.col("n_edges") > cfg.local_edge_cap)
    found = refine_local(edges.join(large.select("component_id"), "component_id", "left_anti"), cfg)
    if large.limit(1).count():
        found = found.unionByName(refine_large(edges, large, cfg))
    found = materialise(found.select("component_id", "record_id", "community", "m"), "communities")
    per = found.groupBy("component_id", "community").agg(F.count("*").alias("n"), F.max("m").alias("m"))
    return per.groupBy("component_id").agg(F.sum("n").alias("parts"), F.count("*").alias("communities"), F.max("n").alias("largest"), F.round(F.max("m"), 4).alias("modularity"))


_COPIES = QUERIES["w6_document_copies"]
_STRATA = cat.ORACLE_SQL["w6_document_copies"].removesuffix("SELECT component_id, record_id FROM comp")


@query(
    "w10_quality_strata",
    _STRATA + """SELECT quality, count(*) AS documents, count(component_id) AS copies, count(DISTINCT component_id) AS groups FROM labels LEFT JOIN comp ON record_id = lpad(CAST(doc_id AS VARCHAR), 12, '0')
    WHERE quality IS NOT NULL GROUP BY quality""",
)
def _(spark, sf):
    """Near copies among labelled documents, by quality."""
    labels = spark.read.parquet(f"{sf}/labels.parquet").where("quality is not null").select(F.lpad(F.col("doc_id").cast("string"), 12, "0").alias("record_id"), "quality")
    found = labels.join(_COPIES(spark, sf), "record_id", "left")
    return found.groupBy("quality").agg(F.count("*").alias("documents"), F.count("component_id").alias("copies"), F.count_distinct("component_id").alias("groups"))
