"""What SQL twins don't show: greedy matching, hash blocks, the distributed refinement, batches of a stream, and plans."""

import itertools

import pytest
from pyspark.sql import functions as F

from entitygraph.errors import LocalCapExceeded
from entitygraph.functions.sql import edit_distance, register_expressions, register_tables
from entitygraph.operators import blocking, closure, evaluation, matching, modularity, parsing, relational
from entitygraph.operators.hierarchical import cluster_modularity
from entitygraph.operators.louvain import RefineConfig, louvain, refine_distributed, refine_local
from entitygraph.plans import experiment
from entitygraph.plans.pipeline import ResolveConfig, resolve, resolve_iterative
from entitygraph.shared import new_path
from entitygraph.sources.fixtures import references
from entitygraph.streaming.arrivals import IncrementalLinkIndex

SF = "/root/testdata/sf0.001"


def one_to_one(a, b):
    cells = sorted((-(1 - edit_distance(x, y) / max(len(x), len(y))), i, j) for i, x in enumerate(a) for j, y in enumerate(b))
    rows, cols, total = set(), set(), 0.0
    for s, i, j in cells:
        if i not in rows and j not in cols:
            rows.add(i), cols.add(j)
            total -= s
    return 2 * total / (len(a) + len(b)) if a and b else 0.0


LISTS = [([], []), (["AB"], []), (["ABC", "ABD", "X"], ["ABD", "ABC"]), (["SMITH", "JOHN"], ["JOHN", "SMYTH", "JON"]), (["A", "A"], ["A", "B"])]


def test_greedy_matrix_and_aliases(spark):
    df = spark.createDataFrame([(i, a, b) for i, (a, b) in enumerate(LISTS)], "i int, a array<string>, b array<string>")
    got = df.select("i", matching.similarity("greedy", F.col("a"), F.col("b")).alias("g"), matching.similarity("monge_elkan", F.col("a"), F.col("b")).alias("m"), matching.similarity("rows", F.col("a"), F.col("b")).alias("r")).collect()
    for r in got:
        assert r["g"] == pytest.approx(one_to_one(*LISTS[r["i"]]), abs=1e-6) and r["m"] == r["r"]


@pytest.mark.parametrize("measure", ["both", "rows", "cols", "shorter", "greedy", "exact", "jaccard", "overlap", "levenshtein_body"])
def test_records_without_tokens_score_nothing(spark, measure):
    df = spark.createDataFrame(LISTS[:2], "a array<string>, b array<string>")
    assert [r[0] for r in df.select(matching.similarity(measure, F.col("a"), F.col("b"))).collect()] == [0.0, 0.0]


def test_hash_blocks_are_all_pairs_of_a_signature(spark):
    tokens = parsing.explode_tokens(references(spark, SF, "S1")).cache()
    bands, rows = 6, 2
    marks = tokens.groupBy("record_id").agg(*[F.min(F.xxhash64("token", F.lit(i))).alias(f"h{i}") for i in range(bands * rows)]).collect()
    want = {
        (x, y): n
        for (x, p), (y, q) in itertools.combinations(sorted((r["record_id"], [tuple(r[f"h{b * rows + k}"] for k in range(rows)) for b in range(bands)]) for r in marks), 2)
        if (n := sum(s == t for s, t in zip(p, q, strict=True)))
    }
    for largest in (3, 200):
        got = {(r["a"], r["b"]): r["shared"] for r in blocking.lsh_pairs(tokens, bands, rows, largest).collect()}
        assert got == want


def test_stop_tokens_leave_before_the_join(spark):
    tokens = parsing.explode_tokens(references(spark, SF, "S2"))
    plan = blocking.cut_stop_tokens(tokens, parsing.token_frequencies(tokens))._jdf.queryExecution().executedPlan().toString()
    assert "LeftAnti" in plan and "BroadcastHashJoin" in plan


def test_distributed_refinement_is_close(spark):
    names = [f"n{i:02d}" for i in range(24)]
    rows = [("c", a, b, 0.9 if i // 6 == j // 6 else 0.05) for (i, a), (j, b) in itertools.combinations(enumerate(names), 2) if i // 6 == j // 6 or (i + j) % 5 == 0]
    edges = spark.createDataFrame(rows, "component_id string, u string, v string, w double")
    near, far = refine_local(edges).collect(), refine_distributed(edges).collect()
    assert far[0]["m"] >= 0.98 * near[0]["m"] > 0
    told = modularity.modularity(edges, refine_distributed(edges)).first()["m"]
    assert told == pytest.approx(far[0]["m"])


def test_distributed_refinement_leaves_out_what_has_no_weight(spark):
    schema = "component_id string, u string, v string, w double"
    found = refine_distributed(spark.createDataFrame([("z", "a", "b", 0.0), ("y", "p", "p", 1.0), ("y", "p", "q", 1.0)], schema)).collect()
    assert {r["record_id"] for r in found} == {"p", "q"} and len(found) == 2
    assert refine_distributed(spark.createDataFrame([], schema)).collect() == []


def test_graph_alone_in_parts_is_the_whole_graph(spark):
    """Parts searched by themselves with the whole weight give a partition as good as one search over all."""
    edges = [("a", "b", 0.9), ("b", "c", 0.8), ("a", "c", 0.7), ("c", "d", 0.2), ("d", "e", 0.9), ("p", "q", 0.6), ("q", "r", 0.9), ("x", "y", 0.5)]
    scored = spark.createDataFrame(edges, "a string, b string, score double")
    records = spark.createDataFrame([(x,) for x in "abcdepqrxyz"], "record_id string")
    got = {r["record_id"]: r["cluster_id"] for r in cluster_modularity(scored, records).collect()}
    whole, m = louvain(edges)[-1]
    assign = spark.createDataFrame([("w", x, got[x]) for x in whole], "component_id string, record_id string, community string")
    graph = spark.createDataFrame([("w", *e) for e in edges], "component_id string, u string, v string, w double")
    assert got["z"] == "z" and modularity.modularity(graph, assign).first()["m"] == pytest.approx(m)


def test_references_have_caps(spark):
    pred = spark.createDataFrame([(str(i), str(i)) for i in range(5)], "cluster_id string, record_id string")
    truth = spark.createDataFrame([(str(i), i) for i in range(5)], "record_id string, truth_id long")
    with pytest.raises(LocalCapExceeded):
        evaluation.pair_confusion_enumerated(pred, truth, max_records=4)
    edges = spark.createDataFrame([("c", "1", "2", 1.0)], "component_id string, u string, v string, w double")
    with pytest.raises(LocalCapExceeded):
        modularity.modularity_dense(edges, spark.createDataFrame([("c", str(i), "1") for i in range(5)], "component_id string, record_id string, community string"), max_nodes=4)


def test_references_in_batches(spark):
    """In one batch the pipeline's own result; in several, every link that is found stays and a batch tried again changes nothing."""
    refs = references(spark, SF, "S2").select("record_id", "body").cache()
    cfg = ResolveConfig(clusterer="closure")
    want = {(r["cluster_id"], r["record_id"]) for r in resolve(refs, cfg).collect()}
    one = IncrementalLinkIndex(spark, cfg)
    one.add(refs, 0)
    assert {(r["cluster_id"], r["record_id"]) for r in one.link_index().collect()} == want
    some = IncrementalLinkIndex(spark, cfg)
    parts = [refs.where(F.pmod(F.xxhash64("record_id"), F.lit(3)) == k) for k in range(3)]
    for k, p in enumerate(parts):
        some.add(p, k)
    first = {(r["cluster_id"], r["record_id"]) for r in some.link_index().collect()}
    some.add(parts[2], 2)
    assert {(r["cluster_id"], r["record_id"]) for r in some.link_index().collect()} == first and len(first) == refs.count()
    together = {r for r, _ in ((r, c) for c, r in want if c != r)}
    assert together <= {r for c, r in first if c != r} | {c for c, r in first if c != r}


def test_runs_of_the_grid_are_single_runs(spark):
    """A run inside the grid gives the clusters of the same run by itself: two-step, closure, and the baseline through all its rounds."""
    names = ["S1", "S2"]
    records = experiment.sample_records(spark, SF, names)
    scored = experiment.score_runs(records.select("record_id", "body"), ResolveConfig())
    plain = lambda df, run: {(r["cluster_id"].split("|")[1], r["record_id"].split("|")[1]) for r in df.where(F.col("record_id").startswith(run + "|")).collect()}
    same = lambda df: {(r["cluster_id"], r["record_id"]) for r in df.collect()}
    refs = references(spark, SF, "S2")
    assert plain(experiment.two_step_runs(scored, records, (0.5, 0.7)), "S2;0.5") == same(resolve(refs, ResolveConfig(mu=0.5)))
    assert plain(experiment.closure_runs(scored, records, (0.5, 0.7)), "S2;0.7") == same(resolve(refs, ResolveConfig(mu=0.7, clusterer="closure")))
    clusters, costs = experiment.baseline_runs(scored, records, (0.6,), (0.5, 0.8))
    found, rounds = resolve_iterative(refs, 0.6, 0.8)
    assert plain(clusters, "S2;0.6;0.8") == same(found) and costs.where("run = 'S2;0.6;0.8'").first()["rounds"] == rounds


def test_relational_on_odd_rows(spark):
    left = spark.createDataFrame([(1, 0.0), (2, None), (3, -4.9), (4, 5.0)], "i int, x double")
    right = spark.createDataFrame([(7, 5.0), (8, None), (9, -10.0)], "j int, y double")
    assert {(r["i"], r["j"]) for r in relational.range_join(left, right, "x", "y", 5).collect()} == {(1, 7), (4, 7)}
    t = spark.createDataFrame([("k", 1, "a"), ("k", 3, "b")], "key string, t int, v string")
    asked = spark.createDataFrame([("k", 0), ("k", 1), ("k", 9), ("q", 9)], "key string, t int")
    got = {(r["key"], r["t"]): r["last"] for r in relational.as_of_join(asked, t, "key", "t", "v", "last").collect()}
    assert got == {("k", 0): None, ("k", 1): "a", ("k", 9): "b", ("q", 9): None}


def test_sql_functions(spark):
    register_expressions(spark)
    register_tables(spark)
    assert spark.sql("SELECT normalise_reference(' a-b,  c '), token_similarity('AB', 'AC')").first()[:] == ("AB C", 0.5)
    assert [tuple(r) for r in spark.sql("SELECT * FROM tokens_of('A  B')").collect()] == [(0, "A"), (1, "B")]


def test_finished_rounds_are_deleted(spark, tmp_path, monkeypatch):
    monkeypatch.setattr("entitygraph.shared.shared_dir", lambda _: str(tmp_path))
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)], "a int, b int")
    assert closure.connected_components(edges).count() == 41
    assert len(list(tmp_path.iterdir())) == 1
    assert new_path(spark, "x").startswith(str(tmp_path))


def test_refine_config_has_effect(spark):
    edges = [(f"n{i}", f"n{j}", 1.0 if i // 3 == j // 3 else 0.3) for i, j in itertools.combinations(range(9), 2)]
    few, many = (len(set(louvain(edges, RefineConfig(resolution=g))[-1][0].values())) for g in (0.5, 2.0))
    assert few < many
